"""Small learners fitted on the driver from bounded samples: boosted trees, isotonic steps, pairwise ranking."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def crc_of_id(column: str = "doc_id"):
    return F.crc32(F.col(column).cast("string").cast("binary"))


def labelled_sample(docs: DataFrame, labels: DataFrame, name: str, usable, bound: int) -> DataFrame:
    """(doc_id, text, label) of at most `bound` labelled documents, chosen by a hash of doc_id.

    Only that bounded sample of labels is broadcast, so no text is shuffled. Of repeated
    labels of one document the largest counts; null labels and ids are left out.
    """
    known = labels.filter(F.col(name).isNotNull() & F.col("doc_id").isNotNull()).filter(usable).groupBy("doc_id").agg(F.max(F.col(name).cast("int")).alias("label"))
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(bound)
    return docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id")


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


@dataclass
class BoostedTrees:
    """Gradient-boosted regression trees for logistic loss on binned dense features."""

    rounds: int = 80
    depth: int = 3
    rate: float = 0.15
    bins: int = 48
    least_weight: float = 2.0
    ridge: float = 1.0
    start: float = 0.0
    edges: list[np.ndarray] = field(default_factory=list)
    trees: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = field(default_factory=list)

    def _binned(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, k], side="right") for k, e in enumerate(self.edges)], axis=1)

    def fit(self, x: np.ndarray, y: np.ndarray) -> BoostedTrees:
        self.edges = [np.unique(np.quantile(x[:, k], np.linspace(0, 1, self.bins + 1)[1:-1])) for k in range(x.shape[1])]
        b, width = self._binned(x), self.bins
        cells = b + np.arange(x.shape[1]) * width
        rate = np.clip(y.mean(), 1e-3, 1 - 1e-3)
        self.start = float(np.log(rate / (1 - rate)))
        raw = np.full(len(y), self.start)
        nodes = 2**self.depth - 1
        for _ in range(self.rounds):
            p = sigmoid(raw)
            g, h = p - y, p * (1 - p)
            feature, cut = np.full(nodes, -1), np.zeros(nodes, np.int64)
            at = np.zeros(len(y), np.int64)
            for node in range(nodes):
                inside = np.flatnonzero(at == node)
                if len(inside) < 4:
                    continue
                flat = cells[inside].ravel()
                gs = np.bincount(flat, np.repeat(g[inside], x.shape[1]), width * x.shape[1]).reshape(-1, width)
                hs = np.bincount(flat, np.repeat(h[inside], x.shape[1]), width * x.shape[1]).reshape(-1, width)
                gl, hl = gs.cumsum(1)[:, :-1], hs.cumsum(1)[:, :-1]
                gt, ht = g[inside].sum(), h[inside].sum()
                gain = gl**2 / (hl + self.ridge) + (gt - gl) ** 2 / (ht - hl + self.ridge) - gt**2 / (ht + self.ridge)
                gain[(hl < self.least_weight / 4) | (ht - hl < self.least_weight / 4)] = -1
                best = np.unravel_index(np.argmax(gain), gain.shape)
                if gain[best] <= 1e-6:
                    continue
                feature[node], cut[node] = best
                right = b[inside, best[0]] > best[1]
                at[inside] = 2 * node + 1 + right
            # rows that stopped early sit in an inner node; every node may carry a value
            value = np.zeros(2 * nodes + 1)
            gn, hn = np.bincount(at, g, 2 * nodes + 1), np.bincount(at, h, 2 * nodes + 1)
            value = -self.rate * gn / (hn + self.ridge)
            self.trees.append((feature, cut, value))
            raw += value[at]
        return self

    def raw(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.start)
        if not len(x):
            return out
        b, rows = self._binned(x), np.arange(len(x))
        for feature, cut, value in self.trees:
            at = np.zeros(len(x), np.int64)
            for _ in range(self.depth):
                inner = at < len(feature)
                f = np.where(inner, feature[np.minimum(at, len(feature) - 1)], -1)
                go = b[rows, np.maximum(f, 0)] > cut[np.minimum(at, len(feature) - 1)]
                at = np.where(f >= 0, 2 * at + 1 + go, at)
            out += value[at]
        return out


@dataclass
class IsotonicSteps:
    """Non-decreasing map from raw scores to rates, fitted by pooling adjacent violators."""

    points: np.ndarray = field(default_factory=lambda: np.zeros(1))
    rates: np.ndarray = field(default_factory=lambda: np.full(1, 0.5))

    def fit(self, raw: np.ndarray, y: np.ndarray) -> IsotonicSteps:
        order = np.argsort(raw, kind="stable")
        blocks: list[list[float]] = []
        for r, v in zip(raw[order].tolist(), y[order].tolist()):
            blocks.append([v, 1.0, r, r])
            while len(blocks) > 1 and (blocks[-2][0] * blocks[-1][1] >= blocks[-1][0] * blocks[-2][1] or blocks[-2][3] == blocks[-1][2]):
                v2, w2, _, high = blocks.pop()
                blocks[-1] = [blocks[-1][0] + v2, blocks[-1][1] + w2, blocks[-1][2], high]
        self.points = np.array([(b[2] + b[3]) / 2 for b in blocks])
        self.rates = np.array([b[0] / b[1] for b in blocks])
        return self

    def __call__(self, raw: np.ndarray) -> np.ndarray:
        return np.interp(raw, self.points, self.rates)


def fit_pairwise(x: np.ndarray, y: np.ndarray, pairs: int, ridge: float, seed: int = 7) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bradley-Terry weights: P(i before j) = sigmoid(w (x_i - x_j)), over pairs of a good and a bad row.

    Newton steps on the logistic loss of feature differences. Returns weights, centre, scale.
    """
    centre, scale = x.mean(0), x.std(0) + 1e-9
    z = (x - centre) / scale
    good, bad = np.flatnonzero(y == 1), np.flatnonzero(y == 0)
    rng = np.random.default_rng(seed)
    d = z[rng.choice(good, pairs)] - z[rng.choice(bad, pairs)]
    w = np.zeros(x.shape[1])
    for _ in range(25):
        p = sigmoid(d @ w)
        gradient = d.T @ (p - 1) / pairs + ridge * w
        hessian = (d * (p * (1 - p))[:, None]).T @ d / pairs + ridge * np.eye(len(w))
        step = np.linalg.solve(hessian, gradient)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return w, centre, scale
