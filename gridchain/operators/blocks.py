"""A graph between near dense rows that is made where it is used: pairs of blocks of rows meet in tasks, and no edge is stored or dealt.

The edges grow with the square of the rows, so a kernel over such a graph takes them from the
block that makes them and hands on what the caller wants: edges, or partial dense rows.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Rows of a block at most; blocks of a side that small inputs are cut into as well, from LEAST rows each; cells of a strip that is worked on at once.
SIZE, SPREAD, LEAST, STRIP = 8192, 8, 512, 1 << 21
#: Partial rows held before they are merged.
HELD = 1 << 15
EDGES = "i bigint, j bigint, v double"


@dataclass(frozen=True)
class NearGraph:
    """Directed edges (i, j), i <> j, between rows (id, x) whose dot is above `least`; every edge has the value 1."""

    d: DataFrame
    least: float
    size: int = SIZE

    def run(self, kernel: Callable, schema: str, rows: DataFrame | None = None, left: Column | None = None, right: Column | None = None) -> DataFrame:
        """kernel(ids, carried, other ids, other carried, dots, mask) over strips of every pair of blocks.

        With rows (id, ...) each row brings along `left` where it is an edge's start and `right`
        where it is its end; rows without one take no part.
        """
        nodes, least = self.d.filter("x is not null"), self.least
        count = nodes.count()
        blocks = max(-(-count // self.size), min(-(-count // LEAST), SPREAD), 1)
        if rows is None:
            d = nodes.select("id", "x", *[F.array().cast("array<double>").alias(side) for side in ("left", "right")])
        else:
            d = nodes.join(rows.select("id", left.alias("left"), right.alias("right")), "id")
        # one pass over the rows serves both sides: blocks of the start's side, then of the end's
        own = F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")
        dealt = d.select("id", "x", "left", "right", own.alias("block"), F.explode(F.sequence(F.lit(0), F.lit(2 * blocks - 1))).alias("at"))
        start = F.col("at") < blocks
        dealt = dealt.select("id", "x", F.when(start, F.col("left")).otherwise(F.col("right")).alias("carried"), F.when(start, F.col("block")).otherwise(F.col("at") - blocks).alias("rows"), F.when(start, F.col("at")).otherwise(F.col("block")).alias("columns"), (~start).alias("end"))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            table = pa.Table.from_batches(list(batches))
            end = np.asarray(table.column("end"))
            sides = []
            for side in (~end, end):
                part = table.filter(pa.array(side)).combine_chunks()
                n = part.num_rows
                sides.append((np.asarray(part.column("id")), *(_matrix(part.column(c), n) for c in ("x", "carried"))))
            (ids, x, own), (others, y, brought) = sides
            step = max(STRIP // max(len(others), 1), 1)
            for a in range(0, len(ids) if len(others) else 0, step):
                dots = x[a : a + step] @ y.T
                yield from kernel(ids[a : a + step], own[a : a + step], others, brought, dots, (dots > least) & (ids[a : a + step, None] != others))

        return dealt.groupBy("rows", "columns").applyInArrow(run, schema)

    def edges(self) -> DataFrame:
        return self.run(lambda ids, own, others, brought, dots, mask: _edges(ids, others, mask, lambda p, q: np.ones(len(p))), EDGES)


def _matrix(column: pa.ChunkedArray, n: int) -> np.ndarray:
    values = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return np.asarray(values.flatten(), float).reshape(n, -1) if n else np.zeros((0, 0))


def _edges(ids: np.ndarray, others: np.ndarray, mask: np.ndarray, value: Callable) -> Iterator[pa.RecordBatch]:
    p, q = np.nonzero(mask)
    for a in range(0, len(p), 1 << 16):
        at, to = p[a : a + (1 << 16)], q[a : a + (1 << 16)]
        yield pa.RecordBatch.from_arrays([pa.array(ids[at]), pa.array(others[to]), pa.array(value(at, to))], ["i", "j", "v"])


def masked_in_blocks(graph: NearGraph) -> DataFrame:
    """The masked product of the graph's own rows: each edge's dot, from the block that found it."""
    return graph.run(lambda ids, own, others, brought, dots, mask: _edges(ids, others, mask, lambda p, q: dots[p, q]), EDGES)


def scores_in_blocks(graph: NearGraph, a: DataFrame, u: list[float], v: list[float], slope: float, split: bool) -> DataFrame:
    """leaky(u . a_i + v . a_j) at every edge; split moves one number for each end, else whole rows move to the blocks."""
    from gridchain.functions.vectors import dot

    ends = [np.array(part, float) for part in (u, v)]
    brought_along = [F.array(dot("x", F.array(*[F.lit(float(t)) for t in part]))) if split else F.col("x") for part in (u, v)]

    def kernel(ids, own, others, brought, dots, mask):
        left, right = (own[:, 0], brought[:, 0]) if split else (own @ ends[0], brought @ ends[1])
        return _edges(ids, others, mask, lambda p, q: _leaky(left[p] + right[q], slope))

    return graph.run(kernel, EDGES, a, *brought_along)


def _leaky(x: np.ndarray, slope: float) -> np.ndarray:
    return np.where(x >= 0, x, x * slope)


def attention_in_blocks(graph: NearGraph, rows: DataFrame, froms: list[Column], tos: list[Column], values: list[Column], widths: list[int], softmax: bool, slope: float) -> DataFrame:
    """(id, x): sums of each head's values over a row's edges, weighted by leaky(from + to) or its softmax, heads side by side.

    A block sums its own edges under its own greatest score of each row and head; partial rows
    meet by id, where those of smaller greatest scores shrink.
    """
    heads = len(widths)
    first = np.cumsum([0, *[w + 1 for w in widths]])
    spans = [(int(first[k]), int(first[k + 1])) for k in range(heads)]

    def kernel(ids, own, others, brought, dots, mask):
        some = np.flatnonzero(mask.any(1))
        if not len(some):
            return
        mask = mask[some]
        p, q = np.nonzero(mask)
        starts = np.searchsorted(p, np.arange(len(some)))
        tops, sums = np.zeros((len(some), heads)), np.zeros((len(some), spans[-1][1]))
        weights = np.zeros(mask.shape)
        for k, (a, b) in enumerate(spans):
            e = _leaky(own[some, k][p] + brought[:, k][q], slope)
            if softmax:
                tops[:, k] = np.maximum.reduceat(e, starts)
                e = np.exp(e - tops[p, k])
            weights[p, q] = e
            at = heads + a - k
            sums[:, a : b - 1], sums[:, b - 1] = weights @ brought[:, at : at + b - a - 1], weights.sum(1)
        yield _partial(ids[some], tops, sums)

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, waiting = [], 0
        for batch in batches:
            n = batch.num_rows
            held.append((np.asarray(batch.column("id")), *(_matrix(batch.column(c), n) for c in ("top", "y"))))
            waiting += n
            if waiting > HELD and len(held) > 1:
                held = [_met(held, spans)]
                waiting = 0
        if held:
            ids, tops, sums = _met(held, spans)
            parts = [sums[:, a : b - 1] / sums[:, b - 1 : b] if softmax else sums[:, a : b - 1] for a, b in spans]
            x = np.concatenate(parts, axis=1)
            for a in range(0, len(ids), 4096):
                yield pa.RecordBatch.from_arrays([pa.array(ids[a : a + 4096]), _lists(x[a : a + 4096])], ["id", "x"])

    partial = graph.run(kernel, "id bigint, top array<double>, y array<double>", rows, F.array(*froms), F.concat(F.array(*tos), *values))
    spread = max(-(-graph.d.count() // graph.size), SPREAD)
    bucket = F.pmod(F.xxhash64("id"), F.lit(spread)).cast("int")
    return partial.select(bucket.alias("bucket"), "id", "top", "y").groupBy("bucket").applyInArrow(merge, "id bigint, x array<double>")


def _met(parts: list[tuple], spans: list[tuple[int, int]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Partial rows of the same id as one: under the greatest of their greatest scores."""
    ids, tops, sums = (np.concatenate(x) for x in zip(*parts))
    order = np.argsort(ids, kind="stable")
    ids, tops, sums = ids[order], tops[order], sums[order]
    starts = np.flatnonzero(np.concatenate([[True], ids[1:] != ids[:-1]]))
    top = np.maximum.reduceat(tops, starts, axis=0)
    shrink = np.exp(tops - np.repeat(top, np.diff(np.append(starts, len(ids))), axis=0))
    for k, (a, b) in enumerate(spans):
        sums[:, a:b] *= shrink[:, k : k + 1]
    return ids[starts], top, np.add.reduceat(sums, starts, axis=0)


def _lists(x: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * x.shape[1]), pa.array(x.ravel()))


def _partial(ids: np.ndarray, tops: np.ndarray, sums: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(ids), _lists(tops), _lists(sums)], ["id", "top", "y"])
