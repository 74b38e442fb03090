"""Least squares and attention on small inputs against NumPy."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from gridchain.operators import als, chain, gnn
from gridchain.plans.cost import VARIANTS
from gridchain.plans.grid import Grid
from gridchain.sources import tables


def _problem(spark):
    rng = np.random.default_rng(5)
    cells = sorted({(int(i), int(j)) for i, j in rng.integers(0, [12, 9], (70, 2))})
    c = spark.createDataFrame([(i, j, float(rng.integers(1, 9))) for i, j in cells], "i long, j long, v double").cache()
    a, b = tables.left_factor(c, 4).cache(), tables.right_factor(c, 4).cache()
    return c, a, b


def _array(d):
    return {r.id: np.array(r.x) for r in d.collect()}


def test_cg_solves_each_row(spark):
    c, a, b = _problem(spark)
    got = _array(als.cg(c, als.rhs(c, b), a, b, 6, 0.5))
    y = _array(b)
    for i in got:
        rows = [(r.j, r.v) for r in c.filter(F.col("i") == i).collect()]
        q = np.array([y[j] for j, _ in rows])
        want = np.linalg.solve(q.T @ q + 0.5 * np.eye(4), q.T @ np.array([v for _, v in rows]))
        assert np.allclose(got[i], want, atol=1e-8)


@pytest.mark.parametrize("family,elision", VARIANTS)
def test_matvec_and_steps_on_grids(spark, family, elision):
    c, a, b = _problem(spark)
    on = chain.choose(c, 4, 4, 12, 9, family=family, elision=elision, c=1 if family in ("rd", "rs") else 2)
    plain, grid = (_array(als.batched_matvec(c, a, b, 0.5, x)) for x in (None, on))
    assert plain.keys() == grid.keys() and all(np.allclose(plain[i], grid[i]) for i in plain)
    if (family, elision) in (("ds", "fuse"), ("ss", "reuse")):
        one, two = (_array(als.cg(c, als.rhs(c, b), a, b, 2, 0.5, on=x)) for x in (None, on))
        assert all(np.allclose(one[i], two[i]) for i in one)


@pytest.mark.parametrize("family,elision", [("ds", "none"), ("ds", "reuse"), ("ss", "reuse"), ("rd", "reuse"), ("rs", "none")])
def test_attention_on_grids(spark, family, elision):
    rng = np.random.default_rng(9)
    cells = sorted({(int(i), int(j)) for i, j in rng.integers(0, 14, (60, 2))})
    s = spark.createDataFrame([(i, j, 1.0) for i, j in cells], "i long, j long, v double").cache()
    x = spark.createDataFrame([(k, rng.integers(-8, 9, 6).astype(float).tolist()) for k in range(14)], "id long, x array<double>").cache()
    heads = gnn.seeded_heads(2, 6, 4, 3, project_first=True)
    assert heads == gnn.seeded_heads(2, 6, 4, 3, project_first=True) != gnn.seeded_heads(2, 6, 4, 4, project_first=True)
    want = _array(gnn.multi_head(s, x, heads, project_first=True))
    got = _array(gnn.multi_head_on_grid(s, x, heads, Grid(family, 8, 2, 14, 14, 4), elision))
    assert want.keys() == got.keys() and all(np.allclose(want[i], got[i]) for i in want)
    with pytest.raises(ValueError, match="softmax"):
        gnn.attention_on_grid(s, x, *heads[0], Grid("ds", 8, 2, 14, 14, 4), "fuse")


def test_two_layers(spark):
    rng = np.random.default_rng(2)
    cells = sorted({(int(i), int(j)) for i, j in rng.integers(0, 9, (40, 2))} | {(k, k) for k in range(9)})
    s = spark.createDataFrame([(i, j, 1.0) for i, j in cells], "i long, j long, v double")
    m = rng.integers(-4, 5, (9, 3)).astype(float)
    layers = [gnn.seeded_heads(2, 3, 2, 1), gnn.seeded_heads(1, 4, 3, 2)]
    x = spark.createDataFrame([(k, m[k].tolist()) for k in range(9)], "id long, x array<double>")
    mask = np.zeros((9, 9), bool)
    mask[tuple(zip(*cells))] = True
    for heads in layers:
        parts = []
        for w, vector in heads:
            half = len(vector) // 2
            raw = (m @ vector[:half])[:, None] + (m @ vector[half:])[None, :]
            e = np.where(mask, np.exp(np.where(raw >= 0, raw, 0.2 * raw)), 0)
            parts.append(e / e.sum(1, keepdims=True) @ m @ np.array(w))
        m = np.hstack(parts)
    got = _array(gnn.forward(s, x, layers))
    assert all(np.allclose(got[k], m[k]) for k in range(9))


def test_loss_falls_and_extra_steps_stay_finite(spark):
    c, a, b = _problem(spark)
    before = als.loss(c, a, b).first().loss
    a, b = als.sweep(c, a, b, 7, 0.1)
    after = als.loss(c, a, b).first().loss
    assert after < before and np.isfinite(after)


def test_attention(spark):
    s = spark.createDataFrame([(0, 1, 1.0), (0, 2, 1.0), (1, 0, 1.0)], "i long, j long, v double")
    x = spark.createDataFrame([(0, [1.0, 2.0]), (1, [0.5, -1.0]), (2, [3.0, 0.0])], "id long, x array<double>")
    w, vector = [[1.0, 0.0, 2.0], [0.0, 1.0, 1.0]], [1.0, -1.0, 0.5, 2.0]
    m = {0: np.array([1.0, 2.0]), 1: np.array([0.5, -1.0]), 2: np.array([3.0, 0.0])}
    raw = {(i, j): m[i] @ vector[:2] + m[j] @ vector[2:] for i, j in ((0, 1), (0, 2), (1, 0))}
    want = {k: v if v >= 0 else 0.2 * v for k, v in raw.items()}
    for split in (True, False):
        got = {(r.i, r.j): r.v for r in gnn.attention_scores(s, x, vector, split=split).collect()}
        assert all(np.isclose(got[k], want[k]) for k in want)
    soft = {(r.i, r.j): r.v for r in gnn.row_softmax(gnn.attention_scores(s, x, vector)).collect()}
    assert np.isclose(soft[0, 1] + soft[0, 2], 1) and np.isclose(soft[1, 0], 1)
    head = _array(gnn.attention_layer(s, x, w, vector))
    assert np.allclose(head[0], soft[0, 1] * (m[1] @ np.array(w)) + soft[0, 2] * (m[2] @ np.array(w)))
    both = _array(gnn.multi_head(s, x, [(w, vector), (w, vector)]))
    assert np.allclose(both[0], np.concatenate([head[0], head[0]]))
    conv = _array(gnn.conv_layer(s, x, w))
    assert np.allclose(conv[1], np.maximum(m[0] @ np.array(w), 0))
