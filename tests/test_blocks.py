"""Kernels over a graph that is made in the blocks that use it, against the same graph as rows."""

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from gridchain.operators import blocks, gnn, kernels, station
from gridchain.plans.cost import VARIANTS
from gridchain.plans.grid import Grid

SMALL = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def graph(spark):
    rng = np.random.default_rng(4)
    rows = [(int(k), (x / np.linalg.norm(x)).tolist()) for k, x in zip(rng.permutation(300)[:90] - 20, rng.normal(size=(90, 6)))]
    x = spark.createDataFrame([*rows, (999, None)], "id long, x array<double>").cache()
    near = blocks.NearGraph(x, 0.3, size=16)
    m = {k: np.array(v) for k, v in rows}
    pairs = {(i, j) for i in m for j in m if i != j and m[i] @ m[j] > 0.3}
    return near, near.edges().cache(), x.filter("x is not null").cache(), m, pairs


def array(d):
    return {r.id: np.array(r.x) for r in d.collect()}


def test_edges_and_masked_product(graph):
    near, s, x, m, pairs = graph
    got = [(r.i, r.j) for r in s.collect()]
    assert len(got) == len(set(got)) and set(got) == pairs
    dots = {(r.i, r.j): r.v for r in blocks.masked_in_blocks(near).collect()}
    want = {(r.i, r.j): r.v for r in kernels.masked_product(s, x, x).collect()}
    assert dots.keys() == want.keys() and all(np.isclose(dots[k], want[k]) for k in want)


@pytest.mark.parametrize("split", [True, False])
def test_scores(graph, split):
    near, s, x, *_ = graph
    vector = gnn.lattice_attention(12)
    got, want = ({(r.i, r.j): r.v for r in gnn.attention_scores(g, x, vector, split=split).collect()} for g in (near, s))
    assert got.keys() == want.keys() and all(np.isclose(got[k], want[k]) for k in want)


@pytest.mark.parametrize("project_first,softmax", [(False, True), (True, True), (True, False)])
def test_heads_of_unequal_width_and_large_scores(graph, project_first, softmax):
    near, s, x, *_ = graph
    heads = gnn.seeded_heads(1, 6, 4, 3, project_first) + gnn.seeded_heads(1, 6, 3, 7, project_first)
    # scores of several hundred: only sums under each row's own greatest score stay finite
    heads = [(w, [900 * t for t in vector]) for w, vector in heads]
    some = x.filter("id % 5 <> 0")
    got, want = (array(gnn.multi_head(g, some, heads, softmax, project_first=project_first)) for g in (near, s))
    assert got.keys() == want.keys() and all(np.allclose(got[i], want[i], rtol=1e-9) and np.isfinite(got[i]).all() for i in want)


def test_layers(graph):
    near, s, x, *_ = graph
    layers = [gnn.seeded_heads(2, 6, 4, 1), gnn.seeded_heads(2, 8, 3, 2)]
    got, want = (array(gnn.forward(g, x, layers)) for g in (near, s))
    assert got.keys() == want.keys() and all(np.allclose(got[i], want[i]) for i in want)


@pytest.mark.parametrize("order,softmax", [("layer", True), ("fiber", False)])
@pytest.mark.parametrize("family,elision", [v for v in VARIANTS if v[1] != "fuse"])
def test_heads_at_stations(graph, family, elision, order, softmax):
    near, s, x, m, pairs = graph
    moved = blocks.NearGraph(near.d.withColumn("id", F.col("id") + 20), near.least)  # a grid's ids start at 0
    x, s = (d.select(*[(F.col(c) + 20).alias(c) if c in ("id", "i", "j") else c for c in d.columns]) for d in (x, s))
    # scores of several hundred: only sums under each row's own greatest score stay finite
    heads = [(w, [900 * t for t in vector]) for w, vector in gnn.seeded_heads(2, 6, 5, 3, project_first=True)]
    some = x.filter("id % 5 <> 0")
    grid = Grid(family, 8, 2, 320, 320, 5, order)
    want = array(gnn.multi_head(s, some, heads, softmax, project_first=True))
    got = array(gnn.multi_head_on_grid(moved, some, heads, grid, elision, softmax=softmax))
    assert got.keys() == want.keys() and all(np.allclose(got[i], want[i], rtol=1e-9) and np.isfinite(got[i]).all() for i in want)


@pytest.mark.parametrize("family,elision", [v for v in VARIANTS if v[1] != "fuse"])
def test_heads_in_turns(graph, monkeypatch, spark, family, elision):
    """Starts and ends of edges come a part at a time: no turn deals all vectors, and the heads are the same."""
    from gridchain.operators import near_stations

    near, s, x, *_ = graph
    moved = blocks.NearGraph(near.d.withColumn("id", F.col("id") + 20), near.least)
    x, s = (d.select(*[(F.col(c) + 20).alias(c) if c in ("id", "i", "j") else c for c in d.columns]) for d in (x, s))
    heads = [(w, [900 * t for t in vector]) for w, vector in gnn.seeded_heads(2, 6, 5, 3, project_first=True)]
    dealt, real = [], near_stations._dealt

    def seen(d, grid, side, tag, *rest, **more):
        if tag == near_stations.START and rest[1]:
            dealt.append(d.count())
        return real(d, grid, side, tag, *rest, **more)

    monkeypatch.setattr(near_stations, "_dealt", seen)
    count = near.d.filter("x is not null").count()
    monkeypatch.setattr(near_stations, "TURN", -(-count // 2), raising=False)
    got = array(gnn.multi_head_on_grid(moved, x, heads, Grid(family, 8, 2, 320, 320, 5), elision))
    want = array(gnn.multi_head(s, x, heads, project_first=True))
    assert max(dealt) < 0.8 * count
    assert got.keys() == want.keys() and all(np.allclose(got[i], want[i], rtol=1e-9) and np.isfinite(got[i]).all() for i in want)


def moved_rows(df):
    """Rows that a plan's exchanges wrote, after running it."""
    plan = df._jdf.queryExecution().executedPlan()
    rows = plan.execute().count()
    total, todo = 0, [plan]
    while todo:
        node = todo.pop()
        children = node.children()
        todo += [children.apply(k) for k in range(children.size())]
        if node.nodeName() == "Exchange":
            total += node.metrics().apply("shuffleRecordsWritten").value()
    return total, rows


@pytest.mark.parametrize("name", ["gat_forward_two_layers", "gat_scores_moving_rows", "gat_multi_head_projected", "cosine_graph_masked", "gat_multi_head"])
def test_no_edge_is_moved(spark, name):
    names = {"spark.sql.adaptive.enabled": "false", "spark.sql.autoBroadcastJoinThreshold": "-1"}
    before = {k: spark.conf.get(k) for k in names}
    for k, v in names.items():
        spark.conf.set(k, v)
    try:
        moved, rows = moved_rows(__spark_entry__.queries()[name](spark, SMALL))
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)
    # 13,880 edges between 500 rows
    assert moved < 5000 and rows in (500, 8000, 13880)


@pytest.mark.parametrize("family,elision", [v for v in VARIANTS if v[1] != "fuse"])
def test_no_edge_is_dealt_to_a_station(spark, family, elision):
    """All pairs of 300 rows are edges; what is stored on the way is moved and counted before."""
    names = {"spark.sql.adaptive.enabled": "false", "spark.sql.autoBroadcastJoinThreshold": "-1"}
    before = {k: spark.conf.get(k) for k in names}
    for k, v in names.items():
        spark.conf.set(k, v)
    try:
        x = spark.range(300).selectExpr("id", "array(1D + id / 300, 2D) as x")
        heads = gnn.seeded_heads(2, 2, 4, 5, project_first=True)
        moved, rows = moved_rows(gnn.multi_head_on_grid(blocks.NearGraph(x, 0.0), x, heads, Grid(family, 8, 2, 300, 300, 4), elision))
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)
    assert moved < 300 * 60 and rows == 300


@pytest.mark.parametrize("family,elision", [("ds", "reuse"), ("rs", "none")])
def test_vectors_travel_in_single_precision(spark, family, elision):
    """Where it is exact, row by row; other rows keep double precision, and the heads are the same."""
    x = np.random.default_rng(3).normal(size=(90, 64)).astype("f4").astype(float)
    x[::3, 5] += 1e-12
    heads = gnn.seeded_heads(2, 64, 8, 5, project_first=True)
    rows = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(x)], "id long, x array<double>")
    got = array(gnn.multi_head_on_grid(blocks.NearGraph(rows, 1.0), rows, heads, Grid(family, 8, 2, 90, 90, 8), elision))
    want = array(gnn.multi_head(blocks.NearGraph(rows, 1.0), rows, heads, project_first=True))
    assert got.keys() == want.keys() and len(got) > 80 and all(np.allclose(got[k], want[k]) for k in want)


def test_exact_vectors_are_halved(spark):
    """What a row of 64 exact numbers takes when it is dealt: below 8 bytes a number; rows that only their home reads go there alone."""
    from gridchain.operators import near_stations

    grid = Grid("ds", 8, 2, 40, 40, 8)
    rows = spark.range(40).selectExpr("id", "array(array(1D, 2D)) as x", "cast(null as array<double>) as near", "transform(sequence(1, 64), k -> cast(k / 64 as float)) as near32")
    dealt = near_stations._dealt(rows, grid, "right", near_stations.DENSE, True, True, False)
    assert dealt.count() == 160 and dealt.filter("near is null and size(near32) = 64 and size(x) = 2").count() == 160
    assert near_stations._dealt(rows, grid, "right", near_stations.DENSE, True, False, False, home=True).count() == 40


@pytest.mark.parametrize("name", ["als_matvec_ss_reuse", "chain_left_ss_none", "chain_right_ss_reuse", "special_2d"])
def test_nonzeros_move_in_chunks(spark, name):
    """Fewer rows move than there are nonzeros, though each visits several stations."""
    names = {"spark.sql.adaptive.enabled": "false", "spark.sql.autoBroadcastJoinThreshold": "-1"}
    before = {k: spark.conf.get(k) for k in names}
    for k, v in names.items():
        spark.conf.set(k, v)
    try:
        moved, _ = moved_rows(__spark_entry__.queries()[name](spark, "/root/testdata/sf0.001"))
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)
    assert moved < 5500


@pytest.mark.parametrize("base,width", [(0, 200), (-(1 << 40), 1 << 17), (1 << 62, 1 << 34)])
def test_packed_nonzeros(base, width):
    rng = np.random.default_rng(1)
    i, j = np.sort(rng.integers(base, base + width, 500)), rng.integers(base, base + width, 500)
    v = np.concatenate([rng.normal(size=497), [np.nan, np.inf, -0.0]])
    got = station.unpack(station.pack(i, j, v))
    assert all(np.array_equal(a, b, equal_nan=a.dtype.kind == "f") for a, b in zip(got, (i, j, v)))
