"""Kernels, chains and their invariants on small matrices with exact sums."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from gridchain.operators import baselines, chain, kernels, station
from gridchain.operators.matrix import densify, from_long, from_row_map, max_error, stats, to_long, to_row_map, transpose, validate_dense, validate_sparse
from gridchain.plans import cost
from gridchain.plans.cost import VARIANTS
from gridchain.plans.grid import Grid, place_left, place_right, place_sparse
from gridchain.sources import random_matrices, tables
from gridchain.sources.scratch import stored

M, N, R = 13, 11, 8


@pytest.fixture(scope="module")
def operands(spark):
    rng = np.random.default_rng(3)
    cells = sorted({(int(i), int(j)) for i, j in rng.integers(0, [M, N], (60, 2)) if i != 4})
    s = spark.createDataFrame([(i, j, float(k % 5)) for k, (i, j) in enumerate(cells)], "i long, j long, v double").cache()
    a, b = (tables.dense_lattice(spark.range(n).select("id"), R, x, y).cache() for n, x, y in ((M, 31, 17), (N, 13, 19)))
    dense = np.zeros((M, N))
    mask = np.zeros((M, N), bool)
    for r in s.collect():
        dense[r.i, r.j], mask[r.i, r.j] = r.v, True
    x = np.array([r.x for r in a.orderBy("id").collect()])
    y = np.array([r.x for r in b.orderBy("id").collect()])
    return s, a, b, dense, mask, x, y


def long(df):
    return {(r.id, r.k): r.x for r in df.collect()}


def expected(matrix, rows):
    return {(i, k): matrix[i, k] for i in rows for k in range(matrix.shape[1])}


def test_masked_product_keeps_the_pattern(operands):
    s, a, b, dense, mask, x, y = operands
    got = {(r.i, r.j): r.v for r in kernels.masked_product(s, a, b).collect()}
    want = dense * (x @ y.T)
    assert got == {(i, j): want[i, j] for i, j in zip(*np.nonzero(mask))}
    plain = {(r.i, r.j): r.v for r in kernels.masked_product(s, a, b, scaled=False).collect()}
    assert plain == {(i, j): (x @ y.T)[i, j] for i, j in zip(*np.nonzero(mask))}
    assert {(r.i, r.j): r.v for r in baselines.dense_then_mask(s, a, b).collect()} == got


def test_gathers_and_zero_rows(operands, spark):
    s, a, b, dense, mask, x, y = operands
    left = kernels.gather_left(s, b, spark.range(M), R)
    assert {r.id: r.x for r in left.collect()} == {i: (dense @ y)[i].tolist() for i in range(M)}
    right = kernels.gather_right(s, a)
    assert long(to_long(right)) == expected(dense.T @ x, np.flatnonzero(mask.any(0)))


@pytest.mark.parametrize("family,elision", VARIANTS)
@pytest.mark.parametrize("p,c", [(8, 2), (16, 4), (4, 1)])
def test_every_variant_gives_the_same_chain(operands, family, elision, p, c):
    s, a, b, dense, mask, x, y = operands
    want = (dense * (x @ y.T)) @ y
    got = long(chain.chain_left(s, a, b, Grid(family, p, c, M, N, R), elision))
    assert got == expected(want, np.flatnonzero(mask.any(1)))


def test_chain_right_and_phases(operands):
    s, a, b, dense, mask, x, y = operands
    right = (dense * (x @ y.T)).T @ x
    got = long(chain.chain_right(s, a, b, Grid("ds", 8, 2, M, N, R), "reuse"))
    assert got == expected(right, np.flatnonzero(mask.any(0)))
    left = (dense * (x @ y.T)) @ y
    for order in ("layer", "fiber"):
        assert long(chain.chain_phased(s, a, b, Grid("ds", 8, 2, M, N, R, order))) == expected(left, np.flatnonzero(mask.any(1)))


@pytest.mark.parametrize("family", ["ds", "ss", "rd", "rs"])
@pytest.mark.parametrize("p,c", [(8, 2), (16, 4), (4, 4)])
def test_every_triple_meets_once(spark, family, p, c):
    grid = Grid(family, p, c, 8, 8, 8)
    cells = spark.range(64).select(F.floor(F.col("id") / 8).alias("i"), (F.col("id") % 8).alias("j"), F.lit(1.0).alias("v"))
    d = spark.range(8).select("id", F.array_repeat(F.lit(1.0), 8).alias("x"))
    met = place_sparse(cells, grid).drop("home").join(place_left(d, grid).drop("start", "home"), ["station", "i"]).join(place_right(d, grid).drop("home"), ["station", "slab", "j"])
    triples = met.select("i", "j", F.explode(F.sequence(F.col("start"), F.col("start") + F.size("bx") - 1)).alias("k")).groupBy("i", "j", "k").count()
    assert triples.count() == 512 and triples.filter("count <> 1").isEmpty()


def test_refusals():
    for family in ("ss", "rd", "rs"):
        with pytest.raises(ValueError, match="fuse"):
            chain.check_elision(family, "fuse")
    with pytest.raises(ValueError, match="replicates no dense"):
        chain.check_elision("rs", "reuse")
    with pytest.raises(ValueError, match="exclude"):
        chain.check_elision("ds", "reuse+fuse")
    with pytest.raises(ValueError, match="softmax"):
        chain.check_elision("ds", "fuse", softmax=True)
    with pytest.raises(ValueError, match="divide"):
        Grid("ds", 8, 3, 4, 4, 4)
    with pytest.raises(ValueError, match="square"):
        Grid("rd", 8, 1, 4, 4, 4)
    with pytest.raises(ValueError, match="slabs"):
        Grid("ss", 256, 1, 10, 10, 128)
    with pytest.raises(ValueError, match="inferior"):
        Grid("15_sparse_replicate", 8, 2, 4, 4, 4)


def test_missing_rows_and_checks(spark, operands):
    s, a, b, *_ = operands
    some = b.filter("id <> 3")
    with pytest.raises(ValueError, match="no dense row"):
        kernels.masked_product(s, a, some, on_missing="error")
    zero = kernels.masked_product(s, a, some, on_missing="zero")
    assert zero.count() == s.count() and {r.v for r in zero.filter("j = 3").collect()} <= {0.0}
    assert kernels.masked_product(s, a, some, on_missing="drop").filter("j = 3").isEmpty()
    with pytest.raises(Exception, match="holds a null"):
        validate_sparse(spark.createDataFrame([(1, None, 2.0)], "i long, j long, v double")).collect()
    with pytest.raises(Exception, match="needs 3 values"):
        validate_dense(b, 3).collect()


def test_empty_and_special_values(spark):
    empty = spark.createDataFrame([], "i long, j long, v double")
    d = spark.createDataFrame([(0, [1.0])], "id long, x array<double>")
    assert kernels.masked_product(empty, d, d).isEmpty() and kernels.gather_left(empty, d).isEmpty()
    odd = spark.createDataFrame([(0, 0, float("nan"))], "i long, j long, v double")
    assert np.isnan(kernels.gather_left(odd, d).first().x[0])


def test_forms_and_permutations(spark, operands):
    s, a, b, *_ = operands
    assert sorted(from_row_map(to_row_map(s)).collect()) == sorted(s.collect())
    assert sorted(from_long(to_long(b)).collect()) == sorted(b.collect())
    assert sorted(transpose(transpose(s)).collect()) == sorted(s.collect())
    moved = random_matrices.affine(s, M, N, 101)
    back = random_matrices.inverse_affine(random_matrices.inverse_affine(moved, M, 101, key="i"), N, 101, key="j")
    assert sorted(back.collect()) == sorted(s.collect())
    assert densify(a.filter("id < 2"), spark.range(4), R).filter("id = 3").first().x == [0.0] * R
    assert stats(s, R).nnz == s.count()


def test_coordinate_text_round_trip(spark, operands, tmp_path):
    s = operands[0]
    tables.write_coordinate_text(s, f"file://{tmp_path}/m", M, N)
    assert sorted(tables.read_coordinate_text(spark, f"file://{tmp_path}/m").collect()) == sorted(s.collect())
    for form in ("csv", "json", "orc", "parquet"):
        tables.write(s, f"file://{tmp_path}/{form}", form)
        assert sorted(tables.read(spark, f"file://{tmp_path}/{form}", form).collect()) == sorted(s.collect())


def test_weight_stays_below_the_generator(operands):
    s, _, b, *_ = operands
    plan = kernels.gather_long(s, b)._jdf.queryExecution().optimizedPlan().toString()
    lines = plan.splitlines()
    generate = next(k for k, line in enumerate(lines) if "Generate posexplode" in line)
    assert not any("lambdafunction" in line or "transform(" in line for line in lines[:generate])
    assert any("transform(" in line for line in lines[generate:])


@pytest.fixture
def plain_plans(spark):
    """Plans as they run, without adaptive changes or broadcasts of these small tables."""
    names = {"spark.sql.adaptive.enabled": "false", "spark.sql.autoBroadcastJoinThreshold": "-1"}
    before = {k: spark.conf.get(k) for k in names}
    for k, v in names.items():
        spark.conf.set(k, v)
    yield
    for k, v in before.items():
        spark.conf.set(k, v)


def exchanges(df):
    """(exchanges that are made, exchanges that are read again) of a plan."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return sum("Exchange hashpartitioning" in x and "Reused" not in x for x in plan.splitlines()), plan.count("ReusedExchange")


@pytest.fixture
def stored_plans(monkeypatch):
    """Exchanges of the jobs whose results are stored, in order."""
    seen = []

    def keep(df, tag, codec="zstd"):
        seen.append(exchanges(df))
        return stored(df, tag, codec)

    monkeypatch.setattr(chain, "stored", keep)
    monkeypatch.setattr(baselines, "stored", keep)
    return seen


def test_exchanges_of_each_variant(operands, plain_plans, stored_plans):
    """The savings are exchanges that are absent; operands are laid out first, so only the chain's own are seen."""
    s, a, b, *_ = operands
    own = lambda f, e: exchanges(chain.chain_left(s, a, b, Grid(f, 8, 2, M, N, R), e))
    # fuse: copy, moving operand, nonzeros, and the sum over the fiber
    assert own("ds", "fuse") == (4, 0) and own("ds", "reuse") == (4, 0) and not stored_plans
    # none: a first job deals all three operands; the second deals the moving operand and the result again, and sums
    assert own("ds", "none") == (3, 0) and stored_plans == [(3, 0)]
    stored_plans.clear()
    # slabs: partial dots meet by nonzero; reuse reads the copied operand's one exchange twice, none makes two
    assert own("ss", "reuse") == (5, 1) and own("rd", "reuse") == (6, 1) and not stored_plans
    assert own("ss", "none") == (3, 0) and own("rd", "none") == (3, 0) and own("rs", "none") == (3, 0)
    assert stored_plans == [(4, 0)] * 3
    stored_plans.clear()
    assert exchanges(baselines.two_gathers(s, b, 4, M))[1] == 0 and stored_plans == [(2, 0), (2, 0)]


def shuffled_bytes(df):
    """Bytes of rows that a plan's exchanges wrote, after running it."""
    plan = df._jdf.queryExecution().executedPlan()
    plan.execute().count()
    total, todo = 0, [plan]
    while todo:
        node = todo.pop()
        children = node.children()
        todo += [children.apply(k) for k in range(children.size())]
        if node.nodeName() == "Exchange":
            total += node.metrics().apply("dataSize").value()
    return total


@pytest.mark.parametrize("family,elision", [("ds", "fuse"), ("ds", "reuse"), ("ss", "reuse")])
def test_shuffled_bytes_follow_the_words(spark, plain_plans, family, elision):
    """Rows of 64 numbers: an exchange writes 8 bytes a dense word, plus some for each row; a nonzero's 3 words are a row of at most 120 bytes."""
    n, d, r, p = 256, 4, 64, 16
    s = random_matrices.lattice(spark, n, d).cache()
    a, b = (tables.dense_lattice(spark.range(n).select("id"), r, x, y).cache() for x, y in ((31, 17), (13, 19)))
    for c in (2, 4, 8):
        words = cost.predict_words(family, elision, p, c, d / r, n * r) * p
        # a closed form leaves out what does not move in a ring: the copy's own block, and a stationary operand
        home = n * r * (2 if family == "ss" else 1)
        cells = n * d * (p // c if family == "ss" else 1)
        got = shuffled_bytes(chain.chain_left(s, a, b, Grid(family, p, c, n, n, r), elision))
        low, high = 8 * 0.5 * words, 8 * 1.9 * (words + home) + 120 * 4 * cells
        assert low < got < high, (c, low, got, high)


def test_each_station_has_a_partition(spark):
    for p in (1, 8, 30, 128):
        rows = spark.range(p * 3).select((F.col("id") % p).cast("int").alias("station"), F.lit(2).alias("tag"), F.lit(0).cast("long").alias("i"), F.lit(0).cast("long").alias("j"), F.lit(0.0).alias("v"), F.lit(None).cast("array<double>").alias("x"))
        sizes = station.deal(rows, p).groupBy(F.spark_partition_id()).count().collect()
        assert len(sizes) == p and {r["count"] for r in sizes} == {3}


def test_planner_runs_the_chain(operands, spark):
    s, a, b, dense, mask, x, y = operands
    want = expected((dense * (x @ y.T)) @ y, np.flatnonzero(mask.any(1)))
    assert long(chain.chain(s, a, b, 8, R)) == want
    assert long(chain.chain(s, a, b, 8, R, family="ss", c=2)) == want
    found = chain.choose(s, 8, R, remote_rows=0)
    assert found.grid is None and long(chain.chain(s, a, b, 8, R, remote_rows=0)) == want
    plain = expected((mask * (x @ y.T)) @ y, np.flatnonzero(mask.any(1)))
    for family, elision in VARIANTS:
        assert long(chain.chain(s, a, b, 8, R, family=family, elision=elision, c=2, scaled=False)) == plain
    with pytest.raises(ValueError, match="admissible"):
        chain.choose(s, 8, R, family="rs", elision="fuse")


def test_kernels_with_missing_rows_and_empty_sides(operands, spark):
    s, a, b, *_ = operands
    grid = Grid("rd", 8, 2, M, N, R)
    some = b.filter("id <> 3")
    got = {(r.i, r.j): r.v for r in chain.masked(s, a, some, grid).collect()}
    assert got == {(r.i, r.j): r.v for r in kernels.masked_product(s, a, some).collect()}
    nothing = s.filter("false")
    assert chain.chain_left(nothing, a, b, grid, "reuse").isEmpty() and chain.masked(s, a, b.filter("false"), grid).isEmpty()


def test_numbers_and_errors(spark):
    rows = spark.createDataFrame([(k * 7 % 50, f"w{k}") for k in range(50)], "total long, word string").repartition(6)
    got = tables.numbered(rows, F.desc("total"), "word").collect()
    assert {r.number: r.total for r in got} == {k: 49 - k for k in range(50)}
    one = spark.createDataFrame([(0, 0, 1.0), (1, 0, 2.0)], "id long, k long, x double")
    other = spark.createDataFrame([(0, 0, 1.5), (2, 0, 3.0)], "id long, k long, x double")
    row = max_error(one, other).first()
    assert (row.largest, row.relative, row.missing) == (0.5, 0.5 / 1.5, 2)
    assert max_error(one, one).first().largest == 0.0


@pytest.mark.parametrize("step", [1, 5, 1000])
def test_places_of_ids(step):
    rng = np.random.default_rng(3)
    ids = rng.permutation(50) * step - 20
    rows = station.Slabs()
    rows.add(ids, np.zeros(50, np.int64), pa.array([[float(k), 1.0] for k in ids]))
    rows.close()
    wanted = np.concatenate([ids, [-10**12, 10**12, ids.max() + 1, ids.min() - 1]])
    at, there = rows.find(0, wanted)
    assert there.tolist() == [True] * 50 + [False] * 4 and np.array_equal(rows.blocks[0][1][at[:50], 0], ids)


def test_sums_go_through_what_they_hold_rarely(monkeypatch):
    monkeypatch.setattr(station, "HELD", 64)
    runs, total = [], station.Sums.total
    monkeypatch.setattr(station.Sums, "total", lambda self: runs.append(sum(len(i) for i, _ in self.held)) or total(self))
    sums, want, rng = station.Sums(), np.zeros(4000), np.random.default_rng(2)
    for _ in range(500):
        ids = rng.integers(0, 4000, 80)
        sums.add(ids, np.ones((80, 1)))
        np.add.at(want, ids, 1)
    ids, x = sums.total()
    assert np.array_equal(x[:, 0], want[ids]) and len(ids) == (want > 0).sum()
    assert sum(runs) < 4 * 500 * 80
