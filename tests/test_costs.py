"""Closed forms, planner and ledger against each other and against limits known beforehand."""

import math
import types

import pytest
from pyspark.sql import functions as F

from gridchain.operators.baselines import sparse_replicate_15_words
from gridchain.plans import cost, ledger, planner
from gridchain.plans.grid import Grid, place_left
from gridchain.sources import random_matrices, scratch, tables


@pytest.mark.parametrize("family,elision", cost.VARIANTS)
@pytest.mark.parametrize("p,phi", [(256, 0.125), (64, 1.0), (1024, 4.0)])
def test_closed_best_c_is_the_minimum(family, elision, p, phi):
    best = min((k / 200 for k in range(20, 200 * 400)), key=lambda c: cost.predict_words(family, elision, p, c, phi))
    assert cost.best_c_closed(family, elision, p, phi) == pytest.approx(best, abs=0.02)


@pytest.mark.parametrize("p,reuse,fuse", [(64, 0.7209, 0.6876), (256, 0.7138, 0.6977), (4096, 0.7087, 0.7048)])
def test_elision_ratios(p, reuse, fuse):
    assert cost.elision_ratio("ds", "reuse", p) == pytest.approx(reuse, abs=5e-5)
    assert cost.elision_ratio("ds", "fuse", p) == pytest.approx(fuse, abs=5e-5)
    assert cost.elision_ratio("rd", "reuse", 10**9, 1.0) == pytest.approx(2 ** (-1 / 3), abs=2e-3)


def test_best_c_curve():
    curve = {e: [cost.best_c_admissible("ds", e, 2**k, 0.125, 256, 8) for k in range(1, 9)] for e in ("reuse", "none", "fuse")}
    assert curve == {"reuse": [2, 2, 4, 4, 8, 8, 8, 8], "none": [1, 2, 2, 4, 4, 8, 8, 8], "fuse": [1, 1, 2, 2, 4, 4, 8, 8]}


@pytest.mark.parametrize("phi,want", [(0.005, ("ss", 1)), (0.03, ("ss", 2)), (0.1, ("ss", 4)), (0.25, ("ss", 8)), (0.5, ("ds", 4))])
def test_planner_at_32_stations(phi, want):
    n, r = 1 << 22, 1000
    family, _, c = planner.choose(32, n, r, round(n * r * phi), 16)
    assert (family, c) == want


def test_crossover():
    assert planner.crossover_phi(32) == pytest.approx(7 / 24, abs=1e-3)


def test_weak_scaling_exponents():
    sizes = [2**k for k in range(10, 20)]
    for family, elision in cost.VARIANTS:
        want = 1 / 2 if family in ("ds", "ss") else 1 / 3
        grown = cost.scaling_exponent(family, elision, sizes)
        assert grown == pytest.approx(want, abs=0.06), (family, elision)


@pytest.mark.parametrize("family,elision", cost.VARIANTS)
def test_ledger_agrees_with_the_formula(spark, family, elision):
    n, d, r = 256, 4, 16
    s = random_matrices.lattice(spark, n, d)
    a, b = tables.left_factor(s, r), tables.dense_lattice(spark.range(n).select("id"), r, 13, 19)
    row = ledger.words(ledger.chain_ledger(s, a, b, Grid(family, 16, 4, n, n, r), elision)).first()
    assert row.mean_words == pytest.approx(cost.predict_words(family, elision, 16, 4, d / r, n * r))
    assert row.messages == pytest.approx(cost.predict_messages(family, elision, 16, 4))


def test_what_exchanges_bring_is_below_the_ring(spark):
    """A shuffle skips a station's own blocks and partial sums that no nonzero makes; 1.5D results need no relayout."""
    n, d, r = 256, 4, 16
    s = random_matrices.lattice(spark, n, d)
    a, b = (tables.dense_lattice(spark.range(n).select("id"), r, x, y) for x, y in ((31, 17), (13, 19)))
    for family, elision in (("ds", "fuse"), ("ds", "none"), ("rd", "reuse")):
        grid = Grid(family, 16, 4, n, n, r)
        stages = {x.stage: x for x in ledger.by_stage(ledger.chain_ledger(s, a, b, grid, elision)).collect()}
        assert all(x.remote_words <= x.all_words for x in stages.values() if x.stage != "partial dots")
        assert stages["copy"].all_words == stages["copy"].remote_words == 3 * n * r
        outside = {x.stage: x.all_words for x in ledger.by_stage(ledger.iteration_ledger(a, grid, elision)).collect()}
        assert ("relayout" in outside) == (family == "rd") and ("row_dot" in outside) == (family == "rd")


@pytest.mark.parametrize("order", ["layer", "fiber"])
def test_skew_is_an_option(spark, order):
    n, r = 64, 16
    s = random_matrices.lattice(spark, n, 4)
    a, b = (tables.dense_lattice(spark.range(n).select("id"), r, x, y) for x, y in ((31, 17), (13, 19)))
    for family, moved in (("rd", [b]), ("rs", [a, b]), ("ds", [])):
        grid = Grid(family, 16, 4, n, n, r, order)
        plain, more = (ledger.by_stage(ledger.chain_ledger(s, a, b, grid, "none", x)) for x in (False, True))
        extra = more.filter("stage = 'skew'").collect()
        assert plain.filter("stage = 'skew'").isEmpty() and len(extra) == (1 if moved else 0)
        if moved:  # q = 2: blocks of the second row or column move, half of all
            cells = 3 * s.count() / 2 if family == "rd" else 0
            assert extra[0].remote_words == 0 and extra[0].all_words == pytest.approx(len(moved) * n * r / 2 + cells, rel=0.1)


def test_local_sizes_and_placed_tables(spark, tmp_path):
    n, r = 64, 16
    s = random_matrices.lattice(spark, n, 4)
    d = tables.dense_lattice(spark.range(n).select("id"), r, 31, 17)
    for family in ("ds", "ss", "rd", "rs"):
        grid = Grid(family, 16, 4, n, n, r)
        sizes = cost.local_dims(family, 16, 4, n, r)
        high, wide = sizes.get("copied", sizes["moving"] if "moving" in sizes else None)
        found = place_left(d, grid).groupBy("station").agg(F.sum(F.size("ax")).alias("words")).select("words").distinct().collect()
        # 2.5D sparse-replicating stations hold a slab for each of the q blocks that pass
        assert [x.words for x in found] == [high * wide * (grid.q if family == "rs" else 1)]
    grid = Grid("ds", 16, 4, n, n, r)
    tables.write_placed(s, grid, f"file://{tmp_path}/placed")
    back = spark.read.parquet(f"file://{tmp_path}/placed")
    assert back.count() == s.count() and back.select("station").distinct().count() == 16
    renamed = random_matrices.hashed(s)
    assert renamed.select("i").distinct().count() == n and renamed.count() == renamed.distinct().count() == s.count()


def test_prior_scheme_pays_more_for_tall_operands():
    best = lambda f: min(f(c) for c in (1, 2, 4, 8, 16))
    for phi in (0.1, 0.5, 1.0):
        ours = best(lambda c, phi=phi: cost.predict_words("ss", "reuse", 64, c, phi))
        assert ours < best(lambda c, phi=phi: sparse_replicate_15_words(64, c, phi))


def test_scratch_folder(spark, monkeypatch):
    """The named folder; without one the warehouse on a cluster, and a temporary folder only where the master is local."""
    named = scratch.scratch_dir(spark)
    assert named == spark.sparkContext.getConf().get("spark.checkpoint.dir").rstrip("/")
    path = scratch.scratch_path(spark, "x")
    assert path.startswith(named + "/gridchain-") and path.rsplit("/", 1)[0] == scratch.scratch_path(spark, "y").rsplit("/", 1)[0]
    settings = types.SimpleNamespace(get=lambda name, default=None: "hdfs://shared/warehouse" if name == "spark.sql.warehouse.dir" else default)
    context = types.SimpleNamespace(getConf=lambda: types.SimpleNamespace(get=lambda name: None), master="spark://host:7077")
    assert scratch.scratch_dir(types.SimpleNamespace(conf=settings, sparkContext=context)) == "hdfs://shared/warehouse"
    kept = scratch.stored(spark.range(3), "kept")
    assert kept.count() == 3
    scratch.delete(spark, path.rsplit("/", 1)[0])
    with pytest.raises(Exception, match="(?i)not.exist|no such file"):
        kept.count()


def test_generators(spark):
    s = random_matrices.lattice(spark, 512, 8)
    assert s.count() == s.select("i", "j").distinct().count() == 4096
    assert random_matrices.weak_setup1(4) == (1024, 8) and random_matrices.weak_setup2(16) == (1024, 32)
    assert 0.98 * 4096 < random_matrices.bernoulli(spark, 512, 8).count() <= 4096
    with pytest.raises(ValueError):
        random_matrices.lattice(spark, 100, 8)


def test_memory_limits_and_refusals():
    rows = planner.candidates(32, 1 << 20, 128, 1 << 24, 16, memory=2e7)
    assert any(x[7] and "more than" in x[7] for x in rows) and math.isfinite(next(x[4] for x in rows if x[7] is None))
    assert planner.prefer_fetch(10, 8, 4, 1000.0) and not planner.prefer_fetch(10**6, 8, 4, 1000.0)
