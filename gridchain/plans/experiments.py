"""The reference's experiments on this engine: python -m gridchain.plans.experiments [name ...] prints one JSON line for each.

Seconds are of one machine whose stations are partitions, so ratios, words and winners are
what can be compared. Every timed result is written in full by Spark's noop sink or stored.
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridchain.operators import als, baselines, chain, gnn
from gridchain.operators.matrix import pattern, transpose
from gridchain.plans import cost, ledger, planner
from gridchain.plans.grid import Grid
from gridchain.sources import random_matrices, tables
from gridchain.sources.scratch import stored


def timed(df: DataFrame) -> float:
    began = time.time()
    df.write.format("noop").mode("overwrite").save()
    return time.time() - began


def seconds(make, runs: int = 2) -> float:
    """The least of some runs; make builds the result anew, with whatever jobs that takes."""
    best = float("inf")
    for _ in range(runs):
        began = time.time()
        make().write.format("noop").mode("overwrite").save()
        best = min(best, time.time() - began)
    return round(best, 3)


def breakdown(s: DataFrame, a: DataFrame, b: DataFrame, grid: Grid, elision: str) -> dict[str, float]:
    """Seconds of a chain: dealing the copied operand, dealing what moves, and the rest (kernels and sums)."""
    turned = grid.turned if elision == "reuse" else grid
    copied, moving, cells = (b, a, transpose(s)) if elision == "reuse" else (a, b, s)
    whole = seconds(lambda: chain.chain_left(s, a, b, grid, elision))
    replicate = timed(chain._left(copied, turned)) * (2 if elision == "none" else 1)
    passes = 1 if elision == "fuse" or grid.family == "ds" and elision == "reuse" else 2
    propagate = timed(chain._right(moving, turned)) * passes + (timed(chain._cells(cells, turned)) * passes if grid.family != "ds" else 0)
    return {"whole": whole, "replicate": round(replicate, 3), "propagate": round(propagate, 3), "rest": round(max(whole - replicate - propagate, 0), 3)}


def _operands(s: DataFrame, r: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    s = stored(s, "matrix")
    return s, stored(tables.left_factor(s, r), "left"), stored(tables.right_factor(s, r), "right")


def weak_scaling(spark: SparkSession, sf_dir: str, r: int = 64) -> list[dict]:
    """Both setups: seconds, their parts and words of every variant at its best c up to 8."""
    out = []
    for setup, shape, sizes in ((1, random_matrices.weak_setup1, (1, 2, 4, 8, 16)), (2, random_matrices.weak_setup2, (1, 4, 16))):
        for p in sizes:
            n, d = shape(p)
            s, a, b = _operands(random_matrices.lattice(spark, n, d), r)
            for f, e in cost.VARIANTS:
                c = cost.best_c_admissible(f, e, p, d / r, r, 8)
                if c is not None:
                    words = cost.predict_words(f, e, p, c, d / r, n * r)
                    out.append({"setup": setup, "p": p, "n": n, "per_row": d, "family": f, "elision": e, "c": c, "words": round(words, 1)} | breakdown(s, a, b, Grid(f, p, c, n, n, r), e))
    return out


def best_map(spark: SparkSession, sf_dir: str, p: int = 16, n: int = 512) -> list[dict]:
    """Predicted best variant over r and nonzeros per row, and the one whose counted ring words are least; agreement by cell."""
    out = []
    for r in (8, 32, 128):
        for d in (2, 8, 32):
            s, a, b = _operands(random_matrices.lattice(spark, n, d), r)
            family, elision, c = planner.choose(p, n, r, n * d, 8)
            counted = []
            for f, e in cost.VARIANTS:
                at = cost.best_c_admissible(f, e, p, d / r, r, 8)
                if at is not None:
                    row = ledger.words(ledger.chain_ledger(s, a, b, Grid(f, p, at, n, n, r), e)).first()
                    counted.append((round(row.mean_words, 6), at, f, e))
            best = min(counted)
            out.append({"r": r, "per_row": d, "phi": d / r, "predicted": [family, elision, c], "counted": [best[2], best[3], best[1]], "agree": (family, c) == (best[2], best[1])})
    return out


def best_c(spark: SparkSession, sf_dir: str, r: int = 64) -> list[dict]:
    """Words that the exchanges bring, counted for each c of the dense-moving variants, beside the predicted best c."""
    out = []
    for p in (4, 8, 16):
        n, d = random_matrices.weak_setup1(p, 64)
        s, a, b = _operands(random_matrices.lattice(spark, n, d), r)
        for e in ("reuse", "none", "fuse"):
            words = {c: ledger.words(ledger.chain_ledger(s, a, b, Grid("ds", p, c, n, n, r), e)).first() for c in cost.admissible("ds", p, r, 8)}
            ring, remote = (min(words, key=lambda c, k=k: (round(words[c][k], 6), c)) for k in ("mean_words", "remote_words"))
            out.append({"p": p, "elision": e, "predicted": cost.best_c_admissible("ds", e, p, d / r, r, 8), "counted_ring": ring, "counted_remote": remote})
    return out


def strong_scaling(spark: SparkSession, sf_dir: str, r: int = 128) -> list[dict]:
    """Five chains of each variant at its best c against ten gathers of the baseline, on part x supplier."""
    s, a, b = _operands(tables.part_supplier(spark, sf_dir), r)
    row = s.agg(F.max("i") + 1, F.max("j") + 1, F.count(F.lit(1))).first()
    m, n, nnz = row
    out = []
    for p in (4, 8, 16):
        gathers = 5 * seconds(lambda p=p: baselines.two_gathers(s, b, p, m), 1)
        out.append({"p": p, "variant": "baseline, 10 gathers", "seconds": round(gathers, 2)})
        for f, e in cost.VARIANTS:
            c = cost.best_c_admissible(f, e, p, nnz / (m * r), r, 16)
            if c is not None:
                took = 5 * seconds(lambda f=f, e=e, p=p, c=c: chain.chain_left(s, a, b, Grid(f, p, c, m, n, r), e), 1)
                out.append({"p": p, "variant": f"{f} {e}", "c": c, "seconds": round(took, 2), "times_baseline": round(gathers / took, 2)})
    return out


def applications(spark: SparkSession, sf_dir: str, rank: int = 32) -> list[dict]:
    """Seconds of least squares (10 + 10 steps) and of a two-head attention layer, inside the chain's kernels and outside."""
    out = []
    s, a, b = _operands(tables.customer_part(spark, sf_dir), rank)
    took: dict[str, float] = {}

    def keep(stage: str, df: DataFrame) -> DataFrame:
        began = time.time()
        kept = stored(df, stage)
        took[stage] = took.get(stage, 0) + time.time() - began
        return kept

    for f, e in (("ds", "none"), ("ds", "reuse"), ("ds", "fuse"), ("ss", "reuse"), ("rd", "reuse"), ("rs", "none")):
        took.clear()
        als.sweep(s, a, b, 10, 0.1, chain.choose(s, 8, rank, family=f, elision=e, c=2), timed=keep)
        out.append({"application": "least squares", "family": f, "elision": e, "chain": round(took["chain"], 2), "rest": round(took["state"], 2)})
    graph, x = stored(tables.cosine_graph(spark, sf_dir), "graph"), tables.embeddings(spark, sf_dir)
    n = x.agg(F.max("id") + 1).first()[0]
    heads = gnn.seeded_heads(2, 64, 16, 1, project_first=True)
    for f, e in (("ds", "none"), ("ds", "reuse"), ("ss", "reuse"), ("rd", "reuse"), ("rs", "none")):
        grid = Grid(f, 8, 2, n, n, 16)
        whole = seconds(lambda f=f, e=e, grid=grid: gnn.multi_head_on_grid(graph, x, heads, grid, e), 1)
        rows = gnn.project(x, heads[0][0])
        inside = 2 * seconds(lambda e=e, grid=grid, rows=rows: chain.chain_left(pattern(graph), rows, rows, grid, e), 1)
        out.append({"application": "attention", "family": f, "elision": e, "chain": round(inside, 2), "rest": round(max(whole - inside, 0), 2)})
    return out


EXPERIMENTS = {f.__name__: f for f in (weak_scaling, best_map, best_c, strong_scaling, applications)}


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    names = sys.argv[1:] or list(EXPERIMENTS)
    builder = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g")
    spark = builder.config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    s, a, b = _operands(random_matrices.lattice(spark, 1024, 8), 16)
    for f, e in cost.VARIANTS:  # warm-up
        timed(chain.chain_left(s, a, b, Grid(f, 8, 2, 1024, 1024, 16), e))
    for name in names:
        print(json.dumps({"experiment": name, "rows": EXPERIMENTS[name](spark, sf_dir)}), flush=True)


if __name__ == "__main__":
    main()
