"""What the grid algorithms are compared with."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridchain.functions.vectors import dot, scale
from gridchain.operators.kernels import gather_long, summed
from gridchain.operators.station import PARTIAL, RIGHT, at_stations, cell_rows, deal, dense_rows, gather_kernel, reduced
from gridchain.plans.grid import Grid, block, place_sparse
from gridchain.sources.scratch import stored

#: Largest full product that the strawman may form.
DENSE_LIMIT = 5_000_000


def dense_then_mask(s: DataFrame, a: DataFrame, b: DataFrame, limit: int = DENSE_LIMIT) -> DataFrame:
    """All m*n dots, then the mask: wasteful, refused above a size, kept as a brute-force oracle."""
    if (cells := a.count() * b.count()) > limit:
        raise ValueError(f"{cells} dots are more than {limit}")
    full = a.select(F.col("id").alias("i"), F.col("x").alias("ax")).crossJoin(b.select(F.col("id").alias("j"), F.col("x").alias("bx"))).select("i", "j", dot("ax", "bx").alias("full"))
    return s.join(full, ["i", "j"]).select("i", "j", (F.col("v") * F.col("full")).alias("v"))


def dense_in_blocks(s: DataFrame, a: DataFrame, b: DataFrame, size: int = 512) -> DataFrame:
    """All m*n dots, then the mask, in blocks of about size by size dots: a task holds one block, whatever m and n."""
    high, wide = (max(-(-d.count() // size), 1) for d in (a, b))
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    part = lambda c, n: F.pmod(F.col(c), F.lit(n)).cast("int")
    nothing = F.lit(None)
    left = a.select(part("id", high).alias("rows"), every(wide).alias("columns"), F.lit(0).alias("side"), F.col("id").alias("i"), nothing.cast("bigint").alias("j"), nothing.cast("double").alias("v"), F.col("x").cast("array<double>").alias("x"))
    right = b.select(every(high).alias("rows"), part("id", wide).alias("columns"), F.lit(1).alias("side"), nothing.cast("bigint").alias("i"), F.col("id").alias("j"), nothing.cast("double").alias("v"), F.col("x").cast("array<double>").alias("x"))
    mask = s.select(part("i", high).alias("rows"), part("j", wide).alias("columns"), F.lit(2).alias("side"), "i", "j", F.col("v").cast("double").alias("v"), nothing.cast("array<double>").alias("x"))

    def product(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        a_rows, b_rows, cells = (table.filter(pa.array(np.asarray(table.column("side")) == k)) for k in range(3))
        if not (a_rows.num_rows and b_rows.num_rows and cells.num_rows):
            return pa.table({"i": pa.array([], pa.int64()), "j": pa.array([], pa.int64()), "v": pa.array([], pa.float64())})
        x, y = (np.asarray(t.column("x").combine_chunks().flatten(), float).reshape(t.num_rows, -1) for t in (a_rows, b_rows))
        full = x @ y.T
        i, j = np.asarray(cells.column("i")), np.asarray(cells.column("j"))
        ids, others = np.asarray(a_rows.column("i")), np.asarray(b_rows.column("j"))
        up, along = np.argsort(ids), np.argsort(others)
        p, q = (np.minimum(np.searchsorted(k, w, sorter=o), len(k) - 1) for k, w, o in ((ids, i, up), (others, j, along)))
        p, q = up[p], along[q]
        there = (ids[p] == i) & (others[q] == j)
        v = np.asarray(cells.column("v")) * full[p, q]
        return pa.table({"i": i[there], "j": j[there], "v": v[there]})

    return left.unionByName(right).unionByName(mask).groupBy("rows", "columns").applyInArrow(product, "i bigint, j bigint, v double")


def one_d_gather(s: DataFrame, b: DataFrame, p: int, m: int) -> DataFrame:
    """Block rows without replication: b is delivered to each of the p row blocks, and a block's rows are summed there."""
    cells = deal(cell_rows(s.withColumn("station", block("i", p, m))), p)
    every = b.select(F.explode(F.sequence(F.lit(0), F.lit(p - 1))).alias("station"), F.lit(0).cast("bigint").alias("start"), F.col("id").alias("j"), F.col("x").alias("bx"))
    return reduced(at_stations([deal(dense_rows(every, RIGHT, "j", "bx"), p), cells], gather_kernel(RIGHT), PARTIAL), True)


def two_gathers(s: DataFrame, b: DataFrame, p: int, m: int) -> DataFrame:
    """A library without the masked kernel runs two gathers in place of a chain, each with its own communication: two stored jobs, summed here."""
    first, second = (stored(one_d_gather(s, b, p, m), "gather") for _ in range(2))
    return first.unionAll(second).groupBy("id", "k").agg(F.sum("x").alias("x"))


def fetch_rows(s: DataFrame, b: DataFrame, p: int, m: int) -> DataFrame:
    """Sparsity-aware gather: each block of rows fetches only the dense rows that it needs."""
    placed = s.withColumn("station", block("i", p, m))
    wanted = placed.select("station", "j").distinct()
    fetched = wanted.join(b.select(F.col("id").alias("j"), F.col("x").alias("bx")), "j")
    return summed(placed.join(fetched, ["station", "j"]).select("i", scale("bx", F.col("v")).alias("y")), "i")


def unoptimised_chain(s: DataFrame, a: DataFrame, b: DataFrame, masked: DataFrame) -> DataFrame:
    """Second kernel, as a job of its own, over the stored masked product."""
    return gather_long(stored(masked, "masked"), b)


def sparse_replicate_15_words(p: int, c: float, phi: float) -> float:
    """Words of a station, in units of n*r, in a prior 1.5D scheme that copies the sparse operand c times and shifts it.

    A model only: c copies are gathered on the fiber, p/c^2 shifts bring every block by, the
    dense output is summed over the fiber. It was made for square operands, where a dense copy costs more.
    """
    return 3 * phi * (c - 1) / p + 6 * phi / c + 2 * (c - 1) / p


def remote_rows(s: DataFrame, grid: Grid) -> DataFrame:
    """Dense rows that stations fetch from others: distinct (station, column) pairs less one owner each."""
    pairs = place_sparse(s, grid).select("station", "j").distinct()
    return pairs.agg(F.count(F.lit(1)).alias("fetched"), F.count_distinct("j").alias("columns")).select("fetched", "columns", (F.col("fetched") - F.col("columns")).alias("remote"))


def block_products(d: DataFrame, least: float, size: int = 512) -> DataFrame:
    """(i, j, s) of row pairs, i <> j, whose dot is above `least`; blocks of rows meet pairwise in tasks."""
    blocks = -(-d.count() // size)
    dealt = d.withColumn("block", F.pmod(F.col("id"), F.lit(max(blocks, 1))).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.lit(max(blocks, 1) - 1)))
    left = dealt.select("id", "x", F.col("block").alias("rows"), every.alias("columns"), F.lit(0).alias("side"))
    right = dealt.select("id", "x", every.alias("rows"), F.col("block").alias("columns"), F.lit(1).alias("side"))

    def product(table: pa.Table) -> pa.Table:
        side = np.asarray(table.column("side"))
        ids = np.asarray(table.column("id"))
        x = np.asarray(table.column("x").combine_chunks().flatten(), float).reshape(len(ids), -1)
        a, b = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        s = x[a] @ x[b].T
        p, q = np.nonzero(s > least)
        keep = ids[a[p]] != ids[b[q]]
        p, q = p[keep], q[keep]
        return pa.table({"i": ids[a[p]], "j": ids[b[q]], "s": s[p, q]})

    return left.union(right).groupBy("rows", "columns").applyInArrow(product, "i bigint, j bigint, s double")
