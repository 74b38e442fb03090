"""Alternating least squares by batched conjugate gradients over chains.

The query products of all rows at once are one chain over the rating pattern. Plain joins run
it where no grid is given; on a grid the pattern and the fixed factor are dealt to their
stations once for a whole half-sweep, and only the directions and the results move.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridchain.functions.vectors import axpy, dot, scale, vec_add, vec_sub
from gridchain.operators.chain import Choice, PlacedChain, choose
from gridchain.operators.kernels import chain_long, gather_left, masked_product
from gridchain.operators.matrix import from_long, pattern, transpose
from gridchain.plans.grid import Grid
from gridchain.sources.scratch import stored

#: Relative residual below which a row stops.
SMALL = 1e-10


def loss(c: DataFrame, a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: Frobenius norm of c - dots at the entries of c."""
    dots = masked_product(c, a, b, scaled=False).withColumnRenamed("v", "dot")
    return c.join(dots, ["i", "j"]).agg(F.sqrt(F.sum((F.col("v") - F.col("dot")) * (F.col("v") - F.col("dot")))).alias("loss"))


def _with_ridge(x: DataFrame, chained: DataFrame, ridge: float) -> DataFrame:
    joined = x.join(from_long(chained).withColumnRenamed("x", "y"), "id", "left")
    return joined.select("id", vec_add(F.coalesce("y", scale("x", F.lit(0.0))), scale("x", F.lit(ridge))).alias("x"))


def batched_matvec(s: DataFrame, x: DataFrame, b: DataFrame, ridge: float = 0.0, on: Choice | None = None) -> DataFrame:
    """(sum of b_j b_j' over a row's entries + ridge) x_i for every row at once: one chain over the pattern."""
    if on is None or on.grid is None:
        return _with_ridge(x, chain_long(pattern(s), x, b), ridge)
    return _with_ridge(x, PlacedChain(pattern(s), b, on.grid, on.elision, keep=False)(x), ridge)


def rhs(c: DataFrame, b: DataFrame) -> DataFrame:
    return gather_left(c, b)


def row_dots(x: DataFrame, y: DataFrame, grid: Grid) -> DataFrame:
    """(id, dot) of two dense matrices that lie in slabs: parts of a row are summed over the stations that hold them."""
    from gridchain.plans.grid import _slabbed

    parts = _slabbed(x, grid).join(_slabbed(y, grid).select("id", "slab", F.col("x").alias("y")), ["id", "slab"])
    return parts.select("id", dot("x", "y").alias("part")).groupBy("id").agg(F.sum("part").alias("dot"))


def cg(s: DataFrame, right: DataFrame, x0: DataFrame, b: DataFrame, iters: int = 10, ridge: float = 0.0, keep_every: int = 1, on: Choice | None = None, timed: Callable | None = None) -> DataFrame:
    """Conjugate gradients of all row systems at once; returns (id, x).

    With a choice of grid and elision (chain.choose) every product runs on its stations.
    timed(stage, DataFrame) may store the chain's and the rest's results by itself, to tell
    their times apart. A row stops once its residual is at most SMALL of its right-hand side or its direction
    has no curvature left; more steps than the dimension would only add up round-off.
    """
    # the placed pattern and the fixed factor serve every step
    s, b = stored(pattern(s), "pattern"), stored(b, "factor")
    keep = timed or (lambda stage, df: stored(df, stage))
    placed = PlacedChain(s, b, on.grid, on.elision) if on is not None and on.grid is not None else None

    def product(x: DataFrame) -> DataFrame:
        chained = placed(x) if placed else chain_long(s, x, b)
        if timed:
            chained = timed("chain", chained)
        return _with_ridge(x, chained, ridge)

    start = right.withColumnRenamed("x", "right").join(x0, "id").join(product(x0).withColumnRenamed("x", "q"), "id")
    state = start.select("id", "x", vec_sub("right", "q").alias("res"), dot("right", "right").alias("size"))
    state = state.withColumn("rs", dot("res", "res"))
    live = F.col("rs") > F.lit(SMALL * SMALL) * F.col("size")
    state = keep("state", state.withColumn("dir", F.when(live, F.col("res")).otherwise(scale("res", F.lit(0.0)))))
    for step in range(iters):
        q = product(state.select("id", F.col("dir").alias("x"))).withColumnRenamed("x", "q")
        joined = state.join(q, "id").withColumn("curve", dot("dir", "q"))
        moves = (F.col("curve") > 0) & live
        joined = joined.withColumn("alpha", F.when(moves, F.col("rs") / F.col("curve")).otherwise(F.lit(0.0)))
        moved = joined.select("id", "size", "rs", "dir", "alpha", axpy(F.col("alpha"), "dir", "x").alias("x"), axpy(-F.col("alpha"), "q", "res").alias("res"))
        moved = moved.withColumn("next", dot("res", "res"))
        goes = (F.col("alpha") > 0) & (F.col("next") > F.lit(SMALL * SMALL) * F.col("size"))
        beta = F.when(goes, F.col("next") / F.col("rs")).otherwise(F.lit(0.0))
        moved = moved.withColumn("beta", beta).withColumn("goes", goes)
        state = moved.select("id", "x", "res", "size", F.col("next").alias("rs"), F.when(F.col("goes"), axpy(F.col("beta"), "dir", "res")).otherwise(scale("dir", F.lit(0.0))).alias("dir"))
        if (step + 1) % keep_every == 0 or step + 1 == iters:
            state = keep("state", state)
    if placed:
        placed.release()
    return state.select("id", "x")


def turned(on: Choice | None) -> Choice | None:
    return on if on is None or on.grid is None else Choice(on.grid.turned, on.elision)


def sweep(c: DataFrame, a: DataFrame, b: DataFrame, cg_iters: int = 10, ridge: float = 0.1, on: Choice | None = None, timed: Callable | None = None) -> tuple[DataFrame, DataFrame]:
    """Solve for a with b fixed, then for b with a fixed through the transposed copy: 2 * (cg_iters + 1) chains."""
    a = cg(c, rhs(c, b), a, b, cg_iters, ridge, on=on, timed=timed)
    other = transpose(c)
    return a, cg(other, rhs(other, a), b, a, cg_iters, ridge, on=turned(on), timed=timed)


def fit(c: DataFrame, a: DataFrame, b: DataFrame, sweeps: int = 3, cg_iters: int = 10, ridge: float = 0.1, p: int | None = None, r: int | None = None, **wanted) -> tuple[DataFrame, DataFrame]:
    """Sweeps on the planner's grid of p stations for rank r (wanted as in chain.choose), or on plain joins without p."""
    on = choose(c, p, r, **wanted) if p else None
    for _ in range(sweeps):
        a, b = sweep(c, a, b, cg_iters, ridge, on)
    return a, b
