"""Sparse (i, j, v) and dense (id, x) matrices as DataFrames: forms, checks and statistics."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SPARSE = "i bigint, j bigint, v double"
DENSE = "id bigint, x array<double>"


@dataclass(frozen=True)
class MatrixStats:
    """Shape and fill of a sparse matrix; phi compares it with a dense operand of r columns."""

    m: int
    n: int
    nnz: int
    r: int

    @property
    def phi_a(self) -> float:
        return self.nnz / (self.m * self.r)

    @property
    def phi_b(self) -> float:
        return self.nnz / (self.n * self.r)

    @property
    def percent(self) -> float:
        return 100.0 * self.nnz / (self.m * self.n)


def as_sparse(df: DataFrame, i: str = "i", j: str = "j", v: str | Column = "v") -> DataFrame:
    """Declared types; repeated (i, j) are summed."""
    value = F.col(v) if isinstance(v, str) else v
    return coalesce_duplicates(df.select(F.col(i).cast("bigint").alias("i"), F.col(j).cast("bigint").alias("j"), value.cast("double").alias("v")))


def coalesce_duplicates(s: DataFrame) -> DataFrame:
    return s.groupBy("i", "j").agg(F.sum("v").alias("v"))


def as_dense(df: DataFrame, id_name: str = "id", x: str = "x") -> DataFrame:
    return df.select(F.col(id_name).cast("bigint").alias("id"), F.col(x).cast("array<double>").alias("x"))


def pattern(s: DataFrame) -> DataFrame:
    return s.select("i", "j", F.lit(1.0).alias("v"))


def transpose(s: DataFrame) -> DataFrame:
    """Second copy keyed by column; the exchange comes with whatever places it."""
    return s.select(F.col("j").alias("i"), F.col("i").alias("j"), "v")


def stats(s: DataFrame, r: int, m: int | None = None, n: int | None = None) -> MatrixStats:
    """One aggregate; four numbers reach the driver. Shapes are taken from ids where not given."""
    row = s.agg(F.max("i"), F.max("j"), F.count(F.lit(1))).first()
    return MatrixStats(m or (row[0] or 0) + 1, n or (row[1] or 0) + 1, row[2], r)


def validate_sparse(s: DataFrame) -> DataFrame:
    """Raises at run time on a null id or value; NaN and infinities pass."""
    broken = F.col("i").isNull() | F.col("j").isNull() | F.col("v").isNull()
    return s.withColumn("i", F.when(broken, F.raise_error(F.lit("sparse matrix holds a null")).cast("bigint")).otherwise(F.col("i")))


def validate_dense(d: DataFrame, r: int) -> DataFrame:
    broken = F.col("id").isNull() | F.col("x").isNull() | (F.size("x") != r)
    return d.withColumn("id", F.when(broken, F.raise_error(F.lit(f"dense matrix needs {r} values in every row")).cast("bigint")).otherwise(F.col("id")))


def to_long(d: DataFrame) -> DataFrame:
    return d.select(F.col("id"), F.posexplode("x").alias("k", "x")).select("id", F.col("k").cast("bigint").alias("k"), "x")


def from_long(d: DataFrame) -> DataFrame:
    """(id, x) from (id, k, x), values in the order of k."""
    packed = d.groupBy("id").agg(F.sort_array(F.collect_list(F.struct("k", "x"))).alias("cells"))
    return packed.select("id", F.transform("cells", lambda c: c["x"]).alias("x"))


def densify(d: DataFrame, ids: DataFrame, r: int) -> DataFrame:
    """A zero row for every id without one."""
    return ids.select("id").join(d, "id", "left").select("id", F.coalesce("x", F.array_repeat(F.lit(0.0), r)).alias("x"))


def submatrix(s: DataFrame, rows: tuple[int, int], columns: tuple[int, int]) -> DataFrame:
    return s.filter(F.col("i").between(*rows) & F.col("j").between(*columns))


def threshold(s: DataFrame, least: float) -> DataFrame:
    return s.filter(F.col("v") >= least)


def to_row_map(s: DataFrame) -> DataFrame:
    return s.groupBy("i").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("j", "v")))).alias("row"))


def from_row_map(d: DataFrame) -> DataFrame:
    return d.select("i", F.explode("row").alias("j", "v"))


def max_error(got: DataFrame, want: DataFrame) -> DataFrame:
    """One row: largest absolute and relative difference of two long matrices (id, k, x), and cells that only one has."""
    both = got.select("id", "k", F.col("x").alias("p")).join(want.select("id", "k", F.col("x").alias("q")), ["id", "k"], "full")
    away = F.abs(F.col("p") - F.col("q"))
    return both.agg(F.max(away).alias("largest"), F.max(F.when(away > 0, away / F.greatest(F.abs("p"), F.abs("q"))).otherwise(0.0)).alias("relative"), F.count_if(F.col("p").isNull() | F.col("q").isNull()).alias("missing"))
