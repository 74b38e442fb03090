"""Random and lattice sparse matrices with a fixed number of nonzeros in each row, and permutations."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def bernoulli(spark: SparkSession, n: int, d: int, seed: int = 1) -> DataFrame:
    """About d uniform columns in each row; repeated columns are merged, so nnz is slightly below n*d."""
    return bernoulli_rows(spark.range(n), n, d, seed)


def bernoulli_rows(ids: DataFrame, n: int, d: int, seed: int = 1) -> DataFrame:
    """The same for given rows (id) and n columns."""
    cells = ids.select(F.col("id").alias("i"), F.explode(F.sequence(F.lit(0), F.lit(d - 1))).alias("t"))
    return cells.select("i", F.pmod(F.xxhash64("i", "t", F.lit(seed)), F.lit(n)).alias("j")).distinct().withColumn("v", F.lit(1.0))


def lattice(spark: SparkSession, n: int, d: int, seed: int = 1) -> DataFrame:
    """Exactly d distinct columns in each row of a side that is a power of two: an odd stride from a scattered start."""
    if n & (n - 1) or d > n:
        raise ValueError("the side must be a power of two and hold d columns")
    cells = spark.range(n).select(F.col("id").alias("i"), F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(d - 1).cast("bigint"))).alias("t"))
    start, stride = F.col("i") * 40503 + seed * 7919, F.lit(2) * F.pmod(F.col("i") * 31 + 5, F.lit(n)) + 1
    return cells.select("i", F.pmod(start + F.col("t") * stride, F.lit(n)).alias("j"), (F.pmod(F.col("i") + F.col("t"), F.lit(7)) + 1).cast("double").alias("v"))


def weak_setup1(p: int, side: int = 1 << 8, per_row: int = 8) -> tuple[int, int]:
    """(side, nonzeros in a row): both operands grow with p, phi stays."""
    return side * p, per_row


def weak_setup2(p: int, side: int = 1 << 8, per_row: int = 8) -> tuple[int, int]:
    """Side and row length grow with the root of p, phi doubles as p quadruples."""
    root = math.isqrt(p)
    if root * root != p:
        raise ValueError("this setup needs a square number of stations")
    return side * root, per_row * root


def affine(s: DataFrame, m: int, n: int, a: int = 30011, b: int = 7) -> DataFrame:
    """Rows and columns renamed by id -> (a id + b) mod size; a must share no factor with either size."""
    if math.gcd(a, m) > 1 or math.gcd(a, n) > 1:
        raise ValueError(f"{a} isn't coprime with {m} and {n}")
    return s.select(F.pmod(F.col("i") * a + b, F.lit(m)).alias("i"), F.pmod(F.col("j") * a + b, F.lit(n)).alias("j"), "v")


def inverse_affine(d: DataFrame, size: int, a: int = 30011, b: int = 7, key: str = "id") -> DataFrame:
    return d.withColumn(key, F.pmod((F.col(key) - b) * pow(a, -1, size), F.lit(size)))


def permuted_ids(d: DataFrame, size: int, a: int = 30011, b: int = 7, key: str = "id") -> DataFrame:
    return d.withColumn(key, F.pmod(F.col(key) * a + b, F.lit(size)))


def hashed(s: DataFrame, seed: int = 1) -> DataFrame:
    """Rows and columns renamed by a 64-bit hash: no map is stored at any size."""
    return s.select(F.xxhash64("i", F.lit(seed)).alias("i"), F.xxhash64("j", F.lit(seed + 1)).alias("j"), "v")
