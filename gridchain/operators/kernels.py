"""Masked product and gather as a caller sees them, and the Arrow forms of the local work."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridchain.functions.vectors import dot, scale
from gridchain.operators.matrix import densify as with_zero_rows
from gridchain.operators.matrix import from_long, transpose


def _missing(s: DataFrame, d: DataFrame, key: str, on_missing: str) -> None:
    if on_missing == "error" and not s.select(F.col(key).alias("id")).join(d.select("id"), "id", "left_anti").isEmpty():
        raise ValueError(f"a nonzero's {key} has no dense row")


def masked_product(s: DataFrame, a: DataFrame, b: DataFrame, scaled: bool = True, pair: str | Callable[[Column, Column], Column] = "dot", on_missing: str = "drop") -> DataFrame:
    """s_ij * pair(a_i, b_j) at every entry of s, also where it is 0.

    pair 'concat' takes dense rows of one number each (scores of the two ends) and adds them.
    on_missing: 'error' checks first, 'zero' counts a missing row as zeros, 'drop' leaves the
    entry out.
    """
    _missing(s, a, "i", on_missing)
    _missing(s, b, "j", on_missing)
    how = "left" if on_missing == "zero" else "inner"
    joined = s.join(a.select(F.col("id").alias("i"), F.col("x").alias("ax")), "i", how).join(b.select(F.col("id").alias("j"), F.col("x").alias("bx")), "j", how)
    if pair == "concat":
        value = F.col("ax")[0] + F.col("bx")[0]
    else:
        value = dot("ax", "bx") if pair == "dot" else pair(F.col("ax"), F.col("bx"))
    value = F.coalesce(value, F.lit(0.0)) if on_missing == "zero" else value
    return joined.select("i", "j", (F.col("v") * value if scaled else value).alias("v"))


def summed(weighted: DataFrame, key: str, vector: str = "y", start: Column | None = None) -> DataFrame:
    """Long sums (id, k, x) of weighted vectors by key; start is the first k of a slab."""
    at = F.col("pos").cast("bigint") if start is None else F.col("pos").cast("bigint") + F.col("start")
    kept = [key, vector] + (["start"] if start is not None else [])
    return weighted.select(*kept).select(*[c for c in kept if c != vector], F.posexplode(vector).alias("pos", "value")).groupBy(F.col(key).alias("id"), at.alias("k")).agg(F.sum("value").alias("x"))


def gather_long(s: DataFrame, b: DataFrame) -> DataFrame:
    """s * b in long form. The weight is taken in a projection of its own: in one with the
    generator it would be evaluated again for each component."""
    weighted = s.join(b.select(F.col("id").alias("j"), F.col("x").alias("bx")), "j").select("i", scale("bx", F.col("v")).alias("y"))
    return summed(weighted, "i")


def gather_left(s: DataFrame, b: DataFrame, ids: DataFrame | None = None, r: int | None = None) -> DataFrame:
    """s * b as (id, x); with ids and r, rows without a nonzero are zero rows."""
    out = from_long(gather_long(s, b))
    return with_zero_rows(out, ids, r) if ids is not None else out


def gather_right(s: DataFrame, a: DataFrame, ids: DataFrame | None = None, r: int | None = None) -> DataFrame:
    return gather_left(transpose(s), a, ids, r)


def chain_long(s: DataFrame, a: DataFrame, b: DataFrame) -> DataFrame:
    """Both kernels with one join of b: the row carries b from the dot to the sum."""
    joined = s.join(a.select(F.col("id").alias("i"), F.col("x").alias("ax")), "i").join(b.select(F.col("id").alias("j"), F.col("x").alias("bx")), "j")
    weighted = joined.select("i", (F.col("v") * dot("ax", "bx")).alias("w"), "bx").select("i", scale("bx", F.col("w")).alias("y"))
    return summed(weighted, "i")


def _rows(column: pa.Array) -> np.ndarray:
    return np.asarray(column.flatten(), float).reshape(len(column), -1)


def arrow_masked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """mapInArrow form of the dot: columns i, j, v, ax, bx to i, j, v."""
    for batch in batches:
        if batch.num_rows:
            value = np.einsum("nr,nr->n", _rows(batch.column("ax")), _rows(batch.column("bx"))) * np.asarray(batch.column("v"))
            yield pa.RecordBatch.from_arrays([batch.column("i"), batch.column("j"), pa.array(value)], ["i", "j", "v"])
