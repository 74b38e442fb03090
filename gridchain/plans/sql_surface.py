"""The kernels for SQL users: temporary views sparse_s, dense_a, dense_b and statements over them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def register(spark: SparkSession, s: DataFrame, a: DataFrame, b: DataFrame) -> None:
    for name, df in (("sparse_s", s), ("dense_a", a), ("dense_b", b)):
        df.createOrReplaceTempView(name)


def masked_text() -> str:
    return """SELECT s.i, s.j, s.v * aggregate(zip_with(a.x, b.x, (p, q) -> p * q), 0D, (t, x) -> t + x) AS v
    FROM sparse_s s JOIN dense_a a ON a.id = s.i JOIN dense_b b ON b.id = s.j"""


def gather_text(source: str = "sparse_s", dense: str = "dense_b") -> str:
    return f"""SELECT i AS id, CAST(pos AS BIGINT) AS k, sum(y) AS x
    FROM (SELECT s.i, transform(d.x, t -> t * s.v) AS row FROM {source} s JOIN {dense} d ON d.id = s.j) LATERAL VIEW posexplode(row) AS pos, y
    GROUP BY i, pos"""


def chain_text() -> str:
    return f"WITH masked AS ({masked_text()}) {gather_text('masked')}"
