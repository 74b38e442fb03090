"""Streams of events as growing sparse matrices; each query drains what is there and returns the table it wrote."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridchain.functions.vectors import dot, scale
from gridchain.operators.kernels import summed
from gridchain.sources.scratch import scratch_path
from gridchain.sources.tables import lattice_value

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
WATERMARK = "40 days"


def add(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def _folder(spark: SparkSession) -> str:
    return scratch_path(spark, "stream")


def source(spark: SparkSession, path: str, files: int | None = None) -> DataFrame:
    """A file stream of events in the types of the stored table."""
    schema = spark.read.parquet(path).schema
    reader = spark.readStream.schema(schema)
    # a pattern, as a stream takes a plain path for a folder
    stream = (reader.option("maxFilesPerTrigger", files) if files else reader).parquet(f"{path[:-1]}[{path[-1]}]")
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run until all input is read; every batch is a folder of its own, so a repeated batch replaces itself."""
    spark, folder = stream.sparkSession, _folder(stream.sparkSession)

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out/batch={number}")

    stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{folder}/state").foreachBatch(keep).start().awaitTermination()
    return spark.read.option("basePath", f"{folder}/out").parquet(f"{folder}/out")


def latest(updates: DataFrame, keys: list[str], value: str) -> DataFrame:
    """The last value of each key over all batches."""
    return updates.groupBy(*keys).agg(F.max_by(value, "batch").alias(value))


_A = "CAST((user_id * 31 + k2 * 17 + 7 * user_id * (k2 + 3) * (k2 + 1) + 7) % 101 - 50 AS DOUBLE) / 64"
_B = "CAST((key * 13 + k2 * 19 + 7 * key * (k2 + 3) * (k2 + 1) + 7) % 101 - 50 AS DOUBLE) / 64"


def _factor(ids: DataFrame, a: int, b: int) -> DataFrame:
    steps = F.sequence(F.lit(0).cast("bigint"), F.lit(7).cast("bigint"))
    return ids.select("id", F.transform(steps, lambda k: lattice_value(F.col("id"), k, a, b)).alias("x"))


def _keys(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Stream of (event_id, i, j, v) with the dense rows of both sides."""
    path = f"{sf_dir}/events.parquet"
    known = spark.read.parquet(path)
    cells = source(spark, path).select("event_id", F.col("user_id").alias("i"), F.get_json_object("props", "$.k").cast("bigint").alias("j"), F.lit(1.0).alias("v")).filter("j is not null")
    left = _factor(known.select(F.col("user_id").alias("id")).distinct(), 31, 17)
    right = _factor(known.select(F.get_json_object("props", "$.k").cast("bigint").alias("id")).filter("id is not null").distinct(), 13, 19)
    return cells, left, right


@add("st_static_join", f"SELECT event_id, sum({_A} * {_B}) AS v FROM (SELECT event_id, user_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS key FROM events), (SELECT unnest(range(8)) AS k2) WHERE key IS NOT NULL GROUP BY event_id")
def _static(spark, sf_dir):
    """Masked product of each arriving nonzero with static operands."""
    cells, left, right = _keys(spark, sf_dir)
    met = cells.join(left.withColumnsRenamed({"id": "i", "x": "ax"}), "i").join(right.withColumnsRenamed({"id": "j", "x": "bx"}), "j")
    return drain(met.select("event_id", (F.col("v") * dot("ax", "bx")).alias("v"))).drop("batch")


@add("st_tumbling", "SELECT date_trunc('day', ts) AS day, event_type, count(*) AS n FROM events GROUP BY ALL")
def _tumbling(spark, sf_dir):
    stream = source(spark, f"{sf_dir}/events.parquet").withWatermark("ts", WATERMARK)
    counts = stream.groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return latest(drain(counts.select(F.col("w.start").alias("day"), "event_type", "n"), "update"), ["day", "event_type"], "n")


@add("st_sliding", "SELECT date_trunc('hour', ts) - to_hours(back) AS start, count(*) AS n FROM events, (SELECT unnest(range(2)) AS back) GROUP BY ALL")
def _sliding(spark, sf_dir):
    stream = source(spark, f"{sf_dir}/events.parquet").withWatermark("ts", WATERMARK)
    counts = stream.groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return latest(drain(counts.select(F.col("w.start").alias("start"), "n"), "update"), ["start"], "n")


@add("st_session", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, session")
def _session(spark, sf_dir):
    stream = source(spark, f"{sf_dir}/events.parquet").withWatermark("ts", WATERMARK)
    counts = stream.groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    out = drain(counts.select("user_id", F.col("w.start").alias("start"), "n"), "complete")
    return out.filter(F.col("batch") == out.agg(F.max("batch")).first()[0]).drop("batch")


@add("st_dedup", "SELECT event_id, user_id FROM events")
def _dedup(spark, sf_dir):
    """Every event arrives twice; the second is dropped within the watermark."""
    stream = source(spark, f"{sf_dir}/events.parquet")
    twice = stream.withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).withWatermark("ts", WATERMARK)
    return drain(twice.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id")).drop("batch")


@add("st_late_rows", "SELECT count(*) FILTER (ts >= TIMESTAMP '2024-01-20') AS kept, count(*) FILTER (ts < TIMESTAMP '2024-01-20') AS late FROM events")
def _late(spark, sf_dir):
    """The newer part arrives first; a day's watermark then drops the older part, which the batch twin counts.

    Rows are held against the watermark that the batch before used, so the newer part comes in two files.
    """
    folder, known = _folder(spark), spark.read.parquet(f"{sf_dir}/events.parquet")
    cut = F.col("ts") >= F.lit("2024-01-20").cast("timestamp")
    odd = F.pmod("event_id", F.lit(2)) == 1
    for k, part in enumerate((cut & odd, cut & ~odd, ~cut)):
        known.filter(part).coalesce(1).write.parquet(f"{folder}/in/part={k}")
    schema = known.schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in/part=*").withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 day")
    counts = stream.groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    kept = latest(drain(counts.select(F.col("w.start").alias("day"), "n"), "update"), ["day"], "n").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("kept"))
    return known.agg(F.count(F.lit(1)).alias("every")).crossJoin(kept).select("kept", (F.col("every") - F.col("kept")).alias("late"))


@add("st_interval_join", "SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts >= c.ts AND p.ts < c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def _interval(spark, sf_dir):
    path = f"{sf_dir}/events.parquet"
    clicks = source(spark, path).filter("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("clicker"), F.col("ts").alias("clicked")).withWatermark("clicked", WATERMARK)
    bought = source(spark, path).filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", "ts").withWatermark("ts", WATERMARK)
    met = clicks.join(bought, F.expr("user_id = clicker AND ts >= clicked AND ts < clicked + INTERVAL 1 HOUR"))
    return drain(met.select("click_id", "purchase_id")).drop("batch")


@add("st_running_gather", f"SELECT user_id AS id, k2 AS k, sum({_B}) AS x FROM (SELECT user_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS key FROM events), (SELECT unnest(range(8)) AS k2) WHERE key IS NOT NULL GROUP BY ALL")
def _running(spark, sf_dir):
    """Row sums of the gather: each batch leaves its partial sums, a reader adds them up."""
    cells, _, right = _keys(spark, sf_dir)
    folder = _folder(spark)

    def keep(batch: DataFrame, number: int) -> None:
        weighted = batch.join(right.withColumnsRenamed({"id": "j", "x": "bx"}), "j").select("i", scale("bx", F.col("v")).alias("y"))
        summed(weighted, "i").write.mode("overwrite").parquet(f"{folder}/out/batch={number}")

    cells.writeStream.trigger(availableNow=True).option("checkpointLocation", f"{folder}/state").foreachBatch(keep).start().awaitTermination()
    parts = spark.read.option("basePath", f"{folder}/out").parquet(f"{folder}/out")
    return parts.groupBy("id", "k").agg(F.sum("x").alias("x"))
