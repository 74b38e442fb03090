"""Matrices from the given tables, dense lattice factors, and readers and writers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gridchain.operators.blocks import NearGraph
from gridchain.operators.matrix import as_dense, as_sparse
from gridchain.plans.grid import Grid, place_sparse
from gridchain.sources.scratch import stored


def table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def part_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return as_sparse(table(spark, sf_dir, "lineitem"), "l_partkey", "l_suppkey", "l_quantity")


def order_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return as_sparse(table(spark, sf_dir, "lineitem"), "l_orderkey", "l_partkey", "l_quantity")


def customer_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_quantity"])
    orders = table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"])
    return as_sparse(lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")), "o_custkey", "l_partkey", "l_quantity")


def user_key(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = table(spark, sf_dir, "events", ["user_id", "props"]).withColumn("k", F.get_json_object("props", "$.k"))
    return as_sparse(events.filter("k is not null"), "user_id", "k", F.lit(1.0))


def numbered(df: DataFrame, *order) -> DataFrame:
    """df with `number`: 0, 1, ... in the given order of all rows, without a window over them in one task.

    Rows are dealt in ranges and numbered within; each range adds the rows before it (one number for each range).
    """
    ranged = stored(df.repartitionByRange(*order).withColumn("part", F.spark_partition_id()), "numbered")
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = ranged.groupBy("part").agg(F.count(F.lit(1)).alias("rows")).select("part", F.coalesce(F.sum("rows").over(before), F.lit(0)).alias("offset"))
    inside = F.row_number().over(Window.partitionBy("part").orderBy(*order)) - 1
    return ranged.withColumn("inside", inside).join(offsets, "part").withColumn("number", (F.col("inside") + F.col("offset")).cast("bigint")).drop("part", "inside", "offset")


def user_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = table(spark, sf_dir, "events", ["user_id", "event_type"])
    names = numbered(events.select("event_type").distinct(), "event_type").withColumnRenamed("number", "j")
    return as_sparse(events.join(names, "event_type"), "user_id", "j", F.lit(1.0))


def words(documents: DataFrame) -> DataFrame:
    """doc_id, word of every token: lower case, cut at anything but a-z."""
    return documents.select("doc_id", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("word")).filter("word <> ''")


def doc_word(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Document by word counts; word ids by falling count, then word."""
    cells = words(table(spark, sf_dir, "documents", ["doc_id", "text"])).groupBy("doc_id", "word").agg(F.count(F.lit(1)).alias("v"))
    totals = cells.groupBy("word").agg(F.sum("v").alias("total"))
    ids = numbered(totals, F.desc("total"), "word").select("word", F.col("number").alias("j"))
    return as_sparse(cells.join(ids, "word"), "doc_id", "j", "v")


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page_id, target, count of links."""
    found = F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))
    return table(spark, sf_dir, "pages", ["page_id", "html"]).select("page_id", found.alias("target")).groupBy("page_id", "target").agg(F.count(F.lit(1)).cast("double").alias("v"))


def page_link(spark: SparkSession, sf_dir: str) -> DataFrame:
    links = page_links(spark, sf_dir)
    ids = numbered(links.select("target").distinct(), "target").withColumnRenamed("number", "j")
    return as_sparse(links.join(ids, "target"), "page_id", "j", "v")


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return as_dense(table(spark, sf_dir, "embeddings", ["vec_id", "embedding"]), "vec_id", "embedding")


def cosine_graph(spark: SparkSession, sf_dir: str, least: float = 0.2, block: int = 512) -> DataFrame:
    """Directed edges between unit vectors of cosine above `least`, v = 1.

    Blocks of rows meet pairwise: each task multiplies two blocks of a bounded size.
    """
    from gridchain.operators.baselines import block_products

    return block_products(embeddings(spark, sf_dir), least, block).select("i", "j", F.lit(1.0).alias("v"))


def near_graph(spark: SparkSession, sf_dir: str, least: float = 0.2) -> NearGraph:
    """The same edges, made where they are used."""
    return NearGraph(embeddings(spark, sf_dir), least)


def lattice_value(id_value: Column, k: Column, a: int, b: int, modulus: int = 101) -> Column:
    """Dyadic values: sums of their products with integers are exact in any order."""
    if modulus == 11:
        return (F.pmod(id_value * a + k * b + 7, F.lit(11)) - 5) / F.lit(8.0)
    return (F.pmod(id_value * a + k * b + 7 * id_value * (k + 3) * (k + 1) + 7, F.lit(101)) - 50) / F.lit(64.0)


def dense_lattice(ids: DataFrame, r: int, a: int, b: int, modulus: int = 101) -> DataFrame:
    x = F.transform(F.sequence(F.lit(0).cast("bigint"), F.lit(r - 1).cast("bigint")), lambda k: lattice_value(F.col("id"), k, a, b, modulus))
    return ids.select("id", x.alias("x"))


def left_factor(s: DataFrame, r: int = 8, modulus: int = 101) -> DataFrame:
    return dense_lattice(s.select(F.col("i").alias("id")).distinct(), r, 31, 17, modulus)


def right_factor(s: DataFrame, r: int = 8, modulus: int = 101) -> DataFrame:
    return dense_lattice(s.select(F.col("j").alias("id")).distinct(), r, 13, 19, modulus)


def read(spark: SparkSession, path: str, form: str = "parquet", schema: str = "i bigint, j bigint, v double") -> DataFrame:
    """A matrix written in any of Spark's file formats, with its declared types."""
    reader = spark.read.schema(schema)
    return reader.option("header", True).csv(path) if form == "csv" else reader.format(form).load(path)


def write(s: DataFrame, path: str, form: str = "parquet") -> None:
    (s.write.option("header", True) if form == "csv" else s.write).format(form).save(path)


def write_placed(s: DataFrame, grid: Grid, path: str) -> None:
    """A placed pattern, partitioned by station, so that later calls read only what they need."""
    place_sparse(s, grid).write.partitionBy("station").parquet(path)


def read_coordinate_text(spark: SparkSession, path: str) -> DataFrame:
    """The public 1-based coordinate text format: comments, a size line, then `row column [value]`.

    The size line is the first that is no comment in the file that holds the header; other
    files of a folder go on with entries.
    """
    lines = spark.read.text(path).select("value", F.col("_metadata.file_path").alias("file"), F.struct(F.col("_metadata.file_block_start").alias("block"), F.monotonically_increasing_id().alias("at")).alias("place"))
    comment = F.col("value").startswith("%")
    body = lines.filter(~comment & (F.trim("value") != ""))
    head = lines.filter(comment).agg(F.min("file").alias("file"))
    size = body.join(F.broadcast(head), "file").agg(F.min("place").alias("place"))  # one row each
    parts = F.split(F.trim("value"), "\\s+")
    rest = body.join(F.broadcast(size), "place", "left_anti")
    return rest.select((parts[0].cast("bigint") - 1).alias("i"), (parts[1].cast("bigint") - 1).alias("j"), F.coalesce(F.try_element_at(parts, F.lit(3)).cast("double"), F.lit(1.0)).alias("v"))


def write_coordinate_text(s: DataFrame, path: str, m: int, n: int) -> None:
    count = s.count()
    head = s.sparkSession.createDataFrame([("%%MatrixMarket matrix coordinate real general",), (f"{m} {n} {count}",)], "value string").coalesce(1)
    head.unionAll(s.select(F.concat_ws(" ", F.col("i") + 1, F.col("j") + 1, F.col("v")).alias("value"))).write.text(path)
