"""One query for each relational operator around the kernels, with its SQL."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gridchain.functions import vectors
from gridchain.operators import kernels
from gridchain.operators.baselines import block_products
from gridchain.operators.matrix import from_row_map, submatrix, threshold, to_row_map
from gridchain.operators.station import LEFT, PARTIAL, RIGHT, at_stations, cell_rows, chain_kernel, deal, dense_rows, reduced
from gridchain.plans.grid import Grid, block, place_left, place_right, place_sparse
from gridchain.sources import tables
from gridchain.sources.scratch import stored

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
PS = "SELECT l_partkey AS i, l_suppkey AS j, sum(l_quantity) AS v FROM lineitem GROUP BY ALL"
CUT = "1996-01-01"
#: Largest side that is broadcast, in rows.
BROADCAST_ROWS = 100_000


def add(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return keep


def ps(spark, sf_dir) -> DataFrame:
    return tables.part_supplier(spark, sf_dir)


def lines(spark, sf_dir, *columns) -> DataFrame:
    return tables.table(spark, sf_dir, "lineitem", list(columns))


def events(spark, sf_dir, *columns) -> DataFrame:
    return tables.table(spark, sf_dir, "events", list(columns))


# ---- scans and filters ----

add("op_scan_prune", "SELECT l_partkey, l_quantity FROM lineitem WHERE l_quantity > 45")(lambda s, d: lines(s, d, "l_partkey", "l_quantity").filter("l_quantity > 45"))
add("op_filter_submatrix", f"SELECT * FROM ({PS}) WHERE i BETWEEN 10 AND 60 AND j BETWEEN 2 AND 7")(lambda s, d: submatrix(ps(s, d), (10, 60), (2, 7)))
add("op_filter_null_in_like", "SELECT p_partkey, p_brand, p_type FROM part WHERE p_brand IS NOT NULL AND p_size IN (1, 5, 9, 14) AND p_type LIKE '%E%'")(lambda s, d: tables.table(s, d, "part").filter(F.col("p_brand").isNotNull() & F.col("p_size").isin(1, 5, 9, 14) & F.col("p_type").like("%E%")).select("p_partkey", "p_brand", "p_type"))
add("op_threshold", f"SELECT * FROM ({PS}) WHERE v >= 60")(lambda s, d: threshold(ps(s, d), 60.0))

# ---- joins ----

_SUPPLIER = "SELECT i, j, v, s_nationkey FROM ({ps}) JOIN supplier ON s_suppkey = j".format(ps=PS)


def _suppliers(s, d) -> DataFrame:
    return tables.table(s, d, "supplier", ["s_suppkey", "s_nationkey"])


def _joined(hint: str | None):
    def run(s, d):
        side = _suppliers(s, d)
        if hint == "broadcast":
            if side.limit(BROADCAST_ROWS + 1).count() > BROADCAST_ROWS:
                return ps(s, d).join(side, F.col("s_suppkey") == F.col("j")).select("i", "j", "v", "s_nationkey")
            side = F.broadcast(side)
        elif hint:
            side = side.hint(hint)
        return ps(s, d).join(side, F.col("s_suppkey") == F.col("j")).select("i", "j", "v", "s_nationkey")

    return run


for _name, _hint in (("inner", None), ("broadcast", "broadcast"), ("merge", "merge"), ("shuffle_hash", "shuffle_hash")):
    add(f"op_join_{_name}", _SUPPLIER)(_joined(_hint))
add("op_join_left_densify", "SELECT o_orderkey AS id, coalesce(x, 0) AS x FROM orders LEFT JOIN (SELECT l_orderkey, sum(l_quantity) AS x FROM lineitem WHERE l_quantity > 40 GROUP BY 1) ON l_orderkey = o_orderkey")(lambda s, d: tables.table(s, d, "orders", ["o_orderkey"]).join(lines(s, d, "l_orderkey", "l_quantity").filter("l_quantity > 40").groupBy("l_orderkey").agg(F.sum("l_quantity").alias("x")), F.col("l_orderkey") == F.col("o_orderkey"), "left").select(F.col("o_orderkey").alias("id"), F.coalesce("x", F.lit(0.0)).alias("x")))
add("op_join_right", "SELECT l_orderkey, o_orderkey FROM (SELECT DISTINCT l_orderkey FROM lineitem WHERE l_quantity > 49) RIGHT JOIN orders ON l_orderkey = o_orderkey")(lambda s, d: lines(s, d, "l_orderkey", "l_quantity").filter("l_quantity > 49").select("l_orderkey").distinct().join(tables.table(s, d, "orders", ["o_orderkey"]), F.col("l_orderkey") == F.col("o_orderkey"), "right"))


def _half(s, d, late: bool) -> DataFrame:
    rows = lines(s, d, "l_partkey", "l_suppkey", "l_quantity", "l_shipdate").filter((F.col("l_shipdate") >= CUT) if late else (F.col("l_shipdate") < CUT))
    return rows.groupBy(F.col("l_partkey").alias("i"), F.col("l_suppkey").alias("j")).agg(F.sum("l_quantity").alias("v"))


_EARLY, _LATE = (f"SELECT l_partkey AS i, l_suppkey AS j, sum(l_quantity) AS v FROM lineitem WHERE l_shipdate {o} TIMESTAMP '{CUT}' GROUP BY ALL" for o in ("<", ">="))
add("op_join_full_sparse_add", f"SELECT coalesce(a.i, b.i) AS i, coalesce(a.j, b.j) AS j, coalesce(a.v, 0) + coalesce(b.v, 0) AS v FROM ({_EARLY}) a FULL JOIN ({_LATE}) b ON a.i = b.i AND a.j = b.j")(lambda s, d: _half(s, d, False).withColumnRenamed("v", "a").join(_half(s, d, True).withColumnRenamed("v", "b"), ["i", "j"], "full").select("i", "j", (F.coalesce("a", F.lit(0.0)) + F.coalesce("b", F.lit(0.0))).alias("v")))
add("op_join_semi", "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity = 50)")(lambda s, d: tables.table(s, d, "orders", ["o_orderkey"]).join(lines(s, d, "l_orderkey", "l_quantity").filter("l_quantity = 50"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi"))
add("op_join_anti_missing", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")(lambda s, d: tables.table(s, d, "orders", ["o_orderkey"]).join(lines(s, d, "l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti"))
add("op_join_cross_small", "SELECT r_name, n_name FROM region, nation")(lambda s, d: tables.table(s, d, "region", ["r_name"]).crossJoin(F.broadcast(tables.table(s, d, "nation", ["n_name"]))))


_RANGE = """WITH k AS (SELECT min(p_partkey) // 250 AS low, max(p_partkey) // 250 AS high FROM part), b AS (SELECT unnest(range(low, high + 1)) AS block FROM k)
SELECT p_partkey, block FROM part JOIN b ON p_partkey >= block * 250 AND p_partkey < block * 250 + 250"""


@add("op_join_range_blocks", _RANGE)
def _range(s, d):
    """Blocks of 250 keys from the least to the greatest key; a wider band as equal key leaves each part few blocks to try."""
    parts = tables.table(s, d, "part", ["p_partkey"])
    low, high = parts.agg(F.floor(F.min("p_partkey") / 250), F.floor(F.max("p_partkey") / 250)).first()
    blocks = s.range(low or 0, 0 if high is None else high + 1).select(F.col("id").alias("block"), (F.col("id") * 250).alias("low"), (F.col("id") * 250 + 250).alias("high"), F.floor(F.col("id") / 16).alias("band"))
    inside = (F.floor(F.col("p_partkey") / 4000) == F.col("band")) & (F.col("p_partkey") >= F.col("low")) & (F.col("p_partkey") < F.col("high"))
    return parts.join(blocks, inside).select("p_partkey", "block")


@add("op_join_asof_events", "SELECT p.event_id, v.value AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'view' GROUP BY ALL) v ON p.user_id = v.user_id AND p.ts >= v.ts")
def _asof(s, d):
    """Value of each purchase's last view: one union sorted by user and time, no range join."""
    rows = events(s, d, "event_id", "ts", "user_id", "event_type", "value")
    views = rows.filter("event_type = 'view'").groupBy("user_id", "ts").agg(F.max("value").alias("view")).select("user_id", "ts", F.lit(None).cast("bigint").alias("event_id"), "view", F.lit(0).alias("turn"))
    bought = rows.filter("event_type = 'purchase'").select("user_id", "ts", "event_id", F.lit(None).cast("double").alias("view"), F.lit(1).alias("turn"))
    order = Window.partitionBy("user_id").orderBy("ts", "turn").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return views.union(bought).withColumn("last_view", F.last("view", ignorenulls=True).over(order)).filter("turn = 1").select("event_id", "last_view")


@add("op_join_interval_events", "SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts >= c.ts AND p.ts < c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def _interval(s, d):
    """Click and purchase within an hour: equal user and hour bucket (a click enters two), then the exact bounds."""
    rows = events(s, d, "event_id", "ts", "user_id", "event_type").withColumn("hour", F.floor(F.unix_timestamp("ts") / 3600))
    clicks = rows.filter("event_type = 'click'").select("user_id", F.col("event_id").alias("click_id"), F.col("ts").alias("clicked"), F.explode(F.array(F.col("hour"), F.col("hour") + 1)).alias("hour"))
    bought = rows.filter("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), "ts", "hour")
    return clicks.join(bought, ["user_id", "hour"]).filter("ts >= clicked and ts < clicked + interval 1 hour").select("click_id", "purchase_id")


add("op_join_theta_cosine", "SELECT a.vec_id AS i, b.vec_id AS j FROM embeddings a, embeddings b WHERE a.vec_id <> b.vec_id AND list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) > 0.3")(lambda s, d: block_products(tables.embeddings(s, d), 0.3).select("i", "j"))


@add("op_join_salted", _SUPPLIER)
def _salted(s, d):
    """A hot column's nonzeros are spread over 16 salts; the small side has a copy for each."""
    left = ps(s, d).withColumn("salt", F.pmod(F.xxhash64("i"), F.lit(16)))
    right = _suppliers(s, d).withColumn("salt", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(15).cast("bigint"))))
    return left.join(right.hint("merge"), (F.col("j") == F.col("s_suppkey")) & (left["salt"] == right["salt"])).select("i", "j", "v", "s_nationkey")


# ---- aggregates ----

add("op_agg_stats", f"SELECT j, count(*) AS n, round(avg(v), 6) AS mean, min(v) AS least, max(v) AS most, round(stddev_samp(v), 6) AS spread FROM ({PS}) GROUP BY j")(lambda s, d: ps(s, d).groupBy("j").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("v"), 6).alias("mean"), F.min("v").alias("least"), F.max("v").alias("most"), F.round(F.stddev_samp("v"), 6).alias("spread")))
add("op_agg_distinct", f"SELECT count(DISTINCT i) AS rows, count(DISTINCT j) AS columns FROM ({PS})")(lambda s, d: ps(s, d).agg(F.count_distinct("i").alias("rows"), F.count_distinct("j").alias("columns")))
add("op_agg_approx")(lambda s, d: ps(s, d).agg(F.approx_count_distinct("i").alias("rows"), F.percentile_approx("v", [0.5, 0.99]).alias("quantiles")))
_CUBE = "SELECT l_returnflag, l_linestatus, sum(l_quantity) AS quantity, CAST(grouping(l_returnflag) * 2 + grouping(l_linestatus) AS BIGINT) AS level FROM lineitem GROUP BY {how}"
for _how, _sql in (("cube", "CUBE (l_returnflag, l_linestatus)"), ("rollup", "ROLLUP (l_returnflag, l_linestatus)")):
    add(f"op_agg_{_how}", _CUBE.format(how=_sql))(lambda s, d, how=_how: getattr(lines(s, d, "l_returnflag", "l_linestatus", "l_quantity"), how)("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("quantity"), F.grouping_id().alias("level")))
add("op_agg_grouping_sets", _CUBE.format(how="GROUPING SETS ((l_returnflag), (l_linestatus))"))(lambda s, d: lines(s, d, "l_returnflag", "l_linestatus", "l_quantity").groupingSets([["l_returnflag"], ["l_linestatus"]], "l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("quantity"), F.grouping_id().alias("level")))
add("op_agg_pivot", "SELECT user_id, CAST(count(*) FILTER (event_type = 'click') AS BIGINT) AS click, CAST(count(*) FILTER (event_type = 'view') AS BIGINT) AS view FROM events GROUP BY user_id")(lambda s, d: events(s, d, "user_id", "event_type").groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).fillna(0))
add("op_agg_having", f"SELECT i, count(*) AS n FROM ({PS}) GROUP BY i HAVING count(*) > 20")(lambda s, d: ps(s, d).groupBy("i").agg(F.count(F.lit(1)).alias("n")).filter("n > 20"))
add("op_agg_max_by", f"SELECT i, arg_max(j, v * 100000 - j) AS best FROM ({PS}) GROUP BY i")(lambda s, d: ps(s, d).groupBy("i").agg(F.max_by("j", F.col("v") * 100000 - F.col("j")).alias("best")))

# ---- windows, sorts, sets ----



def _by_row():
    return Window.partitionBy("i").orderBy(F.desc("v"), "j")


add("op_window_rank", f"SELECT i, j, CAST(rank() OVER w AS INTEGER) AS r, CAST(dense_rank() OVER w AS INTEGER) AS dr, round(percent_rank() OVER w, 9) AS pr FROM ({PS}) WINDOW w AS (PARTITION BY i ORDER BY v DESC)")(lambda s, d: ps(s, d).select("i", "j", F.rank().over(Window.partitionBy("i").orderBy(F.desc("v"))).alias("r"), F.dense_rank().over(Window.partitionBy("i").orderBy(F.desc("v"))).alias("dr"), F.round(F.percent_rank().over(Window.partitionBy("i").orderBy(F.desc("v"))), 9).alias("pr")))
add("op_window_ntile", f"SELECT i, j, CAST(ntile(4) OVER (PARTITION BY i ORDER BY v DESC, j) AS INTEGER) AS quarter FROM ({PS})")(lambda s, d: ps(s, d).select("i", "j", F.ntile(4).over(_by_row()).alias("quarter")))
add("op_window_lag", f"SELECT i, j, v - lag(v) OVER (PARTITION BY i ORDER BY j) AS step, lead(j) OVER (PARTITION BY i ORDER BY j) AS next_j FROM ({PS})")(lambda s, d: ps(s, d).select("i", "j", (F.col("v") - F.lag("v").over(Window.partitionBy("i").orderBy("j"))).alias("step"), F.lead("j").over(Window.partitionBy("i").orderBy("j")).alias("next_j")))


@add("op_window_running_offsets", f"SELECT i, CAST(coalesce(sum(n) OVER (ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS first FROM (SELECT i, count(*) AS n FROM ({PS}) GROUP BY i)")
def _offsets(s, d, size: int = 256):
    """Row offsets of the compressed form: running sums within blocks, then the sums of the blocks before."""
    counts = ps(s, d).groupBy("i").agg(F.count(F.lit(1)).alias("n")).withColumn("block", F.floor(F.col("i") / size))
    inner = Window.partitionBy("block").orderBy("i").rowsBetween(Window.unboundedPreceding, -1)
    blocks = counts.groupBy("block").agg(F.sum("n").alias("all"))
    before = blocks.select("block", F.coalesce(F.sum("all").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    return counts.withColumn("inside", F.coalesce(F.sum("n").over(inner), F.lit(0))).join(before, "block").select("i", (F.col("inside") + F.col("base")).alias("first"))


add("op_window_range", f"SELECT i, j, sum(v) OVER (PARTITION BY i ORDER BY j RANGE BETWEEN 3 PRECEDING AND CURRENT ROW) AS near FROM ({PS})")(lambda s, d: ps(s, d).select("i", "j", F.sum("v").over(Window.partitionBy("i").orderBy("j").rangeBetween(-3, 0)).alias("near")))
add("op_window_softmax", f"SELECT i, j, round(exp(v / 50 - m) / sum(exp(v / 50 - m)) OVER (PARTITION BY i), 9) AS p FROM (SELECT i, j, v, max(v / 50) OVER (PARTITION BY i) AS m FROM ({PS}))")(lambda s, d: ps(s, d).withColumn("m", F.max(F.col("v") / 50).over(Window.partitionBy("i"))).withColumn("e", F.exp(F.col("v") / 50 - F.col("m"))).select("i", "j", F.round(F.col("e") / F.sum("e").over(Window.partitionBy("i")), 9).alias("p")))
add("op_topk_per_row", f"SELECT i, j, v FROM (SELECT *, row_number() OVER (PARTITION BY i ORDER BY v DESC, j) AS r FROM ({PS})) WHERE r <= 3")(lambda s, d: ps(s, d).withColumn("r", F.row_number().over(_by_row())).filter("r <= 3").select("i", "j", "v"))
add("op_sort_limit", f"SELECT i, j, v FROM ({PS}) ORDER BY v DESC, i, j LIMIT 25")(lambda s, d: ps(s, d).orderBy(F.desc("v"), "i", "j").limit(25))
for _name, _sql, _f in (("union_all", "UNION ALL", "unionAll"), ("union", "UNION", "union"), ("intersect", "INTERSECT", "intersect"), ("except", "EXCEPT", "subtract"), ("except_all", "EXCEPT ALL", "exceptAll")):
    def _sets(s, d, f=_f, name=_name):
        out = getattr(_half(s, d, False).select("i", "j"), f)(_half(s, d, True).select("i", "j"))
        return out.distinct() if name == "union" else out

    add(f"op_set_{_name}", f"SELECT i, j FROM ({_EARLY}) {_sql} SELECT i, j FROM ({_LATE})")(_sets)

# ---- functions ----

add("op_fn_math", f"SELECT i, j, round(sqrt(v), 6) AS root, round(exp(-v / 100), 6) AS decay, CAST(floor(v / 7) AS BIGINT) AS sevens, greatest(v, 50) AS most, i % 7 AS rest FROM ({PS})")(lambda s, d: ps(s, d).select("i", "j", F.round(F.sqrt("v"), 6).alias("root"), F.round(F.exp(-F.col("v") / 100), 6).alias("decay"), F.floor(F.col("v") / 7).alias("sevens"), F.greatest("v", F.lit(50.0)).alias("most"), F.pmod("i", F.lit(7)).alias("rest")))
add("op_fn_array", "SELECT vec_id, CAST(len(embedding) AS INTEGER) AS size, round(list_sum(list_transform(embedding[1:8], lambda x: x::DOUBLE)), 6) AS head FROM embeddings")(lambda s, d: tables.embeddings(s, d).select(F.col("id").alias("vec_id"), F.size("x").alias("size"), F.round(F.aggregate(F.slice("x", 1, 8), F.lit(0.0), lambda a, x: a + x), 6).alias("head")))
add("op_fn_vector", "SELECT vec_id AS id, round(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[]), 6) AS square FROM embeddings")(lambda s, d: tables.embeddings(s, d).select("id", F.round(vectors.dot("x", "x"), 6).alias("square")))
add("op_fn_string_tokens", "SELECT word, count(*) AS n FROM (SELECT unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS word FROM documents) WHERE word <> '' GROUP BY word")(lambda s, d: tables.words(tables.table(s, d, "documents", ["doc_id", "text"])).groupBy("word").agg(F.count(F.lit(1)).alias("n")))
add("op_fn_json_key", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")(lambda s, d: events(s, d, "props").groupBy(F.get_json_object("props", "$.k").cast("bigint").alias("k")).agg(F.count(F.lit(1)).alias("n")))
add("op_fn_map_row", PS)(lambda s, d: from_row_map(to_row_map(ps(s, d))))
add("op_fn_date_slices", "SELECT CAST(year(o_orderdate) AS INTEGER) AS y, o_custkey, round(sum(exp(-date_diff('day', o_orderdate, TIMESTAMP '1999-01-01') / 365.0)), 6) AS v FROM orders GROUP BY ALL")(lambda s, d: tables.table(s, d, "orders", ["o_orderdate", "o_custkey"]).groupBy(F.year("o_orderdate").alias("y"), "o_custkey").agg(F.round(F.sum(F.exp(-F.datediff(F.lit("1999-01-01").cast("date"), "o_orderdate") / 365.0)), 6).alias("v")))
add("op_fn_decimal", "SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS VARCHAR) AS price FROM lineitem GROUP BY 1")(lambda s, d: lines(s, d, "l_returnflag", "l_extendedprice").groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("string").alias("price")))
add("op_fn_activation", f"SELECT i, j, CASE WHEN v >= 30 THEN v - 30 ELSE 0.2 * (v - 30) END AS leaky, greatest(v - 30, 0) AS relu, round(1 / (1 + exp((30 - v) / 10)), 6) AS sigmoid FROM ({PS})")(lambda s, d: ps(s, d).withColumn("x", F.col("v") - 30).select("i", "j", vectors.leaky_relu(F.col("x")).alias("leaky"), vectors.relu(F.col("x")).alias("relu"), F.round(vectors.sigmoid(F.col("x") / 10), 6).alias("sigmoid")))

# ---- user functions; the SQL forms above are the default, these are there to compare ----


def _lattice(ids: str, a: int, b: int) -> str:
    return f"SELECT id, k, CAST((id * {a} + k * {b} + 7 * id * (k + 3) * (k + 1) + 7) % 101 - 50 AS DOUBLE) / 64 AS x FROM ({ids}), (SELECT unnest(range(8)) AS k)"


_WITH = f"WITH s AS ({PS}), a AS ({_lattice('SELECT DISTINCT i AS id FROM s', 31, 17)}), b AS ({_lattice('SELECT DISTINCT j AS id FROM s', 13, 19)}), r AS (SELECT s.i, s.j, s.v * sum(a.x * b.x) AS v FROM s JOIN a ON a.id = s.i JOIN b ON b.id = s.j AND b.k = a.k GROUP BY s.i, s.j, s.v)"


def _met(s, d) -> DataFrame:
    m = ps(s, d)
    return m.join(tables.left_factor(m).withColumnsRenamed({"id": "i", "x": "ax"}), "i").join(tables.right_factor(m).withColumnsRenamed({"id": "j", "x": "bx"}), "j")


@add("op_udf_dot", f"{_WITH} SELECT i, j, v FROM r")
def _udf(s, d):
    @F.pandas_udf("double")
    def dot_udf(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series(np.einsum("nr,nr->n", np.stack(a), np.stack(b)) if len(a) else [], dtype=float)

    return _met(s, d).select("i", "j", (F.col("v") * dot_udf("ax", "bx")).alias("v"))


add("op_map_arrow_dot", f"{_WITH} SELECT i, j, v FROM r")(lambda s, d: _met(s, d).select("i", "j", "v", "ax", "bx").mapInArrow(kernels.arrow_masked, "i bigint, j bigint, v double"))


@add("op_udaf_vector_sum", f"{_WITH} SELECT s.i AS id, b.k, sum(s.v * b.x) AS x FROM s JOIN b ON b.id = s.j GROUP BY ALL")
def _udaf(s, d):
    @F.pandas_udf("array<double>")
    def vector_sum(y: pd.Series) -> list:
        return np.stack(y).sum(0).tolist()

    m = ps(s, d)
    weighted = m.join(tables.right_factor(m).withColumnsRenamed({"id": "j", "x": "bx"}), "j").select("i", vectors.scale("bx", F.col("v")).alias("y"))
    summed = weighted.groupBy("i").agg(vector_sum("y").alias("x"))
    return summed.select(F.col("i").alias("id"), F.posexplode("x").alias("k", "x")).select("id", F.col("k").cast("bigint").alias("k"), "x")


@add("op_udtf_targets", "SELECT id, CAST(id * 4 // m AS INTEGER) AS block, CAST((id * 4 // m) * 2 + f AS INTEGER) AS station FROM (SELECT DISTINCT l_partkey AS id FROM lineitem), (SELECT max(l_partkey) + 1 AS m FROM lineitem), (SELECT unnest(range(2)) AS f)")
def _udtf(s, d):
    """The stations that a row of the part side is copied to: those of its block's fiber."""

    class Targets:
        def eval(self, block: int, c: int):
            for fiber in range(c):
                yield (block * c + fiber,)

    parts = lines(s, d, "l_partkey").select(F.col("l_partkey").alias("id")).distinct()
    m = (lines(s, d, "l_partkey").agg(F.max("l_partkey")).first()[0] or 0) + 1
    s.udtf.register("grid_targets", F.udtf(Targets, returnType="station int"))
    return s.sql("SELECT id, block, station FROM {parts}, LATERAL grid_targets(block, 2)", parts=parts.select("id", block("id", 4, m).alias("block")))


@add("op_apply_arrow_chain", f"{_WITH} SELECT r.i AS id, b.k, sum(r.v * b.x) AS x FROM r JOIN b ON b.id = r.j GROUP BY ALL")
def _apply(s, d):
    """The fused local kernel on each station, with partial sums met by one exchange: dense rows come to a station once, nonzeros stream."""
    m = stored(ps(s, d), "matrix")
    top = m.agg(F.max("i"), F.max("j")).first()
    grid = Grid("ds", 8, 2, (top[0] or 0) + 1, (top[1] or 0) + 1, 8)
    left = deal(dense_rows(place_left(tables.left_factor(m), grid), LEFT, "i", "ax"), grid.p)
    right = deal(dense_rows(place_right(tables.right_factor(m), grid), RIGHT, "j", "bx"), grid.p)
    cells = deal(cell_rows(place_sparse(m, grid)), grid.p)
    return reduced(at_stations([left, right, cells], chain_kernel(RIGHT), PARTIAL), grid.holders("left") == 1)


@add("op_cogroup_arrow_gather", f"{_WITH} SELECT s.i AS id, b.k, sum(s.v * b.x) AS x FROM s JOIN b ON b.id = s.j GROUP BY ALL")
def _cogroup(s, d):
    """A block of nonzeros meets the dense rows of its columns in one co-grouped call."""
    m = ps(s, d)
    top = m.agg(F.max("j")).first()
    n = (top[0] or 0) + 1

    def gather(left: pa.Table, right: pa.Table) -> pa.Table:
        ids = np.asarray(right.column("id"))
        order = np.argsort(ids)
        x = np.asarray(right.column("x").combine_chunks().flatten(), float).reshape(len(ids), -1)[order]
        i, j, v = (np.asarray(left.column(c)) for c in ("i", "j", "v"))
        y = x[np.searchsorted(ids[order], j)] * v[:, None] if len(ids) else np.zeros((0, 8))
        if not len(i):
            return pa.table({"id": pa.array([], pa.int64()), "k": pa.array([], pa.int64()), "x": pa.array([], pa.float64())})
        by = np.argsort(i, kind="stable")
        first = np.flatnonzero(np.concatenate([[True], i[by][1:] != i[by][:-1]]))
        sums = np.add.reduceat(y[by], first, axis=0)
        return pa.table({"id": np.repeat(i[by][first], sums.shape[1]), "k": np.tile(np.arange(sums.shape[1], dtype=np.int64), len(first)), "x": sums.ravel()})

    left = m.withColumn("block", block("j", 8, n))
    right = tables.right_factor(m).withColumn("block", block("id", 8, n))
    part = left.groupBy("block").cogroup(right.groupBy("block")).applyInArrow(gather, "id bigint, k bigint, x double")
    return part.groupBy("id", "k").agg(F.sum("x").alias("x"))


@add("op_sql_surface_chain", f"{_WITH} SELECT r.i AS id, b.k, sum(r.v * b.x) AS x FROM r JOIN b ON b.id = r.j GROUP BY ALL")
def _sql_surface(s, d):
    from gridchain.plans.sql_surface import chain_text, register

    m = ps(s, d)
    register(s, m, tables.left_factor(m), tables.right_factor(m))
    return s.sql(chain_text())


