"""Queries that once left rows out, on tables large enough to show it."""

import os

import duckdb
import pytest

import __spark_entry__

DATA = "/root/testdata"

#: Queries that once read no table, and those that they read.
READ: dict[str, list[tuple[str, str]]] = {
    "best_c_table": [("lineitem", "l_suppkey")],
    "cost_table": [("lineitem", "l_suppkey")],
    "elision_ratios": [("lineitem", "l_suppkey")],
    "model_table": [("lineitem", "l_suppkey")],
    "op_udtf_targets": [("lineitem", "l_partkey")],
    "planner_explain": [("lineitem", "l_suppkey")],
    "planner_map_p32": [("lineitem", "l_suppkey")],
    "random_bernoulli": [("orders", "o_orderkey"), ("part", "p_partkey")],
    "weak_scaling_exponents": [("lineitem", "l_suppkey")],
}

pytestmark = pytest.mark.skipif(not os.path.isdir(DATA), reason="the given tables are absent")


def test_dense_then_mask_has_all_rows(spark):
    con = duckdb.connect()
    con.sql(f"CREATE VIEW lineitem AS SELECT * FROM '{DATA}/sf0.01/lineitem.parquet'")
    want = con.sql(__spark_entry__.oracle_sql()["masked_part_supplier"]).select("i, j, v").fetchall()
    got = __spark_entry__.queries()["dense_then_mask"](spark, f"{DATA}/sf0.01").select("i", "j", "v").collect()
    assert sorted(map(tuple, got)) == sorted(want) and max(r.i for r in got) >= 500


def test_range_blocks_hold_every_part(spark):
    con = duckdb.connect()
    keys = [k for (k,) in con.sql(f"SELECT p_partkey FROM '{DATA}/sf0.1/part.parquet'").fetchall()]
    got = __spark_entry__.queries()["op_join_range_blocks"](spark, f"{DATA}/sf0.1").collect()
    assert sorted((r.p_partkey, r.block) for r in got) == sorted((k, k // 250) for k in keys) and max(keys) >= 2000
    con.sql(f"CREATE VIEW part AS SELECT * FROM '{DATA}/sf0.01/part.parquet'")
    want = con.sql(__spark_entry__.oracle_sql()["op_join_range_blocks"]).fetchall()
    got = __spark_entry__.queries()["op_join_range_blocks"](spark, f"{DATA}/sf0.01").select("p_partkey", "block").collect()
    assert sorted(map(tuple, got)) == sorted(want)


def test_apply_streams_nonzeros_past_dense_rows(spark):
    """No nonzero travels with its dense rows: the station's exchange holds each once, and no join of them comes before it."""
    got = __spark_entry__.queries()["op_apply_arrow_chain"](spark, f"{DATA}/sf0.001")
    plan = got._jdf.queryExecution().sparkPlan().toString()
    assert "FlatMapGroupsInArrow" in plan and "Join" not in plan
    con = duckdb.connect()
    con.sql(f"CREATE VIEW lineitem AS SELECT * FROM '{DATA}/sf0.001/lineitem.parquet'")
    want = con.sql(__spark_entry__.oracle_sql()["op_apply_arrow_chain"]).select("id, k, x").fetchall()
    assert sorted(map(tuple, got.select("id", "k", "x").collect())) == sorted(want)


@pytest.mark.parametrize("name", READ)
def test_query_depends_on_its_table(spark, name, tmp_path):
    """Rows of the given table decide the result: with half of it the result is another, each as its SQL has it."""
    con, results = duckdb.connect(), []
    for part, keep in (("whole", "true"), ("half", "{0} < 0.4 * (SELECT max({0}) FROM t)")):
        (tmp_path / part).mkdir()
        for table, key in READ[name]:
            con.sql(f"CREATE OR REPLACE VIEW t AS SELECT * FROM '{DATA}/sf0.001/{table}.parquet'")
            con.sql(f"COPY (SELECT * FROM t WHERE {keep.format(key)}) TO '{tmp_path}/{part}/{table}.parquet' (FORMAT parquet)")
            con.sql(f"CREATE OR REPLACE VIEW {table} AS SELECT * FROM '{tmp_path}/{part}/{table}.parquet'")
        got = __spark_entry__.queries()[name](spark, str(tmp_path / part))
        columns = sorted(got.columns)
        results.append(sorted(str(tuple(r)) for r in got.select(*columns).collect()))
        if name in __spark_entry__.oracle_sql():
            want = con.sql(__spark_entry__.oracle_sql()[name])
            assert results[-1] == sorted(str(row) for row in want.select(", ".join(columns)).fetchall())
    assert results[0] and results[0] != results[1]
