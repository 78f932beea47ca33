"""Whole-table forms against their SQL, and that no id is left out."""

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from sparsepairs.plans import whole
from test_oracles import duck  # noqa: F401

KEYS = [
    "join_range", "join_left", "join_right", "join_full", "join_theta", "set_union_all", "set_union", "set_intersect", "set_except", "set_intersect_all", "set_except_all",
    "fn_sp_hits", "sink_sketch", "m_dangling",
]


@pytest.mark.parametrize("key", KEYS)
def test_whole_oracle(spark, sf, duck, key):  # noqa: F811
    key = f"{key}_whole"
    assert " % " not in entry.oracle_sql()[key]
    ours, theirs = entry.queries()[key](spark, sf), duck.sql(entry.oracle_sql()[key])
    assert ours.columns == theirs.columns
    assert sorted(map(str, map(tuple, ours.collect()))) == sorted(map(str, theirs.fetchall())) != []


def test_nothing_of_the_preserved_sides_is_lost(spark, sf):
    full = entry.queries()["join_full_whole"](spark, sf)
    n = {t: spark.read.parquet(f"{sf}/{t}.parquet").count() for t in ("customer", "orders", "part", "nation")}
    assert full.select("c_custkey").where("c_custkey is not null").distinct().count() == n["customer"]
    assert full.select("o_orderkey").where("o_orderkey is not null").distinct().count() == n["orders"]
    assert full.where("o_orderkey is null").count() and full.where("c_custkey is null").count()
    kept = entry.queries()["m_dangling_whole"](spark, sf).first()
    assert 0 < kept["n_left"] < n["part"] and 0 < kept["n_right"] < n["nation"]


def test_parts_of_repeated_prices_meet_as_lists(spark, sf, tmp_path, monkeypatch):
    monkeypatch.setattr(whole, "LISTED", 7)
    part = spark.read.parquet(f"{sf}/part.parquet").where("p_partkey < 40")
    copies = part.crossJoin(spark.range(30)).withColumn("p_partkey", F.col("p_partkey") + 1000 * F.col("id")).drop("id")
    odd = part.limit(4).withColumns({"p_partkey": F.when(F.col("p_partkey") > 1, F.col("p_partkey") + 10**6), "p_retailprice": F.expr("case p_partkey when 2 then null when 3 then 'NaN' else p_retailprice end").cast("double")})
    copies.unionByName(odd).write.parquet(str(tmp_path / "part.parquet"))
    found = entry.queries()["join_theta_whole"](spark, str(tmp_path))
    part = spark.read.parquet(str(tmp_path / "part.parquet"))
    want = part.select(F.col("p_partkey").alias("a"), F.col("p_retailprice").alias("x")).crossJoin(part.select(F.col("p_partkey").alias("b"), F.col("p_retailprice").alias("y"))).where("x < y and x > y - 1")
    counts = lambda df: sorted((str(r["a"]), str(r["b"]), r["count"]) for r in df.groupBy("a", "b").count().collect())
    assert counts(found) == counts(want) != []
    assert found.where("a is null").count() > 0
    # Before, every part met every other of its whole price in the join, and the tasks were the whole prices.
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert "collect_list" in plan and "Repartition" in plan
