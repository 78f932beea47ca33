"""Runs in one pass and exact sizes by bits, beside the joins that they replace."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from sparsepairs.functions.hashing import MD5_60
from sparsepairs.operators import baselines, exact, runs, sampling
from sparsepairs.operators.estimate import Spec, run_estimates
from sparsepairs.plans import methods

RUNS = range(1, 61)


def test_texts_hash_as_md5_60(spark):
    values = ["0", "17", "\\N", "", "ä" * 20, "x" * 54, "y" * 70]
    seen = spark.createDataFrame([(v,) for v in values], "v string").select(MD5_60.hash(F.col("v"), "SL7:").alias("h")).collect()
    assert [int(h) >> 4 for h in runs.Texts(pa.array(values)).hashes("SL7:")] == [r["h"] for r in seen]


@pytest.mark.parametrize("name", ["cust_type", "part_part_order", "vec_vec"])
def test_one_pass_keeps_what_the_joined_runs_keep(spark, sf, name):
    r = methods.rel(spark, sf, name)
    want = {x["run"]: x for x in run_estimates(r, Spec(k=64, family="md5_60", policy="one"), range(1, 5), 1.0).collect()}
    for z in (1.0, 10.0**7):  # the second threshold is too low for all runs, which are walked again
        for x in runs.runs_from_one(r, (16, 64), range(1, 5), z)[64].collect():
            assert (x["kept"], x["kth_hash"], x["z_hat"]) == (want[x["run"]]["kept"], want[x["run"]]["kth_hash"], want[x["run"]]["z_hat"])


def test_tuples_travel_once(spark, sf):
    # Before, each tuple was dealt once a run: 60 rows for each.
    plan = runs.kept_of_runs(methods.rel(spark, sf, "part_part_order"), 64, RUNS, 2**40)._jdf.queryExecution().optimizedPlan().toString()
    assert "Generate" not in plan and "MapInArrow" in plan


@pytest.mark.parametrize("name", ["x_failure_split", "x_study_supp_cust_order"])
def test_studies_deal_no_tuple_for_each_run(spark, sf, monkeypatch, name):
    # Before, every joined row went through a shuffle once a run.
    dealt, own = [], runs.kept_of_runs
    monkeypatch.setattr(runs, "kept_of_runs", lambda *a: dealt.append(own(*a)) or dealt[-1])
    __import__("__spark_entry__").queries()[name](spark, sf).collect()
    assert dealt and all("Join" not in (plan := d._jdf.queryExecution().optimizedPlan().toString()) and "Generate" not in plan for d in dealt)


@pytest.mark.parametrize("name", ["x_study_cust_type", "x_sample_study_vec_vec"])
def test_dense_studies_shuffle_no_joined_row(spark, sf, monkeypatch, name):
    # Before, the exact size went through a join and a shuffled distinct, and the runs through a join for each of them.
    query, dealt, own = __import__("__spark_entry__").queries()[name], [], runs.kept_of_runs
    want = sorted(map(tuple, query(spark, sf).collect()))
    monkeypatch.setattr(exact, "FEW_JOINED", 0)
    monkeypatch.setattr(baselines, "exact_size", None)
    monkeypatch.setattr(runs, "kept_of_runs", lambda *a: dealt.append(own(*a)) or dealt[-1])
    assert sorted(map(tuple, query(spark, sf).collect())) == want
    assert dealt and all("Join" not in (plan := d._jdf.queryExecution().optimizedPlan().toString()) and "Generate" not in plan for d in dealt)


def test_sample_sketches_equal_joined_samples(spark, sf):
    r = methods.rel(spark, sf, "doc_doc_word")
    z = baselines.exact_size(r).first()["z"]
    want = {x["run"]: (x["kept"], x["z_hat"]) for x in sampling.sample_runs(r, 0.3, 0.2, RUNS, k=100).collect()}
    assert {x["run"]: (x["kept"], x["z_hat"]) for x in runs.sample_sketches(r, 0.3, 0.2, RUNS, 100, z).collect()} == want


def test_heavy_groups_are_walked_like_light_ones(monkeypatch):
    rng = np.random.default_rng(3)
    rows = pa.table({"jk": np.repeat(np.arange(3), 300), "side": np.zeros(900, np.int32), "v": pa.array([str(x) for x in rng.integers(0, 400, 900)])})
    found = []
    for heavy in (0, 10**9):
        monkeypatch.setattr(runs, "HEAVY", heavy)
        kept = runs.Kept(50, range(1, 4), 2**60)
        runs.Chunk(rows, True).whole(kept)
        kept.settle()
        found.append([s.rows.tolist() for s in kept.sets])
    assert found[0] == found[1] and all(len(x) == 50 for x in found[0])


@pytest.mark.parametrize("name", ["cust_type", "part_part_order", "vec_vec", "doc_doc_word"])
def test_bits_count_what_the_join_counts(spark, sf, name, monkeypatch):
    r = methods.rel(spark, sf, name)
    n_c = r.right.select("rk").distinct().count()
    want = {x["run"]: x["kept"] for x in sampling.sample_runs(r, 0.2, 0.1, RUNS).collect()} | {0: baselines.exact_size(r).first()["z"]}
    assert {x["run"]: x["kept"] for x in exact.by_bits(r, n_c, (0.2, 0.1), RUNS).collect()} == want
    monkeypatch.setattr(exact, "FILLED", max(1, n_c // 3))  # several blocks
    assert exact.by_bits(r, n_c).first()["kept"] == want[0]


@pytest.mark.parametrize("name", ["cust_cust_part", "supp_cust_order", "cust_type", "doc_doc_word"])
def test_lists_count_what_the_join_counts(spark, sf, name, monkeypatch):
    r = methods.rel(spark, sf, name)
    monkeypatch.setattr(exact, "BLOCK_TUPLES", max(1, r.right.count() // 2))  # several passes
    assert exact.by_lists(r).first()["z"] == baselines.exact_size(r).first()["z"]


def test_a_left_value_is_listed_in_turns(monkeypatch):
    rng = np.random.default_rng(5)
    left, right = (np.unique(rng.integers(0, 40, (400, 2)), axis=0).astype(np.uint64) for _ in range(2))
    want = {(a, c) for a, j in left.tolist() for i, c in right.tolist() if i == j}
    lists = exact.Lists((right[:, 0] << np.uint64(32)) | right[:, 1])
    for listed in (exact.LISTED, 300, 10, 1):
        monkeypatch.setattr(exact, "LISTED", listed)
        assert lists.count(left[:, 0].astype(np.uint32), left[:, 1].astype(np.uint32)) == len(want)


def test_lists_take_nulls_and_large_values(spark):
    left = spark.createDataFrame([(1, -5), (None, -5), (2**40, 2**50), (None, 2**50), (7, 1)], "lk long, jk long")
    right = spark.createDataFrame([(-5, None), (-5, "x"), (2**50, None), (2, "y")], "jk long, rk string")
    assert exact.by_lists(exact.Rel(left, right, True)).first()["z"] == 5


def test_many_sparse_joined_rows_are_not_shuffled(spark, sf, monkeypatch):
    # Before, they went through a join and a shuffled distinct.
    monkeypatch.setattr(exact, "FEW_JOINED", 0)
    monkeypatch.setattr(exact, "WORTH", 0)
    monkeypatch.setattr(baselines, "exact_size", None)
    r = methods.rel(spark, sf, "cust_cust_part")
    assert exact.size(r).first()["z"] == r.left.join(r.right, "jk").select("lk", "rk").distinct().count()


def test_a_value_of_lone_join_values_pairs_with_itself(spark):
    left = spark.createDataFrame([(1, "a"), (2, "a"), (3, "b"), (None, "c")], "lk long, jk string")
    r = exact.Rel(left, left.select("jk", F.col("lk").alias("rk")), True, True)
    assert exact.by_bits(r, 4).first()["kept"] == baselines.exact_size(r).first()["z"] == 6


@pytest.mark.parametrize("name", ["doc_doc_word", "vec_vec"])
def test_ranks_count_what_the_join_counts(spark, sf, name, monkeypatch):
    want = baselines.exact_size(methods.rel(spark, sf, name)).first()["z"]
    r = exact.stored_rel(methods.rel(spark, sf, name))
    n = r.left.select("lk").distinct().count()
    for values, tuples, first in ((1 << 16, 10**8, 24), (37, 10**8, 2), (1 << 16, 900, 0)):  # one block, several by values, by tuples
        monkeypatch.setattr(exact, "RANK_VALUES", values)
        monkeypatch.setattr(exact, "RANK_TUPLES", tuples)
        monkeypatch.setattr(exact, "FIRST_ROWS", first)
        assert exact.by_ranks(r, n).first()["z"] == want


@pytest.mark.parametrize(("first", "missing", "long"), [(24, 100, 64), (2, 10**9, 8), (0, 0, 8), (3, 100, 20)])
def test_a_block_counts_what_a_product_counts(monkeypatch, first, missing, long):
    monkeypatch.setattr(exact, "FIRST_ROWS", first)
    monkeypatch.setattr(exact, "MISSING", missing)
    monkeypatch.setattr(exact, "LONG", long)
    rng = np.random.default_rng(7)
    held = rng.random((300, 90)) < 0.15 * rng.random(90)
    keys = pa.array([np.flatnonzero(x).astype(np.uint32).tobytes() for x in held], pa.binary())
    found = exact.RankBlock([keys.slice(0, 100), keys.slice(100)]).counts(keys.slice(50))
    assert found.tolist() == ((held.astype(int) @ held.T.astype(int)) > 0).sum(1)[50:].tolist()


def test_dense_words_are_counted_by_ranks(spark, sf, monkeypatch):
    # Before, each document met each block of documents, whole.
    monkeypatch.setattr(exact, "FEW_JOINED", 0)
    monkeypatch.setattr(exact, "by_bits", None)
    monkeypatch.setattr(baselines, "exact_size", None)
    r = methods.rel(spark, sf, "doc_doc_word")
    assert exact.size(exact.stored_rel(r)).first()["z"] == r.left.join(r.right, "jk").select("lk", "rk").distinct().count()


def test_numbered_words_keep_the_tuples(spark):
    docs = spark.createDataFrame([(1, "a B  b"), (1, "c a"), (2, ""), (3, None), (None, "b a a"), (4, "\u00e4 c")], "doc_id long, text string")
    from sparsepairs.plans import workloads

    r = workloads.shared_words(docs, "doc_id")
    own = exact.stored_rel(r)
    sets = lambda df: sorted(sorted(map(str, x["v"])) + [str(x["n"])] for x in df.groupBy("jk").agg(F.collect_list(F.coalesce(F.col("lk").cast("string"), F.lit("-"))).alias("v"), F.count("*").alias("n")).collect())
    assert sets(own.left) == sets(r.left) and own.left.schema["jk"].dataType.typeName() == "long"
    assert baselines.exact_size(own).first()["z"] == baselines.exact_size(r).first()["z"]


def test_listed_pairs_keep_what_the_walk_keeps(spark, sf, monkeypatch):
    r = exact.stored_rel(methods.rel(spark, sf, "doc_doc_word"))
    z = baselines.exact_size(r).first()["z"]
    both = lambda: (sorted(tuple(x) for df in runs.runs_from_one(r, (16, 64), RUNS, z).values() for x in df.collect()), sorted(map(tuple, runs.sample_sketches(r, 0.3, 0.4, RUNS, 32, z).collect())))
    want = both()
    # Before, dense relations were walked whole for every run.
    walked, own = [], runs.kept_of_runs
    monkeypatch.setattr(runs, "MANY", 16)
    monkeypatch.setattr(runs, "kept_of_runs", lambda *a: walked.append(a[2]) or own(*a))
    assert both() == want
    assert not walked
    monkeypatch.setattr(runs, "FIRST_PASS", 0.9)  # runs are left unfilled
    assert both() == want


def test_clear_texts_are_not_dealt(spark, sf):
    from sparsepairs.llm import near_duplicates

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    docs = docs.unionByName(docs.where("doc_id % 7 = 0")).unionByName(docs.where("doc_id = 3").withColumn("text", F.lit(None).cast("string")))
    docs = docs.unionByName(docs.where("text is null"))
    found = near_duplicates.members(docs).where("component is not null").toPandas()
    found["none"] = found.doc_id.isna()
    heads = found.sort_values(["none", "doc_id", "text_key"]).drop_duplicates("component")
    heads, gone = set(zip(heads.doc_id, heads.text_key)), set(zip(found.doc_id, found.text_key))
    rows = {(r["doc_id"], r["text"], r["k"]) for r in docs.select("doc_id", "text", F.xxhash64("text").alias("k")).collect()}
    want = sorted((a, b or "") for a, b, k in rows if (a, k) in heads or (a, k) not in gone)
    out = near_duplicates.without_copies(docs)
    assert sorted((r["doc_id"], r["text"] or "") for r in out.collect()) == want
    # Before, every row's text was dealt twice; now the rows that are surely kept stay in a branch without an exchange.
    assert "Union" in out._jdf.queryExecution().optimizedPlan().toString()


def test_two_bits_keep_agreements():
    from sparsepairs.llm import near_duplicates

    sample = np.random.default_rng(1).integers(0, 2**32, (5, near_duplicates.COORDINATES), dtype=np.uint32)
    assert (near_duplicates.unpacked(near_duplicates.packed(sample).tobytes()) == (sample & 3)).all()
