"""The queries opN_<name> of the training-data operators and their oracles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decision_list, knn_join, license_scan, near_duplicates, packing, pairwise_quality, secret_scan, shared, subword_sampling, text_stats, token_rollup, toxicity


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Digest of the license scan over all documents."""
    found = license_scan.scan_licenses(table(spark, sf_dir, "documents"))
    labels = F.array_sort(F.array_distinct(F.concat("base_labels", F.transform("notices", lambda x: x["label"]))))
    best = F.coalesce(F.array_max(F.transform("notices", lambda x: x["score"])), F.lit(0.0))
    return found.select(
        "doc_id",
        "n_words",
        "n_base",
        "first_word",
        "last_word",
        F.array_join("base_labels", ",").alias("base_labels"),
        F.array_join(labels, ",").alias("labels"),
        F.when(F.col("n_base") > 0, 1.0).otherwise(best).alias("score"),
        F.size("notices").cast("long").alias("n_notices"),
    )


def op8_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Digest of the secret scan over all documents."""
    found = secret_scan.scan_secrets(table(spark, sf_dir, "documents"))
    written = lambda spans: F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"], x["stop"])), ",")
    return found.select(
        "doc_id",
        "n_assign",
        "n_access",
        "n_hex",
        F.sha2(written(F.filter("spans", lambda x: x["kind"] != "entropy")), 256).alias("base_sha256"),
        written(F.col("spans")).alias("spans"),
    )


def op7_decision_list(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Statistics and verdict of the learned rules for all documents."""
    docs = table(spark, sf_dir, "documents")
    rules = decision_list.fit(docs, table(spark, sf_dir, "labels"))
    return decision_list.apply(docs, rules).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"
    )


def held_out() -> Column:
    return F.coalesce(text_stats.fold() == 0, F.lit(False)).alias("held_out")


def op9_pairwise_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairwise quality score of all documents."""
    docs = table(spark, sf_dir, "documents")
    scorer = pairwise_quality.fit(docs, table(spark, sf_dir, "labels"))
    scored = pairwise_quality.score(docs.select("doc_id", "text"), scorer)
    return scored.select("doc_id", held_out(), "score", (F.col("score") >= pairwise_quality.CUT).cast("int").alias("predicted"))


def op2_subword_sampling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three distinct segmentations of every document, as ids, with inclusion scores."""
    return subword_sampling.sample_encodings(table(spark, sf_dir, "documents"))


def op3_knn_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The five largest inner products of every 50th vector."""
    return knn_join.knn_join(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0, 5)


OP3_SQL = """
with v as (
    select vec_id, list_transform(embedding, lambda e: cast(floor(256 * cast(e as double)) as bigint)) as x
    from embeddings
    where vec_id is not null and embedding is not null
      and list_count(embedding) = len(embedding)
      and len(list_filter(embedding, lambda e: not isfinite(e))) = 0
),
s as (
    select q.vec_id as query_id, c.vec_id,
           cast(coalesce(list_sum(list_transform(list_zip(q.x, c.x), lambda p: p[1] * p[2])), 0) as bigint) as score
    from v q join v c on c.vec_id <> q.vec_id
    where q.vec_id % 50 = 0
),
r as (select *, cast(row_number() over (partition by query_id order by score desc, vec_id) as integer) as rank from s)
select query_id, rank, vec_id, score from r where rank <= 5
"""


def op4_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Class and links of every document at a similarity of 0.8 over five-word shingles."""
    return near_duplicates.classes(table(spark, sf_dir, "documents"))


def op5_token_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Totals after five batches: all documents are inserted, all are revised to count the end token,
    fold 0 is deleted and inserted again, and the first batch is delivered a second time."""
    counts = shared.written(token_rollup.token_counts(table(spark, sf_dir, "documents")), "token-counts")
    counts = counts.withColumn("tokenizer", F.lit("byte_bpe_50k"))
    longer = counts.withColumn("n_tokens", F.col("n_tokens") + 1)
    rollup = token_rollup.TokenRollup(spark, shared.fresh(spark, "token-rollup"))
    again = longer.where(text_stats.fold() == 0)
    rollup.commit("1-load", counts.withColumn("op", F.lit("insert")))
    rollup.commit("2-end-token", longer.withColumn("op", F.lit("revise")))
    rollup.commit("3-withdrawn", again.withColumn("op", F.lit("delete")))
    rollup.commit("4-restored", again.withColumn("op", F.lit("insert")))
    rollup.commit("1-load", counts.withColumn("op", F.lit("insert")))
    return rollup.totals()


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity score of all documents; ``flagged`` uses the threshold of the language."""
    docs = table(spark, sf_dir, "documents")
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    scored = toxicity.score(docs.select("doc_id", "lang", "text"), model)
    return scored.select(
        "doc_id",
        held_out(),
        "score",
        (F.col("score") >= 0.5).cast("int").alias("predicted"),
        (F.col("score") >= toxicity.threshold(model)).alias("flagged"),
    )


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents packed into sequences of 1024 tokens."""
    return packing.pack_documents(table(spark, sf_dir, "documents"))


def queries() -> dict:
    found = (op1_license_scan, op2_subword_sampling, op3_knn_join, op4_jaccard_join, op5_token_rollup, op6_toxicity, op7_decision_list, op8_secret_scan, op9_pairwise_quality, op10_packing)
    return {f.__name__: f for f in found}


def oracle_sql() -> dict:
    return {"op3_knn_join": OP3_SQL}
