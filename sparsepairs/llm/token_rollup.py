"""Token counts: rollups by source, language and tokenizer, kept by signed deltas.

A batch of changes (insert, delete, revise) becomes signed contributions of
single documents and their sums by group.  Both are written under the batch's
name, and a commit record is written last.  Totals add up the sums of committed
batches.  A batch that is delivered again after its commit changes nothing;
one that failed before it is written anew, so any number of retries is safe.
After every ``COMPACTED`` commits the state is written as one table of current
contributions and one of totals, so a commit reads the documents that are
there and few batches, not the history.

Defined cases: a null count is 0; null source or language is a group of its
own; rows without an id are inserted one by one, and as nothing names them
revisions and deletions without an id change nothing; of several changes to a document and tokenizer in one batch the last by
``op``, then count, holds; deleting or revising what isn't there adds nothing
or the new count; empty batches commit and change nothing.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import shared
from .batches import fields, sliced, spark_schema
from .tokens import encoder

GROUP = ("source", "lang", "tokenizer")
CONTRIBUTION = "doc_id long, source string, lang string, tokenizer string, docs long, tokens long"
DELTA = "source string, lang string, tokenizer string, docs long, tokens long"
#: Commits after which the state is written as one.
COMPACTED = 8
COUNTS = fields(doc_id=pa.int64(), source=pa.string(), lang=pa.string(), n_tokens=pa.int64())


def token_counts(docs: DataFrame, tokenizer_folder: str | None = None) -> DataFrame:
    """doc_id, source, lang and the tokens of each whole text (null: 0)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(tokenizer_folder).ids
        for batch in sliced(batches, "text"):
            n = [len(encode(x)) if x else 0 for x in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(n, pa.int64())], schema=COUNTS)

    own = docs.select(F.col("doc_id").cast("long"), F.col("source").cast("string"), F.col("lang").cast("string"), "text")
    return own.mapInArrow(run, spark_schema(COUNTS))


class TokenRollup:
    """A rollup that lives under one path of the shared folder."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def _done(self, folder: str) -> list[str]:
        """Names below a folder that were written to the end."""
        path = self.spark._jvm.org.apache.hadoop.fs.Path
        at = path(f"{self.path}/{folder}")
        fs = at.getFileSystem(self.spark._jsparkSession.sessionState().newHadoopConf())
        if not fs.exists(at):
            return []
        return sorted(x.getPath().getName() for x in fs.listStatus(at) if fs.exists(path(x.getPath(), "_SUCCESS")))

    def batches(self) -> list[str]:
        """The names of committed batches; there is one for each delivery, not for each document."""
        return self._done("commits")

    def _state(self) -> tuple[str | None, list[str]]:
        """The last compacted state and the batches that came after it."""
        names, states = self.batches(), self._done("states")
        if not states:
            return None, names
        held = {r["batch"] for r in self.spark.read.schema("batch string").parquet(f"{self.path}/states/{states[-1]}").collect()}
        return states[-1], [n for n in names if n not in held]

    def _read(self, kind: str, schema: str) -> DataFrame:
        """The rows of the compacted state and of the batches committed after it."""
        state, names = self._state()
        paths = ([f"{self.path}/compacted/{state}/{kind}"] if state else []) + [f"{self.path}/{kind}/{name}" for name in names]
        return self.spark.read.schema(schema).parquet(*paths) if paths else self.spark.createDataFrame([], schema)

    def compact(self) -> None:
        """Writes current contributions and totals as one state; readers take it once its list of batches is there."""
        names = self.batches()
        state = f"{len(names):012d}"
        there = self._read("contributions", CONTRIBUTION)
        none = there.where(F.col("doc_id").isNull())
        known = there.where(F.col("doc_id").isNotNull()).groupBy("doc_id", *GROUP).agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens")).where("docs != 0 or tokens != 0")
        known.unionByName(none).write.mode("overwrite").parquet(f"{self.path}/compacted/{state}/contributions")
        sums = self._read("deltas", DELTA).groupBy(*GROUP).agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens"))
        sums.coalesce(1).write.mode("overwrite").parquet(f"{self.path}/compacted/{state}/deltas")
        self.spark.createDataFrame([(n,) for n in names], "batch string").coalesce(1).write.mode("overwrite").parquet(f"{self.path}/states/{state}")

    def commit(self, batch: str, changes: DataFrame) -> bool:
        """Applies changes (op, doc_id, source, lang, tokenizer, n_tokens) once; False if the batch was there."""
        if batch in self.batches():
            return False
        own = Window.partitionBy("doc_id", "tokenizer").orderBy(F.desc("op"), F.desc("n_tokens"), F.desc("source"), F.desc("lang"))
        changes = changes.where(F.col("op").isin("insert", "delete", "revise"))
        nameless = changes.where(F.col("doc_id").isNull() & (F.col("op") == "insert"))
        changes = changes.where(F.col("doc_id").isNotNull()).withColumn("__k", F.row_number().over(own)).where("__k = 1").drop("__k")
        count = F.coalesce(F.col("n_tokens"), F.lit(0)).cast("long").alias("tokens")
        plus = changes.where(F.col("op") != "delete").unionByName(nameless).select("doc_id", *GROUP, F.lit(1).cast("long").alias("docs"), count)
        touched = changes.select(F.col("doc_id").alias("__d"), F.col("tokenizer").alias("__t"))
        held = self._read("contributions", CONTRIBUTION)
        held = held.join(touched, (F.col("doc_id") == F.col("__d")) & F.col("tokenizer").eqNullSafe(F.col("__t")), "left_semi")
        minus = held.groupBy("doc_id", *GROUP).agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens"))
        minus = minus.where("docs != 0 or tokens != 0").select("doc_id", *GROUP, (-F.col("docs")).alias("docs"), (-F.col("tokens")).alias("tokens"))
        plus.unionByName(minus).write.mode("overwrite").parquet(f"{self.path}/contributions/{batch}")
        made = self.spark.read.schema(CONTRIBUTION).parquet(f"{self.path}/contributions/{batch}")
        sums = made.groupBy(*GROUP).agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens"))
        sums.coalesce(1).write.mode("overwrite").parquet(f"{self.path}/deltas/{batch}")
        self.spark.createDataFrame([(batch,)], "batch string").coalesce(1).write.mode("overwrite").parquet(f"{self.path}/commits/{batch}")
        if len(self._state()[1]) >= COMPACTED:
            self.compact()
        return True

    def totals(self) -> DataFrame:
        """source, lang, tokenizer, n_docs, n_tokens over all committed batches."""
        sums = self._read("deltas", DELTA).groupBy(*GROUP).agg(F.sum("docs").alias("n_docs"), F.sum("tokens").alias("n_tokens"))
        return sums.where("n_docs != 0 or n_tokens != 0")
