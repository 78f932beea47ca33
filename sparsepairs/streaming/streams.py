"""Structured Streaming forms: samples, running estimates, windows, and windowed sizes."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from ..functions.hashing import FAMILIES, MD5_60
from ..operators.estimate import Spec, finish, k_smallest, kept_set, walk_group
from ..operators.relations import Rel
from ..operators.sampling import sample_side
from ..sources.sketches import scratch

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, path: str) -> DataFrame:
    """The event files as a stream; ``ts`` becomes a timestamp, which watermarks need."""
    return spark.readStream.schema(EVENTS).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def spread(spark: SparkSession, path: str, files: int = 4) -> str:
    """The events as several files in a scratch folder, so that a stream has several batches."""
    out = scratch(spark, "events")
    spark.read.parquet(path).repartitionByRange(files, "ts").sortWithinPartitions("ts").write.parquet(out)
    return out


def drain(stream: DataFrame, name: str, mode: str = "append", each=None) -> DataFrame:
    """Runs a stream over what is there; the rows it wrote, or None where ``each`` takes the batches."""
    spark = stream.sparkSession
    writer = stream.writeStream.trigger(availableNow=True).option("checkpointLocation", scratch(spark, f"{name}-state"))
    if each is not None:
        query = writer.foreachBatch(each).start()
        query.awaitTermination()
        return None
    out = scratch(spark, name)
    query = writer.outputMode(mode).format("parquet").option("path", out).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def stream_sample(stream: DataFrame, role: str, p: float, seed: str, family: str = "md5_60") -> DataFrame:
    """The sample of a stream's tuples: a stateless filter; replays are harmless after distinct."""
    return sample_side(stream, role, p, seed, family)


def windowed_counts(stream: DataFrame, width: str, slide: str | None = None, late: str = "1 day") -> DataFrame:
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return stream.withWatermark("ts", late).groupBy(window.alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def session_counts(stream: DataFrame, gap: str, late: str = "1 day") -> DataFrame:
    session = F.session_window("ts", gap).alias("w")
    return stream.withWatermark("ts", late).groupBy("user_id", session).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def stream_join(a: DataFrame, b: DataFrame, within: str, late: str = "1 day") -> DataFrame:
    """Events of b at most ``within`` after an event of a by the same user; state is bounded by the time range."""
    left = a.withWatermark("ts", late).select(F.col("event_id").alias("a_id"), F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts"))
    right = b.withWatermark("ts", late).select(F.col("event_id").alias("b_id"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"))
    return left.join(right, F.expr(f"a_user = b_user and b_ts >= a_ts and b_ts <= a_ts + interval {within}")).select("a_id", "b_id")


class RunningEstimate:
    """A kept set that new rows extend: each batch joins the rows stored so far, in both roles.

    Rows and kept set of a batch are written under its number, the kept set
    last.  The newest number with a whole kept set is the version, also for
    an object made after a restart, so a batch that comes again finds its
    result and does nothing, and one that broke off is written anew.
    """

    def __init__(self, spark: SparkSession, path: str, spec: Spec, p: float):
        self.spark, self.path, self.spec, self.p = spark, path, spec, p
        self.numbers = self._stored()

    def _stored(self) -> list[int]:
        path = self.spark._jvm.org.apache.hadoop.fs.Path
        at = path(f"{self.path}/kept")
        fs = at.getFileSystem(self.spark._jsparkSession.sessionState().newHadoopConf())
        found = [x.getPath() for x in fs.listStatus(at)] if fs.exists(at) else []
        return sorted(int(x.getName()) for x in found if fs.exists(path(x, "_SUCCESS")))

    @property
    def version(self) -> int:
        return self.numbers[-1] if self.numbers else -1

    def add(self, rows: DataFrame, batch: int) -> None:
        """``rows`` are (keep, on) of a self-join."""
        if batch <= self.version:
            return
        rows.select(F.col("keep").alias("lk"), F.col("on").alias("jk")).distinct().write.mode("overwrite").parquet(f"{self.path}/rows/{batch}")
        new = self.spark.read.parquet(f"{self.path}/rows/{batch}")
        mirror = lambda df: df.select("jk", F.col("lk").alias("rk"))
        # Each task of the scan gives k pairs at most, and only those below the stored k-th are looked at.
        spec, p = replace(self.spec, strategy="sweep", tighten="local"), self.p
        if not self.numbers:
            found = kept_set(Rel(new, mirror(new)), spec, p)
        else:
            old = self.spark.read.parquet(*[f"{self.path}/rows/{n}" for n in self.numbers])
            kept = self.spark.read.parquet(f"{self.path}/kept/{self.version}")
            last = kept.agg(F.count("*").alias("n"), F.max("pair_h").alias("h")).first()
            if last["n"] >= spec.k:
                p = min(p, (last["h"] + 1) / FAMILIES[spec.family].domain * (1 + 1e-12))
            found = kept_set(Rel(new, mirror(old.unionByName(new))), spec, p).unionByName(kept_set(Rel(old, mirror(new)), spec, p)).unionByName(kept)
        k_smallest(found, self.spec.k).write.mode("overwrite").parquet(f"{self.path}/kept/{batch}")
        self.numbers.append(batch)

    def result(self) -> DataFrame:
        return finish(self.spark.read.parquet(f"{self.path}/kept/{self.version}"), self.spec, self.p)


class WindowPairs(StatefulProcessor):
    """Per day: the k smallest hashes of distinct user pairs that share a minute.

    State is k hashes and the users of minutes that may still grow; a timer at
    the day's end emits the estimate once and clears both.
    """

    def __init__(self, k: int, delay_ms: int = 86_400_000):
        self.k, self.delay = k, delay_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.minutes = handle.getMapState("minutes", "minute long", "users array<long>")
        self.kept = handle.getValueState("kept", "hashes array<long>")

    @staticmethod
    def _digest(side: str, users: list[int]) -> np.ndarray:
        import hashlib

        return np.array([int(hashlib.md5(f"{side}1:{u}".encode()).hexdigest()[:15], 16) for u in users], np.int64)

    def handleInputRows(self, key, rows, timerValues):  # noqa: N802, N803
        kept = set(self.kept.get()[0] or []) if self.kept.exists() else set()
        for pdf in rows:
            for minute, users in pdf.groupby("minute")["user_id"]:
                old = list(self.minutes.getValue((int(minute),))[0]) if self.minutes.containsKey((int(minute),)) else []
                new = sorted(set(users.tolist()) - set(old))
                if not new:
                    continue
                # New pairs only: those with a new user on either side, and below the k-th hash so far.
                every, t = old + new, max(kept) + 1 if len(kept) >= self.k else 2**60
                for left, right in ((every, new), (new, old)):
                    x, y, _, _ = walk_group(self._digest("L", left), self._digest("R", right), t, 2**60)
                    kept |= set(((x - y) & (2**60 - 1)).tolist())
                kept = set(sorted(kept)[: self.k])
                self.minutes.updateValue((int(minute),), (every,))
        self.kept.update((sorted(kept),))
        self.handle.registerTimer((int(key[0]) + 1) * 86_400_000)
        return iter(())

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo):  # noqa: N802, N803
        kept = list(self.kept.get()[0] or []) if self.kept.exists() else []
        full = len(kept) >= self.k
        size = self.k * float(2**60) / max(kept[-1], 1) if full else float(len(kept))
        self.kept.clear()
        self.minutes.clear()
        yield pd.DataFrame({"day": [int(key[0])], "kept": [len(kept)], "z_hat": [size]})

    def close(self) -> None:
        pass


def stream_windowed_size(stream: DataFrame, k: int, late: str = "1 hour") -> DataFrame:
    """(day, kept, z_hat) for each closed day."""
    rows = stream.withWatermark("ts", late).select(F.expr("cast(unix_millis(ts) div 86400000 as long)").alias("day"), F.expr("cast(unix_millis(ts) div 60000 as long)").alias("minute"), "user_id", "ts")
    return rows.groupBy("day").transformWithStateInPandas(WindowPairs(k), "day long, kept long, z_hat double", "Append", "EventTime")


def batch_windowed_size(rows: DataFrame, k: int) -> DataFrame:
    """The same of a table."""
    from pyspark.sql import Window

    r = rows.select(F.expr("cast(unix_millis(cast(ts as timestamp)) div 86400000 as long)").alias("day"), F.expr("cast(unix_millis(cast(ts as timestamp)) div 60000 as long)").alias("minute"), "user_id").distinct()
    a = r.select("day", "minute", "user_id", MD5_60.hash(F.col("user_id"), "L1:").alias("x"))
    b = r.select("day", "minute", MD5_60.hash(F.col("user_id"), "R1:").alias("y"))
    h = a.join(b, ["day", "minute"]).select("day", (F.col("x") - F.col("y")).bitwiseAND(F.lit(2**60 - 1)).alias("h")).distinct()
    kept = h.withColumn("i", F.row_number().over(Window.partitionBy("day").orderBy("h"))).where(F.col("i") <= k)
    one = kept.groupBy("day").agg(F.count("*").alias("kept"), F.max("h").alias("kth"))
    return one.select("day", "kept", F.when(F.col("kept") >= k, F.lit(k * float(2**60)) / F.greatest("kth", F.lit(1)).cast("double")).otherwise(F.col("kept").cast("double")).alias("z_hat"))
