"""Statistics of whole texts by DataFrame functions only.

A null text counts as empty: every count is then 0.  Words are runs of
characters other than space and U+0009..U+000D.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_SPACE = "[\\x20\\x09-\\x0D]+"
_P = "__stats_"

#: The counts that ``with_stats`` adds.
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_capitals", "n_marks", "n_bars")

#: The ratios that classifiers and rules look at.
FEATURES = ("log_words", "word_length", "symbol_share", "bar_share", "mark_share", "capital_share", "dup_line_share", "repeat_share")


def _repeat_words(windows: str, ranked: str) -> Column:
    """Words inside three-word windows that occur twice or more: places of equal neighbours in hash order, merged."""
    same = lambda e, i: (
        F.get(ranked, i - 1)["h"].eqNullSafe(e["h"]) | F.get(ranked, i + 1)["h"].eqNullSafe(e["h"])
    )
    places = F.sort_array(F.filter(F.transform(ranked, lambda e, i: F.when(same(e, i), e["i"])), lambda p: p.isNotNull()))
    start = F.struct(F.lit(-3).alias("last"), F.lit(0).alias("n"))
    step = lambda acc, p: F.struct(p.alias("last"), (acc["n"] + F.least(F.lit(3), p - acc["last"])).alias("n"))
    return F.when(F.col(ranked).isNull(), 0).otherwise(F.aggregate(places, start, step, lambda acc: acc["n"]))


def with_stats(docs: DataFrame, text: str = "text") -> DataFrame:
    """``docs`` with the columns of ``COUNTS``; columns of those names are replaced."""
    whole, words, lines, windows, ranked = (_P + x for x in ("text", "words", "lines", "windows", "ranked"))
    out = docs.withColumn(whole, F.coalesce(F.col(text), F.lit("")))
    out = out.withColumns(
        {
            words: F.array_remove(F.split(whole, _SPACE), ""),
            lines: F.filter(F.split(whole, "\n"), lambda x: x.rlike("[^\\x20\\x09-\\x0D]")),
        }
    )
    hashed = F.transform(words, lambda w, i: F.xxhash64(w, F.get(words, i + 1), F.get(words, i + 2)))
    out = out.withColumn(windows, F.slice(hashed, F.lit(1), F.greatest(F.size(words) - 2, F.lit(0))))
    pairs = F.transform(windows, lambda h, i: F.struct(h.alias("h"), i.alias("i")))
    some = F.size(F.array_distinct(windows)) < F.size(windows)
    out = out.withColumn(ranked, F.when(some, F.sort_array(pairs)))
    counts = (
        {
            "n_words": F.size(words).cast("long"),
            "word_chars": F.length(F.array_join(words, "")).cast("long"),
            "n_symbols": F.regexp_count(whole, F.lit("[#*$%&|<>]")).cast("long"),
            "n_lines": F.size(lines).cast("long"),
            "n_dup_lines": (F.size(lines) - F.size(F.array_distinct(lines))).cast("long"),
            "n_repeat_words": _repeat_words(windows, ranked).cast("long"),
            "n_capitals": F.regexp_count(whole, F.lit("\\p{Lu}")).cast("long"),
            "n_marks": F.regexp_count(whole, F.lit("!")).cast("long"),
            "n_bars": F.regexp_count(whole, F.lit("\\|")).cast("long"),
        }
    )
    # Filters over the counts stop at the generator; pushed below it they would compute every count again for each use.
    once = F.explode(F.array(F.struct(*[c.alias(k) for k, c in counts.items()]))).alias(_P + "counts")
    kept = [c for c in docs.columns if c not in counts]
    out = out.select(*[F.col(f"`{c}`") for c in kept], once)
    return out.select(*[F.col(f"`{c}`") for c in kept], *[F.col(_P + "counts")[k].alias(k) for k in counts])


def features() -> dict[str, Column]:
    """The ratios of ``FEATURES`` over the counts."""
    part = lambda a, b: F.col(a) / F.greatest(F.col(b), F.lit(1))
    return {
        "log_words": F.log1p(F.col("n_words")),
        "word_length": part("word_chars", "n_words"),
        "symbol_share": part("n_symbols", "n_words"),
        "bar_share": part("n_bars", "n_words"),
        "mark_share": part("n_marks", "n_words"),
        "capital_share": part("n_capitals", "word_chars"),
        "dup_line_share": part("n_dup_lines", "n_lines"),
        "repeat_share": part("n_repeat_words", "n_words"),
    }


def fold(doc_id: str = "doc_id") -> Column:
    """crc32 of the id as text, modulo 5; fold 0 is held out."""
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5


def labelled(docs: DataFrame, labels: DataFrame, label: str, most: int, columns: list[str]) -> DataFrame:
    """At most ``most`` rows of ``columns`` with their 0/1 ``label``, none of fold 0.

    The sample is the smallest hashes of the labelled ids, so it is the same
    for any partitioning, and its bound is what may be broadcast and collected.
    """
    known = labels.where(F.col(label).isin(0, 1) & (fold() != 0)).groupBy("doc_id").agg(F.max(label).cast("int").alias(_P + "label"))
    known = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most).withColumnRenamed("doc_id", _P + "id")
    picked = docs.select("doc_id", *columns).join(F.broadcast(known), F.col("doc_id") == F.col(_P + "id"))
    return picked.select("doc_id", *columns, F.col(_P + "label").alias(label))
