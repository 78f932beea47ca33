"""The workloads: pairs of relations over the given tables, as DataFrames and as SQL text."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.relations import Rel, normalize, self_rel


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@dataclass(frozen=True)
class Workload:
    """``build`` gives the Rel; ``left`` and ``right`` are the oracle's SELECTs of (lk, jk) and (jk, rk)."""

    name: str
    build: Callable[[SparkSession, str], Rel]
    left: str
    right: str


def _mirror(sql: str) -> str:
    return f"select jk, lk as rk from ({sql})"


def _self(name: str, rows: Callable[[SparkSession, str], DataFrame], keep: str, on: str, sql: str) -> Workload:
    return Workload(name, lambda s, d: self_rel(rows(s, d), keep, on), sql, _mirror(sql))


def lineitem(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "lineitem")


def order_lines(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "orders").join(table(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))


def tokens(df: DataFrame, key: str) -> DataFrame:
    """(key, word): lower-cased words between single spaces."""
    return df.select(key, F.explode(_words()).alias("word")).where("word <> ''")


def _words() -> Column:
    return F.split(F.lower("text"), " ")


def shared_words(df: DataFrame, key: str) -> Rel:
    """Keys that share a word, with the words of a row side by side."""
    words = F.array_remove(F.array_distinct(_words()), "")
    return replace(self_rel(tokens(df, key), key, "word"), rows=df.select(F.col(key).alias("lk"), words.alias("jk")))


def coordinates(df: DataFrame, cutoff: float = 0.15) -> DataFrame:
    """The sparse boolean matrix (vec_id, dim) of vector components above the cutoff."""
    return df.select("vec_id", F.posexplode("embedding").alias("dim", "v")).where(F.col("v").cast("double") > cutoff).select("vec_id", "dim")


def frequent(rows: DataFrame, item: str, basket: str, support: int) -> DataFrame:
    """Rows of items that are in at least ``support`` baskets."""
    counts = rows.groupBy(item).agg(F.count_distinct(basket).alias("n")).where(F.col("n") >= support)
    return rows.join(counts.select(item), item, "left_semi")


def links(df: DataFrame) -> DataFrame:
    return df.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("target"))


def hours(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "events").select("user_id", F.date_trunc("hour", "ts").alias("hour"))


_ORDER_PART = "select distinct l_partkey as lk, l_orderkey as jk from lineitem"
_ORDER_SUPP = "select distinct l_suppkey as lk, l_orderkey as jk from lineitem"
_CUST_PART = "select distinct o_custkey as lk, l_partkey as jk from orders join lineitem on o_orderkey = l_orderkey"
_WORDS = "select distinct {key} as lk, w as jk from (select {key}, unnest(string_split(lower(text), ' ')) as w from {table}) where w <> ''"
_DOC_WORDS = _WORDS.format(key="doc_id", table="documents")
_CELLS = "select vec_id, i - 1 as dim from (select vec_id, embedding, unnest(range(1, len(embedding) + 1)) as i from embeddings) where cast(embedding[i] as double) > 0.15"

WORKLOADS = {
    w.name: w
    for w in (
        _self("user_user_hour", hours, "user_id", "hour", "select distinct user_id as lk, date_trunc('hour', ts) as jk from events"),
        _self("user_user_minute", lambda s, d: table(s, d, "events").select("user_id", F.date_trunc("minute", "ts").alias("minute")), "user_id", "minute", "select distinct user_id as lk, date_trunc('minute', ts) as jk from events"),
        _self(
            "user_user_prop", lambda s, d: table(s, d, "events").select("user_id", F.get_json_object("props", "$.k").cast("long").alias("k")), "user_id", "k",
            "select distinct user_id as lk, cast(json_extract_string(props, '$.k') as bigint) as jk from events where json_extract_string(props, '$.k') is not null",
        ),
        _self("part_part_cust", order_lines, "l_partkey", "o_custkey", "select distinct l_partkey as lk, o_custkey as jk from orders join lineitem on o_orderkey = l_orderkey"),
        _self("cust_cust_part", order_lines, "o_custkey", "l_partkey", _CUST_PART),
        Workload(
            "supp_cust_order",
            lambda s, d: normalize(lineitem(s, d), table(s, d, "orders"), "l_suppkey", "o_custkey", ("l_orderkey", "o_orderkey")),
            _ORDER_SUPP,
            "select distinct o_orderkey as jk, o_custkey as rk from orders",
        ),
        Workload(
            "cust_type",
            lambda s, d: normalize(order_lines(s, d), table(s, d, "part"), "o_custkey", "p_type", ("l_partkey", "p_partkey")),
            _CUST_PART,
            "select distinct p_partkey as jk, p_type as rk from part",
        ),
        Workload(
            "cust_brand",
            lambda s, d: normalize(
                table(s, d, "orders"), lineitem(s, d).join(table(s, d, "part"), F.col("l_partkey") == F.col("p_partkey")), "o_custkey", "p_brand", ("o_orderkey", "l_orderkey")
            ),
            "select distinct o_custkey as lk, o_orderkey as jk from orders",
            "select distinct l_orderkey as jk, p_brand as rk from lineitem join part on l_partkey = p_partkey",
        ),
        _self(
            "freq_parts", lambda s, d: frequent(lineitem(s, d), "l_partkey", "l_orderkey", 30), "l_partkey", "l_orderkey",
            _ORDER_PART + " where l_partkey in (select l_partkey from lineitem group by 1 having count(distinct l_orderkey) >= 30)",
        ),
        _self("part_part_order", lineitem, "l_partkey", "l_orderkey", _ORDER_PART),
        _self("dim_dim", lambda s, d: coordinates(table(s, d, "embeddings")), "dim", "vec_id", f"select distinct dim as lk, vec_id as jk from ({_CELLS})"),
        _self("vec_vec", lambda s, d: coordinates(table(s, d, "embeddings")), "vec_id", "dim", f"select distinct vec_id as lk, dim as jk from ({_CELLS})"),
        _self("supp_supp_order", lineitem, "l_suppkey", "l_orderkey", _ORDER_SUPP),
        Workload("doc_doc_word", lambda s, d: shared_words(table(s, d, "documents"), "doc_id"), _DOC_WORDS, _mirror(_DOC_WORDS)),
        _self(
            "word_word_doc", lambda s, d: tokens(table(s, d, "documents"), "doc_id"), "word", "doc_id",
            f"select lk2 as lk, jk2 as jk from (select jk as lk2, lk as jk2 from ({_WORDS.format(key='doc_id', table='documents')}))",
        ),
        _self("conv_conv_word", lambda s, d: tokens(table(s, d, "conversations"), "conv_id"), "conv_id", "word", _WORDS.format(key="conv_id", table="conversations")),
        _self(
            "page_link", lambda s, d: links(table(s, d, "pages")), "page_id", "target",
            "select distinct page_id as lk, t as jk from (select page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as t from pages)",
        ),
    )
}

#: The keys under which the driver knows the workloads.
KEYS = {f"w_{'conv_conv' if n == 'conv_conv_word' else n}": n for n in WORKLOADS}
#: Workloads whose joined rows stay small enough for an exact count in tests.
SMALL = ("part_part_order", "cust_type", "freq_parts", "dim_dim", "supp_cust_order")
