"""Whole-table forms of the queries whose first forms take an id subset.

The first forms and their SQL stay as they were; these have no modulo filter.
Dangling tuples come from predicates of an outer join's condition, which drop
no row, or from key ranges that differ, and set operands from two tables.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import sqlfuncs
from ..operators import joins
from ..operators.relations import drop_dangling, normalize
from ..operators.sampling import sample_side, sample_threshold
from ..sources.sketches import scratch
from . import oracle as O
from .registry import register
from .relational import PPO, _cyclic_frames, over_sql, rel
from .workloads import table

RATE, SEED = 0.1, "SL1:"

for how in ("left", "right", "full"):
    over_sql(f"join_{how}_whole", f"select c_custkey, o_orderkey from customer {how} join orders on c_custkey = o_custkey and c_acctbal > 0 and o_orderstatus = 'F'", "customer", "orders")


#: Parts of a price on average from which they meet as lists, parts of a list at most, and bits of the row numbers that are listed together.
REPEATED, LISTED, TOGETHER = 8, 256, 20


def join_theta_whole(s: SparkSession, d: str) -> DataFrame:
    """Prices less than 1 apart have equal or adjacent whole parts: an equi-join, not a product.

    Where prices repeat, a price is compared once for a list of its parts, and
    pairs of lists are dealt evenly before they give their rows.
    """
    part = table(s, d, "part")
    whole = F.floor("p_retailprice")
    repeated = part.count() >= REPEATED * part.select("p_retailprice").distinct().count()
    key = F.col("p_partkey")
    if repeated:
        # Lists hold structs, as a null alone would not be listed.
        block = F.shiftright(F.monotonically_increasing_id(), TOGETHER).alias("block")
        lists = part.groupBy("p_retailprice", block).agg(F.collect_list(F.struct("p_partkey")).alias("parts"))
        cuts = F.sequence(F.lit(1), F.size("parts"), F.lit(LISTED))
        part, key = lists.select("p_retailprice", "parts", F.explode(cuts).alias("at")), F.slice(F.col("parts.p_partkey"), F.col("at"), LISTED)
    a = part.select(key.alias("a"), F.col("p_retailprice").alias("x"), whole.alias("cell"))
    b = part.select(key.alias("b"), F.col("p_retailprice").alias("y"), F.explode(F.sequence(whole - 1, whole)).alias("cell"))
    pairs = a.join(b, "cell").where("x < y and x > y - 1").select("a", "b")
    if repeated:
        tasks = max(4 * s.sparkContext.defaultParallelism, int(s.conf.get("spark.sql.shuffle.partitions")))
        pairs = pairs.repartition(tasks).select(F.explode("a").alias("a"), "b").select("a", F.explode("b").alias("b"))
    return pairs


register("join_theta_whole", join_theta_whole, "select a.p_partkey as a, b.p_partkey as b from part a join part b on a.p_retailprice < b.p_retailprice and a.p_retailprice > b.p_retailprice - 1")


def join_range_whole(s: SparkSession, d: str) -> DataFrame:
    epoch = F.lit("1970-01-01").cast("date")
    # Ships are counted by day first: an order meets two rows at most, not every line of two days.
    ships = table(s, d, "lineitem").groupBy(F.datediff("l_shipdate", epoch).cast("long").alias("ship")).agg(F.count("*").alias("lines"))
    dates = table(s, d, "orders").select("o_orderkey", F.datediff("o_orderdate", epoch).cast("long").alias("day"))
    return joins.band_join(ships, dates, "ship", "day", 0, 1).groupBy("o_orderkey").agg(F.sum("lines").alias("n"))


register(
    "join_range_whole", join_range_whole,
    "select o_orderkey, cast(sum(n) as bigint) as n from orders join (select l_shipdate::date as ship, count(*) as n from lineitem group by 1) on date_diff('day', o_orderdate::date, ship) between 0 and 1 group by 1",
)

for key, word in (("set_union_all", "union all"), ("set_union", "union"), ("set_intersect", "intersect"), ("set_except", "except"), ("set_intersect_all", "intersect all"), ("set_except_all", "except all")):
    over_sql(f"{key}_whole", f"select l_partkey as k from lineitem {word} select o_custkey as k from orders", "lineitem", "orders")


def fn_sp_hits_whole(s: SparkSession, d: str) -> DataFrame:
    sqlfuncs.register_functions(s)
    left, right = _cyclic_frames(s, d)
    a, b = (x.groupBy("jk").agg(F.collect_list(c).alias(f"{c}s")) for x, c in ((left, "x"), (right, "y")))
    a.join(b, "jk").createOrReplaceTempView("sp_groups_whole")
    return s.sql(f"select jk, h.x_h, h.y_h from sp_groups_whole, lateral sp_hits(xs, ys, {2**56}) h")


register(
    "fn_sp_hits_whole", fn_sp_hits_whole,
    f"with {O.sides(PPO)} select jk, x_h, y_h from (select jk, {O.digest(chr(39) + 'L1:' + chr(39), 'lk')} as x_h from l) join (select jk, {O.digest(chr(39) + 'R1:' + chr(39), 'rk')} as y_h from r) using (jk) where ((x_h - y_h) & {O.MASK}) < {2**56}",
)


def sink_sketch_whole(s: SparkSession, d: str) -> DataFrame:
    """The hash sample of the whole left side by rate and seed, written and read again."""
    path = scratch(s, "sink")
    sample_side(rel(s, d).left, "lk", RATE, SEED, "md5_60").write.parquet(path)
    return s.read.parquet(path).agg(F.count("*").alias("n"), F.sum("jk").alias("total"))


register(
    "sink_sketch_whole", sink_sketch_whole,
    f"with {O.sides(PPO)} select count(*) as n, cast(sum(jk) as bigint) as total from l where {O.digest(chr(39) + SEED + chr(39), 'lk')} < {sample_threshold(RATE, 'md5_60')}",
)


def m_dangling_whole(s: SparkSession, d: str) -> DataFrame:
    """Sizes 1 to 50 against nation keys 0 to 24: both whole tables have tuples without a partner."""
    out = drop_dangling(normalize(table(s, d, "part"), table(s, d, "nation"), "p_partkey", "n_name", ("p_size", "n_nationkey")))
    return out.left.agg(F.count("*").alias("n_left")).crossJoin(out.right.agg(F.count("*").alias("n_right")))


register(
    "m_dangling_whole", m_dangling_whole,
    """with l as (select distinct p_partkey as lk, p_size as jk from part), r as (select distinct n_nationkey as jk, n_name as rk from nation)
    select (select count(*) from l where jk in (select jk from r)) as n_left, (select count(*) from r where jk in (select jk from l)) as n_right""",
)
