"""Queries of the relational operators round the methods, with oracles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import sqlfuncs
from ..functions.hashing import AFFINE61, MD5_60, affine61_udf
from ..operators import joins
from ..operators.baselines import join_project
from ..operators.estimate import Spec
from ..operators.relations import Rel, group_sizes, work
from ..sources import readers
from ..sources.sketches import scratch
from . import oracle as O
from .registry import register
from .workloads import WORKLOADS, table

PPO = "part_part_order"


def rel(s, d, n=PPO) -> Rel:
    return WORKLOADS[n].build(s, d)


def simple(key: str, name: str, build, sql: str | None) -> None:
    """A query over one table."""
    register(key, lambda s, d: build(table(s, d, name)), sql)


def over_sql(key: str, sql: str, *tables: str) -> None:
    """A query as SQL text over temporary views; DuckDB runs the same text."""

    def run(s: SparkSession, d: str) -> DataFrame:
        return _views(s, d, tables).sql(sql)

    register(key, run, sql)


def _views(s: SparkSession, d: str, tables) -> SparkSession:
    for n in tables:
        table(s, d, n).createOrReplaceTempView(n)
    return s


# ---- scans, sources, sinks
register("scan_parquet", lambda s, d: readers.read_relation(s, f"{d}/lineitem.parquet", "l_partkey", "l_orderkey", "l_quantity > 45"), "select l_partkey, l_orderkey from lineitem where l_quantity > 45")
simple("scan_baskets", "documents", lambda x: readers.read_baskets(x, "doc_id", "text").groupBy("bag").agg(F.count("*").alias("items"), F.count_distinct("item").alias("kinds")), "select doc_id as bag, count(*) as items, count(distinct w) as kinds from (select doc_id, unnest(string_split(lower(text), ' ')) as w from documents) where w <> '' group by doc_id")
simple("scan_coords", "embeddings", lambda x: readers.to_coordinates(x, "vec_id", "embedding", 0.15), "select vec_id as row, i - 1 as col from (select vec_id, embedding, unnest(range(1, len(embedding) + 1)) as i from embeddings) where cast(embedding[i] as double) > 0.15")


def _edges(fmt: str):
    def run(s, d):
        path = scratch(s, f"edges-{fmt}")
        table(s, d, "orders").select(F.col("o_custkey").alias("src"), F.col("o_orderkey").alias("dst")).write.format(fmt).save(path)
        return readers.read_edges(s, path, fmt, "src long, dst long")

    return run


register("scan_csv_edges", _edges("csv"), "select o_custkey as src, o_orderkey as dst from orders")
register("scan_jsonl", _edges("json"), "select o_custkey as src, o_orderkey as dst from orders")


def scan_blocks(s, d):
    """The pairs of (size, type) that brands give: each brand is a rectangle of its sizes and its types, and brands share both."""
    left, right = readers.table_blocks(table(s, d, "part"), "p_brand", "p_size", "p_type")
    return join_project(Rel(left, right)).agg(F.count("*").alias("z"))


register("scan_blocks", scan_blocks, "select count(*) as z from (select distinct a.p_size, b.p_type from (select distinct p_brand, p_size from part) a join (select distinct p_brand, p_type from part) b using (p_brand))")


def sink_sketch(s, d):
    path = scratch(s, "sink")
    rel(s, d).left.where("lk % 7 = 0").write.parquet(path)
    return s.read.parquet(path).agg(F.count("*").alias("n"), F.sum("jk").alias("total"))


register("sink_sketch", sink_sketch, "select count(*) as n, cast(sum(l_orderkey) as bigint) as total from (select distinct l_partkey, l_orderkey from lineitem where l_partkey % 7 = 0)")


def sink_bucketed(s, d):
    name = f"clustered_{abs(hash(d)) % 10**6}"
    readers.save_clustered(rel(s, d), name, 8)
    return s.table(f"{name}_left").join(s.table(f"{name}_right"), "jk").agg(F.count("*").alias("joined"))


register("sink_bucketed", sink_bucketed)

# ---- projection, filter, predicate
simple("op_project", "orders", lambda x: x.select(F.col("o_orderkey").alias("jk"), F.struct("o_custkey", "o_orderstatus").alias("k")).select("jk", "k.o_custkey", "k.o_orderstatus"), "select o_orderkey as jk, o_custkey, o_orderstatus from orders")
simple("op_fingerprint", "part", lambda x: x.select("p_partkey", MD5_60.hash(F.col("p_brand"), "L1:").alias("h")), f"select p_partkey, {O.digest(chr(39) + 'L1:' + chr(39), 'p_brand')} as h from part")
simple("op_filter_join_value", "lineitem", lambda x: x.where("l_orderkey = 7").select("l_partkey").distinct(), "select distinct l_partkey from lineitem where l_orderkey = 7")
simple("op_filter_hash_range", "part", lambda x: x.where(MD5_60.hash(F.col("p_partkey"), "S:") < 2**57).select("p_partkey"), f"select p_partkey from part where {O.digest(chr(39) + 'S:' + chr(39), 'p_partkey')} < {2**57}")
over_sql("op_filter_compound", "select p_partkey from part where p_size between 5 and 20 and p_brand in ('Brand#11', 'Brand#12', 'Brand#13', 'Brand#1') or p_type like 'S%' and p_name is not null and p_brand is not distinct from p_brand", "part")
over_sql("op_case", "select o_orderkey, case when o_totalprice > 100000 then 'high' when o_totalprice > 50000 then 'mid' else 'low' end as band from orders", "orders")
simple("op_distinct", "lineitem", lambda x: x.select("l_partkey", "l_suppkey").distinct(), "select distinct l_partkey, l_suppkey from lineitem")
simple("op_dedupe_keep_first", "orders", lambda x: joins.keep_first(x.select("o_custkey", "o_orderkey", "o_totalprice"), ["o_custkey"], ["o_orderkey"]), "select o_custkey, o_orderkey, o_totalprice from (select *, row_number() over (partition by o_custkey order by o_orderkey) as i from orders) where i = 1")

# ---- joins


def _hinted(hint: str, right: str, lk: str, rk: str):
    return lambda s, d: table(s, d, "lineitem").join(table(s, d, right).hint(hint), F.col(lk) == F.col(rk)).groupBy(lk).agg(F.count("*").alias("n"))


register("join_inner_broadcast", _hinted("broadcast", "part", "l_partkey", "p_partkey"), "select l_partkey, count(*) as n from lineitem join part on l_partkey = p_partkey group by 1")
for key, hint in (("join_inner_shuffle_hash", "shuffle_hash"), ("join_inner_merge", "merge")):
    register(key, _hinted(hint, "orders", "l_orderkey", "o_orderkey"), "select l_orderkey, count(*) as n from lineitem join orders on l_orderkey = o_orderkey group by 1")
for key, how in (("join_left", "left"), ("join_right", "right"), ("join_full", "full")):
    register(
        key,
        lambda s, d, how=how: table(s, d, "customer").where("c_custkey % 2 = 0").join(table(s, d, "orders").where("o_orderkey % 3 = 0"), F.col("c_custkey") == F.col("o_custkey"), how).select("c_custkey", "o_orderkey"),
        f"select c_custkey, o_orderkey from (select * from customer where c_custkey % 2 = 0) c {how} join (select * from orders where o_orderkey % 3 = 0) o on c_custkey = o_custkey",
    )
register("join_semi", lambda s, d: table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"), "select c_custkey from customer where c_custkey in (select o_custkey from orders)")
register("join_anti", lambda s, d: table(s, d, "documents").join(table(s, d, "labels"), "doc_id", "left_anti").select("doc_id"), "select doc_id from documents where doc_id not in (select doc_id from labels)")
over_sql("join_null_safe", "select a.k as a, b.k as b, a.n * b.n as joined from (select nullif(o_orderstatus, 'F') as k, count(*) as n from orders group by 1) a join (select nullif(l_linestatus, 'F') as k, count(*) as n from lineitem group by 1) b on a.k is not distinct from b.k", "orders", "lineitem")
register("join_multi_key", lambda s, d: table(s, d, "lineitem").alias("a").join(table(s, d, "lineitem").alias("b"), ["l_orderkey", "l_linenumber"]).agg(F.count("*").alias("n")), "select count(*) as n from lineitem a join lineitem b using (l_orderkey, l_linenumber)")
register("join_self", lambda s, d: rel(s, d).left.join(rel(s, d).right, "jk").agg(F.count("*").alias("joined")), f"with {O.sides(PPO)} select count(*) as joined from l join r using (jk)")
register("join_project_distinct", lambda s, d: join_project(rel(s, d, "cust_type")), f"with {O.sides('cust_type')} select distinct lk, rk from l join r using (jk)")
over_sql("join_theta", "select a.p_partkey as a, b.p_partkey as b from part a join part b on a.p_retailprice < b.p_retailprice and a.p_retailprice > b.p_retailprice - 1 where a.p_partkey % 10 = 0 and b.p_partkey % 10 = 1", "part")
over_sql("join_cross", "select n_name, r_name from nation cross join region", "nation", "region")


def _cyclic_frames(s, d):
    r = rel(s, d)
    return r.left.select("jk", MD5_60.hash(F.col("lk"), "L1:").alias("x")), r.right.select("jk", MD5_60.hash(F.col("rk"), "R1:").alias("y"))


register(
    "join_cells", lambda s, d: joins.cyclic_join(*_cyclic_frames(s, d), "x", "y", 2**52, 2**60, ["jk"]).select("jk", "x", "y"),
    f"with {O.sides(PPO)} select jk, x, y from (select jk, {O.digest(chr(39) + 'L1:' + chr(39), 'lk')} as x from l) join (select jk, {O.digest(chr(39) + 'R1:' + chr(39), 'rk')} as y from r) using (jk) where ((x - y) & {2**60 - 1}) < {2**52}",
)


def join_range(s, d):
    epoch = F.lit("1970-01-01").cast("date")
    ships = table(s, d, "lineitem").select("l_orderkey", F.datediff("l_shipdate", epoch).cast("long").alias("ship"))
    dates = table(s, d, "orders").where("o_orderkey % 50 = 0").select("o_orderkey", F.datediff("o_orderdate", epoch).cast("long").alias("day"))
    return joins.band_join(ships, dates, "ship", "day", 0, 1).groupBy("o_orderkey").agg(F.count("*").alias("n"))


register("join_range", join_range, "select o_orderkey, count(*) as n from lineitem join orders on date_diff('day', o_orderdate::date, l_shipdate::date) between 0 and 1 where o_orderkey % 50 = 0 group by 1")


def join_interval(s, d):
    sec = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    e = table(s, d, "events").select("event_id", F.col("user_id").alias("u"), sec("ts").alias("at"))
    o = table(s, d, "orders").select("o_orderkey", F.col("o_custkey").alias("u"), sec("o_orderdate").alias("from"))
    return joins.band_join(e, o, "at", "from", 0, 30 * 86_400_000_000, ["u"]).select("event_id", "o_orderkey")


register("join_interval", join_interval, "select event_id, o_orderkey from events join orders on user_id = o_custkey and ts between o_orderdate and o_orderdate + interval 30 day")


def join_asof(s, d):
    e = table(s, d, "events").select("event_id", F.col("user_id").alias("u"), "ts")
    o = table(s, d, "orders").groupBy(F.col("o_custkey").alias("u"), "o_orderdate").agg(F.max("o_orderkey").alias("o_orderkey"))
    return joins.asof_join(e, o, "u", "ts", "o_orderdate", "o_orderkey").select("event_id", "o_orderkey")


register("join_asof", join_asof, "select event_id, o.o_orderkey from events e asof left join (select o_custkey, o_orderdate, max(o_orderkey) as o_orderkey from orders group by 1, 2) o on e.user_id = o.o_custkey and e.ts >= o.o_orderdate")
register(
    "join_lookup_bits", lambda s, d: table(s, d, "lineitem").join(F.broadcast(table(s, d, "part").select(F.col("p_partkey").alias("l_partkey"), MD5_60.hash(F.col("p_partkey"), "B:").alias("bits"))), "l_partkey").groupBy("l_orderkey").agg(F.min("bits").alias("low")),
    f"select l_orderkey, min({O.digest(chr(39) + 'B:' + chr(39), 'l_partkey')}) as low from lineitem group by 1",
)

# ---- aggregation
register("agg_group_sizes", lambda s, d: group_sizes(rel(s, d, "cust_type")), f"with {O.sides('cust_type')} select jk, l, r from (select jk, count(distinct lk) as l from l group by jk) join (select jk, count(distinct rk) as r from r group by jk) using (jk)")
register("agg_max_product", lambda s, d: work(rel(s, d)), f"with {O.sides(PPO)}, {O.stats()} select maxprod, joined from st")
register("agg_degrees", lambda s, d: join_project(rel(s, d, "cust_type")).groupBy("lk").agg(F.count("*").alias("degree")), f"with {O.sides('cust_type')} select lk, count(*) as degree from (select distinct lk, rk from l join r using (jk)) group by lk")
simple("agg_partial_final", "lineitem", lambda x: x.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("q"), F.round(F.avg("l_discount"), 6).alias("a")), "select l_returnflag, l_linestatus, count(*) as n, round(sum(l_quantity), 2) as q, round(avg(l_discount), 6) as a from lineitem group by 1, 2")
simple("agg_distinct_multi", "lineitem", lambda x: x.agg(F.count_distinct("l_partkey").alias("p"), F.count_distinct("l_suppkey").alias("s"), F.count_distinct("l_orderkey").alias("o")), "select count(distinct l_partkey) as p, count(distinct l_suppkey) as s, count(distinct l_orderkey) as o from lineitem")
simple("agg_approx_distinct", "lineitem", lambda x: x.agg(F.approx_count_distinct("l_orderkey", 0.02).alias("n")), None)
simple("agg_hll", "lineitem", lambda x: x.groupBy("l_returnflag").agg(F.hll_sketch_agg("l_orderkey").alias("s")).agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("n")), None)
simple("agg_theta", "lineitem", lambda x: x.groupBy("l_returnflag").agg(F.theta_sketch_agg("l_orderkey").alias("s")).agg(F.theta_sketch_estimate(F.theta_union_agg("s")).alias("n")), None)
simple("agg_bottom_k", "lineitem", lambda x: x.groupBy("l_suppkey").agg(F.slice(F.array_sort(F.collect_set(MD5_60.hash(F.col("l_partkey"), "L1:"))), 1, 4).alias("h")).select("l_suppkey", F.explode("h").alias("h")), f"select l_suppkey, h from (select l_suppkey, h, row_number() over (partition by l_suppkey order by h) as i from (select distinct l_suppkey, {O.digest(chr(39) + 'L1:' + chr(39), 'l_partkey')} as h from lineitem)) where i <= 4")
simple("agg_min_ranks", "lineitem", lambda x: x.groupBy("l_orderkey").agg(*[F.min(MD5_60.hash(F.col("l_partkey"), f"r{i}:")).alias(f"m{i}") for i in range(4)]), "select l_orderkey, " + ", ".join(f"min({O.digest(chr(39) + f'r{i}:' + chr(39), 'l_partkey')}) as m{i}" for i in range(4)) + " from lineitem group by 1")
simple("agg_median_quantile", "orders", lambda x: x.groupBy("o_orderstatus").agg(F.round(F.median("o_totalprice"), 4).alias("m"), F.round(F.percentile("o_totalprice", 2 / 3), 4).alias("q")), f"select o_orderstatus, round(median(o_totalprice), 4) as m, round(quantile_cont(o_totalprice, {2 / 3!r}), 4) as q from orders group by 1")
simple("agg_collect", "lineitem", lambda x: x.groupBy("l_orderkey").agg(F.array_join(F.array_sort(F.collect_set("l_partkey")), ",").alias("parts")), "select l_orderkey, array_to_string(list_sort(list(distinct l_partkey)), ',') as parts from lineitem group by 1")
simple("agg_argmin", "lineitem", lambda x: x.groupBy("l_suppkey").agg(F.min_by("l_partkey", MD5_60.hash(F.col("l_partkey"), "L1:")).alias("p")), f"select l_suppkey, min_by(l_partkey, {O.digest(chr(39) + 'L1:' + chr(39), 'l_partkey')}) as p from lineitem group by 1")
simple("agg_pivot", "orders", lambda x: x.groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count("o_orderkey")).na.fill(0), "select o_orderpriority, count(*) filter (o_orderstatus = 'F') as F, count(*) filter (o_orderstatus = 'O') as O, count(*) filter (o_orderstatus = 'P') as P from orders group by 1")
for key, clause in (("agg_grouping_sets", "grouping sets ((c_mktsegment, o_orderstatus), (c_mktsegment), ())"), ("agg_cube", "cube (c_mktsegment, o_orderstatus)"), ("agg_rollup", "rollup (c_mktsegment, o_orderstatus)")):
    over_sql(key, f"select c_mktsegment, o_orderstatus, count(*) as n from customer join orders on c_custkey = o_custkey group by {clause}", "customer", "orders")
over_sql("agg_filter_having", "select l_partkey, count(distinct l_orderkey) as support from lineitem group by l_partkey having count(distinct l_orderkey) >= 30", "lineitem")

# ---- windows, sort, top-k, set operations
for key, fn in (("win_row_number", "row_number()"), ("win_rank", "rank()"), ("win_dense_rank", "dense_rank()"), ("win_ntile", "ntile(4)")):
    order = "p_size, p_partkey" if fn in ("row_number()", "ntile(4)") else "p_size"
    over_sql(key, f"select p_partkey, cast({fn} over (partition by p_brand order by {order}) as bigint) as v from part", "part")
over_sql("win_lag_lead", "select o_orderkey, lag(o_orderkey) over (partition by o_custkey order by o_orderkey) as prev, lead(o_orderkey) over (partition by o_custkey order by o_orderkey) as nxt from orders", "orders")
over_sql("win_cume_dist", "select p_partkey, round(cume_dist() over (partition by p_brand order by p_size), 6) as v from part", "part")
over_sql("win_percent_rank", "select p_partkey, round(percent_rank() over (partition by p_brand order by p_size), 6) as v from part", "part")
over_sql("win_rows_frame", "select o_orderkey, round(sum(o_totalprice) over (partition by o_custkey order by o_orderkey rows between 2 preceding and current row), 2) as v from orders", "orders")
over_sql("win_range_frame", "select p_partkey, count(*) over (partition by p_brand order by p_size range between current row and 3 following) as v from part", "part")
over_sql("win_first_last", "select o_orderkey, first_value(o_orderkey) over (partition by o_custkey order by o_orderkey) as a, last_value(o_orderkey) over (partition by o_custkey order by o_orderkey rows between unbounded preceding and unbounded following) as b from orders", "orders")
simple("sort_global", "orders", lambda x: x.select("o_custkey", "o_orderkey").orderBy("o_custkey", F.desc("o_orderkey")), "select o_custkey, o_orderkey from orders order by o_custkey, o_orderkey desc")
simple("sort_partitions", "orders", lambda x: x.select("o_custkey", "o_orderkey").repartitionByRange(8, "o_custkey").sortWithinPartitions("o_custkey", "o_orderkey"), "select o_custkey, o_orderkey from orders")
over_sql("topk_smallest", "select distinct l_partkey, l_suppkey from lineitem order by l_partkey, l_suppkey limit 100", "lineitem")
over_sql("topk_per_group", "select o_custkey, o_orderkey from (select o_custkey, o_orderkey, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as i from orders) where i <= 3", "orders")
over_sql("limit_offset", "select o_orderkey from orders order by o_totalprice, o_orderkey limit 50 offset 100", "orders")
_A, _B = "select l_partkey from lineitem where l_orderkey % 5 = 0", "select l_partkey from lineitem where l_orderkey % 5 = 1"
for key, word in (("set_union_all", "union all"), ("set_union", "union"), ("set_intersect", "intersect"), ("set_except", "except"), ("set_intersect_all", "intersect all"), ("set_except_all", "except all")):
    over_sql(key, f"{_A} {word} {_B}", "lineitem")

# ---- scalar functions
over_sql("fn_string", "select doc_id, lower(substr(text, 1, 20)) as a, length(text) as b, replace(trim(substr(text, 1, 9)), 'e', '3') as c, md5(text) as d, concat_ws('-', lang, source) as e from documents", "documents")
simple("fn_date", "orders", lambda x: x.select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.datediff("o_orderdate", F.lit("1990-01-01")).alias("d"), F.date_format(F.add_months("o_orderdate", 2), "yyyy-MM-dd").alias("a")), "select o_orderkey, year(o_orderdate) as y, month(o_orderdate) as m, date_diff('day', date '1990-01-01', o_orderdate::date) as d, strftime(o_orderdate::date + interval 2 month, '%Y-%m-%d') as a from orders")
over_sql("fn_math", "select p_partkey, round(sqrt(p_size), 6) as a, cast(ceil(p_retailprice) as bigint) as b, cast(floor(p_retailprice) as bigint) as c, round(ln(p_size + 1), 6) as d, round(exp(-p_size / 10.0), 6) as e, greatest(p_size, 10) as f, least(p_size, 10) as g from part", "part")
simple("fn_bits", "part", lambda x: x.select("p_partkey", F.shiftright("p_partkey", 2).alias("a"), F.col("p_partkey").bitwiseAND(7).alias("b"), F.col("p_partkey").bitwiseXOR(F.lit(5)).alias("c"), F.shiftrightunsigned("p_partkey", 1).alias("e")), "select p_partkey, p_partkey >> 2 as a, p_partkey & 7 as b, xor(p_partkey, 5) as c, p_partkey >> 1 as e from part")
_AL, _BE = AFFINE61.coefficients("L1:")
simple("fn_decimal", "part", lambda x: x.select("p_partkey", AFFINE61.hash(F.col("p_partkey"), "L1:").alias("h")), f"select p_partkey, cast(({_AL}::hugeint * p_partkey::hugeint + {_BE}::hugeint) % {2**61 - 1}::hugeint as bigint) as h from part")
simple("fn_array", "embeddings", lambda x: x.select("vec_id", F.size(F.filter("embedding", lambda v: v.cast("double") > 0.15)).alias("n"), F.exists("embedding", lambda v: v > 0.3).alias("any"), F.aggregate(F.transform("embedding", lambda v: F.when(v > 0, 1).otherwise(0)), F.lit(0), lambda a, v: a + v).alias("pos")), "select vec_id, len(list_filter(embedding, lambda v: cast(v as double) > 0.15)) as n, len(list_filter(embedding, lambda v: v > 0.3)) > 0 as any, cast(list_sum(list_transform(embedding, lambda v: case when v > 0 then 1 else 0 end)) as integer) as pos from embeddings")
simple("fn_map", "orders", lambda x: x.groupBy("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")).groupBy("o_orderstatus").agg(F.map_from_entries(F.collect_list(F.struct("o_orderpriority", "n"))).alias("m")).select("o_orderstatus", F.size("m").alias("keys"), F.aggregate(F.map_values(F.transform_values("m", lambda k, v: v * 2)), F.lit(0).cast("long"), lambda a, v: a + v).alias("twice")), "select o_orderstatus, count(distinct o_orderpriority) as keys, cast(2 * count(*) as bigint) as twice from orders group by 1")
simple("fn_json", "events", lambda x: x.select("event_id", F.get_json_object("props", "$.k").alias("a"), F.from_json("props", "k int")["k"].alias("b")), "select event_id, json_extract_string(props, '$.k') as a, cast(json_extract_string(props, '$.k') as integer) as b from events")
over_sql("fn_null", "select o_orderkey, coalesce(nullif(o_orderstatus, 'F'), 'none') as a, nullif(o_custkey, 1) as b from orders", "orders")
simple("fn_struct", "orders", lambda x: x.select(F.struct("o_custkey", F.struct("o_orderstatus").alias("s")).alias("k")).select("k.o_custkey", "k.s.o_orderstatus").distinct(), "select distinct o_custkey, o_orderstatus from orders")

# ---- functions for SQL users


def fn_sp_hashes(s, d):
    sqlfuncs.register_functions(s)
    _views(s, d, ["part"])
    return s.sql("select p_partkey, sp_attr_hash(cast(p_partkey as string), 'L1:') as x, sp_pair_hash(sp_attr_hash(cast(p_partkey as string), 'L1:'), sp_attr_hash(cast(p_size as string), 'R1:')) as h from part")


_X, _Y = O.digest("'L1:'", "p_partkey"), O.digest("'R1:'", "p_size")
register("fn_sp_hashes", fn_sp_hashes, f"select p_partkey, {_X} as x, (({_X}) - ({_Y})) & {O.MASK} as h from part")
simple("fn_sp_affine61", "part", lambda x: x.select("p_partkey", affine61_udf("L1:")("p_partkey").alias("h")), f"select p_partkey, cast(({_AL}::hugeint * p_partkey::hugeint + {_BE}::hugeint) % {2**61 - 1}::hugeint as bigint) as h from part")
simple("fn_sp_bottom_k", "lineitem", lambda x: x.groupBy("l_suppkey").agg(sqlfuncs.bottom_k_udaf(4)("l_partkey").alias("p")).select("l_suppkey", F.explode("p").alias("p")), "select l_suppkey, p from (select l_suppkey, p, row_number() over (partition by l_suppkey order by p) as i from (select distinct l_suppkey, l_partkey as p from lineitem)) where i <= 4")


def fn_sp_hits(s, d):
    sqlfuncs.register_functions(s)
    left, right = _cyclic_frames(s, d)
    a = left.where("jk % 10 = 0").groupBy("jk").agg(F.collect_list("x").alias("xs"))
    a.join(right.groupBy("jk").agg(F.collect_list("y").alias("ys")), "jk").createOrReplaceTempView("sp_groups")
    return s.sql(f"select jk, h.x_h, h.y_h from sp_groups, lateral sp_hits(xs, ys, {2**56}) h")


register(
    "fn_sp_hits", fn_sp_hits,
    f"with {O.sides(PPO)} select jk, x_h, y_h from (select jk, {O.digest(chr(39) + 'L1:' + chr(39), 'lk')} as x_h from l where jk % 10 = 0) join (select jk, {O.digest(chr(39) + 'R1:' + chr(39), 'rk')} as y_h from r) using (jk) where ((x_h - y_h) & {O.MASK}) < {2**56}",
)


def fn_sp_size(s, d):
    _views(s, d, ["orders", "lineitem"])
    out = sqlfuncs.sp_size(s, "select l_suppkey, l_orderkey from lineitem", "orders", "l_suppkey", "o_custkey", ("l_orderkey", "o_orderkey"), Spec(k=256, family="md5_60"))
    return out.select("threshold", "kept", "kth_hash", F.round("z_hat").cast("long").alias("z_hat"), "status")


register("fn_sp_size", fn_sp_size, O.estimate("supp_cust_order"))
