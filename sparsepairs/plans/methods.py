"""Queries of the methods, baselines and measures, each with the SQL that recomputes it."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import bounds
from ..functions.hashing import AFFINE61, drawn_table, lookup_table, rounding_risk
from ..operators import applications, baselines, exact, measures, sampling
from ..operators.estimate import (
    Spec,
    as_threshold,
    cells_for,
    choose_threshold,
    estimate_size,
    finish,
    hashed,
    hits,
    hits_by_cell,
    hits_by_sweep,
    k_smallest,
    kept_set,
    median_of_runs,
    merge,
    run_estimates,
    sqrt_n_k,
    threshold_p,
)
from ..operators.relations import Rel, cluster, drop_dangling, group_sizes, normalize, profile, self_rel, work
from ..operators.runs import runs_from_one, sample_sketches
from ..sources.sketches import released, scratch
from . import oracle as O
from .registry import register
from .workloads import KEYS, SMALL, WORKLOADS, table

BASE = Spec(k=256, family="md5_60", tighten="none")
D = O.DOMAIN


def rel(s: SparkSession, d: str, name: str) -> Rel:
    return WORKLOADS[name].build(s, d)


def direct(s: SparkSession, d: str) -> Rel:
    """part_part_order as it is read: repeated rows do no harm where no group is counted."""
    return self_rel(table(s, d, "lineitem"), "l_partkey", "l_orderkey", dedup=False)


def slim(rows: DataFrame) -> DataFrame:
    return rows.select("threshold", "kept", "kth_hash", F.round("z_hat").cast("long").alias("z_hat"), "status")


def _estimate(name: str, **settings):
    spec = replace(BASE, **settings)
    return lambda s, d: slim(estimate_size(rel(s, d, name), spec))


def _rows(spark: SparkSession, columns: str, *rows) -> DataFrame:
    return spark.createDataFrame(list(rows), columns)


# ---- workloads: profile and estimate -------------------------------------------------


def _workload(name: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        r = rel(s, d, name)
        return profile(r).crossJoin(slim(estimate_size(r, BASE)))

    return run


for key, name in KEYS.items():
    register(key, _workload(name), f"select * from ({O.profile(name)}), ({O.estimate(name)})")

for k in (256, 1024):
    register(f"m_estimate_k{k}", _estimate("part_part_order", k=k), O.estimate("part_part_order", k))
    register(f"m_estimate_k{k}_cust", _estimate("cust_cust_part", k=k), O.estimate("cust_cust_part", k))

for key, name in (("m_estimate_doc_doc", "doc_doc_word"), ("m_estimate_word_word", "word_word_doc")):
    register(key, _estimate(name), O.estimate(name))

# ---- method 1 ------------------------------------------------------------------------


def m_normalize(s, d):
    r = normalize(table(s, d, "orders"), table(s, d, "customer"), ["o_custkey", "o_orderpriority"], "c_mktsegment", ("o_custkey", "c_custkey"))
    return r.left.agg(F.count("*").alias("n_left")).crossJoin(r.right.agg(F.count("*").alias("n_right")))


register(
    "m_normalize", m_normalize,
    "select (select count(*) from (select distinct o_custkey, o_orderpriority from orders)) as n_left, (select count(*) from (select distinct c_custkey, c_mktsegment from customer)) as n_right",
)


def m_dangling(s, d):
    r = normalize(table(s, d, "customer"), table(s, d, "orders"), "c_mktsegment", "o_orderstatus", ("c_custkey", "o_custkey"))
    left = normalize(table(s, d, "customer").where("c_custkey % 3 = 0"), table(s, d, "orders"), "c_mktsegment", "o_orderstatus", ("c_custkey", "o_custkey")).left
    out = drop_dangling(Rel(left, r.right))
    return out.left.agg(F.count("*").alias("n_left")).crossJoin(out.right.agg(F.count("*").alias("n_right")))


register(
    "m_dangling", m_dangling,
    """with l as (select distinct c_mktsegment as lk, c_custkey as jk from customer where c_custkey % 3 = 0),
    r as (select distinct o_custkey as jk, o_orderstatus as rk from orders)
    select (select count(*) from l where jk in (select jk from r)) as n_left, (select count(*) from r where jk in (select jk from l)) as n_right""",
)


def m_threshold(s: SparkSession, d: str, policy: str, p: float | None) -> DataFrame:
    """The threshold of two workloads, from a row of statistics that every policy reads, as the SQL does."""
    frames = []
    for n in ("cust_type", "part_part_order"):
        r = rel(s, d, n)
        row = work(r).first()
        t = as_threshold(threshold_p(256, policy, int(row["maxprod"]), p), D)
        frames.append((n, t))
    return _rows(s, "workload string, threshold long", *frames)


for policy, p in (("printed", None), ("doubled", None), ("inverse_k", None), ("fixed", 0.001)):
    register(
        f"m_threshold_{policy}",
        lambda s, d, policy=policy, p=p: m_threshold(s, d, policy, p),
        " union all ".join(
            f"select '{n}' as workload, t as threshold from (with {O.sides(n)}, {O.stats()} select cast(ceil({O.p_of(256, policy, p)} * {float(D)!r}::double) as bigint) as t from st)"
            for n in ("cust_type", "part_part_order")
        ),
    )

register("m_hits_scan", lambda s, d: hits_by_sweep(*hashed(rel(s, d, "part_part_order"), BASE, 1), BASE, choose_threshold(rel(s, d, "part_part_order"), BASE), how="range").distinct(), f"with {O.found('part_part_order')} select x_h, y_h, pair_h from h")
_HITS = f"with {O.found('part_part_order')} select x_h, y_h, pair_h from h"
for strategy in ("cells", "sweep", "grouped", "full"):
    register(f"m_hits_{strategy}", lambda s, d, st=strategy: hits(rel(s, d, "part_part_order"), replace(BASE, strategy=st)).distinct(), _HITS)


def m_hits_wrap(s, d):
    out = None
    for label, p in (("1/2", 0.5), ("1/3", 1 / 3), ("1", 1.0)):
        for strategy in ("cells", "sweep", "grouped", "full"):
            found = hits(rel(s, d, "dim_dim"), replace(BASE, strategy=strategy), p).distinct()
            row = found.agg(F.count("*").alias("hits"), F.bit_xor("pair_h").alias("parity")).select(F.lit(label).alias("p"), F.lit(strategy).alias("strategy"), "hits", "parity")
            out = row if out is None else out.unionByName(row)
    return out


register(
    "m_hits_wrap", m_hits_wrap,
    f"with {O.sides('dim_dim')}, lh as (select jk, {O.digest(chr(39) + 'L1:' + chr(39), 'lk')} as x_h from l), rh as (select jk, {O.digest(chr(39) + 'R1:' + chr(39), 'rk')} as y_h from r), "
    f"a as (select distinct x_h, y_h, (x_h - y_h) & {O.MASK} as pair_h from lh join rh using (jk)), "
    f"ps as (select * from (values ('1/2', cast(ceil(0.5::double * {float(D)!r}) as bigint)), ('1/3', cast(ceil({1 / 3!r}::double * {float(D)!r}::double) as bigint)), ('1', {D})) v(p, t)), "
    "ss as (select unnest(['cells', 'sweep', 'grouped', 'full']) as strategy) "
    "select p, strategy, count(*) as hits, bit_xor(pair_h) as parity from a, ps, ss where pair_h < t group by p, strategy",
)

_KEPT = f"with {O.found('part_part_order')}, {O.kept(256)} select x_h, y_h, pair_h from ks"
for key, method in (("m_k_smallest", "buffer"), ("m_k_smallest_heap", "heap"), ("m_k_smallest_rank", "rank"), ("m_k_smallest_native", "native")):
    register(key, lambda s, d, m=method: k_smallest(hits(rel(s, d, "part_part_order"), BASE), 256, m), _KEPT)
for tighten in ("pilot", "local"):
    register(
        f"m_tighten_{tighten}",
        lambda s, d, t=tighten: kept_set(rel(s, d, "cust_cust_part"), replace(BASE, tighten=t), choose_threshold(rel(s, d, "cust_cust_part"), BASE)),
        f"with {O.found('cust_cust_part')}, {O.kept(256)} select x_h, y_h, pair_h from ks",
    )
register("m_estimate_unbiased", _estimate("part_part_order", estimator="unbiased"), O.estimate("part_part_order", top=255))
register("m_p_one", _estimate("cust_type", policy="one"), O.estimate("cust_type", policy="one"))
register("m_p_one_freq", _estimate("freq_parts", policy="one"), O.estimate("freq_parts", policy="one"))
register("m_short_bound", _estimate("cust_type"), O.estimate("cust_type"))
register("m_short_count", _estimate("cust_type", on_short="count"), O.estimate("cust_type", short="e.kept / th.p"))
register("m_short_scaled", _estimate("cust_type", on_short="scaled"), O.estimate("cust_type", short="e.kept / 1.0"))


def m_short_widen(s, d):
    return slim(estimate_size(rel(s, d, "cust_type"), replace(BASE, on_short="widen"))).select("kept", "kth_hash", "z_hat", "status")


register("m_short_widen", m_short_widen, f"select kept, kth_hash, z_hat, status from ({O.estimate('cust_type', policy='one')})")


def _run_sql(name: str, k: int, runs: range, policy: str = "doubled") -> str:
    parts = []
    for r in runs:
        parts.append(
            f"select {r} as run, * from (with {O.found(name, k, policy, run=r)}, {O.kept(k)} select count(*) as kept, max(pair_h) as kth_hash, "
            f"case when count(*) >= {k} then {float(k * D)!r}::double / greatest(max(pair_h), 1) else count(*) / any_value(th.p) end as z_hat from ks, th)"
        )
    return " union all ".join(parts)


register(
    "m_median_runs",
    lambda s, d: median_of_runs(rel(s, d, "part_part_order"), BASE, 9).select("runs", F.round("z_hat").cast("long").alias("z_hat")),
    f"select count(*) as runs, cast(round(median(z_hat)) as bigint) as z_hat from ({_run_sql('part_part_order', 256, range(1, 10))})",
)


def m_sqrt_n(s, d):
    r = rel(s, d, "part_part_order")
    k = sqrt_n_k(r.left.count() + r.right.count())
    return slim(estimate_size(r, replace(BASE, k=k))).select(F.lit(k).alias("k"), "kept", "kth_hash")


register(
    "m_sqrt_n", m_sqrt_n,
    f"with {O.sides('part_part_order')}, {O.stats()}, kk as (select cast(ceil(sqrt((select count(*) from l) + (select count(*) from r))) as integer) as k), "
    f"th as (select cast(ceil(least(1.0::double, 2.0::double / k, 2.0::double * k / maxprod) * {float(D)!r}::double) as bigint) as t from st, kk), "
    f"lh as (select jk, {O.digest(chr(39) + 'L1:' + chr(39), 'lk')} as x_h from l), rh as (select jk, {O.digest(chr(39) + 'R1:' + chr(39), 'rk')} as y_h from r), "
    f"h as (select distinct x_h, y_h, (x_h - y_h) & {O.MASK} as pair_h from lh join rh using (jk), th where ((x_h - y_h) & {O.MASK}) < th.t), "
    "ks as (select *, row_number() over (order by pair_h, x_h, y_h) as i from h) "
    "select any_value(kk.k) as k, count(*) as kept, case when count(*) >= any_value(kk.k) then max(pair_h) end as kth_hash from ks, kk where i <= kk.k",
)


def _affine_sql(seed: str, col: str) -> str:
    a, b = AFFINE61.coefficients(seed)
    return f"cast(({a}::hugeint * {col}::hugeint + {b}::hugeint) % {2**61 - 1}::hugeint as bigint)"


def m_family_affine61(s, d):
    return slim(estimate_size(rel(s, d, "part_part_order"), replace(BASE, family="affine61")))


register(
    "m_family_affine61", m_family_affine61,
    f"with {O.sides('part_part_order')}, {O.stats()}, th as (select cast(ceil({O.p_of(256, 'doubled')} * {float(2**61 - 1)!r}::double) as bigint) as t from st), "
    f"lh as (select jk, {_affine_sql('L1:', 'lk')} as x_h from l), rh as (select jk, {_affine_sql('R1:', 'rk')} as y_h from r), "
    f"h as (select distinct x_h, y_h, case when x_h >= y_h then x_h - y_h else x_h - y_h + {2**61 - 1} end as pair_h from lh join rh using (jk)), "
    "f as (select h.* from h, th where pair_h < t order by pair_h, x_h, y_h limit 256), e as (select count(*) as kept, max(pair_h) as kth from f) "
    f"select t as threshold, kept, case when kept >= 256 then kth end as kth_hash, cast(round(case when kept >= 256 then {256 * float(2**61 - 1)!r}::double / kth else 65536.0 end) as bigint) as z_hat, "
    "case when kept >= 256 then 'estimate' else 'upper_bound' end as status from e, th",
)
register("m_family_mix63", lambda s, d: slim(estimate_size(rel(s, d, "part_part_order"), replace(BASE, family="mix63"))))


def m_family_table(s, d):
    """Random bits stored for each value and joined, instead of a hash of the value."""
    r = rel(s, d, "part_part_order")
    left, right = lookup_table(r.left, "lk", "L1:"), lookup_table(r.right, "rk", "R1:")
    x = r.left.join(left, "lk").select("jk", F.col("bits").alias("x_h"))
    y = r.right.join(right, "rk").select("jk", F.col("bits").alias("y_h"))
    p = choose_threshold(r, BASE)
    return k_smallest(hits_by_cell(x, y, BASE, p), 256)


register("m_family_table", m_family_table, _KEPT)


def m_family_drawn(s, d):
    """Truly random bits, drawn once and stored: k, kept and the estimate of one draw."""
    r = rel(s, d, "part_part_order")
    left, right = drawn_table(r.left, "lk", "L1:", scratch(s, "bits-left")), drawn_table(r.right, "rk", "R1:", scratch(s, "bits-right"))
    x = r.left.join(left, "lk").select("jk", F.col("bits").alias("x_h"))
    y = r.right.join(right, "rk").select("jk", F.col("bits").alias("y_h"))
    p = choose_threshold(r, BASE)
    return slim(finish(k_smallest(hits_by_cell(x, y, BASE, p), 256), BASE, p))


register("m_family_drawn", m_family_drawn)
for strategy in ("cells", "sweep", "grouped"):
    # The threshold falls inside the enumeration from p = 1.
    register(
        f"m_falling_{strategy}",
        lambda s, d, st=strategy: kept_set(rel(s, d, "cust_cust_part"), replace(BASE, tighten="local", strategy=st), 1.0),
        f"with {O.found('cust_cust_part', policy='one')}, {O.kept(256)} select x_h, y_h, pair_h from ks",
    )
register("m_estimate_direct", lambda s, d: slim(estimate_size(direct(s, d), replace(BASE, k=1024, policy="inverse_k", tighten="local"))), O.estimate("part_part_order", 1024, "inverse_k"))
register("m_estimate_mix63", lambda s, d: slim(estimate_size(direct(s, d), Spec(k=1024, policy="inverse_k"))))


def m_interval(s, d):
    out = None
    for n in ("part_part_order", "cust_type"):
        row = estimate_size(rel(s, d, n), BASE).select(F.lit(n).alias("workload"), F.round("lo").cast("long").alias("lo"), F.round("hi").cast("long").alias("hi"))
        out = row if out is None else out.unionByName(row)
    return out


register(
    "m_interval", m_interval,
    " union all ".join(
        f"select '{n}' as workload, cast(round(case when kth_hash is null then 0 else {256.0 * D!r}::double / greatest(kth_hash, 1) / (1 + 0.1875) end) as bigint) as lo, "
        f"cast(round(case when kth_hash is null then (1 + 0.1875) * 65536 else {256.0 * D!r}::double / greatest(kth_hash, 1) / (1 - 0.1875) end) as bigint) as hi from ({O.estimate(n)})"
        for n in ("part_part_order", "cust_type")
    ),
)


def m_merge(s, d):
    r = rel(s, d, "part_part_order")
    p = choose_threshold(r, BASE)
    half = lambda odd: Rel(r.left.where(F.col("jk") % 2 == odd), r.right.where(F.col("jk") % 2 == odd))
    parts = [k_smallest(hits(half(o), BASE, p), 256) for o in (0, 1)]
    return merge(*parts, 256)


register("m_merge", m_merge, _KEPT)


def m_wide_keys(s, d):
    o = table(s, d, "orders").join(table(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"))
    r = normalize(o, table(s, d, "part"), ["o_custkey", "o_orderpriority"], ["p_brand", "p_type"], ("l_partkey", "p_partkey"), fingerprint=True)
    return baselines.exact_size(r)


register(
    "m_wide_keys", m_wide_keys,
    "select count(*) as z from (select distinct o_custkey, o_orderpriority, p_brand, p_type from orders join lineitem on o_orderkey = l_orderkey join part on l_partkey = p_partkey)",
)



def m_cluster(s, d):
    """Every join value lies in one partition of each side, by hash and by range: partitions that share a value with another."""
    out = None
    for how in ("hash", "sort"):
        r = cluster(rel(s, d, "cust_type"), how, 8)
        rows = r.left.select("jk", F.spark_partition_id().alias("p")).groupBy("jk").agg(F.count_distinct("p").alias("n"), F.count("*").alias("rows"))
        row = rows.agg(F.lit(how).alias("how"), F.sum(F.col("n") - 1).alias("shared"), F.sum("rows").alias("n_rows"))
        out = row if out is None else out.unionByName(row)
    return out


register("m_cluster", m_cluster, " union all ".join(f"select '{how}' as how, cast(0 as bigint) as shared, n1 as n_rows from ({O.profile('cust_type')})" for how in ("hash", "sort")))

# ---- method 3 ------------------------------------------------------------------------


def _keep(col: str, seed: str, p: float) -> str:
    return f"{O.digest(chr(39) + seed + chr(39), col)} < {sampling.sample_threshold(p, 'md5_60')}"


def _sampled(name: str, p1: float, p2: float, run: int = 1) -> str:
    return f"{O.sides(name)}, sl as (select * from l where {_keep('lk', f'SL{run}:', p1)}), sr as (select * from r where {_keep('rk', f'SR{run}:', p2)})"


def _checksum(df: DataFrame, role: str) -> DataFrame:
    return df.agg(F.count("*").alias("n_kept"), F.count_distinct(role).alias("n_values"))


register(
    "s_left", lambda s, d: _checksum(sampling.sample_side(rel(s, d, "part_part_order").left, "lk", 0.1, "SL1:", "md5_60"), "lk"),
    f"with {_sampled('part_part_order', 0.1, 0.1)} select count(*) as n_kept, count(distinct lk) as n_values from sl",
)
register(
    "s_right", lambda s, d: _checksum(sampling.sample_side(rel(s, d, "doc_doc_word").right, "rk", 0.1, "SR1:", "md5_60"), "rk"),
    f"with {_sampled('doc_doc_word', 0.1, 0.1)} select count(*) as n_kept, count(distinct rk) as n_values from sr",
)


def s_rates(s, d):
    n = profile(rel(s, d, "cust_type")).select("n1", "n2")
    return n.select(F.least(F.lit(1.0), 500.0 / F.col("n1")).alias("p1"), F.least(F.lit(1.0), 500.0 / F.col("n2")).alias("p2"))


register("s_rates", s_rates, f"select least(1.0::double, 500.0::double / n1) as p1, least(1.0::double, 500.0::double / n2) as p2 from ({O.profile('cust_type')})")


def s_size(s, d):
    r = profile(rel(s, d, "part_part_order")).first()
    return _rows(s, "size long", (round(bounds.sample_size(r["n1"], r["n2"], r["n_a"], r["n_c"], 100_000, 0.2)),))


register("s_size", s_size, f"select cast(round((n_c * n1 + n_a * n2) / 100000.0::double * 14.0 / (0.2::double * 0.2)) as bigint) as size from ({O.profile('part_part_order')})")


def s_beta(s, d):
    r = profile(rel(s, d, "part_part_order")).first()
    return _rows(s, "beta long", (round(bounds.beta(r["n1"], r["n2"], r["n_a"], r["n_c"], 5_000, 0.25)),))


register("s_beta", s_beta, f"select cast(round(14.0::double / 0.0625 * (n_c * n1 + n_a * n2) / 5000) as bigint) as beta from ({O.profile('part_part_order')})")


def _sample_row(rows: DataFrame) -> DataFrame:
    return rows.select("kept", F.round("z_hat").cast("long").alias("z_hat"), "status")


def _sample_exact(name: str, p: float) -> str:
    return (
        f"with {_sampled(name, p, p)} select count(*) as kept, case when count(*) > 0 then cast(round(count(*) / ({p}::double * {p}::double)) as bigint) end as z_hat, "
        "case when count(*) > 0 then 'estimate' else 'empty' end as status from (select distinct lk, rk from sl join sr using (jk))"
    )


for label, p in (("10", 0.1), ("01", 0.01)):
    for key, n in ((f"s_exact_{label}", "part_part_order"), (f"s_exact_{label}_vec", "vec_vec")):
        register(key, lambda s, d, n=n, p=p: _sample_row(sampling.sample_estimate(rel(s, d, n), p, p, "exact", BASE)), _sample_exact(n, p))


def _sample_bottomk(p: float):
    # At p = 1 the scan lowers its threshold on the way; listed pairs would fill the disk.
    spec = replace(BASE, k=1024, policy="one", on_short="scaled", tighten="local")
    return lambda s, d: sampling.sample_estimate(rel(s, d, "doc_doc_word"), p, p, "bottomk", spec).select("kept", "kth_hash", F.round("z_hat").cast("long").alias("z_hat"))


for label, p in (("10", 0.1), ("01", 0.01)):
    register(
        f"s_bottomk_{label}", _sample_bottomk(p),
        f"with {_sampled('doc_doc_word', p, p)}, lh as (select jk, {O.digest(chr(39) + 'L1:' + chr(39), 'lk')} as x_h from sl), rh as (select jk, {O.digest(chr(39) + 'R1:' + chr(39), 'rk')} as y_h from sr), "
        f"h as (select distinct x_h, y_h, (x_h - y_h) & {O.MASK} as pair_h from lh join rh using (jk)), {O.kept(1024)} "
        f"select count(*) as kept, case when count(*) >= 1024 then max(pair_h) end as kth_hash, cast(round(case when count(*) >= 1024 then {1024.0 * D!r}::double / max(pair_h) * (1 / ({p}::double * {p}::double)) "
        f"when count(*) = 0 then null else count(*) / ({p}::double * {p}::double) end) as bigint) as z_hat from ks",
    )
def _bottomk_default_sql(name: str, p: float, k: int) -> str:
    """The default policy over the samples: an unfilled set gives the bound of the relation, not of the sample."""
    sides = _sampled(name, p, p)
    return (
        f"with {sides.replace('sl as', 'sl0 as').replace('sr as', 'sr0 as')}, sl as (select * from sl0 where jk in (select jk from sr0)), sr as (select * from sr0 where jk in (select jk from sl0)), "
        f"{O.stats().replace('from l ', 'from sl ').replace('from r ', 'from sr ')}, th as (select {O.p_of(k, 'doubled')} as p, least({D}, cast(ceil({O.p_of(k, 'doubled')} * {float(D)!r}::double) as bigint)) as t from st), "
        f"lh as (select jk, {O.digest(chr(39) + 'L1:' + chr(39), 'lk')} as x_h from sl), rh as (select jk, {O.digest(chr(39) + 'R1:' + chr(39), 'rk')} as y_h from sr), "
        f"h as (select distinct x_h, y_h, (x_h - y_h) & {O.MASK} as pair_h from lh join rh using (jk), th where ((x_h - y_h) & {O.MASK}) < th.t), {O.kept(k)}, e as (select count(*) as kept, max(pair_h) as kth from ks) "
        f"select kept, case when kept >= {k} then kth end as kth_hash, cast(round(case when kept = 0 then null when kept >= {k} then {float(k * D)!r}::double / greatest(kth, 1) when th.p >= 1 then kept else {float(k * k)} end "
        f"* (1 / ({p}::double * {p}::double))) as bigint) as z_hat, case when kept = 0 then 'empty' when kept >= {k} then 'estimate' when th.p >= 1 then 'scaled_count' else 'upper_bound' end as status from e, th"
    )


for key, n, p, k in (("s_bottomk_default", "doc_doc_word", 0.1, 1024), ("s_bottomk_unfilled", "part_part_order", 0.1, 1024), ("s_bottomk_256", "cust_cust_part", 0.5, 256)):
    register(
        key,
        lambda s, d, n=n, p=p, k=k: sampling.sample_estimate(rel(s, d, n), p, p, "bottomk", Spec(k=k, family="md5_60")).select("kept", "kth_hash", F.round("z_hat").cast("long").alias("z_hat"), "status"),
        _bottomk_default_sql(n, p, k),
    )
register("s_empty", lambda s, d: _sample_row(sampling.sample_estimate(rel(s, d, "cust_type"), 0.01, 0.01, "exact", BASE)), _sample_exact("cust_type", 0.01))
register("s_table", lambda s, d: _sample_row(sampling.sample_estimate(rel(s, d, "part_part_order"), 0.1, 0.1, "exact", BASE, mode="table")))


def s_store(s, d):
    store = sampling.SketchStore(s, scratch(s, "sketches"))
    r = rel(s, d, "part_part_order")
    store.put("part_order", "lk", r.left, 0.1, "SL1:", "md5_60")
    store.put("part_order", "rk", r.right, 0.1, "SR1:", "md5_60")
    own = Rel(store.get("part_order", "lk", "SL1:", 0.1), store.get("part_order", "rk", "SR1:", 0.1))
    return baselines.exact_size(own).crossJoin(store.list().agg(F.sum("n_kept").alias("n_kept")))


register(
    "s_store", s_store,
    f"with {_sampled('part_part_order', 0.1, 0.1)} select count(*) as z, (select count(*) from sl) + (select count(*) from sr) as n_kept from (select distinct lk, rk from sl join sr using (jk))",
)


def s_thin(s, d):
    wide = sampling.sample_side(rel(s, d, "part_part_order").left, "lk", 0.1, "SL1:", "md5_60")
    return _checksum(sampling.thin(wide, "lk", 0.02, "SL1:", "md5_60"), "lk")


register("s_thin", s_thin, f"with {_sampled('part_part_order', 0.02, 0.02)} select count(*) as n_kept, count(distinct lk) as n_values from sl")


def s_maintain(s, d):
    left = rel(s, d, "part_part_order").left
    old = sampling.sample_side(left.where("jk % 10 < 8"), "lk", 0.1, "SL1:", "md5_60")
    return _checksum(sampling.maintain(old, "lk", 0.1, "SL1:", left.where("jk % 10 >= 8"), left.where("jk % 10 = 3"), "md5_60"), "lk")


register("s_maintain", s_maintain, f"with {_sampled('part_part_order', 0.1, 0.1)} select count(*) as n_kept, count(distinct lk) as n_values from sl where jk % 10 <> 3")
register(
    "s_fingerprint", lambda s, d: sampling.fingerprint_sketch(rel(s, d, "part_part_order")).groupBy("side").agg(F.count_distinct("fingerprint").alias("n")),
    f"with {O.sides('part_part_order')} select 'left' as side, count(*) as n from l union all select 'right', count(*) from r",
)


def _sample_runs_sql(name: str, p: float, runs: int) -> str:
    t = sampling.sample_threshold(p, "md5_60")
    return (
        f"with {O.sides(name)}, rr as (select unnest(range(1, {runs + 1})) as run), "
        f"cl as (select run, lk from (select distinct lk from l), rr where {O.digest(chr(39) + 'SL' + chr(39) + ' || run || ' + chr(39) + ':' + chr(39), 'lk')} < {t}), "
        f"cr as (select run, rk from (select distinct rk from r), rr where {O.digest(chr(39) + 'SR' + chr(39) + ' || run || ' + chr(39) + ':' + chr(39), 'rk')} < {t}), "
        "pr as (select run, count(*) as kept from (select distinct run, lk, rk from (select run, lk, jk from l join cl using (lk)) a join (select run, rk, jk from r join cr using (rk)) b using (run, jk)) group by run) "
        f"select rr.run, coalesce(kept, 0) as kept, kept / ({p}::double * {p}::double) as z_hat from rr left join pr on rr.run = pr.run"
    )


register(
    "s_median", lambda s, d: sampling.median_of_samples(rel(s, d, "part_part_order"), 0.1, 0.1, 9, BASE).select("runs", F.round("z_hat").cast("long").alias("z_hat")),
    f"select count(*) as runs, cast(round(median(coalesce(z_hat, 0))) as bigint) as z_hat from ({_sample_runs_sql('part_part_order', 0.1, 9)})",
)

# ---- baselines -----------------------------------------------------------------------

for key, hint in (("b_exact_hash", "shuffle_hash"), ("b_exact_merge", "merge"), ("b_exact_broadcast", "broadcast")):
    register(key, lambda s, d, h=hint: baselines.exact_size(rel(s, d, "part_part_order"), h), O.exact("part_part_order"))
register("b_exact_doc_doc", lambda s, d: exact.size(exact.stored_rel(rel(s, d, "doc_doc_word"))), O.exact("doc_doc_word"))
register("b_exact_by_left", lambda s, d: baselines.exact_by_left(rel(s, d, "part_part_order")), O.exact("part_part_order"))


def _unit(col: str, round_: str) -> str:
    return f"-ln((cast('0x' || substr(md5('rank' || {round_} || ':' || coalesce(cast({col} as varchar), '\\N')), 1, 13) as bigint)::double + 0.5) / {float(2**52)!r}::double)"


def _min_rank_sql(name: str) -> str:
    return (
        f"with {O.sides(name)}, rr as (select unnest(range(1, 65)) as i), rk as (select rk, i, {_unit('rk', 'i')} as x from (select distinct rk from r), rr), "
        "a as (select jk, i, min(x) as x from r join rk using (rk) group by jk, i), b as (select lk, i, min(x) as x from l join a using (jk) group by lk, i) "
        "select cast(round(sum(v)) as bigint) as z_hat from (select 63 / sum(x) as v from b group by lk)"
    )


for key, n in (("b_min_rank", "cust_type"), ("b_min_rank_parts", "part_part_order")):
    register(key, lambda s, d, n=n: baselines.min_rank_size(rel(s, d, n)).select(F.round("z_hat").cast("long").alias("z_hat")), _min_rank_sql(n))


def chain(s: SparkSession, d: str) -> list[DataFrame]:
    """nation - order, order - part, part - supplier."""
    a = table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey")).select(F.col("c_nationkey").cast("long").alias("a"), F.col("o_orderkey").alias("b")).distinct()
    line = table(s, d, "lineitem")
    return [a, line.select(F.col("l_orderkey").alias("a"), F.col("l_partkey").alias("b")).distinct(), line.select(F.col("l_partkey").alias("a"), F.col("l_suppkey").alias("b")).distinct()]


register(
    "b_min_rank_chain", lambda s, d: baselines.min_rank_chain(chain(s, d)).select(F.round("z_hat").cast("long").alias("z_hat")),
    f"""with a as (select distinct c_nationkey as n, o_orderkey as o from customer join orders on c_custkey = o_custkey), b as (select distinct l_orderkey as o, l_partkey as p from lineitem),
    c as (select distinct l_partkey as p, l_suppkey as s from lineitem), rr as (select unnest(range(1, 65)) as i), rk as (select s, i, {_unit('s', 'i')} as x from (select distinct s from c), rr),
    m1 as (select p, i, min(x) as x from c join rk using (s) group by p, i), m2 as (select o, i, min(x) as x from b join m1 using (p) group by o, i),
    m3 as (select n, i, min(x) as x from a join m2 using (o) group by n, i) select cast(round(sum(v)) as bigint) as z_hat from (select 63 / sum(x) as v from m3 group by n)""",
)
register("b_explicit", lambda s, d: slim(baselines.explicit_bottomk(rel(s, d, "part_part_order"), BASE)), O.estimate("part_part_order", policy="one"))


def b_space_bound(s, d):
    r = rel(s, d, "part_part_order")
    n = profile(r).first()
    z = baselines.exact_size(r).first()["z"]
    return _rows(s, "tuples double", (round(bounds.prior_space_bound(n["n1"], n["n2"], z, 0.25), 3),))


register("b_space_bound", b_space_bound, f"select round(least(n1 + n2, sqrt(n1::double * n2 / ({1 / 6!r}::double * z)) / 0.25), 3) as tuples from ({O.profile('part_part_order')}), ({O.exact('part_part_order')})")
register("b_hll", lambda s, d: baselines.builtin_hll(rel(s, d, "part_part_order")))
register("b_theta", lambda s, d: baselines.builtin_theta(rel(s, d, "part_part_order")))
register("b_tuple_sample", lambda s, d: baselines.tuple_sample_size(rel(s, d, "part_part_order"), 0.1))
register("b_catalyst", lambda s, d: baselines.catalyst_size(rel(s, d, "part_part_order")))

# ---- measures ------------------------------------------------------------------------

RUNS = range(1, 61)


def ratio_runs(s: SparkSession, d: str, name: str, k: int, runs: range = RUNS) -> DataFrame:
    """Runs with their ratios to the exact size.

    The published runs begin at p = 1 and end below it; any threshold that all
    sets pass gives the same sets, so one with 4k expected pairs is tried first.
    """
    r = exact.stored_rel(rel(s, d, name))
    with released(s):
        z = exact.size(r).first()["z"]
    return measures.with_ratio(runs_from_one(r, (k,), runs, z)[k], z)


def _ratios_sql(name: str, k: int, runs: range = RUNS) -> str:
    """All runs in one statement: distinct values are hashed for each run."""
    return (
        f"with {O.sides(name)}, z as (select count(*) as z from (select distinct lk, rk from l join r using (jk))), zz as (select distinct lk, rk from l join r using (jk)), "
        f"rr as (select unnest(range({runs.start}, {runs.stop})) as run), "
        f"lv as (select run, lk, {O.digest(chr(39) + 'L' + chr(39) + ' || run || ' + chr(39) + ':' + chr(39), 'lk')} as x_h from (select distinct lk from l), rr), "
        f"rv as (select run, rk, {O.digest(chr(39) + 'R' + chr(39) + ' || run || ' + chr(39) + ':' + chr(39), 'rk')} as y_h from (select distinct rk from r), rr), "
        f"pp as (select lv.run, (x_h - y_h) & {O.MASK} as pair_h, row_number() over (partition by lv.run order by (x_h - y_h) & {O.MASK}, x_h, y_h) as i from zz join lv on zz.lk = lv.lk join rv on zz.rk = rv.rk and rv.run = lv.run), "
        f"ee as (select run, count(*) as kept, max(pair_h) as kth from pp where i <= {k} group by run) "
        f"select cast(run as integer) as run, kept, kth as kth_hash, case when kept >= {k} then {float(k * D)!r}::double / greatest(kth, 1) else kept end / z.z as ratio from ee, z"
    )


for k in (256, 1024):
    register(
        f"x_cdf_k{k}",
        lambda s, d, k=k: measures.ratio_cdf(ratio_runs(s, d, "dim_dim", k)).select(F.round("ratio", 6).alias("ratio"), F.round("cdf", 6).alias("cdf")),
        f"select round(ratio, 6) as ratio, round(cume_dist() over (order by ratio), 6) as cdf from ({_ratios_sql('dim_dim', k)})",
    )
register(
    "x_ratio", lambda s, d: ratio_runs(s, d, "dim_dim", 256).select("run", "kept", "kth_hash", F.round("ratio", 6).alias("ratio")),
    f"select run, kept, kth_hash, round(ratio, 6) as ratio from ({_ratios_sql('dim_dim', 256)})",
)
_TWO_THIRDS = "select round(min(e), 6) as error from (select e, row_number() over (order by e) as i, count(*) over () as n from (select abs(ratio - 1) as e from ({}))) where i * 3 >= 2 * n"
register("x_two_thirds", lambda s, d: measures.two_thirds_error(ratio_runs(s, d, "dim_dim", 256)).select(F.round("error", 6).alias("error")), _TWO_THIRDS.format(_ratios_sql("dim_dim", 256)))
register(
    "x_success", lambda s, d: measures.success_share(ratio_runs(s, d, "cust_type", 256), bounds.eps_for(256)).select(F.round("share", 6).alias("share")),
    f"select round(avg(case when abs(ratio - 1) <= 0.1875 then 1 else 0 end), 6) as share from ({_ratios_sql('cust_type', 256)})",
)
register(
    "x_failure_split", lambda s, d: measures.failure_split(ratio_runs(s, d, "cust_type", 256), bounds.eps_for(256), 256),
    f"select avg(case when kept >= 256 and ratio > 1.1875 then 1 else 0 end) as over, avg(case when kept >= 256 and ratio < 0.8125 then 1 else 0 end) as under, avg(case when kept < 256 then 1 else 0 end) as unfilled from ({_ratios_sql('cust_type', 256)})".replace(" as over", ' as "over"'),
)
#: Instances of the error and sampling studies; the SQL of the larger ones takes too long, tests recompute them in numpy.
INSTANCES = ("part_part_order", "freq_parts", "supp_cust_order", "cust_type", "dim_dim", "vec_vec", "supp_supp_order", "cust_cust_part", "doc_doc_word")
STUDIED_BY_SQL = ("supp_cust_order", "cust_type", "dim_dim", "vec_vec", "supp_supp_order")


def study(s: SparkSession, d: str, name: str) -> DataFrame:
    """A row for each k: error of the theory and of two thirds of 60 runs, quartiles of the ratio, success, unfilled runs, mean ratio."""
    rows = []
    r = exact.stored_rel(rel(s, d, name))
    with released(s):
        z = exact.size(r).first()["z"]
    for k, found in runs_from_one(r, (256, 1024), RUNS, z).items():
        runs = measures.with_ratio(found, z)
        eps = bounds.eps_for(k)
        shares = runs.agg(
            F.round(F.min("ratio"), 6).alias("lowest"), F.round(F.percentile("ratio", F.lit(0.5)), 6).alias("middle"), F.round(F.max("ratio"), 6).alias("highest"),
            F.round(F.avg((F.abs(F.col("ratio") - 1) <= eps).cast("int")), 6).alias("success"), F.round(F.avg((F.col("kept") < k).cast("int")), 6).alias("unfilled"), F.round(F.avg("ratio"), 6).alias("mean_ratio"),
        )
        error = measures.two_thirds_error(runs).select(F.lit(k).alias("k"), F.lit(round(eps, 6)).alias("theory"), F.round("error", 6).alias("error"))
        rows.append(error.crossJoin(shares))
    return _union(rows)


def _study_sql(name: str) -> str:
    return " union all ".join(
        f"select {k} as k, round(3 / sqrt({k}::double), 6) as theory, (" + _TWO_THIRDS.format(_ratios_sql(name, k)) + f") as error, round(min(ratio), 6) as lowest, round(median(ratio), 6) as middle, round(max(ratio), 6) as highest, "
        f"round(avg(case when abs(ratio - 1) <= 3 / sqrt({k}::double) then 1 else 0 end), 6) as success, round(avg(case when kept < {k} then 1 else 0 end), 6) as unfilled, round(avg(ratio), 6) as mean_ratio from ({_ratios_sql(name, k)})"
        for k in (256, 1024)
    )


def sample_study(s: SparkSession, d: str, name: str) -> DataFrame:
    """A row for each rate: 60 runs of samples with a sketch of 1024 inside; theory, error of two thirds of the runs with an estimate, share of empty runs, mean ratio."""
    r = exact.stored_rel(rel(s, d, name))
    with released(s):
        z = exact.size(r).first()["z"]
        n = exact.matched(r).first()
    rows = []
    for p in (0.1, 0.01):
        runs = measures.with_ratio(sample_sketches(r, p, p, RUNS, 1024, z), z)
        theory = bounds.sample_eps(z, n["n_a"], n["n_c"], p, p)
        error = measures.two_thirds_error(runs).select(F.lit(p).alias("p"), F.lit(round(theory, 6)).alias("theory"), F.round("error", 6).alias("error"))
        shares = runs.agg(F.round(F.avg((F.col("kept") == 0).cast("int")), 6).alias("empty"), F.round(F.avg(F.coalesce("ratio", F.lit(0.0))), 6).alias("mean_ratio"), F.sum("kept").alias("kept"))
        rows.append(error.crossJoin(shares))
    return _union(rows)


def _sample_study_sql(name: str, k: int = 1024) -> str:
    parts = []
    for p in (0.1, 0.01):
        t = sampling.sample_threshold(p, "md5_60")
        seed = lambda side: f"'{side}' || run || ':'"
        parts.append(
            f"select * from (with {O.sides(name)}, rr as (select unnest(range(1, 61)) as run), zz as (select distinct lk, rk from l join r using (jk)), "
            "g as (select count(*) as z, count(distinct lk) as n_a, count(distinct rk) as n_c from zz), "
            f"cl as (select run, lk, {O.digest(seed('L'), 'lk')} as x_h from (select distinct lk from l), rr where {O.digest(seed('SL'), 'lk')} < {t}), "
            f"cr as (select run, rk, {O.digest(seed('R'), 'rk')} as y_h from (select distinct rk from r), rr where {O.digest(seed('SR'), 'rk')} < {t}), "
            "pr as (select distinct run, lk, rk, x_h, y_h from (select run, lk, jk, x_h from l join cl using (lk)) a join (select run, rk, jk, y_h from r join cr using (rk)) b using (run, jk)), "
            f"ranked as (select run, (x_h - y_h) & {O.MASK} as h, row_number() over (partition by run order by (x_h - y_h) & {O.MASK}, x_h, y_h) as i from pr), "
            f"one as (select run, count(*) as kept, max(h) as kth from ranked where i <= {k} group by run), "
            f"e as (select rr.run, coalesce(kept, 0) as kept, case when kept >= {k} then {float(k * D)!r}::double / greatest(kth, 1) else kept end / ({p}::double * {p}::double) / g.z as ratio from rr left join one on rr.run = one.run, g), "
            "o as (select abs(ratio - 1) as e, row_number() over (order by abs(ratio - 1)) as i, count(*) over () as n from e where ratio is not null) "
            f"select {p}::double as p, (select round(sqrt(14.0::double * (n_c / {p}::double + n_a / {p}::double) / z), 6) from g) as theory, (select round(min(e), 6) from o where i * 3 >= 2 * n) as error, "
            "round(avg(case when kept = 0 then 1 else 0 end), 6) as empty, round(avg(coalesce(ratio, 0)), 6) as mean_ratio, cast(sum(kept) as bigint) as kept from e)"
        )
    return " union all ".join(parts)


for n in INSTANCES:
    register(f"x_study_{n}", lambda s, d, n=n: study(s, d, n), _study_sql(n) if n in STUDIED_BY_SQL else None)
    register(f"x_sample_study_{n}", lambda s, d, n=n: sample_study(s, d, n), _sample_study_sql(n))
for label, p in (("10", 0.1), ("01", 0.01)):
    register(
        f"x_sample_{label}",
        lambda s, d, p=p: sampling.sample_runs(rel(s, d, "dim_dim"), p, p, RUNS).select(F.col("run").cast("long").alias("run"), "kept", F.round("z_hat", 3).alias("z_hat")),
        f"select run, kept, round(z_hat, 3) as z_hat from ({_sample_runs_sql('dim_dim', p, 60)})",
    )
register(
    "x_empty_share", lambda s, d: measures.empty_share(sampling.sample_runs(rel(s, d, "cust_type"), 0.1, 0.1, RUNS)),
    f"select avg(case when kept = 0 then 1 else 0 end) as share from ({_sample_runs_sql('cust_type', 0.1, 60)})",
)


def x_bias(s, d):
    """Mean ratio of 60 sample estimates to the exact size, empty runs as 0: 1 without bias."""
    found = exact.samples(exact.stored_rel(rel(s, d, "vec_vec")), 0.1, 0.1, RUNS)
    return measures.mean_ratio(found.select((F.col("kept") / (0.1 * 0.1) / F.col("z")).alias("ratio"))).select(F.round("mean_ratio", 6).alias("mean_ratio"))


register("x_bias", x_bias, f"select round(avg(coalesce(z_hat, 0)) / any_value(z.z), 6) as mean_ratio from ({_sample_runs_sql('vec_vec', 0.1, 60)}), ({O.exact('vec_vec')}) z")
_DEGREES = (
    "with {0}, zz as (select distinct lk, rk from l join r using (jk)) select (select count(*) from zz) as z, (select count(distinct lk) from zz) as n_a, (select count(distinct rk) from zz) as n_c, "
    "(select cast(sum(d * d) as bigint) from (select count(*) as d from zz group by lk)) as row_squares, (select cast(sum(d * d) as bigint) from (select count(*) as d from zz group by rk)) as col_squares"
)


def _variance(s, d, whole: bool):
    r = measures.degree_squares(baselines.join_project(rel(s, d, "part_part_order"))).first()
    v = bounds.variance_exact(r["row_squares"], r["col_squares"], r["z"], 0.1, 0.1) if whole else bounds.variance_bound(r["z"], r["n_a"], r["n_c"], 0.1, 0.1)
    return _rows(s, "variance long", (round(v),))


register("x_variance_bound", lambda s, d: _variance(s, d, False), f"select cast(round((n_c / 0.1::double + n_a / 0.1::double + 1 / (0.1::double * 0.1::double)) * z) as bigint) as variance from ({_DEGREES.format(O.sides('part_part_order'))})")
register(
    "x_variance_exact", lambda s, d: _variance(s, d, True),
    f"select cast(round((0.01::double * 0.09 * row_squares + 0.01::double * 0.09 * col_squares + z * 0.09::double * 0.09) / 0.0001::double) as bigint) as variance from ({_DEGREES.format(O.sides('part_part_order'))})",
)


def x_work(s, d):
    r = rel(s, d, "part_part_order")
    return measures.work_profile(r, BASE, choose_threshold(r, BASE)).select("hits", "joined", "n1", "n2", "probes")


def _cells_sql(name: str, shift: int, cells: int) -> str:
    return f"(select jk, x_h >> {shift} as c, x_h from lh) a join (select jk, y_h, unnest(case when {cells} = 1 then [0] else [y_h >> {shift}, ((y_h >> {shift}) + 1) % {cells}] end) as c from rh) b using (jk, c)"


register(
    "x_work", x_work,
    f"with {O.found('part_part_order')}, m as (select cast(floor(log2(1 / p)) as integer) as e from th), "
    "a as (select jk, x_h, x_h >> (60 - e) as c from lh, m), b as (select jk, y_h, unnest([y_h >> (60 - e), ((y_h >> (60 - e)) + 1) % (1::bigint << e)]) as c from rh, m), "
    f"pr as (select count(*) as probes, cast(sum(case when ((x_h - y_h) & {O.MASK}) < t then 1 else 0 end) as bigint) as hits from a join b using (jk, c), th) "
    "select hits, joined, (select count(*) from l) as n1, (select count(*) from r) as n2, probes from pr, st",
)
register("x_moves", lambda s, d: measures.scan_counters(rel(s, d, "cust_type"), BASE, 0.01).select("left_rows", "right_rows", "moves", "visited"))
register("x_selections", lambda s, d: measures.scan_counters(rel(s, d, "cust_type"), replace(BASE, k=16), 1.0).select("selections", "inserts", "visited", "first_t", "last_t"))
register(
    "x_first_last_p",
    lambda s, d: measures.thresholds(run_estimates(rel(s, d, "supp_cust_order"), replace(BASE, policy="one"), range(1, 11), 1.0), 256, D).select(
        "run", "first_p", F.round("last_p", 9).alias("last_p"), (F.col("last_p") < 1 / 256).alias("below")
    ),
    "select run, 1.0::double as first_p, round(case when kept >= 256 then kth / " + repr(float(D)) + "::double else 1 end, 9) as last_p, "
    "case when kept >= 256 then kth / " + repr(float(D)) + "::double else 1 end < 1 / 256.0::double as below from (" + " union all ".join(
        f"select {r} as run, * from (with {O.found('supp_cust_order', policy='one', run=r)}, {O.kept(256)} select count(*) as kept, max(pair_h) as kth from ks)" for r in range(1, 11)
    ) + ")",
)


def x_io(s, d):
    """Rows that the single scan sorts, and the transfers of sorting them, beside rows that the whole join would make."""
    r = rel(s, d, "part_part_order")
    n = profile(r).first()
    rows = n["n1"] + 2 * n["n2"]
    return _rows(s, "sorted_rows long, transfers double, joined long", (rows, round(bounds.sort_bound(rows, 64, 1024), 3), n["joined"]))


register("x_io", x_io, f"select n1 + 2 * n2 as sorted_rows, round((n1 + 2 * n2) / 64.0::double * greatest(1.0, log2((n1 + 2 * n2) / 64.0::double) / log2(16.0::double)), 3) as transfers, joined from ({O.profile('part_part_order')})")


def x_io_measured(s, d):
    """Bytes that the executors read and shuffled for the kept set, by strategy."""
    r, out = rel(s, d, "part_part_order"), []
    p = choose_threshold(r, BASE)
    for strategy in ("cells", "sweep", "full"):
        got = measures.io_profile(s, lambda st=strategy: k_smallest(hits(r, replace(BASE, strategy=st), p), 256).collect())
        out.append((strategy, got["input"], got["shuffle_read"], got["shuffle_write"]))
    return _rows(s, "strategy string, input long, shuffle_read long, shuffle_write long", *out)


register("x_io_measured", x_io_measured)


def x_profile(s, d):
    """Sizes of every instance beside the error that sampling a tenth and a hundredth of it promises."""
    frames = []
    for n in INSTANCES:
        r = exact.stored_rel(rel(s, d, n))
        z, theory = F.col("z"), lambda p: F.round(F.sqrt(14.0 * (F.col("n_c") / p + F.col("n_a") / p) / F.col("z")), 6)
        frames.append(profile(r).crossJoin(exact.size(r)).select(F.lit(n).alias("workload"), "n_a", "n_c", "n1", "n2", "joined", "maxprod", z, theory(0.1).alias("eps10"), theory(0.01).alias("eps01")))
    return _union(frames)


register(
    "x_profile", x_profile,
    " union all ".join(
        f"select '{n}' as workload, n_a, n_c, n1, n2, joined, maxprod, z, round(sqrt(14.0::double * (n_c / 0.1::double + n_a / 0.1::double) / z), 6) as eps10, "
        f"round(sqrt(14.0::double * (n_c / 0.01::double + n_a / 0.01::double) / z), 6) as eps01 from ({O.profile(n)}), ({O.exact(n)})"
        for n in INSTANCES
    ),
)

# ---- closed forms --------------------------------------------------------------------


def blocks(s: SparkSession, d: str) -> DataFrame:
    """(k, z): the sizes of suppliers' blocks in lineitem, n lines each, and the pairs of a block with itself."""
    sizes = table(s, d, "lineitem").groupBy("l_suppkey").agg(F.count("*").alias("k"))
    return sizes.select("k", (F.col("k") * F.col("k")).alias("z")).distinct()


_BLOCKS = "(select distinct n as k, n * n as z from (select count(*) as n from lineitem group by l_suppkey))"
_EPS = (0.1875, 0.09375, 0.05)
_EACH = "(select unnest([" + ", ".join(f"{e!r}::double" for e in _EPS) + "]) as eps)"


def _tail(bound):
    """A bound at each block's size as k and each error."""
    def run(s: SparkSession, d: str) -> DataFrame:
        each = F.explode(F.array(*[F.lit(e) for e in _EPS])).alias("eps")
        return blocks(s, d).select("k", each).select("k", "eps", F.round(bound(F.col("eps"), F.col("k")), 9).alias("bound"))

    return run


register("c_overshoot", _tail(bounds.overshoot), f"select k, eps, round((1 + eps) / (k * (eps * eps)), 9) as bound from {_BLOCKS}, {_EACH}")
register("c_undershoot", _tail(bounds.undershoot), f"select k, eps, round((1 - eps) / (k * (eps * eps)), 9) as bound from {_BLOCKS}, {_EACH}")
_KS = (16, 256, 1024)
_EACH_K = "(select unnest([" + ", ".join(map(str, _KS)) + "]) as k)"


def _by_k(s: SparkSession, d: str, kind: str, value) -> DataFrame:
    """A closed form of (z, k) at each block's pairs and three k; the distinct z are few, and go through Python."""
    form = F.udf(value, kind)
    return blocks(s, d).select(F.explode(F.array(*[F.lit(k) for k in _KS])).alias("k"), "z").select("k", "z", form("z", "k").alias("v"))


register(
    "c_unfilled", lambda s, d: _by_k(s, d, "double", lambda z, k: bounds.unfilled(z, 2 / k, k)).select("k", "z", F.round("v", 9).alias("bound")),
    f"select k.k, z, round(case when z * (2.0::double / k.k) > k.k then z * (2.0::double / k.k) / power(z * (2.0::double / k.k) - k.k, 2) else 1 end, 9) as bound from {_BLOCKS} b, {_EACH_K} k",
)
register("c_regime", lambda s, d: _by_k(s, d, "string", bounds.regime).withColumnRenamed("v", "regime"), f"select k.k, z, case when z > k.k * k.k then 'guarantee' else 'bound' end as regime from {_BLOCKS} b, {_EACH_K} k")
#: Failure chances and errors: the discounts of the lines, from 0.01.
_RATES = "(select distinct l_discount as x from lineitem where l_discount >= 0.01)"


def _by_rate(s: SparkSession, d: str, name: str, out: str, value) -> DataFrame:
    rates = table(s, d, "lineitem").where("l_discount >= 0.01").select(F.col("l_discount").alias(name)).distinct()
    return rates.select(name, F.udf(value, "int")(name).alias(out))


register(
    "c_runs_for",
    lambda s, d: _by_rate(s, d, "delta", "runs", bounds.runs_for),
    "with recursive f(n, x) as (select 0, 1.0::double union all select n + 1, x * (n + 1) from f where n < 100), "
    "tail as (select r, sum(a.x / (b.x * c.x) * power(2.0, r - i)) / power(3.0::double, r) as fails from (select unnest(range(1, 100, 2)) as r), lateral (select unnest(range((r + 1) // 2, r + 1)) as i), f a, f b, f c where a.n = r and b.n = i and c.n = r - i group by r) "
    f"select x as delta, cast(min(r) as integer) as runs from tail, {_RATES} where fails <= x group by x",
)
register(
    "c_work_ok",
    lambda s, d: measures_work(s, d),
    " union all ".join(
        f"select '{policy}' as policy, count(*) as groups, cast(sum(case when p * ln * rn <= {2 if policy == 'doubled' else 1} * greatest(ln, rn) then 1 else 0 end) as bigint) as within, "
        f"round(sum(p * ln * rn), 3) as expected from (with {O.sides('cust_cust_part')}, {O.stats()} select gs.*, {O.p_of(256, policy)} as p from gs, st)"
        for policy in ("doubled", "printed")
    ),
)
register(
    "c_deviation",
    lambda s, d: _deviation(s, d),
    f"select round((n_c * n1 + n_a * n2 + n1::double * n2 / 20000.0) / (20000.0::double * 0.0625 * z), 9) as bound from ({O.profile('part_part_order')}), ({O.exact('part_part_order')})",
)
register("c_rounds_for", lambda s, d: _by_rate(s, d, "eps", "rounds", bounds.rounds_for), f"select x as eps, cast(ceil(1 / (x * x) - 1e-9) as integer) + 1 as rounds from {_RATES}")


def measures_work(s, d):
    """Groups whose expected hits stay within their size, and the expected hits of all, by policy."""
    sizes = group_sizes(rel(s, d, "cust_cust_part"))
    frames = []
    for policy in ("doubled", "printed"):
        p = choose_threshold(rel(s, d, "cust_cust_part"), replace(BASE, policy=policy))
        hits_ = F.lit(p) * F.col("l") * F.col("r")
        fine = hits_ <= (2 if policy == "doubled" else 1) * F.greatest("l", "r")
        frames.append(sizes.agg(F.lit(policy).alias("policy"), F.count("*").alias("groups"), F.sum(fine.cast("long")).alias("within"), F.round(F.sum(hits_), 3).alias("expected")))
    return _union(frames)


def _deviation(s, d):
    r = rel(s, d, "part_part_order")
    n, z = profile(r).first(), baselines.exact_size(r).first()["z"]
    return _rows(s, "bound double", (round(bounds.deviation_bound(n["n1"], n["n2"], n["n_a"], n["n_c"], 20_000, 0.25, z), 9),))


#: Published instances, z, n_a, and theoretical errors at the rates 0.1 and 0.01.
PUBLISHED = [
    ("accidents", 94e3, 468, 1.18, 3.73),
    ("bms-pos", 760e3, 1657, 0.78, 2.47),
    ("bms-webview-1", 128e3, 497, 1.04, 3.29),
    ("bms-webview-2", 1.45e6, 3340, 0.80, 2.54),
    ("chess", 5.24e3, 75, 2.00, 6.33),
    ("connect", 13.8e3, 129, 1.62, 5.12),
    ("directoractor", 734e6, 50645, 0.14, 0.44),
    ("kosarak", 66.2e6, 41270, 0.42, 1.32),
    ("movieactor", 111e6, 51226, 0.36, 1.14),
    ("mushroom", 7.17e3, 119, 2.16, 6.82),
    ("pumsb", 1.07e6, 2113, 0.74, 2.35),
    ("pumsb_star", 967e3, 2088, 0.78, 2.46),
    ("retail", 7.19e6, 16470, 0.80, 2.53),
]


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def x_published_bounds(s, d):
    rows = [(n, round(bounds.sample_eps(z, a, a, 0.1, 0.1), 4), round(bounds.sample_eps(z, a, a, 0.01, 0.01), 4), bounds.vacuous(bounds.sample_eps(z, a, a, 0.1, 0.1))) for n, z, a, _, _ in PUBLISHED]
    return _rows(s, "instance string, eps10 double, eps01 double, vacuous boolean", *rows)


register(
    "x_published_bounds", x_published_bounds,
    "select n as instance, round(sqrt(28.0::double * a / (0.1::double * z)), 4) as eps10, round(sqrt(28.0::double * a / (0.01::double * z)), 4) as eps01, sqrt(28.0::double * a / (0.1::double * z)) > 1 as vacuous from (values "
    + ", ".join(f"('{n}', {z!r}::double, {a})" for n, z, a, _, _ in PUBLISHED) + ") v(n, z, a)",
)


def x_bound_vs_observed(s, d):
    frames = [measures.two_thirds_error(ratio_runs(s, d, "dim_dim", k)).select(F.lit(k).alias("k"), F.lit(round(bounds.eps_for(k), 6)).alias("theory"), F.round("error", 6).alias("observed")) for k in (256, 1024)]
    return _union(frames)


register(
    "x_bound_vs_observed", x_bound_vs_observed,
    " union all ".join(f"select {k} as k, round(3 / sqrt({k}::double), 6) as theory, error as observed from ({_TWO_THIRDS.format(_ratios_sql('dim_dim', k))})" for k in (256, 1024)),
)
register("x_space", lambda s, d: _rows(s, "k int, bits long", *[(k, bounds.space_bits(k)) for k in (256, 1024)]), "select k, cast(120 * k as bigint) as bits from (values (256), (1024)) v(k)")


def x_sort_bound(s, d):
    n = profile(rel(s, d, "part_part_order")).first()
    return _rows(s, "transfers double", (round(bounds.sort_bound(n["n1"] + n["n2"], 64, 1024), 3),))


register("x_sort_bound", x_sort_bound, f"select round((n1 + n2) / 64.0::double * greatest(1.0, log2((n1 + n2) / 64.0::double) / log2(16.0::double)), 3) as transfers from ({O.profile('part_part_order')})")
register("x_rounding", lambda s, d: _rows(s, "risk double", (rounding_risk(1024, 10**12, 2**63),)), f"select 1024.0::double * 1e12 / {float(2**63)!r}::double as risk")

# ---- applications --------------------------------------------------------------------


def app_allocate(s, d):
    return applications.allocate(rel(s, d, "freq_parts"), 16, BASE).select(F.round("z_hat").cast("long").alias("z_hat"), "bytes")


register(
    "app_allocate", app_allocate,
    f"select z_hat, cast(ceil(case when kth_hash is null then 1.1875 * 65536 else {256.0 * D!r}::double / greatest(kth_hash, 1) / (1 - 0.1875) end * 16) as bigint) as bytes from ({O.estimate('freq_parts')})",
)


def app_chain_order(s, d):
    """Two-factor sizes by the estimator (counting where unfilled), the order by dynamic programming."""
    a, b, c = chain(s, d)
    pair = lambda x, y: Rel(x.select(F.col("a").alias("lk"), F.col("b").alias("jk")), y.select(F.col("a").alias("jk"), F.col("b").alias("rk")))
    spec = replace(BASE, on_short="count")
    ab, bc = applications.size_of(pair(a, b), spec), applications.size_of(pair(b, c), spec)
    text, _ = applications.order_chain(["A", "B", "C"], {(0, 1): ab, (1, 2): bc, (0, 2): 0.0})
    return _rows(s, "chain string, z_ab long, z_bc long", (text, int(ab + 0.5), int(bc + 0.5)))


def _pair_sql(left: str, right: str) -> str:
    return O.estimate("part_part_order", short="e.kept / th.p").replace(O.sides("part_part_order"), f"l as ({left}), r as ({right})")


_A = "select distinct c_nationkey as lk, o_orderkey as jk from customer join orders on c_custkey = o_custkey"
register(
    "app_chain_order", app_chain_order,
    f"select case when a.z_hat <= b.z_hat then '((AB)C)' else '(A(BC))' end as chain, a.z_hat as z_ab, b.z_hat as z_bc from ({_pair_sql(_A, 'select distinct l_orderkey as jk, l_partkey as rk from lineitem')}) a, "
    f"({_pair_sql('select distinct l_orderkey as lk, l_partkey as jk from lineitem', 'select distinct l_partkey as jk, l_suppkey as rk from lineitem')}) b",
)
SUPPORTS = [20, 30, 35, 40]


def app_choose_support(s, d):
    line = table(s, d, "lineitem")
    budget = 60_000.0
    chosen, _ = applications.choose_support(line, "l_partkey", "l_orderkey", SUPPORTS, budget, replace(BASE, on_short="count"))
    return _rows(s, "support int", (chosen,))


def _support_sql(n: int) -> str:
    one = f"select distinct l_partkey as lk, l_orderkey as jk from lineitem where l_partkey in (select l_partkey from lineitem group by 1 having count(distinct l_orderkey) >= {n})"
    return f"select {n} as s, z_hat from ({_pair_sql(one, f'select jk, lk as rk from ({one})')})"


register("app_choose_support", app_choose_support, "select cast(min(s) as integer) as support from (" + " union all ".join(map(_support_sql, SUPPORTS)) + ") where z_hat <= 60000")


def app_advise_join(s, d):
    r = rel(s, d, "cust_cust_part")
    joined = profile(r).first()["joined"]
    a = applications.advise_join(applications.size_of(r, BASE), joined)
    return _rows(s, "strategy string, partitions int", (a.strategy, a.partitions))


register(
    "app_advise_join", app_advise_join,
    f"select case when z_hat * 16 <= 10000000 then 'broadcast' when joined > 2 * z_hat then 'early_distinct' else 'shuffle' end as strategy, cast(greatest(1, ceil(z_hat * 16 / 128000000.0)) as integer) as partitions from ({O.estimate('cust_cust_part')}), ({O.profile('cust_cust_part')})",
)
