"""Hand examples, closed forms, guards and plans of the estimators."""

import itertools
from math import isclose, sqrt

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from sparsepairs.functions import bounds, hashing
from sparsepairs.operators import applications, baselines, measures, sampling
from sparsepairs.operators.estimate import Spec, as_threshold, cells_for, estimate_size, hashed, hits, hits_by_sweep, k_smallest, kept_set, run_estimates, walk_group
from sparsepairs.operators.relations import Rel, cluster, drop_dangling, normalize, profile, self_rel
from sparsepairs.operators.scan import BottomK, Scan
from sparsepairs.plans import methods
from sparsepairs.plans.methods import PUBLISHED
from sparsepairs.plans.workloads import WORKLOADS

EXACT = Spec(k=256, family="md5_60", policy="one")


def make(spark, left, right):
    return Rel(spark.createDataFrame(left, "lk long, jk long"), spark.createDataFrame(right, "jk long, rk long"))


def size(rel):
    return estimate_size(rel, EXACT).first()


@pytest.mark.parametrize(
    "left, right, z",
    [
        ([(1, 1)], [(1, 1)], 1),
        ([(a, 1) for a in range(4)], [(1, c) for c in range(3)], 12),
        ([(a, 1) for a in range(3)] + [(a + 9, 2) for a in range(3)], [(1, c) for c in range(3)] + [(2, c + 9) for c in range(3)], 18),
        ([(a, j) for a in range(2) for j in range(100)], [(j, c) for c in range(2) for j in range(100)], 4),
        ([(a, 1) for a in range(4)] + [(9, 8)], [(1, c) for c in range(3)], 12),
    ],
)
def test_hand_sizes(spark, left, right, z):
    rel = make(spark, left, right)
    row = size(rel)
    assert (row["kept"], row["z_hat"], row["status"]) == (z, z, "exact")
    assert baselines.exact_size(rel).first()["z"] == baselines.exact_by_left(rel).first()["z"] == z


def test_empty_and_nulls(spark):
    assert size(make(spark, [(1, 1)], [(2, 1)]))["status"] == "empty"
    df = spark.createDataFrame([(None, 1), (5, 1), (6, None)], "a long, j long")
    rel = normalize(df, df, "a", "a", "j")
    assert rel.left.count() == 2 and size(rel)["kept"] == 4
    with pytest.raises(TypeError):
        normalize(spark.sql("select map(1, 2) as m, 1 as j"), df, "m", "a", "j")


def test_dangling_and_profile(spark):
    rel = drop_dangling(make(spark, [(1, 1), (2, 7)], [(1, 3), (9, 3)]))
    assert rel.left.count() == rel.right.count() == 1
    p = profile(make(spark, [(a, 1) for a in range(4)], [(1, c) for c in range(3)])).first()
    assert (p["n1"], p["n2"], p["n_a"], p["n_c"], p["joined"], p["maxprod"]) == (4, 3, 4, 3, 12, 12)
    assert cluster(rel, "sort").left.count() == 1


@given(st.lists(st.integers(0, 15), max_size=12), st.lists(st.integers(0, 15), max_size=12), st.integers(1, 16))
@settings(max_examples=200, deadline=None)
def test_walk_group_is_the_cyclic_range(xs, ys, t):
    x, y, moves, visited = walk_group(np.array(xs, np.int64), np.array(ys, np.int64), t, 16)
    want = {(a, b) for a in set(xs) for b in set(ys) if (a - b) % 16 < t}
    assert set(zip(x.tolist(), y.tolist())) == want and visited == len(want)
    # The start cursor, walked step by step.
    left, at, steps = sorted(set(xs)), 0, 0
    for b in sorted(set(ys)) if left else []:
        while at < len(left) and left[at] < b:
            at, steps = at + 1, steps + 1
    assert moves == steps <= 2 * max(1, len(left))


def test_hand_trace():
    x, y, *_ = walk_group(np.array([1, 6, 13]), np.array([12, 5]), 4, 16)
    assert set(zip(x.tolist(), y.tolist())) == {(13, 12), (6, 5)}
    x, y, *_ = walk_group(np.array([1, 6, 13]), np.array([14]), 4, 16)
    assert list(zip(x.tolist(), y.tolist())) == [(1, 14)]
    assert cells_for(0.25, 16) == (4, 4)


@pytest.mark.parametrize("p", [1.0, 0.5, 1 / 3, 1 / 64, 1e-5])
def test_strategies_agree(spark, sf, p):
    rel = WORKLOADS["dim_dim"].build(spark, sf)
    want = None
    for strategy in ("full", "cells", "sweep", "grouped"):
        got = {tuple(r) for r in hits(rel, Spec(k=64, family="md5_60", strategy=strategy), p).distinct().collect()}
        want = got if want is None else want
        assert got == want, strategy


@given(st.lists(st.tuples(st.integers(0, 50), st.integers(0, 9), st.integers(0, 9)), max_size=80), st.integers(1, 10), st.integers(1, 79))
@settings(max_examples=100, deadline=None)
def test_kept_sets_merge(rows, k, cut):
    def state(part):
        s = BottomK(k)
        a = np.array(part, np.int64).reshape(-1, 3)
        for i in range(0, len(a), 7):
            s.add_batch(a[i : i + 7, 0], a[i : i + 7, 1], a[i : i + 7, 2])
        return s

    want = sorted(set(rows))[:k]
    a, b = state(rows[:cut]), state(rows[cut:])
    for s in (state(rows), a.merge(b), b.merge(a), a.merge(b).merge(b)):
        assert [tuple(r) for r in s.rows.tolist()] == want


def test_kept_set_methods_agree(spark, sf):
    found = hits(WORKLOADS["dim_dim"].build(spark, sf), Spec(k=50, family="md5_60"), 1.0)
    sets = [{tuple(r) for r in k_smallest(found, 50, m).collect()} for m in ("native", "buffer", "heap", "rank")]
    assert len(sets[0]) == 50 and all(s == sets[0] for s in sets)


def test_affine_limbs():
    alpha, beta = hashing.AFFINE61.coefficients("L1:")
    v = np.array([0, 1, 2, 12345, 2**31, 2**45 + 7, 2**61 - 2], np.int64)
    want = [(alpha * int(x) + beta) % hashing.PRIME for x in v]
    assert hashing._affine_arrays(v, alpha, beta).tolist() == want


def test_pair_hash_is_pairwise_independent_on_a_small_prime():
    p = 5
    seen = {}
    for a, b, c, d in itertools.product(range(1, p), range(p), range(1, p), range(p)):
        u = ((a * 1 + b) - (c * 2 + d)) % p
        v = ((a * 3 + b) - (c * 4 + d)) % p
        seen[u, v] = seen.get((u, v), 0) + 1
    assert len(seen) == p * p and max(seen.values()) < 2 * min(seen.values())


def test_bounds():
    assert bounds.k_for(0.1875) == 256 and isclose(bounds.eps_for(1024), 0.09375)
    assert round(bounds.eps_for(256), 3) == 0.188 and round(bounds.eps_for(1024), 3) == 0.094
    near = [(abs(bounds.sample_eps(z, a, a, p, p) - e), e) for _, z, a, e1, e2 in PUBLISHED for p, e in ((0.1, e1), (0.01, e2))]
    assert sum(d <= 0.005 + 1e-9 for d, _ in near) == 25 and max(d for d, _ in near) < 0.01
    assert isclose(bounds.constant(printed=False), 13.348, rel_tol=1e-3)
    assert bounds.overshoot(0.1875, 256) <= 1 / 6 and bounds.undershoot(0.1875, 256) <= 1 / 9 and bounds.unfilled(2 * 256, 1.0, 256) <= 1 / 18
    assert bounds.runs_for(0.34) == 1 and bounds.runs_for(0.2) % 2 == 1
    assert isclose(bounds.sample_eps(100, 5, 5, 0.1, 0.1), sqrt(28 * 5 / 10))
    with pytest.raises(ValueError):
        bounds.k_for(0.25)


def test_guards():
    assert Spec(k=100).below_guarantee and not Spec(k=144).below_guarantee
    for bad in ({"eps": 0.3}, {"policy": "x"}, {"policy": "fixed"}, {"k": 0}, {"on_short": "x"}):
        with pytest.raises(ValueError):
            Spec(**bad)
    with pytest.raises(ValueError):
        sampling.sample_side(None, "lk", 0.0, "s")


def test_accuracy_over_runs(spark, sf):
    rel = WORKLOADS["cust_cust_part"].build(spark, sf)
    z = baselines.exact_size(rel).first()["z"]
    runs = measures.with_ratio(run_estimates(rel, Spec(k=128, family="md5_60"), range(1, 31), 0.05), z).cache()
    assert runs.count() == 30 and runs.where("kept >= 128").count() == 30
    assert measures.success_share(runs, bounds.eps_for(128)).first()["share"] >= 2 / 3
    assert measures.two_thirds_error(runs).first()["error"] < 0.15


def test_sample_estimator_is_unbiased_within_its_variance(spark, sf):
    rel = WORKLOADS["dim_dim"].build(spark, sf)
    d = measures.degree_squares(baselines.join_project(rel)).first()
    runs = [r["z_hat"] or 0.0 for r in sampling.sample_runs(rel, 0.3, 0.3, range(1, 101)).collect()]
    exact = bounds.variance_exact(d["row_squares"], d["col_squares"], d["z"], 0.3, 0.3)
    assert exact <= bounds.variance_bound(d["z"], d["n_a"], d["n_c"], 0.3, 0.3)
    assert abs(np.mean(runs) - d["z"]) < 4 * sqrt(exact / len(runs))


def test_sketches_are_maintained(spark):
    rows = spark.createDataFrame([(i, i % 7) for i in range(300)], "lk long, jk long")
    whole = sampling.sample_side(rows, "lk", 0.3, "s")
    part = sampling.sample_side(rows.where("lk < 200"), "lk", 0.3, "s")
    kept = sampling.maintain(part, "lk", 0.3, "s", rows.where("lk >= 150"), rows.where("lk < 20"))
    assert {tuple(r) for r in kept.collect()} == {tuple(r) for r in whole.where("lk >= 20").collect()}
    assert {tuple(r) for r in sampling.thin(whole, "lk", 0.1, "s").collect()} == {tuple(r) for r in sampling.sample_side(rows, "lk", 0.1, "s").collect()}


def test_plan_has_equi_keys_and_no_product(spark, sf):
    found = hits(WORKLOADS["part_part_order"].build(spark, sf), Spec(k=256), 1 / 128)
    text = found._jdf.queryExecution().executedPlan().toString()
    assert "Cartesian" not in text and "NestedLoop" not in text and "cell" in text
    top = k_smallest(found, 256)._jdf.queryExecution().executedPlan().toString()
    assert "TakeOrderedAndProject" in top


def test_scan_is_pruned(spark, sf):
    from sparsepairs.sources.readers import read_relation

    text = read_relation(spark, f"{sf}/lineitem.parquet", "l_partkey", "l_orderkey", "l_quantity > 45")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,45.0)]" in text and "l_comment" not in text and "l_tax" not in text


def test_applications(spark, sf):
    assert applications.order_chain(["A", "B", "C"], {(0, 1): 10, (1, 2): 99, (0, 2): 0})[0] == "((AB)C)"
    assert applications.advise_join(10, 10).strategy == "broadcast" and applications.advise_join(1e9, 1e10).strategy == "early_distinct"
    line = spark.read.parquet(f"{sf}/lineitem.parquet")
    chosen, seen = applications.choose_support(line, "l_partkey", "l_orderkey", [1, 30, 40], 7_000, EXACT)
    assert chosen == 30 and len(seen) == 2


def test_self_join_counts_equal_pairs(spark):
    df = spark.createDataFrame([(1, 1), (2, 1)], "a long, j long")
    assert size(self_rel(df, "a", "j"))["kept"] == 4


def literal_scan(lefts, rights, t, domain):
    """Three cursors over one sorted run, a row at a time: hits, moves of the start cursor, visited pairs."""
    found, at, moves = [], 0, 0
    for kind, y in sorted(rights, key=lambda r: r[1]):
        if kind == 1:
            while at < len(lefts) and lefts[at] < y:
                at, moves = at + 1, moves + 1
        low = at if kind == 1 else 0
        end = min(y + t, domain) if kind != 3 else y + t - domain
        while low < len(lefts) and lefts[low] < end:
            found.append((lefts[low], y))
            low += 1
    return found, moves


@given(
    st.lists(st.tuples(st.integers(0, 2), st.lists(st.integers(0, 31), max_size=6), st.lists(st.integers(0, 31), max_size=6)), max_size=4), st.integers(1, 32), st.integers(1, 5)
)
@settings(max_examples=150, deadline=None)
def test_forward_scan_is_the_literal_one(groups, t, size):
    """Any cut into batches gives the hits, the cursor moves and the visited pairs of three literal cursors."""
    rows, want, moves = [], [], 0
    for jk, (_, xs, ys) in enumerate(groups):
        lefts, rights = sorted(set(xs)), [(kind, y) for y in set(ys) for kind in (1, 3)]
        rows += [(jk, 0, 0, x) for x in lefts] + [(jk, 0, kind, y) for kind, y in sorted(rights, key=lambda r: (r[1], r[0]))]
        got, steps = literal_scan(lefts, rights, t, 32)
        assert sorted(got) == sorted((x, y) for x in lefts for y in set(ys) if (x - y) % 32 < t)
        want, moves = want + got, moves + steps
    scan, found = Scan(32, t), []
    for i in range(0, len(rows), size):
        part = list(zip(*rows[i : i + size], strict=True))
        batch = pa.RecordBatch.from_arrays([pa.array(part[0], pa.int64()), pa.array(part[1], pa.int64()), pa.array(part[2], pa.int32()), pa.array(part[3], pa.int64())], names=["jk", "cell", "side", "h"])
        for x, y, h in scan.batch(batch):
            assert ((x - y) % 32 == h).all()
            found += zip(x.tolist(), y.tolist(), strict=True)
    assert sorted(found) == sorted(want) and scan.counts["moves"] == moves and scan.counts["visited"] == len(want)


@given(st.lists(st.tuples(st.integers(0, 40), st.integers(0, 5), st.integers(0, 5)), max_size=90), st.integers(1, 8), st.integers(1, 20))
@settings(max_examples=100, deadline=None)
def test_buffer_selects_when_full(rows, k, size):
    """Fed in any portions, the buffer keeps the k smallest and combines as often as one pair at a time would."""
    def run(step):
        s, a = BottomK(k), np.array(rows, np.int64).reshape(-1, 3)
        for i in range(0, len(a), step):
            s.feed(a[i : i + step, 0], a[i : i + step, 1], a[i : i + step, 2])
        return s

    one, many = run(1), run(size)
    assert (one.inserts, one.selections) == (many.inserts, many.selections)
    one.flush(), many.flush()
    assert [tuple(r) for r in one.rows.tolist()] == [tuple(r) for r in many.rows.tolist()] == sorted(set(rows))[:k]


@pytest.mark.parametrize("family", ["md5_60", "mix63", "affine61"])
@pytest.mark.parametrize("p", [1.0, 0.3, 1 / 64])
def test_scan_gives_the_hits_of_the_join(spark, sf, family, p):
    rel, spec = WORKLOADS["dim_dim"].build(spark, sf), Spec(k=64, family=family)
    sides = hashed(rel, spec, 1)
    want = {tuple(r) for r in hits(rel, Spec(k=64, family=family, strategy="full"), p).distinct().collect()}
    for how in ("hash", "range"):
        assert {tuple(r) for r in hits_by_sweep(*sides, spec, p, how=how).distinct().collect()} == want
    few = hits_by_sweep(*sides, spec, p, 64)
    assert {tuple(r) for r in k_smallest(few, 64).collect()} == set(sorted(want, key=lambda r: (r[2], r[0], r[1]))[:64])


def test_falling_threshold_saves_work(spark, sf):
    """From p = 1 every strategy keeps the same set, and the scan looks at a part of the joined pairs."""
    rel = WORKLOADS["cust_cust_part"].build(spark, sf)
    sets = [{tuple(r) for r in kept_set(rel, Spec(k=64, family="md5_60", policy="one", strategy=s, tighten=t), 1.0).collect()} for s, t in (("full", "none"), ("cells", "local"), ("sweep", "local"), ("grouped", "local"))]
    assert len(sets[0]) == 64 and all(s == sets[0] for s in sets)
    done = measures.scan_counters(rel, Spec(k=64, family="md5_60"), 1.0).first()
    joined = profile(rel).first()["joined"]
    assert done["visited"] < joined / 10 and done["last_t"] < done["first_t"] == 1.0 and done["selections"] >= done["inserts"] // 64


def test_mix63_is_checked_by_brute_force(spark, sf):
    """The default family: the kept set and the estimate, recomputed from the distinct pairs' own hashes."""
    rel = WORKLOADS["supp_cust_order"].build(spark, sf)
    a, b = (spark.createDataFrame(df.select(c).distinct().toPandas()) for df, c in ((rel.left, "lk"), (rel.right, "rk")))
    x = {r["lk"]: r["h"] for r in a.select("lk", hashing.MIX63.hash(F.col("lk"), "L1:").alias("h")).collect()}
    y = {r["rk"]: r["h"] for r in b.select("rk", hashing.MIX63.hash(F.col("rk"), "R1:").alias("h")).collect()}
    pairs = sorted({((x[r["lk"]] - y[r["rk"]]) % 2**63, x[r["lk"]], y[r["rk"]]) for r in baselines.join_project(rel).collect()})
    kept = kept_set(rel, Spec(k=100), 0.2)
    assert sorted((r["pair_h"], r["x_h"], r["y_h"]) for r in kept.collect()) == pairs[:100]
    row = estimate_size(rel, Spec(k=100, policy="fixed", p=0.2)).first()
    assert isclose(row["z_hat"], 100 * 2.0**63 / pairs[99][0]) and row["status"] == "estimate"


@pytest.mark.parametrize("name", ["part_part_order", "freq_parts", "cust_cust_part"])
def test_study_runs_are_brute_force(spark, sf, name):
    """Runs of the instances whose SQL takes too long, recomputed in numpy."""
    import hashlib

    pairs = baselines.join_project(WORKLOADS[name].build(spark, sf)).toPandas()
    digest = lambda seed, v: int(hashlib.md5(f"{seed}{v}".encode()).hexdigest()[:15], 16)
    got = {r["run"]: r for r in methods.ratio_runs(spark, sf, name, 256, range(1, 4)).collect()}
    for run in range(1, 4):
        x, y = ({v: digest(f"{side}{run}:", v) for v in set(pairs[c])} for side, c in (("L", "lk"), ("R", "rk")))
        h = np.sort((pairs.lk.map(x).to_numpy() - pairs.rk.map(y).to_numpy()) % 2**60)
        assert got[run]["kth_hash"] == h[255] and isclose(got[run]["ratio"], 256 * 2.0**60 / h[255] / len(h))


def test_sampled_bounds_hold_for_the_relation(spark, sf):
    rel = WORKLOADS["part_part_order"].build(spark, sf)
    row = sampling.sample_estimate(rel, 0.5, 0.5, "bottomk").first()
    assert row["status"] == "upper_bound" and row["z_hat"] == 4 * 1024.0**2 and row["hi"] > row["z_hat"]
    exact = sampling.sample_estimate(rel, 0.5, 0.5, "exact").first()["z_hat"]
    counted = sampling.sample_estimate(rel, 0.5, 0.5, "bottomk", Spec(k=10**6, policy="one")).first()
    assert counted["status"] == "scaled_count" and counted["z_hat"] == exact


def test_drawn_bits_are_stored(spark, sf, tmp_path):
    """Every reader of a drawn table sees the same bits; samples and sketches follow from them."""
    rel = WORKLOADS["supp_cust_order"].build(spark, sf)
    drawn = hashing.drawn_table(rel.left, "lk", "L1:", f"file://{tmp_path}/bits")
    bits = {r["lk"]: r["bits"] for r in drawn.collect()}
    assert {r["lk"]: r["bits"] for r in drawn.collect()} == bits and len(set(bits.values())) == len(bits) and all(0 <= b < 2**60 for b in bits.values())
    got = {tuple(r) for r in sampling.table_sample(rel.left, "lk", 0.4, drawn).collect()}
    assert got == {tuple(r) for r in rel.left.collect() if bits[r["lk"]] < sampling.sample_threshold(0.4, "md5_60")}


def test_built_in_baselines_are_near(spark, sf):
    rel = WORKLOADS["part_part_order"].build(spark, sf)
    z = baselines.exact_size(rel).first()["z"]
    hll, theta = baselines.builtin_hll(rel).first(), baselines.builtin_theta(rel).first()
    assert all(abs(v / z - 1) < 0.1 for v in (hll["hll_plus"], hll["hll"], theta["theta"]))
    # Uniform tuples meet too seldom in pairs that several join values give: the control is biased.
    assert baselines.tuple_sample_size(rel, 0.3).first()["z_hat"] > z


def test_more_closed_forms():
    assert bounds.regime(256**2 + 1, 256) == "guarantee" and bounds.regime(256**2, 256) == "bound"
    assert bounds.expected_hits(0.25, 100) == 25 and bounds.work_ok(0.01, 100, 50) and not bounds.work_ok(0.05, 100, 50)
    assert isclose(bounds.deviation_bound(10, 20, 3, 4, 5, 0.5, 100), (4 * 10 + 3 * 20 + 10 * 20 / 5) / (5 * 0.25 * 100))
    assert bounds.rounds_for(0.25) == 17 and as_threshold(1.0, 2**60) == 2**60


def test_running_estimate_survives_a_restart(spark, sf, tmp_path):
    """A new object takes up the stored version; replayed batches change nothing, a broken one is written anew."""
    from sparsepairs.streaming.streams import RunningEstimate

    spec, path = Spec(k=400, family="md5_60", policy="one"), f"file://{tmp_path}/running"
    rows = spark.createDataFrame([(i % 17, i % 5) for i in range(60)], "keep long, on long")
    parts = [rows.where("keep < 6"), rows.where("keep between 6 and 11"), rows.where("keep > 11")]
    one = RunningEstimate(spark, path, spec, 1.0)
    one.add(parts[0], 0)
    one.add(parts[1], 1)
    parts[2].limit(1).selectExpr("keep as lk", "on as jk").write.parquet(f"{path}/rows/2")
    two = RunningEstimate(spark, path, spec, 1.0)
    assert two.version == 1
    two.add(parts[1], 1)
    two.add(parts[2], 2)
    two.add(parts[2], 2)
    z = baselines.exact_size(self_rel(rows, "keep", "on")).first()["z"]
    assert RunningEstimate(spark, path, spec, 1.0).result().first()["z_hat"] == two.result().first()["z_hat"] == z


def test_broadcast_is_for_small_right_sides(spark, monkeypatch):
    """A right side above the limit is not gathered in the driver; the size stays exact."""
    rel = make(spark, [(i, i % 4) for i in range(20)], [(i % 4, i) for i in range(20)])
    plan = lambda: baselines.join_project(rel, "broadcast")._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan()
    monkeypatch.setattr(baselines, "BROADCAST_ROWS", 10)
    assert "Broadcast" not in plan() and "ShuffledHashJoin" in plan()
    assert baselines.exact_size(rel, "broadcast").first()["z"] == 100


def rows_out_of(df, node):
    """Rows that the plan's nodes of one kind gave in a finished run."""
    df.collect()
    plan = df._jdf.queryExecution().executedPlan()
    plan = plan.finalPhysicalPlan() if "AdaptiveSparkPlan" in plan.nodeName() else plan
    found, todo = [], [plan]
    while todo:
        at = todo.pop()
        if node in at.nodeName() and at.metrics().contains("numOutputRows"):
            found.append(at.metrics().apply("numOutputRows").value())
        if at.nodeName() in ("ShuffleQueryStage", "BroadcastQueryStage"):
            at = at.plan()
            todo.append(at)
        todo.extend(at.children().apply(i) for i in range(at.children().size()))
    return found


def test_sampled_sketch_lists_no_joined_rows(spark, sf):
    """s_bottomk_10: the scan gives at most k pairs of each task, and no join lists the sample's pairs."""
    plan = methods._sample_bottomk(0.1)(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "Join Inner" not in plan and "JoinExec Inner" not in plan


def test_range_join_meets_counted_days(spark, sf):
    """join_range_whole: an order meets a row of each of two days, not the lines of two days."""
    import __spark_entry__ as entry

    df = entry.queries()["join_range_whole"](spark, sf)
    orders = spark.read.parquet(f"{sf}/orders.parquet").count()
    joined = rows_out_of(df, "Join")
    assert joined and max(joined) <= 2 * orders < sum(r["n"] for r in df.collect())


def test_running_estimate_lists_k_pairs_of_a_task(spark, tmp_path, monkeypatch):
    """st_estimate: batches go through the scan that keeps k pairs, and start below the stored k-th."""
    from sparsepairs.streaming import streams

    seen = []
    monkeypatch.setattr(streams, "kept_set", lambda rel, spec, p: seen.append((spec.strategy, spec.tighten, p)) or kept_set(rel, spec, p))
    one = streams.RunningEstimate(spark, f"file://{tmp_path}/running", Spec(k=16, family="md5_60", tighten="none"), 1.0)
    rows = spark.createDataFrame([(i % 40, i % 3) for i in range(400)], "keep long, on long")
    one.add(rows.where("keep < 20"), 0)
    one.add(rows.where("keep >= 20"), 1)
    assert {x[:2] for x in seen} == {("sweep", "local")} and seen[0][2] == 1.0 and max(x[2] for x in seen[1:]) < 0.2
    want = kept_set(self_rel(rows, "keep", "on"), Spec(k=16, family="md5_60", policy="one"), 1.0).agg(F.max("pair_h")).first()[0]
    assert one.result().first()["kth_hash"] == want


@given(st.lists(st.tuples(st.integers(0, 4), st.booleans(), st.integers(0, 15)), min_size=1, max_size=60), st.integers(1, 16))
@settings(max_examples=100, deadline=None)
def test_groups_are_walked_together(rows, t):
    """m_hits_grouped: many groups in one call give what they give one by one, whatever batches they come in."""
    from unittest.mock import patch

    from sparsepairs.operators import estimate

    rows = sorted((j, 0, int(side), h) for j, side, h in rows)
    batches = [pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows[i : i + 7], strict=True)], names=["jk", "cell", "side", "h"]) for i in range(0, len(rows), 7)]
    with patch.object(estimate, "GROUP_ROWS", 10):
        got = [(x, y) for b in estimate._grouped(t, 16, None)(iter(batches)) for x, y in zip(*(c.to_pylist() for c in b.columns), strict=True)]
    want = []
    for j in range(5):
        sides = [np.array([h for k, _, s, h in rows if k == j and s == side], np.int64) for side in (0, 1)]
        x, y, *_ = walk_group(*sides, t, 16)
        want += zip(x.tolist(), y.tolist(), strict=True)
    assert sorted(got) == sorted(want)


def test_grouped_makes_no_call_a_group(spark, sf):
    """m_hits_grouped: join values are not cogrouped one by one."""
    rel = WORKLOADS["part_part_order"].build(spark, sf)
    plan = hits(rel, Spec(k=64, family="md5_60", strategy="grouped"), 0.01)._jdf.queryExecution().executedPlan().toString()
    assert "CoGroups" not in plan and "MapInArrow" in plan


@pytest.mark.parametrize(
    "key",
    ["b_catalyst", "c_overshoot", "c_undershoot", "c_unfilled", "c_regime", "c_runs_for", "c_rounds_for", "join_null_safe", "scan_blocks", "m_threshold_fixed", "m_threshold_inverse_k"],
)
def test_tasks_read_a_table(spark, sf, key):
    import __spark_entry__ as entry

    got = measures.io_profile(spark, lambda: entry.queries()[key](spark, sf).collect())
    assert got["input"] > 1000


def test_generated_blocks_have_their_size(spark):
    from sparsepairs.sources import readers

    spark.dataSource.register(readers.BlockSource)
    rows = spark.read.format("sparse_blocks").options(blocks=6, left=20, right=15, overlap=5).load()
    r = Rel(rows.where("side = 'left'").select(F.col("value").alias("lk"), "jk"), rows.where("side = 'right'").select("jk", F.col("value").alias("rk")))
    assert baselines.exact_size(r).first()["z"] == (6 * 20 - 5 * 5) * 15


@pytest.mark.parametrize("few", [0, 256])
def test_min_ranks_travel_as_edges(spark, monkeypatch, few):
    """b_min_rank_parts, b_min_rank_chain: no row for each round is shuffled; nulls, strings and full stores change nothing."""
    monkeypatch.setattr(baselines, "FEW_FIRSTS", few)
    a = spark.createDataFrame([(i % 5 if i % 11 else None, i % 13) for i in range(60)], "a long, b long").distinct()
    b = spark.createDataFrame([(i % 13, i % 17 if i % 7 else None) for i in range(90)], "a long, b long").distinct()
    c = spark.createDataFrame([(i % 17, f"e{i % 29}" if i % 9 else None) for i in range(120)], "a long, b string").distinct()
    for chain in ([a, b], [a, b, c], [c]):
        got = {r["first"]: r["size"] for r in baselines.min_rank_sizes(chain, 8).collect()}
        reach = {(r["a"], r["b"]) for r in baselines._reached(chain).where("b is not null").collect()}
        want = {x: 7 / sum(min(float(baselines._ranks_of([e], 8)[0, i]) for y, e in reach if y == x) for i in range(8)) for x in {x for x, _ in reach}}
        assert got.keys() == want.keys() and all(isclose(got[x], want[x], rel_tol=1e-12) for x in got)
    assert "round" not in baselines.min_rank_sizes([a, b], 8)._jdf.queryExecution().optimizedPlan().toString()
    e = spark.createDataFrame([("x",), ("7",)], "e string").select(*[baselines.exponential_rank(F.col("e"), F.lit(i)).alias(str(i)) for i in range(1, 9)])
    assert np.allclose(np.array(e.collect()), baselines._ranks_of(["x", "7"], 8), rtol=1e-14)


def test_min_rank_stores_overflow():
    """Full stores of vectors are emptied and go on."""
    from unittest.mock import patch

    rows = [(k, 0, f"e{(k * 7 + j) % 30}", None) for k in range(40) for j in range(3)] + [(k, 1, None, (k * 3 + j) % 20) for k in range(40) for j in range(2)]
    rows.sort(key=lambda r: r[:2])
    parts = [pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows[i : i + 9], strict=True), (pa.int64(), pa.int32(), pa.string(), pa.int64()), strict=True)], names=["key", "side", "end", "first"]) for i in range(0, len(rows), 9)]

    def lows():
        out = {}
        for b in baselines._min_ranks(4, pa.int64())(iter(parts)):
            for x, v in zip(*(c.to_pylist() for c in b.columns), strict=True):
                out[x] = np.minimum(out.get(x, np.inf), v).tolist()
        return out

    whole = lows()
    with patch.object(baselines, "VECTORS", 12):
        assert lows() == whole and len(whole) == 20
