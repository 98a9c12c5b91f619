import itertools
import random

import pytest
from hypothesis import HealthCheck, given, settings, strategies as st

from pyspark.sql import functions as F
from trianglestream.functions.hashing import coin, coin_value, colour, colour_value
from trianglestream.operators import analysis, baselines, counting, exact, metrics
from trianglestream.operators.kernels import simulate
from trianglestream.operators.mapping import GreedyColours, adaptive_map
from trianglestream.operators.sampling import assign, load_before, messages, rank_in_worker, reservoir
from trianglestream.plans import experiments
from trianglestream.plans.estimators import estimate_broadcast, estimate_routed, estimate_single
from trianglestream.plans.planner import budget_fraction, recommend
from trianglestream.schemas import require_edge_stream
from trianglestream.sources.streams import edge_stream, union_streams


def frame(spark, edges):
    return spark.createDataFrame([(t, u, v) for t, (u, v) in enumerate(edges, 1)], "t bigint, u bigint, v bigint")


def complete(n):
    return [(a, b) for a in range(n) for b in range(a + 1, n)]


def random_graph(nodes, edges, seed):
    every = complete(nodes)
    random.Random(seed).shuffle(every)
    return every[:edges]


@pytest.fixture(scope="module")
def mid(spark):
    edges = random_graph(30, 220, 5)
    return edges, frame(spark, edges).cache()


def test_coins_agree_with_python(spark):
    rows = spark.range(50).select("id", coin(7, F.col("id"), 3).alias("c"), colour(F.col("id"), 5, 2).alias("w")).collect()
    for r in rows:
        assert r["c"] == coin_value(7, r["id"], 3) and r["w"] == colour_value(r["id"], 5, 2)


def test_clean_up_of_raw_pairs(spark):
    raw = spark.createDataFrame([(1, 1, 0), (2, 1, 5), (1, 2, 3), (3, 2, 9), (None, 2, 1)], "u bigint, v bigint, arrival bigint")
    for order in ("random", "arrival"):
        got = edge_stream(raw, order).collect()
        assert sorted((r["u"], r["v"]) for r in got) == [(1, 2), (2, 3)] and sorted(r["t"] for r in got) == [1, 2]
    assert edge_stream(raw.limit(0)).count() == 0
    assert [tuple(r) for r in edge_stream(raw, "arrival").orderBy("t").collect()] == [(1, 1, 2), (2, 2, 3)]


def test_union_of_streams_keeps_first_times(spark):
    one, two = frame(spark, [(1, 2), (2, 3)]), frame(spark, [(2, 3), (3, 4), (1, 2)])
    assert sorted((r["u"], r["v"]) for r in union_streams([one, two]).collect()) == [(1, 2), (2, 3), (3, 4)]


def test_entry_checks(spark):
    with pytest.raises(ValueError):
        require_edge_stream(spark.range(3))
    with pytest.raises(ValueError):
        require_edge_stream(spark.createDataFrame([(1, 2, 2)], "t bigint, u bigint, v bigint"), check_rows=True)
    with pytest.raises(ValueError):
        estimate_routed(frame(spark, [(1, 2)]), 2, 1)


def test_exact_counts_of_complete_graphs(spark):
    e = frame(spark, complete(9))
    assert exact.exact_global(e).first()["n"] == 84 == exact.exact_bruteforce(e).first()["n"]
    assert {r["n"] for r in exact.exact_local(e).collect()} == {28}
    assert exact.transitivity(e).first()[0] == 1.0
    assert {r["support"] for r in exact.edge_support(e).collect()} == {7}


def test_one_counting_worker_for_all_orders_and_colourings(spark):
    sides = [(0, 1), (1, 2), (0, 2)]
    for order in itertools.permutations(sides):
        e = frame(spark, order)
        for colours in itertools.product(range(2), repeat=3):
            nodemap = spark.createDataFrame(list(enumerate(colours)), "node bigint, worker int")
            able = analysis.able_workers(e, nodemap, 3).collect()
            assert [(r["able"], r["triangles"]) for r in able] == [(1, 1)]
        if order != tuple(sides):
            break


@pytest.mark.parametrize("mapping", ["modulo", "random"])
@pytest.mark.parametrize("k,b", [(1, 30), (4, 25), (7, 12)])
def test_plan_equals_kernel(spark, mid, mapping, k, b):
    edges, e = mid
    rule = (lambda x: x % k) if mapping == "modulo" else (lambda x: colour_value(x, k, 3))
    hits, num = simulate([(t, u, v) for t, (u, v) in enumerate(edges, 1)], k, b, rule, seed=3)
    for strategy in ("wedge", "triangle"):
        sums = estimate_routed(e, k, b, mapping, seed=3, strategy=strategy).sums.collect()
        assert {r["node"]: (r["hits"], int(r["num"])) for r in sums} == {n: (hits[n], num[n]) for n in hits}


def test_broadcast_plan_equals_kernel(spark, mid):
    edges, e = mid
    hits, num = simulate([(t, u, v) for t, (u, v) in enumerate(edges, 1)], 3, 40, None, seed=4)
    got = estimate_broadcast(e, 3, 40, seed=4).sums.collect()
    assert {r["node"]: (r["hits"], int(r["num"])) for r in got} == {n: (hits[n], num[n]) for n in hits}


def test_identities(spark, mid):
    _, e = mid
    one = estimate_routed(e, 4, 30, seed=1, strategy="wedge")
    total = one.global_df.first()["est"]
    local = one.local_df.agg(F.sum("est")).first()[0]
    assert abs(local - 3 * total) < 1e-6 * max(1, total)
    eager = estimate_routed(e, 4, 30, seed=1, aggregation="eager", aggregators=3).global_df.first()["est"]
    assert eager == total
    shots = [r["est"] for r in one.snapshots([50, 120, 220]).orderBy("as_of").collect()]
    assert shots == sorted(shots) and shots[-1] == total
    single = estimate_single(e, 30, seed=2).global_df.first()["est"]
    assert single == estimate_routed(e, 1, 30, seed=2).global_df.first()["est"] == estimate_broadcast(e, 1, 30, seed=2).global_df.first()["est"]


def test_exact_where_the_budget_suffices(spark, mid):
    _, e = mid
    truth = exact.exact_global(e).first()["n"]
    for mapping in ("modulo", "random"):
        need = analysis.exact_budget(e, mapping, 4).first()["budget"]
        assert estimate_routed(e, 4, need, mapping, seed=9).global_df.first()["est"] == truth
    assert estimate_broadcast(e, 2, 219, seed=1).global_df.first()["est"] == truth


def test_estimates_are_unbiased(spark, mid):
    _, e = mid
    truth = exact.exact_global(e).first()["n"]
    runs = {
        "routed": estimate_routed(e, 3, 40, seed=21, trials=200, strategy="triangle").global_df,
        "broadcast": estimate_broadcast(e, 2, 80, seed=22, trials=200).global_df,
        "coin": spark.range(200).select(F.col("id").cast("int").alias("trial")).join(baselines.edge_coin(e, 0.4, 23, 200).where("node is null").select("trial", "est"), "trial", "left").na.fill(0.0),
        "wedge": baselines.wedge_reservoir(e, 40, 24, 200),
        "hold": baselines.hold_sampler(e, 0.5, 0.4, 25, 200).select("trial", "est"),
        "hold_plain": baselines.hold_sampler(e, 0.5, 0.4, 26, 200, sure=False).select("trial", "est"),
    }
    for name, est in runs.items():
        m = metrics.global_metrics(est, truth).first()
        assert m["trials"] == 200 and abs(m["mean"] - truth) < 4 * m["stderr"] + 1e-9, (name, m)


def test_variance_within_the_doubled_bound(spark, mid):
    _, e = mid
    truth = exact.exact_global(e).first()["n"]
    seen = metrics.global_metrics(estimate_single(e, 60, 31, 150).global_df, truth).first()["variance"]
    assert seen <= 1.3 * analysis.variance_bound(e, "single", 60).first()["bound"]
    routed = metrics.global_metrics(estimate_routed(e, 4, 30, seed=32, trials=150, strategy="triangle").global_df, truth).first()["variance"]
    assert routed <= 1.3 * analysis.variance_bound(e, "routed", 30, 4).first()["bound"]


def test_adversarial_stream_passes_the_single_factor(spark):
    spokes = [(0, 1)] + [(0, 10 + i) for i in range(20)] + [(1000 + 2 * i, 1001 + 2 * i) for i in range(80)] + [(1, 10 + i) for i in range(20)]
    e = frame(spark, spokes)
    once, twice = (analysis.variance_bound(e, "single", 20, pair_factor=f).first()["bound"] for f in (1, 2))
    seen = metrics.global_metrics(estimate_single(e, 20, 5, 400).global_df, 20).first()["variance"]
    assert once < seen < 1.2 * twice


def test_pair_tallies_equal_listing(spark, mid):
    _, e = mid
    small = e.where("t <= 120")
    assert tuple(analysis.pair_counts(small).first()) == tuple(analysis.pair_counts_listed(small).first())


def test_uniformity_polynomials():
    for k in range(1, 6):
        listed, stated = analysis.listed_uniformity(k), analysis.expected_uniformity(k)
        assert abs(listed["type1"] - stated["type1"]) < 1e-12 and abs(listed["type2"] - stated["type2"]) < 1e-12


def test_adaptive_rule_by_hand(spark):
    g = GreedyColours(2, 0.2)
    assert g.see(1, 2) == (0, 0, [1, 2]) and g.loads == [1, 0]
    assert g.see(2, 3)[1] == 1 and g.loads == [2, 1]  # partner too loaded: the newcomer goes to the lightest
    assert g.see(4, 5) == (1, 1, [4, 5]) and g.loads == [2, 2]
    assert g.see(1, 6)[1] == 0 and g.loads == [3, 2]  # within tolerance: together
    assert g.see(1, 2) == (0, 0, []) and g.loads == [4, 2]
    e = frame(spark, [(1, 2), (2, 3), (4, 5), (1, 6), (1, 2)][:4])
    assert {r["node"]: r["worker"] for r in adaptive_map(e, 2, 0.2).collect()} == {k: v for k, v in g.colour.items()}


def test_adaptive_gathers_with_large_tolerance_and_epochs_cover_all(spark, mid):
    edges, e = mid
    assert metrics.load_balance(e, adaptive_map(e, 3, 1e9), 3).first()["most"] >= metrics.load_balance(e, adaptive_map(e, 3, 0.0), 3).first()["most"]
    nodemap = adaptive_map(e, 4, 0.2, "epoch", 5)
    assert {r["node"] for r in nodemap.collect()} == {x for p in edges for x in p} and nodemap.count() == 30
    truth = exact.exact_global(e).first()["n"]
    assert estimate_routed(e, 4, 220, nodemap).global_df.first()["est"] == truth


def test_loads_before_a_time(spark):
    e = frame(spark, [(0, 1), (0, 2), (1, 2), (0, 4), (1, 3)])
    a = assign(e, "modulo", 2)
    probes = spark.createDataFrame([(0, 1), (0, 3), (1, 3), (1, 6), (0, 6)], "worker int, t bigint").withColumn("tag", F.lit("x"))
    for chunk in (1, 2, 100):
        got = {(r["worker"], r["t"]): r["load_before"] for r in load_before(a, probes, chunk).collect()}
        assert got == {(0, 1): 0, (0, 3): 2, (1, 3): 1, (1, 6): 3, (0, 6): 4}
        assert {(r["worker"], r["t"]): r["rank"] for r in rank_in_worker(a, chunk).collect()} == {(r["worker"], r["t"]): r["rank"] for r in rank_in_worker(a, 1000).collect()}


def test_samples_never_exceed_the_budget_and_messages_count(spark, mid):
    edges, e = mid
    stay = reservoir(rank_in_worker(assign(e, "modulo", 3)), 15, seed=1)
    assert stay.where("t_out is null").groupBy("worker").count().agg(F.max("count")).first()[0] <= 15
    sent = messages(e, "modulo", 3).count()
    assert sent == metrics.message_costs(e, "modulo", 3).first()["messages"] == metrics.counting_calls(e, "modulo", 3).agg(F.sum("calls")).first()[0]


def test_local_measures_by_hand(spark):
    pairs = spark.createDataFrame([(1, 0, 1.0), (2, 1, 1.0), (3, 3, 2.0), (4, 3, 4.0)], "node bigint, x bigint, est double")
    m = metrics.local_metrics(pairs).first()
    assert m["nodes"] == 4 and abs(m["error"] - (1 + 0 + 0.25 + 0.25) / 4) < 1e-12 and abs(m["rmse"] - (3 / 4) ** 0.5) < 1e-12
    assert abs(m["spearman"] - 8 / 9) < 1e-12  # ranks 1, 2, 3.5, 3.5 against 1.5, 1.5, 3, 4


def test_ranks_with_ties_at_any_scale(spark):
    values = [0.0, 0.0, 1e-9, 3.0, 3.0, 3.0, 7.5, 1e12, 1e12 + 1]
    rows = spark.createDataFrame([(v,) for v in values], "x double")
    got = {r["x"]: r["x_rank"] for r in metrics.ranked(rows, "x").collect()}
    assert got == {0.0: 1.5, 1e-9: 3.0, 3.0: 5.0, 7.5: 7.0, 1e12: 8.0, 1e12 + 1: 9.0}


def test_empty_streams_give_zero(spark):
    none = frame(spark, [(1, 2)]).limit(0)
    assert estimate_routed(none, 3, 5, strategy="wedge").global_df.first()["est"] == 0
    assert estimate_broadcast(none, 3, 5).global_df.first()["est"] == 0
    assert adaptive_map(none, 3).count() == 0 and adaptive_map(none, 3, engine="epoch").count() == 0
    assert analysis.exact_budget(none, "modulo", 3).first()["budget"] == 2


def test_parameter_advice(spark, mid):
    _, e = mid
    assert budget_fraction(e, 0.1) == 22 and budget_fraction(e, 0.0) == 2
    assert recommend(10_000)["k"] == 1000 and recommend(10_000, "broadcast")["budget"] == 10_000


@settings(max_examples=6, deadline=None, suppress_health_check=[HealthCheck.function_scoped_fixture])
@given(st.integers(0, 10_000))
def test_plans_equal_kernel_on_random_streams(spark, seed):
    rng = random.Random(seed)
    edges = random_graph(rng.randrange(3, 12), rng.randrange(1, 40), seed)
    k, b = rng.randrange(1, 5), rng.randrange(2, 12)
    hits, num = simulate([(t, u, v) for t, (u, v) in enumerate(edges, 1)], k, b, lambda x: x % k, seed=seed)
    got = estimate_routed(frame(spark, edges), k, b, seed=seed, strategy=rng.choice(["wedge", "triangle"])).sums.collect()
    assert {r["node"]: (r["hits"], int(r["num"])) for r in got} == {n: (hits[n], num[n]) for n in hits}


def found(df):
    return sorted(tuple(r) for r in df.select("trial", "worker", "u", "v", "apex", "t").collect())


@pytest.mark.parametrize("mapping, k", [("modulo", 4), ("random", 3), (None, 1)])
def test_strategies_find_the_same(spark, mid, mapping, k):
    _, e = mid
    own = assign(e, mapping, k) if mapping else e.withColumn("worker", F.lit(0)).select("worker", "t", "u", "v")
    held = reservoir(rank_in_worker(own), 25, seed=3, trials=2)
    want = found(counting.closures(e, held, mapping, k))
    assert want and found(counting.closures_probed(e, held, mapping, k)) == want == found(counting.closures(e, held, mapping, k, small=True))
    if mapping:
        assert found(counting.closures_from_triangles(counting.placed_triangles(e, mapping, k), held)) == want


def test_a_star_costs_no_wedges(spark):
    """No mapping spreads a star's centre, and pairs of its edges are quadratic; probing stays within the edges."""
    n = 400
    star = frame(spark, [(0, i) for i in range(1, n + 1)])
    held = reservoir(rank_in_worker(assign(star, "modulo", 4)), 1000, seed=1)
    assert counting.wedges(held).count() >= n * (n - 1) / 2 and counting.probes(star, held, "modulo", 4).count() <= n
    assert assign(star, "modulo", 4).groupBy("worker").count().agg(F.max("count")).first()[0] == n
    shares = analysis.epsilon_uniform(star, "random", 4).first()
    assert shares["load"] == 4.0


def test_formulas_of_the_theory(spark, mid):
    _, e = mid
    assert analysis.variance_terms(10, 1000, 10**5, 10**6, 10**6, 10**6)["routed"] == (10**6 * 10**10 / 10**8, 1e7, 1e6)
    one = analysis.variance_terms(1, 50, 1000, 7, 8, 9)
    assert one["routed"] == one["broadcast"]
    assert analysis.variance_bound(e, "routed", 30, 1).first()["bound"] == pytest.approx(analysis.variance_bound(e, "single", 30).first()["bound"])
    cost = lambda m: analysis.predicted_cost(m, 1000, 5, 100, 300, 80)
    assert [cost(m)["master_space"] for m in ("routed_modulo", "routed_adaptive", "broadcast")] == [5, 85, 5]
    assert cost("routed_modulo")["aggregator_time"] == 300 and cost("broadcast")["aggregator_time"] == 1500 and cost("broadcast")["worker_space"] == 500
    whole = frame(spark, complete(12))
    twice = analysis.storage_copies(whole, "modulo", 5).where("copies = 2").first()["edges"]
    assert twice == analysis.complete_graph_redundancy([3, 3, 2, 2, 2]) == 66 - 3 - 3 - 1 - 1 - 1


def test_snapshots_hold_every_trial_and_end_at_the_estimate(spark, mid):
    _, e = mid
    est = estimate_routed(e, 4, 3, "modulo", seed=2, trials=12, strategy="triangle")
    rows = est.snapshots([20, 220]).collect()
    last = {r["trial"]: r["est"] for r in rows if r["as_of"] == 220}
    assert len(rows) == 24 and last == {r["trial"]: r["est"] for r in est.global_df.collect()} and 0.0 in last.values()
    local = {(r["trial"], r["node"]): r["est"] for r in est.snapshots([20, 220], local=True).where("as_of = 220").collect()}
    assert local == {(r["trial"], r["node"]): r["est"] for r in est.local_df.collect()}


def test_epochs_keep_balance_and_estimates(spark):
    edges = frame(spark, random_graph(120, 1500, 8))
    exact_map, epoch = (adaptive_map(edges, 6, 0.2, engine).cache() for engine in ("sequential", "epoch"))
    spread = [metrics.load_balance(edges, m, 6).first()["imbalance"] for m in (exact_map, epoch)]
    assert spread[0] < 1.3 and spread[1] < 1.6
    truth = exact.exact_global(edges).first()["n"]
    for m in (exact_map, epoch):
        got = metrics.global_metrics(estimate_routed(edges, 6, 120, m, seed=4, trials=60, strategy="triangle").global_df, truth).first()
        assert abs(got["mean"] - truth) < 4 * got["stderr"]


def test_claims_of_the_workloads(spark):
    """Variance falls faster with workers than the average's; errors vanish once the budget holds the loads."""
    sf = "/root/testdata/sf0.01"
    slopes = {r["method"]: r["slope"] for r in experiments.variance_by_workers(spark, sf, ks=(5, 20), trials=30).collect()}
    assert slopes["routed_modulo"] < -1.4 and slopes["routed_adaptive"] < -1.4 and -1.6 < slopes["broadcast_avg"] < -0.4
    for r in experiments.effect_of_budget(spark, sf, fractions=(0.02, 0.12), trials=10).where("method <> 'broadcast_avg'").collect():
        assert r["exact_from"] < 0.12 and (r["error"] == 0) == (r["fraction"] >= r["exact_from"])


def test_ratios_of_methods(spark):
    rows = spark.createDataFrame([("a", 2.0, 0.5), ("b", 6.0, 0.25)], "method string, seconds double, error double")
    assert {tuple(r) for r in metrics.ratios(rows, "a", ["seconds", "error"]).collect()} == {("a", 1.0, 1.0), ("b", 3.0, 0.5)}


def test_cliques_are_counted_without_their_edges(spark):
    """Groups of members of their own in closed form, groups that share a member by their links; nulls take no part."""
    from trianglestream.operators.exact import exact_global, exact_local, grouped_global, grouped_local
    from trianglestream.sources.graphs import _sharing, split_groups
    from trianglestream.sources.streams import edge_stream

    rows = [(i, "a") for i in range(5)] + [(i, "b") for i in range(5, 8)] + [(8, "c"), (8, "d"), (9, "c"), (10, "c"), (10, "d"), (11, "d")] + [(0, "a"), (None, "a"), (12, None), (13, "e")]
    df = spark.createDataFrame(rows, "id bigint, key string")
    edges = edge_stream(_sharing(df, None))
    assert grouped_global(*split_groups(df)).first()["n"] == exact_global(edges).first()["n"] == 10 + 1 + 2
    assert sorted(grouped_local(*split_groups(df)).collect()) == sorted(exact_local(edges).collect())
    groups, pairs = split_groups(df)
    assert {r["key"] for r in groups.collect()} == {"a", "b", "e"} and pairs.where("u < 8").isEmpty()
    assert grouped_global(*split_groups(df.limit(0))).first()["n"] == 0


def test_nearest_vectors_by_blocks(spark, tmp_path):
    """Against all pairs, with many copies, vectors that differ below the rounding, a null vector and one with a null component."""
    import math

    from trianglestream.sources.graphs import knn

    draw = random.Random(4)
    vectors = [[draw.gauss(0, 1) for _ in range(5)] for _ in range(60)] + [[1.0, 2.0, 3.0, 4.0, 5.0]] * 30 + [[1.0, 2.0, 3.0, 4.0, 5.0 + i * 1e-7] for i in range(30)]
    rows = [(i * 3, x) for i, x in enumerate(vectors)] + [(1, None), (2, [1.0, None, 0.0, 0.0, 0.0])]
    spark.createDataFrame(rows, "vec_id bigint, embedding array<double>").write.parquet(str(tmp_path / "embeddings.parquet"))
    dot = lambda a, b: sum(p * q for p, q in zip(a, b))
    score = lambda a, b: -math.inf if a is None or b is None or None in a or None in b else round(dot(a, b) / (math.sqrt(dot(a, a)) * math.sqrt(dot(b, b))), 9)
    want = {(u, v) for u, x in rows for _, v in sorted((-score(x, y), v) for v, y in rows if v != u)[:10]}
    got = {(r["u"], r["v"]) for r in knn(spark, str(tmp_path)).collect()}
    assert got == want


def test_each_setting_of_a_workload_is_planned_alone(spark):
    """A grid's plan is the union of written rows, without the stages that made them."""
    plan = experiments.variance_by_workers(spark, "/root/testdata/sf0.001", ks=(2, 3), budget=20, trials=3)
    single = experiments._union([spark.range(3).groupBy((F.col("id") % 2).alias("x")).count()] * 2)
    assert "Exchange" not in single._jdf.queryExecution().executedPlan().toString() and plan.count() == 6


def test_hashes_of_pairs_in_arrays_equal_md5():
    """All lengths of ids, signs and the greatest and least ones, so all places of v's first digit in its word."""
    import hashlib

    import numpy as np
    from trianglestream.sources.cliques import Hashes, in_order, pack_ids, unpack_ids

    draw = random.Random(3)
    ids = np.array(sorted({-(2**63), 2**63 - 1, 0, *(s * (10**k - d) for k in range(19) for d in (0, 1) for s in (1, -1))}), np.int64)
    i, j = (np.array([draw.randrange(len(ids)) for _ in range(4000)], np.int32) for _ in range(2))
    text = [hashlib.md5(f"s{ids[a]},{ids[b]}".encode()).hexdigest() for a, b in zip(i, j)]
    assert Hashes(ids).leading(i, j, 2).tolist() == [int(x[:16], 16) for x in text]
    assert Hashes(ids).leading(i, j, 1).tolist() == [int(x[:8], 16) for x in text]
    assert [text[x] for x in in_order(ids, i, j)] == sorted(text)
    assert unpack_ids(pack_ids(ids)).tolist() == ids.tolist() and unpack_ids(pack_ids(ids[:1])).tolist() == ids[:1].tolist()


def test_equal_leading_bits_are_settled_by_the_whole_hash(monkeypatch):
    import hashlib

    import numpy as np
    from trianglestream.sources import cliques

    real = cliques.Hashes.leading
    monkeypatch.setattr(cliques.Hashes, "leading", lambda self, i, j, words: real(self, i, j, words) >> np.uint64(60))
    ids, (i, j) = np.arange(30), np.triu_indices(30, 1)
    text = [hashlib.md5(f"s{a},{b}".encode()).hexdigest() for a, b in zip(i, j)]
    assert [text[x] for x in cliques.in_order(ids, i, j)] == sorted(text)


@pytest.mark.parametrize("edges,side", [(1500, 40), (200, 1000), (10**6, 2048)])
def test_stream_of_cliques_equals_the_stream_of_their_pairs(spark, edges, side):
    """Cells coded by themselves and small ones gathered, groups that share members, nulls and negative ids."""
    from trianglestream.sources.cliques import clique_stream
    from trianglestream.sources.graphs import _sharing

    rows = [(i * 37 - 900, "a") for i in range(130)] + [(10**15 + i, f"b{i // 3}") for i in range(60)] + [(-(2**62) + i, "c") for i in range(20)] + [(-(2**62) + i, "d") for i in range(15, 40)]
    rows += [(-900, "c"), (-863, "c"), (10**15, "a"), (10**15 + 1, "a")]  # pairs that meet twice, inside other cliques
    df = spark.createDataFrame([*rows, *rows[:9], (None, "a"), (7, None), (8, "alone")], "id bigint, key string")
    found, want = clique_stream(df, edges, side), edge_stream(_sharing(df, None))
    assert sorted(found.collect()) == sorted(want.collect()) and found.count() > 8385
    assert clique_stream(df.limit(0), edges, side).isEmpty()


def test_cells_send_few_bytes_an_edge():
    """A cell of two blocks of 1,000 ids gives each part its share in about a byte an edge, and the two blocks."""
    import numpy as np
    import pyarrow as pa
    from trianglestream.sources.cliques import _cell_packer

    ids = np.arange(2000) * 11
    batch = pa.RecordBatch.from_arrays([pa.array([ids[:1000], ids[:2]]), pa.array([ids[1000:], ids[:2]])], ["us", "vs"])
    cell, small = list(_cell_packer(20)([batch]))
    assert sum(cell.column("n").to_pylist()) == 10**6 and sum(small.column("n").to_pylist()) == 1 and small.column("us").null_count == 1
    assert cell.num_rows == 20 and cell.nbytes < 1.2 * 10**6


def test_host_links_are_not_shuffled(spark, monkeypatch):
    """Edges of large hosts are too many to move with their ids and keys of order."""
    from helpers import duck, same
    from trianglestream.plans import catalog
    from trianglestream.sources import graphs

    monkeypatch.setattr(graphs, "edge_stream", None)
    sf = "/root/testdata/sf0.01"
    stream = catalog.queries()["edges_hostlinks"](spark, sf)
    assert same(stream, duck(sf), catalog.oracle_sql()["edges_hostlinks"])
    plan = stream._jdf.queryExecution().executedPlan().toString()
    assert "ReusedExchange [part" in plan[: plan.index("Initial Plan")]  # counted and sorted from one exchange
