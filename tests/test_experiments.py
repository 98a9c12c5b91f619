"""Workloads at small settings against SQL, without the plans that do not fit at size."""

import math

import pytest

from helpers import duck, same
from trianglestream.functions.coins import Coins
from trianglestream.functions.hashing import coin_value
from trianglestream.operators import sampling
from trianglestream.plans import experiments, oracles as sql

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def con():
    return duck(SF)


def test_budgets_share_one_plan_and_equal_sql(spark, con, monkeypatch):
    """A plan for each budget held more than the driver has; two fractions may have one budget."""
    monkeypatch.setattr(experiments, "estimate_routed", None)
    monkeypatch.setattr(experiments, "estimate_broadcast", None)
    fractions = (0.0001, 0.0002, 0.05, 0.3)
    got = experiments.effect_of_budget(spark, SF, fractions=fractions, k=4, trials=6)
    exact_from = {r["method"]: r["exact_from"] for r in got.collect()}
    assert 0 < exact_from["routed_modulo"] < 1 and exact_from["broadcast_avg"] == 1.0
    names = (("routed_modulo", "modulo", 6), ("routed_adaptive", "adaptive", 6), ("broadcast_avg", "broadcast", 3))
    rows = [sql.measured_sql({"method": name, "fraction": f}, "coactivity", 4, sql.fraction_budget(f), m, 7, trials) for name, m, trials in names for f in fractions]
    assert same(got.drop("exact_from"), con, sql.rows_sql(rows, "method, fraction, trials, mean, stderr, error, variance, truth"))


@pytest.mark.parametrize("prefix,low,high,most", [("2:59:29:", 1, 31_000, 100), ("12:0:10:", 99_990, 120_001, 3000), ("1:1:1:", 9998, 10_002, 5000), ("2:1:22:", 5_999_000, 6_002_000, 900_000), ("1:1:1:", 5, 5, 50)])
def test_coins_in_arrays_equal_md5(prefix, low, high, most):
    """Blocks of 10⁴ and 10⁵ ranks, their borders, all places of the last digits in a word, and ranges without a rank."""
    want = [(r, math.floor(coin_value(*prefix.split(":")[:3], r) * r) + 1) for r in range(low, high)]
    rank, slot = Coins().slots_within(prefix, low, high, most)
    assert list(zip(rank.tolist(), slot.tolist())) == [x for x in want if x[1] <= most]


def test_variance_draws_no_row_for_each_coin(spark, con, monkeypatch):
    """Rows of edges, trials and workers are too many at size."""
    for module, name in ((sampling, "accepted"), (experiments, "estimate_routed"), (experiments, "estimate_broadcast")):
        monkeypatch.setattr(module, name, None)
    got = experiments.variance_by_workers(spark, SF, ks=(3, 5), budget=40, trials=7)
    names = (("routed_modulo", "modulo"), ("routed_adaptive", "adaptive"), ("broadcast_avg", "broadcast"))
    rows = [sql.measured_sql({"method": name, "k": k}, "coactivity", k, 40, m, 2, 7) for k in (3, 5) for name, m in names]
    assert same(got.drop("slope"), con, sql.rows_sql(rows, "method, k, trials, mean, stderr, error, variance, truth"))


def test_parts_of_a_stream_make_their_wedges_once(spark, monkeypatch):
    """A plan that weighs discoveries reads them more than once; each reading made and moved all wedges again."""
    from trianglestream.plans.estimators import estimate_routed
    from trianglestream.sources.graphs import stream

    seen, loads = [], experiments.load_before
    monkeypatch.setattr(experiments, "load_before", lambda assigned, found: seen.append(found) or loads(assigned, found))
    rows = experiments.scalability_prefix(spark, SF, graph="coactivity", fractions=(0.5, 1.0), k=4).collect()
    assert len(seen) == 2 and all("Join" not in df._jdf.queryExecution().executedPlan().toString() for df in seen)
    edges = stream(spark, SF, "coactivity")
    n = edges.count()
    for r in rows:
        part = edges.where(f"t <= {r['edges']}")
        assert r["est"] == estimate_routed(part, 4, max(2, int(n * 0.02)), seed=5, strategy="wedge").global_df.first()["est"]


@pytest.mark.parametrize("edges_of_a_cell", [1 << 21, 300])
def test_triangles_are_listed_without_moved_wedges(spark, monkeypatch, edges_of_a_cell):
    """Wedges of all edges, shuffled, are many times the disk at size."""
    from trianglestream.operators import exact, lookups
    from trianglestream.sources.graphs import stream

    monkeypatch.setattr(lookups, "EDGES", edges_of_a_cell)
    edges = experiments.pin(stream(spark, SF, "coactivity"), "stream")
    got = lookups.listed(edges)
    assert "Join" not in got._jdf.queryExecution().optimizedPlan().toString()
    want = sorted(map(tuple, exact.triangles(edges).collect()))
    assert len(want) > 100 and sorted(map(tuple, got.collect())) == want


def test_sums_of_samples_in_arrays_equal_residency(spark):
    """Also loads whose sums pass 64 bits, workers without a triangle, and budgets beyond a worker's edges."""
    import numpy as np
    from trianglestream.operators import lookups
    from trianglestream.plans.estimators import estimate_routed
    from trianglestream.sources.graphs import stream

    assert lookups._sum_of_pairs(np.full(10, 3_000_000_000, np.int64)) == 10 * 3_000_000_000 * 2_999_999_999
    edges = stream(spark, SF, "coactivity")
    assigned, placed = experiments._placed(edges, lookups.listed(edges), "modulo", 40, 3)
    for b in (2, 30, 10_000):
        want = estimate_routed(edges, 40, b, seed=3, trials=4, strategy="triangle").global_df.collect()
        sums = lookups.held_sums(placed, assigned, 40, [b, 5], 3, 4).where(f"budget = {b}").groupBy("trial").agg({"hit": "sum", "num": "sum"}).collect()
        assert {r[0]: (r["sum(hit)"], r["sum(num)"]) for r in sums} == {r["trial"]: (r["hits"], r["num"]) for r in want}


def test_average_by_budget_runs_as_many_trials_as_the_others(spark, monkeypatch):
    """It had a tenth of them."""
    seen = {}
    monkeypatch.setattr(experiments, "effect_of_budget", lambda spark, d, **given: seen.update(given))
    experiments.WORKLOADS["w7_effect_of_budget"](spark, SF)
    assert seen["averaged"] == 30


def test_average_by_true_triangles_equals_wedges(spark):
    """Also its sums by node; the whole graph's come without a row for each discovery."""
    from trianglestream.plans.estimators import estimate_broadcast
    from trianglestream.sources.graphs import stream

    edges = experiments.pin(stream(spark, SF, "coactivity"), "stream")
    one, two = (estimate_broadcast(edges, 3, 60, 5, 4, strategy=s) for s in ("wedge", "triangle"))
    rows = sorted(map(tuple, one.global_df.collect()))
    assert any(r[2] for r in rows) and sorted(map(tuple, two.global_df.collect())) == rows
    assert "MapInArrow" in two.global_df._jdf.queryExecution().optimizedPlan().toString()
    assert sorted(map(tuple, one.local_df.collect())) == sorted(map(tuple, two.local_df.collect()))


@pytest.mark.parametrize("mapping", [None, "modulo"])
def test_small_streams_go_to_the_samples_without_a_broadcast(spark, monkeypatch, mapping):
    """The driver held the stream to broadcast it."""
    from trianglestream.operators import lookups
    from trianglestream.operators.counting import closures
    from trianglestream.sources.graphs import stream

    monkeypatch.setattr(lookups, "FOUND", 1 << 12)
    edges = experiments.pin(stream(spark, SF, "coactivity"), "stream")
    ranked = sampling.everywhere(edges, 4) if mapping is None else sampling.rank_in_worker(sampling.assign(edges, mapping, 4, 2))
    held = experiments.pin(sampling.reservoir(ranked, 120, 2, 3), "held")
    small = closures(edges, held, mapping, 4, 2, small=True)
    plan = small._jdf.queryExecution().executedPlan().toString()
    assert "Broadcast" not in plan and "Join" not in plan
    want = sorted(map(tuple, closures(edges, held, mapping, 4, 2).collect()))
    assert len(want) > 50 and sorted(map(tuple, small.collect())) == want


def _first_call(monkeypatch, module, name, run):
    seen = []

    def spied(*args, **given):
        seen.append((args, given))
        raise InterruptedError

    monkeypatch.setattr(module, name, spied)
    with pytest.raises(InterruptedError):
        run()
    return seen[0]


def test_single_machine_coin_meets_the_stream_in_tasks(spark, monkeypatch):
    """Its wedges of all trials were joined with the stream."""
    from trianglestream.operators import baselines

    assert _first_call(monkeypatch, baselines, "closures", lambda: experiments.single_machine(spark, SF, trials=2))[1] == {"small": True}


def test_speed_accuracy_meets_the_stream_in_tasks(spark, monkeypatch):
    """Joins of wedges by each of nine methods held more than the driver has."""
    from trianglestream.plans import estimators

    assert _first_call(monkeypatch, estimators, "closures", lambda: experiments.speed_accuracy(spark, SF))[0][5] is True


def test_workers_effect_lists_triangles_once(spark, monkeypatch):
    """Each of its ten settings listed them by joins."""
    given = _first_call(monkeypatch, experiments, "estimate_routed", lambda: experiments.effect_of_k(spark, SF, ks=(3,)))[1]
    assert given["strategy"] == "triangle" and given["found"].inputFiles()
