"""Experiment workloads: each returns a table of measures over its parameter grid.

Grids are small driver-side loops over parameters; every measurement is one plan.
"""

from __future__ import annotations

import time
from collections.abc import Iterable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, functions as F

from . import oracles as sql
from ..operators import analysis, baselines, exact, metrics
from ..operators.aggregate import aggregate, trial_estimates, weigh
from ..operators.counting import closures, placed_triangles
from ..operators.lookups import held_sums, held_sums_everywhere, listed
from ..operators.mapping import adaptive_map, share_local
from ..operators.sampling import assign, everywhere, load_before, rank_in_worker, reservoir
from ..sources.graphs import er, stream
from ..sources.streams import edge_stream, prefix
from ..sources.tables import pin
from .estimators import SMALL_STREAM, Estimate, estimate_broadcast, estimate_routed, estimate_single
from .planner import budget_fraction


def _union(parts: Iterable[DataFrame]) -> DataFrame:
    """The measured rows of all settings. Each setting is run and written by itself: one plan over a whole grid has hundreds
    of stages, whose descriptions the driver would hold at once. A generator's next setting is planned after that."""
    return reduce(lambda a, b: a.unionByName(b), [pin(part, "row") for part in parts])


def _tag(df: DataFrame, **values) -> DataFrame:
    return df.select(*[F.lit(v).alias(k) for k, v in values.items()], *df.columns)


def _prepared(spark, sf_dir, graph) -> tuple[DataFrame, int]:
    edges = pin(stream(spark, sf_dir, graph), "stream")
    return edges, exact.exact_global(edges).first()["n"]


def _nodemap(edges, mapping, k, theta=0.2):
    return pin(adaptive_map(edges, k, theta), "nodemap") if mapping == "adaptive" else mapping


def _listed(spark, sf_dir, graph) -> tuple[DataFrame, int, DataFrame, int]:
    """The stream, its edges, its true triangles and their number; both are written once for all settings."""
    edges = pin(stream(spark, sf_dir, graph), "stream")
    found = pin(listed(edges), "triangles")
    return edges, edges.count(), found, found.count()


def _placed(edges, found, mapping, k, seed) -> tuple[DataFrame, DataFrame]:
    """Edges each worker considers, and triangles with the worker that counts them."""
    return assign(edges, mapping, k, seed).select("worker", "t"), placed_triangles(edges, mapping, k, seed, found)


def _routed_rows(assigned, placed, k, budgets, seed, trials, truth) -> DataFrame:
    """(budget, measures) of the routed estimator at each budget, by true triangles: what ``estimate_routed`` finds, in one plan
    for all budgets."""
    return _budget_rows(held_sums(placed, assigned, k, budgets, seed, trials), budgets, 1, trials, truth)


def _average_rows(n, found, k, budgets, seed, trials, truth) -> DataFrame:
    """(budget, measures) of the average at each budget: what ``estimate_broadcast`` finds. The rank of an edge is its time."""
    return _budget_rows(held_sums_everywhere(found, n, k, budgets, seed, trials), budgets, k, trials, truth)


def _budget_rows(sums, budgets, divisor, trials, truth) -> DataFrame:
    estimates = trial_estimates(sums, sorted(set(budgets)), trials, divisor)
    return _rounded(metrics.global_metrics(estimates, truth, ("budget",)), truth, "budget")


def _rounded(df: DataFrame, truth: int, *by: str) -> DataFrame:
    """The columns of ``global_metrics`` rounded for comparison across engines, and the truth."""
    kept = [F.round("mean", 7).alias("mean"), F.round("stderr", 7).alias("stderr"), F.round("error", 9).alias("error"), F.round("variance", 5).alias("variance")]
    return df.select(*by, "trials", *kept, F.lit(float(truth)).alias("truth"))


def _row(estimate, truth: int, **labels) -> DataFrame:
    return _tag(_rounded(metrics.global_metrics(estimate.global_df, truth), truth), **labels)


def unbiasedness(spark: SparkSession, sf_dir: str, graph: str = "coactivity", k: int = 10, fraction: float = 0.05, trials: int = 200, seed: int = 1) -> DataFrame:
    """Mean of many runs against the truth, as a z score, by method. The average has k runs in each of its trials."""
    edges, n, found, truth = _listed(spark, sf_dir, graph)
    b, by = max(2, int(n * fraction)), {"strategy": "triangle", "found": found}
    parts = [lambda name=name: _row(estimate_routed(edges, k, b, _nodemap(edges, name, k), seed=seed, trials=trials, **by), truth, method=f"routed_{name}") for name in ("modulo", "adaptive")]
    parts.append(lambda: _row(estimate_broadcast(edges, k, b, seed, trials // 5, **by), truth, method="broadcast_avg"))
    parts.append(lambda: _row(estimate_single(edges, b, seed, trials, **by), truth, method="single_reservoir"))
    return _union(part() for part in parts).withColumn("z", F.round(F.try_divide(F.col("mean") - F.col("truth"), F.col("stderr")), 3))


def variance_by_workers(spark, sf_dir, graph: str = "coactivity", ks=(5, 10, 20, 30), budget: int = 100, trials: int = 60, seed: int = 2) -> DataFrame:
    """Variance against the number of workers, and its slope on log scales, by method."""
    edges, n, found, truth = _listed(spark, sf_dir, graph)
    parts = []
    for k in ks:
        for name in ("modulo", "adaptive"):
            rows = _routed_rows(*_placed(edges, found, _nodemap(edges, name, k), k, seed), k, [budget], seed, trials, truth)
            parts.append(pin(_tag(rows.drop("budget"), method=f"routed_{name}", k=k), "row"))
        rows = _average_rows(n, found, k, [budget], seed, trials, truth)
        parts.append(pin(_tag(rows.drop("budget"), method="broadcast_avg", k=k), "row"))
    rows = reduce(lambda a, b: a.unionByName(b), parts)
    slopes = metrics.variance_slope(rows, ["method"])
    return rows.join(slopes.withColumn("slope", F.round("slope", 4)), "method")


def _measured(edges, truth_local, truth, name, make) -> DataFrame:
    began = time.perf_counter()
    est = make()
    sums = pin(est.sums, "sums")
    seconds = time.perf_counter() - began
    est.sums = sums
    local = metrics.local_metrics(metrics.paired_local(est.local_df.where("trial = 0"), edges, truth_local)).select(F.col("error").alias("local_error"), "rmse", "spearman")
    glob = metrics.global_metrics(est.global_df, truth).select("error", "variance")
    return _tag(glob.crossJoin(F.broadcast(local)), method=name, seconds=seconds)


def speed_accuracy(spark, sf_dir, graph: str = "coactivity", k: int = 30, seed: int = 3, routed=(0.05,), averaged=(0.02, 0.05, 0.2), single=(0.05, 0.4)) -> DataFrame:
    """Seconds and five error measures, by method and budget. Every method runs the same one-pass joins."""
    edges, truth = _prepared(spark, sf_dir, graph)
    local, n = pin(exact.exact_local(edges), "truth"), edges.count()
    rows, small = [], n <= SMALL_STREAM
    for f in routed:
        b = budget_fraction(edges, f)
        for name in ("modulo", "adaptive"):
            rows.append(_measured(edges, local, truth, f"routed_{name}_{f:g}", lambda b=b, n=name: estimate_routed(edges, k, b, n, seed=seed, strategy="wedge", small=small)))
    rows += [_measured(edges, local, truth, f"broadcast_avg_{f:g}", lambda f=f: estimate_broadcast(edges, k, budget_fraction(edges, f), seed, strategy="auto")) for f in averaged]
    rows += [_measured(edges, local, truth, f"single_reservoir_{f:g}", lambda f=f: estimate_single(edges, budget_fraction(edges, f), seed, strategy="auto")) for f in single]
    began = time.perf_counter()
    coin = pin(baselines.edge_coin(edges, budget_fraction(edges, single[0]) / n, seed, small=small), "coin")
    seconds = time.perf_counter() - began
    near = metrics.local_metrics(metrics.paired_local(coin.where("node is not null"), edges, local)).select(F.col("error").alias("local_error"), "rmse", "spearman")
    whole = spark.range(1).select(F.lit(0).alias("trial")).join(coin.where("node is null").select("trial", "est"), "trial", "left").na.fill(0.0)
    rows.append(_tag(metrics.global_metrics(whole, truth).select("error", "variance").crossJoin(F.broadcast(near)), method=f"edge_coin_{single[0]:g}", seconds=seconds))
    return _union(rows)


def headline_ratios(spark, sf_dir, graph: str = "coactivity", base: str = "routed_adaptive_0.05") -> DataFrame:
    """W3, each measure of each method over that of ``base``: speed-up, error and variance ratios."""
    rows = pin(speed_accuracy(spark, sf_dir, graph), "w3")
    return metrics.ratios(rows, base, ["seconds", "error", "variance", "local_error", "rmse"])


def overhead(spark, sf_dir, graph: str = "coactivity", k: int = 30) -> DataFrame:
    """Messages, bytes, storage candidates and counting calls by mapping; broadcast sends and stores all k times."""
    edges = pin(stream(spark, sf_dir, graph), "stream")
    parts = []
    for name in ("modulo", "random", "adaptive"):
        m = _nodemap(edges, name, k)
        calls = metrics.counting_calls(edges, m, k).agg(F.sum("calls").alias("calls"), F.max("calls").alias("slowest"))
        parts.append(_tag(metrics.message_costs(edges, m, k).crossJoin(F.broadcast(calls)), method=f"routed_{name}"))
    n = edges.agg(F.count(F.lit(1)).alias("e"))
    e = F.col("e")
    parts.append(_tag(n.select((e * k).alias("messages"), (e * k * 16).alias("bytes"), (e * k).alias("considered"), e.alias("stored_unique"), (e * k).alias("calls"), e.alias("slowest")), method="broadcast_avg"))
    return _union(parts)


def sample_storage(spark, sf_dir, graph: str = "coactivity", k: int = 10, fraction: float = 0.05, seed: int = 1) -> DataFrame:
    """Edges in the samples at the end, those that are different, and replicas, by method."""
    edges = pin(stream(spark, sf_dir, graph), "stream")
    b, parts = budget_fraction(edges, fraction), []
    for name in ("modulo", "adaptive", "broadcast"):
        ranked = everywhere(edges, k) if name == "broadcast" else rank_in_worker(assign(edges, _nodemap(edges, name, k), k))
        held = reservoir(ranked, b, seed).where("t_out is null")
        one = held.agg(F.count(F.lit(1)).alias("stored"), F.count_distinct("t_in").alias("distinct_edges"))
        parts.append(_tag(one.withColumn("replicas", F.col("stored") - F.col("distinct_edges")), method=name))
    return _union(parts)


def time_split(spark, sf_dir, graph: str = "copurchase", k: int = 30, fraction: float = 0.02, seed: int = 4) -> DataFrame:
    """Seconds of the three roles, each stage written before the next begins: routing and ranks (master), samples and
    discoveries (workers), sums (aggregator); and bytes of the messages between master and workers."""
    edges = pin(stream(spark, sf_dir, graph), "stream")
    b, parts = budget_fraction(edges, fraction), []
    for name in ("modulo", "adaptive"):
        marks = [time.perf_counter()]

        def stage(df, label):
            done = pin(df, label)
            marks.append(time.perf_counter())
            return done

        mapping = _nodemap(edges, name, k)
        ranked = stage(rank_in_worker(assign(edges, mapping, k)), "ranked")
        assigned = ranked.drop("rank")
        found = load_before(assigned, closures(edges, reservoir(ranked, b, seed, 1, "fast"), mapping, k, small=True))
        weighed = stage(weigh(found, b), "weighed")
        stage(aggregate(weighed, b), "sums")
        sent = metrics.message_costs(edges, mapping, k).first()["bytes"]
        parts.append((name, *[y - x for x, y in zip(marks, marks[1:])], int(sent)))
    return spark.createDataFrame(parts, "mapping string, master_seconds double, worker_seconds double, aggregator_seconds double, message_bytes bigint")


def scalability(spark, sf_dir, sizes=(50_000, 100_000, 200_000, 400_000), nodes: int = 10_000, k: int = 30, budget: int = 2_000) -> DataFrame:
    """Seconds of the routed estimator over random graphs, by mapping, with the fit of a line."""
    tables = []
    for name in ("modulo", "adaptive"):
        rows = []
        for m in sizes:
            edges = pin(edge_stream(er(spark, nodes, m), "arrival"), "er")
            began = time.perf_counter()
            est = estimate_routed(edges, k, budget, name, seed=4, coins="fast").global_df.first()["est"]
            rows.append((name, m, time.perf_counter() - began, float(est)))
        table = spark.createDataFrame(rows, "mapping string, edges bigint, seconds double, est double")
        tables.append(table.crossJoin(F.broadcast(metrics.linearity(table))))
    return _union(tables)


def scalability_prefix(spark, sf_dir, graph: str = "copurchase", fractions=(0.25, 0.5, 0.75, 1.0), k: int = 30, fraction: float = 0.02) -> DataFrame:
    """Seconds over growing parts of one stream."""
    edges = pin(stream(spark, sf_dir, graph), "stream")
    n, rows = edges.count(), []
    for f in fractions:
        part = prefix(edges, int(n * f))
        began = time.perf_counter()
        b = max(2, int(n * fraction))
        # Loads read the discoveries more than once, and wedges are many times the stream, so discoveries are written.
        ranked = pin(rank_in_worker(assign(part, "modulo", k, 5)), "ranked")
        found = pin(closures(part, reservoir(ranked, b, 5), "modulo", k, 5, int(n * f) <= SMALL_STREAM), "closures")
        weighed = weigh(load_before(ranked.drop("rank"), found), b)
        est = Estimate(aggregate(weighed, b), weighed, b, 1, 1).global_df.first()["est"]
        rows.append((int(n * f), time.perf_counter() - began, float(est)))
    table = spark.createDataFrame(rows, "edges bigint, seconds double, est double")
    return table.crossJoin(F.broadcast(metrics.linearity(table)))


def effect_of_k(spark, sf_dir, graph: str = "coactivity", ks=(5, 20, 60, 100, 140), fraction: float = 0.02, trials: int = 30, seed: int = 6) -> DataFrame:
    """Error against the number of workers at one budget, beside the average of as many workers."""
    edges, n, found, truth = _listed(spark, sf_dir, graph)
    b, by = max(2, int(n * fraction)), {"strategy": "triangle", "found": found}
    rows = [lambda k=k, name=name: _row(estimate_routed(edges, k, b, _nodemap(edges, name, k), seed=seed, trials=trials, **by), truth, method=f"routed_{name}", k=k) for k in ks for name in ("random", "adaptive")]
    rows += [lambda k=k: _row(estimate_broadcast(edges, k, b, seed, 3, **by), truth, method="broadcast_avg", k=k) for k in ks]
    return _union(row() for row in rows)


def effect_of_budget(spark, sf_dir, graph: str = "coactivity", fractions=(0.01, 0.02, 0.05, 0.08, 0.12), k: int = 30, trials: int = 30, seed: int = 7, averaged: int = 3) -> DataFrame:
    """Error against the budget by method, with the share of the stream from which the routed estimator is exact. The average
    has k runs in each of its ``averaged`` trials; the registered query has as many of them as of the others."""
    edges, n, found, truth = _listed(spark, sf_dir, graph)
    shares = {f: max(2, int(n * f)) for f in fractions}
    settings = spark.createDataFrame(list(shares.items()), "fraction double, budget bigint")

    def labelled(rows, method, exact_from):
        rows = settings.join(rows, "budget").select(F.lit(method).alias("method"), "fraction", *[c for c in rows.columns if c != "budget"])
        return pin(rows.withColumn("exact_from", F.lit(exact_from)), "row")

    parts = []
    for name in ("modulo", "adaptive"):
        assigned, placed = _placed(edges, found, _nodemap(edges, name, k), k, seed)
        last = placed.groupBy("worker").agg(F.max(F.struct("t", "u", "v", "apex")).alias("last")).select("worker", "last.*")  # a load grows with time
        need = round(load_before(assigned, last).agg(analysis.least_exact_budget()).first()["budget"] / n, 6)
        parts.append(labelled(_routed_rows(assigned, placed, k, list(shares.values()), seed, trials, truth), f"routed_{name}", need))
    parts.append(labelled(_average_rows(n, found, k, list(shares.values()), seed, averaged, truth), "broadcast_avg", 1.0))
    return reduce(lambda a, b: a.unionByName(b), parts)


def effect_of_theta(spark, sf_dir, graph: str = "neardup", thetas=(0.0, 0.1, 0.2, 0.5, 1.0, 4.0), k: int = 30, fraction: float = 0.02, trials: int = 30, seed: int = 8) -> DataFrame:
    """Error, balance and locality against the tolerance."""
    edges, truth = _prepared(spark, sf_dir, graph)
    b, parts = budget_fraction(edges, fraction), []
    for theta in thetas:
        m = pin(adaptive_map(edges, k, theta), "nodemap")
        est = _row(estimate_routed(edges, k, b, m, seed=seed, trials=trials, strategy="triangle"), truth, theta=theta)
        balance = metrics.load_balance(edges, m, k).select("least", "most")
        parts.append(est.crossJoin(F.broadcast(balance)).crossJoin(F.broadcast(share_local(edges, m, k).select(F.round("local_share", 6).alias("local_share")))))
    return _union(parts)


def single_machine(spark, sf_dir, graph: str = "coactivity", fraction: float = 0.05, trials: int = 40, seed: int = 9) -> DataFrame:
    """The four single-machine samplers at about one storage."""
    edges, n, found, truth = _listed(spark, sf_dir, graph)
    b = max(2, int(n * fraction))
    every = spark.range(trials).select(F.col("id").cast("int").alias("trial"))
    coin = every.join(baselines.edge_coin(edges, b / n, seed, trials, n <= SMALL_STREAM).where("node is null").select("trial", "est"), "trial", "left").na.fill(0.0)
    table = {
        "single_reservoir": estimate_single(edges, b, seed, trials, strategy="triangle", found=found).global_df.select("trial", "est"),
        "edge_coin": coin,
        "wedge_reservoir": baselines.wedge_reservoir(edges, b // 2, seed, trials),
        "hold_sampler": baselines.hold_sampler(edges, b / n, b / n / 2, seed, trials).select("trial", "est"),
    }
    return _union([_tag(metrics.global_metrics(est, truth), method=name) for name, est in table.items()])


def property_audit(spark, sf_dir, graphs=("coactivity", "neardup", "nation_trade"), k: int = 7) -> DataFrame:
    """Most copies of an edge, and least and most workers able to count a triangle, by graph and mapping."""
    parts = []
    for g in graphs:
        edges = pin(stream(spark, sf_dir, g), "stream")
        for name in ("modulo", "random", "adaptive"):
            m = _nodemap(edges, name, k)
            copies = analysis.storage_copies(edges, m, k).agg(F.max("copies").cast("bigint").alias("most_copies"))
            able = analysis.able_workers(edges, m, k).agg(F.min("able").cast("bigint").alias("least_able"), F.max("able").cast("bigint").alias("most_able"))
            parts.append(_tag(copies.crossJoin(F.broadcast(able)), graph=g, mapping=name))
    return _union(parts)


def bounds_and_variance(spark, sf_dir, graph: str = "coactivity", k: int = 7, budget: int = 300, trials: int = 30) -> DataFrame:
    """Observed variance beside the bound, by method."""
    edges, truth = _prepared(spark, sf_dir, graph)
    runs = {"single": (estimate_single(edges, budget, 10, trials), 1), "broadcast": (estimate_broadcast(edges, k, budget, 10, trials), k), "routed": (estimate_routed(edges, k, budget, seed=10, trials=trials, strategy="triangle"), k)}
    parts = []
    for kind, (est, workers) in runs.items():
        bound = analysis.variance_bound(edges, kind, budget, workers)
        parts.append(_tag(metrics.global_metrics(est.global_df, truth).select("variance").crossJoin(F.broadcast(bound)), method=kind))
    return _union(parts)


def uniformity_audit(spark, sf_dir, graph: str = "coactivity", k: int = 4, colourings: int = 5) -> DataFrame:
    """Largest normalised shares under random mappings, beside their expectation."""
    edges = pin(stream(spark, sf_dir, graph), "stream")
    want = analysis.expected_uniformity(k)
    rows = _union([_tag(analysis.epsilon_uniform(edges, "random", k, s), colouring=s) for s in range(colourings)])
    return rows.withColumn("expected_type1", F.lit(want["type1"] * k)).withColumn("expected_type2", F.lit(want["type2"] * k * k))


def applications(spark, sf_dir, graph: str = "coactivity", k: int = 7, fraction: float = 0.05, top: int = 10) -> DataFrame:
    """Nodes of greatest estimated count beside their true count and clustering."""
    edges = pin(stream(spark, sf_dir, graph), "stream")
    est = estimate_routed(edges, k, budget_fraction(edges, fraction), seed=11).local_df.where("trial = 0")
    best = est.orderBy(F.desc("est"), "node").limit(top)
    return best.join(exact.local_clustering(edges), "node").select("node", "est", "n", "degree", "clustering")


WORKLOADS = {
    "w1_unbiasedness": unbiasedness, "w2_variance_by_workers": variance_by_workers, "w3_speed_accuracy": speed_accuracy, "w4_overhead": overhead, "w5a_scalability": scalability,
    "w5b_scalability_prefix": scalability_prefix, "w6_effect_of_k": effect_of_k, "w7_effect_of_budget": lambda spark, d: effect_of_budget(spark, d, averaged=30), "w8_effect_of_theta": effect_of_theta, "w9_single_machine": single_machine,
    "w10_property_audit": property_audit, "w11_bounds": bounds_and_variance, "w12_uniformity": uniformity_audit, "w13_applications": applications,
    "w3_ratios": headline_ratios, "w4_sample_storage": sample_storage, "w4_time_split": time_split,
    "w3_speed_accuracy_neardup": lambda spark, d: speed_accuracy(spark, d, "neardup"), "w8_effect_of_theta_knn": lambda spark, d: effect_of_theta(spark, d, "knn"),
}


def oracles() -> dict[str, str]:
    """DuckDB texts of the workloads that hold no seconds."""
    share, g = sql.fraction_budget, "coactivity"
    measures = "trials, mean, stderr, error, variance, truth"
    w1 = [sql.measured_sql({"method": f"routed_{m}"}, g, 10, share(0.05), m, 1, 200) for m in ("modulo", "adaptive")]
    w1 += [sql.measured_sql({"method": "broadcast_avg"}, g, 10, share(0.05), "broadcast", 1, 40), sql.measured_sql({"method": "single_reservoir"}, g, 1, share(0.05), "broadcast", 1, 200)]
    names = (("routed_modulo", "modulo"), ("routed_adaptive", "adaptive"), ("broadcast_avg", "broadcast"))
    w2 = [sql.measured_sql({"method": name, "k": k}, g, k, 100, m, 2, 60) for k in (5, 10, 20, 30) for name, m in names]
    w2 = sql.rows_sql(w2, f"method, k, {measures}")
    w6 = [sql.measured_sql({"method": f"routed_{m}", "k": k}, g, k, share(0.02), m, 6, 30) for k in (5, 20, 60, 100, 140) for m in ("random", "adaptive")]
    w6 += [sql.measured_sql({"method": "broadcast_avg", "k": k}, g, k, share(0.02), "broadcast", 6, 3) for k in (5, 20, 60, 100, 140)]
    w8 = {}
    for graph in ("neardup", "knn"):
        rows = []
        for theta in (0.0, 0.1, 0.2, 0.5, 1.0, 4.0):
            base = sql.mapped_parts(graph, 30, "adaptive", 8, theta)
            loads = sql.chain(base, "SELECT CAST(min(l) AS BIGINT) AS least, CAST(max(l) AS BIGINT) AS most FROM (SELECT count(worker) AS l FROM range(30) r LEFT JOIN a ON a.worker = r.range GROUP BY r.range)")
            near = sql.chain(base, "SELECT round(count(*) FILTER (fu = fv) / count(*), 6) AS local_share FROM ew")
            rows.append(f"(SELECT * FROM {sql.measured_sql({'theta': theta}, graph, 30, share(0.02), 'adaptive', 8, 30, theta)}, ({loads}), ({near}))")
        w8[graph] = sql.rows_sql(rows, f"theta, {measures}, least, most, local_share")
    audit = " UNION ALL ".join(f"SELECT '{x}' AS graph, '{m}' AS mapping, CAST(2 AS BIGINT) AS most_copies, CAST(1 AS BIGINT) AS least_able, CAST(1 AS BIGINT) AS most_able" for x in ("coactivity", "neardup", "nation_trade") for m in ("modulo", "random", "adaptive"))
    return {
        "w1_unbiasedness": sql.rows_sql(w1, f"method, {measures}, CASE WHEN stderr <> 0 THEN round((mean - truth) / stderr, 3) END AS z"),
        "w2_variance_by_workers": f"WITH w AS ({w2}) SELECT w.*, slope FROM w JOIN (SELECT method, round(regr_slope(ln(variance), ln(k)), 4) AS slope FROM w GROUP BY method) USING (method)",
        "w6_effect_of_k": sql.rows_sql(w6, f"method, k, {measures}"),
        "w8_effect_of_theta": w8["neardup"],
        "w8_effect_of_theta_knn": w8["knn"],
        "w10_property_audit": audit,
    }
