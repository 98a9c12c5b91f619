"""The estimators: policies over one plan of ranks, residency, closures, weights and sums."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, functions as F

from ..operators.aggregate import aggregate, finish, snapshots, weigh
from ..operators.counting import closures, closures_from_triangles, closures_probed, placed_triangles
from ..operators.kernels import closures_by_kernel
from ..operators.lookups import held_sums, held_sums_everywhere, listed
from ..operators.mapping import adaptive_map
from ..operators.sampling import assign, everywhere, load_before, rank_in_worker, reservoir
from ..schemas import require_edge_stream, require_parameters
from ..sources.tables import pin


@dataclass
class Estimate:
    """Sums of one estimator: ``sums`` has (trial, node, hits, num, est), node null for the whole graph. ``totals`` has what workers
    ship for the whole graph, (trial, hit, num), where that is found without a row for each discovery."""

    sums: DataFrame
    weighed: DataFrame
    budget: int
    divisor: int
    trials: int
    totals: DataFrame | None = None

    @property
    def global_df(self) -> DataFrame:
        """(trial, hits, num, est) for every trial, with zeros where nothing was found."""
        spark = self.sums.sparkSession
        found = self.sums.where("node is null").drop("node")
        if self.totals is not None:
            added = self.totals.groupBy("trial").agg(F.sum("hit").alias("hits"), F.sum("num").cast("decimal(38,0)").alias("num"))
            found = finish(added, self.budget, self.divisor)
        every = spark.range(self.trials).select(F.col("id").cast("int").alias("trial"))
        rows = every.join(found, "trial", "left")
        return rows.select("trial", F.coalesce("hits", F.lit(0)).alias("hits"), F.coalesce(F.col("num"), F.lit(0)).cast("decimal(38,0)").alias("num"), F.coalesce("est", F.lit(0.0)).alias("est"))

    @property
    def local_df(self) -> DataFrame:
        """(trial, node, est) of nodes in a discovery."""
        return self.sums.where("node is not null").select("trial", "node", "est")

    def snapshots(self, times: list[int], local: bool = False) -> DataFrame:
        """Global estimates at each of ``times``, or the local ones."""
        return snapshots(self.weighed, self.budget, times, self.divisor, self.trials, local)


#: A stream of so many counted edges may be held by each task that counts: some 40 bytes each.
SMALL_STREAM = 1_500_000


def choose_strategy(trials: int, k: int, budget: int, edges: int) -> str:
    """Wedges while the samples are small beside the stream; true triangles for large samples or many trials."""
    return "triangle" if trials > 3 or k * budget >= edges else "wedge"


def routed_closures(edges: DataFrame, k: int, budget: int, mapping, seed: int, trials: int, strategy: str = "wedge", coins: str = "portable", small: bool = False, placed: DataFrame | None = None) -> DataFrame:
    """Weighed discoveries of the routed estimator. ``small``: the stream is counted and a task may hold it. ``placed``: true triangles
    have their workers."""
    assigned = assign(edges, mapping, k, seed)
    residency = reservoir(rank_in_worker(assigned), budget, seed, trials, coins)
    if strategy == "wedge":
        found = load_before(assigned, closures(edges, residency, mapping, k, seed, small))
    elif strategy == "kernel":
        if coins != "portable":
            raise ValueError("the kernel draws portable coins")
        found = closures_by_kernel(edges, mapping, k, budget, seed, trials, seed)
    elif strategy == "probe":
        found = load_before(assigned, closures_probed(edges, residency, mapping, k, seed))
    elif strategy == "triangle":
        found = closures_from_triangles(load_before(assigned, placed_triangles(edges, mapping, k, seed) if placed is None else placed), residency)
    else:
        raise ValueError(f"unknown strategy {strategy!r}")
    return weigh(found, budget)


def estimate_routed(edges: DataFrame, k: int, budget: int, mapping="modulo", theta: float = 0.2, seed: int = 0, trials: int = 1, aggregation: str = "lazy", strategy: str = "auto", aggregators: int | None = None, coins: str = "portable", engine: str = "sequential", found: DataFrame | None = None, small: bool = False) -> Estimate:
    """Nodes have a worker each; edges go where an end lives, triangles are counted by one worker. ``found``: true triangles are listed.
    ``small``: the caller has counted the stream."""
    require_parameters(k, budget)
    edges = require_edge_stream(edges)
    if isinstance(mapping, str) and mapping == "adaptive":
        mapping = pin(adaptive_map(edges, k, theta, engine), "nodemap")
    size = edges.count() if strategy == "auto" else None
    if strategy == "auto":
        strategy = choose_strategy(trials, k, budget, size)
    placed = totals = None
    if strategy == "triangle":
        placed = placed_triangles(edges, mapping, k, seed, listed(edges) if found is None else found)
        if coins == "portable":
            totals = held_sums(placed, assign(edges, mapping, k, seed), k, [budget], seed, trials)
    weighed = routed_closures(edges, k, budget, mapping, seed, trials, strategy, coins, small or size is not None and size <= SMALL_STREAM, placed)
    return Estimate(aggregate(weighed, budget, 1, aggregation == "lazy", aggregators), weighed, budget, 1, trials, totals)


def estimate_broadcast(edges: DataFrame, k: int, budget: int, seed: int = 0, trials: int = 1, aggregation: str = "lazy", coins: str = "portable", strategy: str = "wedge", found: DataFrame | None = None) -> Estimate:
    """Every worker samples the whole stream with coins of its own; the answers are averaged. Strategies wedge, probe, triangle,
    and auto, which is wedge with a counted stream. ``found``: true triangles are listed."""
    require_parameters(k, budget)
    edges = require_edge_stream(edges)
    residency = reservoir(everywhere(edges, k), budget, seed, trials, coins)
    totals = None
    if strategy == "triangle":
        found = listed(edges) if found is None else found
        if coins == "portable":
            totals = held_sums_everywhere(found, edges.count(), k, [budget], seed, trials)
        met = closures_from_triangles(found, residency)
    elif strategy == "probe":
        met = closures_probed(edges, residency)
    else:
        met = closures(edges, residency, small=strategy == "auto" and edges.count() <= SMALL_STREAM)
    weighed = weigh(met.withColumn("load_before", F.col("t") - 1), budget)
    return Estimate(aggregate(weighed, budget, k, aggregation == "lazy"), weighed, budget, k, trials, totals)


def estimate_single(edges: DataFrame, budget: int, seed: int = 0, trials: int = 1, **options) -> Estimate:
    """One worker's answer."""
    return estimate_broadcast(edges, 1, budget, seed, trials, **options)


__all__ = ["Estimate", "choose_strategy", "estimate_broadcast", "estimate_routed", "estimate_single", "routed_closures"]
