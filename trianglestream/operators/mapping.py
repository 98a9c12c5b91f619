"""Node-to-worker mappings: modulo, random, load-aware (sequential and by epochs), or the caller's own.

Stateless mappings are column expressions and cost nothing to apply. A node map is
a table (node, worker); it is joined to the stream on either end.
"""

from __future__ import annotations

from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from ..functions.hashing import coin, colour
from ..sources.tables import pin


def modulo_map(node: Column, k: int) -> Column:
    return F.pmod(node, F.lit(k)).cast("int")


def random_map(node: Column, k: int, seed: int = 0) -> Column:
    return colour(node, k, seed)


class GreedyColours:
    """The load-aware rule, one edge at a time; ties of load go to the smallest worker."""

    def __init__(self, k: int, theta: float):
        self.loads, self.colour, self.slack = [0] * k, {}, 1 + theta

    def see(self, u: int, v: int) -> tuple[int, int, list[int]]:
        """Colours of both ends and the nodes that got theirs just now."""
        colour, loads = self.colour, self.loads
        cu, cv = colour.get(u), colour.get(v)
        new = []
        if cu is None or cv is None:
            lightest = min(loads)
            spare = loads.index(lightest)
            if cu is None and cv is None:
                cu = cv = spare
                new = [u, v]
            elif cu is None:
                cu = cv if loads[cv] <= self.slack * lightest else spare
                new = [u]
            else:
                cv = cu if loads[cu] <= self.slack * lightest else spare
                new = [v]
            for node in new:
                colour[node] = cu if node == u else cv
        loads[cu] += 1
        if cv != cu:
            loads[cv] += 1
        return cu, cv, new


def adaptive_map(edges: DataFrame, k: int, theta: float = 0.2, engine: str = "sequential", epochs: int = 8) -> DataFrame:
    """(node, worker). ``sequential`` is the exact rule, a single ordered task by its nature; ``epoch`` spreads out."""
    if engine == "sequential":

        def run(batches):
            state = GreedyColours(k, theta)
            for batch in batches:
                nodes, workers = [], []
                for u, v in zip(batch.column("u").to_pylist(), batch.column("v").to_pylist()):
                    for node in state.see(u, v)[2]:
                        nodes.append(node)
                        workers.append(state.colour[node])
                yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array(workers, pa.int32())], ["node", "worker"])

        return edges.select("t", "u", "v").repartition(1).sortWithinPartitions("t").mapInArrow(run, "node bigint, worker int")
    if engine != "epoch":
        raise ValueError(f"unknown engine {engine!r}")
    return epoch_map(edges, k, theta, epochs)


def epoch_map(edges: DataFrame, k: int, theta: float, epochs: int) -> DataFrame:
    """Loads stand still within an epoch, whose new nodes are coloured side by side.

    A newcomer follows the known partner of its first edge while that worker's load is
    within tolerance; others go, together with their first partner, to a lightly loaded
    worker picked by hash. Any colouring keeps estimates unbiased, so staleness costs
    balance only. Epochs double in length, so the number of jobs is logarithmic.
    """
    last = edges.agg(F.max("t")).first()[0] or 0
    bounds = sorted({0, last, *[last >> i for i in range(epochs - 1)]})
    loads, known = [0] * k, None
    for begin, end in zip(bounds, bounds[1:]):
        part = edges.where((F.col("t") > begin) & (F.col("t") <= end))
        ends = part.select("t", F.explode(F.array(F.struct(F.col("u").alias("node"), F.col("v").alias("partner")), F.struct(F.col("v").alias("node"), F.col("u").alias("partner")))).alias("e")).select("t", "e.*")
        first = ends.groupBy("node").agg(F.min(F.struct("t", "partner")).alias("first")).select("node", F.col("first.partner").alias("partner"))
        light = sorted(range(k), key=lambda w: (loads[w], w))[: max(1, (k + 1) // 2)]
        fits = F.array(*[F.lit(load <= (1 + theta) * min(loads)) for load in loads])
        if known is not None:
            first = first.join(known, "node", "left_anti").join(known.select(F.col("node").alias("partner"), F.col("worker").alias("theirs")), "partner", "left")
        else:
            first = first.withColumn("theirs", F.lit(None).cast("int"))
        spare = F.get(F.array(*[F.lit(w) for w in light]), F.floor(coin("p", F.least("node", "partner")) * len(light)).cast("int"))
        fresh = first.select("node", F.when(F.col("theirs").isNotNull() & F.get(fits, F.col("theirs")), F.col("theirs")).otherwise(spare).cast("int").alias("worker"))
        known = pin(fresh if known is None else known.unionByName(fresh), "nodemap")
        both = with_workers(part, known, k)
        per = both.select(F.explode(F.array_distinct(F.array("fu", "fv"))).alias("worker")).groupBy("worker").count().collect()  # at most k rows
        for row in per:
            loads[row["worker"]] += row["count"]
    if known is None:
        return edges.select(F.col("u").alias("node"), F.lit(0).alias("worker")).limit(0)
    return known


def with_workers(edges: DataFrame, mapping: str | DataFrame | Callable[[Column], Column], k: int, seed: int = 0) -> DataFrame:
    """``edges`` with fu and fv, the workers of both ends. Catalyst broadcasts a node map only if its size allows."""
    if isinstance(mapping, DataFrame):
        u, v = mapping.select(F.col("node").alias("u"), F.col("worker").alias("fu")), mapping.select(F.col("node").alias("v"), F.col("worker").alias("fv"))
        return edges.join(u, "u").join(v, "v")
    if mapping == "modulo":
        rule = lambda c: modulo_map(c, k)
    elif mapping == "random":
        rule = lambda c: random_map(c, k, seed)
    elif callable(mapping):
        rule = mapping
    else:
        raise ValueError(f"unknown mapping {mapping!r}")
    return edges.withColumn("fu", rule(F.col("u"))).withColumn("fv", rule(F.col("v")))


def first_worker(nodes: DataFrame, mapping, k: int, seed: int = 0) -> DataFrame:
    """``nodes`` (node) with their worker."""
    if isinstance(mapping, DataFrame):
        return nodes.join(mapping, "node")
    return with_workers(nodes.select(F.col("node").alias("u"), F.col("node").alias("v")), mapping, k, seed).select(F.col("u").alias("node"), F.col("fu").alias("worker"))


def share_local(edges: DataFrame, mapping, k: int, seed: int = 0) -> DataFrame:
    """Share of edges whose ends have one worker."""
    both = with_workers(edges, mapping, k, seed)
    return both.agg((F.count_if(F.col("fu") == F.col("fv")) / F.count(F.lit(1))).alias("local_share"))


__all__ = ["GreedyColours", "adaptive_map", "epoch_map", "first_worker", "modulo_map", "random_map", "share_local", "with_workers"]
