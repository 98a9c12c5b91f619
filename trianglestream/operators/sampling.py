"""Routing, ranks, loads and reservoirs as set operations.

A worker's reservoir needs no state: the edge of rank r asks for slot r while there
is room and for a uniform slot of r afterwards; it is taken in if the slot exists
and stays until the next edge taken into that slot. Ranks are numbered inside
chunks of time and shifted by what came before, so windows stay small.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from ..functions.hashing import coin
from ..functions.weights import edge_slot
from .mapping import with_workers

#: Length of a chunk of time.
CHUNK = 1 << 16


def assign(edges: DataFrame, mapping, k: int, seed: int = 0) -> DataFrame:
    """(worker, t, u, v): the workers that may store an edge, one or two of them."""
    both = with_workers(edges, mapping, k, seed)
    return both.select(F.explode(F.array_distinct(F.array("fu", "fv"))).alias("worker"), "t", "u", "v")


def messages(edges: DataFrame, mapping, k: int, seed: int = 0) -> DataFrame:
    """(worker, t, u, v, assigned): every delivery, with the bit that tells a worker the edge is its own."""
    both = with_workers(edges, mapping, k, seed)
    to = F.when(F.col("fu") == F.col("fv"), F.array("fu")).otherwise(F.sequence(F.lit(0), F.lit(k - 1)))
    sent = both.select(F.explode(to).alias("worker"), "t", "u", "v", "fu", "fv")
    return sent.select("worker", "t", "u", "v", ((F.col("worker") == F.col("fu")) | (F.col("worker") == F.col("fv"))).alias("assigned"))


def chunk_offsets(assigned: DataFrame, chunk: int = CHUNK) -> DataFrame:
    """(chunk, worker, before): edges of a worker in all earlier chunks."""
    counts = assigned.groupBy(F.floor(F.col("t") / chunk).alias("chunk"), "worker").agg(F.count(F.lit(1)).alias("n"))
    earlier = Window.partitionBy("worker").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    return counts.select("chunk", "worker", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("before"))


def rank_in_worker(assigned: DataFrame, chunk: int = CHUNK) -> DataFrame:
    """``assigned`` with rank: how many edges the worker has considered, this one included."""
    rows = assigned.withColumn("chunk", F.floor(F.col("t") / chunk))
    inside = Window.partitionBy("chunk", "worker").orderBy("t")
    return rows.join(chunk_offsets(assigned, chunk), ["chunk", "worker"]).withColumn("rank", (F.row_number().over(inside) + F.col("before")).cast("bigint")).drop("chunk", "before")


def load_before(assigned: DataFrame, probes: DataFrame, chunk: int = CHUNK) -> DataFrame:
    """``probes`` (worker, t, ...) with load_before: edges the worker considered strictly before t.

    Edges and probes of a chunk run through one window; counts of earlier chunks come from the
    last chunk of the worker at or before the probe's.
    """
    probe_cols = [c for c in probes.columns if c not in ("worker", "t")]
    own = assigned.select("worker", "t", F.lit(1).alias("one"), F.lit(None).cast(F_struct(probes, probe_cols)).alias("probe"))
    asked = probes.select("worker", "t", F.lit(0).alias("one"), F.struct(*probe_cols, F.lit(True).alias("_is")).alias("probe"))
    rows = own.unionByName(asked).withColumn("chunk", F.floor(F.col("t") / chunk))
    past = Window.partitionBy("worker", "chunk").orderBy("t").rangeBetween(Window.unboundedPreceding, -1)
    inside = rows.withColumn("inside", F.coalesce(F.sum("one").over(past), F.lit(0))).where("probe is not null")
    # A worker with no edge in the probe's chunk still has those of earlier ones.
    chunks = rows.groupBy("worker", "chunk").agg(F.sum("one").alias("n"))
    earlier = Window.partitionBy("worker").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    before = chunks.select("worker", "chunk", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("before"))
    found = inside.join(before, ["worker", "chunk"])
    return found.select("worker", "t", *[F.col(f"probe.{c}").alias(c) for c in probe_cols], (F.col("inside") + F.col("before")).cast("bigint").alias("load_before"))


def F_struct(df: DataFrame, columns: list[str]) -> str:
    """Type of the struct that holds a probe."""
    kinds = dict(df.dtypes)
    return "struct<" + ",".join(f"`{c}`:{kinds[c]}" for c in columns) + ",_is:boolean>"


def accepted(ranked: DataFrame, budget: int, seed: int, trials: int = 1, kind: str = "portable") -> DataFrame:
    """``ranked`` rows that enter their worker's sample, per trial, with their slot."""
    rows = ranked.withColumn("trial", F.explode(F.sequence(F.lit(0), F.lit(trials - 1))))
    u01 = coin(seed, F.col("trial"), F.col("worker"), F.col("rank"), kind=kind)
    return rows.withColumn("slot", edge_slot(F.col("rank"), budget, u01)).where(F.col("slot") <= budget)


def reservoir(ranked: DataFrame, budget: int, seed: int = 0, trials: int = 1, kind: str = "portable") -> DataFrame:
    """Residency: (trial, worker, u, v, rank, slot, t_in, t_out), t_out null while it stays."""
    turn = Window.partitionBy("trial", "worker", "slot").orderBy("t")
    rows = accepted(ranked, budget, seed, trials, kind).withColumn("t_out", F.lead("t").over(turn))
    return rows.select("trial", "worker", "u", "v", "rank", "slot", F.col("t").alias("t_in"), "t_out")


def everywhere(edges: DataFrame, k: int) -> DataFrame:
    """Ranks under the broadcast policy: each worker considers all edges, so the rank is the time."""
    return edges.select(F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("worker"), "t", "u", "v", F.col("t").alias("rank"))
