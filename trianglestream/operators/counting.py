"""Discoveries: triangles a worker's sample closes, by three strategies with the same result.

``wedge`` joins the samples with themselves and then with the stream; it is the
one-pass algorithm seen as joins. ``probe`` goes from each arriving edge to the samples
at its end of fewer sampled edges and looks the third edge up, so its work is bounded by
the lesser degrees and a hub costs nothing of its own. ``triangle`` lists the true
triangles once, by degree order, and asks which the samples hold; it serves many trials
at small cost.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..functions.weights import counting_worker
from .exact import triangles
from .lookups import closures_at_workers
from .mapping import with_workers

#: A time after all others; a node map of so many counted nodes may be broadcast to triangles.
END, SMALL_MAP = 1 << 62, 1 << 18


def wedges(residency: DataFrame) -> DataFrame:
    """(trial, worker, apex, a, b, t_lo, t_hi): pairs of sampled edges at one node that overlap in time."""
    stay = residency.select("trial", "worker", "u", "v", "t_in", F.coalesce("t_out", F.lit(END)).alias("t_out"))
    ends = F.explode(F.array(F.struct(F.col("u").alias("apex"), F.col("v").alias("o")), F.struct(F.col("v").alias("apex"), F.col("u").alias("o"))))
    rows = stay.select("trial", "worker", ends.alias("e"), "t_in", "t_out").select("trial", "worker", "e.apex", "e.o", "t_in", "t_out")
    left = rows.withColumnsRenamed({"o": "a", "t_in": "in_a", "t_out": "out_a"})
    right = rows.withColumnsRenamed({"o": "b", "t_in": "in_b", "t_out": "out_b"})
    met = left.join(right, ["trial", "worker", "apex"]).where("a < b")
    return met.select("trial", "worker", "apex", "a", "b", F.greatest("in_a", "in_b").alias("t_lo"), F.least("out_a", "out_b").alias("t_hi")).where("t_lo < t_hi")


def closures(edges: DataFrame, residency: DataFrame, mapping=None, k: int = 1, seed: int = 0, small: bool = False) -> DataFrame:
    """(trial, worker, u, v, apex, t). With a mapping, an edge inside one worker is sent to that worker only.

    ``small``: the caller has counted the stream and found that each task may hold it, so wedges are not shuffled."""
    stream = edges if mapping is None else with_workers(edges, mapping, k, seed)
    if small:
        return closures_at_workers(stream, residency)
    found = wedges(residency).join(stream, (F.col("a") == F.col("u")) & (F.col("b") == F.col("v")))
    found = found.where("t_lo < t and t <= t_hi")
    if mapping is not None:
        found = found.where("fu <> fv or worker = fu")
    return found.select("trial", "worker", "u", "v", "apex", "t")


def probes(edges: DataFrame, residency: DataFrame, mapping=None, k: int = 1, seed: int = 0) -> DataFrame:
    """(trial, worker, t, u, v, y, w): for each arriving edge, the sampled edges (x, w) at its end x of fewer sampled edges
    that stand when it arrives; y is the other end. No more than the lesser sampled degrees add up to."""
    stream = edges if mapping is None else with_workers(edges, mapping, k, seed)
    both = F.explode(F.array(F.struct(F.col("u").alias("x"), F.col("v").alias("w")), F.struct(F.col("v").alias("x"), F.col("u").alias("w"))))
    ends = residency.select("trial", "worker", both.alias("e"), "t_in", F.coalesce("t_out", F.lit(END)).alias("t_out")).select("trial", "worker", "e.x", "e.w", "t_in", "t_out")
    held = ends.groupBy("x").agg(F.count(F.lit(1)).alias("held"))
    sides = stream.join(held.withColumnsRenamed({"x": "u", "held": "du"}), "u").join(held.withColumnsRenamed({"x": "v", "held": "dv"}), "v")
    low = F.col("du") <= F.col("dv")
    sides = sides.withColumns({"x": F.when(low, F.col("u")).otherwise(F.col("v")), "y": F.when(low, F.col("v")).otherwise(F.col("u"))}).drop("du", "dv")
    met = sides.join(ends, "x").where("w <> y and t_in < t and t <= t_out")
    if mapping is not None:
        met = met.where("fu <> fv or worker = fu")
    return met.select("trial", "worker", "t", "u", "v", "y", "w")


def closures_probed(edges: DataFrame, residency: DataFrame, mapping=None, k: int = 1, seed: int = 0) -> DataFrame:
    """The same closures as ``closures``, from the arriving edges' side."""
    third = residency.select("trial", "worker", F.col("u").alias("a"), F.col("v").alias("b"), "t_in", F.coalesce("t_out", F.lit(END)).alias("t_out"))
    asked = probes(edges, residency, mapping, k, seed).withColumns({"a": F.least("y", "w"), "b": F.greatest("y", "w")})
    found = asked.join(third, ["trial", "worker", "a", "b"]).where("t_in < t and t <= t_out")
    return found.select("trial", "worker", "u", "v", F.col("w").alias("apex"), "t")


def placed_triangles(edges: DataFrame, mapping, k: int, seed: int = 0, found: DataFrame | None = None) -> DataFrame:
    """True triangles with their counting worker: (worker, u, v, apex, t, t1, t2), older edges' times t1 < t2. ``found``: they are listed."""
    found = triangles(edges) if found is None else found
    if isinstance(mapping, DataFrame):
        mapping = F.broadcast(mapping) if mapping.count() <= SMALL_MAP else mapping
        rows = found.join(mapping.select(F.col("node").alias("apex"), F.col("worker").alias("fw")), "apex")
    else:
        third = with_workers(found.select(F.col("apex").alias("u"), F.col("apex").alias("v"), F.struct(*found.columns).alias("row")), mapping, k, seed)
        rows = third.select("row.*", F.col("fu").alias("fw"))
    return with_workers(rows, mapping, k, seed).select(counting_worker(F.col("fu"), F.col("fv"), F.col("fw")).alias("worker"), "u", "v", "apex", "t", "t1", "t2")


def closures_from_triangles(placed: DataFrame, residency: DataFrame) -> DataFrame:
    """The same closures, from placed triangles and two look-ups of the samples; a load of the triangles is kept, and a budget of
    the samples. Triangles without a worker are counted by every one."""
    runs = [c for c in ("budget", "trial") if c in residency.columns]
    stay = residency.select(*runs, "worker", "t_in", F.coalesce("t_out", F.lit(END)).alias("t_out"))
    one = stay.withColumnsRenamed({"t_in": "t1", "t_out": "out1"})
    two = stay.withColumnsRenamed({"t_in": "t2", "t_out": "out2"})
    met = placed.join(one, [c for c in ("worker", "t1") if c in placed.columns]).join(two, [*runs, "worker", "t2"])
    load = ["load_before"] if "load_before" in placed.columns else []
    return met.where("t <= out1 and t <= out2").select(*runs, "worker", "u", "v", "apex", "t", *load)
