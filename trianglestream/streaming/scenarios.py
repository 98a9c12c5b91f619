"""Registered runs of the streaming forms over the event files, to their end."""

from __future__ import annotations

from uuid import uuid4

from pyspark.sql import DataFrame, functions as F

from ..sources.tables import shared_root
from .edges import edge_counts, edge_files
from .routed import estimate_adaptive_stream, estimate_stream, files_in_order, run_to_end, settle, stream_events, timed_events


def _files(spark, sf_dir: str) -> tuple[str, DataFrame]:
    """A folder of its own and a stream over six files of events, one a batch."""
    root = f"{shared_root(spark)}/live-{uuid4().hex}"
    return root, edge_files(spark, stream_events(spark, sf_dir, f"{root}/in"), 1)


def _fed(spark, sf_dir: str, updates, budget: int, files: int = 6) -> DataFrame:
    """Estimates after six files of events. Each file is written when the run over those before it has ended, so that files come in
    order of their events whatever time the store gives them, and all state passes through the checkpoint. ``updates``: from the
    folder and the stream over its files."""
    root, found = f"{shared_root(spark)}/live-{uuid4().hex}", []

    def run():
        found[:] = [run_to_end(updates(root, edge_files(spark, f"{root}/in")), f"{root}/out", f"{root}/state")]

    files_in_order(*timed_events(spark, sf_dir), f"{root}/in", files, run)
    return settle(found[0], budget)


def estimated(spark, sf_dir: str, k: int, budget: int, seed: int, lazy: bool) -> DataFrame:
    return _fed(spark, sf_dir, lambda root, edges: estimate_stream(edges, k, budget, seed=seed, lazy=lazy), budget)


def estimated_adaptive(spark, sf_dir: str, k: int, budget: int, seed: int) -> DataFrame:
    return _fed(spark, sf_dir, lambda root, edges: estimate_adaptive_stream(edges, k, budget, f"{root}/routed", f"{root}/state", seed=seed), budget)


def _table(df: DataFrame, mode: str) -> DataFrame:
    """What a query leaves in a memory table."""
    name = f"live_{uuid4().hex}"
    query = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return df.sparkSession.table(name)


def sliding(spark, sf_dir: str) -> DataFrame:
    """Edges in windows of ten minutes that begin every five."""
    _, edges = _files(spark, sf_dir)
    return _table(edge_counts(edges, "10 minutes", "5 minutes"), "complete")


def late(spark, sf_dir: str) -> DataFrame:
    """Rows kept and rows that came after the watermark: the files in order, then one with seven edges of long ago,
    each in a window of its own, as the engine counts late rows after its partial aggregation."""
    root, edges = _files(spark, sf_dir)
    counts = edge_counts(edges, "1 minute", late="10 seconds")
    sink, state = f"{root}/late", f"{root}/late-state"

    def run() -> int:
        query = counts.writeStream.format("parquet").option("path", sink).option("checkpointLocation", state).outputMode("append").trigger(availableNow=True).start()
        query.awaitTermination()
        return sum(int(op.numRowsDroppedByWatermark) for progress in query.recentProgress for op in progress.stateOperators)

    run()
    old = spark.range(7).select(F.timestamp_seconds(F.lit(-1_000_000) - F.col("id") * 60).alias("ts"), (-F.col("id") - 2).alias("u"), (-F.col("id") - 1).alias("v"))
    old.coalesce(1).write.mode("append").parquet(f"{root}/in")
    dropped = run()
    kept = spark.read.parquet(f"{root}/in").where("ts > timestamp'1970-01-01 00:00:00'").agg(F.count(F.lit(1)).alias("edges"))
    return kept.withColumn("dropped", F.lit(dropped).cast("bigint"))
