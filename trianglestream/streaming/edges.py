"""Edges from live events: source, late data, windows, and removal of repeats."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F, types as T

from ..functions.weights import canonical

EDGE_EVENTS = T.StructType([T.StructField("ts", T.TimestampType()), T.StructField("u", T.LongType()), T.StructField("v", T.LongType())])


def edge_files(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """A file stream of (ts, u, v); a batch takes so many new files."""
    return spark.readStream.schema(EDGE_EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def edge_rate(spark: SparkSession, nodes: int, rows_per_second: int = 1000) -> DataFrame:
    """Hash-made edges at a steady rate, for load tests."""
    rate = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    end = lambda salt: F.pmod(F.xxhash64("value", F.lit(salt)), F.lit(nodes))
    return rate.select(F.col("timestamp").alias("ts"), end(1).alias("u"), end(2).alias("v"))


def clean_stream(edges: DataFrame, late: str = "10 minutes", forget: bool = True) -> DataFrame:
    """Canonical edges without loops; repeats go as long as the watermark remembers them.

    Edges later than ``late`` are dropped by the engine and show in the query's progress as rows
    dropped by watermark. ``forget=False`` remembers all edges, for exact removal at the price of state.
    """
    u, v = canonical(F.col("u"), F.col("v"))
    rows = edges.select("ts", u.alias("u"), v.alias("v")).where("u < v").withWatermark("ts", late)
    return rows.dropDuplicatesWithinWatermark(["u", "v"]) if forget else rows.dropDuplicates(["u", "v"])


def edge_counts(edges: DataFrame, width: str = "1 hour", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """(begin, edges) of tumbling or sliding windows."""
    rows = edges.withWatermark("ts", late)
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return rows.groupBy(window.alias("w")).agg(F.count(F.lit(1)).alias("edges")).select(F.col("w.start").alias("begin"), "edges")


def activity_sessions(edges: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """(node, begin, finish, edges): bursts of edges at a node."""
    rows = edges.withWatermark("ts", late).select("ts", F.explode(F.array("u", "v")).alias("node"))
    return rows.groupBy("node", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("edges")).select("node", F.col("w.start").alias("begin"), F.col("w.end").alias("finish"), "edges")
