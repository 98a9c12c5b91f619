"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from .exact import nodes_of
from .mapping import with_workers
from .sampling import assign


def global_metrics(estimates: DataFrame, truth: int, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, trials, mean, stderr, error, variance) of (by, trial, est) against the true count."""
    x = F.lit(float(truth))
    return estimates.groupBy(*by).agg(
        F.count(F.lit(1)).alias("trials"), F.avg("est").alias("mean"), (F.stddev_samp("est") / F.sqrt(F.count(F.lit(1)))).alias("stderr"),
        F.avg(F.abs(F.col("est") - x) / (x + 1)).alias("error"), F.avg((F.col("est") - x) * (F.col("est") - x)).alias("variance"),
    )


def paired_local(local: DataFrame, edges: DataFrame, truth: DataFrame) -> DataFrame:
    """(node, x, est) over all nodes; what is absent is zero."""
    rows = nodes_of(edges).join(truth.withColumnRenamed("n", "x"), "node", "left").join(local.select("node", "est"), "node", "left")
    return rows.select("node", F.coalesce("x", F.lit(0)).alias("x"), F.coalesce("est", F.lit(0.0)).alias("est"))


def ranked(rows: DataFrame, column: str) -> DataFrame:
    """(column, rank): mean rank of each value, none of them negative. Distinct values may be as many as rows, so they are
    numbered inside chunks of the scale, and only chunks, whose number is bounded, are ordered in one window."""
    chunk = F.floor(F.log2(F.col(column).cast("double") + 1) * 1024)
    values = rows.groupBy(column).agg(F.count(F.lit(1)).alias("same")).withColumn("chunk", chunk)
    earlier = Window.orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    chunks = values.groupBy("chunk").agg(F.sum("same").alias("n")).select("chunk", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("before"))
    inside = Window.partitionBy("chunk").orderBy(column).rowsBetween(Window.unboundedPreceding, -1)
    placed = values.join(chunks, "chunk").withColumn("before", F.col("before") + F.coalesce(F.sum("same").over(inside), F.lit(0)))
    return placed.select(column, (F.col("before") + (F.col("same") + 1) / 2).alias(f"{column}_rank"))


def local_metrics(paired: DataFrame) -> DataFrame:
    """(nodes, error, rmse, spearman) of (node, x, est); the rank correlation of constants is null."""
    both = paired.join(ranked(paired, "x"), "x").join(ranked(paired, "est"), "est")
    return both.agg(
        F.count(F.lit(1)).alias("nodes"), F.avg(F.abs(F.col("x") - F.col("est")) / (F.col("x") + 1)).alias("error"),
        F.sqrt(F.avg((F.col("x") - F.col("est")) * (F.col("x") - F.col("est")))).alias("rmse"), F.try_divide(F.covar_pop("x_rank", "est_rank"), F.stddev_pop("x_rank") * F.stddev_pop("est_rank")).alias("spearman"),
    )


def variance_slope(rows: DataFrame, by: list[str]) -> DataFrame:
    """(by, slope) of ln variance on ln k."""
    return rows.groupBy(*by).agg(F.regr_slope(F.ln("variance"), F.ln(F.col("k").cast("double"))).alias("slope"))


def linearity(rows: DataFrame) -> DataFrame:
    """(r2) of seconds on edges."""
    return rows.agg(F.regr_r2("seconds", "edges").alias("r2"))


def message_costs(edges: DataFrame, mapping, k: int, seed: int = 0) -> DataFrame:
    """(messages, bytes, considered, stored_unique): deliveries, 16 bytes and a bit each, storage candidates."""
    both = with_workers(edges, mapping, k, seed).withColumn("same", F.col("fu") == F.col("fv"))
    out = both.agg(F.sum(F.when(F.col("same"), 1).otherwise(k)).alias("messages"), F.sum(F.when(F.col("same"), 1).otherwise(2)).alias("considered"), F.count(F.lit(1)).alias("stored_unique"))
    return out.select("messages", (F.col("messages") * 16).alias("bytes"), "considered", "stored_unique")


def load_balance(edges: DataFrame, mapping, k: int, seed: int = 0) -> DataFrame:
    """(least, most, mean, imbalance) of worker loads; workers without edges count."""
    loads = assign(edges, mapping, k, seed).groupBy("worker").agg(F.count(F.lit(1)).alias("load"))
    every = edges.sparkSession.range(k).select(F.col("id").cast("int").alias("worker")).join(loads, "worker", "left").select(F.coalesce("load", F.lit(0)).alias("load"))
    return every.agg(F.min("load").alias("least"), F.max("load").alias("most"), F.avg("load").alias("mean")).withColumn("imbalance", F.col("most") / F.col("mean"))


def counting_calls(edges: DataFrame, mapping, k: int, seed: int = 0) -> DataFrame:
    """(worker, calls): deliveries at each worker, on each of which it looks for common neighbours."""
    both = with_workers(edges, mapping, k, seed)
    local = both.where("fu = fv").groupBy(F.col("fu").alias("worker")).agg(F.count(F.lit(1)).alias("own"))
    cross = both.where("fu <> fv").agg(F.count(F.lit(1)).alias("cross")).first()["cross"]
    every = edges.sparkSession.range(k).select(F.col("id").cast("int").alias("worker"))
    return every.join(local, "worker", "left").select("worker", (F.coalesce("own", F.lit(0)) + F.lit(cross)).alias("calls"))


def ratios(rows: DataFrame, base: str, metrics: list[str]) -> DataFrame:
    """(method, <metric>_ratio): each method's metrics over those of ``base``."""
    ref = rows.where(F.col("method") == base).select(*[F.col(m).alias(f"_{m}") for m in metrics])
    return rows.crossJoin(F.broadcast(ref.limit(1))).select("method", *[(F.col(m) / F.col(f"_{m}")).alias(f"{m}_ratio") for m in metrics])
