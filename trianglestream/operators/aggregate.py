"""From discoveries to estimates, with exact integer sums until the last step.

A discovery at a load within the budget weighs one and goes to ``hits``; beyond it
the numerator l(l-1) goes to ``num`` and the fixed denominator b(b-1) divides once.
Node null stands for the whole graph.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F


def weigh(closures: DataFrame, budget: int | Column) -> DataFrame:
    """``closures`` with load_before to (.., hit, num). ``budget`` may be a column."""
    load = F.col("load_before")
    return closures.withColumn("hit", F.when(load <= budget, 1).otherwise(0).cast("bigint")).withColumn("num", F.when(load <= budget, F.lit(0)).otherwise(load * (load - 1)).cast("decimal(38,0)"))


def updates(weighed: DataFrame) -> DataFrame:
    """Eager form: four rows for each discovery, (trial, worker, node, t, hit, num)."""
    keys = F.explode(F.array(F.lit(None).cast("bigint"), F.col("u"), F.col("v"), F.col("apex")))
    return weighed.select("trial", "worker", keys.alias("node"), "t", "hit", "num")


def lazy_updates(weighed: DataFrame) -> DataFrame:
    """Lazy form: what each worker ships once, (trial, worker, node, hits, num)."""
    return updates(weighed).groupBy("trial", "worker", "node").agg(F.sum("hit").alias("hits"), F.sum("num").cast("decimal(38,0)").alias("num"))


def finish(sums: DataFrame, budget: int | Column, divisor: int = 1) -> DataFrame:
    """(.., est) of (.., hits, num)."""
    room = budget.cast("double") * (budget - 1) if isinstance(budget, Column) else F.lit(float(budget) * (budget - 1))
    est = (F.col("hits").cast("double") + F.col("num").cast("double") / room) / F.lit(float(divisor))
    return sums.withColumn("est", est)


def aggregate(weighed: DataFrame, budget: int, divisor: int = 1, lazy: bool = True, aggregators: int | None = None) -> DataFrame:
    """(trial, node, hits, num, est). ``aggregators`` fixes the number of hash partitions that add."""
    if lazy:
        rows = lazy_updates(weighed).select("trial", "node", "hits", "num")
    else:
        rows = updates(weighed).select("trial", "node", F.col("hit").alias("hits"), "num")
    if aggregators is not None:
        rows = rows.repartition(aggregators, "trial", "node")
    sums = rows.groupBy("trial", "node").agg(F.sum("hits").alias("hits"), F.sum("num").cast("decimal(38,0)").alias("num"))
    return finish(sums, budget, divisor)


def trial_estimates(weighed: DataFrame, budgets: list[int], trials: int, divisor: int = 1) -> DataFrame:
    """(budget, trial, est) of the whole graph from (budget, trial, hit, num), zero where nothing was found."""
    sums = weighed.groupBy("budget", "trial").agg(F.sum("hit").alias("hits"), F.sum("num").cast("decimal(38,0)").alias("num"))
    every = weighed.sparkSession.range(trials).select(F.explode(F.array(*[F.lit(b).cast("bigint") for b in sorted(set(budgets))])).alias("budget"), F.col("id").cast("int").alias("trial"))
    rows = every.join(sums, ["budget", "trial"], "left")
    return finish(rows.select("budget", "trial", F.coalesce("hits", F.lit(0)).alias("hits"), F.coalesce("num", F.lit(0)).cast("decimal(38,0)").alias("num")), F.col("budget"), divisor).select("budget", "trial", "est")


def snapshots(weighed: DataFrame, budget: int, times: list[int], divisor: int = 1, trials: int = 1, local: bool = False) -> DataFrame:
    """(trial, as_of, hits, num, est): the global estimate of every trial at each of ``times``, zero where nothing was found.
    With ``local``, (trial, as_of, node, est) of the nodes in a discovery by then."""
    times = sorted(times)
    at = F.lit(len(times))
    for i in range(len(times) - 1, -1, -1):
        at = F.when(F.col("t") <= times[i], F.lit(i)).otherwise(at)
    keys = ["trial", "node"] if local else ["trial"]
    found = updates(weighed).where("node is not null") if local else weighed
    total = [F.sum("hit").alias("hit"), F.sum("num").cast("decimal(38,0)").alias("num")]
    # Sums between snapshots first; each then counts for its own and all later ones.
    part = found.select(*keys, at.alias("i"), "hit", "num").where(F.col("i") < len(times)).groupBy(*keys, "i").agg(*total)
    upto = part.withColumn("i", F.explode(F.sequence("i", F.lit(len(times) - 1)))).groupBy(*keys, "i").agg(*total).withColumnRenamed("hit", "hits")
    moments = F.array(*[F.lit(t).cast("bigint") for t in times])
    if local:
        return finish(upto.select("trial", F.get(moments, F.col("i")).alias("as_of"), "node", "hits", "num"), budget, divisor).select("trial", "as_of", "node", "est")
    grid = weighed.sparkSession.range(trials).select(F.col("id").cast("int").alias("trial"), F.posexplode(moments).alias("i", "as_of"))
    rows = grid.join(upto, ["trial", "i"], "left")
    return finish(rows.select("trial", "as_of", F.coalesce("hits", F.lit(0)).alias("hits"), F.coalesce("num", F.lit(0)).cast("decimal(38,0)").alias("num")), budget, divisor)
