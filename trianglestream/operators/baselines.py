"""Single-machine baselines: fixed-rate coin, wedge reservoir and adjacency-biased hold sampler."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from ..functions.hashing import coin, coin_value
from .counting import closures


def edge_coin(edges: DataFrame, p: float, seed: int = 0, trials: int = 1, small: bool = False) -> DataFrame:
    """(trial, node, found, est): each edge is kept with chance ``p``; a triangle closed over two kept edges weighs 1/p². ``small``: as
    of ``closures``."""
    rows = edges.withColumn("trial", F.explode(F.sequence(F.lit(0), F.lit(trials - 1)))).withColumn("worker", F.lit(0))
    kept = rows.where(coin("c", seed, F.col("trial"), F.col("t")) < p)
    stay = kept.select("trial", "worker", "u", "v", F.col("t").alias("rank"), F.col("t").alias("slot"), F.col("t").alias("t_in"), F.lit(None).cast("bigint").alias("t_out"))
    keys = F.explode(F.array(F.lit(None).cast("bigint"), F.col("u"), F.col("v"), F.col("apex")))
    found = closures(edges, stay, small=small).select("trial", keys.alias("node")).groupBy("trial", "node").agg(F.count(F.lit(1)).alias("found"))
    return found.withColumn("est", F.col("found") / F.lit(p * p))


def wedge_picks(edges: DataFrame, estimators: int, seed: int = 0, trials: int = 1) -> DataFrame:
    """(trial, i, c, closed): each estimator's uniform edge, how many later edges touch it, and whether the wedge
    with a uniform one of them is closed still later."""
    n = edges.agg(F.max("t")).first()[0] or 0
    grid = edges.sparkSession.range(estimators * trials).select((F.col("id") % trials).cast("int").alias("trial"), F.floor(F.col("id") / trials).alias("i"))
    grid = grid.withColumn("t1", (F.floor(coin("w1", seed, F.col("trial"), F.col("i")) * n) + 1).cast("bigint"))
    first = grid.join(edges.select(F.col("t").alias("t1"), F.col("u").alias("u1"), F.col("v").alias("v1")), "t1")
    ends = F.explode(F.array(F.struct(F.col("u1").alias("end"), F.col("v1").alias("far")), F.struct(F.col("v1").alias("end"), F.col("u1").alias("far"))))
    touching = edges.select(F.explode(F.array(F.struct(F.col("u").alias("end"), F.col("v").alias("o")), F.struct(F.col("v").alias("end"), F.col("u").alias("o")))).alias("e"), F.col("t").alias("t2")).select("e.end", "e.o", "t2")
    later = first.select("trial", "i", "t1", ends.alias("e")).select("trial", "i", "t1", "e.end", "e.far").join(touching, "end").where("t2 > t1")
    own = Window.partitionBy("trial", "i")
    later = later.withColumn("nth", F.row_number().over(own.orderBy("t2"))).withColumn("c", F.count(F.lit(1)).over(own))
    chosen = later.where(F.col("nth") == F.floor(coin("w2", seed, F.col("trial"), F.col("i")) * F.col("c")) + 1)
    closing = edges.select(F.col("u").alias("x"), F.col("v").alias("y"), F.col("t").alias("t3"))
    closed = chosen.withColumn("x", F.least("far", "o")).withColumn("y", F.greatest("far", "o")).join(closing, ["x", "y"], "left")
    return closed.select("trial", "i", "c", F.coalesce(F.col("t3") > F.col("t2"), F.lit(False)).alias("closed"))


def wedge_reservoir(edges: DataFrame, estimators: int, seed: int = 0, trials: int = 1) -> DataFrame:
    """(trial, est): mean over estimators of touching edges times all edges where the wedge closes; global only."""
    n = edges.agg(F.max("t")).first()[0] or 0
    every = edges.sparkSession.range(trials).select(F.col("id").cast("int").alias("trial"))
    sums = wedge_picks(edges, estimators, seed, trials).groupBy("trial").agg(F.sum(F.when(F.col("closed"), F.col("c")).otherwise(0)).alias("s"))
    return every.join(sums, "trial", "left").select("trial", (F.coalesce("s", F.lit(0)) * F.lit(float(n)) / F.lit(float(estimators))).alias("est"))


class HoldSampler:
    """Keeps an edge with chance p if it touches no kept edge, q if it does, surely if it closes a kept wedge
    (``sure``); triangles inside the sample weigh the product of reciprocal chances."""

    def __init__(self, p: float, q: float, sure: bool):
        self.p, self.q, self.sure, self.near, self.est, self.held = p, q, sure, {}, 0.0, 0

    def see(self, u: int, v: int, toss: float) -> None:
        mine, theirs = self.near.get(u, {}), self.near.get(v, {})
        common = [w for w in (mine if len(mine) < len(theirs) else theirs) if w in mine and w in theirs]
        chance = 1.0 if common and self.sure else self.q if mine or theirs else self.p
        if toss < chance:
            self.est += sum(mine[w] * theirs[w] / chance for w in common)
            self.near.setdefault(u, {})[v] = 1 / chance
            self.near.setdefault(v, {})[u] = 1 / chance
            self.held += 1


def hold_sampler(edges: DataFrame, p: float, q: float, seed: int = 0, trials: int = 1, sure: bool = True) -> DataFrame:
    """(trial, est, held): one ordered task per trial, as each choice depends on the sample; global only."""

    def run(batches):
        state, current = None, None
        for batch in batches:
            done = []
            for trial, t, u, v in zip(*[batch.column(c).to_pylist() for c in ("trial", "t", "u", "v")]):
                if trial != current:
                    if state is not None:
                        done.append((current, state.est, state.held))
                    state, current = HoldSampler(p, q, sure), trial
                state.see(u, v, coin_value("h", seed, trial, t))
            if done:
                yield pa.RecordBatch.from_pylist([{"trial": a, "est": b, "held": c} for a, b, c in done], schema=out)
        if state is not None:
            yield pa.RecordBatch.from_pylist([{"trial": current, "est": state.est, "held": state.held}], schema=out)

    out = pa.schema([("trial", pa.int32()), ("est", pa.float64()), ("held", pa.int64())])
    rows = edges.select("t", "u", "v").withColumn("trial", F.explode(F.sequence(F.lit(0), F.lit(trials - 1))))
    return rows.repartition(trials, "trial").sortWithinPartitions("trial", "t").mapInArrow(run, "trial int, est double, held bigint")
