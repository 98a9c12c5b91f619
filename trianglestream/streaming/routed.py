"""The routed estimator over a live stream: one keyed state per worker.

The route is stateless: an edge goes to its one worker, or to all of them. A
worker's state holds its load, its reservoir and the sums it has not shipped.
Coins depend on seed, worker and rank only, so a replay from a checkpoint gives the
same sample. Eager mode emits what each batch found; lazy mode keeps sums and emits
totals, of which the latest counts.
"""

from __future__ import annotations

import pickle
from collections import Counter

import pandas as pd
from pyspark.sql import DataFrame, functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.kernels import Worker
from ..operators.mapping import GreedyColours, with_workers

OUT = "worker int, node bigint, hits bigint, num decimal(38,0), total boolean"


def route(edges: DataFrame, mapping, k: int, seed: int = 0) -> DataFrame:
    """(ts, u, v, worker, own) messages of a stream of (ts, u, v)."""
    both = edges if mapping == "given" else with_workers(edges, mapping, k, seed)
    to = F.when(F.col("fu") == F.col("fv"), F.array("fu")).otherwise(F.sequence(F.lit(0), F.lit(k - 1)))
    sent = both.select("ts", "u", "v", "fu", "fv", F.explode(to).alias("worker"))
    return sent.select("ts", "u", "v", "worker", ((F.col("worker") == F.col("fu")) | (F.col("worker") == F.col("fv"))).alias("own"))


def worker_step(budget: int, seed: int, lazy: bool):
    """Processor of one worker's messages in a batch, in order of (ts, u, v)."""

    def step(key, batches, state: GroupState):
        worker, hits, num = Worker(int(key[0]), budget, seed), Counter(), Counter()
        if state.exists:  # plain values only, so any executor can read them
            worker.load, worker.slots, worker.near, hits, num = pickle.loads(state.get[0])
        if not lazy:
            hits, num = Counter(), Counter()
        rows = pd.concat(list(batches)).sort_values(["ts", "u", "v"], kind="stable")
        for u, v, own in zip(rows["u"].tolist(), rows["v"].tolist(), rows["own"].tolist()):
            found = worker.count(u, v)
            if found:
                hit, n = worker.weight()
                for w in found:
                    for node in (-1, u, v, w):
                        hits[node] += hit
                        num[node] += n
            if own:
                worker.store(u, v)
        state.update((pickle.dumps((worker.load, worker.slots, worker.near, hits, num)),))
        if hits:
            nodes = list(hits)
            from decimal import Decimal

            yield pd.DataFrame({"worker": int(key[0]), "node": nodes, "hits": [hits[x] for x in nodes], "num": [Decimal(num[x]) for x in nodes], "total": lazy})

    return step


def estimate_stream(edges: DataFrame, k: int, budget: int, mapping="modulo", seed: int = 0, lazy: bool = False) -> DataFrame:
    """Streaming updates (worker, node, hits, num, total); node -1 is the whole graph. Write in append or update mode.

    Mappings: modulo, random, a node map or column function, or "given", where the stream has fu and fv; for the adaptive
    one see ``estimate_adaptive_stream``."""
    if isinstance(mapping, str) and mapping == "adaptive":
        raise ValueError("the adaptive mapping needs a master before the workers: use estimate_adaptive_stream")
    sent = route(edges, mapping, k, seed)
    return sent.groupBy("worker").applyInPandasWithState(worker_step(budget, seed, lazy), OUT, "state binary", "update", GroupStateTimeout.NoTimeout)


def settle(updates: DataFrame, budget: int) -> DataFrame:
    """(node, est) of collected updates: eager ones add up, of lazy totals the greatest per worker counts."""
    eager = updates.where("not total").groupBy("node").agg(F.sum("hits").alias("hits"), F.sum("num").alias("num"))
    last = updates.where("total").groupBy("worker", "node").agg(F.max("hits").alias("hits"), F.max("num").alias("num"))
    lazy = last.groupBy("node").agg(F.sum("hits").alias("hits"), F.sum("num").alias("num"))
    sums = eager.unionByName(lazy).groupBy("node").agg(F.sum("hits").alias("hits"), F.sum("num").alias("num"))
    return sums.select("node", (F.col("hits").cast("double") + F.col("num").cast("double") / F.lit(float(budget) * (budget - 1))).alias("est"))


def run_to_end(updates: DataFrame, path: str, checkpoint: str) -> DataFrame:
    """Process all that is there, append each batch's updates to ``path``, and read them back."""
    spark = updates.sparkSession

    def keep(batch: DataFrame, number: int) -> None:
        # One folder per batch, overwritten when a batch is replayed.
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    query = updates.writeStream.outputMode("update").foreachBatch(keep).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.option("basePath", path).parquet(path)


class AdaptiveMaster:
    """Load-aware colouring across micro-batches: a batch's new nodes are coloured before it is routed.

    For ``foreachBatch``. Only the (u, v) pairs of a batch pass the driver, in order, as the rule is sequential; the colours
    of their nodes go back as a table. Colours and loads are written beside the checkpoint after each batch, so a restart
    goes on where the last finished batch ended, and a replayed batch is coloured from the same state.
    """

    def __init__(self, k: int, theta: float = 0.2, path: str | None = None):
        self.k, self.theta, self.path, self.state = k, theta, path, GreedyColours(k, theta)

    def resume(self, spark, batch: int) -> None:
        """The state after the batch before ``batch``."""
        self.state = GreedyColours(self.k, self.theta)
        if batch > 0:
            for row in spark.read.schema("kind string, id bigint, n bigint").parquet(f"{self.path}/after={batch - 1}").toLocalIterator():
                if row["kind"] == "load":
                    self.state.loads[row["id"]] = row["n"]
                else:
                    self.state.colour[row["id"]] = row["n"]

    def save(self, spark, batch: int) -> None:
        rows = [("load", i, n) for i, n in enumerate(self.state.loads)] + [("node", x, w) for x, w in self.state.colour.items()]
        spark.createDataFrame(rows, "kind string, id bigint, n bigint").write.mode("overwrite").parquet(f"{self.path}/after={batch}")

    def colour_batch(self, batch: DataFrame) -> DataFrame:
        """``batch`` (ts, u, v) with fu, fv."""
        nodes = {}
        for r in batch.orderBy("ts", "u", "v").select("u", "v").toLocalIterator():
            cu, cv, _ = self.state.see(r["u"], r["v"])
            nodes[r["u"]], nodes[r["v"]] = cu, cv
        table = batch.sparkSession.createDataFrame(list(nodes.items()), "node bigint, worker int")
        return with_workers(batch, table, self.k).select("ts", "u", "v", "fu", "fv")


def coloured_files(edges: DataFrame, k: int, theta: float, path: str, checkpoint: str) -> str:
    """Run the adaptive master over a live stream; it writes routed edges (ts, u, v, fu, fv), one folder for each batch, from
    which a second stream can read. Returns that folder."""
    master = AdaptiveMaster(k, theta, f"{path}-state")

    def colour(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        master.resume(spark, number)
        master.colour_batch(batch).coalesce(1).write.mode("overwrite").parquet(f"{path}/batch={number:06d}")
        master.save(spark, number)

    edges.writeStream.foreachBatch(colour).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return path


def estimate_adaptive_stream(edges: DataFrame, k: int, budget: int, path: str, checkpoint: str, theta: float = 0.2, seed: int = 0, lazy: bool = False) -> DataFrame:
    """As ``estimate_stream`` with the adaptive mapping: a first query colours and routes batch by batch, a second one counts."""
    spark = edges.sparkSession
    routed = coloured_files(edges, k, theta, path, f"{checkpoint}-master")
    schema = "ts timestamp, u bigint, v bigint, fu int, fv int"
    ready = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(routed)
    return estimate_stream(ready, k, budget, "given", seed, lazy)


def stream_events(spark, sf_dir: str, path: str, files: int = 6) -> str:
    """Write the consecutive-users graph of events as (ts, u, v) files, one time range each; returns the folder."""
    return files_in_order(*timed_events(spark, sf_dir), path, files)


def timed_events(spark, sf_dir: str) -> tuple[DataFrame, int]:
    """The consecutive-users graph of events as (ts, u, v), its seconds dense from 1, and the last of them."""
    from ..sources.graphs import successive
    from ..sources.streams import clean, number_rows
    from ..sources.tables import pin, table

    events = table(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    first = clean(successive(events, ["event_type"]))
    numbered = number_rows(first, F.floor(F.col("arrival") / 4096), ["arrival", "u", "v"], "t")
    rows = pin(numbered, "numbered")
    return rows.select(F.timestamp_seconds(F.col("t")).alias("ts"), "u", "v"), rows.agg(F.max("t")).first()[0] or 0


def files_in_order(rows: DataFrame, last: int, path: str, files: int, after=None) -> str:
    """Write ``rows`` (ts, u, v) with seconds 1 to ``last`` one file after another. A file stream takes the oldest file first by
    the store's time of modification, which may be coarse or another machine's: a run in ``after``, called when a file is there,
    has only that file before it."""
    second = F.unix_timestamp("ts")
    for i in range(files):
        part = rows.where((second > last * i // files) & (second <= last * (i + 1) // files))
        part.repartition(1).sortWithinPartitions("ts").write.mode("append" if i else "overwrite").parquet(path)
        if after is not None:
            after()
    return path
