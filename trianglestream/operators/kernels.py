"""One-edge-at-a-time form of all policies, with the coins of the relational plan.

Used to check the plans, as the body of the streaming processor, and as the strategy
``kernel``, which enforces the storage limit: a task holds one worker's sample.
"""

from __future__ import annotations

from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..functions.hashing import coin_value
from .sampling import messages


class Worker:
    """A reservoir of at most ``budget`` edges with neighbour sets."""

    def __init__(self, number: int, budget: int, seed: int, trial: int = 0):
        self.number, self.budget, self.seed, self.trial = number, budget, seed, trial
        self.load, self.slots, self.near = 0, {}, {}

    def count(self, u: int, v: int) -> list[int]:
        """Common neighbours of both ends in the sample."""
        a, b = self.near.get(u, ()), self.near.get(v, ())
        return [w for w in (a if len(a) < len(b) else b) if w in a and w in b]

    def weight(self) -> tuple[int, int]:
        """(hit, numerator) of one discovery at the present load."""
        return (1, 0) if self.load <= self.budget else (0, self.load * (self.load - 1))

    def store(self, u: int, v: int) -> None:
        self.load += 1
        slot = self.load
        if self.load > self.budget:
            slot = int(coin_value(self.seed, self.trial, self.number, self.load) * self.load) + 1
            if slot > self.budget:
                return
            x, y = self.slots[slot]
            self.near[x].discard(y)
            self.near[y].discard(x)
        self.slots[slot] = (u, v)
        self.near.setdefault(u, set()).add(v)
        self.near.setdefault(v, set()).add(u)


def simulate(edges: list[tuple[int, int, int]], k: int, budget: int, colour=None, seed: int = 0, trial: int = 0) -> tuple[Counter, Counter]:
    """(hits, num) by node, None for the whole graph. ``colour`` None is the broadcast policy (divide by k yourself)."""
    workers = [Worker(i, budget, seed, trial) for i in range(k)]
    hits, num = Counter(), Counter()
    for _, u, v in sorted(edges):
        if colour is None:
            receive = store = range(k)
        else:
            cu, cv = colour(u), colour(v)
            store = {cu, cv}
            receive = [cu] if cu == cv else range(k)
        for i in receive:
            found = workers[i].count(u, v)
            if found:
                hit, n = workers[i].weight()
                for w in found:
                    for key in (None, u, v, w):
                        hits[key] += hit
                        num[key] += n
        for i in store:
            workers[i].store(u, v)
    return hits, num


def closures_by_kernel(edges: DataFrame, mapping, k: int, budget: int, seed: int = 0, trials: int = 1, map_seed: int = 0) -> DataFrame:
    """(trial, worker, u, v, apex, t, load_before) in one pass over the messages of each worker, in order of time.

    Cross edges are sent to all workers, as over a network, so the stream is shuffled up to k-fold; a task keeps at most
    ``budget`` edges of one worker and trial."""
    sent = messages(edges, mapping, k, map_seed).withColumn("trial", F.explode(F.sequence(F.lit(0), F.lit(trials - 1))))
    names = ["trial", "worker", "u", "v", "apex", "t", "load_before"]

    def run(batches):
        current, state = None, None
        for batch in batches:
            out = {n: [] for n in names}
            for trial, worker, t, u, v, own in zip(*[batch.column(c).to_pylist() for c in ("trial", "worker", "t", "u", "v", "assigned")]):
                if (trial, worker) != current:
                    current, state = (trial, worker), Worker(worker, budget, seed, trial)
                for apex in state.count(u, v):
                    for n, x in zip(names, (trial, worker, u, v, apex, t, state.load)):
                        out[n].append(x)
                if own:
                    state.store(u, v)
            kinds = [pa.int32(), pa.int32(), *[pa.int64()] * 5]
            yield pa.RecordBatch.from_arrays([pa.array(out[n], kind) for n, kind in zip(names, kinds)], names)

    ordered = sent.repartition(k * trials, "trial", "worker").sortWithinPartitions("trial", "worker", "t")
    return ordered.mapInArrow(run, "trial int, worker int, u bigint, v bigint, apex bigint, t bigint, load_before bigint")
