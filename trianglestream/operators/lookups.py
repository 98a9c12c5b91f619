"""True triangles and their look-ups in many samples, in arrays.

``listed`` deals packed edges by cells of three colours and lists triangles in the
task of a cell, so no wedge is shuffled. ``held_sums`` gives a task all triangles one
worker counts: what a sample holds follows from coins of ranks alone, so a task draws
them for its trials, looks both older edges up and ships its sums once.
``closures_at_workers`` brings a small stream to the tasks that hold the samples.
"""

from __future__ import annotations

from decimal import Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..functions.coins import Coins
from .blocks import _colour, _hash, cell_hits

#: Edges of a cell aimed at; rows packed at once; rows of a batch of found triangles, and wedges at once; bits of the filter.
EDGES, ROWS, FOUND, MARKS = 1 << 21, 1 << 20, 1 << 17, 24
#: A rank after all others.
NEVER = np.iinfo(np.int64).max


def _packed(*columns: np.ndarray) -> bytes:
    """Columns of whole numbers, in order of the first: its differences, then byte plane by byte plane."""
    at = np.argsort(columns[0], kind="stable")
    rows = [np.diff(columns[0][at], prepend=0), *[c[at] for c in columns[1:]]]
    planes = np.ascontiguousarray(np.concatenate(rows).astype("<i8").view(np.uint8).reshape(-1, 8).T)
    return pa.compress(planes.tobytes(), codec="zstd", asbytes=True)


def _unpacked(data: bytes, n: int, columns: int) -> list[np.ndarray]:
    planes = np.frombuffer(pa.decompress(data, 8 * n * columns, codec="zstd", asbytes=True), np.uint8)
    rows = np.ascontiguousarray(planes.reshape(8, -1).T).view("<i8").reshape(columns, n)
    return [np.cumsum(rows[0]), *rows[1:]]


_PACKS = pa.schema([("part", pa.int32()), ("kind", pa.int32()), ("n", pa.int64()), ("data", pa.binary())])
_PACKS_DDL = "part int, kind int, n bigint, data binary"


def _in_packs(rows_of):
    """Kernel from batches to packs, some ``ROWS`` rows at once. ``rows_of`` gives (part, kind, arrays) of columns."""

    def run(batches):
        held, n = [], 0

        def flush():
            table = pa.Table.from_batches(held)
            found = [(part, kind, len(arrays[0]), _packed(*arrays)) for part, kind, arrays in rows_of(*[c.to_numpy() for c in table.columns]) if len(arrays[0])]
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(x, kind.type) for x, kind in zip(zip(*found), _PACKS)], schema=_PACKS)

        for batch in batches:
            if batch.num_rows:
                held.append(batch)
                n += batch.num_rows
            if n >= ROWS:
                yield from flush()
                held, n = [], 0
        if n:
            yield from flush()

    return run


def _whole(batches, columns):
    """(part, {kind: list of arrays}) of packs that come part by part."""
    part, held = None, {}
    for batch in batches:
        for p, kind, n, data in zip(*[batch.column(c).to_pylist() for c in ("part", "kind", "n", "data")]):
            if part is not None and p != part:
                yield part, held
                held = {}
            part = p
            held.setdefault(kind, []).append(_unpacked(data, n, columns[kind]))
    if part is not None:
        yield part, held


def _cells(p: int) -> dict[tuple[int, ...], int]:
    return {c: i for i, c in enumerate((a, b, c) for a in range(p) for b in range(a, p) for c in range(b, p))}


def _to_cells(p: int):
    """Edges (u, v, t) to the p cells of their two colours and any third."""
    number = _cells(p)

    def rows_of(u, v, t):
        low, high = _colour(u, p), _colour(v, p)
        low, high = np.minimum(low, high), np.maximum(low, high)
        for a in range(p):
            for b in range(a, p):
                own = (low == a) & (high == b)
                for cell in sorted({number[tuple(sorted((a, b, x)))] for x in range(p)}) if own.any() else ():
                    yield cell, 0, (u[own], v[own], t[own])

    return rows_of


def _lister(p: int):
    cells = {i: c for c, i in _cells(p).items()}
    names = ["u", "v", "apex", "t", "t1", "t2"]

    def run(batches):
        for part, held in _whole(batches, {0: 3}):
            u, v, t = (np.concatenate(x) for x in zip(*held[0]))
            at = np.lexsort((v, u))
            u, v, t = u[at], v[at], t[at]
            ids = np.unique(np.concatenate([np.unique(u), np.unique(v)]))
            keys = np.searchsorted(ids, u) * len(ids) + np.searchsorted(ids, v)
            for mine, *ends in cell_hits(u, v, cells[part], p):
                for low in range(0, len(ends[0]), FOUND):
                    x, y, z = np.sort(np.stack([mine[e[low : low + FOUND]] for e in ends]), axis=0)
                    i, j, k = (np.searchsorted(ids, n) for n in (x, y, z))
                    times = np.stack([t[np.searchsorted(keys, one * len(ids) + two)] for one, two in ((i, j), (i, k), (j, k))])
                    last = np.argmax(times, axis=0)  # of xy, xz, yz
                    times.sort(axis=0)
                    columns = [np.where(last == 2, y, x), np.where(last == 0, y, z), np.choose(last, [z, y, x]), times[2], times[0], times[1]]
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names)

    return run


def listed(edges: DataFrame) -> DataFrame:
    """(u, v, apex, t, t1, t2) of an edge stream: the same rows as ``exact.triangles``. Edges move once for each colour, packed;
    the number of colours follows from the counted edges, so that a cell has about ``EDGES`` of them."""
    p = max(3, int(np.ceil(np.sqrt(6 * edges.count() / EDGES))))
    packs = edges.select("u", "v", "t").mapInArrow(_in_packs(_to_cells(p)), _PACKS_DDL)
    return packs.repartitionById(len(_cells(p)), "part").sortWithinPartitions("part").mapInArrow(_lister(p), "u bigint, v bigint, apex bigint, t bigint, t1 bigint, t2 bigint")


class _Sample:
    """What the sample of one worker and trial holds, for some budgets, by ranks."""

    def __init__(self, coins: Coins, prefix: str, n: int, budgets: list[int]):
        self.n, self.out = n, np.zeros(n + 1, np.int64)
        rank, slot = coins.slots_within(prefix, min(budgets) + 1, n + 1, max(budgets))
        at = np.argsort(slot, kind="stable")
        self.rank, self.slot = rank[at], slot[at]

    def left(self, budget: int) -> np.ndarray:
        """By rank, the rank of the edge that takes its place: NEVER while it stays, zero if it was not taken in."""
        to = np.searchsorted(self.slot, budget, side="right")
        later = np.flatnonzero(self.rank[:to] > budget)
        rank, slot = self.rank[later], self.slot[later]
        out = self.out
        out.fill(0)
        out[1 : budget + 1] = NEVER
        if len(rank):
            first = np.append(True, slot[1:] != slot[:-1])
            following = np.append(rank[1:], NEVER)
            following[np.append(first[1:], True)] = NEVER
            out[rank] = following
            out[slot[first]] = rank[first]
        return out


def _sum_of_pairs(load: np.ndarray) -> int:
    """Sum of l(l - 1), exact beyond 64 bits."""
    x = load * (load - 1)
    return (int((x >> 31).sum()) << 31) + int((x & 0x7FFFFFFF).sum())


_SUMS = pa.schema([("budget", pa.int64()), ("trial", pa.int32()), ("worker", pa.int32()), ("hit", pa.int64()), ("num", pa.decimal128(38, 0))])
_SUMS_DDL = "budget bigint, trial int, worker int, hit bigint, num decimal(38,0)"


def _sums(triangles, n: int, runs, budgets: list[int], seed: int, coins: Coins):
    """Rows of ``held_sums`` for (worker, trial) of ``runs``; ``triangles`` are arrays (load, rank1, rank2), some at a time. One
    that closes at a load within the budget is held for sure, as nothing has left the sample by then."""
    sure = {b: sum(int((load <= b).sum()) for load, _, _ in triangles) for b in budgets}
    drawn = [b for b in budgets if b < n]
    found = []
    for worker, trial in runs:
        sample = _Sample(coins, f"{seed}:{trial}:{worker}:", n, drawn) if drawn else None
        for b in budgets:
            num = 0
            if b < n:
                left = sample.left(b)
                for load, one, two in triangles:
                    at = np.flatnonzero(left[one] > load)
                    at = at[left[two[at]] > load[at]]
                    late = load[at].astype(np.int64)
                    num += _sum_of_pairs(late[late > b])
            found.append((b, trial, worker, sure[b], Decimal(num)))
    if found:
        yield pa.RecordBatch.from_arrays([pa.array(x, field.type) for x, field in zip(zip(*found), _SUMS)], schema=_SUMS)


def _small(x: np.ndarray) -> np.ndarray:
    return x.astype(np.int32) if len(x) and x.max() < 1 << 31 else x


def _by_worker(worker, kind, t, t1, t2):
    for w in np.unique(worker):
        own = worker == w
        yield int(w), 0, (t[own & (kind == 0)],)
        mine = own & (kind == 1)
        yield int(w), 1, (t1[mine], t2[mine], t[mine])


def held_sums(placed: DataFrame, assigned: DataFrame, k: int, budgets: list[int], seed: int, trials: int) -> DataFrame:
    """(budget, trial, worker, hit, num): sums of what ``weigh`` gives for the discoveries of each worker, by portable coins.
    ``placed`` has (worker, t, t1, t2) of triangles, ``assigned`` (worker, t) of the edges a worker considers."""
    budgets = sorted(set(budgets))

    def run(batches):
        coins = Coins()
        for worker, held in _whole(batches, {0: 1, 1: 3}):
            times = np.sort(np.concatenate([x for x, in held[0]]))
            triangles = [(_small(np.searchsorted(times, t)), _small(np.searchsorted(times, t1) + 1), _small(np.searchsorted(times, t2) + 1)) for t1, t2, t in held.pop(1, [])]
            if triangles:
                yield from _sums(triangles, len(times), [(worker, i) for i in range(trials)], budgets, seed, coins)

    zero = F.lit(0).cast("bigint")
    own = assigned.select("worker", F.lit(0).alias("kind"), "t", zero.alias("t1"), zero.alias("t2"))
    rows = own.unionByName(placed.select("worker", F.lit(1).alias("kind"), "t", "t1", "t2"))
    packs = rows.mapInArrow(_in_packs(_by_worker), _PACKS_DDL)
    return packs.repartitionById(k, "part").sortWithinPartitions("part").mapInArrow(run, _SUMS_DDL)


def held_sums_everywhere(found: DataFrame, n: int, k: int, budgets: list[int], seed: int, trials: int) -> DataFrame:
    """``held_sums`` where each of k workers considers all n edges, so that ranks are times and every worker counts every triangle.
    Packed triangles go to as many tasks as run side by side, each of which has its share of the workers and trials."""
    budgets = sorted(set(budgets))
    tasks = max(1, min(k * trials, found.sparkSession.sparkContext.defaultParallelism))

    def run(batches):
        coins = Coins()
        for task, held in _whole(batches, {0: 3}):
            triangles = [(_small(t - 1), _small(t1), _small(t2)) for t1, t2, t in held.pop(0)]
            yield from _sums(triangles, n, [(i % k, i // k) for i in range(task, k * trials, tasks)], budgets, seed, coins)

    packs = found.select("t1", "t2", "t").mapInArrow(_in_packs(lambda t1, t2, t: [(0, 0, (t1, t2, t))]), _PACKS_DDL)
    dealt = packs.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))))
    return dealt.repartitionById(tasks, "part").sortWithinPartitions("part").mapInArrow(run, _SUMS_DDL)


def _wedges_met(stream, worker, u, v, t_in, t_out):
    """Closures (u, v, apex, t) of one sample: its wedges, some at a time, that meet an edge of the stream while both sides stay.
    ``stream``: (ids, sorted keys, times, homes, marks)."""
    ids, keys, times, homes, marks = stream
    x, y = np.searchsorted(ids, u), np.searchsorted(ids, v)
    apex, far = np.concatenate([x, y]), np.concatenate([y, x])
    at = np.lexsort((far, apex))
    apex, far, begin, end = apex[at], far[at], np.tile(t_in, 2)[at], np.tile(t_out, 2)[at]
    many = np.searchsorted(apex, apex, side="right") - np.arange(len(apex)) - 1  # later ones at the same apex are of greater far ends
    upto, low = np.cumsum(many), 0
    while low < len(apex):
        high = max(low + 1, int(np.searchsorted(upto, (upto[low - 1] if low else 0) + FOUND, side="right")))
        own = many[low:high]
        one = np.repeat(np.arange(low, high), own)
        two = one + 1 + np.arange(len(one)) - np.repeat(np.cumsum(own) - own, own)
        asked = far[one] * len(ids) + far[two]
        left = np.flatnonzero(marks[_hash(asked, MARKS)])
        one, two, asked = one[left], two[left], asked[left]
        place = np.minimum(np.searchsorted(keys, asked), len(keys) - 1)
        t, home = times[place], homes[place]
        met = (keys[place] == asked) & (np.maximum(begin[one], begin[two]) < t) & (t <= np.minimum(end[one], end[two])) & ((home < 0) | (home == worker))
        if met.any():
            yield ids[far[one[met]]], ids[far[two[met]]], ids[apex[one[met]]], t[met]
        low = high


def closures_at_workers(stream: DataFrame, residency: DataFrame) -> DataFrame:
    """(trial, worker, u, v, apex, t) of residency (trial, worker, u, v, t_in, t_out) and a small stream, which has fu and fv if
    nodes are mapped. Packed, the stream goes to each task, which holds some of the workers; neither the driver holds it nor are
    wedges shuffled."""
    tasks = 2 * stream.sparkSession.sparkContext.defaultParallelism
    home = F.when(F.col("fu") == F.col("fv"), F.col("fu")).otherwise(-1) if "fu" in stream.columns else F.lit(-1)
    names, kinds = ["trial", "worker", "u", "v", "apex", "t"], [pa.int32(), pa.int32(), *[pa.int64()] * 4]

    def of_residency(trial, worker, u, v, t_in, t_out):
        run = (trial.astype(np.int64) << 32) + worker
        part = (trial.astype(np.int64) * 7 + worker) % tasks
        for p in np.unique(part):
            own = part == p
            yield int(p), 1, (run[own], u[own], v[own], t_in[own], t_out[own])

    def run(batches):
        for _, held in _whole(batches, {0: 4, 1: 5}):
            if 0 not in held or 1 not in held:
                continue
            u, v, t, homes = (np.concatenate(c) for c in zip(*held.pop(0)))
            ids = np.unique(np.concatenate([np.unique(u), np.unique(v)]))
            keys = np.searchsorted(ids, u) * len(ids) + np.searchsorted(ids, v)
            at = np.argsort(keys)
            marks = np.zeros(1 << MARKS, bool)
            marks[_hash(keys, MARKS)] = True
            whole = ids, keys[at], t[at], homes[at], marks
            runs, *sides = (np.concatenate(c) for c in zip(*held.pop(1)))
            order = np.argsort(runs, kind="stable")
            runs, sides = runs[order], [c[order] for c in sides]
            sides[3] = np.where(sides[3] < 0, NEVER, sides[3])
            bounds = np.append(np.flatnonzero(np.append(True, runs[1:] != runs[:-1])), len(runs))
            for a, b in zip(bounds, bounds[1:]):
                trial, worker = int(runs[a] >> 32), int(runs[a] & 0xFFFFFFFF)
                for found in _wedges_met(whole, worker, *[c[a:b] for c in sides]):
                    same = [np.full(len(found[0]), x) for x in (trial, worker)]
                    yield pa.RecordBatch.from_arrays([pa.array(c, kind) for c, kind in zip([*same, *found], kinds)], names)

    edges = stream.select("u", "v", "t", home.cast("bigint").alias("home")).mapInArrow(_in_packs(lambda u, v, t, h: [(0, 0, (u, v, t, h))]), _PACKS_DDL)
    edges = edges.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))))
    stays = residency.select("trial", "worker", "u", "v", "t_in", F.coalesce("t_out", F.lit(-1)).cast("bigint").alias("t_out")).mapInArrow(_in_packs(of_residency), _PACKS_DDL)
    dealt = edges.unionByName(stays).repartitionById(tasks, "part").sortWithinPartitions("part")
    return dealt.mapInArrow(run, "trial int, worker int, u bigint, v bigint, apex bigint, t bigint")
