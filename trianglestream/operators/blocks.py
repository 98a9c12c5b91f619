"""Exact triangle counts of large graphs without shuffled wedges.

Nodes have p colours by hash, so an edge lies in the block of its two colours and a
triangle in the cell of its three. Distinct edges are written once, packed, by
block; the task of a cell reads its at most three blocks from the shared folder and
intersects neighbour lists in arrays, along the order of degrees. What moves is
each pair once; wedges exist only a few million at a time inside a task.
"""

from __future__ import annotations

import uuid
import zlib
from functools import reduce
from itertools import combinations, combinations_with_replacement

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..sources.tables import pin, shared_root

#: Pairs packed at once, edges of a cell aimed at, candidates looked up at once (few, so that arrays stay in the cache), cells to
#: a plan, bits of the filter.
ROWS, EDGES, CANDIDATES, CELLS, BITS = 1 << 20, 1 << 23, 1 << 18, 64, 20
_ODD = np.uint64(0x9E3779B97F4A7C15)


def _hash(x: np.ndarray, bits: int) -> np.ndarray:
    return ((x.astype(np.uint64) * _ODD) >> np.uint64(64 - bits)).astype(np.int64)


def _colour(x: np.ndarray, p: int) -> np.ndarray:
    return _hash(x ^ (x >> 29), 31) % p


def pack(u: np.ndarray, v: np.ndarray) -> bytes:
    """Bytes of distinct pairs in order of (u, v): differences, byte plane by byte plane, deflated."""
    du, dv = np.diff(u, prepend=0), np.diff(v, prepend=0)
    head = np.append(True, du[1:] != 0)
    dv[head] = (v - u)[head]
    return zlib.compress(np.ascontiguousarray(np.concatenate([du, dv]).view(np.uint8).reshape(-1, 8).T).tobytes(), 1)


def unpack(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    both = np.ascontiguousarray(np.frombuffer(zlib.decompress(data), np.uint8).reshape(8, -1).T).view(np.int64).ravel()
    du, dv = both[: len(both) // 2], both[len(both) // 2 :]
    u, run = np.cumsum(du), np.cumsum(dv)
    head = np.flatnonzero(np.append(True, du[1:] != 0))
    base = np.repeat(run[head] - dv[head], np.diff(np.append(head, len(du))))
    return u, run - base + u


def _parts(by: np.ndarray, u: np.ndarray, v: np.ndarray):
    """(key, bytes) of the distinct pairs of each key, and their number."""
    at = np.lexsort((v, u, by))
    by, u, v = by[at], u[at], v[at]
    new = np.append(True, (by[1:] != by[:-1]) | (u[1:] != u[:-1]) | (v[1:] != v[:-1]))
    by, u, v = by[new], u[new], v[new]
    bounds = np.append(np.flatnonzero(np.append(True, by[1:] != by[:-1])), len(by))
    for a, b in zip(bounds, bounds[1:]):
        yield int(by[a]), int(b - a), pack(u[a:b], v[a:b])


def _rows(found) -> pa.RecordBatch:
    keys, sizes, data = zip(*found)
    return pa.RecordBatch.from_arrays([pa.array(keys, pa.int32()), pa.array(sizes, pa.int64()), pa.array(data, pa.binary())], ["part", "n", "data"])


def _packer(parts: int):
    """Pairs (u, v) to packs by a hash of the lesser end; loops and nulls go."""

    def flush(held):
        u, v = (np.concatenate(x) for x in zip(*held))
        u, v = np.minimum(u, v), np.maximum(u, v)
        u, v = u[u < v], v[u < v]
        if len(u):
            yield _rows(_parts(_hash(u, 31) % parts, u, v))

    def run(batches):
        held, n = [], 0
        for batch in batches:
            batch = batch.drop_null()
            if batch.num_rows:
                held.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
                n += batch.num_rows
            if n >= ROWS:
                yield from flush(held)
                held, n = [], 0
        if held:
            yield from flush(held)

    return run


def _merger(batches):
    """All packs of a partition as packs of distinct pairs."""
    held = [unpack(x) for batch in batches for x in batch.column("data").to_pylist()]
    if held:
        u, v = (np.concatenate(x) for x in zip(*held))
        yield _rows(_parts(np.zeros(len(u), np.int32), u, v))


def _splitter(p: int):
    def run(batches):
        for batch in batches:
            for data in batch.column("data").to_pylist():
                u, v = unpack(data)
                cu, cv = _colour(u, p), _colour(v, p)
                yield _rows(_parts(np.minimum(cu, cv) * p + np.maximum(cu, cv), u, v))

    return run


def cell_hits(u: np.ndarray, v: np.ndarray, cell: tuple[int, ...], p: int):
    """Triangles of a cell among its distinct edges, as arrays of their three nodes, some at a time."""
    ids = np.unique(np.concatenate([np.unique(u), np.unique(v)]))
    n = len(ids)
    x, y = np.searchsorted(ids, u), np.searchsorted(ids, v)
    rank = np.empty(n, np.int64)
    order = np.argsort(np.bincount(x, minlength=n) + np.bincount(y, minlength=n), kind="stable")
    rank[order] = np.arange(n)
    x, y = rank[x], rank[y]
    ids = ids[order]
    colours = sorted(set(cell))
    slot = np.searchsorted(colours, _colour(ids, p))
    third = np.full((3, 3), -1)  # the colour that completes two of them
    for i, a in enumerate(colours):
        for j, b in enumerate(colours):
            rest = list(cell)
            if a in rest:
                rest.remove(a)
                if b in rest:
                    rest.remove(b)
                    third[i, j] = colours.index(rest[0])
    a, b = np.minimum(x, y), np.maximum(x, y)
    key = np.sort((a * 3 + slot[b]) * n + b)
    row, b = np.divmod(key, n)
    a = row // 3
    start = np.append(0, np.cumsum(np.bincount(row, minlength=3 * n)))
    want = third[slot[a], slot[b]]
    near = b * 3 + np.maximum(want, 0)
    size = np.where(want >= 0, start[near + 1] - start[near], 0)
    upto = np.cumsum(size)
    filtered, at = np.zeros(1 << BITS, bool), 0
    while at < len(key):
        to = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + CANDIDATES, side="right")))
        many = size[at:to]
        total = int(many.sum())
        if total:
            edge = np.repeat(np.arange(at, to), many)
            w = b[np.arange(total) + np.repeat(start[near[at:to]] - (np.cumsum(many) - many), many)]
            asked = ((a[at:to] * 3 + want[at:to]) * n)[edge - at] + w
            low, high = start[3 * a[at]], start[3 * (a[to - 1] + 1)]
            marks = _hash(key[low:high], BITS)
            filtered[marks] = True
            left = np.flatnonzero(filtered[_hash(asked, BITS)])
            filtered[marks] = False
            place = np.searchsorted(key[low:high], asked[left])
            left = left[key[low:high][np.minimum(place, high - low - 1)] == asked[left]]
            if len(left):
                yield ids, a[edge[left]], b[edge[left]], w[left]
        at = to


def _counter(cell, p: int, local: bool):
    def run(batches):
        held = [unpack(x) for batch in batches for x in batch.column("data").to_pylist()]
        total, ids = 0, np.zeros(0, np.int64)
        if held:
            u, v = (np.concatenate(x) for x in zip(*held))
            del held
            each = None
            for ids, *ends in cell_hits(u, v, cell, p):
                total += len(ends[0])
                if local:
                    each = sum((np.bincount(e, minlength=len(ids)) for e in ends), 0 if each is None else each)
        if not local:
            yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], ["n"])
        elif total:
            yield pa.RecordBatch.from_arrays([pa.array(ids[each > 0]), pa.array(each[each > 0].astype(np.int64))], ["node", "n"])

    return run


def counted(pairs: DataFrame, local: bool = False, colours: int | None = None) -> DataFrame:
    """(n), or (node, n) of nodes with a triangle, of the graph of ``pairs`` (u, v). Loops, repeats and nulls do not count.

    The number of colours follows from the counted edges, so that a cell has about ``EDGES`` of them."""
    spark, form = pairs.sparkSession, "part int, n bigint, data binary"
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    packs = pairs.select(F.col("u").cast("bigint"), F.col("v").cast("bigint")).mapInArrow(_packer(parts), form)
    packs = pin(packs.repartition(parts, "part").mapInArrow(_merger, form), "edges")
    size = packs.agg(F.sum("n")).first()[0] or 0
    p = colours or max(3, int(np.ceil(np.sqrt(6 * size / EDGES))))
    root = f"{shared_root(spark)}/blocks-{uuid.uuid4().hex}"
    packs.mapInArrow(_splitter(p), form).write.partitionBy("part").parquet(root)
    there = {r[0] for r in spark.read.schema(form).parquet(root).select("part").distinct().collect()} if size else set()  # p² at most
    shape, found = ("node bigint, n bigint" if local else "n bigint"), []
    cells = [(c, sorted({x * p + y for x, y in combinations(c, 2)} & there)) for c in combinations_with_replacement(range(p), 3)]
    cells = [(c, blocks) for c, blocks in cells if blocks]
    for i in range(0, len(cells), CELLS):
        tasks = [
            spark.read.schema("n bigint, data binary").parquet(*[f"{root}/part={x}" for x in blocks]).select("data").coalesce(1).mapInArrow(_counter(c, p, local), shape)
            for c, blocks in cells[i : i + CELLS]
        ]
        rows = reduce(lambda one, two: one.unionByName(two), tasks)
        found.append(pin(rows.groupBy("node").agg(F.sum("n").alias("n")) if local else rows, "counts"))
    every = reduce(lambda one, two: one.unionByName(two), found) if found else spark.createDataFrame([], shape)
    if local:
        return every.groupBy("node").agg(F.sum("n").alias("n"))
    return every.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"))
