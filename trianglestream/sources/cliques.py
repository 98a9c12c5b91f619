"""Edge streams of graphs whose groups are cliques, in the random order, without shuffled edges.

The order is by md5 of an edge, so that every edge must be hashed and placed; a
clique of n nodes has n(n-1)/2 edges of n ids. Ids go in blocks, a task lists and
hashes the edges of two blocks in arrays, and what moves to the task of a range of
the order is which of the cell's edges it gets: about a byte an edge, beside the two
blocks. There they are listed and hashed again, and sorted.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F
from pyspark.sql.types import BinaryType, IntegerType, LongType, StructField, StructType

from ..operators.blocks import pack, unpack
from .streams import clean

#: Ids of a block, edges of a range of the order aimed at, edges to a range from which a cell is coded by itself, edges of small
#: cells gathered, edges hashed at once (few, so that arrays stay in the cache), rows of a batch that goes back.
SIDE, EDGES, LEAST, ROWS, CHUNK, BATCH = 2048, 1 << 22, 64, 1 << 20, 1 << 14, 1 << 16
_TURNS = [(7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)]
_SHIFTS = [[(np.array(t, np.uint32), np.array(32 - t, np.uint32)) for t in row] for row in _TURNS]
_SINES = [int(abs(np.sin(i + 1.0)) * 2**32) for i in range(64)]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)
_POWERS = np.array([10**i for i in range(20)], np.uint64)
#: us, vs: ids of the two blocks of a cell, null where ``data`` holds packed pairs. No column is null otherwise, so that a join by
#: part filters nothing and both readers share one exchange.
FORM = StructType([StructField("part", IntegerType(), False), StructField("n", LongType(), False), StructField("us", BinaryType()), StructField("vs", BinaryType()), StructField("data", BinaryType(), False)])


def _word(i: int) -> int:
    """Word of the text that step i takes."""
    return (i, 5 * i + 1, 3 * i + 5, 7 * i)[i // 16] % 16


class Hashes:
    """md5 of ``seed`` + u + ',' + v for many pairs of some ids, in arrays."""

    def __init__(self, ids: np.ndarray, seed: str = "s"):
        if len(seed) != 1:
            raise ValueError("the seed of an order is one letter")
        n, below = len(ids), ids < 0
        size = np.abs(ids).view(np.uint64)  # the least integer is its own absolute value, and right without a sign
        self.length = np.searchsorted(_POWERS[1:], size, side="right") + 1 + below
        text = np.zeros((n, 20), np.uint8)
        for l in np.unique(self.length):  # noqa: E741
            at = np.flatnonzero(self.length == l)
            for j in range(l):
                text[at, j] = size[at] // _POWERS[l - 1 - j] % np.uint64(10) + np.uint64(ord("0"))
        text[below, 0] = ord("-")
        first = np.zeros((n, 24), np.uint8)
        first[:, 0], first[:, 1:21] = ord(seed), text
        first[np.arange(n), 1 + self.length] = ord(",")
        self.first, self.second = self._words(first), []
        for s in range(4):  # by the place of v's first digit in its word
            second = np.zeros((n, 24), np.uint8)
            second[:, s : s + 20] = text
            second[np.arange(n), s + self.length] = 0x80
            self.second.append(self._words(second))
        self.length = self.length.astype(np.uint16)
        self.buffers = [np.empty(CHUNK, np.uint32) for _ in range(5)]

    @staticmethod
    def _words(text: np.ndarray) -> np.ndarray:
        return np.ascontiguousarray(text.view("<u4").T)

    def leading(self, i: np.ndarray, j: np.ndarray, words: int) -> np.ndarray:
        """The first 32 or, with two words, 64 bits of the hashes of (ids[i], ids[j]), as numbers that sort as the text does."""
        out = np.empty(len(i), np.uint64 if words == 2 else np.uint32)
        kind = self.length[i] * np.uint16(32) + self.length[j]
        kinds = np.flatnonzero(np.bincount(kind, minlength=1))
        at = None if len(kinds) == 1 else np.argsort(kind, kind="stable")
        bounds = np.append(0, np.cumsum(np.bincount(kind, minlength=1)[kinds]))
        for k, low, high in zip(kinds.tolist(), bounds.tolist(), bounds[1:].tolist()):
            for a in range(low, high, CHUNK):
                here = slice(a, min(a + CHUNK, high)) if at is None else at[a : min(a + CHUNK, high)]
                out[here] = self._hashed(i[here], j[here], k // 32, k % 32, words)
        return out

    def _hashed(self, i, j, lu: int, lv: int, words: int) -> np.ndarray:
        begin, length = lu + 2, lu + 2 + lv
        text = [0] * 16
        second = self.second[begin % 4]
        for k in range(length // 4 + 1):
            one = self.first[k].take(i) if 4 * k < begin else None
            two = second[k - begin // 4].take(j) if k >= begin // 4 else None
            text[k] = two if one is None else one if two is None else np.bitwise_or(one, two, one)
        text[14] = 8 * length
        a, b, c, d, x = (buffer[: len(i)] for buffer in self.buffers)
        for buffer, value in zip((a, b, c, d), _START):
            buffer.fill(value)
        added = np.zeros((), np.uint32)
        for step in range(64 if words == 2 else 61):
            if step < 16:
                np.bitwise_xor(c, d, x)
                np.bitwise_and(x, b, x)
                np.bitwise_xor(x, d, x)
            elif step < 32:
                np.bitwise_xor(b, c, x)
                np.bitwise_and(x, d, x)
                np.bitwise_xor(x, c, x)
            elif step < 48:
                np.bitwise_xor(b, c, x)
                np.bitwise_xor(x, d, x)
            else:
                np.invert(d, x)
                np.bitwise_or(x, b, x)
                np.bitwise_xor(x, c, x)
            np.add(a, x, a)
            word, (left, right) = text[_word(step)], _SHIFTS[step // 16][step % 4]
            if isinstance(word, int):
                added[...] = (word + _SINES[step]) & 0xFFFFFFFF
            else:
                np.add(a, word, a)
                added[...] = _SINES[step]
            np.add(a, added, a)
            np.left_shift(a, left, x)
            np.right_shift(a, right, a)
            np.bitwise_or(a, x, a)
            np.add(a, b, a)
            a, b, c, d = d, a, b, c
        if words == 1:  # the newest word after step 60 ends as the first
            return (b + np.uint32(_START[0])).byteswap()
        return (a + np.uint32(_START[0])).byteswap().astype(np.uint64) << np.uint64(32) | (b + np.uint32(_START[1])).byteswap()


def _part(lead: np.ndarray, parts: int) -> np.ndarray:
    """Range of the order of a hash by its first 32 bits."""
    return (lead.astype(np.uint64) * np.uint64(parts) >> np.uint64(32)).astype(np.uint16)


def pack_ids(ids: np.ndarray) -> bytes:
    """Ascending ids as bytes: the first, and differences of least width."""
    gaps = np.diff(ids.view(np.uint64))
    width = next(w for w in (1, 2, 4, 8) if not len(gaps) or int(gaps.max()) < 1 << 8 * w)
    return bytes([width]) + ids[:1].tobytes() + gaps.astype(f"u{width}").tobytes()


def unpack_ids(data: bytes) -> np.ndarray:
    gaps = np.frombuffer(data, f"u{data[0]}", offset=9).astype(np.uint64)
    return np.cumsum(np.append(np.frombuffer(data, np.uint64, 1, offset=1), gaps), dtype=np.uint64).view(np.int64)


def pack_places(places: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, bounds of bytes) of ascending places, below 2³², of each stretch: differences, where a byte of 255 adds to the next."""
    places = places.astype(np.uint32)
    gaps = np.diff(places, prepend=np.uint32(0))
    begins = bounds[:-1][bounds[:-1] < bounds[1:]]
    gaps[begins] = places[begins]
    more = gaps // np.uint32(255)
    ends = np.cumsum(more + np.uint32(1), dtype=np.int64)
    out = np.full(int(ends[-1]) if len(ends) else 0, 255, np.uint8)
    out[ends - 1] = gaps - np.uint32(255) * more
    return out, np.append(0, ends)[bounds]


def unpack_places(data: bytes) -> np.ndarray:
    data = np.frombuffer(data, np.uint8)
    return np.cumsum(data, dtype=np.int64)[data != 255]


def _starts(us: np.ndarray, vs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of a cell's pairs u < v, listed by u and v: each u's first v, and the place of its first pair with the number of all."""
    first = np.searchsorted(vs, us, side="right")
    return first, np.append(0, np.cumsum(len(vs) - first))


def _rows(part, n, us, vs, data) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), pa.array(n, pa.int64()), pa.array(us, pa.binary()), pa.array(vs, pa.binary()), pa.array(data, pa.binary())], schema=SHAPE)


SHAPE = pa.schema([pa.field("part", pa.int32(), False), pa.field("n", pa.int64(), False), pa.field("us", pa.binary()), pa.field("vs", pa.binary()), pa.field("data", pa.binary(), False)])


def _packed(u: np.ndarray, v: np.ndarray, parts: int):
    """Rows of distinct pairs u < v, whatever their groups."""
    ids, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    part = _part(Hashes(ids).leading(at[: len(u)], at[len(u) :], 1), parts)
    order = np.lexsort((v, u, part))
    part, u, v = part[order], u[order], v[order]
    bounds = np.append(np.flatnonzero(np.append(True, part[1:] != part[:-1])), len(part))
    stretches = list(zip(bounds.tolist(), bounds[1:].tolist()))
    yield _rows(part[bounds[:-1]], np.diff(bounds), [None] * len(stretches), [None] * len(stretches), [pack(u[a:b], v[a:b]) for a, b in stretches])


def _pooled(parts: int):
    """Pairs (u, v) in arrays to rows, some at a time."""
    held, n = [], 0

    def flush():
        nonlocal held, n
        if n:
            yield from _packed(*(np.concatenate(x) for x in zip(*held)), parts)
        held, n = [], 0

    def put(u, v):
        nonlocal n
        if len(u):
            held.append((u, v))
            n += len(u)
        if n >= ROWS:
            yield from flush()

    return put, flush


def _pair_packer(parts: int):
    """Kernel: distinct (u, v) to rows."""

    def run(batches):
        put, flush = _pooled(parts)
        for batch in batches:
            yield from put(batch.column(0).to_numpy(), batch.column(1).to_numpy())
        yield from flush()

    return run


def _cell_packer(parts: int):
    """Kernel: cells (us, vs), ascending, whose edges are all u < v, to rows. Small cells are gathered."""

    def run(batches):
        put, flush = _pooled(parts)
        for batch in batches:
            for k in range(batch.num_rows):
                us, vs = (batch.column(c)[k].values.to_numpy() for c in (0, 1))
                first, start = _starts(us, vs)
                size = int(start[-1])
                i = np.repeat(np.arange(len(us), dtype=np.int32), np.diff(start))
                j = (np.arange(size) + np.repeat(first - start[:-1], np.diff(start))).astype(np.int32)
                if size < LEAST * parts:
                    yield from put(us[i], vs[j])
                    continue
                part = _part(Hashes(np.concatenate([us, vs])).leading(i, j + np.int32(len(us)), 1), parts)
                del i, j
                n = np.bincount(part, minlength=parts)
                data, bounds = pack_places(np.argsort(part, kind="stable"), np.append(0, np.cumsum(n)))
                there = np.flatnonzero(n)
                us, vs = pack_ids(us), pack_ids(vs)
                yield _rows(there, n[there], [us] * len(there), [vs] * len(there), [data[bounds[p] : bounds[p + 1]].tobytes() for p in there])
        yield from flush()

    return run


def _counter(batches):
    """Edges of each part of a batch. It takes whole rows, as the sorter does."""
    for batch in batches:
        found = pa.table([batch.column("part"), batch.column("n")], names=["part", "n"]).group_by("part").aggregate([("n", "sum")])
        yield from found.select(["part", "n_sum"]).rename_columns(["part", "n"]).to_batches()


def in_order(ids: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Order of the pairs (ids[i], ids[j]) by (md5, u, v)."""
    key = Hashes(ids).leading(i, j, 2)
    order = np.argsort(key)
    key = key[order]
    same = np.flatnonzero(key[1:] == key[:-1])
    if len(same):  # equal in 64 bits
        for low, high in zip(same[np.append(True, np.diff(same) > 1)].tolist(), same[np.append(np.diff(same) > 1, True)].tolist()):
            held = [(hashlib.md5(f"s{ids[i[x]]},{ids[j[x]]}".encode()).digest(), ids[i[x]], ids[j[x]], x) for x in order[low : high + 2].tolist()]
            order[low : high + 2] = [x[3] for x in sorted(held)]
    return order


def _sorter(batches):
    """All rows of a part, with the number of edges before it, to (t, u, v)."""
    cells, before = [], 0
    for batch in batches:
        for part, n, us, vs, data, before in zip(*(batch.column(c).to_pylist() for c in ("part", "n", "us", "vs", "data", "before"))):
            cells.append((n, us, vs, data))
    if not cells:
        return
    parts, blocks = [], {}
    for n, us, vs, data in cells:
        if us is None:
            u, v = unpack(data)
            mine = np.unique(np.concatenate([u, v]))
            parts.append((mine, np.searchsorted(mine, u), mine, np.searchsorted(mine, v)))
        else:
            for x in (us, vs):
                if x not in blocks:
                    blocks[x] = unpack_ids(x)
            us, vs, places = blocks[us], blocks[vs], unpack_places(data)
            first, start = _starts(us, vs)
            i = np.repeat(np.arange(len(us)), np.diff(np.searchsorted(places, start)))
            parts.append((us, i.astype(np.int32), vs, (places + (first - start[:-1])[i]).astype(np.int32)))
    del cells
    ids = np.unique(np.concatenate([*blocks.values(), *(p[0] for p in parts if p[0] is p[2])]))
    size = sum(len(p[1]) for p in parts)
    i, j, at = np.empty(size, np.int32), np.empty(size, np.int32), 0
    for us, a, vs, b in parts:
        i[at : at + len(a)], j[at : at + len(a)] = np.searchsorted(ids, us)[a], np.searchsorted(ids, vs)[b]
        at += len(a)
    del parts
    order = in_order(ids, i, j)
    for a in range(0, size, BATCH):
        some = order[a : a + BATCH]
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(before + a + 1, before + a + 1 + len(some))), pa.array(ids[i[some]]), pa.array(ids[j[some]])], ["t", "u", "v"])


def clique_stream(rows: DataFrame, edges: int = EDGES, side: int = SIDE) -> DataFrame:
    """(t, u, v) in the random order: pairs of ids that share a key, from rows (id, key). A range of the order gets about ``edges``
    edges, a block about ``side`` ids. Only pairs of ids that both have several keys can meet twice, so these alone are made one by one."""
    rows = rows.where("id is not null and key is not null").distinct()
    rows = rows.withColumn("several", F.count(F.lit(1)).over(Window.partitionBy("id")) > 1)
    sizes = rows.groupBy("key").agg(F.count(F.lit(1)).alias("c"))
    found = sizes.agg(F.sum(F.expr("c * (c - 1) div 2"))).first()[0] or 0  # pairs that meet twice count so, which is near enough
    parts = max(1, min(1 << 16, math.ceil(found / edges)))
    many = F.ceil(F.col("c") / side).cast("bigint")
    blocks = rows.join(sizes.where("c > 1"), "key").groupBy("key", "several", F.pmod(F.xxhash64("id"), many).alias("block"))
    blocks = blocks.agg(F.sort_array(F.collect_list("id")).alias("ids"))  # in one order, lest a task that runs again deals otherwise
    left, right = (blocks.select("key", F.col("several").alias(f"several_{x}"), F.col("ids").alias(x)) for x in ("us", "vs"))
    cells = left.join(right, "key").where("not (several_us and several_vs)").select("us", "vs")
    left, right = (rows.where("several").select("key", F.col("id").alias(x)) for x in ("u", "v"))
    others = clean(left.join(right, "key").where("u < v").select("u", "v", F.lit(0).alias("arrival"))).select("u", "v")
    packs = cells.repartition(parts).mapInArrow(_cell_packer(parts), FORM).unionByName(others.mapInArrow(_pair_packer(parts), FORM))
    packs = packs.repartitionById(parts, "part")
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = packs.mapInArrow(_counter, "part int, n bigint").groupBy("part").agg(F.sum("n").alias("own"))
    offsets = offsets.select("part", F.coalesce(F.sum("own").over(before), F.lit(0)).alias("before"))  # one row a part
    return packs.join(F.broadcast(offsets), "part").mapInArrow(_sorter, "t bigint, u bigint, v bigint")
