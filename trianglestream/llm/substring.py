"""Substring dedup with suffix automata.

The reference is the corpus itself, so its automata are not broadcast whole: every
window of ``length`` words belongs to the shard of its minimiser, the least hash of
its word 8-grams. Equal windows have equal minimisers, so each shard's automaton
decides its windows alone. Steps:

1. Scan documents into runs, the stretches of windows with one minimiser. Only
   (minimiser, document, start, number) leaves the scan; long runs, which one
   repeated passage makes, are cut into runs of ``MOST_RUN`` windows.
2. Runs whose minimiser never comes again are dropped; the rest are cut out of
   their documents as segments. A minimiser met more than ``hot`` times is split:
   its windows become segments of their own, keyed by their whole hash, so no
   frequent phrase gathers its contexts in one task.
3. Equal segments of a key are counted before they meet (partial aggregation).
   Per shard a suffix automaton of the distinct segments, with occurrence counts,
   gives matching statistics; a window whose state occurs twice or more is repeated.
4. Repeated windows go back to the documents as spans; covered words are removed.

For a reference apart from the documents (``matched_spans``) automata of its shards are
broadcast, in rounds of a bounded size each, and documents stream past them.

A document is known by its identifier and its text's hash, so rows with a null or a
repeated identifier take full part. Equal rows are documents of their own and removed
against each other. Null texts have no words; documents shorter than ``length`` keep
all; empty tables give no rows; other columns are not read.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from .common import documents, materialize, read_batches, release, tidied
from .toxicity import cut_points

GRAM, MOST_RUN = 8, 512
MULT = 0x5851F42D4C957F2D | 1
STEP = 0x2545F4914F6CDD1D | 1


def mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x9E3779B97F4A7C15)
    x = x ^ (x >> np.uint64(29))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(32))


def powers(base: int, n: int) -> np.ndarray:
    out = np.empty(n, np.uint64)
    out[0] = 1
    have = 1
    while have < n:
        more = min(have, n - have)
        out[have : have + more] = out[:more] * np.uint64(pow(base, have, 1 << 64))
        have += more
    return out


def word_grid(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Start and end of each word: maximal runs of bytes other than the six ASCII spaces."""
    space = (data == 32) | ((data >= 9) & (data <= 13))
    edge = np.flatnonzero(np.diff(np.concatenate([[True], space, [True]]).view(np.int8)))
    return edge[0::2], edge[1::2]


def word_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hash of each word, from prefix sums of a polynomial over bytes."""
    if not len(start):
        return np.zeros(0, np.uint64)
    n = len(data) + 1
    up, down = powers(MULT, n), powers(pow(MULT, -1, 1 << 64), n)
    total = np.zeros(n, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[:-1], out=total[1:])
    raw = (total[end] - total[start]) * down[start]
    return mix(raw + (end - start).astype(np.uint64) * np.uint64(STEP))


def gram_hashes(words: np.ndarray, size: int) -> np.ndarray:
    """Hash of every run of ``size`` words."""
    if len(words) < size:
        return np.zeros(0, np.uint64)
    out = np.zeros(len(words) - size + 1, np.uint64)
    for j in range(size):
        out = out * np.uint64(STEP) + words[j : j + len(out)]
    return mix(out)


def sliding_least(values: np.ndarray, width: int) -> np.ndarray:
    """Least of each ``width`` neighbours, by doubling."""
    least, have = values, 1
    while have < width:
        step = min(have, width - have)
        least = np.minimum(least[: len(least) - step], least[step:])
        have += step
    return least


RUNS = T.StructType([T.StructField("key", T.LongType()), T.StructField("id", T.LongType()), T.StructField("sign", T.LongType()), T.StructField("start", T.IntegerType()), T.StructField("many", T.IntegerType()), T.StructField("weight", T.IntegerType())])


def runs_of(words: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Runs of one document: minimiser, first window, number of windows, 2 if a window repeats inside else 1."""
    grams = gram_hashes(words, GRAM)
    least = sliding_least(grams, length - GRAM + 1)
    change = np.flatnonzero(np.concatenate([[True], least[1:] != least[:-1]]))
    if np.diff(np.append(change, len(least))).max() > MOST_RUN:
        change = np.unique(np.concatenate([np.arange(a, b, MOST_RUN) for a, b in zip(change, [*change[1:], len(least)])]))
    many = np.diff(np.append(change, len(least)))
    whole = gram_hashes(words, length)
    again = np.zeros(len(least), bool)
    for lag in range(1, min(length, len(least))):
        again[lag:] |= (whole[lag:] == whole[:-lag]) & (least[lag:] == least[:-lag])
    inside = np.add.reduceat(again.astype(np.int32), change) > 0
    return least[change].view(np.int64), change, many, np.where(inside | (many > length), 2, 1)


def chunked_words(batch, most_bytes: int = 1_000_000):
    """(identifiers, bytes, word starts, word ends, first word of each document) of pieces of a batch."""
    at = 0
    for end in cut_points(batch.column(1), most_bytes):
        part = batch.slice(at, end - at)
        at = end
        texts = [(x or "").encode() for x in part.column(1).to_pylist()]
        data = np.frombuffer(b" ".join(texts) + b" ", np.uint8)
        begin, stop = word_grid(data)
        ends = np.cumsum([len(x) + 1 for x in texts])
        first = np.concatenate([[0], np.searchsorted(begin, ends)])
        yield part.column(0), data, begin, stop, first


def run_kernel(length: int):
    def run(batches):
        for batch in batches:
            done = 0
            for ids, data, begin, stop, first in chunked_words(batch):
                words = word_hashes(data, begin, stop)
                signs = batch.column(2).slice(done, len(ids)).to_pylist()
                done += len(ids)
                parts = []
                for doc, sign, a, b in zip(ids.to_pylist(), signs, first, first[1:]):
                    if b - a >= length:
                        key, start, many, weight = runs_of(words[a:b], length)
                        parts.append((key, np.full(len(key), doc, np.int64), np.full(len(key), sign, np.int64), start.astype(np.int32), many.astype(np.int32), weight.astype(np.int32)))
                if parts:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*parts)], RUNS.names)

    return run


SEGMENTS = T.StructType([T.StructField("key", T.LongType()), T.StructField("hash", T.BinaryType()), T.StructField("words", T.BinaryType()), T.StructField("id", T.LongType()), T.StructField("sign", T.LongType()), T.StructField("start", T.IntegerType())])


def segment_kernel(length: int):
    """Rows (id, sign, text, runs): cut out each run's words; hot runs window by window, under the window's own key."""

    def run(batches):
        for batch in batches:
            for at in range(0, len(batch), 64):
                part = batch.slice(at, 64)
                out = {k: [] for k in SEGMENTS.names}
                for doc, sign, text, runs in zip(*[part.column(c).to_pylist() for c in ("id", "sign", "text", "runs")]):
                    words = (text or "").encode().split()
                    for r in runs:
                        key, start, many = r["key"], r["start"], r["many"]
                        pieces = [(start + i, 1) for i in range(many)] if r["hot"] else [(start, many)]
                        for s, n in pieces:
                            body = b" ".join(words[s : s + n + length - 1])
                            digest = hashlib.blake2b(body, digest_size=16).digest()
                            out["key"].append(int.from_bytes(digest[:8], "little", signed=True) if r["hot"] else key)
                            out["hash"].append(digest)
                            out["words"].append(body)
                            out["id"].append(doc)
                            out["sign"].append(sign)
                            out["start"].append(s)
                if out["key"]:
                    yield pa.RecordBatch.from_arrays([pa.array(out["key"], pa.int64()), pa.array(out["hash"], pa.binary()), pa.array(out["words"], pa.binary()), pa.array(out["id"], pa.int64()), pa.array(out["sign"], pa.int64()), pa.array(out["start"], pa.int32())], SEGMENTS.names)

    return run


class SuffixAutomaton:
    """Of several word sequences, each read from the root; ``count`` is how often a state's words occur."""

    def __init__(self):
        self.next, self.link, self.size, self.count = [{}], [-1], [0], [0]

    def add(self, words: list, weight: int = 1) -> None:
        last = 0
        for w in words:
            last = self._extend(last, w)
            self.count[last] += weight

    def _extend(self, last: int, w) -> int:
        nexts, link, size = self.next, self.link, self.size
        have = nexts[last].get(w)
        if have is not None:
            return have if size[have] == size[last] + 1 else self._split(last, w, have)
        new = len(size)
        nexts.append({})
        size.append(size[last] + 1)
        link.append(0)
        self.count.append(0)
        p = last
        while p != -1 and w not in nexts[p]:
            nexts[p][w] = new
            p = link[p]
        if p != -1:
            q = nexts[p][w]
            link[new] = q if size[q] == size[p] + 1 else self._split(p, w, q)
        return new

    def _split(self, p: int, w, q: int) -> int:
        copy = len(self.size)
        self.next.append(dict(self.next[q]))
        self.size.append(self.size[p] + 1)
        self.link.append(self.link[q])
        self.count.append(0)
        self.link[q] = copy
        while p != -1 and self.next[p].get(w) == q:
            self.next[p][w] = copy
            p = self.link[p]
        return copy

    def settle(self) -> "SuffixAutomaton":
        """Pass counts down the suffix links, longest states first."""
        for s in sorted(range(1, len(self.size)), key=self.size.__getitem__, reverse=True):
            if self.link[s] > 0:
                self.count[self.link[s]] += self.count[s]
        return self

    def matches(self, words: list, cap: int):
        """Matching statistics: for each end position the length matched, at most ``cap``, and its state."""
        state = length = 0
        for w in words:
            while state and w not in self.next[state]:
                state = self.link[state]
                length = self.size[state]
            if w in self.next[state]:
                state, length = self.next[state][w], length + 1
            while state and self.size[self.link[state]] >= cap:
                state = self.link[state]
            length = min(length, cap)
            yield length, state


def shard_kernel(length: int, shard_words: int = 60_000):
    """Distinct segments sorted by key: one automaton for the whole keys that fit ``shard_words``; repeated windows of each segment."""

    def flush(rows):
        automaton = SuffixAutomaton()
        for _, _, words, weight in rows:
            automaton.add(words, weight)
        automaton.settle()
        out = []
        for key, digest, words, _ in rows:
            offsets = [end - length + 1 for end, (size, state) in enumerate(automaton.matches(words, length)) if size >= length and automaton.count[state] >= 2]
            if offsets:
                out.append((key, digest, offsets))
        return out

    def emit(out):
        return pa.RecordBatch.from_arrays([pa.array([x[0] for x in out], pa.int64()), pa.array([x[1] for x in out], pa.binary()), pa.array([x[2] for x in out], pa.list_(pa.int32()))], ["key", "hash", "offsets"])

    def run(batches):
        rows, held, current = [], 0, None
        for batch in batches:
            for key, digest, body, weight in zip(*[batch.column(c).to_pylist() for c in ("key", "hash", "words", "weight")]):
                if key != current and held >= shard_words:
                    if out := flush(rows):
                        yield emit(out)
                    rows, held = [], 0
                current = key
                words = body.split(b" ")
                rows.append((key, digest, words, weight))
                held += len(words)
        if rows and (out := flush(rows)):
            yield emit(out)

    return run


def signed_rows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, text, sign, own): rows of equal id and sign are equal documents; a null identifier, kept in own, counts as zero."""
    text, own = F.col(text_col).cast("string"), F.col(id_col).cast("bigint")
    return docs.select(F.coalesce(own, F.lit(0)).alias("id"), text.alias("text"), F.xxhash64(text).alias("sign"), own.alias("own"))


def repeated_windows(rows: DataFrame, length: int = 35, hot: int = 2000) -> DataFrame:
    """(id, sign, starts): for each document with any, the starts of windows that also start elsewhere.

    ``rows`` has columns id, text and sign (see ``signed_rows``).
    """
    runs = materialize(rows.mapInArrow(tidied(run_kernel(length)), RUNS), "runs", compression="zstd")
    often = runs.groupBy("key").agg(F.sum("weight").alias("met")).where("met > 1")
    kept = runs.join(often, "key").select("id", "sign", F.struct("key", "start", "many", (F.col("met") > hot).alias("hot")).alias("run"))
    # Equal rows send equal runs; each of them is cut by the one list they share, so counts stay right.
    per_doc = kept.groupBy("id", "sign").agg(F.array_distinct(F.collect_list("run")).alias("runs"))
    cut = rows.join(per_doc, ["id", "sign"]).select("id", "sign", "text", "runs").mapInArrow(tidied(segment_kernel(length)), SEGMENTS)
    segments = materialize(cut, "segments", compression="zstd")
    release(runs)
    distinct = segments.groupBy("key", "hash").agg(F.first("words").alias("words"), F.count(F.lit(1)).cast("int").alias("weight"))
    alone = distinct.repartition("key").sortWithinPartitions("key", "hash")
    schema = T.StructType([T.StructField("key", T.LongType()), T.StructField("hash", T.BinaryType()), T.StructField("offsets", T.ArrayType(T.IntegerType()))])
    found = materialize(alone.mapInArrow(tidied(shard_kernel(length)), schema), "repeats", compression="zstd")
    spots = segments.select("key", "hash", "id", "sign", "start").join(found, ["key", "hash"])
    return spots.groupBy("id", "sign").agg(F.array_distinct(F.flatten(F.collect_list(F.transform("offsets", lambda o: o + F.col("start"))))).alias("starts"))


def covered(n: int, starts, length: int) -> np.ndarray:
    """Which of ``n`` words lie in a window that begins at one of ``starts``."""
    depth = np.zeros(n + 1, np.int64)
    at = np.asarray(starts if starts is not None else [], np.int64)
    np.add.at(depth, at, 1)
    np.add.at(depth, at + length, -1)
    return np.cumsum(depth[:-1]) > 0


def removal_kernel(length: int):
    def run(batches):
        for batch in batches:
            for at in range(0, len(batch), 256):
                part = batch.slice(at, 256)
                total, removed, kept = [], [], []
                for text, starts in zip(part.column("text").to_pylist(), part.column("starts").to_pylist()):
                    words = (text or "").encode().split()
                    drop = covered(len(words), starts, length)
                    total.append(len(words))
                    removed.append(int(drop.sum()))
                    kept.append(b" ".join(w for w, d in zip(words, drop.tolist()) if not d) if starts else b" ".join(words))
                yield pa.RecordBatch.from_arrays([part.column("id"), pa.array(total, pa.int64()), pa.array(removed, pa.int64()), pa.array([k.decode() for k in kept], pa.string())], ["id", "n_words", "n_removed", "kept_text"])

    return run


def remove_repeats(docs: DataFrame, length: int = 35, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: id_col, n_words, n_removed, kept_text (words that stay, one space between)."""
    rows = signed_rows(docs, id_col, text_col)
    starts = repeated_windows(rows.drop("own"), length)
    joined = rows.join(starts, ["id", "sign"], "left").select(F.col("own").alias("id"), "text", "starts")
    schema = T.StructType([T.StructField("id", T.LongType()), T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField("kept_text", T.StringType())])
    return joined.mapInArrow(tidied(removal_kernel(length)), schema).withColumnRenamed("id", id_col)


def reference_rounds(reference, shard_words: int, round_words: int):
    """Rounds of automata over texts, as flat states: a shard closes at ``shard_words`` words, a round at ``round_words``."""
    shards, held, size, total = [], SuffixAutomaton(), 0, 0
    for text in reference:
        words = (text or "").encode().split()
        held.add(words)
        size, total = size + len(words), total + len(words)
        if size >= shard_words or total >= round_words:
            shards.append((held.next, held.link, held.size))
            held, size = SuffixAutomaton(), 0
        if total >= round_words:
            yield shards
            shards, total = [], 0
    if size:
        shards.append((held.next, held.link, held.size))
    if shards:
        yield shards


def matched_spans(docs: DataFrame, reference, length: int = 35, shard_words: int = 50_000, round_words: int = 200_000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row of ``docs``: id_col and the maximal spans (start, stop, in words) whose windows of ``length`` words occur in
    ``reference``, a list of texts or a DataFrame with a column text.

    Automata of reference shards are broadcast and documents stream past them for their matching statistics. A broadcast
    holds at most ``round_words`` words and the longest text (a text is never cut); a larger reference takes several
    rounds, each a pass over ``docs``, and reaches the driver row by row.
    """
    spark = docs.sparkSession
    texts = reference if isinstance(reference, list) else (r["text"] for r in reference.select("text").toLocalIterator())
    span = pa.list_(pa.struct([("start", pa.int32()), ("stop", pa.int32())]))

    def spans_of(hit: np.ndarray) -> list[dict]:
        edge = np.flatnonzero(np.diff(np.concatenate([[False], hit, [False]]).view(np.int8)))
        return [{"start": int(s), "stop": int(e)} for s, e in zip(edge[0::2], edge[1::2])]

    def kernel(shared):
        def run(batches):
            automata = []
            for nexts, link, sizes in shared.value:
                a = SuffixAutomaton()
                a.next, a.link, a.size, a.count = nexts, link, sizes, [0] * len(sizes)
                automata.append(a)
            for batch in read_batches(batches, 256):
                spans = []
                for text, known in zip(batch.column("text").to_pylist(), batch.column("spans").to_pylist()):
                    words = (text or "").encode().split()
                    starts = [end - length + 1 for a in automata for end, (n, _) in enumerate(a.matches(words, length)) if n >= length]
                    hit = covered(len(words), starts, length)
                    for s in known:
                        hit[s["start"] : s["stop"]] = True
                    spans.append(spans_of(hit))
                yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("text"), pa.array(spans, span)], ["id", "text", "spans"])

        return run

    schema = "id bigint, text string, spans array<struct<start:int,stop:int>>"
    rows = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).cast("string").alias("text"), F.array().cast("array<struct<start:int,stop:int>>").alias("spans"))
    for round_ in reference_rounds(texts, shard_words, round_words):
        rows = materialize(rows.mapInArrow(tidied(kernel(spark.sparkContext.broadcast(round_))), schema), "spans", compression="zstd")
    return rows.select(F.col("id").alias(id_col), "spans")


def op6_substring_dedup(spark, sf_dir: str) -> DataFrame:
    """Whole ``documents``: doc_id, n_words, n_removed, kept_sha256 at windows of 35 words, for every row, whatever its doc_id."""
    kept = remove_repeats(documents(spark, sf_dir).select("doc_id", "text"), 35)
    return kept.select("doc_id", "n_words", "n_removed", F.sha2("kept_text", 256).alias("kept_sha256"))


def brute_force_removed(texts: dict[int, str | None], length: int = 35) -> dict[int, tuple[int, int, str]]:
    """The stated rule over all windows in memory, for tests."""
    words = {i: (t or "").encode().split() for i, t in texts.items()}
    met: dict[tuple, int] = {}
    for w in words.values():
        for s in range(len(w) - length + 1):
            key = tuple(w[s : s + length])
            met[key] = met.get(key, 0) + 1
    out = {}
    for i, w in words.items():
        drop = covered(len(w), [s for s in range(len(w) - length + 1) if met[tuple(w[s : s + length])] > 1], length)
        kept = b" ".join(x for x, d in zip(w, drop.tolist()) if not d)
        out[i] = (len(w), int(drop.sum()), hashlib.sha256(kept).hexdigest())
    return out
