"""Near-duplicate classes by weighted MinHash over TF-IDF shingles.

1. Texts become sets of five-word shingles. Scan tasks cut their documents into blocks;
   a block hands its distinct shingles on, each with the number of documents of the block
   that hold it, in packs by hash range. All packs of a range meet in one place, where
   exact document frequencies are added up and sent back to the blocks (a keyed join of
   shingles and frequencies, moved in packs instead of rows).
2. A shingle weighs its count times 1 + ln((1 + N) / (1 + documents)). Improved consistent
   weighted sampling draws ``bands * rows`` samples of each text; texts that share a whole
   band are candidates, and the exact weighted Jaccard similarity alone decides.
3. Classes are the connected components of pairs at or over the threshold. All pairs of a
   band are decided, without listing pairs within classes: first every text is compared
   with the least of its bucket, then, in buckets that still hold several classes, each text
   outside the largest class is compared with all texts of other classes: as pairs in
   buckets of up to ``SMALL`` texts, in blocks of bounded size in larger ones. Blocks find
   partners by an index of rare shingles that no pair over the threshold can evade, and
   pairs whose total weights differ by more than the threshold allows are not compared:
   both rules are exact.

Texts with the same words are one node, unfolded at the end, so copies never meet as
pairs. Texts under five words have one shingle of all their words; empty and null texts
are nobody's near duplicate. Rows that repeat an identifier are one document with the
union of links; null identifiers are one row of their own without a class. Results hold
for ties, repeated rows, very long texts and empty tables; other columns are not read.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from .common import bucketed, documents, drop_bucketed, expand, materialize, only_listed, pack_numbers, read_batches, release, squeeze, tidied, unpack_numbers, working_name
from .substring import chunked_words, gram_hashes, mix, word_grid, word_hashes

SHINGLE, THRESHOLD, BANDS, ROWS = 5, 0.8, 14, 4
#: Buckets up to this size are tried as pairs; a leader's text is sent once for so many members.
SMALL, SALT = 8, 256
#: A block of a larger bucket holds about so many nodes and shingles at most.
BLOCK_NODES, BLOCK_SHINGLES = 1024, 1 << 19
#: Pack of a block's texts; characters of a block.
BODY, BLOCK_BYTES = 1 << 30, 8_000_000
#: Shingles are counted by so many bits of their hash: a count holds another shingle's documents with a chance of their
#: number over 2**48. Bits of the tables of draws.
NAME_BITS, R_BITS, C_BITS = 48, 16, 18


def shingle_counts(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of a text, ascending, and how often each comes."""
    grams = gram_hashes(words, min(SHINGLE, len(words))) if len(words) else np.zeros(0, np.uint64)
    return np.unique(grams, return_counts=True)


def text_shingles(text: str) -> tuple[np.ndarray, np.ndarray]:
    data = np.frombuffer((text or "").encode() + b" ", np.uint8)
    return shingle_counts(word_hashes(data, *word_grid(data)))


def name_of(shingles: np.ndarray) -> np.ndarray:
    """The leading bits by which a shingle is counted."""
    return shingles >> np.uint64(64 - NAME_BITS)


def pack_of(names: np.ndarray, packs: int) -> np.ndarray:
    """Hash range of each name; ascending as the names are."""
    return ((names >> np.uint64(NAME_BITS - 32)) * np.uint64(packs) >> np.uint64(32)).astype(np.int64)


def pack_names(names: np.ndarray) -> bytes:
    """Ascending names as byte planes of their differences, then zstd."""
    gaps = np.diff(names, prepend=np.uint64(0)).astype("<u8")
    return squeeze(np.ascontiguousarray(gaps.view(np.uint8).reshape(-1, 8).T).tobytes())


def unpack_names(data: bytes) -> np.ndarray:
    planes = np.frombuffer(expand(data), np.uint8).reshape(8, -1)
    return np.cumsum(np.ascontiguousarray(planes.T).view("<u8").ravel(), dtype=np.uint64)


BLOCKS = T.StructType([
    T.StructField("block", T.LongType()), T.StructField("pack", T.IntegerType()), T.StructField("ids", T.ArrayType(T.LongType())),
    T.StructField("texts", T.ArrayType(T.StringType())), T.StructField("names", T.BinaryType()), T.StructField("counts", T.BinaryType()),
])
ARROW_BLOCKS = pa.schema([("block", pa.int64()), ("pack", pa.int32()), ("ids", pa.list_(pa.int64())), ("texts", pa.list_(pa.string())), ("names", pa.binary()), ("counts", pa.binary())])


def block_kernel(packs: int):
    """Documents (id, text) to blocks: one row of texts (pack BODY) and one row for each pack that has shingles.
    Documents without identifier or words count as documents but have no row."""

    def run(batches):
        from pyspark import TaskContext

        partition, made = TaskContext.get().partitionId(), 0
        ids, texts, sets, held = [], [], [], 0

        def flush():
            names, counts = np.unique(np.concatenate(sets), return_counts=True)
            pack = pack_of(names, packs)
            cuts = [0, *(np.flatnonzero(np.diff(pack)) + 1).tolist(), len(names)]
            rows = [{"block": (partition << 32) | made, "pack": int(pack[a]), "names": pack_names(names[a:b]), "counts": pack_numbers(counts[a:b])} for a, b in zip(cuts, cuts[1:])]
            rows.append({"block": (partition << 32) | made, "pack": BODY, "ids": ids, "texts": texts})
            return pa.RecordBatch.from_pylist(rows, schema=ARROW_BLOCKS)

        for batch in batches:
            for own, data, begin, stop, first in chunked_words(batch):
                words = word_hashes(data, begin, stop)
                ends = np.append(begin, len(data))
                for doc, a, b in zip(own.to_pylist(), first, first[1:]):
                    if b > a:
                        sets.append(np.unique(name_of(shingle_counts(words[a:b])[0])))
                        if doc is not None:
                            ids.append(doc)
                            texts.append(data[begin[a] : stop[b - 1]].tobytes().decode())
                        held += int(ends[b] - ends[a])
                        if held >= BLOCK_BYTES:
                            yield flush()
                            made += 1
                            ids, texts, sets, held = [], [], [], 0
        if sets:
            yield flush()

    return run


def frequency_kernel(batches):
    """Rows sorted by pack: the documents over all blocks that hold each shingle, back to each block."""
    schema = pa.schema([("block", pa.int64()), ("pack", pa.int32()), ("known", pa.binary())])

    def flush(pack, blocks, sets, counts):
        every, where = np.unique(np.concatenate(sets), return_inverse=True)
        total = np.bincount(where, weights=np.concatenate(counts), minlength=len(every)).astype(np.int64)[where]
        ends = np.cumsum([len(s) for s in sets])
        for at in range(0, len(blocks), 64):
            part = [{"block": b, "pack": pack, "known": pack_numbers(total[e - len(s) : e])} for b, s, e in zip(blocks[at : at + 64], sets[at : at + 64], ends[at : at + 64])]
            yield pa.RecordBatch.from_pylist(part, schema=schema)

    current, blocks, sets, counts = None, [], [], []
    for batch in read_batches(batches, 64):
        for block, pack, names, own in zip(*[batch.column(c).to_pylist() for c in ("block", "pack", "names", "counts")]):
            if pack != current and blocks:
                yield from flush(current, blocks, sets, counts)
                blocks, sets, counts = [], [], []
            current = pack
            blocks.append(block)
            sets.append(unpack_names(names))
            counts.append(unpack_numbers(own))
    if blocks:
        yield from flush(current, blocks, sets, counts)


def draw_tables() -> tuple[np.ndarray, np.ndarray]:
    """Quantiles of the gamma law of shape two, as r and ln c: sampling looks its draws up by hash bits."""

    def quantiles(bits):
        want = (np.arange(1 << bits) + 0.5) / (1 << bits)
        x = np.sqrt(2 * want)  # near zero the law is x^2 / 2
        for _ in range(30):
            step = (-np.expm1(-x) - x * np.exp(-x) - want) / np.maximum(x * np.exp(-x), 1e-12)
            x = np.clip(x - step, x / 2, x + 2)
        return x

    return quantiles(R_BITS).astype(np.float32), np.log(quantiles(C_BITS)).astype(np.float32)


def consistent_samples(shingles: np.ndarray, log_weight: np.ndarray, starts: np.ndarray, samples: int, draws: tuple) -> np.ndarray:
    """Improved consistent weighted sampling: (samples, texts) tokens. ``starts``: first row of each text, none empty."""
    r_of, log_c_of = draws
    out = np.empty((samples, len(starts)), np.uint64)
    sizes = np.diff(np.append(starts, len(shingles)))
    for k in range(samples):
        h = (shingles ^ np.uint64(0xD1B54A32D192ED03 * (k + 1) & (1 << 64) - 1)) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
        h *= np.uint64(0xBF58476D1CE4E5B9)
        r = r_of.take((h >> np.uint64(64 - R_BITS)).view(np.int64), mode="clip")
        beta = (h >> np.uint64(32)).astype(np.uint16).astype(np.float32)
        beta *= np.float32(1 / 65536)
        h >>= np.uint64(14)
        h &= np.uint64((1 << C_BITS) - 1)
        log_a = log_c_of.take(h.view(np.int64), mode="clip")
        t = log_weight / r
        t += beta
        np.floor(t, out=t)
        r *= t - beta + np.float32(1)
        log_a -= r
        least = np.minimum.reduceat(log_a, starts)
        spot = np.flatnonzero(log_a == np.repeat(least, sizes))
        chosen = spot[np.searchsorted(spot, starts)]
        out[k] = mix(shingles[chosen] ^ mix(t[chosen].astype(np.int64).view(np.uint64)))
    return out


def band_keys(tokens: np.ndarray, bands: int, rows: int) -> np.ndarray:
    keys = np.empty((tokens.shape[1], bands), np.uint64)
    for b in range(bands):
        h = np.full(tokens.shape[1], b + 1, np.uint64)
        for r in range(rows):
            h = mix(h * np.uint64(0x2545F4914F6CDD1D) + tokens[b * rows + r])
        keys[:, b] = h
    return keys.view(np.int64)


SIGNED = "id bigint, node binary, bands array<bigint>, total double, width int, text string, weights binary"


def signature_kernel(shared, documents_: int, bands: int, rows: int):
    """Blocks with the frequencies of their packs to (id, node, bands, total, width, text, weights): node names the
    sequence of words, total is the sum of weights, width counts shingles, weights are those of the shingles in order."""

    def run(batches):
        draws = shared.value
        for batch in read_batches(batches, 1):
            row = batch.to_pylist()[0]
            known = np.concatenate([unpack_numbers(c["known"]) for c in sorted(row["known"] or [], key=lambda c: c["pack"])])
            idf = (1 + np.log((1 + documents_) / (1 + known))).astype(np.float32)
            texts = pa.record_batch([pa.array(row["ids"], pa.int64()), pa.array(row["texts"], pa.string())], ["id", "text"])
            every, done = np.concatenate([unpack_names(x) for x in row["names"]]), 0
            for ids, data, begin, stop, first in chunked_words(texts):
                words = word_hashes(data, begin, stop)
                sets = [shingle_counts(words[a:b]) for a, b in zip(first, first[1:])]
                flat, ends = np.concatenate([s for s, _ in sets]), np.cumsum([len(s) for s, _ in sets])
                weight = np.concatenate([c for _, c in sets]).astype(np.float32) * idf[np.searchsorted(every, name_of(flat))]
                starts = np.concatenate([[0], ends[:-1]])
                tokens = consistent_samples(flat, np.log(weight), starts, bands * rows, draws)
                keys = band_keys(tokens, bands, rows)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(ids) + 1, dtype=np.int32) * bands), pa.array(keys.ravel()))
                nodes = [hashlib.blake2b(words[a:b].tobytes(), digest_size=16).digest() for a, b in zip(first, first[1:])]
                total = np.add.reduceat(weight.astype(np.float64), starts)
                weights = [weight[e - len(s) : e].tobytes() for (s, _), e in zip(sets, ends)]
                columns = [ids, pa.array(nodes, pa.binary()), lists, pa.array(total), pa.array(np.diff([0, *ends]), pa.int32()), texts.column(1).slice(done, len(ids)), pa.array(weights, pa.binary())]
                done += len(ids)
                yield pa.RecordBatch.from_arrays(columns, ["id", "node", "bands", "total", "width", "text", "weights"])

    return run


def signatures(texts: DataFrame, bands: int, rows: int) -> DataFrame:
    """One row for each row of ``texts`` (id, text) that has an identifier and words, with bands and weights."""
    spark = texts.sparkSession
    partitions = max(16, int(spark.conf.get("spark.sql.shuffle.partitions")))
    packs = 4 * partitions
    blocks, name = bucketed(texts.mapInArrow(tidied(block_kernel(packs)), BLOCKS), partitions)
    own = blocks.where(F.col("pack") != BODY).select("block", "pack", "names", "counts")
    met = own.repartition(partitions, "pack").sortWithinPartitions("pack")
    known = met.mapInArrow(tidied(frequency_kernel), "block bigint, pack int, known binary")
    by_block = known.repartition(partitions, "block").groupBy("block").agg(F.collect_list(F.struct("pack", "known")).alias("known"))
    # A block's rows lie in one bucket: its shingles are gathered beside its texts without a shuffle.
    bodies = blocks.groupBy("block").agg(F.first("ids", ignorenulls=True).alias("ids"), F.first("texts", ignorenulls=True).alias("texts"), F.transform(F.array_sort(F.collect_list(F.when(F.col("pack") != BODY, F.struct("pack", "names")))), lambda x: x["names"]).alias("names"))
    together = bodies.join(by_block.hint("shuffle_hash"), "block").where(F.size("ids") > 0)
    shared = spark.sparkContext.broadcast(draw_tables())
    made = materialize(together.mapInArrow(tidied(signature_kernel(shared, texts.count(), bands, rows)), SIGNED), "signatures", compression="zstd")
    drop_bucketed(blocks, name)
    return made


def weighted_set(text: str, weights: bytes) -> tuple[np.ndarray, np.ndarray]:
    return text_shingles(text)[0], np.frombuffer(weights, np.float32).astype(np.float64)


def weighted_jaccard(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Sum of lesser weights over sum of greater ones."""
    _, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    both = float(np.minimum(a[1][i], b[1][j]).sum())
    either = float(a[1].sum() + b[1].sum()) - both
    return both / either if either > 0 else 0.0


def verify_kernel(threshold: float):
    """Sorted by (a, salt, b), nulls first: a leader's texts (one, if its identifier does not repeat), then its members'.
    Pairs at or over the threshold stay."""

    def run(batches):
        leader, salt, held = None, None, []
        for batch in read_batches(batches, 256):
            out = ([], [], [])
            for row in batch.select(["a", "salt", "b", "text", "weights"]).to_pylist():
                own = weighted_set(row["text"], row["weights"])
                if (row["a"], row["salt"]) != (leader, salt):
                    leader, salt, held = row["a"], row["salt"], []
                if row["b"] is None:
                    held.append(own)
                else:
                    s = max((weighted_jaccard(x, own) for x in held), default=0.0)
                    if s >= threshold:
                        for c, v in zip(out, (row["a"], row["b"], s)):
                            c.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.float64())], ["a", "b", "similarity"])

    return run


def verified(pairs: DataFrame, held: DataFrame, threshold: float) -> DataFrame:
    """Of pairs (a, b) those whose texts are similar; a leader's text is sent once for up to SALT members."""
    many = pairs.groupBy("a").count().select("a", F.ceil(F.col("count") / SALT).alias("salts"))
    salted = pairs.join(many, "a").withColumn("salt", F.pmod(F.xxhash64("b"), F.col("salts")))
    members = salted.select("a", "salt", "b").join(held.withColumnRenamed("id", "b"), "b").select("a", "salt", "b", "text", "weights")
    leaders = salted.select("a", "salt").distinct().join(held.withColumnRenamed("id", "a"), "a").select("a", "salt", F.lit(None).cast("bigint").alias("b"), "text", "weights")
    rows = leaders.unionByName(members).repartition("a", "salt").sortWithinPartitions("a", "salt", F.col("b").asc_nulls_first())
    return rows.mapInArrow(tidied(verify_kernel(threshold)), "a bigint, b bigint, similarity double")


def components(edges: DataFrame) -> DataFrame:
    """(id, label): least node of each node's component; least labels spread along links, then labels jump to their label's."""
    links = materialize(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "links")
    labels = materialize(links.groupBy(F.col("a").alias("id")).agg(F.least(F.col("id"), F.min("b")).alias("label")), "labels")
    while True:
        near = links.join(labels.withColumnRenamed("id", "b"), "b").groupBy(F.col("a").alias("id")).agg(F.min("label").alias("near"))
        spread = labels.join(near, "id").select("id", F.least("label", "near").alias("label"), F.col("label").alias("old"))
        jump = labels.select(F.col("id").alias("label"), F.col("label").alias("further"))
        new = materialize(spread.join(jump, "label", "left").select("id", F.least("label", F.coalesce("further", "label")).alias("label"), "old"), "labels")
        done = new.where("label <> old").isEmpty()
        release(labels)
        labels = new
        if done:
            release(links)
            return labels.select("id", "label")


def likely(pairs: DataFrame, threshold: float) -> DataFrame:
    """Pairs (a, b), a < b, each once, whose total weights allow the threshold: the similarity is at most their ratio."""
    low, high = F.least("total_a", "total_b"), F.greatest("total_a", "total_b")
    fine = pairs.where((F.col("a") != F.col("b")) & (low >= high * (threshold - 1e-6)))
    return fine.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def first_pairs(buckets: DataFrame) -> DataFrame:
    """Each node of a bucket against the least."""
    return buckets.select(F.col("head.id").alias("a"), F.col("head.total").alias("total_a"), F.col("id").alias("b"), F.col("total").alias("total_b"))


def placed_nodes(buckets: DataFrame, labels: DataFrame) -> DataFrame:
    """Rows of ``buckets`` over two nodes with the label of each."""
    return buckets.where("size > 2").join(labels, "id", "left").withColumn("label", F.coalesce("label", "id"))


def small_pairs(placed: DataFrame) -> DataFrame:
    """All pairs of two classes of small buckets, but those with the least node, which are tried already."""
    small = placed.where((F.col("size") <= SMALL) & (F.col("id") != F.col("head.id")))
    side = lambda c: small.select("key", F.col("id").alias(c), F.col("total").alias(f"total_{c}"), F.col("label").alias(f"label_{c}"))
    return side("a").join(side("b"), "key").where("a < b and label_a <> label_b").select("a", "total_a", "b", "total_b")


class Block:
    """Nodes of one bucket as arrays, against which others are compared one by one. A link joins two classes, which
    then need no further one here."""

    def __init__(self, key: int, main: int, nodes: list, threshold: float):
        self.key, self.threshold = key, threshold
        ids, labels, bands, sets = zip(*nodes)
        self.ids, self.labels, self.bands = np.array(ids), np.array(labels), np.array(bands)
        self.stray = self.labels != main
        self.sizes = np.array([len(s) for s, _ in sets])
        self.starts = np.cumsum(self.sizes) - self.sizes
        self.words, self.at = np.unique(np.concatenate([s for s, _ in sets]), return_inverse=True)
        self.weights = np.concatenate([w for _, w in sets])
        self.sums = np.add.reduceat(self.weights, self.starts)
        self.own = np.zeros(len(self.words))
        self.often = np.bincount(self.at, minlength=len(self.words))
        self.first = np.cumsum(self.often) - self.often
        self.holders = np.repeat(np.arange(len(ids)), self.sizes)[np.argsort(self.at, kind="stable")]
        self.joined = {}

    def similarities(self, chosen: np.ndarray, total: float) -> np.ndarray:
        """Weighted Jaccard similarity of the text laid out in ``own`` and each chosen node."""
        sizes = self.sizes[chosen]
        heads = np.cumsum(sizes) - sizes
        flat = np.repeat(self.starts[chosen] - heads, sizes) + np.arange(sizes.sum())
        both = np.add.reduceat(np.minimum(self.own[self.at[flat]], self.weights[flat]), heads)
        return both / (total + self.sums[chosen] - both)

    def partners(self, spot: np.ndarray, hit: np.ndarray, weights: np.ndarray, total: float) -> np.ndarray:
        """Nodes that hold one of the rarest shingles which together outweigh what a similar text may lack: all others
        share less than the threshold times ``total``."""
        often = np.where(hit, self.often[spot], 0)
        order = np.argsort(often, kind="stable")
        need = int(np.searchsorted(np.cumsum(weights[order]), (1 - self.threshold + 1e-6) * total, side="right")) + 1
        rare = order[:need]
        rare = spot[rare[hit[rare]]]
        many = self.often[rare]
        begin = np.cumsum(many) - many
        return np.unique(self.holders[np.repeat(self.first[rare] - begin, many) + np.arange(many.sum())])

    def links(self, node: tuple) -> list[int]:
        """Nodes of other classes similar to ``node``, one for each class. Two nodes outside the largest class meet
        from one side only, and two that share several buckets meet in that of the least key."""
        id_, label, bands, (shingles, weights) = node
        while label in self.joined:
            label = self.joined[label]
        spot = np.minimum(np.searchsorted(self.words, shingles), len(self.words) - 1)
        hit, total = self.words[spot] == shingles, float(weights.sum())
        rest = self.partners(spot, hit, weights, total)
        ratio = np.minimum(self.sums[rest], total) >= (self.threshold - 1e-6) * np.maximum(self.sums[rest], total)
        rest = rest[ratio & (self.labels[rest] != label) & (~self.stray[rest] | (self.ids[rest] < id_))]
        far = np.iinfo(np.int64).max
        rest = rest[np.where(self.bands[rest] == bands, bands, far).min(1, initial=far) == self.key]
        if not len(rest):
            return []
        self.own[spot[hit]] = weights[hit]
        found = []
        while len(rest):
            now, rest = rest[:64], rest[64:]
            for i in now[self.similarities(now, total) >= self.threshold]:
                other = self.labels[i]
                if other != label:
                    found.append(int(self.ids[i]))
                    self.joined[other] = label
                    self.labels[self.labels == other] = label
            rest = rest[self.labels[rest] != label]
        self.own[spot[hit]] = 0
        return found


def rest_kernel(threshold: float):
    """Sorted by (key, part, salt, stray): the nodes of a block, then those outside the bucket's largest class that meet it."""

    def run(batches):
        current, nodes, block = None, [], None
        for batch in read_batches(batches, 256):
            out = ([], [])
            for row in batch.to_pylist():
                place = (row["key"], row["part"], row["salt"])
                if place != current:
                    current, nodes, block = place, [], None
                node = (row["id"], row["label"], np.array(row["bands"], np.int64), weighted_set(row["text"], row["weights"]))
                if not row["stray"]:
                    nodes.append(node)
                elif nodes:
                    block = block or Block(row["key"], row["main"], nodes, threshold)
                    for b in block.links(node):
                        out[0].append(row["id"])
                        out[1].append(b)
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64())], ["a", "b"])

    return run


def rest_links(placed: DataFrame, nodes: DataFrame, held: DataFrame, threshold: float) -> DataFrame:
    """Links (a, b) that join all classes of the large buckets which any similar pair joins. Each node outside its
    bucket's largest class meets the whole bucket, in blocks bounded by nodes and shingles."""
    placed = placed.where(F.col("size") > SMALL).select("key", "id", "label").join(nodes.select("id", "bands", "width"), "id")
    classes = placed.groupBy("key", "label").agg(F.count(F.lit(1)).alias("n"), F.sum("width").alias("width"))
    mixed = classes.groupBy("key").agg(F.max_by("label", F.struct("n", "label")).alias("main"), F.sum("n").alias("n"), F.max("n").alias("most"), F.sum("width").alias("width"), F.count(F.lit(1)).alias("classes")).where("classes > 1")
    parts = F.greatest(F.ceil(F.col("n") / BLOCK_NODES), F.ceil(F.col("width") / BLOCK_SHINGLES)).cast("int")
    mixed = mixed.select("key", "main", parts.alias("parts"), F.ceil((F.col("n") - F.col("most")) / BLOCK_NODES).cast("int").alias("salts"))
    rows = placed.join(mixed, "key").join(held, "id")
    part, salt = F.pmod(F.xxhash64("id"), F.col("parts")).cast("int"), F.pmod(F.xxhash64("id"), F.col("salts")).cast("int")
    every = lambda many: F.explode(F.sequence(F.lit(0), F.col(many) - 1))
    kept = ("key", "main", "id", "label", "bands", "text", "weights")
    members = rows.select(*kept, part.alias("part"), every("salts").alias("salt"), F.lit(False).alias("stray"))
    strays = rows.where("label <> main").select(*kept, every("parts").alias("part"), salt.alias("salt"), F.lit(True).alias("stray"))
    met = members.unionByName(strays).repartition("key", "part", "salt").sortWithinPartitions("key", "part", "salt", "stray")
    return met.mapInArrow(tidied(rest_kernel(threshold)), "a bigint, b bigint")


def near_labels(signed: DataFrame, threshold: float) -> tuple[DataFrame, DataFrame]:
    """Nodes (node, id, ..) and the labels (id, label) of those that have links."""
    nodes = materialize(signed.groupBy("node").agg(F.min("id").alias("id"), F.first("bands").alias("bands"), F.first("total").alias("total"), F.first("width").alias("width")), "nodes", compression="zstd")
    keyed = nodes.select("id", "total", F.explode("bands").alias("key"))
    sizes = keyed.groupBy("key").agg(F.count(F.lit(1)).alias("size"), F.min(F.struct("id", "total")).alias("head")).where("size > 1")
    buckets = materialize(keyed.join(sizes, "key"), "buckets")
    needed = buckets.select("id").distinct()
    own = only_listed(signed.select("id", "node", "text", "weights"), needed).join(nodes.select("id", "node").join(needed, "id"), ["id", "node"])
    # One row for each node; an identifier that repeats may name several.
    held = materialize(own.dropDuplicates(["id", "node"]).select("id", "text", "weights"), "texts", compression="zstd")
    links = materialize(verified(likely(first_pairs(buckets), threshold), held, threshold).select("a", "b"), "edges")
    labels = components(links)
    more = materialize(verified(likely(small_pairs(placed_nodes(buckets, labels)), threshold), held, threshold).select("a", "b"), "edges")
    links = links.unionByName(more)
    if not more.isEmpty():
        labels = components(links)
    more = materialize(rest_links(placed_nodes(buckets, labels), nodes, held, threshold), "edges")
    if not more.isEmpty():
        labels = components(links.unionByName(more))
    release(held, buckets)
    return nodes, labels


def near_classes(docs: DataFrame, threshold: float = THRESHOLD, bands: int = BANDS, rows: int = ROWS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per identifier: id_col, class_id (least identifier of the class), class_size."""
    texts = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).cast("string").alias("text"))
    signed = signatures(texts, bands, rows)
    nodes, labels = near_labels(signed, threshold)
    # Identifiers are nodes too: one that repeats with other words joins the classes of both.
    same = signed.select("id", "node").join(nodes.select("node", F.col("id").alias("head")), "node").select("id", "head")
    of = same.join(labels.withColumnRenamed("id", "head"), "head", "left").select("id", F.coalesce("label", "head").alias("label"))
    classes = of.groupBy("id").agg(F.min("label").alias("class_id"))
    every = texts.select("id").distinct().join(classes, "id", "left").select("id", F.coalesce("class_id", "id").alias("class_id"))
    every = materialize(every, "classes")
    release(signed, nodes)
    # Members of a hot class are dealt over salts, each with a copy of its size.
    salts = 16
    sizes = every.groupBy("class_id").agg(F.count(F.lit(1)).alias("class_size")).where("class_size > 1")
    sizes = sizes.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    out = every.withColumn("salt", F.pmod(F.xxhash64("id"), F.lit(salts)).cast("int")).join(sizes, ["class_id", "salt"], "left")
    return out.select(F.col("id").alias(id_col), "class_id", F.coalesce("class_size", F.lit(1)).alias("class_size"))


def drop_near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` whose identifier stands for its class, with all their columns; null identifiers stay."""
    key = working_name(docs, "_near_id")
    gone = near_classes(docs.select(id_col, text_col), id_col=id_col, text_col=text_col).where(F.col(id_col) != F.col("class_id")).select(F.col(id_col).alias(key))
    return docs.join(gone, docs[id_col] == F.col(key), "left_anti")


def op7_near_dedup(spark, sf_dir: str) -> DataFrame:
    """Whole ``documents``: doc_id, class_id (least doc_id of its near-duplicate class), class_size, kept. Null and empty
    texts are classes of their own; a null doc_id is one row with null class_id and kept."""
    classes = near_classes(documents(spark, sf_dir))
    return classes.select("doc_id", "class_id", "class_size", (F.col("doc_id") == F.col("class_id")).alias("kept"))


def brute_force_classes(texts: list[str | None], threshold: float = THRESHOLD) -> list[int]:
    """Class of each text (its least position) by comparing all pairs with exact frequencies, for tests."""
    sets = [text_shingles(t) for t in texts]
    known: dict[int, int] = {}
    for s, _ in sets:
        for x in s.tolist():
            known[x] = known.get(x, 0) + 1
    idf = lambda s: 1 + np.log((1 + len(texts)) / (1 + np.array([known[x] for x in s.tolist()], np.float64)))
    weighed = [(s, (c.astype(np.float32) * idf(s).astype(np.float32)).astype(np.float64)) for s, c in sets]
    label = list(range(len(texts)))
    for i in range(len(texts)):
        for j in range(i):
            if label[i] != label[j] and weighted_jaccard(weighed[i], weighed[j]) >= threshold:
                low, high = sorted((label[i], label[j]))
                label = [low if x == high else x for x in label]
    return label
