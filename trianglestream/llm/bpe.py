"""Byte-level BPE over a global shuffle of distinct words.

Pass one splits texts into pre-tokens and cuts each task's documents into blocks.
A block keeps its pre-tokens in order as indexes into the block's own distinct
words (compressed), and hands those words on in packs chosen by a word hash. All
packs of one hash class meet in one place, where each distinct word is encoded
once; the ids go back to their blocks, and blocks are put together again by
position. Only distinct words of blocks are shuffled by word, so frequent words
cost one entry a block. Decoding joins ids and the token-byte table by rank, which
is a table's row number there, so the join is one Arrow ``take`` a batch; the
vocabulary file bounds the table.

``encode_exploded`` and ``decode_exploded`` are the same as rows: a row for each
pre-token and position, a distinct-word table, joins by word and by rank. They give
equal results and move several times the input, so the packed form is the main path.

Null texts count as empty and give no ids; identifiers may be null or repeat, each
row is encoded on its own, ties and repeated rows too; very long texts are encoded
whole; an empty table gives no rows; only identifier and text are read, so other
columns cannot clash. Any Unicode text round-trips exactly.
"""

from __future__ import annotations

import base64
import heapq
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from .common import bucketed, documents, drop_bucketed, materialize, pack_numbers, squeeze, expand, read_batches, tidied, unpack_numbers

#: White space as the Unicode property has it; fixed values.
WHITE_SPACE = "\\t\\n\\x0b\\x0c\\r\\x20\\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"
BODY = 1 << 30


def explicit_spaces(pattern: str) -> str:
    """The pattern with ``\\s`` and ``\\S`` written out, so that no library's own notion of space counts."""
    return pattern.replace(r"[^\s", f"[^{WHITE_SPACE}").replace(r"\S", f"[^{WHITE_SPACE}]").replace(r"\s", f"[{WHITE_SPACE}]")


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in lines if line.strip())}


def merge_short(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Join the pair of least rank, leftmost first, until no pair has a rank."""
    parts = [piece[i : i + 1] for i in range(len(piece))]
    none = 1 << 60
    pairs = [ranks.get(a + b, none) for a, b in zip(parts, parts[1:])]
    while pairs:
        best = min(pairs)
        if best == none:
            break
        i = pairs.index(best)
        parts[i : i + 2] = [parts[i] + parts[i + 1]]
        del pairs[i]
        if i < len(pairs):
            pairs[i] = ranks.get(parts[i] + parts[i + 1], none)
        if i:
            pairs[i - 1] = ranks.get(parts[i - 1] + parts[i], none)
    return [ranks[p] for p in parts]


def merge_long(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """The same outcome with a heap of pairs over a linked list, for long pieces."""
    n = len(piece)
    end, after, before = list(range(1, n + 1)), list(range(1, n + 1)), list(range(-1, n - 1))
    alive = [True] * n
    heap = []

    def offer(i):
        j = after[i]
        if j < n:
            rank = ranks.get(piece[i : end[j]])
            if rank is not None:
                heapq.heappush(heap, (rank, i, end[i], end[j]))

    for i in range(n - 1):
        offer(i)
    while heap:
        _, i, middle, stop = heapq.heappop(heap)
        if not alive[i] or end[i] != middle or after[i] >= n or end[after[i]] != stop:
            continue
        j = after[i]
        alive[j], end[i], after[i] = False, stop, after[j]
        if after[j] < n:
            before[after[j]] = i
        offer(i)
        if before[i] >= 0:
            offer(before[i])
    return [ranks[piece[i : end[i]]] for i in range(n) if alive[i]]


def encode_word(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    whole = ranks.get(piece)
    if whole is not None:
        return [whole]
    return merge_short(piece, ranks) if len(piece) <= 64 else merge_long(piece, ranks)


def pack_words(words: list[bytes]) -> tuple[bytes, bytes]:
    return squeeze(b"".join(words)), pack_numbers(np.fromiter(map(len, words), np.int64, len(words)))


def unpack_words(data: bytes, lengths: bytes) -> list[bytes]:
    text, ends = expand(data), np.cumsum(unpack_numbers(lengths)).tolist()
    return [text[a:b] for a, b in zip([0, *ends], ends)]


BLOCK_SCHEMA = T.StructType([
    T.StructField("block", T.LongType()), T.StructField("pack", T.IntegerType()), T.StructField("docs", T.ArrayType(T.LongType())),
    T.StructField("data", T.BinaryType()), T.StructField("ends", T.BinaryType()), T.StructField("packs", T.BinaryType()),
])
ARROW_BLOCK = pa.schema([("block", pa.int64()), ("pack", pa.int32()), ("docs", pa.list_(pa.int64())), ("data", pa.binary()), ("ends", pa.binary()), ("packs", pa.binary())])


def split_kernel(pattern: str, packs: int, block_chars: int):
    """Documents to blocks: one body row (pack BODY) and one row for each pack that has words."""

    def run(batches):
        import regex
        from pyspark import TaskContext

        find = regex.compile(pattern).findall
        partition, made = TaskContext.get().partitionId(), 0
        ids, ends, parts, chars, count = [], [], [], 0, 0

        def flush():
            tokens = pa.chunked_array(parts, pa.string()).combine_chunks() if parts else pa.array([], pa.string())
            coded = tokens.dictionary_encode()
            words = [w.encode() for w in coded.dictionary.to_pylist()]
            index = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)
            often = np.bincount(index, minlength=len(words)).tolist()
            # Numbers follow frequency, so that small ones are common; equals lie in order of their letters.
            order = np.array(sorted(range(len(words)), key=lambda i: (-often[i], words[i])), np.int64)
            rank = np.empty(len(words), np.int64)
            rank[order] = np.arange(len(words))
            pack_of = np.array([zlib.crc32(words[i]) % packs for i in order], np.int64)
            by_pack = np.argsort(pack_of, kind="stable")
            block = (partition << 32) | made
            rows = {k: [] for k in ARROW_BLOCK.names}

            def add(**row):
                for k in rows:
                    rows[k].append(row.get(k))

            sorted_pack = pack_of[by_pack]
            cuts = [0, *(np.flatnonzero(np.diff(sorted_pack)) + 1).tolist(), len(words)] if words else [0]
            for a, b in zip(cuts, cuts[1:]):
                data, lengths = pack_words([words[i] for i in order[by_pack[a:b]]])
                add(block=block, pack=int(sorted_pack[a]), data=data, ends=lengths)
            add(block=block, pack=BODY, docs=list(ids), data=pack_numbers(rank[index]), ends=pack_numbers(np.array(ends, np.int64)), packs=pack_numbers(pack_of))
            return pa.RecordBatch.from_pydict(rows, schema=ARROW_BLOCK)

        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                found = find(text.as_py() or "")
                parts.append(pa.array(found, pa.string()))
                count += len(found)
                ids.append(doc)
                ends.append(count)
                chars += sum(map(len, found))
                if chars >= block_chars:
                    yield flush()
                    made += 1
                    ids, ends, parts, chars, count = [], [], [], 0, 0
        if ids:
            yield flush()

    return run


def encode_kernel(shared_ranks):
    """Packs to ids: words sorted by pack, each distinct word of a pack encoded once."""

    def run(batches):
        ranks = shared_ranks.value
        known, current = {}, None
        for batch in batches:
            rows = {k: [] for k in ("block", "pack", "data", "ends")}
            for block, pack, data, lengths in zip(*[batch.column(c).to_pylist() for c in ("block", "pack", "data", "ends")]):
                if pack != current:
                    known, current = {}, pack
                ids, sizes = [], []
                for word in unpack_words(data, lengths):
                    got = known.get(word)
                    if got is None:
                        got = known[word] = encode_word(word, ranks)
                    ids += got
                    sizes.append(len(got))
                made = {"block": block, "pack": pack, "data": pack_numbers(np.array(ids, np.int64)), "ends": pack_numbers(np.array(sizes, np.int64))}
                for k in rows:
                    rows[k].append(made[k])
            yield pa.RecordBatch.from_pydict(rows, schema=pa.schema([ARROW_BLOCK.field(k) for k in rows]))

    return run


def gather_runs(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Positions of the runs (start, length), one after another."""
    first = np.cumsum(lengths) - lengths
    return np.repeat(starts - first, lengths) + np.arange(int(lengths.sum()))


def assemble_kernel(batches):
    """Block bodies with their coded packs: put each document's ids in order."""
    for batch in (b.slice(at, 1) for b in batches for at in range(len(b))):
        row = batch.to_pylist()[0]
        coded = sorted(row["coded"] or [], key=lambda c: c["pack"])
        flat = np.concatenate([unpack_numbers(c["data"]) for c in coded]) if coded else np.zeros(0, np.int64)
        by_pack = np.concatenate([unpack_numbers(c["ends"]) for c in coded]) if coded else np.zeros(0, np.int64)
        place = np.argsort(unpack_numbers(row["packs"]), kind="stable")
        size, start = np.empty_like(by_pack), np.empty_like(by_pack)
        size[place], start[place] = by_pack, np.cumsum(by_pack) - by_pack
        tokens, ends = unpack_numbers(row["data"]), unpack_numbers(row["ends"])
        begin = 0
        for at in range(0, len(row["docs"]), 256):
            part = ends[at : at + 256]
            own = tokens[begin : part[-1]]
            stream = flat[gather_runs(start[own], size[own])].astype(np.int32)
            total = np.concatenate([[0], np.cumsum(size[own])])
            cuts = np.concatenate([[0], total[part - begin]]).astype(np.int32)
            begin = int(part[-1])
            lists = pa.ListArray.from_arrays(pa.array(cuts), pa.array(stream))
            yield pa.RecordBatch.from_arrays([pa.array(row["docs"][at : at + 256], pa.int64()), lists], ["id", "ids"])


def encode(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", packs: int | None = None, block_chars: int = 8_000_000) -> tuple[DataFrame, tuple]:
    """(id_col, ids) by the rank file at ``path``, one row for each row of ``docs``, and the working table behind it, which
    ``drop_bucketed`` deletes once the rows are read."""
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(load_ranks(path))
    packs = packs or max(16, int(spark.conf.get("spark.sql.shuffle.partitions")))
    rows = docs.select(F.col(id_col).cast("bigint"), F.col(text_col).cast("string"))
    blocks, name = bucketed(rows.mapInArrow(tidied(split_kernel(explicit_spaces(pattern), packs, block_chars)), BLOCK_SCHEMA), packs)
    words = blocks.where(F.col("pack") != BODY).select("block", "pack", "data", "ends").repartition("pack").sortWithinPartitions("pack")
    coded = words.mapInArrow(tidied(encode_kernel(shared)), "block bigint, pack int, data binary, ends binary")
    by_block = coded.repartition(packs, "block").groupBy("block").agg(F.collect_list(F.struct("pack", "data", "ends")).alias("coded"))
    bodies = blocks.where(F.col("pack") == BODY).select("block", "docs", "data", "ends", "packs")
    together = bodies.join(by_block.hint("shuffle_hash"), "block", "left")
    schema = T.StructType([T.StructField("id", T.LongType()), T.StructField("ids", T.ArrayType(T.IntegerType()))])
    return together.mapInArrow(tidied(assemble_kernel), schema).withColumnRenamed("id", id_col), (blocks, name)


def decode_kernel(shared_table, most_tokens: int = 1 << 22):
    """Ids to bytes by one join with the token-byte table for each batch of at most 512 rows and about ``most_tokens`` ids."""

    def run(batches):
        table = shared_table.value
        for batch in read_batches(batches, 512):
            size = batch.column("ids").value_lengths().to_numpy(zero_copy_only=False).cumsum()
            cuts = np.unique(np.append(np.searchsorted(size, np.arange(1, int(size[-1]) // most_tokens + 1) * most_tokens) + 1, len(batch))) if len(batch) else []
            for part in (batch.slice(a, b - a) for a, b in zip([0, *cuts], cuts)):
                lists = part.column("ids")
                ends = lists.offsets.to_numpy()
                tokens = table.take(lists.values.slice(ends[0], ends[-1] - ends[0]).cast(pa.int32()))
                at = np.frombuffer(tokens.buffers()[1], np.int64)[tokens.offset : tokens.offset + len(tokens) + 1] if len(tokens) else np.zeros(1, np.int64)
                data = tokens.buffers()[2] if len(tokens) else pa.py_buffer(b"")
                joined = pa.Array.from_buffers(pa.large_binary(), len(lists), [None, pa.py_buffer(np.ascontiguousarray(at[ends - ends[0]])), data])
                yield part.append_column("decoded", joined.cast(pa.binary()))

    return run


def decode(encoded: DataFrame, path: str) -> DataFrame:
    """``encoded`` with a column decoded (bytes)."""
    by_rank = {rank: token for token, rank in load_ranks(path).items()}
    table = pa.array([by_rank.get(i) for i in range(max(by_rank) + 1)], pa.large_binary())
    shared = encoded.sparkSession.sparkContext.broadcast(table)
    schema = T.StructType([*encoded.schema.fields, T.StructField("decoded", T.BinaryType())])
    return encoded.mapInArrow(tidied(decode_kernel(shared)), schema)


def exploded_words(docs: DataFrame, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(row, id_col, position, word): every pre-token of every row with its place; a row without any has one null word."""
    written = explicit_spaces(pattern)

    def run(batches):
        import regex

        find = regex.compile(written).findall
        for batch in read_batches(batches, 64):
            for row, doc, text in zip(*[batch.column(c).to_pylist() for c in range(3)]):
                words = [w.encode() for w in find(text or "")] or [None]
                for at in range(0, len(words), 1 << 16):
                    part = words[at : at + (1 << 16)]
                    yield pa.RecordBatch.from_arrays([pa.array([row] * len(part), pa.int64()), pa.array([doc] * len(part), pa.int64()), pa.array(np.arange(at, at + len(part))), pa.array(part, pa.binary())], ["row", "id", "position", "word"])

    rows = docs.select(F.monotonically_increasing_id().alias("row"), F.col(id_col).cast("bigint").alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(tidied(run), "row bigint, id bigint, position bigint, word binary").withColumnRenamed("id", id_col)


def encode_exploded(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id_col, ids) as ``encode``, by rows: distinct words are encoded once and joined back to their positions."""
    shared = docs.sparkSession.sparkContext.broadcast(load_ranks(path))

    def run(batches):
        ranks = shared.value
        for batch in read_batches(batches, 4096):
            yield batch.append_column("coded", pa.array([encode_word(w, ranks) for w in batch.column(0).to_pylist()], pa.list_(pa.int32())))

    words = materialize(exploded_words(docs, pattern, id_col, text_col), "words", compression="zstd")
    coded = words.where("word is not null").select("word").distinct().mapInArrow(tidied(run), "word binary, coded array<int>")
    places = words.join(coded, "word", "left").select("row", id_col, "position", F.coalesce("coded", F.array().cast("array<int>")).alias("coded"))
    ids = F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("position", "coded"))), lambda x: x["coded"]))
    return places.groupBy("row", id_col).agg(ids.alias("ids")).drop("row")


def decode_exploded(encoded: DataFrame, path: str) -> DataFrame:
    """``encoded`` with a column decoded, by a join of exploded ids with the token-byte table (rank, token)."""
    spark = encoded.sparkSession
    table = spark.createDataFrame([(rank, token.decode("latin-1")) for token, rank in load_ranks(path).items()], "rank int, token string")
    rows = materialize(encoded.withColumn("row", F.monotonically_increasing_id()), "encoded")
    each = rows.select("row", F.posexplode("ids").alias("position", "rank")).join(F.broadcast(table), "rank")
    text = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("position", "token"))), lambda x: x["token"]), "")
    joined = rows.join(each.groupBy("row").agg(text.alias("decoded")), "row", "left")
    return joined.withColumn("decoded", F.encode(F.coalesce("decoded", F.lit("")), "ISO-8859-1")).drop("row")


def token_digests(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256), written, as the working table goes with this call."""
    coded, working = encode(docs, path, pattern)
    digests = decode(coded, path).select(
        "doc_id",
        F.size("ids").cast("bigint").alias("n_tokens"),
        F.sha2(F.array_join("ids", ","), 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )
    written = materialize(digests, "digests")
    drop_bucketed(*working)
    return written


def op5_byte_bpe(spark, sf_dir: str, vocabulary: str = "byte_bpe_multi_50k.tiktoken") -> DataFrame:
    """Whole ``documents``: doc_id, n_tokens, ids_sha256, decoded_sha256, one row for each row."""
    import public_tokenizers

    return token_digests(documents(spark, sf_dir), public_tokenizers.path(vocabulary), public_tokenizers.PATTERN)
