"""Exact dedup over a log-structured merge index, in DataFrame operations only.

A flush deals the scan's tasks over memtables; each task writes one run of (digest, rank)
rows sorted by digest and marked with its memtable, with a Parquet Bloom filter. Compaction
merges tier by tier: ``fanout`` tables of a level become one of the next, which keeps for
each digest the smallest rank, its row and the number of rows, until one level is left.

Digests that occur more than once are hits, and their bytes are verified. A bitmap of the
hits' digests, of bounded size, is probed by every document before its text is moved, so
only likely hits send bytes; within a digest the least and the greatest normalised text
must be the same string, which partial aggregation decides without gathering a group in
one task. Digests that fail are split by their full text, so results stay exact for any
digest function.

Rank is an order-reversing map of the identifier where the largest identifier is kept, so
"smallest rank" always names the row that stays. Null texts count as empty. Rows with a
null identifier rank behind all others. Of rows that repeat an identifier with the same
text, one stays. No step joins on identifiers, so null or repeated ones gather nowhere.
Empty tables give empty results; extra columns, clashing names too, pass unchanged.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from .common import ascii_lower, documents, materialize, release, working_name

#: Rank of a null identifier: behind every other.
LAST_RANK = (1 << 63) - 1
BLOOM = {"parquet.bloom.filter.enabled#digest": "true", "parquet.bloom.filter.adaptive.enabled": "true"}


def normalise(text: Column) -> Column:
    return ascii_lower(F.coalesce(text.cast("string"), F.lit("")))


def sha256(norm: Column) -> Column:
    return F.unhex(F.sha2(norm, 256))


def bitmap_bits(expected: int, least: int = 1 << 20, most: int = 1 << 27) -> int:
    """Bits of a filter for ``expected`` digests: sixteen for each, up to a bound of 16 MB."""
    bits = least
    while bits < most and bits < 16 * expected:
        bits *= 2
    return bits


def bitmap_filter(digests: DataFrame, bits: int) -> DataFrame:
    """(page, part): the filter of ``digests`` (digest), in pages of 32768 bits; at most ``bits`` / 32768 rows."""
    place = F.pmod(F.xxhash64("digest"), F.lit(bits))
    return digests.select(place.alias("p")).groupBy(F.floor(F.col("p") / 32768).alias("page")).agg(F.bitmap_construct_agg(F.col("p") % 32768).alias("part"))


def probed(rows: DataFrame, pages: DataFrame, bits: int) -> DataFrame:
    """Those of ``rows`` (digest, ..) whose digest the filter may hold. ``pages`` is bounded, so it may be broadcast."""
    place = F.pmod(F.xxhash64("digest"), F.lit(bits))
    spot = rows.withColumn("_place", place).withColumn("_page", F.floor(F.col("_place") / 32768))
    met = spot.join(F.broadcast(pages.withColumnsRenamed({"page": "_page", "part": "_part"})), "_page")
    byte = F.conv(F.hex(F.substring("_part", (F.floor((F.col("_place") % 32768) / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
    bit = F.getbit(byte, (F.col("_place") % 8).cast("int"))
    return met.where(bit == 1).select(*rows.columns)


class DigestIndex:
    """Runs by memtable and their tiered compaction. ``keep``: which identifier of equal texts stays."""

    def __init__(self, keep: str = "largest", digest=sha256, memtables: int = 8, fanout: int = 4, most_hot: int = 10_000):
        self.keep, self.digest, self.memtables, self.fanout, self.most_hot = keep, digest, memtables, fanout, most_hot
        self.runs, self.level = [], None

    def rank(self, identifier: Column) -> Column:
        rank = F.bitwise_not(identifier) if self.keep == "largest" else identifier
        return F.coalesce(rank, F.lit(LAST_RANK))

    def rows_of(self, docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
        norm = normalise(F.col(text_col))
        return docs.select(F.col(id_col).cast("bigint").alias("id"), self.digest(norm).alias("digest"), norm.alias("norm"))

    def flush(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
        """Each scan task writes one sorted run: row number, identifier, digest, rank, memtable."""
        rows = self.rows_of(docs, id_col, text_col).select(F.monotonically_increasing_id().alias("row"), "id", "digest", self.rank(F.col("id")).alias("rank"))
        first = len(self.runs) * self.memtables
        rows = rows.withColumn("memtable", (F.lit(first) + F.pmod(F.spark_partition_id(), F.lit(self.memtables))).cast("int"))
        # Rows are numbered within their flush; the flush's place tells them apart in the index.
        rows = rows.withColumn("row", F.struct(F.lit(len(self.runs)).alias("flush"), F.col("row").alias("row")))
        run = materialize(rows.sortWithinPartitions("memtable", "digest", "rank"), "runs", **BLOOM)
        self.runs.append(run)
        return run

    def all_runs(self) -> DataFrame:
        rows = self.runs[0]
        for more in self.runs[1:]:
            rows = rows.unionByName(more)
        return rows

    def compact(self) -> DataFrame:
        """Merge the runs tier by tier: per digest the smallest rank, its row, and the number of rows."""
        tables = len(self.runs) * self.memtables
        current = self.all_runs().select("digest", F.struct("rank", "row", "id").alias("first"), F.lit(1).cast("bigint").alias("size"), "memtable")
        while True:
            merged = current.groupBy("digest", F.floor(F.col("memtable") / self.fanout).cast("int").alias("memtable")).agg(F.min("first").alias("first"), F.sum("size").alias("size"))
            tables = -(-tables // self.fanout)
            level = materialize(merged.sortWithinPartitions("digest"), "level", **BLOOM)
            if self.level is not None:
                release(self.level)
            self.level = current = level
            if tables <= 1:
                self.level = level.select("digest", F.col("first.id").alias("keep_id"), F.col("first.row").alias("keep_row"), "size")
                return self.level

    def hits(self) -> DataFrame:
        """Rows whose digest was seen before or after."""
        return self.all_runs().join(self.level.where("size > 1"), "digest")

    def failing(self, docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
        """(digest) of hits that do not all have the same bytes. Only documents that pass the filter send theirs."""
        repeated = self.level.where("size > 1").select("digest")
        bits = bitmap_bits(repeated.count())
        pages = materialize(bitmap_filter(repeated, bits), "filter")
        likely = probed(self.rows_of(docs, id_col, text_col).select("digest", "norm"), pages, bits)
        wrong = likely.groupBy("digest").agg(F.min("norm").alias("low"), F.max("norm").alias("high")).where("low <> high").select("digest")
        wrong = materialize(wrong, "failing")
        release(pages)
        return wrong

    def resolve(self, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
        """Every row of ``docs``, flushed before, with the identifier that stays, after byte verification of all hits."""
        # Sizes add up to the number of rows, so at most ``most_hot`` digests are over the line: their rows are joined by a
        # broadcast of that bound and do not gather in one task.
        whole = self.level.agg(F.sum("size")).first()[0] or 0
        line = max(1000, whole // self.most_hot)
        hot, runs = F.broadcast(self.level.where(F.col("size") > line)), self.all_runs()
        cold = runs.join(hot.select("digest"), "digest", "left_anti").join(self.level.where(F.col("size") <= line), "digest")
        rows = runs.join(hot, "digest").unionByName(cold).select("id", "digest", "keep_id", (F.col("row") == F.col("keep_row")).alias("kept"), "size")
        wrong = self.failing(docs, id_col, text_col)
        if wrong.isEmpty():
            release(wrong)
            return rows
        # Colliding digests: their documents are split by whole text, from the table itself.
        split = self.rows_of(docs, id_col, text_col).join(wrong, "digest").select("id", "digest", "norm", self.rank(F.col("id")).alias("rank"), F.monotonically_increasing_id().alias("row"))
        split = materialize(split, "split")
        best = split.groupBy("digest", "norm").agg(F.min(F.struct("rank", "row", "id")).alias("first"), F.count(F.lit(1)).alias("size"))
        again = split.join(best, ["digest", "norm"]).select("id", "digest", F.col("first.id").alias("keep_id"), (F.col("row") == F.col("first.row")).alias("kept"), "size")
        return rows.join(wrong, "digest", "left_anti").unionByName(again)


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep: str = "largest", digest=sha256) -> DataFrame:
    """One row per row of ``docs``: identifier, the one that stays, group size, whether this row stays, digest."""
    index = DigestIndex(keep, digest)
    index.flush(docs, id_col, text_col)
    index.compact()
    rows = index.resolve(docs, id_col, text_col)
    return rows.select(F.col("id").alias(id_col), "keep_id", F.col("size").cast("bigint").alias("group_size"), "kept", "digest")


def drop_exact_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that stay, with all their columns; one row for each text, a null identifier's too."""
    key, norm = working_name(docs, "_copy_id"), working_name(docs, "_copy")
    groups = exact_groups(docs, id_col, text_col).select(F.col(id_col).alias(key), "digest", "kept")
    again = groups.groupBy(key).agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > 1)
    if again.isEmpty():
        # Most documents stay: the dropped identifiers are the small side.
        gone = groups.where(~F.col("kept")).select(key)
        return docs.join(gone, docs[id_col].eqNullSafe(gone[key]), "left_anti")
    # An identifier that occurs again tells rows apart only together with its text.
    rows = docs.withColumn(norm, sha256(normalise(F.col(text_col))))
    kept = groups.where("kept").select(key, F.col("digest").alias("kept_digest")).distinct()
    stay = rows.join(kept, rows[id_col].eqNullSafe(kept[key]) & (rows[norm] == kept["kept_digest"]), "left_semi")
    # Rows that differ elsewhere only: the least by their other columns stays, whatever the order of the scan.
    order = Window.partitionBy(F.col(id_col), F.col(norm)).orderBy(F.to_json(F.struct(*[F.col(f"`{c}`") for c in docs.columns])))
    nth = working_name(stay, "_nth")
    return stay.withColumn(nth, F.row_number().over(order)).where(F.col(nth) == 1).drop(nth, norm)


def op2_exact_dedup(spark, sf_dir: str) -> DataFrame:
    """Whole ``documents``: doc_id, keep_id, group_size, kept, text_sha256, one row for each row, dropped ones too."""
    groups = exact_groups(documents(spark, sf_dir))
    return groups.select("doc_id", "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256"))


OP2_SQL = """
WITH norm AS (
  SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS body FROM documents
), best AS (SELECT body, max(doc_id) AS keep_id, count(*) AS group_size FROM norm GROUP BY body)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, sha256(body) AS text_sha256 FROM norm JOIN best USING (body)
"""
