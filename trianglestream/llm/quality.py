"""Quality classifier: hashed word n-grams, logistic regression by follow-the-regularised-leader.

Training reads at most ``most_rows`` labelled documents, and of these, in the order of a
seeded hash, as many as fit ``most_bytes``; every size draws alike. It runs the per-coordinate proximal update in numpy on
the driver. Scoring streams Arrow batches: words are mapped to hashed one- and
two-gram slots and a document's score is one sparse dot product through a logistic.

Tokens are words in lower case and single marks; words written in capitals, words
beside marks and repeated words also give a shape token, so that the noise that
spoils a text is seen in words never met before. Features are scaled by the square root of a
document's token count. Null and empty texts have the bias alone. Null labels are
not learnt from; if none is left, every score is the prior 0.5. Every row is scored on
its own, so ties, repeated rows and null identifiers change nothing; very long texts are
scored whole; an empty table gives no rows; only identifier and text are read, so other
columns cannot clash.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F, types as T

from .common import documents, tidied, unit_hash

BITS = 18
GOLDEN = np.uint64(0x9E3779B97F4A7C15)


def word_tokens(text: str):
    import re

    return re.findall(r"[^\W_]+|[^\w\s]+|_+", text)


def shape_of(word: str) -> str:
    if not word[0].isalnum():
        return f"<mark{min(len(word), 3)}>"
    if word.isdigit():
        return "<number>"
    if len(word) > 1 and word.isupper():
        return "<capitals>"
    return "<long>" if len(word) > 18 else "<word>"


def hashed_features(texts: list[str], known: dict[str, tuple[int, int]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, slot, value) of all texts; ``known`` caches the hashes of words and is bounded."""
    if len(known) > 300_000:
        known.clear()
    word_ids, shape_ids, sizes = [], [], []
    for text in texts:
        tokens = word_tokens(text)
        for w in tokens:
            pair = known.get(w)
            if pair is None:
                pair = known[w] = (zlib.crc32(w.lower().encode()), zlib.crc32(shape_of(w).encode()))
            word_ids.append(pair[0])
            shape_ids.append(pair[1])
        sizes.append(len(tokens))
    word, shape, size = np.array(word_ids, np.uint64), np.array(shape_ids, np.uint64), np.array(sizes, np.int64)
    row = np.repeat(np.arange(len(texts)), size)
    inner = np.ones(len(word), bool)
    inner[np.cumsum(size)[size > 0] - 1] = False
    at = np.flatnonzero(inner)
    same = np.uint64(zlib.crc32(b"<again>"))
    again = at[word[at] == word[at + 1]]
    mixed = [
        (row, word * GOLDEN),
        (row, shape * GOLDEN),
        (row[at], (word[at] * GOLDEN + word[at + 1] + np.uint64(1)) * GOLDEN),
        (row[at], (shape[at] * GOLDEN + shape[at + 1] + np.uint64(2)) * GOLDEN),
        (row[again], np.full(len(again), same) * GOLDEN),
    ]
    rows = np.concatenate([r for r, _ in mixed])
    slots = np.concatenate([(h >> np.uint64(64 - BITS)).astype(np.int64) for _, h in mixed])
    keys, counts = np.unique(rows * (1 << BITS) + slots, return_counts=True)
    rows, slots = keys >> BITS, keys & ((1 << BITS) - 1)
    return rows, slots, np.log1p(counts) / np.sqrt(np.maximum(size[rows], 1)) * 4


@dataclass
class QualityModel:
    weights: np.ndarray
    bias: float

    def scores(self, texts: list[str], known: dict) -> np.ndarray:
        rows, slots, values = hashed_features(texts, known)
        dot = np.bincount(rows, weights=self.weights[slots].astype(np.float64) * values, minlength=len(texts))
        return 1 / (1 + np.exp(-np.clip(dot + self.bias, -30, 30)))


def train_ftrl(texts: list[str], labels: np.ndarray, passes: int = 3, alpha: float = 0.3, beta: float = 1.0, l1: float = 0.02, l2: float = 0.5, seed: int = 5) -> QualityModel:
    """Per-coordinate follow-the-regularised-leader over single documents; the rarer label weighs more."""
    z, n = np.zeros(1 << BITS), np.zeros(1 << BITS)
    z_bias = n_bias = 0.0
    if not len(texts):
        return QualityModel(np.zeros(1 << BITS, np.float32), 0.0)
    parts, cuts, known = [], [0], {}
    for a in range(0, len(texts), 200):  # small pieces, as the driver holds only slots and values
        rows, own, value = hashed_features(texts[a : a + 200], known)
        parts.append((own.astype(np.int32), value.astype(np.float32)))
        cuts += (cuts[-1] + np.cumsum(np.bincount(rows, minlength=len(texts[a : a + 200])))).tolist()
    slots, values = (np.concatenate(c) for c in zip(*parts))
    known.clear()
    share = labels.mean()
    weight_of = {1: min(1.0, (1 - share) / share) if share else 1.0, 0: min(1.0, share / (1 - share)) if share < 1 else 1.0}
    rng = np.random.default_rng(seed)

    def leader(zs, ns):
        return np.where(np.abs(zs) <= l1, 0.0, -(zs - np.sign(zs) * l1) / ((beta + np.sqrt(ns)) / alpha + l2))

    for _ in range(passes):
        for i in rng.permutation(len(texts)):
            own, value = slots[cuts[i] : cuts[i + 1]], values[cuts[i] : cuts[i + 1]]
            w, b = leader(z[own], n[own]), float(leader(np.float64(z_bias), np.float64(n_bias)))
            error = (1 / (1 + np.exp(-np.clip(w @ value + b, -30, 30))) - labels[i]) * weight_of[int(labels[i])]
            g = error * value
            z[own] += g - (np.sqrt(n[own] + g * g) - np.sqrt(n[own])) / alpha * w
            n[own] += g * g
            z_bias += error - (np.sqrt(n_bias + error * error) - np.sqrt(n_bias)) / alpha * b
            n_bias += error * error
    return QualityModel(leader(z, n).astype(np.float32), float(leader(np.float64(z_bias), np.float64(n_bias))))


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, learn, most_rows: int, seed: int = 3, most_bytes: int = 32 << 20) -> tuple[list[str], np.ndarray]:
    """At most ``most_rows`` labelled texts that ``learn`` (a Column of doc_id) admits, by least seeded hash, of which as
    many reach the driver as take ``most_bytes`` together."""
    rows = labels.select(F.col("doc_id").cast("bigint").alias("key"), F.col(label).cast("int").alias("label")).where(F.col("label").isin(0, 1) & learn(F.col("key")))
    drawn = rows.withColumn("u", unit_hash("key", seed=seed)).orderBy("u", "key", "label").limit(most_rows)
    texts = docs.select(F.col("doc_id").cast("bigint").alias("key"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    chosen = texts.join(F.broadcast(drawn), "key").orderBy("u", "key", "label").limit(most_rows)
    upto = Window.orderBy("u", "key", "label", F.xxhash64("text")).rowsBetween(Window.unboundedPreceding, 0)  # most_rows rows
    got = chosen.withColumn("bytes", F.sum(F.octet_length("text")).over(upto)).where(F.col("bytes") <= most_bytes).select("text", "label").toArrow()
    return got["text"].to_pylist(), got["label"].to_numpy().astype(np.float64)


def score_kernel(shared):
    def run(batches):
        model, known = shared.value, {}
        for batch in batches:
            for at in range(0, len(batch), 256):
                part = batch.slice(at, 256)
                texts = [x or "" for x in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(model.scores(texts, known), pa.float64())], ["id", "score"])

    return run


def score_quality(docs: DataFrame, model: QualityModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: id_col, score."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = T.StructType([T.StructField("id", T.LongType()), T.StructField("score", T.DoubleType())])
    return docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).cast("string")).mapInArrow(tidied(score_kernel(shared)), schema).withColumnRenamed("id", id_col)


def op4_quality(spark, sf_dir: str, most_rows: int = 4000) -> DataFrame:
    """Whole ``documents``: doc_id, held_out, score, predicted, one row for each; a null doc_id is not held out."""
    docs, labels = documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet")

    def fold(key):
        return F.crc32(key.cast("string").cast("binary")) % 4 == 2

    model = train_ftrl(*labelled_sample(docs, labels, "quality", lambda key: ~fold(key), most_rows))
    scored = score_quality(docs, model)
    return scored.select("doc_id", F.coalesce(fold(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))
