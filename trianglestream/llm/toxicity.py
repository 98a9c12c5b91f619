"""Toxicity: a bidirectional gated recurrent network with attention pooling, in numpy.

A word is its hashed embedding plus the hashed embeddings of its character
trigrams; words longer than ``WORD_BYTES`` are read as several pieces, so no text
is cut. Windows of ``WINDOW`` words overlap by half and cover every word. The
network scores each window; a document's score is a logistic of its most toxic
window. Training sees only document labels: it starts from the windows whose words
speak most for their label, then picks each toxic document's best window anew with
the network itself and adds the clean windows it gets most wrong.

Training reads at most ``most_toxic`` and ``most_clean`` labelled documents, by
least seeded hash, and of either label no more than 32 MB. Scoring works on Arrow batches with inputs projected once for
each distinct word of a chunk. Empty, null and wordless texts get the floor score.
Every row is scored on its own, so ties, repeated rows and null identifiers change
nothing; an empty table gives no rows; other columns pass unchanged.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from .common import documents, tidied
from .quality import labelled_sample

WINDOW, STRIDE, WORD_BYTES = 24, 12, 24
WORD_SLOTS, GRAM_SLOTS, DIM, HIDDEN, LOOK = 1 << 14, 1 << 13, 8, 8, 8
WORDS = re.compile(r"\w+")


def words_of(text: str) -> list[str]:
    found = WORDS.findall(text.lower())
    if any(len(w) > WORD_BYTES // 4 and len(w.encode()) > WORD_BYTES for w in found):
        found = [w[i : i + WORD_BYTES // 4] if len(w.encode()) > WORD_BYTES else w for w in found for i in (range(0, len(w), WORD_BYTES // 4) if len(w.encode()) > WORD_BYTES else (0,))]
    return found


def word_inputs(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word slot, trigram slots (padded with GRAM_SLOTS) and their number, for each word."""
    n = len(words)
    raw = [b"\x02" + w.encode() + b"\x03" for w in words]
    size = np.fromiter(map(len, raw), np.int64, n)
    width = WORD_BYTES + 2
    grid = np.frombuffer(b"".join(r.ljust(width, b"\0") for r in raw), np.uint8).reshape(n, width).astype(np.uint32)
    grams = (grid[:, :-2] * np.uint32(0x9E3779B1) + grid[:, 1:-1] * np.uint32(0x85EBCA77) + grid[:, 2:] * np.uint32(0xC2B2AE3D)) >> np.uint32(19)
    count = np.maximum(size - 2, 1)
    grams = np.where(np.arange(width - 2)[None, :] < count[:, None], grams, GRAM_SLOTS).astype(np.int64)
    slots = np.fromiter((zlib.crc32(r) & (WORD_SLOTS - 1) for r in raw), np.int64, n)
    return slots, grams.astype(np.uint16), count


def windows_of(sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For documents of ``sizes`` words: the document and the word positions of each window, -1 beyond its end."""
    many = np.where(sizes > 0, np.maximum(1, -(-(sizes - WINDOW) // STRIDE) + 1), 0)
    doc = np.repeat(np.arange(len(sizes)), many)
    nth = np.arange(len(doc)) - np.repeat(np.cumsum(many) - many, many)
    at = (nth * STRIDE)[:, None] + np.arange(WINDOW)[None, :]
    begin = np.cumsum(sizes) - sizes
    return doc, np.where(at < sizes[doc][:, None], at + begin[doc][:, None], -1)


def sigmoid(x):
    return 1 / (1 + np.exp(-x))


@dataclass
class ToxicityModel:
    p: dict = field(default_factory=dict)
    slope: float = 1.0
    shift: float = 0.0
    floor: float = 0.0

    @staticmethod
    def fresh(seed: int = 11) -> "ToxicityModel":
        rng = np.random.default_rng(seed)
        new = lambda *shape: rng.normal(0, 1 / math.sqrt(shape[0]), shape).astype(np.float32)
        small = lambda *shape: rng.normal(0, 0.1, shape).astype(np.float32)
        p = {"word": small(WORD_SLOTS, DIM), "gram": small(GRAM_SLOTS + 1, DIM), "look": new(2 * HIDDEN, LOOK), "look_b": np.zeros(LOOK, np.float32), "ask": new(LOOK), "out": new(2 * HIDDEN), "out_b": np.zeros(1, np.float32)}
        p["gram"][GRAM_SLOTS] = 0
        for side in "fb":
            p |= {f"in_{side}": new(2 * DIM, 3 * HIDDEN), f"rec_{side}": new(HIDDEN, 3 * HIDDEN), f"bias_{side}": np.zeros(3 * HIDDEN, np.float32)}
        return ToxicityModel(p)

    def embed(self, slots, grams, count) -> np.ndarray:
        if len(slots) > 4096:  # the trigrams of many words at once would not fit a worker
            return np.concatenate([self.embed(slots[a : a + 4096], grams[a : a + 4096], count[a : a + 4096]) for a in range(0, len(slots), 4096)])
        chars = self.p["gram"][grams].sum(1) / np.sqrt(count)[:, None].astype(np.float32)
        return np.concatenate([self.p["word"][slots], chars], 1)

    def project(self, inputs: np.ndarray) -> dict[str, np.ndarray]:
        """Gate inputs of distinct words; the last row stands for "no word" and holds the state as it is."""
        out = {}
        for side in "fb":
            rows = inputs @ self.p[f"in_{side}"] + self.p[f"bias_{side}"]
            none = np.zeros((1, 3 * HIDDEN), np.float32)
            none[0, :HIDDEN] = 40
            out[side] = np.concatenate([rows, none]).astype(np.float32)
        return out

    def logits(self, gates: dict[str, np.ndarray], index: np.ndarray, keep: dict | None = None) -> np.ndarray:
        """Score of each window; ``index`` has rows of ``gates``, -1 for none. ``keep`` gets what the gradient needs."""
        n = len(index)
        states = np.empty((WINDOW, n, 2 * HIDDEN), np.float32)
        for side, part in (("f", slice(0, HIDDEN)), ("b", slice(HIDDEN, 2 * HIDDEN))):
            h, rec = np.zeros((n, HIDDEN), np.float32), self.p[f"rec_{side}"]
            trail = []
            for t in range(WINDOW) if side == "f" else range(WINDOW - 1, -1, -1):
                g, a = gates[side][index[:, t]], h @ rec
                zr = sigmoid(g[:, : 2 * HIDDEN] + a[:, : 2 * HIDDEN])
                z, r, an = zr[:, :HIDDEN], zr[:, HIDDEN:], a[:, 2 * HIDDEN :]
                new = np.tanh(g[:, 2 * HIDDEN :] + r * an)
                if keep is not None:
                    trail.append((t, h, z, r, an, new))
                h = new + z * (h - new)
                states[t, :, part] = h
            if keep is not None:
                keep[side] = trail
        looks = np.tanh(states @ self.p["look"] + self.p["look_b"])
        energy = np.where(index.T >= 0, looks @ self.p["ask"], -1e9)
        share = np.exp(energy - energy.max(0))
        share /= share.sum(0)
        pooled = np.einsum("tn,tnh->nh", share, states)
        if keep is not None:
            keep |= {"states": states, "looks": looks, "share": share, "pooled": pooled}
        return pooled @ self.p["out"] + self.p["out_b"][0]

    def gradient(self, slots, grams, count, index, labels, weights, hide) -> tuple[dict, float]:
        """Gradients of the weighted logistic loss over windows whose words are rows of slots, grams, count."""
        p, keep = self.p, {}
        inputs = self.embed(slots, grams, count)
        inputs[hide, :DIM] = 0
        logit = self.logits(self.project(inputs), index, keep)
        error = (sigmoid(logit) - labels) * weights / weights.sum()
        loss = float((np.logaddexp(0, np.where(labels > 0, -logit, logit)) * weights).sum() / weights.sum())
        g = {"out": keep["pooled"].T @ error, "out_b": error.sum(keepdims=True)}
        d_pooled = error[:, None] * p["out"]
        states, looks, share = keep["states"], keep["looks"], keep["share"]
        d_share = np.einsum("nh,tnh->tn", d_pooled, states)
        d_energy = share * (d_share - (share * d_share).sum(0))
        g["ask"] = np.einsum("tn,tnk->k", d_energy, looks)
        d_looks = d_energy[:, :, None] * p["ask"] * (1 - looks**2)
        g["look"] = np.einsum("tnh,tnk->hk", states, d_looks)
        g["look_b"] = d_looks.sum((0, 1))
        d_states = share[:, :, None] * d_pooled[None] + d_looks @ p["look"].T
        d_inputs = np.zeros_like(inputs)
        for side, part in (("f", slice(0, HIDDEN)), ("b", slice(HIDDEN, 2 * HIDDEN))):
            carried = np.zeros((len(index), HIDDEN), np.float32)
            rec, d_rec = p[f"rec_{side}"], np.zeros_like(p[f"rec_{side}"])
            d_gates = np.zeros((len(slots) + 1, 3 * HIDDEN), np.float32)
            for t, h, z, r, an, new in reversed(keep[side]):
                d = carried + d_states[t, :, part]
                dz, dn = d * (h - new) * z * (1 - z), d * (1 - z) * (1 - new**2)
                dr = dn * an * r * (1 - r)
                da = np.concatenate([dz, dr, dn * r], 1)
                d_rec += h.T @ da
                carried = d * z + da @ rec.T
                np.add.at(d_gates, index[:, t], np.concatenate([dz, dr, dn], 1))
            d_gates = d_gates[:-1]
            g |= {f"rec_{side}": d_rec, f"in_{side}": inputs.T @ d_gates, f"bias_{side}": d_gates.sum(0)}
            d_inputs += d_gates @ p[f"in_{side}"].T
        d_inputs[hide, :DIM] = 0
        g["word"], g["gram"] = np.zeros_like(p["word"]), np.zeros_like(p["gram"])
        np.add.at(g["word"], slots, d_inputs[:, :DIM])
        spread = d_inputs[:, DIM:] / np.sqrt(count)[:, None]
        np.add.at(g["gram"], grams, np.broadcast_to(spread[:, None, :], (*grams.shape, DIM)))
        g["gram"][GRAM_SLOTS] = 0
        return g, loss

    def text_logits(self, texts: list[str]) -> np.ndarray:
        """Greatest window logit of each text; -inf without words."""
        lists = [words_of(x) for x in texts]
        sizes = np.array([len(x) for x in lists], np.int64)
        best = np.full(len(texts), -np.inf)
        if not sizes.sum():
            return best
        coded = pa.chunked_array([pa.array(x, pa.string()) for x in lists]).combine_chunks().dictionary_encode()
        gates = self.project(self.embed(*word_inputs(coded.dictionary.to_pylist())))
        ids = np.append(coded.indices.to_numpy(zero_copy_only=False), -1)
        doc, at = windows_of(sizes)
        for a in range(0, len(doc), 4096):
            np.maximum.at(best, doc[a : a + 4096], self.logits(gates, ids[at[a : a + 4096]]))
        return best

    def scores(self, texts: list[str]) -> np.ndarray:
        best = self.text_logits(texts)
        return np.where(np.isfinite(best), sigmoid(self.slope * np.where(np.isfinite(best), best, 0) + self.shift), self.floor)


def starting_windows(ids: np.ndarray, doc: np.ndarray, at: np.ndarray, labels: np.ndarray, vocabulary: int) -> np.ndarray:
    """How much each window's words speak for its document's label, from document counts of words."""
    seen = [np.zeros(vocabulary + 1), np.zeros(vocabulary + 1)]
    firsts = np.concatenate([np.flatnonzero(np.diff(doc, prepend=-1)), [len(doc)]])
    for a, b in zip(firsts, firsts[1:]):
        words = np.unique(ids[at[a:b]])
        seen[int(labels[doc[a]])][words[words >= 0]] += 1
    n0, n1 = max(1, (labels == 0).sum()), max(1, (labels == 1).sum())
    odds = np.log((seen[1] + 0.5) / n1) - np.log((seen[0] + 0.5) / n0)
    odds[(seen[1] < 3) | (odds < 1)] = 0
    odds[-1] = 0
    return np.concatenate([odds[ids[at[a : a + 4096]]].sum(1) for a in range(0, len(at), 4096)])


def train(texts: list[str], labels: np.ndarray, seed: int = 11, epochs: tuple[int, ...] = (4, 3, 2)) -> ToxicityModel:
    model, rng = ToxicityModel.fresh(seed), np.random.default_rng(seed)
    if not len(texts) or labels.min() == labels.max():
        model.slope, model.shift = 0.0, -3.0 if not len(texts) or labels.max() == 0 else 3.0
        model.floor = float(sigmoid(model.shift))
        return model
    lists = [words_of(x) for x in texts]
    sizes = np.array([len(x) for x in lists], np.int64)
    names = {w: i for i, w in enumerate(dict.fromkeys(w for x in lists for w in x))}
    ids = np.fromiter((names[w] for x in lists for w in x), np.int32, int(sizes.sum()))
    ids = np.append(ids, np.int32(-1))
    slots, grams, count = word_inputs(list(names))
    doc, at = windows_of(sizes)
    at = at.astype(np.int32)
    del lists
    rank = starting_windows(ids, doc, at, labels, len(names))
    moments = {k: (np.zeros_like(v), np.zeros_like(v)) for k, v in model.p.items()}
    step = 0
    for round_, n_epochs in enumerate(epochs):
        order = np.lexsort((-rank, doc))
        first = order[np.r_[True, np.diff(doc[order]) != 0]]
        best_toxic = first[labels[doc[first]] == 1]
        clean = np.flatnonzero(labels[doc] == 0)
        hard = clean[np.argsort(-rank[clean])[: len(best_toxic)]] if round_ else clean[:0]
        for _ in range(n_epochs):
            easy = rng.choice(clean, min(len(clean), max(3 * len(best_toxic), 600)), replace=False)
            pool = rng.permutation(np.concatenate([best_toxic, hard, easy]))
            for a in range(0, len(pool), 64):
                own = pool[a : a + 64]
                words, index = np.unique(ids[at[own]], return_inverse=True)
                none = int(words[0] == -1)
                index, words = index.reshape(len(own), WINDOW) - none, words[none:]
                y = labels[doc[own]].astype(np.float32)
                hide = rng.random(len(words)) < 0.4
                g, _ = model.gradient(slots[words], grams[words], count[words], index, y, np.where(y > 0, 1.0, 1.0).astype(np.float32), hide)
                step += 1
                rate = 0.01 * min(1, step / 20) * math.sqrt(1 - 0.999**step) / (1 - 0.9**step)
                for k, v in g.items():
                    m1, m2 = moments[k]
                    m1 += 0.1 * (v - m1)
                    m2 += 0.001 * (v * v - m2)
                    model.p[k] -= rate * m1 / (np.sqrt(m2) + 1e-8)
        gates = model.project(model.embed(slots, grams, count))
        rank = np.concatenate([model.logits(gates, ids[at[a : a + 4096]]) for a in range(0, len(doc), 4096)])
    best = np.full(len(texts), -np.inf)
    np.maximum.at(best, doc, rank)
    fit_scale(model, best[sizes > 0], labels[sizes > 0])
    return model


def fit_scale(model: ToxicityModel, best: np.ndarray, labels: np.ndarray) -> None:
    """Logistic scale of document logits, labels weighted alike; the floor is the score of the least."""
    weight = np.where(labels > 0, 0.5 / labels.mean(), 0.5 / (1 - labels.mean()))
    middle, spread = best.mean(), best.std() + 1e-6
    x, a, b = (best - middle) / spread, 1.0, 0.0
    for _ in range(300):
        error = (sigmoid(a * x + b) - labels) * weight
        a, b = a - 0.5 * ((error * x).mean() + 0.01 * a), b - 0.5 * error.mean()
    model.slope, model.shift = a / spread, b - a * middle / spread
    model.floor = float(sigmoid(model.slope * best.min() + model.shift))


def toxic_sample(docs: DataFrame, labels: DataFrame, learn, most_toxic: int, most_clean: int) -> tuple[list[str], np.ndarray]:
    parts = [labelled_sample(docs, labels.where(F.col("toxic") == y), "toxic", learn, n, seed=7) for y, n in ((1, most_toxic), (0, most_clean))]
    return parts[0][0] + parts[1][0], np.concatenate([y for _, y in parts])


def score_kernel(shared):
    def run(batches):
        model = shared.value
        for batch in batches:
            at = 0
            for end in cut_points(batch.column(1), 1_000_000):
                part = batch.slice(at, end - at)
                at = end
                scores = model.scores([x or "" for x in part.column(1).to_pylist()])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(scores, pa.float64())], ["id", "score"])

    return run


def cut_points(texts: pa.Array, most_bytes: int) -> list[int]:
    """Ends of pieces of a batch that hold about ``most_bytes`` each."""
    import pyarrow.compute as pc

    size = pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False).cumsum()
    if not len(size):
        return []
    ends = np.searchsorted(size, np.arange(1, int(size[-1]) // most_bytes + 1) * most_bytes, side="left") + 1
    return np.unique(np.append(ends, len(size))).tolist()


def score_toxicity(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: id_col, score."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = T.StructType([T.StructField("id", T.LongType()), T.StructField("score", T.DoubleType())])
    return docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).cast("string")).mapInArrow(tidied(score_kernel(shared)), schema).withColumnRenamed("id", id_col)


def fit_toxicity(docs: DataFrame, labels: DataFrame, learn, most_toxic: int = 1000, most_clean: int = 1600) -> ToxicityModel:
    return train(*toxic_sample(docs, labels, learn, most_toxic, most_clean))


def fold(key):
    return F.crc32(key.cast("string").cast("binary")) % 5 == 0


def op3_toxicity(spark, sf_dir: str) -> DataFrame:
    """Whole ``documents``: doc_id, held_out, score, predicted, one row for each; a null doc_id is not held out."""
    docs, labels = documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = fit_toxicity(docs, labels, lambda key: ~fold(key))
    scored = score_toxicity(docs, model)
    return scored.select("doc_id", F.coalesce(fold(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def drop_toxic(docs: DataFrame, labels: DataFrame, threshold: float = 0.5, id_col: str = "doc_id", text_col: str = "text", **bounds) -> DataFrame:
    """The rows of ``docs`` that score under ``threshold``, with all their columns.

    Scores stand beside their rows in one pass, so repeated or null identifiers need no join.
    """
    model = fit_toxicity(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")), labels, lambda key: F.lit(True), **bounds)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    names, at = docs.columns, docs.columns.index(text_col)
    packed = docs.toDF(*[f"c{i}" for i in range(len(names))]).withColumn(f"c{at}", F.col(f"c{at}").cast("string"))

    def run(batches):
        for batch in batches:
            start = 0
            for end in cut_points(batch.column(at), 1_000_000):
                part = batch.slice(start, end - start)
                start = end
                clean = shared.value.scores([x or "" for x in part.column(at).to_pylist()]) < threshold
                yield part.filter(pa.array(clean))

    return packed.mapInArrow(tidied(run), packed.schema).toDF(*names)
