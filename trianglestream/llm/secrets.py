"""Secret scan: fixed patterns, plus a randomness battery with false-discovery control.

Candidates of the battery are runs of token characters. For each, the narrowest encoding
that holds all its characters is inferred, and its symbols are tested against a uniform
draw from that encoding's alphabet: chi-squared of the symbol counts, the Wald-Wolfowitz
runs about the middle of the alphabet, and the serial correlation of symbol codes. The
three p-values combine by Fisher's rule into a departure from randomness.

Random strings depart little, ordinary writing much. What "much" means is measured: symbol
successions are counted over all documents, ordinary strings are simulated from them in
each encoding, and the departures of these, by encoding and length, are the null law. A
candidate's p-value is the chance that ordinary writing of its encoding and length departs
as little. A weighted Benjamini-Hochberg step over all candidates of the table decides
which are secrets at the stated rate of false discoveries; weights grow with length and
average one over the candidates, and the threshold comes from a histogram of fixed size.

Null texts count as empty. Null identifiers, repeated rows, very long texts, ties and empty
tables are fine; every row gives one row; other columns are not read.
"""

from __future__ import annotations

import hashlib
import math
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from .common import documents, materialize, read_batches, tidied

#: Kinds of span in listing order.
KINDS = ["assign", "access", "hex", "random"]
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{16,}")
WORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")
CANDIDATE = re.compile(r"[A-Za-z0-9+/_=-]{20,}")
#: Encodings from narrow to wide: name, alphabet.
ENCODINGS = [
    ("hex", "0123456789abcdef"),
    ("hex-upper", "0123456789ABCDEF"),
    ("base32", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"),
    ("base36", "0123456789abcdefghijklmnopqrstuvwxyz"),
    ("base62", "0123456789abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ"),
    ("base64", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/"),
    ("base64url", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789-_"),
    ("token", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/=-_"),
]
SYMBOLS = ENCODINGS[-1][1]
#: Lengths at which the null law is simulated; a candidate takes the longest that it reaches.
LENGTHS = [20, 22, 24, 28, 32, 40, 48, 64, 96, 128]
DRAWS, LEAST = 4000, 60
BINS, STEP = 1200, 0.25  # histogram of -ln p


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the fixed patterns."""
    found = []
    low = text.lower()
    if any(w in low for w in WORDS):
        found += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 12]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 18]
    found += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return found


def infer_encoding(token: str) -> tuple[str, str]:
    used = set(token.rstrip("="))
    return next(((name, letters) for name, letters in ENCODINGS if used <= set(letters)), ENCODINGS[-1])


def normal_tail(z: np.ndarray) -> np.ndarray:
    """ln of the upper tail of the normal law."""
    z = np.asarray(z, float)
    near = np.log(np.maximum(0.5 * np.array([math.erfc(x / math.sqrt(2)) for x in np.clip(z, -8, 8).ravel()]).reshape(z.shape), 1e-300))
    far = -z * z / 2 - np.log(np.maximum(z, 1) * math.sqrt(2 * math.pi))
    return np.where(z > 8, far, near)


def tests(codes: np.ndarray, k: int) -> dict[str, np.ndarray]:
    """ln p of the three tests of rows of symbol codes against a uniform draw from ``k`` symbols, and the departure,
    Fisher's -2 times their sum."""
    rows, n = codes.shape
    counts = np.bincount((codes + k * np.arange(rows)[:, None]).ravel(), minlength=rows * k).reshape(rows, k).astype(float)
    chi, free = (counts**2).sum(1) * k / n - n, k - 1
    z_chi = (np.cbrt(chi / free) - (1 - 2 / (9 * free))) / math.sqrt(2 / (9 * free))
    high = codes >= k // 2
    ups = high.sum(1).astype(float)
    runs = 1 + (high[:, 1:] != high[:, :-1]).sum(1)
    product = 2 * ups * (n - ups)
    spread = np.sqrt(np.maximum(product * (product - n), 0) / (n * n * (n - 1)))
    z_runs = np.where(spread > 0, np.abs(runs - 1 - product / n) / np.maximum(spread, 1e-9), math.sqrt(n))
    off = codes - codes.mean(1, keepdims=True)
    square = (off**2).sum(1)
    z_serial = np.where(square > 0, np.abs((off[:, 1:] * off[:, :-1]).sum(1)) / np.maximum(square, 1e-9), 1.0) * math.sqrt(n)
    two = lambda z: np.minimum(0.0, normal_tail(z) + math.log(2))
    out = {"chi": normal_tail(z_chi), "runs": two(z_runs), "serial": two(z_serial)}
    out["departure"] = -2 * (out["chi"] + out["runs"] + out["serial"])
    return out


def codes_of(token: str) -> tuple[str, np.ndarray, int]:
    """Inferred encoding, symbol codes in it without padding, size of the alphabet."""
    name, letters = infer_encoding(token)
    body = (token.rstrip("=") or token) if "=" not in letters else token
    return name, np.array([[letters.index(c) for c in body]]), len(letters)


def ordinary_strings(pairs: np.ndarray, letters: str, rng) -> np.ndarray:
    """Codes of ``DRAWS`` strings of the greatest length, drawn symbol by symbol from the counted successions."""
    at = [SYMBOLS.index(c) for c in letters]
    own = pairs[np.ix_(at, at)].astype(float)
    follows = own.sum(0) + 0.01
    own += follows / follows.sum()  # a symbol never met is followed as symbols are at large
    first = np.cumsum(own.sum(1)) / own.sum()
    cuts = np.cumsum(own, 1) / own.sum(1, keepdims=True)
    out = np.empty((DRAWS, LENGTHS[-1]), np.int64)
    out[:, 0] = np.minimum(np.searchsorted(first, rng.random(DRAWS)), len(at) - 1)
    for i in range(1, LENGTHS[-1]):
        out[:, i] = np.minimum((cuts[out[:, i - 1]] < rng.random((DRAWS, 1))).sum(1), len(at) - 1)
    return out


def null_law(pairs: np.ndarray, seed: int = 23) -> dict[tuple[str, int], tuple[np.ndarray, float, float]]:
    """By encoding and length: ascending ln departures of ordinary strings, their mean and spread.

    Strings whose encoding would be inferred as a narrower one are left out where ``LEAST`` others remain."""
    rng, law = np.random.default_rng(seed), {}
    for place, (name, letters) in enumerate(ENCODINGS):
        codes = ordinary_strings(pairs, letters, rng)
        inside = [np.isin(codes, [i for i, c in enumerate(letters) if c in set(narrow)]) for _, narrow in ENCODINGS[:place]]
        for n in LENGTHS:
            own = ~np.any([x[:, :n].all(1) for x in inside], 0) if inside else np.ones(DRAWS, bool)
            drawn = codes[own if own.sum() >= LEAST else slice(None), :n]
            y = np.sort(np.log(np.maximum(tests(drawn, len(letters))["departure"], 1e-9)))
            # The lower tail may be heavier than the spread says: it must reach the least draws, too.
            tail = max(float(y.std()), *((y.mean() - y[int(q * len(y))]) / z for q, z in ((0.01, 2.326), (0.0025, 2.807))))
            law[name, n] = (y, float(y.mean()), tail + 1e-9)
    return law


def battery(token: str, law: dict) -> dict[str, float]:
    """The tests of one candidate and ln of the chance that ordinary writing departs as little."""
    name, codes, k = codes_of(token)
    found = tests(codes, k)
    y, mean, spread = law[name, max((n for n in LENGTHS if n <= codes.shape[1]), default=LENGTHS[0])]
    own = math.log(max(float(found["departure"][0]), 1e-9))
    below = int(np.searchsorted(y, own, side="right"))
    log_p = math.log((1 + below) / (1 + len(y)))
    if below < 0.01 * len(y):  # beyond what simulation resolves: the tail of a normal law of the logarithm
        log_p = min(log_p, float(normal_tail(np.array([(mean - own) / spread]))[0]))
    return {"encoding": name, "log_p": log_p, **{t: float(v[0]) for t, v in found.items()}}


def length_weight(n: int) -> float:
    """Grows with length; the scan divides it by its mean over all candidates."""
    return min(4.0, n / 40)


FOUND = T.StructType([T.StructField("id", T.LongType()), T.StructField("base", T.ArrayType(T.StructType([T.StructField("start", T.IntegerType()), T.StructField("kind", T.IntegerType()), T.StructField("stop", T.IntegerType())]))), T.StructField("extra", T.ArrayType(T.StructType([T.StructField("start", T.IntegerType()), T.StructField("stop", T.IntegerType()), T.StructField("encoding", T.StringType()), T.StructField("strength", T.DoubleType())])))])
SPAN, EXTRA = pa.struct([("start", pa.int32()), ("kind", pa.int32()), ("stop", pa.int32())]), pa.struct([("start", pa.int32()), ("stop", pa.int32()), ("encoding", pa.string()), ("strength", pa.float64())])


def long_runs(data: bytes, table: np.ndarray, least: int) -> bool:
    """Whether some run of bytes in ``table`` has ``least`` or more."""
    inside = np.concatenate([[False], table[np.frombuffer(data, np.uint8)], [False]])
    edges = np.flatnonzero(inside[1:] != inside[:-1])
    return bool(len(edges)) and int((edges[1::2] - edges[::2]).max()) >= least


def pair_kernel(batches):
    """Successions of token symbols over whole texts, summed over the task: one row."""
    place = np.full(256, -1, np.int64)
    place[np.frombuffer(SYMBOLS.encode(), np.uint8)] = np.arange(len(SYMBOLS))
    total = np.zeros(len(SYMBOLS) ** 2, np.int64)
    for batch in read_batches(batches, 256):
        codes = place[np.frombuffer("\n".join(x or "" for x in batch.column(0).to_pylist()).encode(), np.uint8)]
        both = (codes[:-1] >= 0) & (codes[1:] >= 0)
        total += np.bincount(codes[:-1][both] * len(SYMBOLS) + codes[1:][both], minlength=len(total))
    yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), pa.array(total)], ["pair", "n"])


def symbol_pairs(rows: DataFrame) -> np.ndarray:
    """How often each token symbol follows each, over all documents; a table of fixed size."""
    counted = rows.select("text").mapInArrow(tidied(pair_kernel), "pair bigint, n bigint").groupBy("pair").agg(F.sum("n").alias("n"))
    out = np.zeros(len(SYMBOLS) ** 2, np.int64)
    for row in counted.collect():
        out[row["pair"]] = row["n"]
    return out.reshape(len(SYMBOLS), len(SYMBOLS))


def scan_kernel(shared):
    token_bytes = np.zeros(256, bool)
    token_bytes[np.frombuffer(b"ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_.=-", np.uint8)] = True

    def run(batches):
        law = shared.value
        for part in read_batches(batches, 1024):
            base, extra = [], []
            for text in part.column(1):
                text = text.as_py() or ""
                spans, more = [], []
                # Every span there can be holds a run of 12 of these bytes.
                if long_runs(text.encode(), token_bytes, 12):
                    spans = base_spans(text)
                    for m in CANDIDATE.finditer(text):
                        result = battery(m[0], law)
                        more.append((m.start(), m.end(), result["encoding"], math.log(length_weight(m.end() - m.start())) - result["log_p"]))
                base.append([{"start": s, "kind": k, "stop": e} for s, k, e in sorted(spans)])
                extra.append([{"start": s, "stop": e, "encoding": n, "strength": x} for s, e, n, x in more])
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(base, pa.list_(SPAN)), pa.array(extra, pa.list_(EXTRA))], ["id", "base", "extra"])

    return run


def discovery_threshold(found: DataFrame, rate: float) -> float:
    """Least strength that the weighted step-up rule accepts, from counts in bins of fixed number. Strengths are
    -ln p plus ln of an unscaled weight; the mean weight of all candidates scales them."""
    each = found.select(F.explode("extra").alias("x")).select("x.*")
    weight = F.avg(F.least(F.lit(4.0), (F.col("stop") - F.col("start")) / F.lit(40.0)))
    mean = each.agg(weight).first()[0]
    if mean is None:
        return math.inf
    shift = math.log(mean)
    one = each.select(F.least(F.floor(F.greatest(F.col("strength") - F.lit(shift), F.lit(0.0)) / STEP), F.lit(BINS - 1)).cast("int").alias("bin"))
    counts = np.zeros(BINS, np.int64)
    for row in one.groupBy("bin").count().collect():
        counts[row["bin"]] = row["count"]
    return step_up(counts, rate) + shift


def step_up(counts: np.ndarray, rate: float) -> float:
    """Benjamini-Hochberg over a histogram of -ln p: the least accepted, infinite if none is."""
    total, above = counts.sum(), np.cumsum(counts[::-1])[::-1]
    for i in range(len(counts)):
        if above[i] and math.exp(-i * STEP) <= rate * above[i] / total:
            return i * STEP
    return math.inf


def scan(docs: DataFrame, rate: float = 0.01, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: id_col, base (start, kind, stop), extra (start, stop, encoding, strength) that the battery adds."""
    rows = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).cast("string").alias("text"))
    shared = docs.sparkSession.sparkContext.broadcast(null_law(symbol_pairs(rows)))
    found = materialize(rows.mapInArrow(tidied(scan_kernel(shared)), FOUND), "secrets")
    least = discovery_threshold(found, rate)
    keep = F.filter("extra", lambda x: x["strength"] >= F.lit(least)) if least < math.inf else F.array().cast(FOUND["extra"].dataType)
    return found.select(F.col("id").alias(id_col), "base", keep.alias("extra"))


def op10_secret_scan(spark, sf_dir: str) -> DataFrame:
    """Whole ``documents``: doc_id, n_assign, n_access, n_hex, base_sha256 and spans of base and added ones, for every row."""
    found = scan(documents(spark, sf_dir))
    names = F.array(*[F.lit(k) for k in KINDS])

    def text_of(spans):
        ordered = F.array_sort(spans)
        return F.array_join(F.transform(ordered, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"], s["stop"])), ",")

    def number(kind):
        return F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("bigint")

    extra = F.transform("extra", lambda s: F.struct(s["start"].alias("start"), F.lit(3).alias("kind"), s["stop"].alias("stop")))
    return found.select(
        "doc_id", number(0).alias("n_assign"), number(1).alias("n_access"), number(2).alias("n_hex"),
        F.sha2(text_of(F.col("base")), 256).alias("base_sha256"), text_of(F.concat("base", extra)).alias("spans"),
    )


def brute_force_digest(text: str | None) -> tuple[int, int, int, str]:
    """Counts and digest straight from the stated patterns, for tests."""
    text = text or ""
    spans = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 12]
    spans += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if len(m[0]) >= 18]
    spans += [(m.start(), 2, m.end()) for m in re.finditer(r"[0-9a-f]+", text) if len(m[0]) >= 16]
    said = ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in sorted(spans))
    return (*[sum(k == i for _, k, _ in spans) for i in range(3)], hashlib.sha256(said.encode()).hexdigest())
