"""Quality rules: countable base rules and a calibrated n-gram classifier."""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .store import written
from .textkern import slices

BITS = 16
WORD_N, CHAR_N = (1, 2), (2, 3, 4)
#: Labelled rows the classifier is fitted on at most: those with the smallest hash of their id.
MAX_TRAINING_ROWS = 3000
#: Entries of their vectors at most, which bounds the driver's memory: rows beyond it, in the same order, take no part.
MAX_TRAINING_ENTRIES = 8_000_000
#: Entries that a step of the fit handles at once.
PIECE = 1 << 19
#: Documents whose calibrated probability of good quality is below this are rejected.
MIN_PROBABILITY = 0.25
MIN_WORDS = 10
MAX_REPEAT_PERCENT = 20

_SYMBOL = re.compile(rb"[#*$%&|<>]")
_SEED = np.uint64(0x9E3779B97F4A7C15)


def base_counts(text: bytes | None) -> tuple[int, int, int, int, int]:
    """n_words, word_char, n_symbols, n_dup_lines, n_repeat_words of one text."""
    if not text:
        return 0, 0, 0, 0, 0
    words = text.split()
    n = len(words)
    joined = b"".join(words)
    chars = len(joined) - int(np.count_nonzero((np.frombuffer(joined, np.uint8) & 0xC0) == 0x80)) if n else 0
    lines = [x for x in text.split(b"\n") if x.strip()]
    dup_lines = len(lines) - len(set(lines))
    repeated = 0
    if n > 5:
        number: dict[bytes, int] = {}
        ids = [number.setdefault(w, len(number)) for w in words]
        if len(number) <= 4096:
            a = np.array(ids, np.uint64)
            grams = ((((a[:-4] << np.uint64(12) | a[1:-3]) << np.uint64(12) | a[2:-2]) << np.uint64(12)) | a[3:-1]) << np.uint64(12) | a[4:]
            _, back, count = np.unique(grams, return_inverse=True, return_counts=True)
            again = np.flatnonzero(count[back] > 1)
        else:
            grams = list(zip(ids, ids[1:], ids[2:], ids[3:], ids[4:]))
            count = Counter(grams)
            again = np.array([i for i, g in enumerate(grams) if count[g] > 1], np.int64)
        if len(again):
            mark = np.zeros(n + 1, np.int64)
            np.add.at(mark, again, 1)
            np.add.at(mark, again + 5, -1)
            repeated = int((np.cumsum(mark) > 0).sum())
    return n, chars, len(_SYMBOL.findall(text)), dup_lines, repeated


def features(text: bytes | None, bits: int = BITS) -> tuple[np.ndarray, np.ndarray]:
    """Hashed counts of word and character n-grams (runs of white space as one
    space): positions and values of a vector of length 1."""
    words = text.split() if text else []
    if not words:
        return np.empty(0, np.int64), np.empty(0, np.float32)
    shift = np.uint64(64 - bits)
    single = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))
    hashed = []
    for n in WORD_N:
        if len(single) >= n:
            h = single[: len(single) - n + 1]
            for k in range(1, n):
                h = (h ^ (h >> np.uint64(29))) * _SEED + single[k : k + len(h)]
            hashed.append(h >> shift)
    plain = (b" " + b" ".join(words) + b" ").decode("utf-8", "replace")
    data = np.frombuffer(plain.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    for n in CHAR_N:
        if len(data) >= n:
            h = np.full(len(data) - n + 1, n, np.uint64)
            for k in range(n):
                h = h * np.uint64(257) + data[k : k + len(h)]
            hashed.append((h * _SEED) >> shift)
    count = np.bincount(np.concatenate(hashed).astype(np.int64), minlength=1 << bits)
    at = np.flatnonzero(count)
    value = np.log1p(count[at]).astype(np.float32)
    return at, value / np.sqrt((value * value).sum())


@dataclass(frozen=True)
class QualityModel:
    """Logistic regression on hashed n-grams with a Platt calibration."""

    weights: np.ndarray
    bias: float
    slope: float
    offset: float

    def score(self, at: np.ndarray, value: np.ndarray) -> float:
        return float(self.weights[at] @ value) + self.bias

    def probability(self, text: bytes | None) -> float:
        z = self.slope * self.score(*features(text)) + self.offset
        return 1.0 / (1.0 + float(np.exp(-np.clip(z, -60, 60))))


def _logistic(index: np.ndarray, value: np.ndarray, start: np.ndarray, y: np.ndarray, size: int, epochs: int = 60, l2: float = 1e-5) -> tuple[np.ndarray, float]:
    """Full-batch gradient descent with adaptive steps; classes weigh the same. Row i has the entries from ``start[i]`` to
    ``start[i + 1]``; they are gone through in pieces, so that nothing of their full number stands beside them."""
    w, b, gw2, gb2 = np.zeros(size), 0.0, np.full(size, 1e-8), 1e-8
    share = np.where(y == 1, 0.5 / max(1, y.sum()), 0.5 / max(1, len(y) - y.sum()))
    cuts = np.unique(np.r_[0, np.searchsorted(start, np.arange(PIECE, start[-1], PIECE)), len(y)])
    pieces = [(lo, hi, slice(start[lo], start[hi])) for lo, hi in zip(cuts, cuts[1:])]
    for _ in range(epochs):
        gw, gb = np.zeros(size), 0.0
        for lo, hi, at in pieces:
            own, x = index[at].astype(np.int64), value[at]
            row = np.repeat(np.arange(hi - lo), np.diff(start[lo : hi + 1]))
            z = np.bincount(row, weights=w[own] * x, minlength=hi - lo) + b
            g = share[lo:hi] * (1.0 / (1.0 + np.exp(-np.clip(z, -60, 60))) - y[lo:hi])
            gw += np.bincount(own, weights=g[row] * x, minlength=size)
            gb += g.sum()
        gw += l2 * w
        gw2 += gw * gw
        gb2 += gb**2
        w -= 0.5 * gw / np.sqrt(gw2)
        b -= 0.5 * gb / np.sqrt(gb2)
    return w, b


def _platt(z: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and offset by damped Newton steps on held-out scores, with smoothed targets."""
    good, bad = y.sum(), len(y) - y.sum()
    t = np.where(y == 1, (good + 1) / (good + 2), 1 / (bad + 2))
    x = np.c_[z, np.ones(len(z))]

    def loss(beta: np.ndarray) -> float:
        a = x @ beta
        return float((np.logaddexp(0, a) - t * a).sum())

    beta = np.zeros(2)
    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        slope = x.T @ (p - t)
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + 1e-9 * np.eye(2), slope)
        size, now = 1.0, loss(beta)
        while size > 1e-6 and loss(beta - size * step) > now - 1e-4 * size * float(slope @ step):
            size /= 2
        beta = beta - size * step
        if np.abs(size * step).max() < 1e-8:
            break
    return float(max(beta[0], 1e-3)), float(beta[1])


def train(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_TRAINING_ROWS, text: str = "text", max_entries: int = MAX_TRAINING_ENTRIES) -> QualityModel | None:
    """Fit on at most ``max_rows`` labelled documents with at most ``max_entries`` entries; None if a class has fewer than 10.

    Features are computed where the texts are; the driver gets hashed vectors, ``max_entries`` entries in all. A document
    with two labels counts as good; of several texts of one doc_id the one with the least vector counts, so that reruns agree. A
    third of the rows is held out to calibrate probabilities. Null labels, ids and empty tables take no part.
    """
    wanted = labels.filter("doc_id is not null and quality in (0, 1)").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("quality").cast("int").alias("quality"))
    chosen = wanted.join(docs.select(F.col("doc_id").cast("long").alias("doc_id")).distinct(), "doc_id", "left_semi").orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_rows)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece, texts in slices(batches, "text"):
            rows = [features(t) for t in texts]
            yield pa.RecordBatch.from_arrays([piece.column("doc_id"), piece.column("quality"), pa.array([a.astype(np.int32).tobytes() for a, _ in rows], pa.binary()), pa.array([v.tobytes() for _, v in rows], pa.binary())], names=["doc_id", "quality", "at", "value"])

    found = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(text).alias("text")).join(F.broadcast(chosen), "doc_id").mapInArrow(run, "doc_id long, quality int, at binary, value binary")
    found = written(found.groupBy("doc_id").agg(F.max("quality").alias("quality"), F.min(F.struct("at", "value")).alias("row")), "training-rows")
    sizes = found.orderBy(F.xxhash64("doc_id"), "doc_id").select("doc_id", F.expr("length(row.at) div 4").alias("n")).collect()
    fits = np.cumsum([r.n for r in sizes]) <= max_entries
    length = dict(sorted((r.doc_id, r.n) for r, ok in zip(sizes, fits) if ok))
    ids = list(length)
    place = {d: i for i, d in enumerate(ids)}
    fold = np.array([xxhash.xxh64_intdigest(str(d), 7) % 3 for d in ids])
    # rows to fit first, then those held out, by doc_id each: two arrays that are filled as the rows come in
    order = np.argsort(fold == 0, kind="stable") if ids else np.empty(0, np.int64)
    start, spot = np.r_[0, np.cumsum([length[ids[i]] for i in order])].astype(np.int64), np.empty(len(ids), np.int64)
    spot[order] = np.arange(len(ids))
    index, value, y = np.empty(start[-1], np.int32), np.empty(start[-1], np.float32), np.zeros(len(ids), np.int64)
    own = docs.sparkSession.createDataFrame([(i,) for i in ids], "doc_id bigint")
    for r in found.join(F.broadcast(own), "doc_id").select("doc_id", "quality", "row.*").toLocalIterator():
        i = spot[place[r.doc_id]]
        index[start[i] : start[i + 1]], value[start[i] : start[i + 1]] = np.frombuffer(r.at, np.int32), np.frombuffer(r.value, np.float32)
        y[i] = r.quality
    if not len(y) or min(y.sum(), len(y) - y.sum()) < 10:
        return None
    n = int((fold != 0).sum())
    w, b = _logistic(index, value, start[: n + 1], y[:n], 1 << BITS)
    held = np.array([w[index[start[i] : start[i + 1]]] @ value[start[i] : start[i + 1]] + b for i in range(n, len(y))])
    slope, offset = _platt(held, y[n:]) if len(held) else (1.0, 0.0)
    return QualityModel(w.astype(np.float32), float(b), slope, offset)


def judge(docs: DataFrame, model: QualityModel | None, text: str = "text", min_probability: float = MIN_PROBABILITY) -> DataFrame:
    """``docs`` with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
    base_failed, probability, kept (columns of those names are replaced).

    Null and blank texts have no words, fail the base rules and have no probability. Without a model the
    base rules alone decide. Every row gets a row; an empty table gives an empty result.
    """
    new = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, probability double, kept boolean"
    names = [x.split()[0] for x in new.split(", ")]
    rest = docs.drop(*names)
    schema = T.StructType([*rest.schema.fields, *T._parse_datatype_string(new).fields])
    columns = rest.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece, texts in slices(batches, text):
            rows = []
            for t in texts:
                counts = base_counts(t)
                failed = counts[0] < MIN_WORDS or 100 * counts[4] > MAX_REPEAT_PERCENT * counts[0]
                p = model.probability(t) if model and counts[0] else None
                rows.append((*counts, failed, p, not failed and (p is None or p >= min_probability)))
            kinds = [pa.int64()] * 5 + [pa.bool_(), pa.float64(), pa.bool_()]
            yield pa.RecordBatch.from_arrays([*(piece.column(c) for c in columns), *(pa.array(x, k) for x, k in zip(zip(*rows), kinds))], names=[*columns, *names])

    return rest.mapInArrow(run, schema)
