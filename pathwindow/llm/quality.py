"""Quality classifier: histogram gradient-boosted trees over document statistics.

One pass turns each text into about thirty statistics; the trees are grown on the driver from a bounded sample of
labelled rows, binned by quantiles, and flattened into arrays that numpy traverses for a whole batch at once.

Defined results: a null or empty text has all-zero statistics and is scored as such; null or non-0/1 labels are
ignored; several labels of one document count as the highest; without labels every score is 0.5; with one class it is
that class's rate; repeated rows each get their row; extra columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_fold, map_batches, texts, written

# Labelled rows that the driver may hold for the fit; a larger labelled set is sampled by id hash.
TRAIN_ROWS = 20_000
BINS, TREES, DEPTH, RATE, RIDGE, MIN_ROWS = 64, 80, 4, 0.12, 2.0, 15
THRESHOLD = 0.3
NAMES = (
    "log_chars", "log_words", "word_mean", "word_std", "upper", "digit", "space", "letter", "other", "exclaim", "comma", "stop",
    "distinct", "top_word", "top_three", "stutter", "pair_distinct", "line_mean", "line_dup", "lines", "packed", "non_ascii",
    "caps_words", "short_words", "long_words", "markup", "urlish", "brace", "end_stops", "cycle",
)
_CLASS = np.zeros(256, np.uint8)
for _name, _chars in (("upper", range(65, 91)), ("lower", range(97, 123)), ("digit", range(48, 58)), ("space", (9, 10, 11, 12, 13, 32)), ("high", range(128, 256))):
    for _c in _chars:
        _CLASS[_c] = ("", "upper", "lower", "digit", "space", "high").index(_name)
_URL = re.compile("https?:|www\\.|\\.com|\\.org")


def statistics(text: str) -> list[float]:
    if not text:
        return [0.0] * len(NAMES)
    raw = text.encode("utf-8", "surrogatepass")
    n = len(raw)
    counts = np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
    kind = np.bincount(_CLASS, weights=counts, minlength=6) / n
    words = raw.split()
    w = max(1, len(words))
    sizes = np.fromiter(map(len, words), np.int64, len(words)) if words else np.zeros(1, np.int64)
    seen = Counter(words)
    tops = [c for _, c in seen.most_common(3)] or [0]
    pairs = len(set(zip(words, words[1:], strict=False)))
    stutter = sum(map(bytes.__eq__, words, words[1:]))
    cycle = sum(map(bytes.__eq__, words, words[seen_gap(words) :])) if len(words) > 30 else 0
    lines = raw.split(b"\n")
    caps = sum(map(bytes.isupper, words))
    return [
        np.log1p(n), np.log1p(len(words)), float(sizes.mean()), float(sizes.std()), kind[1], kind[3], kind[4], kind[1] + kind[2] + kind[5], kind[0],
        counts[33] / n, counts[44] / n, counts[46] / n, len(seen) / w, tops[0] / w, sum(tops) / w, stutter / w, pairs / w,
        n / len(lines), 1 - len(set(lines)) / len(lines), np.log1p(len(lines)), len(zlib.compress(raw, 1)) / (n + 20), kind[5],
        caps / w, float((sizes <= 2).mean()), float((sizes >= 12).mean()), (counts[60] + counts[62]) / n, len(_URL.findall(text)) / w,
        (counts[123] + counts[125] + counts[59]) / n, sum(1 for x in words if x.endswith(b"!!")) / w, cycle / w,
    ]


def seen_gap(words: list[bytes]) -> int:
    """Distance to the next occurrence of the first word, which shows a repeated block of words."""
    try:
        return words.index(words[0], 1)
    except ValueError:
        return len(words)


@dataclass
class Forest:
    """Complete binary trees of one depth as arrays: node i has children 2i+1 and 2i+2."""

    feature: np.ndarray  # trees x inner nodes
    threshold: np.ndarray
    value: np.ndarray  # trees x leaves
    base: float

    def probability(self, x: np.ndarray) -> np.ndarray:
        total, rows = np.full(len(x), self.base), np.arange(len(x))
        depth = int(np.log2(self.value.shape[1])) if len(self.value) else 0
        for feature, threshold, value in zip(self.feature, self.threshold, self.value, strict=True):
            node = np.zeros(len(x), np.int64)
            for _ in range(depth):
                node = 2 * node + 1 + (x[rows, feature[node]] > threshold[node])
            total += value[node - (len(value) - 1)]
        return 1 / (1 + np.exp(-total))


def grow(x: np.ndarray, y: np.ndarray, trees: int = TREES, depth: int = DEPTH, rate: float = RATE) -> Forest:
    """Level-wise boosting for logistic loss on quantile bins."""
    if not len(y):
        return Forest(np.zeros((0, 1), int), np.zeros((0, 1)), np.zeros((0, 2)), 0.0)
    mean = min(max(float(y.mean()), 1e-4), 1 - 1e-4)
    base = float(np.log(mean / (1 - mean)))
    inner, leaves = (1 << depth) - 1, 1 << depth
    if len(np.unique(y)) < 2:
        return Forest(np.zeros((0, inner), int), np.zeros((0, inner)), np.zeros((0, leaves)), base)
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, BINS + 1)[1:-1])) for j in range(x.shape[1])]
    binned = np.column_stack([np.searchsorted(e, x[:, j], "left") for j, e in enumerate(edges)]).astype(np.int64)
    total = np.full(len(y), base)
    features, thresholds, values = [], [], []
    for _ in range(trees):
        p = 1 / (1 + np.exp(-total))
        g, h = y - p, p * (1 - p)
        node = np.zeros(len(y), np.int64)
        feature, threshold = np.zeros(inner, np.int64), np.full(inner, np.inf)
        for level in range(depth):
            first, width = (1 << level) - 1, 1 << level
            best_gain, best = np.zeros(width), [(0, np.inf, BINS)] * width
            local = node - first
            sums = [np.bincount(local, weights=v, minlength=width) for v in (g, h)]
            for j, e in enumerate(edges):
                key = local * BINS + binned[:, j]
                gs, hs, ns = (np.cumsum(np.bincount(key, weights=v, minlength=width * BINS).reshape(width, BINS), axis=1) for v in (g, h, None))
                gl, hl, nl = gs[:, :-1], hs[:, :-1], ns[:, :-1]
                gr, hr, nr = sums[0][:, None] - gl, sums[1][:, None] - hl, ns[:, -1:] - nl
                gain = gl**2 / (hl + RIDGE) + gr**2 / (hr + RIDGE) - (sums[0] ** 2 / (sums[1] + RIDGE))[:, None]
                gain[(nl < MIN_ROWS) | (nr < MIN_ROWS)] = -1
                at = gain.argmax(axis=1)
                for k in np.flatnonzero(gain[np.arange(width), at] > best_gain + 1e-9):
                    if at[k] < len(e):
                        best_gain[k], best[k] = gain[k, at[k]], (j, e[at[k]], at[k])
            cut = np.array([b[2] for b in best])
            for k, (j, t, _) in enumerate(best):
                feature[first + k], threshold[first + k] = j, t
            node = 2 * node + 1 + (binned[np.arange(len(y)), feature[node]] > cut[local])
        leaf = node - inner
        gs, hs = (np.bincount(leaf, weights=v, minlength=leaves) for v in (g, h))
        value = rate * gs / (hs + RIDGE)
        total += value[leaf]
        features.append(feature)
        thresholds.append(threshold)
        values.append(value)
    return Forest(np.array(features), np.array(thresholds), np.array(values), base)


def measure(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, stats): a map over rows."""

    def each(batch):
        rows = np.array([statistics(t) for t in texts(batch)], np.float32)
        yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.FixedSizeListArray.from_arrays(pa.array(rows.ravel()), len(NAMES)).cast(pa.list_(pa.float32()))], names=["doc_id", "stats"])

    return map_batches(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")), each, "doc_id long, stats array<float>")


def held_out(id_col: str = "doc_id"):
    """The fold whose labels are never learned."""
    return crc_fold(id_col, 5) == 0


def fit(measured: DataFrame, labels: DataFrame, id_col: str = "doc_id", label_col: str = "quality", train_rows: int = TRAIN_ROWS, keep_out=None) -> Forest:
    """Trees from at most about ``train_rows`` labelled rows (an id hash picks them when there are more)."""
    marks = labels.select(F.col(id_col).alias("doc_id"), F.col(label_col).cast("int").alias("y")).where(F.col("y").isin(0, 1))
    if keep_out is not None:
        marks = marks.where(~keep_out)
    marks = marks.groupBy("doc_id").agg(F.max("y").alias("y"))
    total = marks.count()
    if total > train_rows:
        marks = marks.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < int((1 << 20) * train_rows / total))
    rows = measured.join(marks, "doc_id").select("doc_id", "stats", "y").toArrow().to_pandas().sort_values("doc_id")
    return grow(np.array(rows["stats"].tolist(), float).reshape(-1, len(NAMES)), rows["y"].to_numpy(float))


def score(measured: DataFrame, forest: Forest, threshold: float = THRESHOLD) -> DataFrame:
    shared = measured.sparkSession.sparkContext.broadcast(forest)

    def each(batch):
        flat = batch.column(1).flatten().to_numpy(zero_copy_only=False)
        p = shared.value.probability(flat.reshape(batch.num_rows, len(NAMES)).astype(float))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(p, pa.float64()), pa.array((p >= threshold).astype(np.int32))], names=["doc_id", "score", "predicted"])

    return map_batches(measured, each, "doc_id long, score double, predicted int")


def classify(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> DataFrame:
    """Measure every text once, fit on the labelled rows outside the held-out fold, score every text."""
    measured = written(measure(docs, id_col, text_col), "quality")
    return score(measured, fit(measured, labels, id_col, label_col, keep_out=held_out("doc_id")))


def digest(scored: DataFrame) -> DataFrame:
    """The contract's columns from the operator's own output."""
    return scored.select("doc_id", held_out("doc_id").alias("held_out"), "score", "predicted")
