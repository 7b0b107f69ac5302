"""Toxicity by maximum-scoring segments of token log-odds.

Each token gets the log-odds of its rate in toxic against clean labelled texts, smoothed by a Dirichlet prior that is
spread as the counts of the whole corpus are. A linear scan finds every maximal scoring run of tokens in a text
(disjoint, each the best of its surroundings); the best run is calibrated by an extreme-value (Gumbel) fit to the best
runs of clean texts, corrected for the length searched, and a two-input logistic fit turns the tail value and the sum
of significant runs into a probability.

Words that alone don't speak for toxicity back off to the strongest of their heads of six, five and four letters,
then to a small negative score.

Defined results: a null or wordless text scores the base rate of the calibration; repeated rows each get their row;
labels that are null or not 0/1 are ignored; without labels of both classes every score is 0; extra columns are ignored.
"""

from __future__ import annotations

import math
import re
import uuid
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from .common import crc_fold, filter_batches, map_batches, texts, written

# Labelled rows that the fit may hold on the driver in counted form; a larger labelled set is sampled by id hash.
TRAIN_ROWS = 40_000
PRIOR_WEIGHT = 200.0
HEADS = (6, 5, 4)
UNSEEN = -0.35
CAP = 6.0
MEMO = 300_000
ERRORS, FOLDS = 2.75, 4
THRESHOLD = 0.3
_WORD = re.compile(r"[^\W_]+")


def words_of(text: str) -> list[str]:
    return _WORD.findall(text.lower())


def maximal_segments(scores: np.ndarray) -> list[tuple[int, int, float]]:
    """All maximal scoring runs [from, to) with their sums, in linear time.

    Neighbouring scores of one sign are summed first; a stack then holds candidate runs as (left sum, right sum), and a
    new run swallows back to the nearest one with a smaller left sum when its right sum tops that one's.
    """
    held: list[list[float]] = []  # from, to, left, right
    links: list[int] = []  # for each held run: the nearest earlier one with a smaller left sum
    total = 0.0
    for at, s in enumerate(scores.tolist()):
        if s <= 0:
            total += s
            continue
        run = [at, at + 1, total, total + s]
        total += s
        while True:
            j = len(held) - 1
            while j >= 0 and held[j][2] >= run[2]:
                j = links[j]
            if j < 0 or held[j][3] >= run[3]:
                held.append(run)
                links.append(j)
                break
            run = [held[j][0], run[1], held[j][2], run[3]]
            del held[j:], links[j:]
    return [(int(a), int(b), right - left) for a, b, left, right in held]


def _compressed(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Only the tokens around positive scores matter one by one; runs of others are summed."""
    positive = values > 0
    starts = np.flatnonzero(positive | np.concatenate([[True], positive[:-1]]))
    return starts, np.add.reduceat(values, starts) if values.size else values


class Model:
    def __init__(self, weights: dict[str, float], heads: dict[str, float], gumbel: tuple[float, float], logistic: tuple[float, float, float] | None):
        self.weights, self.heads, self.gumbel, self.logistic = weights, heads, gumbel, logistic
        self.memo: dict[str, float] = {}

    def value(self, word: str) -> float:
        own = self.weights.get(word, UNSEEN)
        if own <= 0:
            own = max((self.heads[word[:k]] for k in HEADS if word[:k] in self.heads), default=own)
        return own

    def values(self, words: list[str]) -> np.ndarray:
        """Scores of words; a memo of bounded size spares most look-ups."""
        memo = self.memo
        if len(memo) > MEMO:
            memo.clear()
        for x in set(words).difference(memo):
            memo[x] = self.value(x)
        return np.array([memo[x] for x in words], float)

    def passages(self, text: str) -> tuple[list[tuple[int, int, float]], int]:
        words = words_of(text)
        if not words:
            return [], 0
        starts, sums = _compressed(self.values(words))
        ends = np.append(starts[1:], len(words))
        return [(int(starts[a]), int(ends[b - 1]), s) for a, b, s in maximal_segments(sums)], len(words)

    def probability(self, inputs: np.ndarray) -> np.ndarray:
        if self.logistic is None:
            return np.zeros(len(inputs))
        a, b, c = self.logistic
        return 1 / (1 + np.exp(-(a + b * inputs[:, 0] + c * inputs[:, 1])))


def log_odds(toxic: dict[str, int], clean: dict[str, int], prior: dict[str, float], totals: tuple[int, int], weight: float = PRIOR_WEIGHT) -> dict[str, float]:
    """Capped log-odds by token, shrunk to zero where they are within ERRORS standard errors of it."""
    n1, n0 = (total + weight for total in totals)
    out = {}
    for t in toxic.keys() | clean.keys():
        p = weight * prior.get(t, 0.0) + 0.5
        a, b = toxic.get(t, 0) + p, clean.get(t, 0) + p
        delta = math.log(a / (n1 - a)) - math.log(b / (n0 - b))
        error = math.sqrt(1 / a + 1 / b)
        out[t] = max(-CAP, min(CAP, math.copysign(max(0.0, abs(delta) - ERRORS * error), delta)))
    return out


def _logistic(x: np.ndarray, y: np.ndarray, rounds: int = 50, ridge: float = 1.0) -> tuple[float, float, float]:
    design = np.column_stack([np.ones(len(x)), x])
    w = np.zeros(3)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(design @ w, -30, 30)))
        gradient = design.T @ (p - y) + ridge * np.array([0, 1, 1]) * w
        hessian = (design * (p * (1 - p))[:, None]).T @ design + ridge * np.diag([1e-6, 1, 1])
        w = w - np.linalg.solve(hessian, gradient)
    return tuple(float(v) for v in w)


def _with_families(batch):
    """Each row with three least hashes of its five-word runs, which near copies mostly share."""
    keys = []
    for t in texts(batch):
        words = t.encode("utf-8", "surrogatepass").lower().split()
        h = np.array([zlib.crc32(b" ".join(words[i : i + 5])) for i in range(max(1, len(words) - 4))], np.uint64)
        keys.append([int((h * np.uint64(k) % np.uint64(4294967291)).min()) for k in (1, 2654435761, 2246822519)])
    kept = [batch.column(batch.schema.get_field_index(c)) for c in ("doc_id", "text", "y")]
    yield pa.RecordBatch.from_arrays([*kept, *(pa.array([k[i] for k in keys], pa.int64()) for i in range(3))], names=["doc_id", "text", "y", "f0", "f1", "f2"])


def _counts(docs: DataFrame) -> DataFrame:
    """Words of the whole corpus with their counts; each batch counts first, so the shuffle gets sums."""

    def each(batch):
        counted: Counter = Counter()
        for t in texts(batch):
            counted.update(words_of(t))
        yield pa.RecordBatch.from_arrays([pa.array(list(counted), pa.string()), pa.array(list(counted.values()), pa.int64())], names=["word", "n"])

    return map_batches(docs, each, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", train_rows: int = TRAIN_ROWS, held_out=None) -> Model:
    """Learn from at most about ``train_rows`` labelled rows (an id hash picks them when there are more).

    ``held_out``: a Boolean column over ``id_col`` of rows whose labels must not be seen. The corpus counts that spread
    the prior cover every document; only those of words in the labelled sample come to the driver.
    """
    spark = docs.sparkSession
    texts_of = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    marks = labels.select(F.col(id_col).alias("doc_id"), F.col(label_col).cast("int").alias("y")).where(F.col("y").isin(0, 1))
    if held_out is not None:
        marks = marks.where(~held_out)
    marks = marks.groupBy("doc_id").agg(F.max("y").alias("y"))
    total = marks.count()
    if total > train_rows:
        marks = marks.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < int((1 << 20) * train_rows / total))
    train = written(map_batches(texts_of.join(marks, "doc_id").select("doc_id", "text", "y"), _with_families, "doc_id long, text string, y int, f0 long, f1 long, f2 long"), "toxicity-train")
    firsts = train.select("doc_id", *(F.min("doc_id").over(Window.partitionBy(f)).alias(f) for f in ("f0", "f1", "f2"))).where(" and ".join(f"doc_id = {f}" for f in ("f0", "f1", "f2")))
    train = train.drop("f0", "f1", "f2").join(firsts.select("doc_id").distinct(), "doc_id", "left_semi")
    fold = F.pmod(F.xxhash64("doc_id", F.lit("fold")), F.lit(FOLDS)).cast("int").alias("fold")

    def counted(batch):
        ys, fs = (batch.column(batch.schema.get_field_index(c)).to_pylist() for c in ("y", "fold"))
        own: Counter = Counter()
        for t, y, f in zip(texts(batch), ys, fs, strict=True):
            seen = set(words_of(t))
            own.update((w, 0, y, f) for w in seen)
            own.update((w, 1, y, f) for w in {w[:size] for w in seen for size in HEADS if len(w) >= size})
        yield pa.RecordBatch.from_arrays(
            [*(pa.array([k[i] for k in own], kind) for i, kind in enumerate((pa.string(), pa.int32(), pa.int32(), pa.int32()))), pa.array(list(own.values()), pa.int64())],
            names=["token", "head", "y", "fold", "n"],
        )

    amount = lambda y, f: F.sum(F.when((F.col("y") == y) & (F.col("fold") != f), F.col("n")).otherwise(0))
    table = (
        map_batches(train.select("text", "y", fold), counted, "token string, head int, y int, fold int, n long")
        .groupBy("token", "head")
        .agg(*(amount(y, f).alias(f"{name}{f}") for y, name in ((1, "toxic"), (0, "clean")) for f in range(FOLDS + 1)))
        .where(F.col(f"toxic{FOLDS}") + F.col(f"clean{FOLDS}") >= 3)
    )
    table = written(table, "toxicity-table")
    if table.isEmpty():  # no labelled texts, or none that share words: nothing is toxic
        return Model({}, {}, (1.0, 1.0), None)
    corpus = _counts(texts_of)
    size = Observation()
    corpus = corpus.observe(size, F.sum("n").alias("words"))
    told = written(table.join(corpus, (F.col("token") == F.col("word")) & (F.col("head") == 0), "left").drop("word").withColumn("n", F.coalesce("n", F.lit(0))), "toxicity-tokens")
    words = max(1, (size.get or {}).get("words") or 1)
    sums = {r["head"]: r for r in told.groupBy("head").agg(*(F.sum(f"{name}{f}").alias(f"{name}{f}") for name in ("toxic", "clean") for f in range(FOLDS + 1))).collect()}
    # Only tokens whose log-odds stand out in some fold come to the driver; the others would score as unseen ones do.
    share = F.col("n") / words
    prior = PRIOR_WEIGHT * share + 0.5
    stands_out = F.lit(False)
    for head, r in sums.items():
        for f in range(FOLDS + 1):
            a, b = F.col(f"toxic{f}") + prior, F.col(f"clean{f}") + prior
            delta = F.log(a / (r[f"toxic{f}"] + PRIOR_WEIGHT - a)) - F.log(b / (r[f"clean{f}"] + PRIOR_WEIGHT - b))
            error = ERRORS * F.sqrt(1 / a + 1 / b)
            stands_out |= (F.col("head") == head) & F.coalesce((delta > error) | ((-delta - error > -UNSEEN) & F.lit(head == 0)), F.lit(True))
    rows = told.where(stands_out).withColumn("share", share).toArrow().to_pandas()

    def learned(f: int) -> Model:
        """From all rows but those of fold f; f = FOLDS leaves none out."""
        seen = rows[rows[f"toxic{f}"] + rows[f"clean{f}"] > 0]
        toxic, clean, share = ([dict(zip(part["token"], part[c], strict=True)) for part in (seen[seen["head"] == 0], seen[seen["head"] == 1])] for c in (f"toxic{f}", f"clean{f}", "share"))
        total = [tuple(sums[head][f"{name}{f}"] if head in sums else 0 for name in ("toxic", "clean")) for head in (0, 1)]
        words = log_odds(toxic[0], clean[0], share[0], total[0])
        # A head speaks for words that are too rare to speak for themselves; those that do are taken out of its counts.
        for t, v in words.items():
            if v > 0:
                for head in {t[:size] for size in HEADS}:
                    if head in toxic[1]:
                        toxic[1][head] = max(0, toxic[1][head] - toxic[0][t])
        heads = log_odds(toxic[1], clean[1], share[1], total[1])
        words = {t: v if v > 0 else min(v, UNSEEN) for t, v in words.items()}
        return Model({t: v for t, v in words.items() if v != UNSEEN}, {t: v for t, v in heads.items() if v > 0}, (1.0, 1.0), None)

    # Each fold is scored by what the others teach, so the calibration sees no text that its scores were learned from.
    model = learned(FOLDS)
    scored = _score_inputs(train.select("doc_id", "text", "y", fold), [learned(f) for f in range(FOLDS)]).toArrow().to_pandas()
    if scored["y"].nunique() < 2:
        return model
    quiet = scored[scored["y"] == 0]
    best, lengths = quiet["best"].to_numpy(), np.log(np.maximum(quiet["n"].to_numpy(), 1) / 300.0)
    model.gumbel = gumbel_fit(best, lengths)
    x = np.array([model_inputs(model, r) for r in scored[["best", "n", "runs"]].itertuples(index=False)])
    model.logistic = _logistic(x, scored["y"].to_numpy(float))
    return model


def gumbel_fit(best: np.ndarray, lengths: np.ndarray) -> tuple[float, float]:
    """Location and scale by the moments of the best runs of clean texts, with the length effect taken out."""
    beta = max(0.25, float(np.std(best)) * math.sqrt(6) / math.pi)
    for _ in range(5):
        beta = max(0.25, float(np.std(best - beta * lengths)) * math.sqrt(6) / math.pi)
    return max(0.5, float(np.mean(best - beta * lengths)) - 0.5772156649 * beta), beta


def model_inputs(model: Model, row) -> tuple[float, float]:
    """(length-corrected best run on the Gumbel scale, log of the sum of significant runs)."""
    best, n, runs = row
    if n == 0 or len(runs) == 0:
        return (-2.0, 0.0)
    mu, beta = model.gumbel
    z = (best - mu - beta * math.log(max(n, 1) / 300.0)) / beta
    return (max(-2.0, min(12.0, z)), math.log1p(float(sum(r for r in runs if r > mu + beta))))


def _score_inputs(frame: DataFrame, models: list[Model]) -> DataFrame:
    """(y, best, n, runs) of labelled rows, each by the model of its fold."""
    shared, token = frame.sparkSession.sparkContext.broadcast(models), uuid.uuid4().hex

    def each(batch):
        own = _model(shared, token)
        best, sizes, runs = [], [], []
        for t, f in zip(texts(batch), batch.column(3).to_pylist(), strict=True):
            found, n = own[f].passages(t)
            best.append(max((f[2] for f in found), default=0.0))
            sizes.append(n)
            runs.append([f[2] for f in found])
        yield pa.RecordBatch.from_arrays([batch.column(2), pa.array(best, pa.float64()), pa.array(sizes, pa.int64()), pa.array(runs, pa.list_(pa.float64()))], names=["y", "best", "n", "runs"])

    return map_batches(frame, each, "y int, best double, n long, runs array<double>")


_MODELS: dict[str, Model] = {}


def _model(shared, token: str) -> Model:
    if token not in _MODELS:
        _MODELS.clear()
        _MODELS[token] = shared.value
    return _MODELS[token]


SCHEMA = "doc_id long, score double, predicted int, passages array<struct<from: long, to: long, score: double>>"
_PASSAGE = pa.struct([("from", pa.int64()), ("to", pa.int64()), ("score", pa.float64())])


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """One row a document: probability, verdict and the significant passages as runs of words."""
    shared, token = docs.sparkSession.sparkContext.broadcast(model), uuid.uuid4().hex

    def each(batch):
        own = _model(shared, token)
        inputs, passages = [], []
        for t in texts(batch):
            found, n = own.passages(t)
            runs = [f[2] for f in found]
            inputs.append(model_inputs(own, (max(runs, default=0.0), n, runs)))
            passages.append([{"from": a, "to": b, "score": s} for a, b, s in found if s > own.gumbel[0] + 3 * own.gumbel[1]])
        p = own.probability(np.array(inputs, float).reshape(-1, 2))
        yield pa.RecordBatch.from_arrays(
            [batch.column(0).cast(pa.int64()), pa.array(p, pa.float64()), pa.array((p >= threshold).astype(np.int32)), pa.array(passages, pa.list_(_PASSAGE))], names=["doc_id", "score", "predicted", "passages"]
        )

    return map_batches(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")), each, SCHEMA)


def keep_clean(docs: DataFrame, model: Model, text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """The documents under the threshold, with all their columns."""
    shared, token = docs.sparkSession.sparkContext.broadcast(model), uuid.uuid4().hex

    def setup():
        own = _model(shared, token)

        def stays(batch: list[str]) -> list[bool]:
            inputs = []
            for t in batch:
                found, n = own.passages(t)
                runs = [f[2] for f in found]
                inputs.append(model_inputs(own, (max(runs, default=0.0), n, runs)))
            return (own.probability(np.array(inputs, float).reshape(-1, 2)) < threshold).tolist()

        return stays

    return filter_batches(docs, setup, text_col)


def held_out(id_col: str = "doc_id"):
    """The fold whose labels are never learned."""
    return crc_fold(id_col, 4) == 2


def digest(scored: DataFrame) -> DataFrame:
    """The contract's columns from the operator's own output."""
    return scored.select("doc_id", held_out("doc_id").alias("held_out"), "score", "predicted", "passages")
