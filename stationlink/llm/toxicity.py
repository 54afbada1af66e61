"""Toxic passages as maximum-scoring segments of token log-odds.

Tokens are words and their beginnings (so stems that take many endings count as well), hashed to a fixed number of
buckets; a word scores as the best of its tokens. A bucket's score is its log-odds between toxic and other labelled texts
under a Dirichlet prior that follows its frequency in all documents, shrunk by its standard error, less a drift that
makes the expected score of ordinary text negative. One pass over a text's running sums gives its best segment; texts
whose best segment matters are scanned once more for all maximal segments. Best scores of non-toxic labelled texts fix
the extreme-value law (decay from the scores themselves, place from those texts, corrected for length); segments have
p-values under it, and a text's evidence is calibrated to a probability.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stationlink.llm.labelled import MAX_ROWS, labelled_sample
from stationlink.llm.textblocks import ALNUM, U, Words, blocks, words
from stationlink.plans.workspace import materialize

BUCKET_BITS = 18
PRIOR_TOKENS = 500.0
DRIFT = 0.5
#: Standard errors that log-odds lose.
SHRINK = 2.5
#: Segments with a p-value above this are not passages.
SIGNIFICANT = 0.05
#: Lower ends of the classes in which word scores are counted for the extreme-value law.
GRID = np.arange(-8, 9, 0.25)
#: Bytes of the beginnings that are tokens of a longer word.
BEGINNINGS = (4, 5, 6, 7, 8, 9, 10)


def buckets(w: Words) -> np.ndarray:
    """(1 + beginnings, words) buckets; a beginning that isn't shorter than its word is -1."""
    size = w.end - w.start
    out = np.full((1 + len(BEGINNINGS), len(size)), -1, np.int64)
    out[0] = w.hash >> U(64 - BUCKET_BITS)
    for k, n in enumerate(BEGINNINGS):
        longer = np.flatnonzero(size > n)
        out[k + 1, longer] = w.beginnings(longer, n) >> U(64 - BUCKET_BITS)
    return out


def word_scores(w: Words, scores: np.ndarray) -> np.ndarray:
    b = buckets(w)
    return np.r_[scores, -np.inf][b].max(axis=0)


def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Counts of a task by bucket and label (-1: none): tokens of texts without label, texts that have the token of others."""
    total = np.zeros((3, 1 << BUCKET_BITS), np.int64)
    for batch in batches:
        label = batch.column("y").to_numpy(zero_copy_only=False)
        for lo, hi, data, offset in blocks(batch.column("text")):
            w = words(data, offset, ALNUM)
            b, of = buckets(w) + 1, np.repeat(label[lo:hi], np.diff(w.first))
            for k in np.unique(label[lo:hi]):
                own = b[:, of == k]
                if k >= 0:  # a token that one text repeats says no more than once
                    own = np.unique(w.doc[of == k] * (2 << BUCKET_BITS) + own) & ((2 << BUCKET_BITS) - 1)
                total[k + 1] += np.bincount(own.ravel(), minlength=(1 << BUCKET_BITS) + 1)[1:]
    used = np.flatnonzero(total.any(axis=0))
    for lo in range(0, len(used), 1 << 15):
        part = used[lo : lo + (1 << 15)]
        yield pa.RecordBatch.from_arrays([pa.array(part), *[pa.array(total[k, part]) for k in range(3)]], ["bucket", "n_none", "n_clean", "n_toxic"])


def bucket_counts(texts: DataFrame) -> np.ndarray:
    """(3, buckets) counts of unlabelled, clean and toxic tokens over all rows (text, y); bounded, so brought here."""
    parts = texts.mapInArrow(_counted, "bucket long, n_none long, n_clean long, n_toxic long")
    sums = parts.groupBy("bucket").agg(*[F.sum(c).alias(c) for c in ("n_none", "n_clean", "n_toxic")]).toArrow()
    out = np.zeros((3, 1 << BUCKET_BITS))
    for k, c in enumerate(("n_none", "n_clean", "n_toxic")):
        out[k, sums["bucket"].to_numpy()] = sums[c].to_numpy()
    return out


def token_scores(background: np.ndarray, clean: np.ndarray, toxic: np.ndarray) -> np.ndarray:
    """Shrunk log-odds less drift for each bucket."""
    prior = PRIOR_TOKENS * (background + 0.5) / (background + 0.5).sum()

    def log_odds(count: np.ndarray) -> np.ndarray:
        a = count + prior
        return np.log(a / (count.sum() + PRIOR_TOKENS - a))

    error = np.sqrt(1 / (toxic + prior) + 1 / (clean + prior))
    raw = log_odds(toxic) - log_odds(clean)
    shrunk = np.sign(raw) * np.maximum(np.abs(raw) - SHRINK * error, 0)
    return np.clip(shrunk, -4, 8) - DRIFT


def decay(scores: np.ndarray, weight: np.ndarray) -> float:
    """The positive root of the sum of weight * exp(root * score) = 1: how fast best scores fall off."""
    p = weight / weight.sum()
    if not (scores > 0).any() or (p * scores).sum() >= 0:
        return 1.0
    lo, hi = 1e-6, 1.0
    while (p * np.exp(hi * scores)).sum() < 1 and hi < 50:
        hi *= 2
    for _ in range(60):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if (p * np.exp(mid * scores)).sum() < 1 else (lo, mid)
    return (lo + hi) / 2


def best_segments(score: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Largest sum of consecutive scores of each text, 0 if none is positive."""
    n = len(first) - 1
    if not len(score):
        return np.zeros(n)
    total = np.r_[0.0, np.cumsum(score)]
    doc = np.repeat(np.arange(n), np.diff(first))
    step = np.abs(score).sum() + 1.0  # each text starts below all before it, so the running minimum starts anew
    before = total[:-1] - doc * step
    low = np.minimum.accumulate(before)
    gain = total[1:] - doc * step - low
    out = np.zeros(n)
    some = np.flatnonzero(np.diff(first) > 0)
    out[some] = np.maximum(np.maximum.reduceat(gain, first[some]), 0)
    return out


def maximal_segments(score: np.ndarray) -> list[tuple[int, int, float]]:
    """All maximal scoring segments (start, end, sum) of one text, left to right, by one scan over its positive tokens."""
    total = np.r_[0.0, np.cumsum(score)]
    kept: list[tuple[int, int, float, float, int]] = []  # start, end, sum before, sum after, the last one before it whose sum before is smaller
    for i in np.flatnonzero(score > 0).tolist():
        start, low, high, j = i, total[i], total[i + 1], len(kept) - 1
        while True:
            while j >= 0 and kept[j][2] >= low:
                j = kept[j][4]  # what lies between has no smaller sum before
            if j < 0 or kept[j][3] >= high:
                kept.append((start, i + 1, low, high, j))
                break
            start, low, j = kept[j][0], kept[j][2], kept[j][4]
            while len(kept) and kept[-1][0] >= start:  # each segment is taken out once
                kept.pop()
    return [(int(s), int(e), float(b - a)) for s, e, a, b, _ in kept]


@dataclass
class Model:
    """Token scores, extreme-value law and calibration; of a size that doesn't depend on the data."""

    scores: np.ndarray
    root: float
    place: float
    weights: np.ndarray

    def p_value(self, best: np.ndarray, n: np.ndarray) -> np.ndarray:
        """Chance that ordinary text of n tokens has a segment of this score or more."""
        return -np.expm1(-np.exp(np.clip(-(self.root * best - np.log(np.maximum(n, 1)) - self.place), -50, 50)))

    def evidence(self, w: Words) -> tuple[np.ndarray, dict[int, list[tuple[int, int, float, float]]]]:
        """(features of each text, its significant passages (start, end, score, p)) in words."""
        score, n = word_scores(w, self.scores), np.diff(w.first)
        best = best_segments(score, w.first)
        p = np.where(n > 0, self.p_value(best, n), 1.0)
        passages, total, number = {}, np.zeros(len(n)), np.zeros(len(n))
        for d in np.flatnonzero((p <= SIGNIFICANT) & (best > 0)).tolist():
            found = maximal_segments(score[w.first[d] : w.first[d + 1]])
            chance = self.p_value(np.array([x[2] for x in found]), n[d])
            passages[d] = [(s, e, x, float(q)) for (s, e, x), q in zip(found, chance) if q <= SIGNIFICANT]
            total[d] = sum(x for _, _, x, _ in passages[d])
            number[d] = len(passages[d])
        x = np.stack([np.ones(len(n)), -np.log10(np.maximum(p, 1e-20)), best, np.log1p(total), np.log1p(number), np.log1p(n) / 5], axis=1)
        return x, passages

    def probability(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(x @ self.weights, -30, 30)))


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2) -> np.ndarray:
    """Weights by Newton's method; the first column, the constant, isn't shrunk."""
    w, keep = np.zeros(x.shape[1]), ridge * len(y) * np.eye(x.shape[1]) / 100
    keep[0, 0] = 1e-9
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + keep + 1e-9 * np.eye(len(w)), x.T @ (y - p) - keep @ w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w


def fit(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_ROWS) -> Model:
    """Scores from labels of rows that aren't held out (at most ``max_rows``), prior counts from all documents."""
    spark = docs.sparkSession
    sample = materialize(labelled_sample(docs, labels, F.col("toxic").cast("int"), max_rows), "toxic-sample")
    background = bucket_counts(docs.select("text", F.lit(-1).alias("y")))[0]
    counts = bucket_counts(sample.select("text", "y"))
    scores = token_scores(background, counts[1], counts[2])
    model = Model(scores, 1.0, 0.0, np.zeros(6))
    bare = spark.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            for lo, hi, data, offset in blocks(batch.column("text")):
                w = words(data, offset, ALNUM)
                score = word_scores(w, bare.value.scores)
                place = w.doc * len(GRID) + np.searchsorted(GRID, score, "right").clip(1) - 1
                level = np.bincount(place, minlength=(hi - lo) * len(GRID)).reshape(hi - lo, len(GRID))
                yield pa.RecordBatch.from_arrays([batch.column("y")[lo:hi], pa.array(best_segments(score, w.first)), pa.array(np.diff(w.first)), pa.array(list(level))], ["y", "best", "n", "level"])

    got = sample.select("text", "y").mapInArrow(run, "y int, best double, n long, level array<long>").toArrow()  # at most max_rows
    y, best, n = (got[c].to_numpy() for c in ("y", "best", "n"))
    ordinary = (y == 0) & (n > 0)
    if ordinary.any():
        level = np.array(got["level"].to_pylist())[ordinary].sum(axis=0).astype(float)
        model.root = decay(GRID + 0.125, level)
    # Mean of a Gumbel variable is its place plus Euler's constant; zeros stand for "no positive token".
    moved = model.root * best[ordinary] - np.log(np.maximum(n[ordinary], 1))
    model.place = float(moved.mean() - 0.5772156649) if ordinary.any() else 0.0
    calibrated = spark.sparkContext.broadcast(model)

    def features(batches):
        for batch in batches:
            for lo, hi, data, offset in blocks(batch.column("text")):
                x, _ = calibrated.value.evidence(words(data, offset, ALNUM))
                yield pa.RecordBatch.from_arrays([batch.column("y")[lo:hi], *[pa.array(x[:, k]) for k in range(6)]], ["y", *[f"x{k}" for k in range(6)]])

    got = sample.select("text", "y").mapInArrow(features, "y int, " + ", ".join(f"x{k} double" for k in range(6))).toArrow()
    if got.num_rows:
        model.weights = logistic(np.stack([got[f"x{k}"].to_numpy() for k in range(6)], axis=1), got["y"].to_numpy().astype(float))
    return model


def score(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, score, passages) of every row; passages are word ranges [start, end) with score and p-value.

    Null and empty texts have no passage and the score of the calibration there. Rows that repeat are rows of their own;
    other columns are ignored.
    """
    known = docs.sparkSession.sparkContext.broadcast(model)
    kind = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("score", pa.float64()), ("p", pa.float64())]))

    def run(batches):
        for batch in batches:
            for lo, hi, data, offset in blocks(batch.column("text")):
                x, passages = known.value.evidence(words(data, offset, ALNUM))
                found = [[dict(zip(("start", "end", "score", "p"), s)) for s in passages.get(d, [])] for d in range(hi - lo)]
                yield pa.RecordBatch.from_arrays([batch.column("doc_id")[lo:hi], pa.array(known.value.probability(x)), pa.array(found, kind)], ["doc_id", "score", "passages"])

    schema = "doc_id long, score double, passages array<struct<start:int,end:int,score:double,p:double>>"
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, schema)
