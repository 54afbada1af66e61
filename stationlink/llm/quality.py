"""Quality by ordinal cumulative-link regression on graded ratings.

Grades 0 < 1 < 2 share one set of weights over hashed text features; ordered thresholds turn a text's sum into the
probability of each grade or better: P(grade >= k) = logistic(sum - threshold k). Features are shares of words (lower
case), shares of word shapes (letters, capitals, digits and each mark, runs as one), and classes of length, word length
and repetition, all hashed to a fixed number of weights.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stationlink.llm.labelled import labelled_sample
from stationlink.llm.names import unused
from stationlink.llm.textblocks import U, Words, blocks, mix, words

GRADES = 3
WEIGHT_BITS = 16
#: Most labelled rows the regression is fitted on.
FIT_ROWS = 10_000
#: Texts whose probability of grade 1 or better is below this are rejected.
ACCEPT = 0.5

_SIZE = 1 << WEIGHT_BITS
_SHAPE = np.arange(256, dtype=np.uint8)
_SHAPE[97:123] = _SHAPE[128:] = ord("a")
_SHAPE[65:91] = ord("A")
_SHAPE[48:58] = ord("0")


def grade(quality: Column, toxic: Column) -> Column:
    """0: rejected by quality; 1: accepted but toxic; 2: accepted. Null without a quality label."""
    return F.when(quality == 0, 0).when(quality == 1, F.when(toxic == 1, 1).otherwise(2))


def _shapes(data: np.ndarray, offset: np.ndarray, spaced: Words) -> Words:
    """Words of ``data`` as shapes."""
    kinds = _SHAPE[data]
    keep = np.ones(len(data), bool)
    keep[1:] = kinds[1:] != kinds[:-1]
    keep[spaced.start] = True
    return words(kinds[keep], np.r_[0, np.cumsum(keep)][offset], lower=False)


def _classes(w: Words) -> np.ndarray:
    """(texts, 3) hashed classes: number of words, mean word length, share of words seen before in the text."""
    n = np.diff(w.first)
    doc = w.doc
    some = np.maximum(n, 1)
    length = np.bincount(doc, (w.end - w.start).astype(float), minlength=len(n)) / some
    order = np.lexsort((w.hash, doc))
    again = (w.hash[order][1:] == w.hash[order][:-1]) & (doc[order][1:] == doc[order][:-1])
    repeated = np.bincount(doc[order][1:][again], minlength=len(n)) / some
    codes = np.stack([np.log2(some).astype(int), np.minimum(length * 2, 60).astype(int) + 100, (repeated * 20).astype(int) + 200], axis=1)
    codes[n == 0] = 999
    return (mix(codes.astype(U) + U(31)) >> U(64 - WEIGHT_BITS)).astype(np.int64)


def features(data: np.ndarray, offset: np.ndarray) -> tuple[list[tuple[np.ndarray, np.ndarray]], np.ndarray]:
    """([(bucket of each word, first) for words and for shapes], classes of each text)."""
    w = words(data, offset)
    s = _shapes(data, offset, w)
    return [((x.hash ^ salt) >> U(64 - WEIGHT_BITS), x.first) for x, salt in ((w, U(0)), (s, U(0xA5A5 << 48)))], _classes(w)


def sums(data: np.ndarray, offset: np.ndarray, weights: np.ndarray) -> np.ndarray:
    """Weighted feature sums of each text of a block."""
    groups, classes = features(data, offset)
    out = weights[classes].sum(axis=1)
    for bucket, first in groups:
        n = np.diff(first)
        total = np.r_[0.0, np.cumsum(weights[bucket.astype(np.int64)])]
        out += (total[first[1:]] - total[first[:-1]]) / np.maximum(n, 1)
    return out


def _sparse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for lo, hi, data, offset in blocks(batch.column("text")):
            groups, classes = features(data, offset)
            doc, place, value = [np.repeat(np.arange(hi - lo), 3)], [classes.ravel()], [np.ones(classes.size)]
            for bucket, first in groups:
                n = np.diff(first)
                code, times = np.unique(np.repeat(np.arange(hi - lo), n) * _SIZE + bucket.astype(np.int64), return_counts=True)
                doc.append(code >> WEIGHT_BITS)
                place.append(code & (_SIZE - 1))
                value.append(times / n[code >> WEIGHT_BITS])
            doc, place, value = (np.concatenate(x) for x in (doc, place, value))
            order = np.argsort(doc, kind="stable")
            ends = pa.array(np.searchsorted(doc[order], np.arange(hi - lo + 1)), pa.int32())
            lists = [pa.ListArray.from_arrays(ends, pa.array(x[order], t)) for x, t in ((place, pa.int32()), (value, pa.float32()))]
            yield pa.RecordBatch.from_arrays([batch.column("y")[lo:hi], *lists], ["y", "place", "value"])


@dataclass
class Model:
    weights: np.ndarray
    thresholds: np.ndarray

    def tails(self, total: np.ndarray) -> np.ndarray:
        """(texts, GRADES - 1): P(grade >= k) for k = 1 and up."""
        return 1 / (1 + np.exp(-np.clip(total[:, None] - self.thresholds, -30, 30)))


def fit_arrays(y: np.ndarray, first: np.ndarray, place: np.ndarray, value: np.ndarray, steps: int = 200, ridge: float = 1e-5) -> Model:
    """Maximum likelihood with a small ridge by adaptive gradient steps; deterministic."""
    w, gaps = np.zeros(_SIZE), np.array([-2.0, *[0.0] * (GRADES - 2)])  # first threshold, logs of the steps above it
    moment, square = np.zeros(_SIZE + len(gaps)), np.zeros(_SIZE + len(gaps))
    row = np.repeat(np.arange(len(y)), np.diff(first))
    for step in range(1, steps + 1):
        total = np.bincount(row, w[place] * value, minlength=len(y))
        thresholds = gaps[0] + np.r_[0.0, np.cumsum(np.exp(gaps[1:]))]
        tail = 1 / (1 + np.exp(-np.clip(total[:, None] - thresholds, -30, 30)))
        full = np.c_[np.ones(len(y)), tail, np.zeros(len(y))]
        slope = full * (1 - full)
        at = np.arange(len(y))
        p = np.maximum(full[at, y] - full[at, y + 1], 1e-12)
        by_total = -(slope[at, y] - slope[at, y + 1]) / p / len(y)
        by_threshold = np.zeros(GRADES + 1)
        np.add.at(by_threshold, y, slope[at, y] / p / len(y))
        np.add.at(by_threshold, y + 1, -slope[at, y + 1] / p / len(y))
        t = by_threshold[1:GRADES]
        by_gaps = np.r_[t.sum(), [t[k:].sum() * np.exp(gaps[k]) for k in range(1, GRADES - 1)]]
        g = np.r_[np.bincount(place, by_total[row] * value, minlength=_SIZE) + ridge * w, by_gaps]
        moment, square = 0.9 * moment + 0.1 * g, 0.999 * square + 0.001 * g * g
        move = 0.2 * (moment / (1 - 0.9**step)) / (np.sqrt(square / (1 - 0.999**step)) + 1e-8) * min(1.0, 2 * (1 - step / (steps + 1)))
        w, gaps = w - move[:_SIZE], gaps - move[_SIZE:]
    return Model(w, gaps[0] + np.r_[0.0, np.cumsum(np.exp(gaps[1:]))])


def fit(docs: DataFrame, labels: DataFrame, max_rows: int = FIT_ROWS) -> Model:
    """Regression on at most ``max_rows`` graded rows outside the held-out fifth. Without any, all texts are accepted."""
    graded = labels.select("doc_id", grade(F.col("quality"), F.col("toxic")).alias("grade"))
    sample = labelled_sample(docs, graded, F.col("grade"), max_rows)
    got = sample.select("text", "y").mapInArrow(_sparse, "y int, place array<int>, value array<float>").toArrow().combine_chunks()
    if not got.num_rows:
        return Model(np.zeros(_SIZE), np.linspace(-9, -5, GRADES - 1))
    place, value = (got[c].combine_chunks() if hasattr(got[c], "combine_chunks") else got[c] for c in ("place", "value"))
    place, value = (x.chunk(0) if isinstance(x, pa.ChunkedArray) else x for x in (place, value))
    first = np.asarray(place.offsets, np.int64)
    y = got["y"].to_numpy().astype(np.int64)
    order = slice(int(first[0]), int(first[-1]))
    return fit_arrays(y, first - first[0], np.asarray(place.values)[order].astype(np.int64), np.asarray(value.values)[order].astype(float))


def score(docs: DataFrame, model: Model, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """Columns ``keep``, expected_grade (0 to GRADES - 1), tail (P of grade 1 or better), accepted, for every row.

    Null and empty texts are scored by their class alone. Rows that repeat are rows of their own. Columns that aren't in
    ``keep`` are ignored, whatever their names.
    """
    name = unused(docs, "__s")
    return _scored(docs, model, name).select(*keep, f"{name}.*")


def _scored(docs: DataFrame, model: Model, name: str) -> DataFrame:
    """``docs`` with a struct ``name`` of the scores; only texts go through Arrow."""
    known = docs.sparkSession.sparkContext.broadcast(model)

    def run(texts: pa.Array) -> pa.Array:
        tails = [known.value.tails(sums(data, offset, known.value.weights)) for _, _, data, offset in blocks(texts)]
        tail = np.concatenate(tails) if tails else np.zeros((0, GRADES - 1))
        return pa.StructArray.from_arrays([pa.array(tail.sum(axis=1)), pa.array(tail[:, 0]), pa.array(tail[:, 0] >= ACCEPT)], ["expected_grade", "tail", "accepted"])

    return docs.withColumn(name, F.arrow_udf(run, "struct<expected_grade:double,tail:double,accepted:boolean>")("text"))


def accepted(docs: DataFrame, model: Model) -> DataFrame:
    """Rows of ``docs`` that are accepted, with all their columns, whatever their names."""
    name = unused(docs, "__s")
    return _scored(docs, model, name).where(f"{name}.accepted").drop(name)
