"""Benchmark decontamination by winnowed fingerprints that are extended to whole shared spans.

Hashes of K consecutive words are thinned to the smallest (the rightmost of equals) in every window of WINDOW hashes, in
documents and benchmark items alike. A shared span of SPAN = K + WINDOW - 1 words fills a window on either side, which
then selects the same place in it; so each such span has a common fingerprint, and comparing words along that diagonal
finds all of it. Items of fewer than SPAN words keep the hash of all their words, looked up at every place of a document.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stationlink.llm.names import unused
from stationlink.llm.textblocks import ALNUM, U, blocks, ngram_counts, ngrams, words
from stationlink.plans.workspace import materialize

SPAN = 10
K = 5
WINDOW = SPAN - K + 1
#: Most bytes of benchmark text sent to executors at once; a larger benchmark takes several passes over the documents.
PASS_BYTES = 32 << 20


def winnow(grams: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Sorted places of the selected grams; first[d]..first[d+1] are the places of text d."""
    place, _ = ngram_counts(first, WINDOW)
    if not len(place):
        return place
    least, at = grams[place], place.copy()
    for j in range(1, WINDOW):
        other = grams[place + j]
        low = other <= least
        least[low], at[low] = other[low], place[low] + j
    return np.unique(at)


class Fingerprints:
    """Fingerprints of benchmark items [(item_id, text)]; small enough to be sent to executors."""

    def __init__(self, items: list[tuple[str, str]]):
        self.ids: list[str] = []
        self.words: list[np.ndarray] = []
        seeds: dict[int, list[tuple[int, int]]] = defaultdict(list)
        short: dict[int, dict[int, list[int]]] = defaultdict(lambda: defaultdict(list))
        for item_id, text in items:
            data = np.frombuffer(text.encode(), np.uint8)
            h = words(data, np.array([0, len(data)]), ALNUM).hash
            if not len(h):
                continue
            k = len(self.ids)
            self.ids.append(item_id)
            self.words.append(h)
            if len(h) < SPAN:
                short[len(h)][int(ngrams(h, len(h))[0])].append(k)
            else:
                g = ngrams(h, K)
                for p in winnow(g, np.array([0, len(g)])):
                    seeds[int(g[p])].append((k, int(p)))
        self.seeds, self.short = dict(seeds), {n: dict(x) for n, x in short.items()}
        self.keys = np.array(sorted(self.seeds), U)
        self.maybe = np.zeros(1 << 16, bool)
        self.maybe[(self.keys >> U(48)).astype(np.int64)] = True

    def hits(self, data: np.ndarray, offset: np.ndarray) -> tuple[np.ndarray, dict[int, list[tuple[int, int]]], dict[int, set[str]]]:
        """(words of each text, word spans by text, item ids by text) of a block."""
        w = words(data, offset, ALNUM)
        spans: dict[int, list[tuple[int, int]]] = defaultdict(list)
        items: dict[int, set[str]] = defaultdict(set)
        doc = w.doc
        if len(self.keys):
            place, count = ngram_counts(w.first, K)
            grams = ngrams(w.hash, K)[place]
            starts = np.r_[0, np.cumsum(count)]
            got = winnow(grams, starts)
            got = got[self.maybe[(grams[got] >> U(48)).astype(np.int64)]]
            got = got[np.isin(grams[got], self.keys)]
            seen = set()
            for p, g in zip(place[got].tolist(), grams[got].tolist()):
                d = int(doc[p])
                for k, q in self.seeds[g]:
                    if (d, k, p - q) not in seen:
                        seen.add((d, k, p - q))
                        self._extend(w, d, k, p - q, spans, items)
        for n, known in self.short.items():
            place, _ = ngram_counts(w.first, n)
            grams = ngrams(w.hash, n)[place]
            for p, g in zip(place[m := np.isin(grams, np.array(list(known), U))].tolist(), grams[m].tolist()):
                d = int(doc[p])
                at = p - int(w.first[d])
                for k in known[g]:
                    if np.array_equal(w.hash[p : p + n], self.words[k]):
                        spans[d].append((at, at + n))
                        items[d].add(self.ids[k])
        return np.diff(w.first), spans, items

    def _extend(self, w, d: int, k: int, shift: int, spans, items) -> None:
        """All spans of SPAN words or more on which text d and item k agree at this shift."""
        own, lo, hi = self.words[k], int(w.first[d]), int(w.first[d + 1])
        a, b = max(lo, shift), min(hi, shift + len(own))
        same = np.zeros(b - a + 2, np.int8)
        same[1:-1] = w.hash[a:b] == own[a - shift : b - shift]
        turn = np.diff(same)
        for s, e in zip(np.flatnonzero(turn == 1), np.flatnonzero(turn == -1)):
            if e - s >= SPAN:
                spans[d].append((int(a + s) - lo, int(a + e) - lo))
                items[d].add(self.ids[k])


def _merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for s, e in sorted(spans):
        if out and s <= out[-1][1]:
            out[-1] = (out[-1][0], max(e, out[-1][1]))
        else:
            out.append((s, e))
    return out


_SPANS = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))
_FOUND = "struct<n_words:bigint,spans:array<struct<start:int,end:int>>,items:array<string>>"


def _marked(fingerprints, before: Column | None) -> Column:
    """Findings of one pass as a struct, joined with those of the passes ``before``; only texts and findings go through Arrow."""

    def found(texts: pa.Array, old: pa.Array | None) -> pa.Array:
        known = fingerprints.value
        n_words, all_spans, all_items = [], [], []
        for lo, hi, data, offset in blocks(texts):
            counts, spans, items = known.hits(data, offset)
            n_words.append(counts)
            for d in range(hi - lo):
                was = old[lo + d].as_py() if old is not None else None
                a, b = ([(x["start"], x["end"]) for x in was["spans"]], was["items"]) if was else ([], [])
                if d in spans:
                    a, b = _merged(a + spans[d]), sorted({*b, *items[d]})
                all_spans.append([{"start": s, "end": e} for s, e in a])
                all_items.append(b)
        n = pa.array(np.concatenate(n_words) if n_words else [], pa.int64())
        return pa.StructArray.from_arrays([n, pa.array(all_spans, _SPANS), pa.array(all_items, pa.list_(pa.string()))], ["n_words", "spans", "items"])

    def first(texts: pa.Array) -> pa.Array:
        return found(texts, None)

    def further(texts: pa.Array, old: pa.Array) -> pa.Array:
        return found(texts, old)

    return F.arrow_udf(first, _FOUND)("text") if before is None else F.arrow_udf(further, _FOUND)("text", before)


def find_contamination(docs: DataFrame, benchmark: DataFrame, keep: tuple[str, ...] = ("doc_id",), pass_bytes: int = PASS_BYTES) -> DataFrame:
    """Columns ``keep`` of docs, n_words, spans (word ranges [start, end), merged, in order), items (ids, sorted).

    Null text has no words; a benchmark row without words is in no document; a null item id is named "". Rows that repeat
    an id are rows of their own among documents, and one item with several texts in the benchmark. Other columns are
    ignored. An empty benchmark hits nothing.
    """
    name = unused(docs, "__f")
    return _found(docs, benchmark, pass_bytes, name).select(*keep, f"{name}.*")


def _found(docs: DataFrame, benchmark: DataFrame, pass_bytes: int, name: str) -> DataFrame:
    """``docs`` with a struct ``name`` of the findings."""
    spark = docs.sparkSession
    items = benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("item_id"), F.coalesce("text", F.lit("")).alias("text"))
    size = items.agg(F.coalesce(F.sum(F.octet_length("text") + 64), F.lit(0))).first()[0]
    passes = max(1, -(-int(size) // pass_bytes))
    out = docs
    for k in range(passes):
        part = items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(passes)) == k) if passes > 1 else items
        known = spark.sparkContext.broadcast(Fingerprints([(r.item_id, r.text) for r in part.collect()]))
        out = out.withColumn(name, _marked(known, F.col(name) if k else None))
        if k < passes - 1:
            out = materialize(out, "marked")
    return out


def drop_contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """Rows of ``docs`` that hold no window of the benchmark, with all their columns, whatever their names."""
    name = unused(docs, "__f")
    return _found(docs, benchmark, PASS_BYTES, name).where(F.size(f"{name}.items") == 0).drop(name)
