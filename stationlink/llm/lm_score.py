"""Cross-entropy difference of two matched bigram models that share one vocabulary.

The target model is counted on target texts, the background model on all documents; both have the same order, vocabulary
and interpolation weights. A document's score is its mean loss per word under the target model less that under the
background model: below zero, it is more like the target.

``score_all`` keeps every word and every observed pair: the counts lie in buckets whose number grows with the input.
The most frequent words are broadcast only to look up their counts sooner; what is not among them goes to the bucket of
its pair, meets its counts there, and each text's sums come back. ``fit`` and ``score`` are a model of a given vocabulary
size, with one class for the rest, that also scores texts it was not counted on.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stationlink.llm.textblocks import SPACED, U, Words, blocks, mix, word_hash, words
from stationlink.plans.workspace import materialize

VOCABULARY = 1000
#: Weights of bigram, unigram and uniform estimates; they sum to 1.
BIGRAM, UNIGRAM, UNIFORM = 0.6, 0.35, 0.05
#: Most ids of target documents that are broadcast; more are joined by a shuffle of the texts.
BROADCAST_IDS = 4_000_000
#: Bytes of text for each bucket of counts, and the words that a task holds before it writes them to its buckets.
BUCKET_BYTES, CHUNK_WORDS, CHUNK_TEXTS = 14_000_000, 600_000, 16_384
_START = U(0x5BD1E9955BD1E995)
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def vocabulary(docs: DataFrame, size: int = VOCABULARY) -> list[str]:
    """The most frequent lower-cased words of all texts, ties by code point."""
    found = F.explode(F.regexp_extract_all(F.translate("text", _UPPER, _LOWER), F.lit(r"[^\x20\x09-\x0D]+"), 0))
    counted = docs.select(found.alias("word")).groupBy("word").count()
    return [r["word"] for r in counted.orderBy(F.col("count").desc(), "word").limit(size).collect()]


class Ids:
    """Word hashes to ids 1..V in order of frequency; 0 is any other word."""

    def __init__(self, known: list[str] | np.ndarray):
        hashed = known if isinstance(known, np.ndarray) else np.array([word_hash(w) for w in known], U)
        order = np.argsort(hashed)
        self.keys, self.ids, self.number = hashed[order], order + 1, len(known) + 1

    def of(self, w: Words) -> np.ndarray:
        return self.of_hashes(w.hash)

    def of_hashes(self, hashed: np.ndarray) -> np.ndarray:
        if not len(self.keys):
            return np.zeros(len(hashed), np.int64)
        at = np.minimum(np.searchsorted(self.keys, hashed), len(self.keys) - 1)
        return np.where(self.keys[at] == hashed, self.ids[at], 0).astype(np.int64)


def pairs(ids: np.ndarray, first: np.ndarray, number: int) -> np.ndarray:
    """previous * (number + 1) + word for each word; the previous of a text's first word is ``number``."""
    before = np.empty_like(ids)
    before[1:] = ids[:-1]
    before[first[:-1][np.diff(first) > 0]] = number
    return before * (number) + ids


def _bigrams(ids: Ids):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((2, (ids.number + 1) * ids.number), np.int32)
        for batch in batches:
            target = batch.column("target").to_numpy(zero_copy_only=False)
            for lo, hi, data, offset in blocks(batch.column("text")):
                w = words(data, offset)
                key = pairs(ids.of(w), w.first, ids.number)
                for k, some in enumerate((slice(None), np.repeat(target[lo:hi], np.diff(w.first)))):
                    np.add.at(total[k], key[some], 1)
        used = np.flatnonzero(total[0])
        for lo in range(0, len(used), 1 << 15):
            part = used[lo : lo + (1 << 15)]
            yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(total[0, part].astype(np.int64)), pa.array(total[1, part].astype(np.int64))], ["pair", "n_all", "n_target"])

    return run


def losses(count: np.ndarray) -> np.ndarray:
    """-log2 of the interpolated probability for each (previous, word); count is (number + 1, number)."""
    number = count.shape[1]
    unigram = count.sum(axis=0)
    context = count.sum(axis=1, keepdims=True)
    one = UNIGRAM * unigram / max(unigram.sum(), 1) + UNIFORM / number
    two = np.divide(BIGRAM * count, context, out=np.zeros(count.shape), where=context > 0)
    return -np.log2(two + one)


def marked(docs: DataFrame, target_ids: DataFrame, broadcast_ids: int = BROADCAST_IDS) -> DataFrame:
    """(doc_id, text, target) of every row; target is whether the row's doc_id is among ``target_ids`` (doc_id)."""
    ids = materialize(target_ids.where("doc_id is not null").select("doc_id").distinct().withColumn("__in", F.lit(True)), "target-ids")
    small = F.broadcast(ids) if ids.count() <= broadcast_ids else ids.hint("merge")
    return docs.select("doc_id", "text").join(small, "doc_id", "left").select("doc_id", "text", F.coalesce("__in", F.lit(False)).alias("target"))


def fit(docs: DataFrame, size: int = VOCABULARY) -> tuple[Ids, np.ndarray, np.ndarray]:
    """(ids, target losses, background losses) of rows (text, target boolean)."""
    ids = Ids(vocabulary(docs, size))
    background, target = (losses(c) for c in _counted(docs, ids))
    return ids, target, background


def _counted(docs: DataFrame, ids: Ids) -> np.ndarray:
    """Counts (all, target) x (previous, word) of known words; V * (V + 1) entries each."""
    counted = docs.select("text", "target").mapInArrow(_bigrams(ids), "pair long, n_all long, n_target long")
    sums = counted.groupBy("pair").agg(F.sum("n_all").alias("n_all"), F.sum("n_target").alias("n_target")).toArrow()  # V * (V + 1) rows at most
    count = np.zeros((2, (ids.number + 1) * ids.number))
    for k, c in enumerate(("n_all", "n_target")):
        count[k, sums["pair"].to_numpy()] = sums[c].to_numpy()
    return count.reshape(2, ids.number + 1, ids.number)


def score(docs: DataFrame, model: tuple[Ids, np.ndarray, np.ndarray]) -> DataFrame:
    """(doc_id, n_words, target_loss, background_loss, difference): mean bits a word; null without words.

    Null text has no words; rows that repeat are rows of their own; other columns are ignored.
    """
    known = docs.sparkSession.sparkContext.broadcast((model[0], np.stack([m.ravel() for m in model[1:]])))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, loss = known.value
        for batch in batches:
            for lo, hi, data, offset in blocks(batch.column("text")):
                w = words(data, offset)
                key = pairs(ids.of(w), w.first, ids.number)
                n = np.diff(w.first)
                some = np.flatnonzero(n)
                mean = np.full((2, hi - lo), np.nan)
                if len(some):
                    mean[:, some] = np.add.reduceat(loss[:, key], w.first[some], axis=1) / n[some]
                none = n == 0
                columns = [batch.column("doc_id")[lo:hi], pa.array(n), *[pa.array(x, mask=none) for x in (mean[0], mean[1], mean[0] - mean[1])]]
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n_words", "target_loss", "background_loss", "difference"])

    schema = "doc_id long, n_words long, target_loss double, background_loss double, difference double"
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, schema)


def _bucket(hashed: np.ndarray, buckets: int) -> np.ndarray:
    return (mix(hashed ^ U(0x2545F4914F6CDD1D)) % U(buckets)).astype(np.uint32)


def _chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[list, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(doc_ids, target, words of each text, hashes, hashes of the words before) of whole texts, about CHUNK_WORDS words at a time."""
    held, n_words, n_texts = [], 0, 0

    def joined():
        doc_ids, target, n, word, before = zip(*held)
        return [i for some in doc_ids for i in some], *[np.concatenate(x) for x in (target, n, word, before)]

    for batch in batches:
        flags = batch.column("target").to_numpy(zero_copy_only=False)
        for lo, hi, data, offset in blocks(batch.column("text")):
            w = words(data, offset)
            n = np.diff(w.first)
            before = np.empty_like(w.hash)
            before[1:] = w.hash[:-1]
            before[w.first[:-1][n > 0]] = _START
            held.append((batch.column("doc_id")[lo:hi].to_pylist(), flags[lo:hi].astype(bool), n, w.hash, before))
            n_words, n_texts = n_words + len(w.hash), n_texts + hi - lo
            if n_words >= CHUNK_WORDS or n_texts >= CHUNK_TEXTS:
                yield joined()
                held, n_words, n_texts = [], 0, 0
    if held:
        yield joined()


_CODEC = pa.Codec("zstd", 3)


def _squeezed(*parts: np.ndarray) -> bytes:
    raw = b"".join(x.tobytes() for x in parts)
    return len(raw).to_bytes(4, "little") + _CODEC.compress(raw, asbytes=True)


def _whole(row: bytes) -> bytes:
    return _CODEC.decompress(row[4:], int.from_bytes(row[:4], "little"), asbytes=True)


def _dealt(bucket: np.ndarray, **columns: np.ndarray) -> Iterator[pa.RecordBatch]:
    """A row for each bucket: the bytes of its entries of each column."""
    order = np.argsort(bucket, kind="stable")
    bucket, columns = bucket[order], {name: x[order] for name, x in columns.items()}
    first = _runs(bucket)
    for lo in range(0, len(first), 256):  # rows of 256 buckets at a time
        edge = np.r_[first, len(bucket)][lo : lo + 257]
        cut = [pa.array([_squeezed(x[a:b]) for a, b in zip(edge, edge[1:])], pa.binary()) for x in columns.values()]
        yield pa.RecordBatch.from_arrays([pa.array(bucket[edge[:-1]].astype(np.int64), pa.int64()), *cut], ["bucket", *columns])


def _all(table: pa.Table, name: str, kind: type) -> np.ndarray:
    """The numbers of all rows of a column of squeezed bytes."""
    return np.concatenate([np.zeros(0, kind), *[np.frombuffer(_whole(x), kind) for x in table.column(name).to_pylist() if x is not None]])


def _runs(*columns: np.ndarray) -> np.ndarray:
    """First places of runs of equal rows in sorted columns."""
    new = np.ones(len(columns[0]), bool)
    if len(new):
        new[1:] = False
        for x in columns:
            new[1:] |= x[1:] != x[:-1]
    return np.flatnonzero(new)


def _sums(x: np.ndarray, first: np.ndarray) -> np.ndarray:
    return np.add.reduceat(x, first) if len(first) else np.zeros(0, x.dtype)


def _word_counts(buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, _, _, word, _ in _chunks(batches):
            found, n = np.unique(word, return_counts=True)
            yield from _dealt(_bucket(found, buckets), word=found, n=n)

    return run


def _summed_words(least: int):
    def run(table: pa.Table) -> pa.Table:
        word, at = np.unique(_all(table, "word", U), return_inverse=True)
        n = np.bincount(at, _all(table, "n", np.int64)).astype(np.int64)
        often = n >= least
        return pa.table({"words": pa.array([len(word)], pa.int64()), "word": pa.array([_squeezed(word[often])], pa.binary()), "n": pa.array([_squeezed(n[often])], pa.binary())})

    return run


class _Pairs:
    """What all tasks know: the number of buckets, and counts of the most frequent words (``ids``)."""

    def __init__(self, buckets: int, ids: Ids, count: np.ndarray, number: int):
        self.buckets, self.ids, self.number = buckets, ids, number
        self.hash_of = np.zeros(ids.number + 1, U)
        self.hash_of[ids.ids], self.hash_of[ids.number] = ids.keys, _START
        self.word, self.context, self.total = count.sum(axis=1), count.sum(axis=2), count.sum(axis=(1, 2))
        c, u = self.context[:, :, None], self.word[:, None, :]
        self.known = np.stack([self.loss(k, count[k], c[k], u[k]) for k in (1, 0)])  # target, background

    def loss(self, k: int, pair: np.ndarray, context: np.ndarray, word: np.ndarray) -> np.ndarray:
        one = UNIGRAM * word / max(self.total[k], 1) + UNIFORM / self.number
        two = np.divide(BIGRAM * pair, context, out=np.zeros(np.broadcast_shapes(np.shape(pair), np.shape(context))), where=context > 0)
        return -np.log2(two + one)

    def ids_before(self, before: np.ndarray) -> np.ndarray:
        return np.where(before == _START, self.ids.number, self.ids.of_hashes(before))

    def bucket(self, before: np.ndarray, before_id: np.ndarray, word: np.ndarray) -> np.ndarray:
        """By the word before, whose pairs then are together; by the word, which one bucket then asks for, if that before is frequent."""
        return _bucket(np.where(before_id > 0, word, before), self.buckets)

    def read(self, row: bytes) -> tuple[np.ndarray, ...]:
        """(before, word, text, n) of written entries."""
        data, at = _whole(row), 16
        known, runs, rest, rare = np.frombuffer(data, np.uint32, 4).tolist()

        def take(number: int, kind: type) -> np.ndarray:
            nonlocal at
            out = np.frombuffer(data, kind, number, at)
            at += out.nbytes
            return out

        of = self.hash_of
        before_id, word, before, size, word_id, rare_word = take(known, np.uint16), take(known, U), take(runs, U), take(runs, np.uint32), take(rest, np.uint16), take(rare, U)
        other = of[word_id]
        other[word_id == 0] = rare_word
        return np.r_[of[before_id], np.repeat(before, size)], np.r_[word, other], take(known + rest, np.uint16), take(known + rest, np.uint8)


def _asked(known):
    """Counts of words that aren't frequent, with the buckets that ask for them, to the words' buckets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = known.value
        for _, target, n, word, before in _chunks(batches):
            rare = p.ids.of_hashes(word) == 0
            flag, word, before = np.repeat(target, n)[rare], word[rare], before[rare]
            asks = p.bucket(before, p.ids_before(before), word)
            order = np.lexsort((asks, word))
            word, asks, flag = word[order], asks[order], flag[order].astype(np.int32)
            first = _runs(word, asks)
            n_all = np.diff(np.r_[first, len(word)]).astype(np.int32)
            yield from _dealt(_bucket(word[first], p.buckets), word=word[first], asks=asks[first], n=n_all, k=_sums(flag, first).astype(np.int32))

    return run


def _told(known):
    def run(table: pa.Table) -> pa.Table:
        p = known.value
        word, at = np.unique(_all(table, "word", U), return_inverse=True)
        n, k = (np.bincount(at, _all(table, c, np.int32), len(word)).astype(np.int64) for c in "nk")
        asked = np.unique(at * p.buckets + _all(table, "asks", np.uint32).astype(np.int64))
        at, asks = asked // p.buckets, asked % p.buckets
        return pa.Table.from_batches(_dealt(asks, word=word[at], n=n[at], k=k[at]), pa.schema([("bucket", pa.int64()), *[(c, pa.binary()) for c in ("word", "n", "k")]]))

    return run


def _bytes(n: np.ndarray) -> np.ndarray:
    """Numbers as sums of bytes: 255 as often as it fits, and the rest."""
    parts = -(-n // 255)
    out = np.full(parts.sum(), 255, np.uint8)
    out[np.cumsum(parts) - 1] = n - 255 * (parts - 1)
    return out


def _written(before: np.ndarray, before_id: np.ndarray, word: np.ndarray, word_id: np.ndarray, text: np.ndarray, n: np.ndarray) -> bytes:
    """Entries of one chunk and bucket, sorted by the word before: frequent words as ids, the others as hashes."""
    known = before_id > 0
    rest, own = ~known, before[~known]
    run = _runs(own)
    size = np.diff(np.r_[run, len(own)]).astype(np.uint32)
    rare = word_id[rest] == 0
    numbers = np.array([known.sum(), len(run), len(own), rare.sum()], np.uint32)
    order = np.r_[np.flatnonzero(known), np.flatnonzero(rest)]
    return _squeezed(numbers, before_id[known].astype(np.uint16), word[known], own[run], size, word_id[rest].astype(np.uint16), word[rest][rare], text[order], n[order])


_ENTRY_SCHEMA = "bucket long, chunk long, entries binary, doc_ids array<long>, n_words binary, sums binary"


def _entries(known):
    """Pairs of each chunk of texts to the pairs' buckets, and one row a chunk with its texts and the sums known so far."""
    from pyspark import TaskContext

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p, chunk = known.value, TaskContext.get().partitionId() << 32
        names = [c.split()[0] for c in _ENTRY_SCHEMA.split(", ")]

        def row(**given: pa.Array) -> pa.RecordBatch:
            kinds = {"bucket": pa.int64(), "chunk": pa.int64(), "doc_ids": pa.list_(pa.int64())}
            n = len(given["bucket"])
            return pa.RecordBatch.from_arrays([given.get(c, pa.nulls(n, kinds.get(c, pa.binary()))) for c in names], names)

        for doc_ids, target, n, word, before in _chunks(batches):
            text = np.repeat(np.arange(len(n)), n)
            word_id, before_id = p.ids.of_hashes(word), p.ids_before(before)
            both = (word_id > 0) & (before_id > 0)
            sums = np.stack([np.bincount(text[both], p.known[m][before_id[both], word_id[both]], len(n)) for m in range(2)])
            rest = ~both
            text, word, before, before_id = (text * 2 + np.repeat(target, n))[rest].astype(np.uint16), word[rest], before[rest], before_id[rest]
            bucket = p.bucket(before, before_id, word)
            order = np.lexsort((word, before))  # stable: texts ascend within a pair
            order = order[np.argsort(bucket[order], kind="stable")]
            bucket, before, word, text = bucket[order], before[order], word[order], text[order]
            first = _runs(before, word, text)
            times = np.diff(np.r_[first, len(word)])
            first, times = np.repeat(first, -(-times // 255)), _bytes(times)
            bucket, before, word, text = bucket[first], before[first], word[first], text[first]
            before_id, word_id = p.ids_before(before), p.ids.of_hashes(word)
            start = _runs(bucket)
            for lo in range(0, len(start), 256):  # rows of 256 buckets at a time
                edge = np.r_[start, len(bucket)][lo : lo + 257]
                rows = [_written(*[x[a:z] for x in (before, before_id, word, word_id, text, times)]) for a, z in zip(edge, edge[1:])]
                yield row(bucket=pa.array(bucket[edge[:-1]].astype(np.int64)), chunk=pa.array([chunk] * len(rows)), entries=pa.array(rows, pa.binary()))
            yield row(
                bucket=pa.array([chunk % p.buckets], pa.int64()), chunk=pa.array([chunk]), doc_ids=pa.array([doc_ids], pa.list_(pa.int64())),
                n_words=pa.array([n.astype(np.int64).tobytes()], pa.binary()), sums=pa.array([sums.tobytes()], pa.binary()),
            )
            chunk += 1

    return run


_SUM_SCHEMA = "chunk long, text binary, target binary, background binary, doc_ids array<long>, n_words binary, sums binary"


def _met(known):
    """Entries of one bucket with all counts of their pairs: sums of losses for each chunk's texts."""

    def run(entries: pa.Table, told: pa.Table) -> pa.Table:
        p = known.value
        base = entries.filter(pc.is_valid(entries.column("n_words")))
        rows = entries.filter(pc.is_null(entries.column("n_words")))
        got = [p.read(x) for x in rows.column("entries").to_pylist()]
        length = np.array([len(x[3]) for x in got], np.int64)
        before, word, text, n = (np.concatenate(x) for x in (zip(*got) if got else [np.zeros(0, k)[None] for k in (U, U, np.uint16, np.uint8)]))
        del got
        order = np.lexsort((word, before)).astype(np.int32)
        before, word = before[order], word[order]
        first = _runs(before, word)
        times = n[order].astype(np.int64)
        pair = np.stack([_sums(times, first), _sums(times * (text[order] & 1), first)])
        of_entry = np.empty(len(order), np.int32)
        of_entry[order] = np.repeat(np.arange(len(first)), np.diff(np.r_[first, len(order)]))
        del times, order
        before, word = before[first], word[first]
        group = _runs(before)
        own = np.repeat(np.arange(len(group)), np.diff(np.r_[group, len(before)]))
        before_id, word_id = p.ids_before(before), p.ids.of_hashes(word)
        known_words = _all(told, "word", U)
        by_word = np.argsort(known_words)
        known_words = known_words[by_word]
        rare = np.flatnonzero(word_id == 0)
        at = by_word[np.searchsorted(known_words, word[rare])]
        loss = []
        for k, c in ((1, "k"), (0, "n")):
            context = np.where(before_id > 0, p.context[k][before_id], _sums(pair[k], group)[own])
            unigram = p.word[k][word_id]
            unigram[rare] = _all(told, c, np.int64)[at]
            loss.append(p.loss(k, pair[k], context, unigram)[of_entry] * n)
        edge = np.r_[0, np.cumsum(length)]
        out = []
        for j, chunk in enumerate(rows.column("chunk").to_pylist()):
            part = slice(edge[j], edge[j + 1])
            found, at = np.unique(text[part] >> 1, return_inverse=True)
            out.append((chunk, found.astype(np.uint16).tobytes(), *[np.bincount(at, x[part], len(found)).tobytes() for x in loss]))
        names, none = ["chunk", "text", "target", "background"], pa.nulls(len(out), pa.binary())
        kinds = [pa.int64(), pa.binary(), pa.binary(), pa.binary()]
        sums = pa.table([*[pa.array([r[i] for r in out], kind) for i, kind in enumerate(kinds)], pa.nulls(len(out), pa.list_(pa.int64())), none, none], [*names, "doc_ids", "n_words", "sums"])
        none = pa.nulls(len(base), pa.binary())
        kept = pa.table([base.column("chunk"), none, none, none, base.column("doc_ids").cast(pa.list_(pa.int64())), base.column("n_words"), base.column("sums")], sums.column_names)
        return pa.concat_tables([sums, kept.cast(sums.schema)])

    return run


def _texts(table: pa.Table) -> pa.Table:
    """Rows of one chunk's texts from its sums in all buckets."""
    base = next(r for r in table.select(["doc_ids", "n_words", "sums"]).to_pylist() if r["n_words"] is not None)
    n = np.frombuffer(base["n_words"], np.int64)
    sums = np.frombuffer(base["sums"], np.float64).reshape(2, len(n)).copy()
    for r in table.select(["text", "target", "background"]).to_pylist():
        if r["text"] is not None:
            at = np.frombuffer(r["text"], np.uint16)
            for m, c in enumerate(("target", "background")):
                sums[m, at] += np.frombuffer(r[c], np.float64)
    none = n == 0
    mean = sums / np.maximum(n, 1)
    return pa.table([pa.array(base["doc_ids"], pa.int64()), pa.array(n), *[pa.array(x, mask=none) for x in (mean[0], mean[1], mean[0] - mean[1])]], ["doc_id", "n_words", "target_loss", "background_loss", "difference"])


def score_all(docs: DataFrame) -> DataFrame:
    """``score`` of each of the rows (doc_id, text, target) under models of all their words and pairs."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", "target")
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = max(8, -(-size // BUCKET_BYTES))
    words_of = docs.mapInArrow(_word_counts(buckets), "bucket long, word binary, n binary").groupBy("bucket")
    # At most size / 2 / least words are that frequent.
    found = words_of.applyInArrow(_summed_words(max(1, size // 200_000)), "words long, word binary, n binary").toArrow()
    word, n = _all(found, "word", U), _all(found, "n", np.int64)
    ids = Ids(word[np.lexsort((word, -n))[:VOCABULARY]])
    pairs_known = _Pairs(buckets, ids, _counted(docs, ids), sum(found.column("words").to_pylist()) + 1)
    known = docs.sparkSession.sparkContext.broadcast(pairs_known)
    told = docs.mapInArrow(_asked(known), "bucket long, word binary, asks binary, n binary, k binary").groupBy("bucket").applyInArrow(_told(known), "bucket long, word binary, n binary, k binary")
    entries = docs.mapInArrow(_entries(known), _ENTRY_SCHEMA)
    sums = entries.groupBy("bucket").cogroup(told.groupBy("bucket")).applyInArrow(_met(known), _SUM_SCHEMA)
    return sums.groupBy("chunk").applyInArrow(_texts, "doc_id long, n_words long, target_loss double, background_loss double, difference double")
