"""Near-duplicate documents by HyperMinHash registers, banding, estimate and exact confirmation.

A text's distinct shingles of five words are hashed once and dealt to ``REGISTERS`` buckets; a bucket keeps its smallest
hash as six bits of leading zeros and ten bits of mantissa. An empty bucket takes the register of the text's bucket that
comes first in an order fixed for that place, so short texts fill all registers too. Four registers make a band; texts
that share a band are candidates, the Jaccard estimate corrected for register collisions drops those far off, and what is
left is confirmed on full shingle sets. Texts with equal sets are one class from the start; only classes are compared.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stationlink.llm.textblocks import U, blocks, mix, ngram_counts, ngrams, words
from stationlink.operators.components import components
from stationlink.plans.workspace import materialize

SHINGLE = 5
REGISTERS = 160
ROWS = 4
BANDS = REGISTERS // ROWS
MANTISSA = 10
#: Candidates whose estimate is this far (in standard deviations of the estimate) below the threshold are not confirmed.
SLACK = 6.0
HUB_ROUNDS = 2
#: Bands with more than one part in so many of all members are divided.
HOT_BANDS = 4000
#: About how many shingles and texts a block has that is compared with another one as a whole.
BLOCK_SHINGLES, BLOCK_ROWS = 1 << 15, 256

_ORDER = np.argsort(mix(np.arange(REGISTERS * REGISTERS, dtype=U) + U(77)).reshape(REGISTERS, REGISTERS), axis=1)
_RANK = np.argsort(_ORDER, axis=1)
_BAND_SALT = mix(np.arange(BANDS, dtype=U) + U(1234567))


def shingle_sets(data: np.ndarray, offset: np.ndarray, k: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, first) of a block: hashes[first[d]:first[d+1]] are the distinct shingles of text d, sorted."""
    w = words(data, offset)
    place, count = ngram_counts(w.first, k)
    full = ngrams(w.hash, k)[place]
    doc = np.repeat(np.arange(len(count)), count)
    short = np.flatnonzero((count == 0) & (np.diff(w.first) > 0))
    if len(short):
        one = np.array([ngrams(w.hash[w.first[d] : w.first[d + 1]], int(w.first[d + 1] - w.first[d]))[0] for d in short], U)
        full, doc = np.r_[full, one], np.r_[doc, short]
    order = np.lexsort((full, doc))
    full, doc = full[order], doc[order]
    new = np.ones(len(full), bool)
    new[1:] = (full[1:] != full[:-1]) | (doc[1:] != doc[:-1])
    full, doc = full[new], doc[new]
    return full, np.searchsorted(doc, np.arange(len(count) + 1))


def compress(smallest: np.ndarray) -> np.ndarray:
    """Leading zeros (6 bits) and the next MANTISSA bits of each 64-bit minimum, as 16 bits."""
    exponent = np.frexp((smallest >> U(11)).astype(np.float64))[1]  # exact: 53 bits
    zeros = np.minimum(53 - exponent, 63 - MANTISSA).astype(U)
    mantissa = ((smallest << zeros) << U(1)) >> U(64 - MANTISSA)
    return ((zeros << U(MANTISSA)) | mantissa).astype(np.uint16)


def signatures(hashes: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Registers (texts x REGISTERS) of sets that aren't empty."""
    n = len(first) - 1
    bucket = ((hashes >> U(32)) * U(REGISTERS)) >> U(32)
    value = mix(hashes ^ U(0x5851F42D4C957F2D))
    least = np.full(n * REGISTERS, ~U(0), U)
    np.minimum.at(least, np.repeat(np.arange(n), np.diff(first)) * REGISTERS + bucket.astype(np.int64), value)
    least = least.reshape(n, REGISTERS)
    out, filled = compress(least), least != ~U(0)
    for d in np.flatnonzero(~filled.all(axis=1) & filled.any(axis=1)):
        own = np.flatnonzero(filled[d])
        empty = np.flatnonzero(~filled[d])
        out[d, empty] = out[d, own[_RANK[np.ix_(empty, own)].argmin(axis=1)]]
    return out


def band_keys(registers: np.ndarray) -> np.ndarray:
    """One 64-bit key for each band of each row."""
    r = registers.reshape(-1, BANDS, ROWS).astype(U)
    packed = r[:, :, 0]
    for j in range(1, ROWS):
        packed = (packed << U(16)) | r[:, :, j]
    return mix(packed ^ _BAND_SALT)


def chance(n: np.ndarray, m: np.ndarray) -> np.ndarray:
    """Probability that registers of two unrelated sets of n and m shingles agree."""
    level = np.arange(0, 54)[:, None]

    def share(size: np.ndarray) -> np.ndarray:
        tail = (1 - 2.0**-level) ** np.maximum(size / REGISTERS, 1.0)  # P(minimum >= 2^-level) = (1 - 2^-level)^size
        return np.diff(np.vstack([tail, np.ones((1, len(size)))]), axis=0)

    return (share(n) * share(m)).sum(axis=0) * 2.0**-MANTISSA


def estimate(a: np.ndarray, b: np.ndarray, n: np.ndarray, m: np.ndarray) -> np.ndarray:
    """Jaccard estimates of register rows, corrected for chance agreement."""
    c = chance(n.astype(float), m.astype(float))
    return np.clip(((a == b).mean(axis=1) - c) / (1 - c), 0, 1)


def _text_key(text: Column) -> Column:
    """A key of the whole text; null text has one of its own."""
    return F.coalesce(F.unhex(F.md5(text)), F.lit(b""))


def _signed(texts: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi, data, offset in blocks(batch.column(texts)):
                hashes, first = shingle_sets(data, offset)
                n = np.diff(first)
                total = np.zeros((2, len(hashes) + 1), U)
                np.cumsum(mix(hashes + U(11)), out=total[0, 1:])
                np.cumsum(mix(hashes ^ U(0xC2B2AE3D27D4EB4F)), out=total[1, 1:])
                key = np.ascontiguousarray((total[:, first[1:]] - total[:, first[:-1]]).T)
                registers = signatures(hashes, first)
                empty = n == 0
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column("doc_id")[lo:hi],
                        batch.column("text_key")[lo:hi],
                        pa.array(n, pa.int64()),
                        pa.array([None if e else x.tobytes() for e, x in zip(empty, key)], pa.binary()),
                        pa.array([None if e else x.tobytes() for e, x in zip(empty, registers)], pa.binary()),
                    ],
                    ["doc_id", "text_key", "n_shingles", "set_key", "registers"],
                )

    return run


def _banded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        node, registers = batch.column("node").to_numpy(), batch.column("registers")
        for lo in range(0, len(node), 2048):
            part = np.frombuffer(b"".join(registers[lo : lo + 2048].to_pylist()), np.uint16).reshape(-1, REGISTERS)
            keys = band_keys(part).view(np.int64).ravel()
            yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(np.repeat(node[lo : lo + 2048], BANDS))], ["band", "node"])


def _estimated(threshold: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for lo in range(0, batch.num_rows, 4096):
                part = batch.slice(lo, 4096)
                a, b = (np.frombuffer(b"".join(part.column(c).to_pylist()), np.uint16).reshape(-1, REGISTERS) for c in ("ra", "rb"))
                n, m = (part.column(c).to_numpy() for c in ("na", "nb"))
                near = estimate(a, b, n, m) >= threshold - SLACK * (threshold * (1 - threshold) / REGISTERS) ** 0.5
                keep.append(near & (np.minimum(n, m) >= threshold * np.maximum(n, m)))
            keep = pa.array(np.concatenate(keep) if keep else np.zeros(0, bool))
            yield batch.select(["a", "b"]).filter(keep)

    return run


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for lo, hi, data, offset in blocks(batch.column("text")):
            hashes, first = shingle_sets(data, offset)
            sets = pa.ListArray.from_arrays(pa.array(first, pa.int32()), pa.array(hashes.view(np.int64)))
            yield pa.RecordBatch.from_arrays([batch.column("node")[lo:hi], sets], ["node", "shingles"])


def _compared(percent: int):
    """Links between texts of two blocks (or of one) with different roots: enough of them to join what they join."""

    def run(key, table):
        table = table.combine_chunks()
        node, root = (table[c].to_numpy() for c in ("node", "root"))
        lists = table["shingles"].combine_chunks()
        lists = lists.chunk(0) if isinstance(lists, pa.ChunkedArray) else lists
        offset = np.asarray(lists.offsets, np.int64)
        _, code, times = np.unique(np.asarray(lists.values)[offset[0] : offset[-1]], return_inverse=True, return_counts=True)
        size = np.diff(offset)
        row = np.repeat(np.arange(len(size)), size)
        shared = times[code] > 1
        row, code = row[shared], np.unique(code[shared], return_inverse=True)[1]
        common = np.zeros((len(size), len(size)), np.float32)
        for lo in range(0, int(code.max(initial=-1)) + 1, 4096):
            part = (code >= lo) & (code < lo + 4096)
            dense = np.zeros((len(size), 4096), np.float32)
            dense[row[part], code[part] - lo] = 1
            common += dense @ dense.T
        linked = common * (100 + percent) >= percent * (size[:, None] + size[None, :])
        linked &= (root[:, None] != root[None, :]) & (node[:, None] < node[None, :])
        parent = {r: r for r in root.tolist()}

        def top(r: int) -> int:
            while parent[r] != r:
                parent[r] = r = parent[parent[r]]
            return r

        found = []
        for i, j in zip(*(x.tolist() for x in np.nonzero(linked))):
            p, q = top(int(root[i])), top(int(root[j]))
            if p != q:
                parent[p] = q
                found.append((int(node[i]), int(node[j])))
        return pa.table({"a": pa.array([f[0] for f in found], pa.int64()), "b": pa.array([f[1] for f in found], pa.int64())})

    return run


def _of_band(members: DataFrame, bands: DataFrame) -> DataFrame:
    """``members`` (band, salt, ...) with the columns of ``bands`` (band, salts, ...), one row a band; a band is met once for each of its salts."""
    return members.join(bands.withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1))), ["band", "salt"])


class NearDuplicates:
    """Classes, links and groups of ``docs`` (doc_id, text).

    Defined cases: null or wordless text has no shingles and links with nothing; rows that repeat a doc_id count as rows
    of their own; a null doc_id takes part, never names a group that has an id, and comes back as null. Other columns
    are ignored. An empty table gives empty results.
    """

    def __init__(self, docs: DataFrame, percent: int = 75):
        self.percent = percent
        texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
        schema = "doc_id long, text_key binary, n_shingles long, set_key binary, registers binary"
        self.signed = materialize(texts.withColumn("text_key", _text_key(F.col("text"))).mapInArrow(_signed("text"), schema), "registers")
        some = self.signed.where("set_key is not null")
        classes = some.groupBy("set_key").agg(F.min("doc_id").alias("least_id"), F.max("n_shingles").alias("n"), F.first("registers").alias("registers"))
        self.classes = materialize(classes.withColumn("node", F.monotonically_increasing_id()), "classes")
        self.links = self._links(texts)

    def _links(self, texts: DataFrame) -> DataFrame:
        """Roots of all linked classes: (node, root)."""
        banded = self.classes.select("node", "registers").mapInArrow(_banded, "band long, node long")
        shared = materialize(banded.groupBy("band").agg(F.count("*").alias("size")).where("size > 1"), "band-sizes")
        # A band with more than its share of all members is dealt to several tasks; there are at most HOT_BANDS of them.
        share = max(32, self.classes.count() * BANDS // HOT_BANDS)
        hot = F.broadcast(shared.where(F.col("size") > share).select("band", F.ceil(F.col("size") / share).cast("int").alias("salts")))
        sizes = shared.join(hot, "band", "left").withColumn("salts", F.coalesce("salts", F.lit(1)))
        banded = banded.join(hot.withColumnRenamed("salts", "s"), "band", "left")
        banded = banded.select("band", "node", F.pmod(F.xxhash64("node"), F.coalesce("s", F.lit(1))).cast("int").alias("salt"))
        members = materialize(_of_band(banded, sizes), "bands")
        # Texts that meet many others in their bands are the middles of groups: the first hubs.
        central = members.groupBy("node").agg(F.sum("size").alias("central"))
        members = materialize(members.select("band", "salt", "salts", "node").join(central, "node"), "members")
        wanted = members.select("node").distinct().join(self.classes.select("node", "set_key", "least_id"), "node")
        # One row carries the text of a class: its least id; rows that repeat this id are told apart by their set.
        carrier = self.signed.where("set_key is not null").select("doc_id", "set_key").distinct()
        wanted = wanted.join(carrier, (carrier.set_key == wanted.set_key) & carrier.doc_id.eqNullSafe(wanted.least_id), "left_semi")
        with_text = texts.join(wanted.select("node", F.col("least_id").alias("id")), F.col("doc_id").eqNullSafe(F.col("id"))).select("node", "text")
        sets = with_text.mapInArrow(_sets, "node long, shingles array<long>")
        own = self.classes.select("node", "n")
        sets = materialize(sets.join(own, "node").where(F.size("shingles") == F.col("n")), "sets")
        registers = self.classes.select("node", "registers", "n")

        edges, roots = None, None
        for turn in range(HUB_ROUNDS + 1):
            if roots is None:
                open_members = members.withColumn("root", F.col("node"))
            else:
                labelled = members.join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
                mixed = labelled.groupBy("band").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.max("salts").alias("salts")).where("lo < hi").select("band", "salts")
                open_members = _of_band(labelled.drop("salts"), mixed)
            if turn < HUB_ROUNDS:  # each member against one hub of its band, another one in each round
                order = F.xxhash64("node", F.lit(turn)) if turn else F.col("central")
                hubs = open_members.groupBy("band").agg(F.max(F.struct(order.alias("o"), F.col("node").alias("hub"), F.col("root").alias("hub_root"))).alias("h"), F.max("salts").alias("salts"))
                pairs = _of_band(open_members.drop("salts"), hubs.select("band", "salts", "h.*")).where("node != hub and root != hub_root")
                pairs = pairs.select(F.least("node", "hub").alias("a"), F.greatest("node", "hub").alias("b"))
                found = materialize(self._confirmed(pairs.distinct(), registers, sets), "links")
            else:  # what is left: members of one band that no chain of links joins yet
                found = materialize(self._left(materialize(open_members, "open"), sets), "links")
            if turn and not found.limit(1).count():
                continue
            edges = found if edges is None else edges.unionByName(found)
            roots = components(edges.select(F.col("a").alias("src"), F.col("b").alias("dst")))
        return roots

    def _left(self, members: DataFrame, sets: DataFrame) -> DataFrame:
        """Links between members (band, node, central, root) of one band with different roots, enough of them to join all.

        Members that can have a link are put into blocks of bounded size, those with the same most central neighbour
        together; blocks that meet in a band are compared set by set, whole blocks at a time, so that a group of m members
        takes about (m / BLOCK_ROWS)^2 rows and not m^2.
        """
        members = self._possible(members, sets)
        hubs = members.groupBy("band").agg(F.max(F.struct("central", "node")).alias("h"), F.max("salts").alias("salts"))
        placed = _of_band(members.drop("salts"), hubs).groupBy("node").agg(F.first("root").alias("root"), F.max("h").alias("h"))
        placed = placed.select("node", "root", F.col("h.node").alias("cluster")).join(self.classes.select("node", "n"), "node")
        parts = placed.groupBy("cluster").agg(F.ceil(F.greatest(F.sum("n") / BLOCK_SHINGLES, F.count("*") / BLOCK_ROWS)).alias("parts"))
        block = F.xxhash64("cluster", F.pmod(F.xxhash64("node"), F.col("parts")))
        placed = materialize(placed.join(parts, "cluster").select("node", "root", block.alias("block")), "blocks")
        met = members.select("band", "node", "root").join(placed.select("node", "block"), "node").groupBy("band", "block").agg(F.min("root").alias("lo"), F.max("root").alias("hi"))
        other = met.select("band", F.col("block").alias("block_b"), F.col("lo").alias("lo_b"), F.col("hi").alias("hi_b"))
        pairs = met.join(other, "band").where("block <= block_b and least(lo, lo_b) < greatest(hi, hi_b)").select(F.col("block").alias("block_a"), "block_b").distinct()
        sides = pairs.withColumn("block", F.explode(F.array_distinct(F.array("block_a", "block_b"))))
        rows = sides.join(placed.join(sets, "node").select("node", "root", "shingles", "block"), "block")
        return rows.groupBy("block_a", "block_b").applyInArrow(_compared(self.percent), "a long, b long")

    def _possible(self, members: DataFrame, sets: DataFrame) -> DataFrame:
        """``members`` (band, node, root) that can have a link to a text of another root.

        A link of sets of n and m shingles takes at least p / (100 + p) * (n + m) in common, and m is p / 100 * n or more.
        A text with fewer shingles that occur under another root, against the smallest set it meets, is out, without a
        look at any pair.
        """
        p = self.percent
        nodes = members.select("node", "root").distinct().join(self.classes.select("node", "n"), "node")
        sized = members.join(nodes.select("node", "n"), "node")
        least = sized.groupBy("band").agg(F.min("n").alias("least"), F.max("salts").alias("salts"))
        meets = _of_band(sized.drop("salts"), least).groupBy("node").agg(F.min("least").alias("least"))
        shingles = materialize(nodes.select("node", "root").join(sets, "node").select("node", "root", F.explode("shingles").alias("shingle")), "shingles")
        spread = shingles.groupBy("shingle").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo < hi").select("shingle")
        common = shingles.join(spread, "shingle").groupBy("node").agg(F.count("*").alias("common"))
        smallest = F.greatest(F.col("least") * 100, F.col("n") * p)  # times 100
        fit = nodes.join(meets, "node").join(common, "node").where(F.col("common") * 100 * (100 + p) >= (F.col("n") * 100 + smallest) * p)
        return materialize(members.join(fit.select("node"), "node", "left_semi"), "possible")

    def _confirmed(self, pairs: DataFrame, registers: DataFrame, sets: DataFrame) -> DataFrame:
        """Pairs that pass the estimate and whose full sets reach the threshold."""

        def side(t: DataFrame, **names: str) -> DataFrame:
            return t.select(*[F.col(k).alias(v) for k, v in names.items()])

        near = pairs.join(side(registers, node="a", registers="ra", n="na"), "a").join(side(registers, node="b", registers="rb", n="nb"), "b")
        near = near.select("a", "b", "ra", "rb", "na", "nb").mapInArrow(_estimated(self.percent / 100), "a long, b long")
        full = near.join(side(sets, node="a", shingles="sa"), "a").join(side(sets, node="b", shingles="sb"), "b")
        common = full.select("a", "b", F.size(F.array_intersect("sa", "sb")).cast("long").alias("common"), (F.size("sa") + F.size("sb")).cast("long").alias("both"))
        return common.where(F.col("common") * 100 >= F.lit(self.percent) * (F.col("both") - F.col("common"))).select("a", "b")

    def groups(self) -> DataFrame:
        """(doc_id, n_shingles, component_id, kept), a row for each row of the input."""
        rooted = self.classes.join(self.links, "node", "left").select("set_key", "least_id", F.coalesce("root", "node").alias("root"))
        named = rooted.groupBy("root").agg(F.min("least_id").alias("component_id"))
        by_key = rooted.join(named, "root").select("set_key", "component_id")
        out = self.signed.select("doc_id", "n_shingles", "set_key").join(by_key, "set_key", "left")
        component = F.coalesce("component_id", "doc_id")
        return out.select("doc_id", "n_shingles", component.alias("component_id"), component.eqNullSafe(F.col("doc_id")).alias("kept"))

    def kept_texts(self) -> DataFrame:
        """(doc_id, text_key), one of each group: that of least id (null last), then of least set and text.

        Texts without shingles are in no group: each is there, with its id.
        """
        rooted = self.classes.join(self.links, "node", "left").select("set_key", "least_id", F.coalesce("root", "node").alias("root"))
        first = F.min(F.struct(F.col("least_id").isNull().alias("none"), "least_id", "set_key")).alias("first")
        chosen = rooted.groupBy("root").agg(first).select("first.set_key", F.col("first.least_id").alias("doc_id"))
        some = self.signed.where("set_key is not null").select("doc_id", "set_key", "text_key")
        some = some.join(chosen, (some.set_key == chosen.set_key) & some.doc_id.eqNullSafe(chosen.doc_id), "left_semi")
        one = some.groupBy("set_key").agg(F.first("doc_id").alias("doc_id"), F.min("text_key").alias("text_key"))
        return one.select("doc_id", "text_key").unionByName(self.signed.where("set_key is null").select("doc_id", "text_key").distinct())


def near_duplicates(docs: DataFrame, percent: int = 75) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) of (doc_id, text); see NearDuplicates."""
    return NearDuplicates(docs, percent).groups()


def drop_near_duplicates(docs: DataFrame, percent: int = 75) -> DataFrame:
    """Rows of ``docs``, one of each near-duplicate group: that with the least doc_id. All columns stay.

    Rows that repeat both id and text are one document: one row of them stays. Rows that share an id, or have none, but
    have different texts are documents of their own.
    """
    kept = NearDuplicates(docs, percent).kept_texts().select(F.col("doc_id").alias("__kept_id"), F.col("text_key").alias("__kept_text"))
    keyed = docs.withColumn("__id", F.col("doc_id").cast("long")).withColumn("__text", _text_key(F.col("text")))
    same = keyed.join(kept, (keyed["__text"] == kept["__kept_text"]) & keyed["__id"].eqNullSafe(kept["__kept_id"]), "left_semi")
    return same.dropDuplicates(["__id", "__text"]).drop("__id", "__text")
