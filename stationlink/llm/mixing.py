"""Mixing overlapping sources to target weights by a min-cost flow over membership patterns.

Documents are counted by their pattern, the set of sources they belong to. From each pattern tokens flow to the quotas
of its sources; taking a document's tokens once costs nothing, each further time costs more, up to ``max_copies``. The
cheapest flow fills the quotas with as little repetition as can be. A pattern's flow to a source is then made of
documents: all of them as often as the flow covers the pattern whole, and for the rest those first in a seeded order.
The flow's size depends on patterns and sources only, whose numbers are checked; documents stay distributed.
"""

from __future__ import annotations

import heapq

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stationlink.plans.workspace import materialize

MAX_COPIES = 3
#: Most (pattern, source) arcs the driver takes.
MAX_ARCS = 200_000
#: Parts of the seeded order that are counted before one of them is looked at document by document.
BINS = 4096


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def has_words(text: Column) -> Column:
    """Whether ``word_count`` is above 0."""
    return F.coalesce(F.regexp_like(text, F.lit(r"[^\x20\x09-\x0D]")), F.lit(False))


def targets(sizes: list[tuple[str | None, int]], weights: list[float], cap: float = MAX_COPIES) -> list[float]:
    """Shares of the total by weight, none above ``cap`` times its size; what is cut off is shared again by weight."""
    total = float(sum(s for _, s in sizes))
    order = sorted(range(len(sizes)), key=lambda k: (cap * sizes[k][1] / weights[k], k))
    out, left, weight = [0.0] * len(sizes), total, float(sum(weights))
    for k in order:
        out[k] = min(cap * sizes[k][1], left * weights[k] / weight) if weight > 0 else 0.0
        left, weight = left - out[k], weight - weights[k]
    return out


def flow(patterns: dict[tuple[int, ...], int], quotas: list[int], max_copies: int = MAX_COPIES) -> dict[tuple[tuple[int, ...], int], int]:
    """Tokens from each pattern (indices of its sources) to each source, at the least repetition cost.

    Successive cheapest paths over patterns and sources with convex costs: the k-th use of a pattern's tokens costs k*k.
    Patterns that are linked by sources make a network of their own; the networks are solved one after the other.
    """
    parent: dict[int, int] = {}

    def top(s: int) -> int:
        while parent.setdefault(s, s) != s:
            parent[s] = s = parent[parent[s]]
        return s

    for p in patterns:
        for s in p[1:]:
            parent[top(s)] = top(p[0])
    networks: dict[int, dict[tuple[int, ...], int]] = {}
    for p, size in patterns.items():
        networks.setdefault(top(p[0]), {})[p] = size
    out: dict[tuple[tuple[int, ...], int], int] = {}
    for own in networks.values():
        out |= _network(own, quotas, max_copies)
    return out


def _network(patterns: dict[tuple[int, ...], int], quotas: list[int], max_copies: int) -> dict[tuple[tuple[int, ...], int], int]:
    own = {p: 0 for p in patterns}
    sent: dict[tuple[tuple[int, ...], int], int] = {(p, s): 0 for p in patterns for s in p}
    into: dict[int, list[tuple[int, ...]]] = {}
    for p in patterns:
        for s in p:
            into.setdefault(s, []).append(p)
    number = {p: k for k, p in enumerate(patterns)}
    short = {s: quotas[s] for s in into if quotas[s] > 0}

    def next_use(p: tuple[int, ...]) -> tuple[int, int]:
        """(cost, room) of the pattern's cheapest tokens not yet used."""
        k, size = (own[p] // patterns[p] if patterns[p] else max_copies), patterns[p]
        return (k * k, (k + 1) * size - own[p]) if k < max_copies else (0, 0)

    while short:
        best: dict[object, tuple[int, object]] = {}
        heap = [(cost, 0, k, p, None) for p, k in number.items() for cost, room in [next_use(p)] if room > 0]
        heapq.heapify(heap)
        goal = None
        while heap:
            cost, kind, k, node, via = heapq.heappop(heap)
            if (kind, node) in best:
                continue
            best[kind, node] = (cost, via)
            if kind == 1 and node in short:
                goal = node
                break
            if kind == 0:
                for s in node:
                    if (1, s) not in best:
                        heapq.heappush(heap, (cost, 1, s, s, node))
            else:  # tokens sent here may be taken back and go elsewhere
                for p in into[node]:
                    if sent[p, node] > 0 and (0, p) not in best:
                        heapq.heappush(heap, (cost, 0, number[p], p, node))
        if goal is None:
            break
        path, node, kind, amount = [], goal, 1, short[goal]
        while True:
            via = best[kind, node][1]
            if kind == 0 and via is None:
                amount = min(amount, next_use(node)[1])
                break
            path.append((kind, node, via))
            if kind == 0:
                amount = min(amount, sent[node, via])
            kind, node = 1 - kind, via
        own[node] += amount
        for kind, node, via in path:
            if kind == 1:
                sent[via, node] += amount
            else:
                sent[node, via] -= amount
        short[goal] -= amount
        if not short[goal]:
            del short[goal]
    return {k: v for k, v in sent.items() if v}


def source_targets(docs: DataFrame, weights: tuple[float, ...] = (1.0, 2.0, 3.0)) -> list[tuple[str | None, int, float]]:
    """(source, size, target) by code point, null last, of (source, size) rows; weights repeat in this order."""
    rows = docs.groupBy("source").agg(F.sum("size").alias("s")).collect()
    if len(rows) > MAX_ARCS:
        raise ValueError(f"more than {MAX_ARCS} sources: group them before mixing")
    sizes = sorted(((r["source"], r["s"]) for r in rows), key=lambda x: (x[0] is None, (x[0] or "").encode()))
    got = targets(sizes, [weights[k % len(weights)] for k in range(len(sizes))])
    return [(s, n, t) for (s, n), t in zip(sizes, got)]


def _pattern(sources: Column) -> Column:
    return F.to_json(F.struct(F.array_sort(F.array_distinct(sources)).alias("p")), {"ignoreNullFields": "false"})


def _order(key: Column, seed: int) -> Column:
    """Place of a document in the seeded order, 48 bits."""
    return F.conv(F.substr(F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(key.cast("string"), F.lit("")))), F.lit(1), F.lit(12)), 16, 10).cast("long")


class Mix:
    """Which documents a mix takes, and how often: a rule by pattern and seeded order, for tables of any further columns.

    ``docs`` has key, size, sources; other columns are ignored. ``sources`` is the array of sources a document belongs to
    (null is a source; duplicates count once; an empty array belongs nowhere and isn't taken). Documents of size 0 are
    taken 0 times. The seeded order is a hash of ``key`` and the seed, ties by key; rows with one key and pattern are
    taken together or not. Each quota is met to within the size of one document for each of its patterns, or as far as
    ``max_copies`` of its documents go. An empty table gives a rule that takes nothing.

    The place in the order where a pattern's rest is reached is found by counting: in BINS parts of the order, then again
    in BINS parts of the one it lies in, and so on, until few documents are left, which are looked at one by one.
    """

    #: Rows of one part that are sorted in one task.
    FEW = 100_000

    def __init__(self, docs: DataFrame, quotas: list[tuple[str | None, float]], seed: int = 7, max_copies: int = MAX_COPIES):
        self.spark, self.seed, self.max_copies = docs.sparkSession, seed, max_copies
        docs = docs.select("key", "size", F.array_sort(F.array_distinct("sources")).alias("pattern"), _pattern(F.col("sources")).alias("p"))
        counted = docs.groupBy("p").agg(F.first("pattern").alias("pattern"), F.sum("size").alias("s")).limit(MAX_ARCS + 1).collect()
        if sum(len(r["pattern"] or []) for r in counted) > MAX_ARCS or len(counted) > MAX_ARCS:
            raise ValueError(f"more than {MAX_ARCS} membership patterns: group sources before mixing")
        index = {s: k for k, (s, _) in enumerate(quotas)}
        patterns: dict[tuple[int, ...], int] = {}
        names: dict[tuple[int, ...], list[tuple[str, int]]] = {}
        for r in counted:
            p = tuple(sorted(index[s] for s in r["pattern"] or [] if s in index))
            if p and r["s"]:
                patterns[p] = patterns.get(p, 0) + r["s"]
                names.setdefault(p, []).append((r["p"], r["s"]))
        routed: dict[tuple[int, ...], int] = {}
        for (p, _), tokens in flow(patterns, [int(q + 0.5) for _, q in quotas], max_copies).items():
            routed[p] = routed.get(p, 0) + tokens
        plan = []
        for p, tokens in routed.items():
            whole, rest = divmod(tokens, patterns[p])
            for name, size in names[p]:
                plan.append((name, int(min(whole, max_copies)), int(round(rest * size / patterns[p])) if whole < max_copies else 0))
        self.rule = self._edges(docs.select("p", "key", "size", _order(F.col("key"), seed).alias("u")), plan)

    def _edges(self, docs: DataFrame, plan: list[tuple[str, int, int]]) -> DataFrame:
        """(p, whole, last_u, last_key, has): documents of p up to (last_u, last_key) are taken once more, if has."""
        spark = self.spark
        left = {p: (0, 1 << 48, 0, rest) for p, _, rest in plan if rest > 0}  # from, to, size before, rest
        while True:
            wide = {p: x for p, x in left.items() if x[1] - x[0] > 1}
            if not wide:
                break
            table = F.broadcast(spark.createDataFrame([(p, lo, max((hi - lo) // BINS, 1), hi) for p, (lo, hi, _, _) in wide.items()], "p string, lo long, width long, hi long"))
            inside = docs.join(table, "p").where("u >= lo and u < hi")
            bins = inside.groupBy("p", F.expr("(u - lo) div width").alias("bin")).agg(F.sum("size").alias("s"), F.count("*").alias("n"))  # at most BINS + 1 rows a pattern
            w = Window.partitionBy("p").orderBy("bin")
            bins = bins.withColumn("upto", F.sum("s").over(w))
            rests = F.broadcast(spark.createDataFrame([(p, x[2], x[3]) for p, x in wide.items()], "p string, before long, rest long"))
            edge = bins.join(rests, "p").where("before + upto - s < rest and before + upto >= rest").collect()  # one row a pattern
            done = True
            for r in edge:
                lo, hi, before, rest = left[r["p"]]
                width = max((hi - lo) // BINS, 1)
                left[r["p"]] = (lo + r["bin"] * width, min(lo + (r["bin"] + 1) * width, hi), before + r["upto"] - r["s"], rest)
                done = done and r["n"] <= self.FEW
            if done or not edge:
                break
        table = F.broadcast(spark.createDataFrame([(p, *x) for p, x in left.items()], "p string, lo long, hi long, before long, rest long"))
        last = docs.join(table, "p").where("u >= lo and u < hi")
        run = F.col("before") + F.sum("size").over(Window.partitionBy("p").orderBy("u", "key"))
        last = last.withColumn("run", run).where("run <= rest or (run - rest) * 2 <= size")
        last = last.groupBy("p").agg(F.max(F.struct("u", "key")).alias("last"))
        # Without a last document in the part itself, all before the part are taken.
        plan_rows = [(p, whole, left[p][0] if p in left else -1) for p, whole, _ in plan]
        rule = spark.createDataFrame(plan_rows, "p string, whole int, lo long").join(last, "p", "left")
        return materialize(rule.select("p", "whole", "lo", "last"), "mix-rule")

    def copies(self, docs: DataFrame, key: Column, sources: Column, some: Column) -> DataFrame:
        """(row struct of all columns of ``docs``, copies); ``some``: whether a document's size is above 0. No shuffle of ``docs``."""
        rows = docs.select(F.struct("*").alias("row"), _pattern(sources).alias("p"), key.alias("key"), _order(key, self.seed).alias("u"), some.alias("some"))
        met = rows.join(F.broadcast(self.rule), "p", "left")  # at most MAX_ARCS rows
        more = (F.col("u") < F.col("lo")) | F.coalesce(F.struct("u", "key") <= F.col("last"), F.lit(False))
        number = F.coalesce("whole", F.lit(0)) + F.when(F.coalesce(more, F.lit(False)), 1).otherwise(0)
        return met.select("row", F.when(F.col("some"), F.least(number, F.lit(self.max_copies))).otherwise(0).cast("int").alias("copies"))


def mix(docs: DataFrame, quotas: list[tuple[str | None, float]], seed: int = 7, max_copies: int = MAX_COPIES) -> DataFrame:
    """``docs`` (key, size, sources, ...) with ``copies`` by ``Mix``, in place of a column of this name if there is one."""
    found = Mix(docs, quotas, seed, max_copies).copies(docs.drop("copies"), F.col("key"), F.col("sources"), F.col("size") > 0)
    return found.select("row.*", "copies")
