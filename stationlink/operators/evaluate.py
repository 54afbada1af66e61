"""Confusion counts, precision, recall and F1, and threshold sweeps in one pass."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from stationlink.functions import naive, voting
from stationlink.operators.spicing import in_train

#: Threshold grids of the experiments.
STRING_GRID = tuple(k / 20 for k in range(1, 20)) + (0.99,)
DISTANCE_GRID = (5, 10, 20, 25, 30, 40, 50, 60, 70, 75, 80, 90, 100, 125, 150, 175, 200, 225, 250)


def measures(tp: Column, fp: Column, fn: Column, tn: Column) -> list[Column]:
    """Columns tp, fp, fn, tn, prec, rec, f1; a ratio without cases is null, F1 then 0."""
    prec, rec = F.try_divide(tp, tp + fp), F.try_divide(tp, tp + fn)
    f1 = F.coalesce(F.try_divide(2 * tp, 2 * tp + fp + fn), F.lit(0.0))
    return [tp.alias("tp"), fp.alias("fp"), fn.alias("fn"), tn.alias("tn"), F.round(prec, 6).alias("prec"), F.round(rec, 6).alias("rec"), F.round(f1, 6).alias("f1")]


def confusion(scored: DataFrame, predicted: str = "predicted", by: tuple[str, ...] = ()) -> DataFrame:
    """Counts and measures over pairs whose truth is not null."""
    t, p = F.col("truth"), F.col(predicted)
    count = lambda a, b: F.coalesce(F.sum(((t == a) & (p == b)).cast("long")), F.lit(0))
    out = scored.where("truth is not null").groupBy(*by).agg(count(1, 1).alias("tp"), count(0, 1).alias("fp"), count(1, 0).alias("fn"), count(0, 0).alias("tn"))
    return out.select(*by, *measures(*[F.col(c) for c in ("tp", "fp", "fn", "tn")]))


def sweep(scored: DataFrame, score: str, grid: tuple[float, ...], below: bool = False, by: tuple[str, ...] = ()) -> DataFrame:
    """(*by, t, tp, fp, fn, tn, prec, rec, f1) for each threshold: positive if score > t (or score < t if ``below``).

    Pairs are counted once, by the number of thresholds that a score passes; sums over that small table give all thresholds.
    """
    passes = F.size(F.filter(F.array(*[F.lit(float(t)) for t in sorted(grid)]), lambda t: (F.col(score) < t) if below else (F.col(score) > t)))
    binned = scored.where("truth is not null").groupBy(*by, passes.alias("k")).agg(F.sum("truth").alias("pos"), F.sum(1 - F.col("truth")).alias("neg"))
    rank = {t: k + 1 for k, t in enumerate(sorted(grid))}
    need = F.explode(F.array(*[F.struct(F.lit(float(t)).alias("t"), F.lit(len(grid) - rank[t] + 1 if below else rank[t]).alias("need")) for t in grid])).alias("n")
    yes = F.col("k") >= F.col("n.need")
    hit = binned.select("*", need).groupBy(*by, F.col("n.t").alias("t")).agg(*[F.sum(F.when(yes, F.col(c)).otherwise(0)).alias(n) for c, n in (("pos", "tp"), ("neg", "fp"))], F.sum("pos").alias("all_pos"), F.sum("neg").alias("all_neg"))
    return hit.select(*by, "t", *measures(F.col("tp"), F.col("fp"), F.col("all_pos") - F.col("tp"), F.col("all_neg") - F.col("fp")))


def best_threshold(curve: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """Row of the largest F1 (of each group); ties go to the smallest threshold."""
    w = Window.partitionBy(*by).orderBy(F.col("f1").desc(), *[F.col(c) for c in ("d_hat", "t") if c in curve.columns])
    return curve.withColumn("__r", F.row_number().over(w)).where("__r = 1").drop("__r")


REPEATS = 5


def parts_tested(pair_id, repeats: int = REPEATS, share: float = 0.2) -> Column:
    """Bits of the repeats in whose test part a pair is."""
    out = F.lit(0)
    for r in range(repeats):
        out = out + F.when(in_train(pair_id, r, share), 0).otherwise(1 << r)
    return out


_COUNTS = "method string, t double, mask int, truth int, k int, n long"


def _score_columns(batch: pa.RecordBatch, methods: dict[str, str], repeats: int, null: float):
    """(method, mask, scores) of a batch: a score counts in its pair's test parts; an array of scores has one for each repeat."""
    mask = batch["mask"].to_numpy(zero_copy_only=False).astype(np.int64) & ((1 << repeats) - 1)
    for m, c in methods.items():
        col = batch[c]
        if pa.types.is_list(col.type):
            for r in range(repeats):
                yield m, mask & (1 << r), _filled(pc.list_element(col, r), null)
        else:
            yield m, mask, _filled(col, null)


def _filled(col: pa.Array, null: float) -> np.ndarray:
    return pc.fill_null(col.cast(pa.float64()), null).to_numpy(zero_copy_only=False)


def _tallied(rows: DataFrame, columns: list[str], mask: str, weight: str | None, count, keys: list[str]) -> DataFrame:
    """Sums of the counts that ``count`` gives for each Arrow batch of rows with known truth: (*keys, mask, truth, k, n).

    ``count`` yields (method, threshold, mask, k, levels of k); a row counts ``weight`` times.
    """
    rows = rows.where("truth is not null").select("truth", F.col(mask).cast("int").alias("mask"), (F.col(weight) if weight else F.lit(1)).cast("long").alias("n"), *columns)

    def run(batches):
        total: dict[tuple, np.ndarray] = {}
        for whole in batches:
            for lo in range(0, whole.num_rows, 2048):  # what a batch needs stays in the processor's cache
                batch = whole.slice(lo, 2048)
                truth, n = (batch[c].to_numpy(zero_copy_only=False) for c in ("truth", "n"))
                for method, t, parts, k, levels in count(batch):
                    code = (parts * 2 + truth) * levels + k
                    got = np.bincount(code, n).astype(np.int64)
                    old = total.get((method, t, levels))
                    if old is None or len(old) < len(got):
                        old, got = got, old
                    if got is not None:
                        old[: len(got)] += got
                    total[method, t, levels] = old
        for (method, t, levels), sums in total.items():
            at = np.flatnonzero(sums)
            at = at[at // levels // 2 > 0]  # rows of no test part
            parts = [pa.array([method] * len(at), pa.string()), pa.array([t] * len(at), pa.float64()), at // levels // 2, at // levels % 2, at % levels]
            yield pa.RecordBatch.from_arrays([*parts[:2], *[pa.array(x, pa.int32()) for x in parts[2:]], pa.array(sums[at])], ["method", "t", "mask", "truth", "k", "n"])

    return rows.mapInArrow(run, _COUNTS).groupBy(*keys, "mask", "truth", "k").agg(F.sum("n").alias("n"))


def _by_repeat(counts: DataFrame, keys: list[str], need: DataFrame, repeats: int) -> DataFrame:
    """Measures for each row of ``need`` (*keys, need, ...) and repeat, from counts (*keys, mask, truth, k, n): positive if k >= need."""
    parts = F.filter(F.sequence(F.lit(0), F.lit(repeats - 1)), lambda r: F.col("mask").bitwiseAND(F.call_function("shiftleft", F.lit(1), r)) != 0)
    small = counts.select(*keys, "truth", "k", "n", F.explode(parts).alias("repeat")).groupBy(*keys, "repeat", "k")
    small = small.agg(F.sum(F.when(F.col("truth") == 1, F.col("n")).otherwise(0)).alias("pos"), F.sum(F.when(F.col("truth") == 0, F.col("n")).otherwise(0)).alias("neg"))
    total = F.sum("pos").alias("all_pos"), F.sum("neg").alias("all_neg")
    met = F.broadcast(need).join(small, keys)  # a few hundred rows
    yes = F.col("k") >= F.col("need")
    out = met.groupBy(*[c for c in need.columns if c != "need"], "repeat").agg(F.sum(F.when(yes, F.col("pos")).otherwise(0)).alias("tp"), F.sum(F.when(yes, F.col("neg")).otherwise(0)).alias("fp"), *total)
    shown = [c for c in need.columns if c != "need"]
    return out.select(*shown, "repeat", *measures(F.col("tp"), F.col("fp"), F.col("all_pos") - F.col("tp"), F.col("all_neg") - F.col("fp")))


def curves(rows: DataFrame, strings: dict[str, str], repeats: int = REPEATS, mask: str = "test", by_label: DataFrame | None = None) -> DataFrame:
    """(method, t, repeat, tp, ..., f1) of P and of string scores {method: column} at all thresholds, on each test part.

    Rows (truth, dist_m, test, scores) are counted once, by the number of thresholds that each score passes. With
    ``by_label`` (truth, test, n, scores), string scores are counted there: one row stands for n pairs with the same labels.
    """
    spark, near, alike = rows.sparkSession, np.array(sorted(DISTANCE_GRID), float), np.array(sorted(STRING_GRID), float)

    def below(batch):
        for m, parts, s in _score_columns(batch, {"P": "dist_m"}, repeats, np.inf):
            yield m, None, parts, len(near) - np.searchsorted(near, s, "right"), len(near) + 1

    def above(batch):
        for m, parts, s in _score_columns(batch, strings, repeats, -np.inf):
            yield m, None, parts, np.searchsorted(alike, s, "left"), len(alike) + 1

    columns = list(dict.fromkeys(strings.values()))
    if by_label is not None:
        counts = _tallied(rows, ["dist_m"], mask, None, below, ["method"]).unionByName(_tallied(by_label, columns, mask, "n", above, ["method"]))
    else:
        counts = _tallied(rows, list(dict.fromkeys(["dist_m", *columns])), mask, None, lambda batch: (*below(batch), *above(batch)), ["method"])
    need = [("P", float(t), len(DISTANCE_GRID) - i) for i, t in enumerate(sorted(DISTANCE_GRID))]
    need += [(m, float(t), i + 1) for m in strings for i, t in enumerate(sorted(STRING_GRID))]
    return _by_repeat(counts, ["method"], spark.createDataFrame(need, "method string, t double, need int"), repeats)


def combination_curves(rows: DataFrame, strings: dict[str, str], repeats: int = REPEATS, mask: str = "test", mode: str = "soft", d_grid: tuple[float, ...] = DISTANCE_GRID, t_grid: tuple[float, ...] = STRING_GRID) -> DataFrame:
    """(method, d_hat, t, repeat, tp, ..., f1) of P with each string score over both grids, on each test part.

    For one pair and string threshold, those d_hat are positive that are large enough; so a pair is counted once for each
    threshold, by how many they are. No score is rounded.
    """
    spark, d_grid, t_grid = rows.sparkSession, sorted(float(d) for d in d_grid), [float(t) for t in t_grid]
    if d_grid and d_grid[0] <= 0:
        raise ValueError("the half distance must be above 0")
    rates = np.array([-math.log(2) / d for d in d_grid])[:, None]

    def count(batch):
        near = np.exp(_filled(batch["dist_m"], np.nan) * rates)
        unknown = batch["dist_m"].is_null().to_numpy(zero_copy_only=False)
        for m, parts, s in _score_columns(batch, strings, repeats, -np.inf):
            s = np.where(unknown, -np.inf, s)
            for t in t_grid:
                with np.errstate(divide="ignore", invalid="ignore"):
                    r = np.where(s <= t, np.where(np.isinf(s), s, s / (2 * t) if t > 0 else 0.0), 0.5 + (s - t) / (2 * (1 - t)) if t < 1 else -np.inf)
                    yes = ~((near + r) / 2 <= 0.5) if mode == "soft" else ~(near <= 0.5) & ~(r <= 0.5)
                yes &= r != -np.inf
                yield m, t, parts, yes.sum(axis=0), len(d_grid) + 1

    counts = _tallied(rows, list(dict.fromkeys(["dist_m", *strings.values()])), mask, None, count, ["method", "t"])
    need = spark.createDataFrame([(m, float(t), d, len(d_grid) - i) for m in strings for t in t_grid for i, d in enumerate(d_grid)], "method string, t double, d_hat double, need int")
    return _by_repeat(counts, ["method", "t"], need, repeats)


def mean_best(by_repeat: DataFrame) -> DataFrame:
    """The thresholds of each method with the best F1, mean over repeats; ties go to the smallest."""
    at = [c for c in ("d_hat", "t") if c in by_repeat.columns]
    mean = by_repeat.groupBy("method", *at).agg(*[F.round(F.avg(c), 6).alias(c) for c in ("prec", "rec", "f1")], F.min("f1").alias("f1_min"), F.max("f1").alias("f1_max"))
    return best_threshold(mean, ("method",))


def sweep_2d(scored: DataFrame, sim: str, d_grid: tuple[float, ...] = DISTANCE_GRID, t_grid: tuple[float, ...] = STRING_GRID, mode: str = "soft") -> DataFrame:
    """Curve of P combined with one string score over (d_hat, t), on all pairs."""
    rows = scored.select("truth", "dist_m", F.col(sim).alias("s"), F.lit(1).alias("test"))
    return combination_curves(rows, {sim: "s"}, 1, "test", mode, d_grid, t_grid).drop("method", "repeat")


def combined(scored: DataFrame, sim: str, d_hat: float, t: float, mode: str = "soft") -> DataFrame:
    """``scored`` with score and predicted of P with a string similarity."""
    near, string = naive.decay(F.col("dist_m"), d_hat), voting.rescale(F.col(sim), t)
    if mode == "soft":
        score = voting.soft(near, string)
        return scored.withColumn("score", score).withColumn("predicted", voting.decide(score))
    decision = voting.hard(voting.decide(near), voting.decide(string))
    return scored.withColumn("score", decision.cast("double")).withColumn("predicted", decision)


def improvement(new, old) -> Column:
    """Relative improvement in percent."""
    return F.round((F.try_divide(new, old) - 1) * 100, 6)


def easy_share(curve: DataFrame) -> DataFrame:
    """Share of pairs that the best cut gets right."""
    best = best_threshold(curve)
    right = F.col("tp") + F.col("tn")
    return best.select("t", F.round(F.try_divide(right, right + F.col("fp") + F.col("fn")), 6).alias("easy"))


def worst(scored: DataFrame, n: int = 20) -> DataFrame:
    """The most confident mistakes: n false negatives and n false positives."""
    wrong = scored.where("truth is not null and predicted != truth").withColumn("kind", F.when(F.col("truth") == 1, "FN").otherwise("FP"))
    picks = []
    for kind, order in (("FN", F.col("score").asc()), ("FP", F.col("score").desc())):
        picks.append(wrong.where(F.col("kind") == kind).orderBy(order, "pair_id").limit(n))
    return picks[0].unionByName(picks[1])


def mean_over_repeats(results: DataFrame, by: tuple[str, ...] = ("method",)) -> DataFrame:
    """Means of precision, recall and F1 over repeats, with the least and largest F1."""
    return results.groupBy(*by).agg(*[F.round(F.avg(c), 6).alias(c) for c in ("prec", "rec", "f1")], F.min("f1").alias("f1_min"), F.max("f1").alias("f1_max"))


def exact_quantiles(rows: DataFrame, by: str, value: str, shares: dict[str, float], cells: int = 1 << 14) -> DataFrame:
    """(by, *shares) of each group's exact quantiles {name: share}, linear between neighbours.

    Rows are counted by cells of equal width, and only values in the cells of the wanted ranks are ordered; so no task
    holds a group. ``rows`` are read three times. Rows with a null value or group are left out.
    """
    rows = rows.select(F.col(by).alias("g"), F.col(value).cast("double").alias("v")).where("g is not null and v is not null")
    low, high = rows.agg(F.min("v"), F.max("v")).first()
    width = (high - low) / cells if low is not None and high > low else 1.0
    rows = rows.withColumn("cell", F.floor((F.col("v") - F.lit(low)) / width))
    w = Window.partitionBy("g")
    counts = rows.groupBy("g", "cell").agg(F.count("*").alias("n"))
    counts = counts.select("g", "cell", "n", (F.sum("n").over(w.orderBy("cell")) - F.col("n")).alias("before"), F.sum("n").over(w).alias("total"))
    wanted = F.explode(F.array(*[F.struct(F.lit(k).alias("name"), (F.lit(float(q)) * (F.col("total") - 1)).alias("at")) for k, q in shares.items()])).alias("w")
    ranks = counts.select("*", wanted).select("g", "cell", "before", "n", "w.*", F.explode(F.array_distinct(F.array(F.floor("w.at"), F.ceil("w.at")))).alias("rank"))
    ranks = ranks.where("before <= rank and rank < before + n")
    inside = rows.join(ranks.select("g", "cell", "before").distinct(), ["g", "cell"]).groupBy("g", "cell", "before", "v").agg(F.count("*").alias("n"))
    last = F.col("before") + F.sum("n").over(Window.partitionBy("g", "cell").orderBy("v"))
    inside = inside.select("g", "cell", "v", (last - F.col("n")).alias("first"), last.alias("after"))
    found = ranks.select("g", "cell", "name", "at", "rank").join(inside, ["g", "cell"]).where("first <= rank and rank < after")
    part = F.max(F.col("at") - F.floor("at"))
    one = found.groupBy("g", "name").agg((F.min("v") * (1 - part) + F.max("v") * part).alias("q"))
    return one.groupBy(F.col("g").alias(by)).agg(*[F.max(F.when(F.col("name") == k, F.col("q"))).alias(k) for k in shares])
