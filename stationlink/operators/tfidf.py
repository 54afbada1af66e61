"""Cosine similarity of tf-idf vectors of labels' tokens."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stationlink.functions import text


class TfidfModel:
    """Document frequencies of tokens over a table of labels; labels are the documents."""

    def __init__(self, df: DataFrame, n: int, smooth: bool):
        self.df, self.n, self.smooth = df, n, smooth

    @classmethod
    def fit(cls, labels: DataFrame, column: str = "label", idf: str = "plain") -> TfidfModel:
        n = labels.count()
        df = labels.select(F.explode(text.tokens(F.col(column))).alias("token")).groupBy("token").agg(F.count("*").alias("df"))
        return cls(df, n, idf == "smooth")

    def _idf(self, df) -> F.Column:
        seen = F.coalesce(df, F.lit(1))
        return F.log((1 + F.lit(float(self.n))) / (1 + seen)) + 1 if self.smooth else F.log(F.lit(float(max(self.n, 1))) / seen)

    def weights(self, labels: DataFrame, column: str = "label") -> DataFrame:
        """(label, token, w) with tf * idf of each distinct label; tokens not seen in fitting have frequency 1."""
        rows = labels.select(F.col(column).alias("label")).distinct().select("label", F.explode(text.words_in_order(F.col("label"))).alias("token"))
        counted = rows.groupBy("label", "token").agg(F.count("*").alias("tf"))
        return counted.join(self.df, "token", "left").select("label", "token", (F.col("tf") * self._idf(F.col("df"))).alias("w"))

    def similarity(self, pairs: DataFrame, a: str = "label_a", b: str = "label_b") -> DataFrame:
        """``pairs`` with TFIDF; once for each distinct pair of labels. Without weights, 1 if the labels are equal.

        Pairs with a null label are left out.
        """
        distinct = pairs.select(F.col(a).alias("__a"), F.col(b).alias("__b")).distinct()
        both = distinct.select(F.col("__a").alias("label")).union(distinct.select(F.col("__b").alias("label")))
        w = self.weights(both)
        norms = w.groupBy("label").agg(F.map_from_entries(F.collect_list(F.struct("token", "w"))).alias("v"), F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
        left, right = (norms.select(F.col("label").alias(x), F.col("v").alias(f"v{x}"), F.col("norm").alias(f"n{x}")) for x in ("__a", "__b"))
        scored = distinct.join(left, "__a", "left").join(right, "__b", "left")
        shared = F.array_intersect(F.map_keys("v__a"), F.map_keys("v__b"))
        dot = F.aggregate(shared, F.lit(0.0), lambda s, t: s + F.element_at("v__a", t) * F.element_at("v__b", t))
        size = F.col("n__a") * F.col("n__b")
        sim = F.when(F.col("__a") == F.col("__b"), F.lit(1.0)).when(size > 0, F.least(F.lit(1.0), F.try_divide(dot, size))).otherwise(F.lit(0.0))
        scored = scored.select("__a", "__b", F.coalesce(sim, F.lit(0.0)).alias("TFIDF"))
        return pairs.join(scored, (pairs[a] == scored["__a"]) & (pairs[b] == scored["__b"])).drop("__a", "__b")


def similarity_by_repeat(pairs: DataFrame, mask: str = "test", repeats: int = 5, a: str = "a_label", b: str = "b_label") -> DataFrame:
    """(a, b, TFIDF) of each distinct pair of labels: an array of one similarity for each repeat, fitted on the labels of that repeat's train part.

    All repeats go through one pass: a token has a weight for each. Pairs with a null label are left out.
    """
    train = pairs.select(F.col(a).alias("a"), F.col(b).alias("b"), F.explode(F.filter(F.sequence(F.lit(0), F.lit(repeats - 1)), lambda r: F.col(mask).bitwiseAND(F.call_function("shiftleft", F.lit(1), r)) == 0)).alias("repeat"))
    fit = train.select("repeat", F.explode(F.array("a", "b")).alias("label")).distinct()
    sizes = {r["repeat"]: r["n"] for r in fit.groupBy("repeat").agg(F.count("*").alias("n")).collect()}  # one row a repeat
    tokens = fit.select("repeat", F.explode(text.tokens(F.col("label"))).alias("token"))
    df = tokens.groupBy("token").agg(*[F.sum(F.when(F.col("repeat") == r, 1)).alias(f"df{r}") for r in range(repeats)])
    distinct = pairs.select(F.col(a).alias("__a"), F.col(b).alias("__b")).where("__a is not null and __b is not null").distinct()
    labels = distinct.select(F.explode(F.array("__a", "__b")).alias("label")).distinct()
    counted = labels.select("label", F.explode(text.words_in_order(F.col("label"))).alias("token")).groupBy("label", "token").agg(F.count("*").alias("tf"))
    idf = [F.log(F.lit(float(max(sizes.get(r, 0), 1))) / F.coalesce(F.col(f"df{r}"), F.lit(1))) for r in range(repeats)]
    w = counted.join(df, "token", "left").select("label", "token", F.array(*[F.col("tf") * x for x in idf]).alias("w"))
    v = w.groupBy("label").agg(F.collect_list(F.struct("token", "w")).alias("v"))
    v = v.select("label", F.col("v.token").alias("k"), F.flatten("v.w").alias("w"))
    left, right = (v.select(F.col("label").alias(x), F.col("k").alias(f"k{x}"), F.col("w").alias(f"w{x}")) for x in ("__a", "__b"))
    both = distinct.join(left, "__a", "left").join(right, "__b", "left")
    cosine = F.arrow_udf(lambda same, *of: cosines(same, *of, repeats=repeats), "array<double>")
    return both.select(F.col("__a").alias(a), F.col("__b").alias(b), cosine(F.col("__a") == F.col("__b"), "k__a", "w__a", "k__b", "w__b").alias("TFIDF"))


def cosines(same: pa.Array, tokens_a: pa.Array, weights_a: pa.Array, tokens_b: pa.Array, weights_b: pa.Array, repeats: int) -> pa.Array:
    """Lists of ``repeats`` cosines: a row has two lists of distinct tokens and, for each token, its weights in all repeats. Null lists are empty.

    1 where ``same``, else 0 without weights.
    """
    n = len(same)

    def side(tokens, weights):
        rows = np.repeat(np.arange(n), pc.fill_null(pc.list_value_length(tokens), 0).to_numpy(zero_copy_only=False))
        w = pc.list_flatten(weights).to_numpy(zero_copy_only=False).reshape(-1, repeats)
        norm = np.stack([np.sqrt(np.bincount(rows, w[:, r] * w[:, r], n)) for r in range(repeats)], axis=1)
        return rows, pc.list_flatten(tokens), w, norm

    (rows_a, names_a, w_a, norm_a), (rows_b, names_b, w_b, norm_b) = side(tokens_a, weights_a), side(tokens_b, weights_b)
    code = pc.dictionary_encode(pa.concat_arrays([names_a, names_b])).indices.to_numpy(zero_copy_only=False).astype(np.int64)
    many = int(code.max(initial=0)) + 1
    key_a, key_b = rows_a * many + code[: len(rows_a)], rows_b * many + code[len(rows_a) :]
    order = np.argsort(key_b)
    at = np.minimum(np.searchsorted(key_b[order], key_a), max(len(order) - 1, 0))
    hit = np.flatnonzero(key_b[order][at] == key_a) if len(order) else np.zeros(0, int)
    at = order[at[hit]] if len(order) else hit
    dot = np.stack([np.bincount(rows_a[hit], w_a[hit, r] * w_b[at, r], n) for r in range(repeats)], axis=1)
    size = norm_a * norm_b
    got = np.where(size > 0, np.minimum(1.0, dot / np.where(size > 0, size, 1.0)), 0.0)
    got[pc.fill_null(same, False).to_numpy(zero_copy_only=False)] = 1.0
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1) * repeats, pa.int32()), pa.array(got.ravel()))
