"""Random forest over pair features: fitted on a train part, tree by tree in tasks or by MLlib, scored from flat trees without vectors."""

from __future__ import annotations

import json
import math
import uuid
from dataclasses import dataclass
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.ml.classification import RandomForestClassificationModel, RandomForestClassifier
from pyspark.ml.linalg import SparseVector, VectorUDT
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stationlink.functions.numbering import uniform
from stationlink.operators.features import trigram_dictionary, vectors
from stationlink.operators.trees import TrainPart, grow
from stationlink.plans.workspace import materialize, shared_folder

#: Most pairs a forest is fitted on; a larger train part is thinned by a hash of the pair.
MAX_TRAIN = 5_000_000
#: Most entries of vectors of a train part that a task holds whole, to grow trees; MLlib fits on a larger one.
TASK_ENTRIES = 8_000_000
BINS = 256
#: How MLlib saves a forest.
NODES = "treeID int, nodeData struct<id: int, prediction: double, impurity: double, impurityStats: array<double>, rawCount: bigint, gain: double, leftChild: int, rightChild: int, split: struct<featureIndex: int, leftCategoriesOrThreshold: array<double>, numCategories: int>>"


class Wide(NamedTuple):
    """Pairs with ``index`` and ``value`` made once for several forests: their dictionary holds all of those forests' trigrams."""

    rows: DataFrame
    dictionary: list[str]
    grids: int
    order: bool

    @classmethod
    def of(cls, rows: DataFrame, dictionaries: list[list[str]], grids: int, order: bool, keep: tuple[str, ...]) -> Wide:
        dictionary = list(dict.fromkeys(g for d in dictionaries for g in d))
        made = vectors(rows, dictionary, grids, order).select("pair_id", "truth", *keep, "index", "value")
        return cls(materialize(made, "forest-vectors"), dictionary, grids, order)

    def positions(self, dictionary: list[str], grids: int, order: bool) -> np.ndarray:
        """The number that each feature has in a forest with these settings, -1 if it is not one of it."""
        base = 2 + 2 * grids + order
        grams = {g: base + i for i, g in enumerate(dictionary)}
        cells = [i if i < 2 + 2 * grids else -1 for i in range(2 + 2 * self.grids)]
        return np.array(cells + [base - 1 if order else -1] * self.order + [grams.get(g, -1) for g in self.dictionary])


def train_dictionary(train: DataFrame, k: int) -> list[str]:
    labels = train.select(F.col("a_label").alias("label")).union(train.select(F.col("b_label").alias("label"))).distinct()
    return trigram_dictionary(labels, k) if k else []


def _flat(index: pa.Array, value: pa.Array, places: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(index, value, first) of sparse rows; ``places`` renumbers features."""
    first = np.r_[0, np.cumsum(pc.list_value_length(index).to_numpy(zero_copy_only=False))]
    i, v = (pc.list_flatten(x).to_numpy(zero_copy_only=False) for x in (index, value))
    return i if places is None else places[i], v, first


@dataclass
class FlatForest:
    """All trees in arrays: split feature (-1 in leaves), threshold, children, probability of class 1."""

    roots: np.ndarray
    feature: np.ndarray
    threshold: np.ndarray
    left: np.ndarray
    right: np.ndarray
    chance: np.ndarray

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> FlatForest:
        n = "nodeData" if "nodeData" in spark.read.parquet(f"{path}/data").columns else "node"
        nodes = spark.read.parquet(f"{path}/data").select(
            "treeID", f"{n}.id", f"{n}.leftChild", f"{n}.rightChild", f"{n}.split.featureIndex",
            F.get(f"{n}.split.leftCategoriesOrThreshold", F.lit(0)).alias("threshold"), F.try_divide(F.col(f"{n}.impurityStats")[1], F.aggregate(f"{n}.impurityStats", F.lit(0.0), lambda a, x: a + x)).alias("chance"),
        ).orderBy("treeID", "id").toArrow()
        tree, own, left, right, feature = (nodes[c].to_numpy().astype(np.int64) for c in ("treeID", "id", "leftChild", "rightChild", "featureIndex"))
        roots = np.flatnonzero(np.r_[True, tree[1:] != tree[:-1]])
        base = roots[np.cumsum(np.r_[False, tree[1:] != tree[:-1]])]  # nodes of a tree are numbered from 0 in order
        inner = left >= 0
        return cls(roots, np.where(inner, feature, -1), nodes["threshold"].to_numpy().astype(float), np.where(inner, base + left, 0), np.where(inner, base + right, 0), np.nan_to_num(nodes["chance"].to_numpy().astype(float)))

    def probability(self, index: np.ndarray, value: np.ndarray, first: np.ndarray, width: int, rows: int = 256) -> np.ndarray:
        """Mean over trees of the probability of class 1, for sparse rows index[first[k]:first[k + 1]]; an index below 0 is no feature."""
        n, trees = len(first) - 1, len(self.roots)
        x, out = np.zeros((min(n, rows), width)), np.zeros(n)
        for lo in range(0, n, rows):
            m = min(rows, n - lo)
            i, v = index[first[lo] : first[lo + m]], value[first[lo] : first[lo + m]]
            r = np.repeat(np.arange(m), np.diff(first[lo : lo + m + 1]))
            if (i < 0).any():
                r, i, v = r[i >= 0], i[i >= 0], v[i >= 0]
            x[r, i] = v
            # All trees of a few rows at once; walks that are at a leaf drop out.
            at, walk = np.tile(self.roots, m), np.arange(m * trees)
            node = at
            while len(walk):
                feature = self.feature[node]
                inner = feature >= 0
                walk, node, feature = walk[inner], node[inner], feature[inner]
                node = np.where(x[walk // trees, feature] <= self.threshold[node], self.left[node], self.right[node])
                at[walk] = node
            out[lo : lo + m] = self.chance[at].reshape(m, trees).sum(1)
            x[r, i] = 0
        return out / trees


class RandomForestMatcher:
    """fit(pairs with truth) then transform(pairs): adds score and predicted."""

    def __init__(self, trees: int = 100, k: int = 2500, grids: int = 2, seed: int = 1, max_depth: int = 30, max_train: int = MAX_TRAIN, order: bool = False):
        self.trees, self.k, self.grids, self.seed, self.max_depth, self.max_train, self.order = trees, k, grids, seed, max_depth, max_train, order

    @property
    def base(self) -> int:
        """Number of features before the trigrams."""
        return 2 + 2 * self.grids + self.order

    def fit(self, train: DataFrame, wide: Wide | None = None, dictionary: list[str] | None = None) -> RandomForestMatcher:
        """``train`` is pairs with truth, or rows of ``wide`` together with the dictionary of their labels."""
        train = train.where("truth is not null")
        spark = train.sparkSession
        if wide is None:
            self.dictionary = train_dictionary(train, self.k)
            rows = vectors(train, self.dictionary, self.grids, self.order).select("pair_id", "index", "value", "truth").persist()
            places = None
        else:
            self.dictionary = dictionary[: self.k]
            rows, places = train.select("pair_id", "index", "value", "truth"), wide.positions(self.dictionary, self.grids, self.order)
        self.width = self.base + len(self.dictionary)
        n, entries = rows.agg(F.count("*"), F.coalesce(F.sum(F.size("index")), F.lit(0))).first()
        self.path, self._model = f"{shared_folder(spark)}/forest-{uuid.uuid4().hex}", None
        if 0 < entries <= TASK_ENTRIES:
            self._grow(rows, places)
        else:
            self._fit_by_library(rows, places, n)
        rows.unpersist()
        self.flat = FlatForest.load(spark, self.path)
        return self

    def _grow(self, rows: DataFrame, places: np.ndarray | None) -> None:
        """Each task gets the whole train part and grows its share of the trees, which go to the shared folder in the library's format."""
        spark, base, width, trees, depth, seed = rows.sparkSession, self.base, self.width, self.trees, self.max_depth, self.seed
        tasks = max(min(trees, spark.sparkContext.defaultParallelism), 1)
        share = spark.sparkContext.broadcast(places)

        def grown(batches):
            parts = list(batches)
            if not parts:
                return
            table = pa.Table.from_batches(parts).combine_chunks()
            index, value, first = _flat(*(table[c].chunk(0) for c in ("index", "value")), share.value)
            part = TrainPart.of(index, value, first, table["truth"].to_numpy() == 1, base, width, BINS)
            mine = table["task"][0].as_py()
            del parts, table, index, value
            for tree in range(mine, trees, tasks):
                t = grow(part, math.ceil(math.sqrt(width)), depth, np.random.default_rng([seed, tree]))
                inner, n = t["left"] >= 0, len(t["left"])
                lists = lambda x, size: pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(size)], pa.int32()), pa.array(x, pa.float64()))
                of = lambda **x: pa.StructArray.from_arrays(list(x.values()), list(x))
                whole = lambda x: pa.array(x, pa.int32())
                p = t["ones"] / (t["ones"] + t["zeros"])
                split = of(featureIndex=whole(t["feature"]), leftCategoriesOrThreshold=lists(t["threshold"][inner], inner), numCategories=whole(np.full(n, -1)))
                node = of(
                    id=whole(np.arange(n)), prediction=pa.array((t["ones"] > t["zeros"]).astype(float)), impurity=pa.array(2 * p * (1 - p)), impurityStats=lists(np.stack([t["zeros"], t["ones"]], 1).ravel(), np.full(n, 2)),
                    rawCount=pa.array((t["ones"] + t["zeros"]).astype(np.int64)), gain=pa.array(t["gain"]), leftChild=whole(t["left"]), rightChild=whole(t["right"]), split=split,
                )
                yield pa.RecordBatch.from_arrays([whole(np.full(n, tree)), node], ["treeID", "nodeData"])

        dealt = rows.withColumn("task", F.explode(F.sequence(F.lit(0), F.lit(tasks - 1)))).repartitionById(tasks, F.col("task")).sortWithinPartitions("pair_id")
        dealt.mapInArrow(grown, NODES).write.parquet(f"{self.path}/data")
        about = lambda kind, **more: json.dumps({"class": f"org.apache.spark.ml.classification.{kind}", "timestamp": 0, "sparkVersion": spark.version, "uid": f"{kind}_{uuid.uuid4().hex[:12]}", "paramMap": {"maxBins": BINS, "maxDepth": depth, "seed": seed} | more.pop("params", {}), "defaultParamMap": {"featuresCol": "features", "labelCol": "label", "predictionCol": "prediction", "probabilityCol": "probability", "rawPredictionCol": "rawPrediction", "leafCol": "", "impurity": "gini"}} | more)
        sizes = {"numFeatures": width, "numClasses": 2}
        spark.createDataFrame([(about("RandomForestClassificationModel", params={"numTrees": trees, "featureSubsetStrategy": "sqrt"}, numTrees=trees, **sizes),)], "value string").coalesce(1).write.text(f"{self.path}/metadata")
        spark.createDataFrame([(i, about("DecisionTreeClassificationModel", **sizes), 1.0) for i in range(trees)], "_1 int, _2 string, _3 double").coalesce(1).write.parquet(f"{self.path}/treesMetadata")

    def _fit_by_library(self, rows: DataFrame, places: np.ndarray | None, n: int) -> None:
        if n > self.max_train:
            rows = rows.where(uniform("thin", F.col("pair_id")) < self.max_train / n)
        width = self.width

        @F.udf(VectorUDT())  # on the bounded train part only
        def to_vector(index, value):
            if places is None:
                return SparseVector(width, index, value)
            return SparseVector(width, sorted((int(places[i]), v) for i, v in zip(index, value) if places[i] >= 0))

        # Few small files would be few tasks; an order of rows, as bags of rows are drawn by partition.
        rows = rows.repartition(max(rows.sparkSession.sparkContext.defaultParallelism, 1), "pair_id").sortWithinPartitions("pair_id")
        rows = rows.select(to_vector("index", "value").alias("features"), F.col("truth").cast("double").alias("label")).persist()
        forest = RandomForestClassifier(numTrees=self.trees, maxDepth=self.max_depth, maxBins=BINS, seed=self.seed, featureSubsetStrategy="sqrt", cacheNodeIds=True, maxMemoryInMB=512)
        forest.fit(rows).save(self.path)
        rows.unpersist()

    @property
    def model(self) -> RandomForestClassificationModel:
        """The forest as the library's model, read when asked for."""
        if self._model is None:
            self._model = RandomForestClassificationModel.load(self.path)
        return self._model

    def save(self, spark: SparkSession, path: str) -> None:
        """The model, and beside it its dictionary and number of grids."""
        self.model.write().overwrite().save(f"{path}/model")
        rows = [(i, g, self.grids, self.order) for i, g in enumerate(self.dictionary)] or [(-1, None, self.grids, self.order)]
        spark.createDataFrame(rows, "i int, gram string, grids int, with_order boolean").write.mode("overwrite").parquet(f"{path}/dictionary")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> RandomForestMatcher:
        rows = spark.read.parquet(f"{path}/dictionary").orderBy("i").collect()  # k rows
        out = cls(k=len(rows), grids=rows[0]["grids"], order=rows[0]["with_order"])
        out.dictionary = [r["gram"] for r in rows if r["i"] >= 0]
        out.width = out.base + len(out.dictionary)
        out.path, out._model = f"{path}/model", None
        out.flat = FlatForest.load(spark, out.path)
        return out

    def transform(self, pairs: DataFrame, symmetric: bool = False, wide: Wide | None = None) -> DataFrame:
        """``pairs`` (or rows of ``wide``) with score and predicted; ``symmetric`` takes the mean of a pair's score and that of the pair turned round."""
        spark, base, width = pairs.sparkSession, self.base, self.width
        places = None if wide is None else wide.positions(self.dictionary, self.grids, self.order)
        shared = spark.sparkContext.broadcast((self.flat, places))

        def score(index: pa.Array, value: pa.Array) -> pa.Array:
            flat, places = shared.value
            i, v, first = _flat(index, value, places)
            got = flat.probability(i, v, first, width)
            if symmetric:  # trigram differences change their sign, all else stays
                got = (got + flat.probability(i, np.where(i >= base, -v, v), first, width)) / 2
            return pa.array(got)

        rows = pairs if wide is not None else vectors(pairs, self.dictionary, self.grids, self.order)
        tasks = spark.sparkContext.defaultParallelism
        if wide is not None and rows.rdd.getNumPartitions() < tasks:  # few bytes, but much work
            rows = rows.repartition(tasks, "pair_id")
        return rows.withColumn("score", F.arrow_udf(score, "double")("index", "value")).withColumn("predicted", (F.col("score") > 0.5).cast("int")).drop("index", "value")
