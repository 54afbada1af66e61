"""One surface for all classifiers: fit on train pairs, add score and predicted to pairs, match feeds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stationlink.functions import naive, similarity, voting
from stationlink.operators import evaluate, groundtruth
from stationlink.operators.forest import RandomForestMatcher
from stationlink.operators.tfidf import TfidfModel


class StationMatcher:
    """``method``: PEQ, LEQ, P, a string measure (ED PED J JW JAC BTS BTS6 TFIDF), P+ one of those, or RF.

    Without thresholds given, ``fit`` takes those of the best F1 on its pairs.
    """

    def __init__(self, method: str = "P+TFIDF", d_hat: float | None = None, t: float | None = None, mode: str = "soft", **forest):
        self.method, self.d_hat, self.t, self.mode, self.forest, self.tfidf = method, d_hat, t, mode, forest, None

    def _scored(self, pairs: DataFrame, name: str) -> DataFrame:
        if name == "TFIDF":
            return self.tfidf.similarity(pairs, "a_label", "b_label")
        return similarity.score_pairs(pairs, [name], "a_label", "b_label")

    def fit(self, train: DataFrame) -> StationMatcher:
        if self.method == "RF":
            self.model = RandomForestMatcher(**self.forest).fit(train)
            return self
        string = self.method.removeprefix("P+")
        if string == "TFIDF":
            labels = train.select(F.col("a_label").alias("label")).union(train.select(F.col("b_label").alias("label"))).distinct()
            self.tfidf = TfidfModel.fit(labels)
        if self.method == "P" and self.d_hat is None:
            self.d_hat = evaluate.best_threshold(evaluate.sweep(train, "dist_m", evaluate.DISTANCE_GRID, below=True)).first()["t"]
        elif self.method.startswith("P+") and (self.d_hat is None or self.t is None):
            best = evaluate.best_threshold(evaluate.sweep_2d(self._scored(train, string), string, mode=self.mode)).first()
            self.d_hat, self.t = best["d_hat"], best["t"]
        elif self.method not in ("P", "PEQ", "LEQ") and self.t is None:
            self.t = evaluate.best_threshold(evaluate.sweep(self._scored(train, string), string, evaluate.STRING_GRID)).first()["t"]
        return self

    def transform(self, pairs: DataFrame) -> DataFrame:
        if self.method == "RF":
            return self.model.transform(pairs)
        if self.method in ("PEQ", "LEQ"):
            hit = naive.same_position(F.col("dist_m")) if self.method == "PEQ" else naive.same_label(F.col("a_label"), F.col("b_label"))
            return pairs.withColumn("predicted", hit).withColumn("score", hit.cast("double"))
        if self.method == "P":
            score = naive.decay(F.col("dist_m"), self.d_hat)
            return pairs.withColumn("score", score).withColumn("predicted", voting.decide(score))
        string = self.method.removeprefix("P+")
        scored = self._scored(pairs, string)
        if self.method.startswith("P+"):
            return evaluate.combined(scored, string, self.d_hat, self.t, self.mode)
        score = voting.rescale(F.col(string), self.t)
        return scored.withColumn("score", score).withColumn("predicted", voting.decide(score))


def match(idents: DataFrame, matcher: StationMatcher, radius_m: float = groundtruth.RADIUS_M) -> DataFrame:
    """Scored pairs of identifiers within the radius, by a fitted matcher."""
    return matcher.transform(groundtruth.radius_pairs(idents, radius_m))
