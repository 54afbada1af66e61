"""Label preparation: case, normalization rules, tokens, trigrams, stop words."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Rules for German labels (pattern, replacement), applied in this order to lower-cased labels.
GERMAN = (
    (r"[,\-\"]", " "),
    (r"[&+]", " und "),
    ("ä", "ae"),
    ("ö", "oe"),
    ("ü", "ue"),
    ("ß", "ss"),
    (r"str\.", "strasse"),
    (r"([a-z])strasse( |$)", "$1 strasse$2"),
    (r"(^| )str( |$)", "$1strasse$2"),
    (r"(^| )st( |$)", "$1strasse$2"),
    (r"(^| )hbf\.?( |$)", "$1hauptbahnhof$2"),
    (r"\s+", " "),
    (r"^\s|\s$", ""),
)


def fold_case(label) -> Column:
    return F.lower(label)


def normalize(label, rules=GERMAN, stop_words=()) -> Column:
    """Lower-cased label after all rules, without ``stop_words`` as whole tokens."""
    out = fold_case(label)
    for pattern, to in rules:
        out = F.regexp_replace(out, pattern, to)
    if stop_words:
        out = F.array_join(F.filter(F.split(out, " "), lambda t: ~t.isin(list(stop_words))), " ")
    return out


def words_in_order(label) -> Column:
    """Runs of letters, digits and underscores, in order, with repeats."""
    return F.filter(F.split(label, r"[^\p{L}\p{N}_]+"), lambda t: t != "")


def tokens(label) -> Column:
    """The set of word tokens."""
    return F.array_distinct(words_in_order(label))


def trigrams(label) -> Column:
    """All 3-grams of the label with one space at either end; as many as it has characters."""
    label = F.col(label) if isinstance(label, str) else label
    padded = F.concat(F.lit(" "), label, F.lit(" "))
    return F.when(F.length(label) > 0, F.transform(F.sequence(F.lit(1), F.greatest(F.length(label), F.lit(1))), lambda i: F.substr(padded, i, F.lit(3)))).otherwise(F.array().cast("array<string>"))


def drop_stop_words(token_array, words) -> Column:
    return F.filter(token_array, lambda t: ~t.isin(list(words))) if words else token_array


def auto_stop_words(labels: DataFrame, max_df: float = 0.2, column: str = "label") -> DataFrame:
    """(token, df, n) of tokens in more than ``max_df`` of the labels."""
    n = labels.agg(F.count("*").alias("n"))
    df = labels.select(F.explode(tokens(F.col(column))).alias("token")).groupBy("token").agg(F.count("*").alias("df"))
    return df.crossJoin(F.broadcast(n)).where(F.col("df") > max_df * F.col("n"))  # n is one row
