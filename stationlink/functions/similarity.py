"""String similarities of two labels: expressions where Spark has the parts, Arrow functions where it has not."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from stationlink.functions import kernels, text

DOUBLE = T.DoubleType()


def edit(a, b) -> Column:
    """(longer length - edit distance) / longer length; 1 for two empty labels."""
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    longer = F.greatest(F.length(a), F.length(b))
    return F.when(longer == 0, F.lit(1.0)).otherwise(F.try_divide((longer - F.levenshtein(a, b)).cast("double"), longer))


def jaccard(a, b) -> Column:
    """Shared tokens over all tokens; without any, 1 if the labels are equal."""
    x, y = text.tokens(a), text.tokens(b)
    union = F.size(F.array_union(x, y))
    return F.when(union == 0, (a == b).cast("double")).otherwise(F.try_divide(F.size(F.array_intersect(x, y)).cast("double"), union))


def orderings(token_array: Column) -> Column:
    """All orderings of all non-empty subsets of at most two tokens, joined by spaces."""
    t = token_array
    both = F.array(F.concat(t[0], F.lit(" "), t[1]), F.concat(t[1], F.lit(" "), t[0]))
    return F.when(F.size(t) == 2, F.concat(t, both)).otherwise(t)


def bts_small(a: Column, b: Column) -> Column:
    """Best token subsequence similarity of labels of one or two tokens each."""
    ways = F.array_max(F.concat(F.transform(orderings(text.tokens(a)), lambda s: edit(s, b)), F.transform(orderings(text.tokens(b)), lambda s: edit(s, a))))
    return F.greatest(ways, (a == b).cast("double"))


def bts_literal(a, b) -> Column:
    """Best token subsequence if neither label has more than six orderings (two tokens), token Jaccard otherwise."""
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    n, m = F.size(text.tokens(a)), F.size(text.tokens(b))
    small = n.between(1, 2) & m.between(1, 2)
    return F.when(a == b, F.lit(1.0)).when(small, bts_small(a, b)).otherwise(jaccard(a, b))


def _batched(kernel):
    """An Arrow function of two labels from a kernel over lists of them; null if either is."""

    @F.pandas_udf(DOUBLE)
    def run(a: pd.Series, b: pd.Series) -> pd.Series:
        known = (a.notna() & b.notna()).to_numpy()
        out = np.full(len(a), np.nan)
        out[known] = kernel(list(a[known]), list(b[known]))
        return pd.Series(out).where(known, None).astype("float64")

    return run


#: Best of 1 - edit distance to a prefix of the other / length of the whole label, both ways round.
prefix_edit = _batched(kernels.prefix_edits)
jaro = _batched(kernels.jaros)
jaro_winkler = _batched(lambda a, b: kernels.jaros(a, b, winkler=True))
#: Best token subsequence of labels of up to six tokens, Jaccard beyond.
bts_tokens = _batched(kernels.best_token_subsequences)


MEASURES = {"ED": edit, "PED": prefix_edit, "JAC": jaccard, "BTS": bts_literal, "J": jaro, "JW": jaro_winkler, "BTS6": bts_tokens}


def score_pairs(pairs: DataFrame, measures: list[str], a: str = "label_a", b: str = "label_b") -> DataFrame:
    """``pairs`` with a column for each measure, computed once for each distinct pair of labels; pairs with a null label are left out."""
    distinct = pairs.select(F.col(a).alias("__a"), F.col(b).alias("__b")).distinct()
    scored = distinct.select("__a", "__b", *[MEASURES[m](F.col("__a"), F.col("__b")).alias(m) for m in measures])
    return pairs.join(scored, (pairs[a] == scored["__a"]) & (pairs[b] == scored["__b"])).drop("__a", "__b")
