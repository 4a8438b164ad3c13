"""Text similarities: cleaning, token sort, edit similarity in three forms, cosine."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T


def clean(c: Column) -> Column:
    """Lower case; runs of anything but letters and digits become one space."""
    return F.trim(F.regexp_replace(F.lower(c), r"[^\p{L}\p{N}]+", " "))


def token_sort(c: Column) -> Column:
    """The cleaned tokens in alphabetic order; made once for each place, before any pair."""
    return F.array_join(F.array_sort(F.split(clean(c), " ")), " ")


@F.pandas_udf(T.IntegerType())
def _lcs(a: pd.Series, b: pd.Series) -> pd.Series:
    def one(x: str | None, y: str | None) -> int | None:
        if x is None or y is None:
            return None
        row = [0] * (len(y) + 1)
        for p in x:
            diagonal = 0
            for j, q in enumerate(y, 1):
                diagonal, row[j] = row[j], diagonal + 1 if p == q else max(row[j], row[j - 1])
        return row[-1]

    return pd.Series([one(x, y) for x, y in zip(a, b)])


def edit_similarity(a: Column, b: Column, metric: str = "lev_max") -> Column:
    """In [0, 1]; null on either side scores 0, two empty strings 1.

    ``lev_max``: 1 - distance / longer length; ``lev_sum``: 1 - distance / summed lengths; ``indel``: twice the
    longest common subsequence over the summed lengths.
    """
    la, lb = F.char_length(a), F.char_length(b)
    if metric == "lev_max":
        score = 1 - F.try_divide(F.levenshtein(a, b), F.greatest(la, lb))
    elif metric == "lev_sum":
        score = 1 - F.try_divide(F.levenshtein(a, b), la + lb)
    elif metric == "indel":
        score = F.try_divide(2 * _lcs(a, b), la + lb)
    else:
        raise ValueError(metric)
    return F.when(a.isNull() | b.isNull(), F.lit(0.0)).otherwise(F.coalesce(score, F.lit(1.0)))


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def cosine(a: Column, b: Column, clip: bool = False) -> Column:
    """0 where a norm is 0."""
    c = F.coalesce(F.try_divide(dot(a, b), F.sqrt(dot(a, a)) * F.sqrt(dot(b, b))), F.lit(0.0))
    return F.greatest(F.lit(0.0), F.least(F.lit(1.0), c)) if clip else c
