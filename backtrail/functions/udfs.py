"""Opaque steps: vectorised Python functions for what built-in functions cannot say.  They must be deterministic."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import functions as F


def vowel_share():
    """Share of vowels in a text, as an Arrow-batched scalar function."""

    @F.pandas_udf("double")
    def share(texts: pd.Series) -> pd.Series:
        return texts.fillna("").str.count("[aeiou]") / texts.fillna("").str.len().clip(lower=1)

    return share


def dot_product():
    """Product of two vectors in double precision, over Arrow batches."""

    @F.pandas_udf("double")
    def dot(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([float(np.dot(np.asarray(x, float), np.asarray(y, float))) for x, y in zip(a, b)])

    return dot


def median_of():
    """Exact median of a group, as a grouped aggregate.  A group must fit a task."""

    @F.pandas_udf("double")
    def median(values: pd.Series) -> float:
        return float(values.median())

    return median


def numbered_lines():
    """A table function: a text's lines with their ordinal, which is the label part they get."""

    @F.udtf(returnType="position int, line string")
    class Lines:
        def eval(self, text: str):
            for i, line in enumerate((text or "").split("\n")):
                yield i, line

    return Lines
