"""User-defined forms of the library's rules: a vectorised judge, an aggregate, and a table function of name words."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from semcat.plans.lexicon import name_affinity, words


def judge_column():
    """A pandas UDF of (source, target), both as table.column: the lexical judge's score, a batch at a time."""

    @F.pandas_udf("double")
    def score(source: pd.Series, target: pd.Series) -> pd.Series:
        return pd.Series([name_affinity(s.split(".")[1], *t.split(".")) for s, t in zip(source, target, strict=True)], dtype="float64")

    return score


def spread_aggregate():
    """A grouped pandas UDF: the distance between the greatest and the least value; null without values. A group is gathered in one
    task, so built-in min and max are the way for large groups."""

    @F.pandas_udf("double")
    def spread(v: pd.Series) -> float:
        v = v.dropna()
        return float(v.max() - v.min()) if len(v) else None

    return spread


def words_function():
    """A table function that gives the words of a column name with their places."""

    @udtf(returnType="place int, word string")
    class NameWords:
        def eval(self, column: str):
            for i, w in enumerate(words(column)):
                yield i, w

    return NameWords
