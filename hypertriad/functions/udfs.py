"""Python functions for SQL users: a scalar one and an aggregate for comparison with the built-in forms, and a table
function that finds the triads of one small hypergraph."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from .patterns import PATTERN_TABLE

_BY_SIGNATURE = {s[1:]: p for p, s in PATTERN_TABLE.items()}


def pattern_of_python_sets(a: set, b: set, c: set) -> int | None:
    """The pattern of three sets; None unless they are distinct and meet pairwise."""
    if not (a & b and a & c and b & c):
        return None
    nests = sum(x <= y or y <= x for x, y in ((a, b), (a, c), (b, c)))
    pairs = bool((a & b) - c) + bool((a & c) - b) + bool((b & c) - a)
    solos = bool(a - b - c) + bool(b - a - c) + bool(c - a - b)
    return _BY_SIGNATURE.get((nests, int(bool(a & b & c)), pairs, solos))


def register(spark: SparkSession) -> None:
    """hyper_pattern_arrow (scalar, Arrow batches), mean_relative_error (aggregate) and hyper_triangles (table function)."""

    @F.pandas_udf("int")
    def hyper_pattern_arrow(a: pd.Series, b: pd.Series, c: pd.Series) -> pd.Series:
        return pd.Series([pattern_of_python_sets(set(x), set(y), set(z)) for x, y, z in zip(a, b, c)], dtype="Int32")

    @F.pandas_udf("double")
    def mean_relative_error(cnt: pd.Series, est: pd.Series) -> float:
        some = cnt > 0
        return float(np.mean(np.abs(cnt[some] - est[some]) / cnt[some])) if some.any() else float("nan")

    spark.udf.register("hyper_pattern_arrow", hyper_pattern_arrow)
    spark.udf.register("mean_relative_error", mean_relative_error)
    spark.udtf.register("hyper_triangles", F.udtf(HyperTriangles, returnType="i int, j int, k int, pattern int"))


class HyperTriangles:
    """Triads of one small hypergraph given as an array of member arrays; positions count from 0."""

    def eval(self, edges: list):
        sets = [set(e) for e in edges]
        for (i, a), (j, b), (k, c) in combinations(enumerate(sets), 3):
            p = pattern_of_python_sets(a, b, c)
            if p is not None and a != b and a != c and b != c:
                yield i, j, k, p
