"""The SQL surface: distances and clique edges callable from spark.sql."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from .metric import l2sq


def register(spark: SparkSession) -> None:
    """Registers vector_l2sq(a, b), Arrow-batched, and the table function clique_edges(ids)."""

    def l2sq(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([float(((x - y) ** 2).sum()) for x, y in zip(a, b, strict=True)], dtype="float64")

    class CliqueEdges:
        """All ordered pairs of a clique's members, without loops."""

        def eval(self, ids: list):
            for a in ids:
                for b in ids:
                    if a != b:
                        yield a, b

    spark.udf.register("vector_l2sq", F.pandas_udf(l2sq, "double"))
    spark.udtf.register("clique_edges", F.udtf(CliqueEdges, returnType="src long, dst long"))


def register_thresholds(spark: SparkSession) -> None:
    """coverage_need, clique_size and sample_size of a share num / den, as SQL functions in whole numbers."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION coverage_need(num BIGINT, den BIGINT, n BIGINT) RETURNS BIGINT RETURN (num * (n - 1) + den - 1) DIV den")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION clique_size(num BIGINT, den BIGINT, times BIGINT) RETURNS BIGINT RETURN (times * den + den - num - 1) DIV (den - num)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sample_size(num BIGINT, den BIGINT, n BIGINT, delta DOUBLE) RETURNS BIGINT RETURN CAST(ceil(16 * ln(n / delta) * den / (den - num)) AS BIGINT)")


def register_neighbors(spark: SparkSession, ids: np.ndarray, vecs: np.ndarray) -> None:
    """neighbors(vec, k): the k nearest of a bounded block of points, as a table function (id, pos, dist)."""

    class Neighbors:
        def eval(self, vec: list, k: int):
            d = l2sq(np.array([vec], float), vecs)[0]
            for pos, i in enumerate(np.lexsort((ids, d))[:k], 1):
                yield int(ids[i]), pos, float(d[i])

    spark.udtf.register("neighbors", F.udtf(Neighbors, returnType="id long, pos int, dist double"))
