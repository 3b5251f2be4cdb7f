"""User-defined functions in SQL: neighbour expansion as a table function, and vectorised expressions."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


@F.udtf(returnType="src long, dst long, w long")
class Neighbours:
    """Rows ``src, dst, w`` from a vertex and its adjacency array of ``struct<dst, w>``."""

    def eval(self, id: int, neighbours: list):  # noqa: A002
        for n in neighbours or []:
            yield id, n["dst"], n["w"]


def register(spark: SparkSession) -> None:
    """Make ``neighbours(id, adjacency)`` callable in SQL: ``SELECT n.* FROM adj, LATERAL neighbours(id, neighbours) n``."""
    spark.udtf.register("neighbours", Neighbours)


def expression(function: Callable[..., pd.Series], kind: str = "long") -> Callable[..., Column]:
    """A procedure call of a program as a vectorised function over Arrow batches."""
    return F.pandas_udf(function, kind)
