"""Table functions and a grouped aggregate in Python, each beside a form of built-in functions that gives the same rows."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@F.udtf(returnType="at int, gram string")
class Grams:
    """q consecutive tokens of an array as one string, with the place of the first."""

    def eval(self, tokens: list, q: int):
        for i in range(len(tokens or []) - q + 1):
            yield i, "_".join(map(str, tokens[i : i + q]))


@F.udtf(returnType="cx long, cy long")
class BoxCells:
    """Grid cells that a box touches."""

    def eval(self, x1: float, y1: float, x2: float, y2: float, cell: float):
        for cx in range(int(x1 // cell), int(x2 // cell) + 1):
            for cy in range(int(y1 // cell), int(y2 // cell) + 1):
                yield cx, cy


def register(spark: SparkSession) -> None:
    """SQL names ``grams(tokens, q)`` and ``box_cells(x1, y1, x2, y2, cell)``."""
    spark.udtf.register("grams", Grams)
    spark.udtf.register("box_cells", BoxCells)


def grams(df: DataFrame, tokens: str, q: int) -> DataFrame:
    """``Grams`` by built-in functions: the columns of ``df`` and ``at, gram``."""
    n = F.size(tokens) - (q - 1)
    parts = F.when(n > 0, F.transform(F.sequence(F.lit(1), n), lambda i: F.array_join(F.transform(F.slice(tokens, i, q), lambda t: t.cast("string")), "_")))
    return df.select("*", F.posexplode(parts).alias("at", "gram"))


def box_cells(df: DataFrame, cell: float) -> DataFrame:
    """``BoxCells`` by built-in functions."""
    at = lambda c: F.floor(F.col(c) / cell).cast("long")
    return df.withColumn("cx", F.explode(F.sequence(at("x1"), at("x2")))).withColumn("cy", F.explode(F.sequence(at("y1"), at("y2"))))


def mbr_of(x: str = "x", y: str = "y") -> Column:
    """Box of a group's places as an array (x1, y1, x2, y2); ``boxes`` does the same with built-in aggregates."""

    def box(x: pd.Series, y: pd.Series) -> list:
        return [x.min(), y.min(), x.max(), y.max()]

    return F.pandas_udf(box, "array<double>", F.PandasUDFType.GROUPED_AGG)(x, y)
