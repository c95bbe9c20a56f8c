"""Measures of linking and of the utility of protected traces."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .weights import OBJECT, counts, idf


def acc_at(knn: DataFrame, queries: DataFrame, ks: list[int]) -> DataFrame:
    """``k, hits, queries, acc``: share of all queries (``qid``) whose own id is among their first k neighbours."""
    n = queries.select("qid").distinct().agg(F.count(F.lit(1)).alias("queries"))
    hits = knn.where("qid = oid").agg(*[F.count(F.when(F.col("rnk") <= k, 1)).alias(f"h{k}") for k in ks])
    rows = F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.col(f"h{k}").alias("hits")) for k in ks]))
    return hits.crossJoin(n).select(rows.alias("e"), "queries").select("e.k", "e.hits", "queries", F.round(F.col("e.hits") / F.col("queries"), 6).alias("acc"))  # two single rows


def recall_at(knn: DataFrame, exact: DataFrame, k: int) -> DataFrame:
    """Share of the exact first k neighbours that an approximate list has too."""
    want = exact.where(F.col("rnk") <= k).select("qid", "oid")
    got = knn.where(F.col("rnk") <= k).select("qid", "oid", F.lit(1).alias("hit"))
    return want.join(got, ["qid", "oid"], "left").agg(F.count(F.lit(1)).alias("wanted"), F.count("hit").alias("found")).withColumn("recall", F.round(F.col("found") / F.col("wanted"), 6))


def data_remaining(before: DataFrame, after: DataFrame) -> DataFrame:
    """Mean over objects of points kept."""
    a = before.groupBy("oid").agg(F.count(F.lit(1)).alias("n0"))
    b = after.groupBy("oid").agg(F.count(F.lit(1)).alias("n1"))
    return a.join(b, "oid", "left").agg(F.round(F.avg(F.coalesce("n1", F.lit(0)) / F.col("n0")), 6).alias("data_remaining"))


def mbr_retained(before: DataFrame, after: DataFrame) -> DataFrame:
    """Mean over objects of box area after to before; an area of 0 counts as kept if it was 0 before, a vanished trace as 0."""
    area = (F.max("x") - F.min("x")) * (F.max("y") - F.min("y"))
    a = before.groupBy("oid").agg(area.alias("a0"))
    b = after.groupBy("oid").agg(area.alias("a1"))
    ratio = F.when(F.col("a1").isNull(), 0.0).when(F.col("a0") == 0, 1.0).otherwise(F.col("a1") / F.col("a0"))
    return a.join(b, "oid", "left").agg(F.round(F.avg(ratio), 6).alias("mbr_overlap"))


def grid_coverage(before: DataFrame, after: DataFrame, cell: float) -> DataFrame:
    """Mean over objects of visited grid cells after to before."""
    cells = lambda t, n: t.groupBy("oid").agg(F.count_distinct(F.floor(F.col("x") / cell), F.floor(F.col("y") / cell)).alias(n))
    return cells(before, "c0").join(cells(after, "c1"), "oid", "left").agg(F.round(F.avg(F.coalesce("c1", F.lit(0)) / F.col("c0")), 6).alias("coverage"))


def unicity(trace: DataFrame) -> DataFrame:
    """Mean over objects of their mean idf, and share of objects with a place of their own. ``trace`` needs a side."""
    counted = counts(trace)
    own = counted.join(idf(counted), ["side", "fid"]).groupBy(*OBJECT).agg(F.avg("idf").alias("mean_idf"))
    alone = counted.withColumn("df", F.count(F.lit(1)).over(Window.partitionBy("side", "fid"))).where("df = 1").select(*OBJECT).distinct().withColumn("alone", F.lit(1))
    return own.join(alone, OBJECT, "left").agg(F.round(F.avg("mean_idf"), 6).alias("mean_idf"), F.round(F.avg(F.coalesce("alone", F.lit(0))), 6).alias("own_place"))


def k_of_point(trace: DataFrame) -> DataFrame:
    """Objects at each place: the size of the crowd a point hides in."""
    return trace.groupBy("pid").agg(F.count_distinct("oid").alias("objects"))
