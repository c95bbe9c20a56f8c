"""Signatures: features of an object weighted by how common they are in its trace and how rare over objects."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .prepare import time_bin, to_grid

OBJECT = ["side", "oid"]


def counts(trace: DataFrame, feature: str | Column = "pid") -> DataFrame:
    """``side, oid, fid, n``: how often each object has each feature (summed in every task before the exchange)."""
    fid = F.col(feature) if isinstance(feature, str) else feature
    return trace.select(*OBJECT, fid.alias("fid")).where(F.col("fid").isNotNull()).groupBy(*OBJECT, "fid").agg(F.count(F.lit(1)).alias("n"))


def tf(counted: DataFrame) -> DataFrame:
    total = F.sum("n").over(Window.partitionBy(*OBJECT))
    return counted.withColumn("tf", F.col("n") / total)


def idf(counted: DataFrame, scope: str = "own") -> DataFrame:
    """``[side,] fid, idf``: logarithm of objects over objects that hold the feature.

    ``own`` counts within each side, ``candidate`` over the candidates only, ``union`` over both sides' objects.
    """
    base = counted.where("side = 'D'") if scope == "candidate" else counted
    keys = ["side"] if scope == "own" else []
    objects = base.select(*OBJECT).distinct().groupBy(*keys).agg(F.count(F.lit(1)).alias("objects"))
    held = base.groupBy(*keys, "fid").agg(F.count(F.lit(1)).alias("df"))
    # one row a side at most
    joined = held.join(F.broadcast(objects), keys) if keys else held.crossJoin(F.broadcast(objects))
    return joined.select(*keys, "fid", F.log(F.col("objects") / F.col("df")).alias("idf"))


def l2(sig: DataFrame) -> DataFrame:
    norm = F.sqrt(F.sum(F.col("w") * F.col("w")).over(Window.partitionBy(*OBJECT)))
    return sig.withColumn("w", F.col("w") / norm)


def l1(sig: DataFrame) -> DataFrame:
    return sig.withColumn("w", F.col("w") / F.sum("w").over(Window.partitionBy(*OBJECT)))


def weigh(counted: DataFrame, scheme: str = "tfidf", scope: str = "own") -> DataFrame:
    """Unit-length ``side, oid, fid, w`` by 'tfidf', 'tf' or 'idf'; features of weight 0 (held by all) are left out."""
    if scheme == "tf":
        return l2(tf(counted).select(*OBJECT, "fid", F.col("tf").alias("w")))
    rare = idf(counted, scope).where("idf > 0")
    held = tf(counted) if scheme == "tfidf" else counted
    w = F.col("tf") * F.col("idf") if scheme == "tfidf" else F.col("idf")
    return l2(held.join(rare, ["side", "fid"] if scope == "own" else ["fid"]).select(*OBJECT, "fid", w.alias("w")))


def cut(sig: DataFrame, m: int | None, renormalise: bool = True) -> DataFrame:
    """Keep the m heaviest features of each object (ties to the smaller feature), at unit length again; None keeps all."""
    if m is None:
        return sig
    order = Window.partitionBy(*OBJECT).orderBy(F.round("w", 12).desc(), "fid")
    kept = sig.withColumn("__r", F.row_number().over(order)).where(F.col("__r") <= m).drop("__r")
    return l2(kept) if renormalise else kept


def spatial(trace: DataFrame, m: int | None = None, scheme: str = "tfidf", scope: str = "own") -> DataFrame:
    return cut(weigh(counts(trace), scheme, scope), m)


def qgrams(trace: DataFrame, q: int, order: list[str]) -> DataFrame:
    """``side, oid, fid``: q consecutive places as one string; traces shorter than q have none."""
    w = Window.partitionBy(*OBJECT).orderBy(*order)
    parts = [F.col("pid").cast("string")] + [F.lead("pid", i).over(w).cast("string") for i in range(1, q)]
    grams = trace.select(*OBJECT, *[p.alias(f"p{i}") for i, p in enumerate(parts)]).dropna(subset=[f"p{i}" for i in range(q)])
    return grams.select(*OBJECT, F.concat_ws("_", *[f"p{i}" for i in range(q)]).alias("fid"))


def sequential(trace: DataFrame, q: int, order: list[str], m: int | None = None, scheme: str = "tfidf") -> DataFrame:
    return cut(weigh(counts(qgrams(trace, q, order), "fid"), scheme), m)


def spatiotemporal(trace: DataFrame, r: int, hours: int = 1, m: int | None = None) -> DataFrame:
    cells = to_grid(trace, r).withColumn("pid", F.col("pid") * (24 // hours) + time_bin(F.col("t"), hours))
    return cut(weigh(counts(cells)), m)


def weight_curve(sig: DataFrame, places: list[int]) -> DataFrame:
    """``r, share``: part of all (squared) weight that the r heaviest features hold, mean over objects."""
    own = Window.partitionBy(*OBJECT)
    ranked = sig.withColumn("r", F.row_number().over(own.orderBy(F.round("w", 12).desc(), "fid"))).withColumn("total", F.sum(F.col("w") * F.col("w")).over(own))
    shares = ranked.groupBy(*OBJECT).agg(*[(F.sum(F.when(F.col("r") <= p, F.col("w") * F.col("w")).otherwise(0.0)) / F.first("total")).alias(f"s{p}") for p in places])
    stacked = F.explode(F.array(*[F.struct(F.lit(p).alias("r"), F.col(f"s{p}").alias("s")) for p in places]))
    return shares.select(stacked.alias("e")).groupBy("e.r").agg(F.round(F.avg("e.s"), 6).alias("share"))


def pack(sig: DataFrame) -> DataFrame:
    """``side, oid, sig``: one row an object, its features as an array in order of fid (as long as its signature)."""
    return sig.groupBy(*OBJECT).agg(F.sort_array(F.collect_list(F.struct("fid", "w"))).alias("sig"))
