"""Linkability and protection: how much data links an object, and suppression of its signature round by round."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import materialise
from .prepare import int_hash, interleaved, to_grid
from .weights import counts, cut, weigh


def closure(trace: DataFrame, m: int, rounds: int, scope: str = "entire") -> list[tuple[DataFrame, DataFrame]]:
    """Traces before and after each round of suppression.

    A round finds each object's m heaviest places, over its whole trace ('entire') or over each half ('half'), and removes every point at
    one of them from the object's trace. Rounds are written to the shared folder.
    """
    out = []
    now = trace
    for _ in range(rounds):
        split = now.withColumn("side", F.lit("A")) if scope == "entire" else interleaved(now)
        heavy = cut(weigh(counts(split)), m, renormalise=False).select("oid", F.col("fid").alias("pid")).distinct()
        after = materialise(now.join(heavy, ["oid", "pid"], "left_anti").select(*now.columns), "released")
        out.append((now, after))
        now = after
    return out


def release(trace: DataFrame, suppressed: DataFrame, how: str = "suppress", cell: float = 10.0) -> DataFrame:
    """Trace without (oid, pid) of ``suppressed``, or with these places replaced by the centre of a coarse cell ('generalize')."""
    if how == "suppress":
        return trace.join(suppressed.select("oid", "pid").distinct(), ["oid", "pid"], "left_anti").select(*trace.columns)
    marked = trace.join(suppressed.select("oid", "pid", F.lit(1).alias("hit")).distinct(), ["oid", "pid"], "left")
    cx, cy = F.floor(F.col("x") / cell), F.floor(F.col("y") / cell)
    coarse = lambda c, n: F.when(F.col("hit") == 1, (c + 0.5) * cell).otherwise(F.col(n)).alias(n)
    pid = F.when(F.col("hit") == 1, -(cx * 100000 + cy + 1)).otherwise(F.col("pid")).cast("long").alias("pid")
    return marked.select(*[pid if c == "pid" else coarse(cx, "x") if c == "x" else coarse(cy, "y") if c == "y" else F.col(c) for c in trace.columns])


def point_uniqueness(trace: DataFrame, p: int, r: int = 100, hours: int = 24, seed: int = 5) -> DataFrame:
    """``objects, unique``: objects that p random (cell, time bin, day) points of their own trace single out."""
    slot = F.floor(F.unix_timestamp(F.col("t").cast("timestamp")) / (3600 * hours)).cast("long")
    visits = to_grid(trace, r).select("oid", (F.col("pid") * 1000000 + slot % 1000000).alias("v")).distinct()
    order = Window.partitionBy("oid").orderBy(int_hash(F.col("v") + F.col("oid"), seed), "v")
    drawn = visits.withColumn("r", F.row_number().over(order)).where(F.col("r") <= p).select(F.col("oid").alias("qid"), "v")
    full = drawn.groupBy("qid").agg(F.count(F.lit(1)).alias("drawn"))
    hits = drawn.join(visits, "v").groupBy("qid", "oid").agg(F.count(F.lit(1)).alias("n")).join(full, "qid").where("n = drawn").groupBy("qid").agg(F.count(F.lit(1)).alias("crowd"))
    return hits.agg(F.count(F.lit(1)).alias("objects"), F.count(F.when(F.col("crowd") == 1, 1)).alias("unique"))
