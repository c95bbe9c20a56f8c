"""Preparation of traces: assembly, filters, snapping, grids, time bins, samples and splits into the two sides."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Constants of the integer hash that samples and random splits use in every engine.
HASH_A, HASH_B, HASH_P = 48271, 11, 2147483647


def int_hash(c: Column, seed: int) -> Column:
    return ((c.cast("long") + 1) * HASH_A + seed * HASH_B) % HASH_P * HASH_A % HASH_P


def assemble(trace: DataFrame, ties: list[str]) -> DataFrame:
    """Number each object's points in time order from 1; ``ties`` order points of equal time."""
    return trace.withColumn("seq", F.row_number().over(Window.partitionBy("oid").orderBy("t", *ties)))


def min_points(trace: DataFrame, n: int) -> DataFrame:
    """Drop objects with fewer than n points."""
    long = trace.groupBy("oid").agg(F.count(F.lit(1)).alias("points")).where(F.col("points") >= n).select("oid")
    return trace.join(long, "oid", "left_semi")


def snap(points: DataFrame, anchors: DataFrame, radius: float) -> DataFrame:
    """Move each point to its nearest anchor (pid, x, y) within ``radius``, ties to the lower pid; points without one go.

    Anchors are posted in the nine grid cells around theirs, so the join is an equi-join on the cell; rows are told apart by all columns.
    """
    cell = lambda c: F.floor(c / F.lit(radius)).cast("long")
    near = anchors.select(F.col("pid").alias("a_pid"), F.col("x").alias("ax"), F.col("y").alias("ay"))
    shifts = F.array(*[F.lit(i) for i in (-1, 0, 1)])
    near = near.withColumn("dx", F.explode(shifts)).withColumn("dy", F.explode(shifts)).select("a_pid", "ax", "ay", (cell(F.col("ax")) + F.col("dx")).alias("cx"), (cell(F.col("ay")) + F.col("dy")).alias("cy"))
    d2 = (F.col("x") - F.col("ax")) ** 2 + (F.col("y") - F.col("ay")) ** 2
    placed = points.withColumn("cx", cell(F.col("x"))).withColumn("cy", cell(F.col("y"))).join(near, ["cx", "cy"]).withColumn("d2", d2).where(F.col("d2") <= radius * radius)
    return placed.groupBy("oid", "t", "x", "y").agg(F.min_by("a_pid", F.struct("d2", "a_pid")).alias("pid"), F.min("d2").alias("d2"))


def to_grid(trace: DataFrame, r: int, box: tuple[float, float, float, float] = (0.0, 0.0, 100.0, 100.0)) -> DataFrame:
    """Replace the place by its cell in an r x r grid over ``box`` (x1, y1, x2, y2); places beyond an edge fall into the nearest cell."""
    at = lambda c, low, high: F.greatest(F.lit(0), F.least(F.lit(r - 1), F.floor((F.col(c) - F.lit(low)) / F.lit((high - low) / r)))).cast("long")
    return trace.withColumn("pid", at("x", box[0], box[2]) * r + at("y", box[1], box[3]))


def time_bin(t: Column, hours: int) -> Column:
    return F.floor((F.hour(t) * 3600 + F.minute(t) * 60 + F.second(t)) / F.lit(hours * 3600)).cast("int")


def day(t: Column) -> Column:
    """Days since 2024-01-01, from 0."""
    return F.datediff(F.to_date(t), F.lit("2024-01-01").cast("date"))


def sample_objects(trace: DataFrame, n: int, seed: int = 0) -> DataFrame:
    """Trace of n objects, drawn by integer hash (the same in every engine)."""
    drawn = trace.select("oid").distinct().orderBy(int_hash(F.col("oid"), seed), "oid").limit(n)
    return trace.join(drawn, "oid", "left_semi")


def interleaved(trace: DataFrame) -> DataFrame:
    """Odd days (first, third, ...) are queries, even ones candidates."""
    return trace.withColumn("side", F.when(day(F.col("t")) % 2 == 0, "Q").otherwise("D"))


def _days(trace: DataFrame) -> DataFrame:
    return trace.select(day(F.col("t")).alias("d")).distinct()


def random_days(trace: DataFrame, n_q: int = 15, seed: int = 1) -> DataFrame:
    """n_q days drawn by integer hash are queries, the others candidates. A calendar month bounds what is broadcast."""
    ranked = _days(trace).withColumn("r", F.row_number().over(Window.orderBy(int_hash(F.col("d"), seed), "d")))
    side = F.when(F.col("r") <= n_q, "Q").otherwise("D")
    return trace.withColumn("d", day(F.col("t"))).join(F.broadcast(ranked.select("d", side.alias("side"))), "d").drop("d")


def serial(trace: DataFrame, n_q: int = 15) -> DataFrame:
    """The first n_q days are queries, the others candidates."""
    ranked = _days(trace).withColumn("r", F.row_number().over(Window.orderBy("d")))
    side = F.when(F.col("r") <= n_q, "Q").otherwise("D")
    return trace.withColumn("d", day(F.col("t"))).join(F.broadcast(ranked.select("d", side.alias("side"))), "d").drop("d")


def weekend(trace: DataFrame) -> DataFrame:
    """Weekends are queries, other days candidates."""
    return trace.withColumn("side", F.when(F.weekday("t") >= 5, "Q").otherwise("D"))


def limit_days(split: DataFrame, d: int, sides: list[str], seed: int = 3) -> DataFrame:
    """Keep d days, drawn by integer hash, of each named side; other sides stay whole."""
    days = split.select("side", day(F.col("t")).alias("d")).distinct()
    ranked = days.withColumn("r", F.row_number().over(Window.partitionBy("side").orderBy(int_hash(F.col("d"), seed), "d")))
    keep = ranked.where((F.col("r") <= d) | ~F.col("side").isin(sides)).select("side", "d")
    return split.withColumn("d", day(F.col("t"))).join(F.broadcast(keep), ["side", "d"], "left_semi").drop("d")


def two_sources(q: DataFrame, d: DataFrame) -> DataFrame:
    """Sides from two tables instead of a split."""
    return q.withColumn("side", F.lit("Q")).unionByName(d.withColumn("side", F.lit("D")), allowMissingColumns=True)
