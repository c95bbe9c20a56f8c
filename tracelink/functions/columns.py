"""Column expressions (no Python on executors) and their registration for SQL."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def sparse_dot(a: Column, b: Column) -> Column:
    """Dot product of two arrays of (fid, w)."""
    index = F.map_from_entries(b)
    return F.aggregate(a, F.lit(0.0), lambda s, e: s + e["w"] * F.coalesce(index[e["fid"]], F.lit(0.0)))


def sparse_norm(a: Column) -> Column:
    return F.sqrt(F.aggregate(a, F.lit(0.0), lambda s, e: s + e["w"] * e["w"]))


def sparse_max(a: Column, b: Column) -> Column:
    """Feature-wise maximum of two arrays of (fid, w), as a map."""
    return F.map_zip_with(F.map_from_entries(a), F.map_from_entries(b), lambda k, x, y: F.greatest(x, y))


def dense_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, v: s + v)


def _sum(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, v: s + v)


def emd_circular(a: Column, b: Column, hours: int) -> Column:
    """Cheapest circular transport between two histograms of unit sum, scaled so that half a day is 1 (closed form).

    Running differences less their median, summed in absolute value, times the bin width over twelve hours.
    """
    bins = 24 // hours
    run = F.transform(F.sequence(F.lit(1), F.lit(bins)), lambda i: _sum(F.slice(F.zip_with(a, b, lambda x, y: x - y), 1, i)))
    ordered = F.array_sort(run)
    middle = (F.element_at(ordered, (bins + 1) // 2) + F.element_at(ordered, bins // 2 + 1)) / 2
    return _sum(F.transform(run, lambda v: F.abs(v - middle))) * F.lit(hours / 12.0)


def histogram_distance(a: Column, b: Column, how: str, p: int = 2, smooth: float = 1e-6) -> Column:
    """Other comparisons of histograms: correlation, intersection, chi2, bhattacharyya, kl (smoothed), lp."""
    pairs = F.zip_with(a, b, lambda x, y: F.struct(x.alias("x"), y.alias("y")))
    over = lambda f: F.aggregate(pairs, F.lit(0.0), lambda s, e: s + f(e["x"], e["y"]))
    if how == "intersection":
        return over(lambda x, y: F.least(x, y))
    if how == "chi2":
        return over(lambda x, y: F.when(x + y > 0, (x - y) * (x - y) / (x + y)).otherwise(0.0))
    if how == "bhattacharyya":
        return F.sqrt(F.greatest(F.lit(0.0), 1 - over(lambda x, y: F.sqrt(x * y))))
    if how == "kl":
        return over(lambda x, y: (x + smooth) * F.log((x + smooth) / (y + smooth)))
    if how == "lp":
        return F.pow(over(lambda x, y: F.pow(F.abs(x - y), F.lit(float(p)))), F.lit(1.0 / p))
    n = F.size(a)
    mx, my = _sum(a) / n, _sum(b) / n
    cov, vx, vy = over(lambda x, y: (x - mx) * (y - my)), over(lambda x, y: (x - mx) * (x - mx)), over(lambda x, y: (y - my) * (y - my))
    return F.when((vx > 0) & (vy > 0), cov / F.sqrt(vx * vy)).otherwise(F.lit(0.0))


def boxes_overlap(a: str, b: str) -> Column:
    """Whether boxes with columns ``<prefix>x1..y2`` share a point (touching counts)."""
    c = F.col
    return (c(f"{a}x1") <= c(f"{b}x2")) & (c(f"{b}x1") <= c(f"{a}x2")) & (c(f"{a}y1") <= c(f"{b}y2")) & (c(f"{b}y1") <= c(f"{a}y2"))


def box_area(a: str) -> Column:
    return (F.col(f"{a}x2") - F.col(f"{a}x1")) * (F.col(f"{a}y2") - F.col(f"{a}y1"))


def union_area(a: str, b: str) -> Column:
    c = F.col
    return (F.greatest(c(f"{a}x2"), c(f"{b}x2")) - F.least(c(f"{a}x1"), c(f"{b}x1"))) * (F.greatest(c(f"{a}y2"), c(f"{b}y2")) - F.least(c(f"{a}y1"), c(f"{b}y1")))


def overlap_area(a: str, b: str) -> Column:
    c = F.col
    w = F.least(c(f"{a}x2"), c(f"{b}x2")) - F.greatest(c(f"{a}x1"), c(f"{b}x1"))
    h = F.least(c(f"{a}y2"), c(f"{b}y2")) - F.greatest(c(f"{a}y1"), c(f"{b}y1"))
    return F.greatest(F.lit(0.0), w) * F.greatest(F.lit(0.0), h)


def morton(x: Column, y: Column, bits: int = 16) -> Column:
    """Interleaved bits of two cell numbers: neighbours in space get near keys."""
    out = F.lit(0).cast("long")
    for i in range(bits):
        out = out + F.shiftleft(F.shiftright(x.cast("long"), i).bitwiseAND(F.lit(1).cast("long")), 2 * i) + F.shiftleft(F.shiftright(y.cast("long"), i).bitwiseAND(F.lit(1).cast("long")), 2 * i + 1)
    return out


def haversine(lon1: Column, lat1: Column, lon2: Column, lat2: Column) -> Column:
    """Metres between two places on the sphere."""
    a, b = F.radians(lat1), F.radians(lat2)
    s = F.sin((b - a) / 2) ** 2 + F.cos(a) * F.cos(b) * F.sin(F.radians(lon2 - lon1) / 2) ** 2
    return F.lit(2 * 6371008.8) * F.asin(F.sqrt(s))


def register_sql(spark: SparkSession) -> None:
    """SQL functions of a session: sparse_dot, box_overlaps, box_area."""
    sparse = "array<struct<fid: bigint, w: double>>"
    box = "struct<x1: double, y1: double, x2: double, y2: double>"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sparse_dot(a {sparse}, b {sparse}) RETURNS DOUBLE RETURN aggregate(a, 0.0D, (s, e) -> s + e.w * coalesce(map_from_entries(b)[e.fid], 0.0D))")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION box_overlaps(a {box}, b {box}) RETURNS BOOLEAN RETURN a.x1 <= b.x2 AND b.x1 <= a.x2 AND a.y1 <= b.y2 AND b.y1 <= a.y2")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION box_area(a {box}) RETURNS DOUBLE RETURN (a.x2 - a.x1) * (a.y2 - a.y1)")
