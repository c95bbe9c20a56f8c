"""Traces: relations (oid, t, pid, x, y) of time-ordered located points, one row a point.

The given tables carry no coordinates, so places are derived by integer arithmetic that every engine evaluates alike.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

TRACE = T.StructType([
    T.StructField("oid", T.LongType()), T.StructField("t", T.TimestampNTZType()), T.StructField("pid", T.LongType()),
    T.StructField("x", T.DoubleType()), T.StructField("y", T.DoubleType()),
])


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_traces(spark: SparkSession, path: str, fmt: str = "parquet", **options: str) -> DataFrame:
    """User traces of (oid, t, pid, x, y) from Parquet, CSV or JSON, with the fixed schema; nothing is inferred."""
    return spark.read.format(fmt).schema(TRACE).options(**options).load(path)


def _k() -> Column:
    return F.get_json_object("props", "$.k").cast("int")


def habit(events: DataFrame) -> DataFrame:
    """Planted habits: four of ten points lie on few anchors of the object, the others are scattered over a 100 x 100 lattice."""
    h = (F.col("event_id") * 7919 + 104729) % 10
    j = F.expr("event_id div 7") % 8
    u, e = F.col("user_id"), F.col("event_id")
    et = F.expr("case event_type when 'view' then 0 when 'click' then 1 when 'purchase' then 2 when 'signup' then 3 else 4 end")
    gx = F.when(h < 4, ((37 * u) % 97 + (5 * j + u) % 7) % 100).otherwise((13 * _k() + 17 * e) % 100)
    gy = F.when(h < 4, ((91 * u) % 89 + (3 * j + 3 * u) % 7) % 100).otherwise((23 * et + 29 * e + _k()) % 100)
    rows = events.select(u.alias("oid"), F.col("ts").alias("t"), e.alias("event_id"), gx.cast("long").alias("gx"), gy.cast("long").alias("gy"))
    return rows.select("oid", "t", (F.col("gx") * 1000 + F.col("gy")).alias("pid"), F.col("gx").cast("double").alias("x"), F.col("gy").cast("double").alias("y"))


def raw(events: DataFrame) -> DataFrame:
    """Points as the table has them: (k, floor(value / 25)); no habit is planted, so linking is chance."""
    gy = F.floor(F.coalesce("value", F.lit(0.0)) / 25).cast("long")
    rows = events.select(F.col("user_id").alias("oid"), F.col("ts").alias("t"), _k().cast("long").alias("gx"), gy.alias("gy"))
    return rows.select("oid", "t", (F.col("gx") * 100000 + F.col("gy")).alias("pid"), F.col("gx").cast("double").alias("x"), F.col("gy").cast("double").alias("y"))


def suppliers(lineitem: DataFrame, part: DataFrame) -> DataFrame:
    """Suppliers visit parts: long traces over a large vocabulary."""
    rows = lineitem.select(F.col("l_suppkey").alias("oid"), F.col("l_shipdate").alias("t"), F.col("l_partkey").alias("pid"))
    places = part.select(F.col("p_partkey").alias("pid"), F.col("p_size").cast("double").alias("x"), F.col("p_retailprice").alias("y"))
    return rows.join(places, "pid").select("oid", "t", "pid", "x", "y")


def customers(orders: DataFrame, lineitem: DataFrame, place: str = "l_suppkey", below: int | None = None) -> DataFrame:
    """Customers visit suppliers (dense similarities) or parts (sparse); the side is the parity of the order key."""
    held = orders.select("o_orderkey", F.col("o_custkey").alias("oid"), F.col("o_orderdate").alias("t"))
    if below is not None:
        held = held.where(F.col("oid") < below)
    rows = held.join(lineitem.select("l_orderkey", F.col(place).alias("pid")), F.col("o_orderkey") == F.col("l_orderkey"))
    side = F.when(F.col("o_orderkey") % 2 == 1, "Q").otherwise("D")
    return rows.select(side.alias("side"), "oid", "t", "pid", (F.col("pid") % 40).cast("double").alias("x"), F.expr("pid div 40").cast("double").alias("y"))


def documents(docs: DataFrame) -> DataFrame:
    """Documents as traces of words; every other word goes to the other side."""
    words = F.filter(F.split(F.coalesce("text", F.lit("")), r"[\x20\x09-\x0D]+"), lambda w: w != "")
    rows = docs.select(F.col("doc_id").alias("oid"), F.posexplode(words).alias("seq", "pid"))
    return rows.select(F.when(F.col("seq") % 2 == 0, "Q").otherwise("D").alias("side"), "oid", "seq", "pid")


def conversations(conversations: DataFrame) -> DataFrame:
    """Conversations: words of the user on one side, of everyone else on the other."""
    words = F.filter(F.split(F.lower(F.coalesce("text", F.lit(""))), r"[\x20\x09-\x0D]+"), lambda w: w != "")
    side = F.when(F.col("role") == "user", "Q").otherwise("D")
    return conversations.select(side.alias("side"), F.col("conv_id").alias("oid"), F.explode(words).alias("pid"))


def pages(pages: DataFrame) -> DataFrame:
    """Hosts as objects and path words as places."""
    host = F.regexp_extract("url", r"^[a-z]+://([^/?#]+)", 1)
    words = F.filter(F.split(F.regexp_extract("url", r"^[a-z]+://[^/?#]+/([^?#]*)", 1), "/"), lambda w: w != "")
    return pages.select(F.when(F.col("page_id") % 2 == 1, "Q").otherwise("D").alias("side"), host.alias("oid"), F.explode(words).alias("pid"))


def habit_of_size(spark: SparkSession, n_objects: int, points: int) -> DataFrame:
    """Generated events of any size through ``habit``, for scale tests; made on the executors, nothing is read."""
    ids = spark.range(n_objects * points)
    made = ids.select(
        F.col("id").alias("event_id"), F.timestamp_seconds(F.lit(1704067200) + F.pmod(F.col("id") * 7907, F.lit(2592000))).cast("timestamp_ntz").alias("ts"),
        (F.col("id") % n_objects).alias("user_id"), F.lit("view").alias("event_type"), F.format_string('{"k": %d}', F.pmod(F.col("id") * 31, F.lit(100))).alias("props"),
    )
    return habit(made)


def locations(trace: DataFrame) -> DataFrame:
    return trace.groupBy("pid").agg(F.min("x").alias("x"), F.min("y").alias("y"))


def write_signature(sig: DataFrame, path: str, by: str = "fid") -> None:
    """Signatures as Parquet, one folder a side, clustered by feature (for link joins) or object (for re-ranking)."""
    sig.repartition("side", by).sortWithinPartitions("side", by).write.mode("overwrite").partitionBy("side").parquet(path)
