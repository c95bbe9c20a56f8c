"""Traces as streams: running counts, windows, sessions, de-duplication, arrivals, and linking of new objects.

The files carry timestamps without zone; watermarks need zoned ones, so sources cast to TIMESTAMP (sessions run in UTC).
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..operators import blocks
from ..operators import linking as L
from ..operators import prepare as P
from ..operators import sigtree
from ..operators import weights as W
from ..plans import sqltext as Q
from ..plans.workloads import KNN3, SHOWN, add, habit, shown, sig_of
from ..session import materialise, passing, shared_folder
from ..sources import traces as S

EVENTS = T.StructType([T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampNTZType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())])


def event_stream(spark: SparkSession, sf_dir: str, files: int = 1) -> DataFrame:
    """The events files as a stream with zoned event time."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files).parquet(f"{sf_dir}/events*.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Run a stream over what is there and return the result table, written to the shared folder for append, or as the last state."""
    spark = stream.sparkSession
    base = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.option("checkpointLocation", f"{base}/checkpoint").outputMode(mode).trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", f"{base}/out").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{base}/out")

    def keep(df: DataFrame, epoch: int) -> None:
        df.write.mode("overwrite").parquet(f"{base}/out")

    writer.foreachBatch(keep).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/out")


def counts(events: DataFrame, delay: str = "2 days") -> DataFrame:
    """Points of each object a day."""
    return events.withWatermark("ts", delay).groupBy(F.window("ts", "1 day").alias("w"), F.col("user_id").alias("oid")).agg(F.count(F.lit(1)).alias("points")).select(F.col("w.start").cast("date").cast("string").alias("day"), "oid", "points")


def sliding(events: DataFrame, length: str = "7 days", step: str = "1 day") -> DataFrame:
    """Points of each object in sliding windows: how much data a week holds."""
    return events.groupBy(F.window("ts", length, step).alias("w"), F.col("user_id").alias("oid")).agg(F.count(F.lit(1)).alias("points")).select(F.col("w.start").cast("date").cast("string").alias("first_day"), "oid", "points")


def sessions(events: DataFrame, gap: str = "12 hours") -> DataFrame:
    """Trajectories: runs of an object's points without a gap."""
    grouped = events.withWatermark("ts", "2 days").groupBy(F.session_window("ts", gap).alias("w"), F.col("user_id").alias("oid"))
    return grouped.agg(F.count(F.lit(1)).alias("points"), F.min("ts").alias("first")).select("oid", "points", "first")


def arrivals(events: DataFrame, least: int) -> DataFrame:
    """Objects at the point that completes ``least`` points: a running count kept for each object."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        seen = state.get[0] if state.exists else 0
        n = seen + sum(len(b) for b in batches)
        state.update((n,))
        if seen < least <= n:
            yield pd.DataFrame({"oid": [key[0]], "ready": [True]})

    return events.groupBy("user_id").applyInPandasWithState(step, "oid long, ready boolean", "n long", "append", "NoTimeout")


#: Folders over which the points' counts of a stream are dealt by object, so that a batch reads the folders of its own objects only.
BUCKETS = 32


class ObjectStore:
    """Counts (oid, fid, n) of all points a stream has brought, as one Parquet folder a batch and bucket of objects under ``path``.

    A batch that is run again overwrites its own folder, so it counts once. What a batch needs of earlier ones is read for its objects alone.
    """

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path

    def merged(self, delta: DataFrame, epoch: int) -> DataFrame:
        """Write the counts of this batch; the counts so far of the objects it touches."""
        bucket = F.pmod(F.xxhash64("oid"), F.lit(BUCKETS)).cast("int")
        delta.withColumn("bucket", bucket).repartition("bucket").write.mode("overwrite").partitionBy("bucket").parquet(f"{self.path}/batch={epoch}")
        schema = T.StructType([*delta.schema.fields, T.StructField("batch", T.LongType()), T.StructField("bucket", T.IntegerType())])
        every = self.spark.read.schema(schema).option("basePath", self.path).parquet(self.path).where(F.col("batch") <= epoch)
        touched = every.where(F.col("batch") == epoch).select("oid").distinct()
        buckets = [r["b"] for r in touched.select(F.pmod(F.xxhash64("oid"), F.lit(BUCKETS)).cast("int").alias("b")).distinct().collect()]  # BUCKETS rows at most
        return every.where(F.col("bucket").isin(buckets)).join(touched, "oid", "left_semi").groupBy("oid", "fid").agg(F.sum("n").alias("n"))


def latest(df: DataFrame, key: str) -> DataFrame:
    """Rows of each key's last batch: what is valid now of results that were written batch by batch."""
    last = df.groupBy(F.col(key).alias("l_key")).agg(F.max("batch").alias("l_batch"))
    return df.join(last, (F.col(key) == F.col("l_key")) & (F.col("batch") == F.col("l_batch"))).drop("l_key", "l_batch", "batch")


def _run(events: DataFrame, path: str, each) -> None:
    events.writeStream.option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).foreachBatch(each).start().awaitTermination()


def _signed(events: DataFrame, rarity: DataFrame, m: int | None, path: str, then) -> None:
    """Every batch: ``then(signatures, epoch)`` gets ``oid, fid, w`` of the objects it touches, by all points each has so far."""
    store = ObjectStore(events.sparkSession, f"{path}/counts")

    def each(df: DataFrame, epoch: int) -> None:
        trace = S.habit(df.withColumn("ts", F.col("ts").cast("timestamp_ntz"))).withColumn("side", F.lit("Q"))
        counted = store.merged(W.counts(trace).select("oid", "fid", "n"), epoch).withColumn("side", F.lit("Q"))
        weighed = W.tf(counted).join(rarity.where("idf > 0"), "fid").select("side", "oid", "fid", (F.col("tf") * F.col("idf")).alias("w"))
        then(W.cut(W.l2(weighed), m).select("oid", "fid", "w"), epoch)

    _run(events, path, each)


def signature_updates(events: DataFrame, rarity: DataFrame, m: int | None, path: str) -> DataFrame:
    """``oid, fid, w``: signatures of a stream's objects, refreshed in every batch for the objects it touches.

    ``rarity(fid, idf)`` is frozen: it changes with a new generation of the store, not with each point. A replay in any number of batches
    ends with the same signatures.
    """
    _signed(events, rarity, m, path, lambda sig, epoch: sig.write.mode("overwrite").parquet(f"{path}/signatures/batch={epoch}"))
    return latest(events.sparkSession.read.parquet(f"{path}/signatures"), "oid")


def link_arrivals(events: DataFrame, stored: DataFrame, k: int, path: str, m: int | None = None) -> DataFrame:
    """``qid, oid, sim, rnk``: neighbours of a stream's objects among stored candidates, by all points each object has so far.

    Candidates' signatures (also in blocks) and the rarity of places are computed once, from the store, and written. Every batch links the
    objects it touches anew; of an object only its last neighbours are returned, once, however its points were cut into batches. What a
    batch writes on its way to its neighbours goes when it ends, so the disk does not grow with the number of batches but by these.
    """
    counted = W.counts(stored.withColumn("side", F.lit("D")))
    rarity = materialise(W.idf(counted, "candidate"), "rarity")
    d = materialise(W.cut(W.weigh(counted, "tfidf", "candidate"), m).select("oid", "fid", F.col("w").alias("wd")), "candidates")
    made = blocks.ready(d)

    def link(sig: DataFrame, epoch: int) -> None:
        with passing(events.sparkSession):
            L.inverted(sig.select(F.col("oid").alias("qid"), "fid", F.col("w").alias("wq")), d, k, made).write.mode("overwrite").parquet(f"{path}/linked/batch={epoch}")

    _signed(events, rarity, m, path, link)
    return latest(events.sparkSession.read.parquet(f"{path}/linked"), "qid")


def tree_inserts(signatures: DataFrame, tree: sigtree.Tree, place: DataFrame, path: str, most_growth: float = 2.0, criterion: str = "common") -> sigtree.Tree:
    """The tree after a stream of new objects' signatures ``(oid, fid, wd)``, each object whole in one batch.

    Every batch is inserted; a tree whose nodes have grown too far is bulk loaded anew. Objects that the tree has already are passed over,
    so a batch that is run again changes nothing.
    """
    held = [tree]

    def each(df: DataFrame, epoch: int) -> None:
        fresh = materialise(df.join(held[0].levels[0].nodes.select(F.col("nid").alias("oid")), "oid", "left_anti"), "arrivals")
        if not fresh.isEmpty():
            held[0] = sigtree.maintain(sigtree.insert(held[0], fresh, place, criterion), place, most_growth)

    _run(signatures, path, each)
    return held[0]


add("st_counts", lambda s, d: drained(counts(event_stream(s, d))), "SELECT ts::DATE::VARCHAR AS day, user_id AS oid, count(*) AS points FROM events GROUP BY ALL")
add("st_sliding", lambda s, d: drained(sliding(event_stream(s, d))), "SELECT (ts::DATE - o::INT)::DATE::VARCHAR AS first_day, user_id AS oid, count(*) AS points FROM events, range(0, 7) t(o) GROUP BY ALL")
add("st_sessions", lambda s, d: drained(sessions(event_stream(s, d))).groupBy("oid").agg(F.count(F.lit(1)).alias("trips"), F.max("points").alias("longest")),
    """WITH g AS (SELECT user_id AS oid, ts, CASE WHEN ts - lag(ts) OVER w <= INTERVAL 12 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
    n AS (SELECT oid, sum(new) OVER (PARTITION BY oid ORDER BY ts) AS trip FROM g), c AS (SELECT oid, trip, count(*) AS points FROM n GROUP BY ALL) SELECT oid, count(*) AS trips, max(points) AS longest FROM c GROUP BY oid""")  # fmt: skip
add("st_dedup", lambda s, d: drained(event_stream(s, d).withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["user_id", "event_id"]).select("event_id", "user_id"), "append"), "SELECT event_id, user_id FROM events")
add("st_arrivals", lambda s, d: drained(arrivals(event_stream(s, d), 68), "append").select("oid"), "SELECT user_id AS oid FROM events GROUP BY user_id HAVING count(*) >= 68")


def _halves(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """Stream of the points of the queries' days, and the stored points of the others."""
    stored = habit(s, d).where(P.day(F.col("t")) % 2 == 1)
    return event_stream(s, d).where(F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")) % 2 == 0), stored


def _own_path(s: SparkSession, name: str) -> str:
    return f"{shared_folder(s)}/{name}-{uuid.uuid4().hex}"


def _updated(s: SparkSession, d: str) -> DataFrame:
    fresh, stored = _halves(s, d)
    rarity = materialise(W.idf(W.counts(stored.withColumn("side", F.lit("D"))), "candidate"), "rarity")
    return signature_updates(fresh, rarity, 3, _own_path(s, "updated")).select("oid", "fid", F.round("w", 6).alias("w"))


def _inserted(s: SparkSession, d: str) -> DataFrame:
    """A tree of half of the candidates takes in the others from a stream of three files, and is searched."""
    _, q, c, place = sig_of(s, d)
    part = P.int_hash(F.col("oid"), 9) % 6
    path = _own_path(s, "inserted")
    for i in range(3):
        c.where(part == i).select("oid", "fid", "wd").repartition("oid").write.parquet(f"{path}/in/file{i}")
    stream = s.readStream.schema("oid long, fid long, wd double").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(f"{path}/in")
    tree = tree_inserts(stream, sigtree.build(c.where(part >= 3), place, 16), place, path)
    return shown(sigtree.knn_join(q, tree, 5, place))


add("st_link", lambda s, d: link_arrivals(*_halves(s, d), 1, _own_path(s, "linked")).select("qid", "oid", F.round("sim", 6).alias("sim")), f"WITH {Q.BASE}, {Q.sig('split', 'sg', scope='candidate')}, {Q.knn('sg', 1)} SELECT qid, oid, round(sim, 6) AS sim FROM knn")
add("st_signature_updates", _updated, f"WITH {Q.BASE}, {Q.sig('split', 'sg', 3, scope='candidate')} SELECT oid, fid, round(w, 6) AS w FROM sg WHERE side = 'Q'")
add("st_tree_inserts", _inserted, KNN3 + SHOWN + "knn")
