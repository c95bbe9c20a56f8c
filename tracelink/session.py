"""Session helpers: shared work folder, materialised relations, exact global ranks."""

from __future__ import annotations

import gc
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from contextvars import ContextVar

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``, the folder that all executors share; a temporary one only where it is unset."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    return (folder or tempfile.mkdtemp(prefix="tracelink-")).rstrip("/")


#: Where the paths of relations are kept that pass away with what they were made for.
_PASSING: ContextVar[list[str] | None] = ContextVar("passing", default=None)


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write once as Parquet into the shared folder and read back: cuts the lineage of loops and survives lost executors."""
    path = f"{shared_folder(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    if (paths := _PASSING.get()) is not None:
        paths.append(path)
    df.write.parquet(path)
    # shuffle files of the written plan go when the driver's JVM collects it; with a large heap that may take hours
    gc.collect()
    df.sparkSession.sparkContext._jvm.System.gc()
    return df.sparkSession.read.schema(df.schema).parquet(path)


@contextmanager
def passing(spark: SparkSession) -> Iterator[None]:
    """Relations that are materialised within are deleted at its end, so nothing that is still to be read may depend on them."""
    paths: list[str] = []
    token = _PASSING.set(paths)
    try:
        yield
    finally:
        _PASSING.reset(token)
        for path in paths:
            at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def shuffle_width(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))


def global_rank(df: DataFrame, by: str, ties: list[str], name: str) -> DataFrame:
    """Add ``name``: place from 0 in the order (by, *ties) over all rows, without a single-task window.

    Rows are dealt to buckets between quantiles of ``by``; places count on from the rows of the buckets before. The driver holds one row a
    bucket; a value that fills a bucket alone is the limit of how far the work can be spread.
    """
    n = 2 * shuffle_width(df.sparkSession)
    cuts = df.agg(F.percentile_approx(by, [i / n for i in range(1, n)], 20 * n)).first()[0] if n > 1 else None
    cuts = sorted(set(cuts or []))
    # at most one literal a bucket
    bucket: Column = F.size(F.filter(F.array(*[F.lit(c) for c in cuts]), lambda c: c <= F.col(by))) if cuts else F.lit(0)
    held = df.withColumn("__b", bucket)
    sizes = sorted((r["__b"], r["n"]) for r in held.groupBy("__b").agg(F.count(F.lit(1)).alias("n")).collect())
    before, starts = 0, []
    for b, size in sizes:
        starts += [F.lit(b), F.lit(before)]
        before += size
    offset = F.create_map(*starts)[F.col("__b")] if starts else F.lit(0)
    inside = F.row_number().over(Window.partitionBy("__b").orderBy(by, *ties))
    return held.withColumn(name, (inside - 1 + offset).cast("long")).drop("__b")
