"""Shared helpers of the training-data operators: tables, shared work folder, vectorised word hashing."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: ASCII white space that separates words; every other byte belongs to a word.
WHITE_SPACE = b" \t\n\x0b\x0c\r"
_SPACE_TABLE = np.zeros(256, dtype=bool)
_SPACE_TABLE[list(WHITE_SPACE)] = True

_BASE = 0x9E3779B97F4A7C15 | 1
_MASK = (1 << 64) - 1
_BASE_INVERSE = pow(_BASE, -1, 1 << 64)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``; a temporary one only where that is unset (tests)."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        folder = held.get() if held.isDefined() else tempfile.mkdtemp(prefix="tracelink-")
    if not spark.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` once as Parquet into the shared folder and read it back: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    # shuffle files of the written plan go when the driver's JVM collects it; with a large heap that may take hours
    gc.collect()
    spark.sparkContext._jvm.System.gc()
    return spark.read.schema(df.schema).parquet(path)


def shuffle_width(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions", "200")))


def give_back() -> None:
    """Return memory that a Python worker no longer needs to the system: workers are used again by later stages and would go on holding it."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


#: Bytes of rows that go to a Python worker at once.
BATCH_BYTES = 4 << 20


def bounded_batches(spark: SparkSession) -> None:
    """From now on the session's Arrow batches hold about BATCH_BYTES (one row at least), not 10,000 rows however long.

    Buffers of many MB are allocated beside the executor's heap, and what they leave there is not given back to the system.
    """
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    held = int(spark._jsparkSession.sessionState().conf().arrowMaxBytesPerBatch())
    if not 0 < held <= BATCH_BYTES:
        spark.conf.set(name, BATCH_BYTES)


def unused(df: DataFrame, *names: str) -> tuple[str, ...]:
    """Helper column names that no column of ``df`` has: underscores are added until they differ."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return tuple(out)


def drawn(rows: DataFrame, by: str, key: str, bound: int, seed: int) -> DataFrame:
    """At most ``bound`` rows ``key, by, rank``: distinct keys drawn by hash, dealt in turn to the values of ``by`` (not null).

    The rarest value gets as many keys as the most frequent one, as far as it has them; of more than ``bound`` values the most frequent
    stay. A key that comes many times counts once. Only hashes below a bound that follows from approximate counts are sorted, so the
    sorted rows are a small multiple of ``bound`` at any size.
    """
    rows = rows.where(F.col(by).isNotNull()).select(F.col(key).alias(key), F.col(by).alias(by), F.xxhash64(key, by, F.lit(seed)).alias("__h"))
    classes = rows.groupBy(F.col(by).alias("__by")).agg(F.approx_count_distinct("__h").alias("__n"))
    classes = classes.orderBy(F.desc("__n"), "__by").limit(bound)
    near = rows.join(F.broadcast(classes), F.col(by) == F.col("__by"))  # at most ``bound`` classes
    unit = F.col("__h").bitwiseAND(F.lit((1 << 52) - 1)).cast("double") / F.lit(float(1 << 52))
    near = near.where(unit * F.col("__n") < F.lit(2.0 * bound + 100)).select(key, by, "__h").distinct()
    ranked = near.withColumn("rank", F.row_number().over(Window.partitionBy(by).orderBy("__h", key))).where(F.col("rank") <= bound)
    return ranked.orderBy("rank", "__h", by).limit(bound).select(key, by, "rank")


def held_out(doc_id: Column) -> Column:
    """Fold rule of the learned operators: remainder 2 of crc32(doc_id as text) by 4."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def in_chunks(rows: Sequence, sizes: Sequence[int], limit: int) -> Iterator[slice]:
    """Slices of consecutive rows whose sizes add up to about ``limit`` (one row at least)."""
    start, total = 0, 0
    for i, size in enumerate(sizes):
        if i > start and total + size > limit:
            yield slice(start, i)
            start, total = i, 0
        total += size
    if start < len(rows):
        yield slice(start, len(rows))


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads 64-bit integers (public splitmix64 constants)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_STEP = 4096


def _power_table(base: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers 0..4095 of a base modulo 2**64, and powers of its 4096th power."""
    low, high = np.empty(_STEP, dtype=np.uint64), np.empty(1 << 16, dtype=np.uint64)
    for out, b in ((low, base), (high, pow(base, _STEP, 1 << 64))):
        out[0], filled = 1, 1
        while filled < len(out):
            out[filled : 2 * filled] = out[:filled] * np.uint64(pow(b, filled, 1 << 64))
            filled *= 2
    return low, high


_LOW, _HIGH = _power_table(_BASE)
_LOW_INVERSE, _HIGH_INVERSE = _power_table(_BASE_INVERSE)


class Words:
    """Words of several texts, found and hashed in bulk.

    ``start``/``end`` are byte places in ``raw``; words of text ``d`` are ``first[d]:first[d + 1]``; ``hash`` is a 64-bit word hash.
    """

    def __init__(self, texts: Sequence[bytes], lower: bool = False, hashes: bool = True):
        lengths = np.fromiter((len(t) for t in texts), dtype=np.int64, count=len(texts))
        self._find((b" ".join(texts) + b" ").lower() if lower else b" ".join(texts) + b" ", lengths, hashes)

    @classmethod
    def of_joined(cls, raw: bytes, lengths: np.ndarray) -> Words:
        """Words of texts that were joined by one blank each, given their byte lengths."""
        words = cls.__new__(cls)
        words._find(raw + b" ", lengths, True)
        return words

    def _find(self, raw: bytes, lengths: np.ndarray, hashes: bool) -> None:
        self.raw = raw
        buf = np.frombuffer(self.raw, dtype=np.uint8)
        space = _SPACE_TABLE[buf]
        before = np.empty_like(space)
        before[0] = True
        before[1:] = space[:-1]
        self.start = np.flatnonzero(before & ~space)
        self.end = np.flatnonzero(space & ~before)
        self.first = np.searchsorted(self.start, np.concatenate([[0], np.cumsum(lengths + 1)]))
        if hashes:
            blocks = -(-len(buf) // _STEP)
            powers = (_HIGH[:blocks, None] * _LOW[None, :]).ravel()[: len(buf)]
            powers *= buf
            run = np.zeros(len(buf) + 1, dtype=np.uint64)
            np.cumsum(powers, out=run[1:])
            back = _HIGH_INVERSE[self.start // _STEP] * _LOW_INVERSE[self.start % _STEP]
            self.hash = mix64((run[self.end] - run[self.start]) * back + (self.end - self.start).astype(np.uint64))

    def __len__(self) -> int:
        return len(self.start)


def run_hash(h: np.ndarray, width: int, seed: int) -> np.ndarray:
    """Hash of every run of ``width`` consecutive word hashes (length ``len(h) - width + 1``)."""
    n = len(h) - width + 1
    if n <= 0:
        return np.zeros(0, dtype=np.uint64)
    out = np.full(n, seed, dtype=np.uint64)
    for i in range(width):
        out += h[i : i + n] * np.uint64((pow(_BASE, 3 * i + 1, 1 << 64) * (2 * seed + 1)) & _MASK)
    return mix64(out)
