"""Size-balanced sharding by sampled splitters.

A size-weighted sample of keys gives quantile boundaries; rows are dealt to the ranges between them; overfull ranges are subdivided by
splitters drawn inside them. Exact totals of the ranges then give every row its place in the global key order, hence its shard and slot.
"""

from __future__ import annotations

import itertools

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise, shuffle_width, table

#: Sampled keys for each range, and the largest number of ranges: together the bound of what reaches the driver.
SAMPLE_PER_RANGE, MOST_RANGES = 24, 16_384
#: A range of over this many times the mean size is subdivided, in at most so many rounds.
OVERFULL, ROUNDS = 3.0, 4
#: Equal keys stay in one shard unless together they are larger than this part of a shard.
WHOLE_GROUP = 1 / 64


#: Order of rows: text hash, id, number of the row in the written table (which tells repeated rows apart).
KEYS = ["k_hash", "k_id", "k_row"]
Splits = list[tuple[int, int, int]]


def _places(splits: np.ndarray, columns: list[np.ndarray]) -> np.ndarray:
    """Number of splitters (sorted rows of key columns) at or below each key, column by column."""
    low, high = np.searchsorted(splits[:, 0], columns[0], "left"), np.searchsorted(splits[:, 0], columns[0], "right")
    if len(columns) == 1:
        return high
    tied = np.flatnonzero(high > low)
    for value in np.unique(columns[0][tied]):
        rows = tied[columns[0][tied] == value]
        a, b = low[rows[0]], high[rows[0]]
        low[rows] = a + _places(splits[a:b, 1:], [c[rows] for c in columns[1:]])
    return low


def _range_of(splits: Splits):
    """Vectorised search of the range of a key; at most twice MOST_RANGES splitters travel with the function."""
    held = np.array(splits, dtype=np.int64).reshape(-1, len(KEYS))

    def find(h: pd.Series, i: pd.Series, r: pd.Series) -> pd.Series:
        return pd.Series(_places(held, [h.to_numpy(), i.to_numpy(), r.to_numpy()]).astype(np.int32))

    return F.pandas_udf(find, "int")(*KEYS)


def _draw(keyed: DataFrame, chance: Column, seed: int) -> pd.DataFrame:
    """Hash-deterministic sample: a row is drawn with probability ``chance``; returned with the weight it stands for."""
    unit = (F.xxhash64(*KEYS, F.lit(seed)).bitwiseAND(F.lit((1 << 52) - 1))).cast("double") / F.lit(float(1 << 52))
    return keyed.select(*KEYS, "size", chance.alias("p"), unit.alias("u")).where("u < p").select(*KEYS, (F.col("size") / F.least("p", F.lit(1.0))).alias("w")).toPandas()


def _quantiles(sample: pd.DataFrame, parts: int) -> Splits:
    if not len(sample):
        return []
    s = sample.sort_values(KEYS, kind="stable")
    mass = s["w"].cumsum().to_numpy()
    at = np.searchsorted(mass, mass[-1] * np.arange(1, parts) / parts)
    rows = s.iloc[np.minimum(at, len(s) - 1)]
    return sorted(set(zip(*[rows[k].tolist() for k in KEYS], strict=True)))


def _snapped(keyed: DataFrame, splits: Splits, limit: float) -> tuple[Splits, list[int]]:
    """Splitters moved to the begin of their group of equal hashes where that is no larger than ``limit``; and the hashes of larger groups.

    The driver gets one row a splitter. Larger groups are fewer than all bytes over ``limit``.
    """
    if not splits:
        return [], []
    spark = keyed.sparkSession
    edges = spark.createDataFrame([(h,) for h in sorted({s[0] for s in splits})], "e_hash long")
    groups = keyed.join(F.broadcast(edges), F.col("k_hash") == F.col("e_hash")).groupBy("k_hash").agg(F.sum("size").alias("bytes")).collect()
    large = {r["k_hash"] for r in groups if r["bytes"] > limit}
    least = -(1 << 63)
    return sorted({s if s[0] in large else (s[0], least, least) for s in splits}), sorted(large)


def shards(rows: DataFrame, n_shards: int = 16, rows_per_range: int = 250_000) -> DataFrame:
    """Deal rows ``(doc_id, size, key_hash, ...)`` to shards of nearly equal total ``size``; adds ``shard`` and ``slot``.

    Order is (key_hash, doc_id, row); slots count the rows of a shard in that order from 0, without gaps. Rows of equal ``key_hash`` stay in
    one shard unless they outweigh 1/64 of a shard. A null doc_id sorts first; rows equal in both keys keep an arbitrary but gapless
    order, and may be any share of all rows; an empty table gives no rows; columns of any other name pass through (own ``shard`` and
    ``slot`` are replaced). Sizes are at least 1.
    """
    spark = rows.sparkSession
    others = [c for c in rows.columns if c not in ("shard", "slot")]
    keyed = rows.select(F.struct(*[F.col(f"`{c}`") for c in others]).alias("row"), F.col("size").cast("long").alias("size"), F.col("key_hash").alias("k_hash"), F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63))).alias("k_id"))
    keyed = materialise(keyed.withColumn("k_row", F.monotonically_increasing_id()), "shard-keys")
    total = keyed.agg(F.count(F.lit(1)).alias("n"), F.sum("size").alias("bytes")).first()
    n, whole = total["n"], total["bytes"] or 0
    goal = max(whole, 1) / n_shards
    parts = int(min(MOST_RANGES, max(4 * shuffle_width(spark), 8 * n_shards, -(-n // rows_per_range)))) if n else 1
    splits = _quantiles(_draw(keyed, F.col("size") * F.lit(SAMPLE_PER_RANGE * parts / max(whole, 1)), 17), parts)
    mean = whole / parts

    def ranged_by(splits: Splits) -> tuple[DataFrame, pd.DataFrame]:
        out = keyed.withColumn("k_range", _range_of(splits))
        return out, out.groupBy("k_range").agg(F.count(F.lit(1)).alias("rows"), F.sum("size").alias("bytes")).toPandas().sort_values("k_range")

    for seed in range(ROUNDS):
        ranged, sums = ranged_by(splits)
        full = sums[(sums["bytes"] > OVERFULL * mean) & (sums["rows"] > 1)]
        if not len(full) or len(splits) >= 2 * MOST_RANGES:
            break
        chance = F.col("size") * F.lit(2 * SAMPLE_PER_RANGE / mean)
        inside = _draw(ranged.where(F.col("k_range").isin(full["k_range"].tolist())), chance, 1000 + seed)
        more = _quantiles(inside, int(min(MOST_RANGES, max(2, 2 * full["bytes"].sum() / mean))))
        if set(more) <= set(splits):
            break
        splits = sorted({*splits, *more})
    splits, large = _snapped(keyed, splits, goal * WHOLE_GROUP)
    ranged, sums = ranged_by(splits)
    sums["row_from"] = sums["rows"].cumsum() - sums["rows"]
    sums["byte_from"] = sums["bytes"].cumsum() - sums["bytes"]
    offsets = spark.createDataFrame([tuple(map(int, r)) for r in sums[["k_range", "row_from", "byte_from"]].itertuples(index=False)], "o_range int, row_from long, byte_from long")
    inside = Window.partitionBy("k_range").orderBy(*KEYS)
    run = inside.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    group = Window.partitionBy("k_range", "k_hash")
    placed = ranged.join(F.broadcast(offsets), F.col("k_range") == F.col("o_range"))  # one row a range
    placed = placed.withColumn("row_at", F.row_number().over(inside) - 1 + F.col("row_from")).withColumn("byte_at", F.sum("size").over(run) - F.col("size") + F.col("byte_from"))
    placed = placed.withColumn("g_from", F.min("byte_at").over(group)).withColumn("g_bytes", F.sum("size").over(group))
    together = (F.col("g_bytes") <= goal * WHOLE_GROUP) & ~F.col("k_hash").isin(large)
    middle = F.when(together, F.col("g_from") + F.col("g_bytes") / 2).otherwise(F.col("byte_at") + F.col("size") / 2)
    placed = placed.withColumn("shard", F.least(F.lit(n_shards - 1), F.floor(middle / F.lit(goal))).cast("int"))
    placed = materialise(placed.select("row", "shard", "row_at"), "shard-rows")
    first = placed.groupBy(F.col("shard").alias("f_shard")).agg(F.min("row_at").alias("first_row"))
    out = placed.join(F.broadcast(first), F.col("shard") == F.col("f_shard"))  # n_shards rows
    return out.select(*[F.col("row")[c].alias(c) for c in others], "shard", (F.col("row_at") - F.col("first_row")).alias("slot"))


def shard_documents(docs: DataFrame, path: str, n_shards: int = 16) -> None:
    """Write documents as ``shard=NN`` folders in slot order, using the assignment of ``shards``; repeated rows are all written."""
    held = materialise(docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.monotonically_increasing_id().alias("at")), "shard-docs")
    sized = document_sizes(held.select(F.col("row.doc_id").alias("doc_id"), F.col("row.text").alias("text"), "at"), ["at"])
    plan = shards(sized, n_shards).select(F.col("at").alias("p_at"), "shard", "slot")
    rows = held.join(plan, F.col("at") == F.col("p_at")).select(*[F.col("row")[c].alias(c) for c in docs.columns if c not in ("shard", "slot")], "shard", "slot")
    rows.repartition("shard", F.floor(F.col("slot") / 100_000)).sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)


def reference(sizes: list[tuple[int, int, int]], n_shards: int) -> dict[int, tuple[int, int]]:
    """Reference for tests: (key_hash, doc_id, size) of unique ids -> doc_id: shard and slot."""
    rows = sorted(sizes)
    goal = max(sum(r[2] for r in rows), 1) / n_shards
    out: dict[int, tuple[int, int]] = {}
    slots = [0] * n_shards
    at = 0
    for _, same in itertools.groupby(rows, key=lambda r: r[0]):
        group = list(same)
        whole, start = sum(r[2] for r in group), at
        for _, i, size in group:
            middle = start + whole / 2 if whole <= goal * WHOLE_GROUP else at + size / 2
            shard = min(n_shards - 1, int(middle // goal))
            out[i] = shard, slots[shard]
            slots[shard] += 1
            at += size
    return out


def document_sizes(docs: DataFrame, others: list[str] | None = None) -> DataFrame:
    """``doc_id, size, text_crc32, key_hash`` and ``others``; a null text counts as an empty one."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select("doc_id", *(others or []), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.xxhash64(text).alias("key_hash"))


def op9_shards(spark, sf_dir: str) -> DataFrame:
    dealt = shards(document_sizes(table(spark, sf_dir, "documents")), 16)
    return dealt.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
