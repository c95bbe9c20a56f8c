"""Document fingerprints: bottom-k sketches of word-shingle hashes, built and compared by DataFrame functions only.

A sketch is the sorted array of the k smallest distinct 64-bit hashes of a text's shingles. Sketches of parts merge by union. From two
sketches follow the resemblance, the containment and the number of distinct shingles.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import shuffle_width, table, unused

K, SHINGLE_WORDS = 128, 5
_SPAN, _LOWEST = float(2**64), -float(2**63)


def with_shingle_hashes(df: DataFrame, text: str, out: str, words: int = SHINGLE_WORDS) -> DataFrame:
    """Add ``out``: hashes of the text's shingles, repeats included. Fewer words than a shingle: all of them as one; none or null: empty."""
    parts, hashes = unused(df, f"{out}_words", f"{out}_hashes")
    df = df.withColumn(parts, F.filter(F.split(F.coalesce(F.col(f"`{text}`"), F.lit("")), r"[\x20\x09-\x0D]+"), lambda w: w != ""))
    df = df.withColumn(hashes, F.transform(parts, lambda w: F.xxhash64(w))).drop(parts)
    h = F.col(hashes)
    starts = F.sequence(F.lit(1), F.size(h) - (words - 1))
    shingles = F.when(F.size(h) >= words, F.transform(starts, lambda i: F.xxhash64(*[F.get(h, i + (j - 1)) for j in range(words)])))
    return df.withColumn(out, shingles.when(F.size(h) > 0, F.array(F.xxhash64(h))).otherwise(F.expr("cast(array() as array<bigint>)"))).drop(hashes)


def sketch(shingles: Column, k: int = K) -> Column:
    return F.slice(F.sort_array(F.array_distinct(shingles)), 1, k)


def merged(a: Column, b: Column, k: int = K) -> Column:
    """Sketch of the union of two parts."""
    return F.slice(F.sort_array(F.array_union(a, b)), 1, k)


def distinct_count(s: Column, k: int = K) -> Column:
    """Estimated number of distinct shingles; exact while a sketch is not full."""
    filled = (F.element_at(s, -1).cast("double") - F.lit(_LOWEST)) / F.lit(_SPAN)
    return F.when(F.size(s) < k, F.size(s).cast("double")).otherwise(F.lit(k - 1.0) / filled)


def _shared(a: Column, b: Column, both: Column) -> Column:
    return F.size(F.array_intersect(F.array_intersect(both, a), b))


def resemblance(a: Column, b: Column, k: int = K) -> Column:
    """Estimated |A and B| / |A or B|; 1 for two empty sketches, 0 for one."""
    both = merged(a, b, k)
    return F.when(F.size(both) == 0, F.lit(1.0)).otherwise(_shared(a, b, both) / F.size(both))


def containment(a: Column, b: Column, k: int = K) -> Column:
    """Estimated share of A's shingles that B has; 1 for an empty A."""
    part = resemblance(a, b, k) * distinct_count(merged(a, b, k), k) / distinct_count(a, k)
    return F.when(F.size(a) == 0, F.lit(1.0)).otherwise(F.least(F.lit(1.0), part))


def merge_sketches(df: DataFrame, keys: list[str], column: str, k: int = K) -> DataFrame:
    """One sketch per key from the sketches of its parts; hot keys are cut to k rows in every task before the exchange."""
    h, r = unused(df, "h", "r")
    rows = df.select(*keys, F.explode(column).alias(h)).distinct()
    ranked = rows.withColumn(r, F.row_number().over(Window.partitionBy(*keys).orderBy(h))).where(F.col(r) <= k)
    return ranked.groupBy(*keys).agg(F.sort_array(F.collect_list(h)).alias(column))


def as_text(s: Column) -> Column:
    return F.array_join(F.transform(s, lambda h: F.lpad(F.lower(F.hex(h)), 16, "0")), "")


def with_next(df: DataFrame, id_column: str, columns: list[str], prepare: Callable[[DataFrame], DataFrame] = lambda df: df) -> DataFrame:
    """Apply ``prepare`` to dealt rows and add ``next_<column>`` from the following row in descending order of id; the last row's next is the first.

    Rows are dealt to buckets between id quantiles, and the one row that a neighbouring bucket needs is sent there too, so no task sees
    more than its bucket. Ids that occur more than once follow in order of the hash of ``columns``; null ids come last.
    The driver holds two ids for each bucket, four buckets for each shuffle partition.
    """
    spark = df.sparkSession
    least = -(1 << 63)
    key = F.coalesce(F.col(id_column).cast("long"), F.lit(least))
    ids = df.select(key.alias("k"))
    n = 4 * shuffle_width(spark)
    cuts = ids.agg(F.percentile_approx("k", [i / n for i in range(1, n)], 20 * n)).first()[0] if n > 1 else []
    cuts = sorted(set(cuts or []))
    depth = max(1, len(cuts).bit_length())
    padded = cuts + [(1 << 63) - 1] * ((1 << depth) - 1 - len(cuts))
    places = F.array(*[F.lit(c) for c in padded])
    steps = F.array(*[F.lit(1 << i) for i in reversed(range(depth))])

    def bucket_of(k: Column) -> Column:
        return F.aggregate(steps, F.lit(0), lambda at, s: F.when(F.get(places, at + s - 1) <= k, at + s).otherwise(at))

    k, b, to, own, tie = unused(df, "k", "b", "to", "own_row", "tie")
    held = df.withColumn(k, key).withColumn(b, bucket_of(F.col(k)))
    ends = {r["b"]: r["hi"] for r in ids.select("k", bucket_of(F.col("k")).alias("b")).groupBy("b").agg(F.max("k").alias("hi")).collect()}
    order = sorted(ends)
    tops = [ends.get(i) for i in range(1 << depth)]
    above = {i: order[(n + 1) % len(order)] for n, i in enumerate(order)}
    top_of = F.array(*[F.lit(t).cast("long") for t in tops])
    send_to = F.array(*[F.lit(above.get(i, -1)) for i in range(1 << depth)])
    target = F.get(send_to, F.col(b))
    is_top = F.col(k) == F.get(top_of, F.col(b))
    itself = F.struct(F.col(b).alias("b"), F.lit(1).alias("own"))
    guest = F.struct(target.alias("b"), F.lit(0).alias("own"))
    dealt = held.withColumn(to, F.explode(F.when(is_top, F.array(itself, guest)).otherwise(F.array(itself))))
    dealt = dealt.withColumn(own, F.col(to)["own"]).withColumn(b, F.col(to)["b"]).drop(to)
    dealt = prepare(dealt.repartition(shuffle_width(spark), b)).withColumn(tie, F.xxhash64(*columns))
    w = Window.partitionBy(b).orderBy(own, k, tie)
    kept = [F.col(f"`{c}`") for c in dealt.columns if c not in (k, b, own, tie)]
    return dealt.select(*kept, F.col(own).alias(own), *[F.lag(c).over(w).alias(f"next_{c}") for c in columns]).where(F.col(own) == 1).drop(own)


def op5_fingerprints(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", F.coalesce("text", F.lit("")).alias("text"))

    def sketched(df: DataFrame) -> DataFrame:
        return with_shingle_hashes(df, "text", "s").withColumn("own", sketch(F.col("s"))).drop("s")

    docs = with_next(docs, "doc_id", ["text", "own"], sketched).withColumnRenamed("next_own", "following")
    docs = docs.withColumn("n_chars", F.length("text").cast("long")).withColumn("cut", F.floor(F.col("n_chars") / 3).cast("int"))
    whole = F.concat(F.substr("text", F.lit(1), (F.col("n_chars") - F.col("cut")).cast("int")), F.substr("next_text", F.lit(1), F.col("cut")))
    docs = docs.withColumn("edited", whole)
    docs = with_shingle_hashes(docs, "edited", "s").withColumn("changed", sketch(F.col("s")))
    return docs.select(
        "doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), as_text(F.col("own")).alias("fingerprint"), as_text(F.col("changed")).alias("edited_fingerprint"),
        resemblance(F.col("own"), F.col("changed")).alias("near_edited"), resemblance(F.col("own"), F.col("following")).alias("near_next"),
        distinct_count(F.col("own")).alias("distinct_shingles"), containment(F.col("own"), F.col("changed")).alias("contained_in_edited"),
    )
