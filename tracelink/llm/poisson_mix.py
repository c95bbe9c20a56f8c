"""Mixing sources to target weights by Poisson replication.

Each source has a mean repetition rate. The number of copies of a document is a Poisson variate with that mean, obtained by inverting the
distribution at a uniform number hashed from (seed, doc_id): any executor that recomputes a row gets the same count. Copies are exploded
and dealt out and ordered by a hashed key, which is a global shuffle without a sampling pass.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialise, table

#: A rate above this is split into equal independent streams (a sum of Poissons is a Poisson), so that exp(-rate) never underflows.
STREAM_RATE = 16.0
#: Steps of the distribution function kept for a stream; beyond them less than 1e-25 of the mass remains at STREAM_RATE.
CDF_STEPS = 80
#: So many sources at most are sent to every executor, the largest ones; the others, each of few rows, are joined by shuffle.
BROADCAST_SOURCES = 100_000


def _unit(*parts: Column) -> Column:
    """Uniform number in [0, 1) with 52 bits from the digest of the parts joined by '|'."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 13), 16, 10).cast("double") / F.lit(float(2**52))


def source_rates(docs: DataFrame, weights: dict[str, float] | None = None, temperature: float = 0.5, total: float = 1.0) -> DataFrame:
    """One row per source: ``source, share, weight, rate``. Without ``weights`` a source's weight is its row share to the power ``temperature``.

    The rate is weight / share * total, so the output has about ``total`` times the input's rows. Null is a source of its own. Sources
    missing in ``weights`` get weight 0, hence no copies.
    """
    per = docs.groupBy(F.col("source").alias("source")).agg(F.count(F.lit(1)).alias("n"))
    if weights is None:
        raw = F.pow(F.col("n").cast("double"), F.lit(temperature))
    else:
        pairs = [x for k, v in weights.items() for x in (F.lit(k), F.lit(float(v)))]
        raw = F.coalesce(F.create_map(*pairs)[F.coalesce("source", F.lit(""))], F.lit(0.0)) if pairs else F.lit(0.0)
    per = materialise(per.withColumn("raw", raw), "source-rates")
    sums = per.agg(F.sum("n").alias("n"), F.sum("raw").alias("raw")).first()
    n_all, raw_all = float(sums["n"] or 1), float(sums["raw"] or 1) or 1.0
    share, weight = F.col("n") / F.lit(n_all), F.col("raw") / F.lit(raw_all)
    return per.select("source", share.alias("share"), weight.alias("weight"), (weight / share * F.lit(total)).alias("rate"))


def _with_cdf(rates: DataFrame) -> DataFrame:
    """Add the number of streams and the distribution function of one stream, as an array."""
    streams = F.greatest(F.lit(1), F.ceil(F.col("rate") / F.lit(STREAM_RATE))).cast("int")
    rates = rates.withColumn("streams", streams).withColumn("mu", F.col("rate") / F.col("streams"))
    start = F.struct(F.exp(-F.col("mu")).alias("p"), F.exp(-F.col("mu")).alias("c"), F.array(F.exp(-F.col("mu"))).alias("cdf"))

    def step(acc: Column, k: Column) -> Column:
        p = acc["p"] * F.col("mu") / k
        return F.struct(p.alias("p"), (acc["c"] + p).alias("c"), F.concat(acc["cdf"], F.array(acc["c"] + p)).alias("cdf"))

    return rates.withColumn("cdf", F.aggregate(F.sequence(F.lit(1), F.lit(CDF_STEPS)), start, step)["cdf"])


def _with_rates(rows: DataFrame, rates: DataFrame, most: int) -> DataFrame:
    """Join ``rows`` with their source's row without moving the rows of a popular source.

    Up to ``most`` sources are sent to every executor. Of more, the ``most`` largest are; each of the others has at most 1 row in ``most``.
    """
    same = F.col("x_source").eqNullSafe(F.col("r_source"))
    if rates.count() <= most:
        return rows.join(F.broadcast(rates), same)
    large = F.broadcast(materialise(rates.orderBy(F.desc("r_share"), "r_source").limit(most), "large-sources"))
    small = rates.join(large.select(F.col("r_source").alias("l_source")), F.col("r_source").eqNullSafe(F.col("l_source")), "left_anti")
    return rows.join(large, same).union(rows.join(large, same, "left_anti").join(small, same))


def poisson_mix(docs: DataFrame, weights: dict[str, float] | None = None, temperature: float = 0.5, total: float = 1.0, seed: str = "mix", broadcast_sources: int = BROADCAST_SOURCES) -> DataFrame:
    """Replicate every document by its Poisson count and shuffle globally.

    Returns the columns of ``docs`` and ``mix_rate, mix_copies, mix_copy`` (from 1) and ``mix_key``; own columns of these names are replaced,
    columns of any other name pass through. Equal doc_ids draw equal counts, so repeated rows are repeated alike; a null doc_id counts as
    the empty string; a null source is a source of its own; empty tables give no rows. Texts are never looked at, so null, empty and very
    long ones do not matter. A source with a third of all rows is no hot key: its rate is sent to the documents, and the final exchange is
    on the hashed key of the copy.
    """
    own = ["mix_rate", "mix_copies", "mix_copy", "mix_key"]
    others = [c for c in docs.columns if c not in own]
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in others]).alias("row"), F.coalesce(F.col("doc_id").cast("string"), F.lit("")).alias("ident"), F.col("source").alias("x_source"))
    rates = _with_cdf(source_rates(docs, weights, temperature, total)).select(F.col("source").alias("r_source"), F.col("share").alias("r_share"), F.col("rate").alias("mix_rate"), "streams", "cdf")
    drawn = lambda j: F.size(F.filter("cdf", lambda c: c <= _unit(F.lit(seed), F.col("ident"), j.cast("string"))))
    copies = F.aggregate(F.sequence(F.lit(1), F.col("streams")), F.lit(0), lambda n, j: n + drawn(j))
    joined = _with_rates(rows, rates, broadcast_sources).withColumn("mix_copies", F.when(F.col("mix_rate") > 0, copies).otherwise(0))
    joined = joined.select("row", "ident", "mix_rate", "mix_copies").where("mix_copies > 0")
    spread = joined.select("*", F.explode(F.sequence(F.lit(1), F.col("mix_copies"))).alias("mix_copy"))
    key = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(seed + "#"), F.col("ident"), F.col("mix_copy").cast("string"))), 1, 15), 16, 10).cast("long")
    dealt = spread.withColumn("mix_key", key).repartition("mix_key").sortWithinPartitions("mix_key", "ident", "mix_copy")
    return dealt.select(*[F.col("row")[c].alias(c) for c in others], *own)


def op6_poisson_mix(spark, sf_dir: str) -> DataFrame:
    mixed = poisson_mix(table(spark, sf_dir, "documents"))
    return mixed.select("doc_id", "source", "lang", "text", F.round("mix_rate", 6).alias("rate"), F.col("mix_copies").cast("long").alias("copies"), F.col("mix_copy").cast("long").alias("copy"), F.col("mix_key").alias("mix_key"))


def mix_sql(docs: str, columns: str) -> str:
    """DuckDB text of poisson_mix with default parameters over relation ``docs``; ``columns`` picks from its result."""
    return f"""
n_src AS (SELECT source, count(*) AS n, sqrt(count(*)::DOUBLE) AS raw FROM {docs} GROUP BY source),
rate AS (SELECT source, (raw / sum(raw) OVER ()) / (n / (sum(n) OVER ())::DOUBLE) AS rate FROM n_src),
mu AS (SELECT source, rate, greatest(1, ceil(rate / 16.0))::INT AS streams, rate / greatest(1, ceil(rate / 16.0)) AS mu FROM rate),
steps AS (SELECT source, rate, streams, k, sum(exp(-mu + k * ln(mu) - lgamma(k + 1))) OVER (PARTITION BY source ORDER BY k) AS c FROM mu, range(0, 81) t(k)),
cdf AS (SELECT source, rate, streams, list(c ORDER BY k) AS cdf FROM steps GROUP BY ALL),
drawn AS (SELECT d.*, r.rate, list_sum(list_transform(range(1, r.streams + 1), lambda j: len(list_filter(r.cdf, lambda c:
    c <= ('0x' || substr(md5('mix|' || d.doc_id || '|' || j), 1, 13))::BIGINT / 4503599627370496.0))))::BIGINT AS copies
  FROM {docs} d JOIN cdf r ON d.source IS NOT DISTINCT FROM r.source),
mixed AS (SELECT *, ('0x' || substr(md5('mix#|' || doc_id || '|' || copy), 1, 15))::BIGINT AS mix_key FROM (SELECT *, unnest(range(1, copies + 1)) AS copy FROM drawn))
SELECT {columns} FROM mixed"""


OP6_SQL = "WITH " + mix_sql("documents", "doc_id, source, lang, text, round(rate, 6) AS rate, copies, copy, mix_key")
