"""Reduction of signatures by principal components."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import materialise

#: Objects up to which the exact method may bring their Gram matrix to the driver.
GRAM_OBJECTS = 3000


def _projected(spark, ids: list[tuple[str, int]], points: np.ndarray) -> DataFrame:
    return spark.createDataFrame([(s, int(o), [float(x) for x in row]) for (s, o), row in zip(ids, points, strict=True)], "side string, oid long, v array<double>")


def pca(sig: DataFrame, m: int, method: str = "gram", iters: int = 8) -> DataFrame:
    """``side, oid, v``: coordinates on the m leading components of the centred signatures of both sides.

    'gram' is exact: products of objects by a join on the feature, eigenvectors of the n x n matrix on the driver (n at most GRAM_OBJECTS).
    'randomized' never holds more than (m + 8) squared numbers on the driver: it multiplies the sparse rows with a hashed block of m + 8
    columns back and forth, 2 * iters + 2 passes.
    """
    spark = sig.sparkSession
    if method == "gram":
        ids = [(r["side"], r["oid"]) for r in sig.select("side", "oid").distinct().limit(GRAM_OBJECTS + 1).collect()]
        if len(ids) > GRAM_OBJECTS:
            raise ValueError("too many objects for the exact method: use method='randomized'")
        ids.sort()
        at = {x: i for i, x in enumerate(ids)}
        left = sig.select(F.col("side").alias("s1"), F.col("oid").alias("o1"), "fid", F.col("w").alias("w1"))
        right = sig.select(F.col("side").alias("s2"), F.col("oid").alias("o2"), "fid", F.col("w").alias("w2"))
        cells = left.join(right, "fid").groupBy("s1", "o1", "s2", "o2").agg(F.sum(F.col("w1") * F.col("w2")).alias("g")).toPandas()
        gram = np.zeros((len(ids), len(ids)))
        gram[[at[x] for x in zip(cells["s1"], cells["o1"], strict=True)], [at[x] for x in zip(cells["s2"], cells["o2"], strict=True)]] = cells["g"]
        mean = gram.mean(axis=0)
        gram = gram - mean[:, None] - mean[None, :] + mean.mean()
        value, vector = np.linalg.eigh(gram)
        keep = np.argsort(-value)[:m]
        return _projected(spark, ids, vector[:, keep] * np.sqrt(np.maximum(value[keep], 0)))
    width = m + 8
    sig = materialise(sig, "pca-rows")
    objects = sig.select("side", "oid").distinct()
    n = objects.count()
    mean = materialise(sig.groupBy("fid").agg((F.sum("w") / n).alias("mu")), "pca-mean")
    block = F.array(*[((F.xxhash64("fid", F.lit(j)).bitwiseAND(F.lit((1 << 31) - 1))) / float(1 << 30) - 1.0) for j in range(width)])
    columns = materialise(mean.select("fid", "mu", block.alias("v")), "pca-block")

    def summed(rows: DataFrame, keys: list[str], weight: str) -> DataFrame:
        return rows.groupBy(*keys).agg(F.array(*[F.sum(F.col(weight) * F.get("v", F.lit(j))) for j in range(width)]).alias("v"))

    def shifted(df: DataFrame, by: list[float], keys: list[str], scale=None) -> DataFrame:
        parts = [(F.get("v", F.lit(j)) - (F.lit(by[j]) * scale if scale is not None else F.lit(by[j]))) for j in range(width)]
        return df.select(*keys, F.array(*parts).alias("v"))

    def turned(df: DataFrame, keys: list[str], matrix: np.ndarray) -> DataFrame:
        return df.select(*keys, F.array(*[sum((F.get("v", F.lit(i)) * float(matrix[i, j]) for i in range(width)), F.lit(0.0)) for j in range(matrix.shape[1])]).alias("v"))

    def gram_of(df: DataFrame) -> np.ndarray:
        row = df.agg(*[F.sum(F.get("v", F.lit(i)) * F.get("v", F.lit(j))).alias(f"g{i}_{j}") for i in range(width) for j in range(i, width)]).first()
        out = np.zeros((width, width))
        for i in range(width):
            for j in range(i, width):
                out[i, j] = out[j, i] = row[f"g{i}_{j}"] or 0.0
        return out

    def orthonormal(df: DataFrame, keys: list[str]) -> DataFrame:
        value, vector = np.linalg.eigh(gram_of(df))
        ok = value > 1e-12 * max(value.max(), 1e-300)
        root = np.where(ok, 1 / np.sqrt(np.where(ok, value, 1)), 0)
        return materialise(turned(df, keys, vector * root), "pca-basis")

    def forward(cols: DataFrame) -> DataFrame:
        drift = cols.agg(*[F.sum(F.col("mu") * F.get("v", F.lit(j))) for j in range(width)]).first()
        return orthonormal(shifted(summed(sig.join(cols.select("fid", "v"), "fid"), ["side", "oid"], "w"), [float(x or 0) for x in drift], ["side", "oid"]), ["side", "oid"])

    def backward(rows: DataFrame) -> DataFrame:
        total = [float(x or 0) for x in rows.agg(*[F.sum(F.get("v", F.lit(j))) for j in range(width)]).first()]
        back = summed(sig.join(rows, ["side", "oid"]), ["fid"], "w").join(mean, "fid")
        return materialise(shifted(back, total, ["fid", "mu"], F.col("mu")), "pca-block")

    for _ in range(iters):
        columns = backward(forward(columns))
    basis = forward(columns)
    value, vector = np.linalg.eigh(gram_of(backward(basis)))
    keep = np.argsort(-value)[:m]
    return turned(basis, ["side", "oid"], vector[:, keep] * np.sqrt(np.maximum(value[keep], 0)))


def pca_dense(vectors: DataFrame, m: int, id_column: str = "vec_id", column: str = "embedding") -> DataFrame:
    """``id, v``: dense vectors of unit length on their m leading components, by the library's exact method (width squared numbers on the driver)."""
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector, vector_to_array

    from .linking import unit_vectors

    unit = unit_vectors(vectors, id_column, column)
    size = F.size("v")
    means = unit.select(F.posexplode("v").alias("i", "x")).groupBy("i").agg(F.avg("x").alias("mu")).orderBy("i").toPandas()["mu"].tolist()  # one number a dimension
    centred = unit.select("id", F.zip_with("v", F.array(*[F.lit(float(x)) for x in means]), lambda a, b: a - b).alias("v")).where(size > 0)
    held = materialise(centred, "centred").select("id", array_to_vector("v").alias("x"))
    model = PCA(k=m, inputCol="x", outputCol="p").fit(held)
    return model.transform(held).select("id", vector_to_array("p").alias("v"))


def projected_knn(points: DataFrame, k: int) -> DataFrame:
    """Cosine neighbours of projected signatures (every query against every candidate)."""
    from ..functions.columns import dense_dot
    from .linking import top_k, unit_vectors

    q, d = (unit_vectors(points.where(F.col("side") == s), "oid", "v") for s in "QD")
    return top_k(q.select(F.col("id").alias("qid"), F.col("v").alias("a")).crossJoin(d.select(F.col("id").alias("oid"), F.col("v").alias("b"))).select("qid", "oid", dense_dot(F.col("a"), F.col("b")).alias("sim")), k)
