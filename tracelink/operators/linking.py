"""k nearest neighbours of every query among all candidates under cosine similarity.

All exact searches return the same ``qid, oid, sim, rnk``: only positive similarities, ranked by the similarity rounded to nine digits,
then by oid.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.columns import boxes_overlap, dense_dot, sparse_dot
from ..session import materialise
from . import blocks
from .prepare import time_bin
from .weights import OBJECT, pack


def sides(sig: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Split a signature relation into queries (qid, fid, wq) and candidates (oid, fid, wd)."""
    return sig.where("side = 'Q'").select(F.col("oid").alias("qid"), "fid", F.col("w").alias("wq")), sig.where("side = 'D'").select("oid", "fid", F.col("w").alias("wd"))


def top_k(pairs: DataFrame, k: int, sim: str = "sim", descending: bool = True) -> DataFrame:
    first = F.round(sim, 9).desc() if descending else F.round(sim, 9).asc()
    ranked = pairs.withColumn("rnk", F.row_number().over(Window.partitionBy("qid").orderBy(first, "oid")))
    return ranked.where(F.col("rnk") <= k)


def dot_pairs(q: DataFrame, d: DataFrame) -> DataFrame:
    """Similarity of all pairs that share a feature: an equi-join on the feature, summed by pair."""
    return q.join(d, "fid").groupBy("qid", "oid").agg(F.sum(F.col("wq") * F.col("wd")).alias("sim"))


#: Pairs by shared features that are always joined, and how many times the rows of both sides they may be; beyond, postings meet in blocks.
JOINED, JOINED_TIMES = 2_000_000, 8


def shared(q: DataFrame, d: DataFrame, on: list[str]) -> int:
    """Rows that an equi-join makes, from counts by key alone."""
    counted = q.groupBy(*on).agg(F.count(F.lit(1)).alias("nq")).join(d.groupBy(*on).agg(F.count(F.lit(1)).alias("nd")), on)
    return counted.agg(F.sum(F.col("nq") * F.col("nd"))).first()[0] or 0


def inverted(q: DataFrame, d: DataFrame, k: int, made: DataFrame | None = None) -> DataFrame:
    """By posting lists: an equi-join on the feature, or, where it would make many times the rows of both sides, within pairs of blocks.

    ``made``: ``blocks.ready(d)``, where d is written already and searched again and again; few queries then meet its blocks sooner.
    """
    if not blocks.takes(q, d, k):
        return top_k(dot_pairs(q, d), k)
    q, d = materialise(q, "queries"), d if made is not None else materialise(d, "candidates")
    if shared(q, d, ["fid"]) <= max(JOINED, JOINED_TIMES * (q.count() + (d.count() if made is None else 0))):
        return top_k(dot_pairs(q, d), k)
    return top_k(blocks.multiply(q, d, k, None, None, made), k)


def _packed(rows: DataFrame, key: str, w: str, name: str) -> DataFrame:
    return pack(rows.select(F.lit("").alias("side"), F.col(key).alias("oid"), "fid", F.col(w).alias("w"))).select(F.col("oid").alias(key), F.col("sig").alias(name))


def linear(q: DataFrame, d: DataFrame, k: int) -> DataFrame:
    """Yardstick: every query against every candidate, in a nested loop over blocks of signatures (over packed ones, where ids are no numbers)."""
    if blocks.takes(q, d, k):
        return top_k(blocks.multiply(q, d, k), k)
    pairs = _packed(q, "qid", "wq", "a").crossJoin(_packed(d, "oid", "wd", "b"))
    return top_k(pairs.select("qid", "oid", sparse_dot(F.col("a"), F.col("b")).alias("sim")).where("sim > 0"), k)


def euclid(q: DataFrame, d: DataFrame, k: int) -> DataFrame:
    """Smallest Euclidean distances of unit vectors: sqrt(2 - 2 cos), the same neighbours in the same order."""
    pairs = dot_pairs(q, d).withColumn("dist", F.sqrt(F.greatest(F.lit(0.0), 2 - 2 * F.col("sim"))))
    return pairs.withColumn("rnk", F.row_number().over(Window.partitionBy("qid").orderBy(F.round("sim", 9).desc(), "oid"))).where(F.col("rnk") <= k)


# --- threshold joins ---------------------------------------------------------------------------------------------------------------


def threshold(q: DataFrame, d: DataFrame, theta: float, bound: str = "maxweight") -> DataFrame:
    """All pairs with similarity of at least theta (> 0): ``qid, oid, sim``.

    Candidates' features are taken from the commonest to the rarest; those whose bound on the similarity so far stays below theta need no
    posting. Bounds: 'maxweight' (largest query weight of each feature), 'minsize' (and a least number of features), 'length' (and the
    norm of what is not posted), 'l2' (the smaller of both bounds decides what is posted).
    """
    most = q.groupBy("fid").agg(F.max("wq").alias("most"), F.count(F.lit(1)).alias("pf"))
    known = d.join(most, "fid")
    order = Window.partitionBy("oid").orderBy(F.col("pf").desc(), "fid").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    whole = Window.partitionBy("oid")
    run = known.withColumn("by_weight", F.sum(F.col("wd") * F.col("most")).over(order)).withColumn("by_norm", F.sqrt(F.sum(F.col("wd") * F.col("wd")).over(order)))
    reach = F.least("by_weight", "by_norm") if bound == "l2" else F.col("by_weight")
    run = run.withColumn("posted", reach >= theta - 1e-9).withColumn("size", F.count(F.lit(1)).over(whole)).withColumn("top", F.max("wd").over(whole))
    rest = F.coalesce(F.max(F.when(~F.col("posted"), F.col("by_norm"))).over(whole), F.lit(0.0))
    run = run.withColumn("rest", rest)
    heads = q.withColumn("q_top", F.max("wq").over(Window.partitionBy("qid"))) if bound in ("minsize", "l2") else q
    hits = heads.join(run.where("posted").select("oid", "fid", "wd", "size", "top", "rest"), "fid")
    if bound in ("minsize", "l2"):
        hits = hits.where(F.col("size") * F.col("q_top") * F.col("top") >= theta - 1e-9)
    found = hits.groupBy("qid", "oid").agg(F.sum(F.col("wq") * F.col("wd")).alias("part"), F.first("rest").alias("rest"))
    if bound in ("length", "l2"):
        found = found.where(F.col("part") + F.col("rest") >= theta - 1e-9)
    return verify(found.select("qid", "oid"), q, d).where(F.round("sim", 9) >= theta)


def verify(pairs: DataFrame, q: DataFrame, d: DataFrame) -> DataFrame:
    """Exact similarity of given pairs, from both signatures."""
    return pairs.join(q, "qid").join(d, ["oid", "fid"]).groupBy("qid", "oid").agg(F.sum(F.col("wq") * F.col("wd")).alias("sim"))


def calibrate_theta(knn: DataFrame, k: int) -> float:
    """Mean similarity of the k-th neighbours (one number for the driver)."""
    row = knn.where(F.col("rnk") == k).agg(F.avg("sim")).first()
    return float(row[0] or 0.0)


def threshold_knn(q: DataFrame, d: DataFrame, k: int, theta: float, bound: str = "l2") -> DataFrame:
    """k nearest neighbours by a threshold join; queries with fewer than k hits above theta fall back to the inverted join."""
    hits = top_k(threshold(q, d, theta, bound), k)
    done = hits.groupBy("qid").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= k).select("qid")
    rest = inverted(q.join(done, "qid", "left_anti"), d, k)
    return hits.join(done, "qid", "left_semi").select("qid", "oid", "sim", "rnk").union(rest.select("qid", "oid", "sim", "rnk"))


# --- boxes -------------------------------------------------------------------------------------------------------------------------


def boxes(sig: DataFrame, place: DataFrame) -> DataFrame:
    """Tight rectangle of each signature's places: ``side, oid, x1, y1, x2, y2``."""
    return sig.join(place.select(F.col("pid").alias("fid"), "x", "y"), "fid").groupBy(*OBJECT).agg(F.min("x").alias("x1"), F.min("y").alias("y1"), F.max("x").alias("x2"), F.max("y").alias("y2"))


def _spread(box: DataFrame, cell: float) -> DataFrame:
    """Boxes in the grid cells (cx, cy) they touch."""
    at = lambda c: F.floor(F.col(c) / cell).cast("long")
    return box.withColumn("cx", F.explode(F.sequence(at("x1"), at("x2")))).withColumn("cy", F.explode(F.sequence(at("y1"), at("y2"))))


def overlapping(box: DataFrame, cell: float = 25.0) -> DataFrame:
    """``qid, oid`` of queries and candidates whose boxes share a point.

    A range join as an equi-join: boxes are posted in the grid cells they touch; a pair counts only in the cell of the corner where the
    overlap begins, so it comes once.
    """
    spread = _spread(box, cell)
    names = ["x1", "y1", "x2", "y2"]
    q = spread.where("side = 'Q'").select("cx", "cy", F.col("oid").alias("qid"), *[F.col(c).alias(f"q_{c}") for c in names])
    d = spread.where("side = 'D'").select("cx", "cy", "oid", *[F.col(c).alias(f"d_{c}") for c in names])
    corner = (F.floor(F.greatest("q_x1", "d_x1") / cell) == F.col("cx")) & (F.floor(F.greatest("q_y1", "d_y1") / cell) == F.col("cy"))
    return q.join(d, ["cx", "cy"]).where(boxes_overlap("q_", "d_") & corner).select("qid", "oid")


def _boxes_meet(a: dict[str, np.ndarray], b: dict[str, np.ndarray]) -> np.ndarray:
    return (a["x1"] <= b["x2"]) & (b["x1"] <= a["x2"]) & (a["y1"] <= b["y2"]) & (b["y1"] <= a["y2"])


def mbr_range(q: DataFrame, d: DataFrame, box: DataFrame, k: int, cell: float = 25.0) -> DataFrame:
    """Range query with each query's box, then exact similarity of the survivors; where boxes share many times more cells than there are
    boxes, within pairs of blocks."""
    if blocks.takes(q, d, k):
        q, d, box = materialise(q, "queries"), materialise(d, "candidates"), materialise(box, "boxes")
        spread = _spread(box, cell)
        if shared(*(spread.where(F.col("side") == s) for s in "QD"), ["cx", "cy"]) > max(JOINED, JOINED_TIMES * (q.count() + d.count())):
            return top_k(blocks.multiply(q, d, k, box, _boxes_meet), k)
    return top_k(verify(overlapping(box, cell), q, d), k)


def overlap_ratio(box: DataFrame, cell: float = 25.0) -> DataFrame:
    """Share of query-candidate pairs whose boxes overlap."""
    sizes = box.groupBy().agg(F.count(F.when(F.col("side") == "Q", 1)).alias("nq"), F.count(F.when(F.col("side") == "D", 1)).alias("nd"))
    return overlapping(box, cell).groupBy().agg(F.count(F.lit(1)).alias("overlapping")).crossJoin(sizes).select("overlapping", (F.col("nq") * F.col("nd")).alias("pairs"), F.round(F.col("overlapping") / (F.col("nq") * F.col("nd")), 6).alias("ratio"))  # two single rows


# --- histograms --------------------------------------------------------------------------------------------------------------------


def temporal(trace: DataFrame, hours: int) -> DataFrame:
    """``side, oid, h``: share of points in each bin of the day."""
    bins = 24 // hours
    slot = time_bin(F.col("t"), hours)
    held = trace.groupBy(*OBJECT).agg(*[F.count(F.when(slot == b, 1)).alias(f"b{b}") for b in range(bins)], F.count(F.lit(1)).alias("n"))
    return held.select(*OBJECT, F.array(*[(F.col(f"b{b}") / F.col("n")) for b in range(bins)]).alias("h"))


def histogram_knn(hist: DataFrame, hours: int, k: int, how: str = "emd") -> DataFrame:
    """Neighbours by histogram similarity. Every pair is compared: histograms carry no feature to join on, so queries meet all candidates,
    in blocks; equal histograms are compared once.

    The yardstick of the other measures; for the transport cost, a metric, ``histogram_index`` compares far fewer pairs.
    """
    held = materialise(hist, "histograms")
    q = held.where("side = 'Q'").select(F.col("oid").alias("qid"), F.col("h").alias("v"))
    d = held.where("side = 'D'").select("oid", F.col("h").alias("v"))
    return blocks.scan(q, d, k, lambda a, b: _histogram_similarity(a, b, how, hours))


def _histogram_similarity(a: np.ndarray, b: np.ndarray, how: str, hours: int, smooth: float = 1e-6) -> np.ndarray:
    """``histogram_distance`` of each histogram of ``a`` to each of ``b``, distances negated: (len(a), len(b))."""
    if how == "emd":
        return 1 - _transport(a, b, hours)
    if how == "bhattacharyya":
        return -np.sqrt(np.maximum(0.0, 1 - np.sqrt(a) @ np.sqrt(b).T))
    if how == "kl":
        p, q = a + smooth, b + smooth
        return p @ np.log(q).T - (p * np.log(p)).sum(axis=1)[:, None]
    if how == "correlation":
        x, y = a - a.mean(axis=1)[:, None], b - b.mean(axis=1)[:, None]
        vx, vy = (x * x).sum(axis=1), (y * y).sum(axis=1)
        spread = np.sqrt(vx[:, None] * vy[None, :])
        return np.divide(x @ y.T, spread, out=np.zeros_like(spread), where=(vx > 0)[:, None] & (vy > 0)[None, :])
    out, part = np.zeros((len(a), len(b))), np.empty((len(a), len(b)))
    for x, y in zip(a.T, b.T, strict=True):
        x, y = x[:, None], y[None, :]
        if how == "intersection":
            out += np.minimum(x, y, out=part)
        elif how == "lp":
            np.subtract(x, y, out=part)
            out += np.multiply(part, part, out=part)
        else:
            np.subtract(x, y, out=part)
            np.multiply(part, part, out=part)
            both = x + y
            out += np.divide(part, both, out=part, where=both > 0)  # where both are 0 the difference is
    return out if how == "intersection" else -np.sqrt(out) if how == "lp" else -out


#: Histograms aimed at for a cell of the index, and histograms sampled for its planes.
HIST_CELL, HIST_SAMPLE = 64, 20_000


def _transport(a: np.ndarray, b: np.ndarray, hours: int) -> np.ndarray:
    """Circular transport cost of each histogram of ``a`` to each of ``b``: (len(a), len(b))."""
    run = np.cumsum(a, axis=1)[:, None, :] - np.cumsum(b, axis=1)[None, :, :]
    run = np.sort(run, axis=2)
    bins = run.shape[2]
    middle = (run[:, :, (bins - 1) // 2] + run[:, :, bins // 2]) / 2
    return np.abs(run - middle[:, :, None]).sum(axis=2) * (hours / 12.0)


def histogram_index(hist: DataFrame, hours: int, k: int) -> DataFrame:
    """Exact neighbours under the circular transport cost, with pivots.

    A histogram is placed by its cost to each histogram of a single bin (and the even one). By the triangle inequality two histograms are
    at least as far apart as any of these costs differ, so k-d cells over the places bound the cost: a query searches the nearest cell
    first, and then only the cells within the cost of its k-th neighbour there. Candidates of a cell meet its queries in blocks.
    """
    from .spaces import KdTree

    bins = 24 // hours
    pivots = np.concatenate([np.eye(bins), np.full((1, bins), 1 / bins)])
    place = F.pandas_udf(lambda h: pd.Series(list(_transport(np.stack(h.to_numpy()), pivots, hours)) if len(h) else [], dtype=object), "array<double>")
    held = materialise(hist.select("side", "oid", "h", place("h").alias("v")), "histograms")
    spark = hist.sparkSession
    d = held.where("side = 'D'")
    n = d.count()
    sample = d.orderBy(F.xxhash64("oid"), "oid").limit(HIST_SAMPLE).select("v").toPandas()
    if not n:
        return held.where("false").select(F.col("oid").alias("qid"), "oid", F.lit(0.0).alias("sim"), F.lit(0).alias("rnk"))
    cut = KdTree(np.stack(sample["v"].to_numpy()), int(min(len(sample), max(1, -(-n // HIST_CELL)))))
    plan = spark.sparkContext.broadcast(cut)  # no more cells than sampled histograms
    cell = F.pandas_udf(lambda v: pd.Series(plan.value.assign(np.stack(v.to_numpy())) if len(v) else [], dtype="int64"), "long")
    stored = materialise(d.select("oid", "h", "v", cell("v").alias("cell")), "histogram-cells")
    size = bins + 1
    ends = stored.groupBy("cell").agg(*[f(F.get("v", F.lit(j))).alias(f"{a}{j}") for j in range(size) for a, f in (("l", F.min), ("h", F.max))]).toPandas()
    names, low, high = ends["cell"].to_numpy(), ends[[f"l{j}" for j in range(size)]].to_numpy(), ends[[f"h{j}" for j in range(size)]].to_numpy()
    box = spark.sparkContext.broadcast((names, low, high))  # one row a cell

    def gaps(x: np.ndarray) -> np.ndarray:
        _, low, high = box.value
        return np.maximum(np.maximum(low - x, x - high), 0).max(axis=1)

    nearest = F.pandas_udf(lambda v: pd.Series([int(box.value[0][np.argmin(gaps(x))]) for x in v], dtype="int64"), "long")
    q = held.where("side = 'Q'").select(F.col("oid").alias("qid"), "h", "v").withColumn("cell", nearest("v"))

    def search(queries: pd.DataFrame, cands: pd.DataFrame) -> pd.DataFrame:
        if not len(queries) or not len(cands):
            return pd.DataFrame({"qid": [], "oid": [], "sim": []})
        ids, there = cands["oid"].to_numpy(), np.stack(cands["h"].to_numpy())
        out = []
        for i in range(0, len(queries), 256):
            part = queries.iloc[i : i + 256]
            x, oid, sim = np.stack(part["h"].to_numpy()), np.zeros((len(part), 0), dtype=np.int64), np.zeros((len(part), 0))
            for j in range(0, len(there), 256):
                s = 1 - _transport(x, there[j : j + 256], hours)
                oid, sim = np.concatenate([oid, np.broadcast_to(ids[j : j + 256], s.shape)], axis=1), np.concatenate([sim, s], axis=1)
                order = np.lexsort((oid, -np.round(sim, 9)), axis=1)[:, :k]
                oid, sim = np.take_along_axis(oid, order, axis=1), np.take_along_axis(sim, order, axis=1)
            out.append(pd.DataFrame({"qid": np.repeat(part["qid"].to_numpy(), oid.shape[1]), "oid": oid.ravel(), "sim": sim.ravel()}))
        return pd.concat(out)

    cands = stored.select("cell", "oid", "h").groupBy("cell")
    pairs = "qid long, oid long, sim double"
    home = q.groupBy("cell").cogroup(cands).applyInPandas(lambda a, b: search(a, b), pairs)
    reach = top_k(home, k).where(F.col("rnk") == k).select("qid", (1 - F.col("sim") + 2e-9).alias("reach"))

    def others(v: pd.Series, cell: pd.Series, reach: pd.Series) -> pd.Series:
        names = box.value[0]
        return pd.Series([names[(gaps(x) <= r) & (names != c)].tolist() for x, c, r in zip(v, cell, reach.fillna(9.0), strict=True)], dtype=object)

    visits = q.join(reach, "qid", "left").withColumn("to", F.explode(F.pandas_udf(others, "array<long>")("v", "cell", "reach")))
    away = visits.select("qid", "h", F.col("to").alias("cell")).groupBy("cell").cogroup(cands).applyInPandas(lambda a, b: search(a, b), pairs)
    return top_k(home.union(away), k)


def dense_knn(vectors: DataFrame, k: int, id_column: str = "vec_id", column: str = "embedding") -> DataFrame:
    """Exact cosine neighbours of dense vectors (each against all others, in blocks): the yardstick for the spatial indices."""
    unit = materialise(unit_vectors(vectors, id_column, column), "unit")
    q, d = unit.select(F.col("id").alias("qid"), "v"), unit.select(F.col("id").alias("oid"), "v")
    # a vector itself is one of its first k + 1
    return top_k(blocks.scan(q, d, k + 1, lambda a, b: a @ b.T).where("qid <> oid").drop("rnk"), k)


def unit_vectors(vectors: DataFrame, id_column: str = "vec_id", column: str = "embedding") -> DataFrame:
    norm = F.sqrt(dense_dot(F.col(column), F.col(column)))
    return vectors.select(F.col(id_column).alias("id"), F.transform(column, lambda x: x.cast("double") / norm).alias("v"))


# --- hashing -----------------------------------------------------------------------------------------------------------------------


def _sign(fid: Column, j: int) -> Column:
    """Entry +1 or -1 of hyperplane j for a feature, by integer arithmetic (never stored)."""
    h = ((fid.cast("long") % 1000003 + 1) * (7919 + 104729 * (j + 1)) + 1299709 * (j + 1)) % 2147483647
    return F.when(((h * 48271) % 2147483647) % 1048576 < 524288, 1.0).otherwise(-1.0)


def _gauss(fid: Column, j: int) -> Column:
    u = (F.xxhash64(fid, F.lit(2 * j)).bitwiseAND(F.lit((1 << 52) - 1)) + 1) / F.lit(float(1 << 52))
    v = F.xxhash64(fid, F.lit(2 * j + 1)).bitwiseAND(F.lit((1 << 52) - 1)) / F.lit(float(1 << 52))
    return F.sqrt(-2 * F.log(u)) * F.cos(v * F.lit(6.283185307179586))


def lsh_bits(sig: DataFrame, m: int, family: str = "sign", superbit: int | None = None) -> DataFrame:
    """``side, oid, bits``: on which side of m random hyperplanes each signature lies.

    ``superbit`` makes the directions of each batch of that many orthogonal over the vocabulary: the batch's Gram matrix (superbit squared
    numbers) is summed on the executors, its inverse root is applied to the projections.
    """
    entry = _sign if family == "sign" else _gauss
    dots = sig.groupBy(*OBJECT).agg(*[F.sum(F.col("w") * entry(F.col("fid"), j)).alias(f"p{j}") for j in range(m)])
    if superbit:
        import numpy as np

        vocabulary = sig.select("fid").distinct()
        for start in range(0, m, superbit):
            batch = list(range(start, min(m, start + superbit)))
            gram = vocabulary.agg(*[F.sum(entry(F.col("fid"), i) * entry(F.col("fid"), j)).alias(f"g{i}_{j}") for i in batch for j in batch]).first()
            root = np.linalg.inv(np.linalg.cholesky(np.array([[gram[f"g{i}_{j}"] for j in batch] for i in batch]) + 1e-9 * np.eye(len(batch))))
            turned = [sum((F.col(f"p{j}") * float(root[r, c]) for c, j in enumerate(batch)), F.lit(0.0)).alias(f"p{i}") for r, i in enumerate(batch)]
            dots = dots.select(*OBJECT, *[f"p{j}" for j in range(m) if j not in batch], *turned)
    return dots.select(*OBJECT, F.array(*[(F.round(f"p{j}", 9) >= 0).cast("int") for j in range(m)]).alias("bits"))


def lsh_scan(bits: DataFrame, m: int, k: int) -> DataFrame:
    """Neighbours by the cosine estimated from Hamming distance, over all pairs (in blocks): the reduced representation as it is."""
    packed = materialise(bits.select("side", "oid", F.transform("bits", lambda b: b.cast("double") * 2 - 1).alias("v")), "bits")
    q, d = packed.where("side = 'Q'").select(F.col("oid").alias("qid"), "v"), packed.where("side = 'D'").select("oid", "v")
    # signs' products sum to m less twice the bits that differ
    return blocks.scan(q, d, k, lambda a, b: np.cos(np.pi * ((m - a @ b.T) / 2) / m))


def _bands_agree(a: dict[str, np.ndarray], b: dict[str, np.ndarray]) -> np.ndarray:
    return np.logical_or.reduce([a[c] == b[c] for c in a])


def lsh(q: DataFrame, d: DataFrame, bits: DataFrame, bands: int, m: int, k: int) -> DataFrame:
    """Approximate neighbours: objects that agree on all bits of a band are candidates, their similarity is exact.

    Where buckets would make many times more pairs than there are rows, the bands are compared within pairs of blocks.
    """
    width = m // bands
    bits = materialise(bits, "bits")
    keys = F.explode(F.array(*[F.struct(F.lit(i).alias("band"), F.array_join(F.transform(F.slice("bits", i * width + 1, width), lambda b: b.cast("string")), "").alias("key")) for i in range(bands)]))
    posted = bits.select("side", "oid", keys.alias("e")).select("side", "oid", "e.band", "e.key")
    left = posted.where("side = 'Q'").select("band", "key", F.col("oid").alias("qid"))
    right = posted.where("side = 'D'").select("band", "key", "oid")
    if blocks.takes(q, d, k) and width <= 52:
        q, d = materialise(q, "queries"), materialise(d, "candidates")
        if shared(left, right, ["band", "key"]) > max(JOINED, JOINED_TIMES * (q.count() + d.count())):
            number = lambda i: F.aggregate(F.slice("bits", i * width + 1, width), F.lit(0.0), lambda s, b: s * 2 + b)
            return top_k(blocks.multiply(q, d, k, bits.select("side", "oid", *[number(i).alias(f"b{i}") for i in range(bands)]), _bands_agree), k)
    return top_k(verify(left.join(right, ["band", "key"]).select("qid", "oid").distinct(), q, d), k)


#: Queries on which hashing is tuned, and band widths that are tried, from the most selective on.
TUNING_QUERIES, WIDTHS = 400, (16, 12, 8, 6, 4, 3, 2)


def lsh_tune(q: DataFrame, d: DataFrame, sig: DataFrame, target: float, k: int = 1, m: int = 96, family: str = "sign") -> tuple[int, float]:
    """Bands of m bits (and the recall reached) with the widest bands that find ``target`` of the exact first k neighbours.

    Recall is measured on a bounded number of queries drawn by hash against all candidates. If even the narrowest bands miss the target
    they are returned with their recall.
    """
    from .metrics import recall_at

    drawn = q.select("qid").distinct().orderBy(F.xxhash64("qid"), "qid").limit(TUNING_QUERIES)
    few = q.join(F.broadcast(drawn), "qid", "left_semi")
    bits = materialise(lsh_bits(sig, m, family), "bits")
    exact = materialise(inverted(few, d, k).select("qid", "oid", "rnk"), "exact")
    own = bits.where("side = 'D'").union(bits.where("side = 'Q'").join(F.broadcast(drawn.select(F.col("qid").alias("oid"))), "oid", "left_semi").select(*bits.columns))
    recall = 0.0
    for width in WIDTHS:
        recall = recall_at(lsh(few, d, own, m // width, m, k), exact, k).first()["recall"] or 0.0
        if recall >= target:
            break
    return m // width, float(recall)
