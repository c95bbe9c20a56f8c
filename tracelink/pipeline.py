"""Linking as one object, and signatures as an estimator that keeps the rarity it learned."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.ml import Estimator, Model
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .operators import linking as L
from .operators import metrics as M
from .operators import prepare as P
from .operators import refine, sigtree
from .operators import weights as W
from .session import materialise
from .sources import traces as S

SEARCHES: dict[str, Callable[[DataFrame, DataFrame, DataFrame, DataFrame, int], DataFrame]] = {
    "inverted": lambda sig, q, d, place, k: L.inverted(q, d, k),
    "linear": lambda sig, q, d, place, k: L.linear(q, d, k),
    "euclid": lambda sig, q, d, place, k: L.euclid(q, d, k),
    "l2ap": lambda sig, q, d, place, k: L.threshold_knn(q, d, k, 0.3),
    "mbr": lambda sig, q, d, place, k: L.mbr_range(q, d, L.boxes(sig, place), k),
    "lsh": lambda sig, q, d, place, k: L.lsh(q, d, L.lsh_bits(sig, 64), 16, 64, k),
    "tree": lambda sig, q, d, place, k: sigtree.knn(q, sigtree.build(d, place), k, place),
}


@dataclass
class LinkResult:
    """``knn`` (qid, oid, sim, rnk), ``match`` (qid, oid, sim, stage; None without matching) and accuracy of the final ranking."""

    knn: DataFrame
    match: DataFrame | None
    metrics: DataFrame


@dataclass
class LinkPipeline:
    """Split, signatures of ``m`` features, search for ``k`` neighbours, re-ranking by ``rerank`` features, stable matching.

    ``rerank`` 0 leaves the order of the search, None takes whole signatures. Traces are (oid, t, pid, x, y); ``run`` takes one trace and
    splits it, or two traces.
    """

    m: int | None = 10
    k: int = 5
    scheme: str = "tfidf"
    scope: str = "own"
    search: str = "inverted"
    rerank: int | None = 0
    match: bool = False
    split: Callable[[DataFrame], DataFrame] = field(default=P.interleaved)

    def run(self, q: DataFrame, d: DataFrame | None = None) -> LinkResult:
        trace = self.split(q) if d is None else P.two_sources(q, d)
        counted = materialise(W.counts(trace), "counts")
        whole = W.weigh(counted, self.scheme, self.scope)
        sig = W.cut(whole, self.m)
        knn = SEARCHES[self.search](sig, *L.sides(sig), S.locations(trace), self.k).select("qid", "oid", *(["sim"] if self.search != "euclid" else [(1 - F.col("dist") ** 2 / 2).alias("sim")]), "rnk")
        match = None
        if self.rerank != 0:
            knn = refine.rerank(knn, *L.sides(W.cut(whole, self.rerank)))
        if self.match:
            match = refine.stable_match(knn, knn)
            knn = refine.match_ranking(knn, match)
        queries = counted.where("side = 'Q'").select(F.col("oid").alias("qid")).distinct()
        return LinkResult(knn, match, M.acc_at(knn, queries, list(range(1, self.k + 1))))


class SignatureEstimator(Estimator):
    """Learns the rarity of places from traces; the model weighs traces by it."""

    def __init__(self, m: int | None = 10):
        super().__init__()
        self.m = m

    def _fit(self, dataset: DataFrame) -> SignatureModel:
        counted = W.counts(dataset.withColumn("side", F.lit("D")))
        return SignatureModel(materialise(W.idf(counted, "candidate"), "rarity"), self.m)


class SignatureModel(Model):
    """Signatures ``side, oid, fid, w`` of traces (with or without a side) by frozen rarity; places never learned have no weight."""

    def __init__(self, rarity: DataFrame, m: int | None):
        super().__init__()
        self.rarity, self.m = rarity, m

    def _transform(self, dataset: DataFrame) -> DataFrame:
        sided = dataset if "side" in dataset.columns else dataset.withColumn("side", F.lit("Q"))
        weighed = W.tf(W.counts(sided)).join(self.rarity.where("idf > 0"), "fid").select("side", "oid", "fid", (F.col("tf") * F.col("idf")).alias("w"))
        return W.cut(W.l2(weighed), self.m)
