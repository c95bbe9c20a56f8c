"""Toxicity: a linear classifier with a counterfactual penalty.

Labelled documents train a logistic model over words and word beginnings. For each training sentence that names a group, a twin is made
in which the group's name is swapped for another of its kind; differences between the scores of the two are penalised, so that neutral
mentions of a group do not move the score. Terms that no sampled sentence has are swapped into neutral carrier sentences instead.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drawn, held_out, table

#: Interchangeable names of groups, by kind, in the languages of the corpus.
IDENTITY_TERMS = {
    "gender": "women men girls boys woman man trans femmes hommes frauen männer mujeres hombres".split(),
    "faith": "muslims christians jews hindus buddhists atheists muslim christian jewish hindu buddhist musulmans chrétiens juifs muslime christen juden musulmanes cristianos judíos".split(),
    "origin": "immigrants natives africans europeans asians mexicans turks poles refugees foreigners immigrés réfugiés einwanderer flüchtlinge inmigrantes refugiados".split(),
    "orientation": "gay straight lesbian bisexual queer heterosexual homosexuels lesben lesbianas".split(),
    "colour": "black white brown schwarze weiße noirs blancs negros blancos".split(),
    "health": "disabled blind deaf autistic healthy behinderte handicapés discapacitados".split(),
}
CARRIER = "the and of in is with they people were".split()

#: Bound of the labelled sample (documents of each class), and of the features that are kept.
SAMPLE_PER_CLASS, FEATURES = 2000, 1536
#: Evidence a feature needs to be kept (normal deviate of its log odds), weight decay, and strength of the counterfactual penalty.
EVIDENCE, DECAY, FAIRNESS, STEPS = 3.5, 2e-5, 4.0, 400
THRESHOLD = 0.3

_WORD = re.compile(r"\w+")
_PREFIXES = (4, 5, 6, 7)
#: A feature is dense where it comes at least twice and once in so many words.
DENSE_WORDS = 150
#: Weight of label 1 in training, whatever its share.
POSITIVE_WEIGHT = 0.45


def features_of(word: str) -> list[str]:
    """A lower-cased word and its beginnings (marked, so that they differ from whole words)."""
    return [word, *(f"{word[:n]}*" for n in _PREFIXES if len(word) > n)]


def words_of(text: str | None) -> Counter[str]:
    return Counter(_WORD.findall((text or "").lower()))


@dataclass
class ToxicityModel:
    """Weights of each feature: for being there, and for being dense."""

    weights: dict[str, tuple[float, float]]
    bias: float
    _known: dict[str, tuple[str, ...]] = field(default_factory=dict, repr=False)

    def logit(self, words: Counter[str]) -> float:
        known, weights = self._known, self.weights
        if len(known) > 400_000:
            known.clear()
        held: dict[str, int] = {}
        for w, n in words.items():
            hits = known.get(w)
            if hits is None:
                hits = known[w] = tuple(f for f in features_of(w) if f in weights)
            for f in hits:
                held[f] = held.get(f, 0) + n
        total = sum(words.values())
        out = self.bias
        for f in sorted(held):
            n, (there, dense) = held[f], weights[f]
            out += there + dense if n > 1 and n * DENSE_WORDS >= total else there
        return out

    def score(self, text: str | None) -> float:
        return float(1 / (1 + np.exp(-np.clip(self.logit(words_of(text)), -50, 50))))


def twin_of(words: Counter[str], swap: dict[str, str]) -> Counter[str]:
    out: Counter[str] = Counter()
    for w, n in words.items():
        out[swap.get(w, w)] += n
    return out


def swaps(shift: int) -> dict[str, str]:
    """Each term against the one ``shift`` places on among its kind."""
    return {a: terms[(i + shift) % len(terms)] for terms in IDENTITY_TERMS.values() for i, a in enumerate(terms)}


def fit(texts: list[str | None], labels: list[int], fairness: float = FAIRNESS, most: int = FEATURES) -> ToxicityModel:
    """Train on a bounded list of labelled texts. Without both labels the model is a constant at the share of label 1."""
    y = np.asarray(labels, dtype=np.float64)
    if not len(y) or y.min() == y.max():
        share = float(np.clip(y.mean(), 0.01, 0.99)) if len(y) else 0.01
        return ToxicityModel({}, float(np.log(share / (1 - share))))
    number: dict[str, int] = {}
    ids_of: dict[str, tuple[int, ...]] = {}

    def ids(words: Counter[str]) -> np.ndarray:
        """Columns of a text: twice a feature's number for being there, the next one for being dense."""
        out: list[int] = []
        times: list[int] = []
        for w, n in words.items():
            known = ids_of.get(w)
            if known is None:
                known = ids_of[w] = tuple(number.setdefault(f, len(number)) for f in features_of(w))
            out.extend(known)
            times.extend([n] * len(known))
        there, back = np.unique(np.array(out, dtype=np.int64), return_inverse=True)
        n = np.bincount(back, weights=times, minlength=len(there))
        return np.concatenate([2 * there, 2 * there[(n > 1) & (n * DENSE_WORDS >= words.total())] + 1]).astype(np.int32)

    named = {t for kind in IDENTITY_TERMS.values() for t in kind}
    shown: list[np.ndarray] = []
    naming: list[Counter[str]] = []
    for t in texts:
        words = words_of(t)
        shown.append(ids(words))
        if not named.isdisjoint(words):
            naming.append(words)
    counts = np.zeros((2 * len(number), 2))
    for feats, label in zip(shown, labels, strict=True):
        counts[feats, label] += 1
    n0, n1 = float((y == 0).sum()), float((y == 1).sum())
    often = np.flatnonzero(counts.sum(axis=1) >= 3)
    seen = counts[often] + 0.5
    odds = np.log(seen[:, 1] / (n1 + 1 - seen[:, 1])) - np.log(seen[:, 0] / (n0 + 1 - seen[:, 0]))
    error = np.sqrt(1 / seen[:, 1] + 1 / seen[:, 0] + 1 / (n1 + 1 - seen[:, 1]) + 1 / (n0 + 1 - seen[:, 0]))
    power = np.abs(odds / error)
    names = list(number)
    order = sorted((j for j in range(len(often)) if power[j] >= EVIDENCE), key=lambda j: (-power[j], names[int(often[j]) // 2], int(often[j]) % 2))[:most]
    kept = list(dict.fromkeys([int(often[j]) for j in order] + [2 * number[f] for t in sorted(named) for f in features_of(t) if f in number]))
    column = np.full(2 * len(number) + 1, -1, dtype=np.int32)
    column[kept] = np.arange(len(kept))

    def rows(many: list[np.ndarray]) -> np.ndarray:
        x = np.zeros((len(many), len(kept)), dtype=np.float32)
        for r, feats in enumerate(many):
            at = column[np.minimum(feats, len(column) - 1)]
            x[r, at[at >= 0]] = 1
        return x

    x = rows(shown)
    pairs: list[tuple[Counter[str], Counter[str]]] = []
    for shift in (1, 2):
        swap = swaps(shift)
        pairs += [(s, twin_of(s, swap)) for s in naming]
        carried = [Counter([*CARRIER, t]) for t in sorted(named)]
        pairs += [(c, twin_of(c, swap)) for c in carried] + [(c, Counter(CARRIER)) for c in carried]
    gaps = rows([ids(a) for a, _ in pairs]) - rows([ids(b) for _, b in pairs])
    gaps = gaps[np.any(gaps != 0, axis=1)]
    weight = np.where(y == 1, POSITIVE_WEIGHT / n1, (1 - POSITIVE_WEIGHT) / n0)
    weight = weight.astype(np.float32)
    w, b = np.zeros(len(kept), dtype=np.float32), np.float32(0)
    m, v = np.zeros(len(kept) + 1), np.zeros(len(kept) + 1)
    for step in range(1, STEPS + 1):
        p = 1 / (1 + np.exp(-np.clip(x @ w + b, -30, 30)))
        r = (p - y.astype(np.float32)) * weight
        g = r @ x + np.float32(DECAY) * w
        if len(gaps):
            g = g + np.float32(fairness / len(gaps)) * ((gaps @ w) @ gaps)
        full = np.append(g, r.sum())
        m, v = 0.9 * m + 0.1 * full, 0.999 * v + 0.001 * full**2
        move = (0.08 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
        w, b = w - move[:-1], b - move[-1]
    out: dict[str, list[float]] = {}
    for i, c in enumerate(kept):
        if abs(w[i]) > 1e-6:
            out.setdefault(names[c // 2], [0.0, 0.0])[c % 2] = round(float(w[i]), 9)
    return ToxicityModel({f: (a, d) for f, (a, d) in out.items()}, round(float(b), 9))


def training_sample(docs: DataFrame, labels: DataFrame, per_class: int = SAMPLE_PER_CLASS) -> pd.DataFrame:
    """Labelled documents outside the held-out fold, drawn by hash: ``doc_id, text, toxic`` in order of id.

    The rows are at most twice ``per_class``; labels are dealt in turn, and where one label has fewer than ``per_class`` documents the other
    one still gets ``per_class`` at most. A document labelled both ways counts as toxic; of rows that share an id, only the one of the
    smallest text hash is learned from; null ids and other labels are passed over.
    """
    usable = labels.select(F.col("doc_id").alias("l_id"), F.col("toxic").cast("int").alias("toxic")).where(F.col("l_id").isNotNull() & F.col("toxic").isin(0, 1) & ~held_out(F.col("l_id")))
    chosen = drawn(usable, "toxic", "l_id", 2 * per_class, 29).where(F.col("rank") <= per_class).groupBy("l_id").agg(F.max("toxic").alias("toxic"))
    # 2 * per_class ids at most
    rows = docs.select("doc_id", "text").join(F.broadcast(chosen), F.col("doc_id") == F.col("l_id"))
    text = F.struct(F.xxhash64("text").alias("h"), F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.groupBy("doc_id", "toxic").agg(F.min(text).alias("t")).select("doc_id", F.col("t.text").alias("text"), "toxic").toPandas()
    return rows.sort_values("doc_id", kind="stable").reset_index(drop=True)


def scored(docs: DataFrame, model: ToxicityModel, text: str = "text") -> DataFrame:
    """Add ``score`` (0 to 1) and ``predicted`` to every row; a null or empty text gets the score of no evidence.

    Own columns of these names are replaced and other columns pass through. Equal texts get equal scores, repeated rows stay, texts are read
    to their end, and an empty table gives no rows.
    """
    held = docs.sparkSession.sparkContext.broadcast(model)  # at most FEATURES weights and the identity terms

    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        model = held.value
        for batch in batches:
            out = [model.logit(words_of(t)) for t in batch.tolist()]
            yield pd.Series(1 / (1 + np.exp(-np.clip(np.array(out, dtype=np.float64), -50, 50))))

    score = F.pandas_udf(run, "double")
    return docs.drop("score", "predicted").withColumn("score", score(F.col(f"`{text}`").cast("string"))).withColumn("predicted", (F.col("score") >= THRESHOLD).cast("int"))


def op3_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    sample = training_sample(docs, table(spark, sf_dir, "labels"))
    model = fit(sample["text"].tolist(), sample["toxic"].tolist())
    return scored(docs, model).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")
