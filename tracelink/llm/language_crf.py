"""Language identification of words in code-switched text by a linear-chain conditional random field.

Words are observed through affixes, inner character n-grams and a lexicon learned from the sample; transitions between labels of
neighbouring words are learned too. Forward-backward gives each word's distribution over languages; a document's language is the one with
the largest mean over its words. Forward-backward runs over many texts at once, one vectorised step a word place.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drawn, give_back, held_out, in_chunks, table

#: Bound of the training sample: documents drawn by hash, whole texts, dealt to the languages in turn.
SAMPLE_DOCS = 600
#: Hashed feature columns, lexicon words kept for a language, passes over the sample, learning rate, weight decay.
COLUMN_BITS, LEXICON, PASSES, RATE, DECAY = 15, 4000, 5, 0.1, 1e-4
COLUMNS = 1 << COLUMN_BITS
#: Texts of about this many bytes go through forward-backward together; word scores held by a worker; words scored at once.
GROUP_BYTES, CACHE_WORDS, WORDS_AT_ONCE = 1 << 20, 100_000, 8192
#: Code-switched texts made for training, as a share of the sample, and words of each of their parts at most.
SWITCHED, SWITCHED_WORDS = 0.5, 12
#: A longer run of letters (scripts without blanks) is several words of this many letters.
LONGEST_WORD = 64
UNKNOWN = "und"

_WORD = re.compile(r"[^\W\d_]{1,%d}" % LONGEST_WORD)


def words_of(text: str | None) -> list[str]:
    """Lower-cased runs of letters, none left out; a run of over LONGEST_WORD letters is cut into several words."""
    return _WORD.findall((text or "").lower())


#: Lengths of the inner n-grams and of the longest affix; odd multipliers that spread the characters of a gram over the hashed columns.
INNER, LONGEST_AFFIX = (2, 3), 4
_SPREAD = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93], dtype=np.uint64)


def grams(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Beginnings, endings and inner n-grams of several words at once: the word each is of, and its hashed column.

    A gram's column follows from its characters and its kind (inner, beginning or ending, and length) alone.
    """
    lengths = np.fromiter(map(len, words), dtype=np.int64, count=len(words))
    codes = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), dtype=np.uint32).astype(np.uint64)
    ends = np.cumsum(lengths)
    starts = ends - lengths
    word = np.repeat(np.arange(len(words)), lengths)
    owners, columns = [], []

    def add(at: np.ndarray, owner: np.ndarray, n: int, kind: int) -> None:
        h = np.full(len(at), kind * 0x27D4EB2F165667C5 & (1 << 64) - 1, dtype=np.uint64)
        for i in range(n):
            h = (h ^ codes[at + i]) * _SPREAD[i]
            h ^= h >> np.uint64(29)
        owners.append(owner)
        columns.append((h * _SPREAD[0] >> np.uint64(64 - COLUMN_BITS)).astype(np.int64))

    left = ends[word] - np.arange(len(codes))
    for n in INNER:
        at = np.flatnonzero(left >= n)
        add(at, word[at], n, n)
    for n in range(1, LONGEST_AFFIX + 1):
        held = np.flatnonzero(lengths >= n)
        add(starts[held], held, n, 16 + n)
        add(ends[held] - n, held, n, 32 + n)
    return np.concatenate(owners), np.concatenate(columns)


@dataclass
class LanguageModel:
    languages: list[str]
    weights: np.ndarray
    step: np.ndarray
    start: np.ndarray
    lexicon: dict[str, int]
    _cache: dict[str, int] = field(default_factory=dict)
    _rows: np.ndarray | None = None

    def columns(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Feature columns of several words, and the word each is of: hashed grams, and the language of a word in the lexicon."""
        owner, column = grams(words)
        known = [(i, COLUMNS + y) for i, y in enumerate(map(self.lexicon.get, words)) if y is not None]
        if known:
            more = np.array(known, dtype=np.int64)
            owner, column = np.concatenate([owner, more[:, 0]]), np.concatenate([column, more[:, 1]])
        return owner, column

    def scores(self, owner: np.ndarray, column: np.ndarray, n: int) -> np.ndarray:
        """Scores (n words, languages) of words given by their columns."""
        picked = self.weights[column]
        return np.stack([np.bincount(owner, weights=picked[:, y], minlength=n) for y in range(len(self.languages))], axis=1)

    def emissions(self, words: list[str]) -> np.ndarray:
        """Scores (words, languages); each distinct word is scored once."""
        cache = self._cache
        if len(cache) > CACHE_WORDS:
            cache.clear()
        fresh = list(set(words).difference(cache))
        for i in range(0, len(fresh), WORDS_AT_ONCE):
            part = fresh[i : i + WORDS_AT_ONCE]
            need = len(cache) + len(part)
            if self._rows is None or need > len(self._rows):
                rows = np.zeros((need + need // 2, len(self.languages)), dtype=np.float32)
                if self._rows is not None:
                    rows[: len(cache)] = self._rows[: len(cache)]
                self._rows = rows
            self._rows[len(cache) : need] = self.scores(*self.columns(part), len(part))
            cache.update(zip(part, range(len(cache), need), strict=True))
        return self._rows[np.fromiter(map(cache.__getitem__, words), dtype=np.int64, count=len(words))]


def forward_backward(scores: np.ndarray, lengths: np.ndarray, step: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Marginals (words, labels) of texts laid end to end, and the expected transition counts.

    Texts are taken longest first, so that at each place the texts that still go on are a prefix of the block.
    """
    n_labels = scores.shape[1]
    order = np.argsort(-lengths, kind="stable")
    long = lengths[order]
    offset = (np.cumsum(lengths) - lengths)[order]
    live = np.searchsorted(-long, -np.arange(int(long[0]) if len(long) else 0), side="left")
    first = np.cumsum(live) - live
    total = int(live.sum())
    place = np.repeat(np.arange(len(live)), live)
    rank = np.arange(total) - np.repeat(first, live)
    at = offset[rank] + place
    local = scores[at].astype(np.float64)
    local -= local.max(axis=1, keepdims=True)
    np.exp(local, out=local)
    hop = np.exp(step.astype(np.float64))
    alpha, beta = np.empty((total, n_labels)), np.ones((total, n_labels))
    pairs = np.zeros((n_labels, n_labels))
    for t, (i, n) in enumerate(zip(first.tolist(), live.tolist(), strict=True)):
        a = np.exp(start.astype(np.float64)) * local[i : i + n] if t == 0 else (alpha[first[t - 1] : first[t - 1] + n] @ hop) * local[i : i + n]
        alpha[i : i + n] = a / a.sum(axis=1, keepdims=True)
    for t in range(len(live) - 2, -1, -1):
        i, j, n = first[t], first[t + 1], live[t + 1]
        ahead = beta[j : j + n] * local[j : j + n]
        b = ahead @ hop.T
        norm = b.sum(axis=1, keepdims=True)
        beta[i : i + n] = b / norm
        before = alpha[i : i + n]
        mass = (before * b).sum(axis=1, keepdims=True)
        pairs += hop * ((before / mass).T @ ahead)
    gamma = alpha * beta
    gamma /= gamma.sum(axis=1, keepdims=True)
    out = np.empty_like(gamma)
    out[at] = gamma
    return out, pairs


def _switched(coded: list[np.ndarray], truths: list[np.ndarray], n: int) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """Word numbers and labels of ``n`` texts that are joined from two to four runs of words of sampled texts."""
    rng, words, labels = np.random.default_rng(9), [], []
    for _ in range(n):
        a, b = [], []
        for i in rng.integers(0, len(coded), rng.integers(2, 5)).tolist():
            size = int(rng.integers(1, SWITCHED_WORDS + 1))
            at = int(rng.integers(0, max(1, len(coded[i]) - size + 1)))
            a.append(coded[i][at : at + size])
            b.append(truths[i][at : at + size])
        words.append(np.concatenate(a))
        labels.append(np.concatenate(b))
    return words, labels


def fit(texts: list[str | None], labels: list[str], passes: int = PASSES) -> LanguageModel:
    """Train on a bounded list of labelled texts.

    Every word of a text carries the text's label. Code-switched texts are made beside them by joining runs of words of several languages,
    so that transitions between languages are learned from positive examples too.
    """
    languages = sorted(set(labels))
    index = {x: i for i, x in enumerate(languages)}
    k = len(languages)
    model = LanguageModel(languages, np.zeros((COLUMNS + k, k), dtype=np.float32), np.zeros((k, k), dtype=np.float32), np.zeros(k, dtype=np.float32), {})
    split = [words_of(t) for t in texts]
    pick = [i for i, w in enumerate(split) if w]
    if not pick or k < 2:
        return model
    number: dict[str, int] = {}
    coded = [np.fromiter((number.setdefault(w, len(number)) for w in split[i]), dtype=np.int64) for i in pick]
    truths = [np.full(len(c), index[labels[i]]) for c, i in zip(coded, pick, strict=True)]
    seen = np.zeros((len(number), k))
    for ids, y in zip(coded, truths, strict=True):
        np.add.at(seen, (ids, y), 1)
    mixed = _switched(coded, truths, int(SWITCHED * len(coded)))
    coded, truths = coded + mixed[0], truths + mixed[1]
    names = list(number)
    share = seen / np.maximum(seen.sum(axis=1, keepdims=True), 1)
    for y in range(k):
        ranked = sorted((i for i in np.flatnonzero((share[:, y] > 0.9) & (seen[:, y] >= 3)).tolist()), key=lambda i: (-seen[i, y], names[i]))
        model.lexicon |= {names[i]: y for i in ranked[:LEXICON]}
    owner, flat = model.columns(names)
    squares = {"w": np.full((COLUMNS + k, k), 1e-8), "s": np.full((k, k), 1e-8), "b": np.full(k, 1e-8)}
    deal = np.random.default_rng(5).permutation(len(coded))
    for _ in range(passes):
        for part in np.array_split(deal, max(1, len(deal) // 96)):
            lengths = np.array([len(coded[i]) for i in part])
            ids = np.concatenate([coded[i] for i in part])
            used, back = np.unique(ids, return_inverse=True)
            word_scores = model.scores(owner, flat, len(names))[used]
            gamma, pairs = forward_backward(word_scores[back], lengths, model.step, model.start)
            truth = np.concatenate([truths[i] for i in part])
            wrong = -gamma
            wrong[np.arange(len(truth)), truth] += 1
            by_word = np.zeros((len(names), k))
            for y in range(k):
                by_word[:, y] = np.bincount(ids, weights=wrong[:, y], minlength=len(names))
            g = np.zeros((COLUMNS + k, k))
            for y in range(k):
                g[:, y] = np.bincount(flat, weights=by_word[owner, y], minlength=COLUMNS + k)
            heads_at = np.cumsum(lengths) - lengths
            inside = np.setdiff1d(np.arange(len(truth)), heads_at)
            steps = np.zeros((k, k))
            np.add.at(steps, (truth[inside - 1], truth[inside]), 1)
            begin = np.bincount(truth[heads_at], minlength=k) - gamma[heads_at].sum(axis=0)
            for key, grad, target in (("w", g, model.weights), ("s", steps - pairs, model.step), ("b", begin, model.start)):
                grad = grad / lengths.sum() - DECAY * target
                squares[key] += grad**2
                target += (RATE * grad / np.sqrt(squares[key])).astype(np.float32)
    return model


def training_sample(docs: DataFrame, bound: int = SAMPLE_DOCS) -> pd.DataFrame:
    """At most ``bound`` rows ``doc_id, text, lang`` with a language, outside the held-out fold, drawn by hash and dealt to the languages in turn.

    Of rows that share an id (null ids too) and a language, only the one of the smallest text hash is learned from.
    """
    usable = docs.where(F.col("lang").isNotNull() & ~held_out(F.col("doc_id")))
    chosen = drawn(usable.select("doc_id", "lang"), "lang", "doc_id", bound, 31).select(F.col("doc_id").alias("c_id"), F.col("lang").alias("c_lang"))
    # ``bound`` rows at most
    rows = usable.select("doc_id", "text", "lang").join(F.broadcast(chosen), F.col("doc_id").eqNullSafe(F.col("c_id")) & (F.col("lang") == F.col("c_lang")))
    text = F.struct(F.xxhash64("text").alias("h"), F.col("text"))
    rows = rows.groupBy("doc_id", "lang").agg(F.min(text).alias("t")).select("doc_id", F.col("t.text").alias("text"), "lang").toPandas()
    return rows.sort_values(["lang", "doc_id"], kind="stable").reset_index(drop=True)


GUESS = pa.struct([("lang", pa.string()), ("score", pa.float64()), ("n_words", pa.int64()), ("n_switches", pa.int64())])


def identified(docs: DataFrame, model: LanguageModel, text: str = "text") -> DataFrame:
    """Add ``lang_pred``, ``lang_score``, ``lang_words`` and ``lang_switches`` to every row (own columns of these names are replaced).

    ``lang_pred`` is ``und`` with score 0 where the text is null or has no letter, or where nothing could be learned; otherwise the language
    with the largest mean marginal over the text's words, ties to the first in order of name; the score is that mean. ``lang_words`` counts
    words, ``lang_switches`` the places where the likeliest label of a word differs from that of the word before. Equal texts get equal
    values wherever they stand, repeated rows stay, an empty table gives no rows, and texts of any length are read to their end.
    """
    held = docs.sparkSession.sparkContext.broadcast(model)  # COLUMNS x languages weights and LEXICON words a language

    def guess(texts: list[str]) -> list[tuple]:
        model = held.value
        split = [words_of(t) for t in texts]
        out = [(UNKNOWN, 0.0, len(w), 0) for w in split]
        pick = [i for i, w in enumerate(split) if w]
        if not pick or not model.languages:
            return out
        lengths = np.array([len(split[i]) for i in pick])
        e = model.emissions([w for i in pick for w in split[i]])
        gamma, _ = forward_backward(e, lengths, model.step, model.start)
        heads = np.cumsum(lengths) - lengths
        mean = np.add.reduceat(gamma, heads) / lengths[:, None]
        label = gamma.argmax(axis=1)
        change = np.diff(label, prepend=label[:1]) != 0
        change[heads] = False
        turns = np.add.reduceat(change.astype(np.int64), heads)
        for i, b, m, n, c in zip(pick, mean.argmax(axis=1).tolist(), mean.max(axis=1).tolist(), lengths.tolist(), turns.tolist(), strict=True):
            out[i] = model.languages[b], min(1.0, m), n, c
        return out

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for batch in batches:
            sizes = pc.binary_length(batch).fill_null(0).to_numpy(zero_copy_only=False)
            # texts of like length go together: forward-backward takes as many steps as a group's longest text has words
            order = np.argsort(sizes, kind="stable")
            found: list[tuple] = [None] * len(batch)
            for part in in_chunks(order, sizes[order].tolist(), GROUP_BYTES):
                rows = order[part]
                for i, g in zip(rows.tolist(), guess(batch.take(pa.array(rows)).to_pylist()), strict=True):
                    found[i] = g
            columns = list(zip(*found, strict=True)) or [()] * len(GUESS)
            yield pa.StructArray.from_arrays([pa.array(c, type=f.type) for c, f in zip(columns, GUESS, strict=True)], fields=list(GUESS))
        give_back()

    # declared nondeterministic so that a filter on the result is not pushed below it, which would run it twice
    guessed = F.arrow_udf(run, "lang string, score double, n_words long, n_switches long").asNondeterministic()
    own = {"lang_pred": "lang", "lang_score": "score", "lang_words": "n_words", "lang_switches": "n_switches"}
    kept = [F.col(f"`{c}`") for c in docs.columns if c not in own]
    rows = docs.select(F.struct(*kept).alias("row"), guessed(F.col(f"`{text}`").cast("string")).alias("guess"))
    return rows.select("row.*", *[F.col("guess")[f].alias(c) for c, f in own.items()])


def word_languages(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """``doc_id, word_no, word, lang, score`` for every word: the labelling of code-switched text."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        model = held.value
        for batch in batches:
            for i, t in zip(batch["doc_id"].tolist(), batch["text"].tolist(), strict=True):
                words = words_of(t)
                if words and model.languages:
                    gamma, _ = forward_backward(model.emissions(words), np.array([len(words)]), model.step, model.start)
                    best = gamma.argmax(axis=1)
                    yield pd.DataFrame({"doc_id": i, "word_no": np.arange(len(words)), "word": words, "lang": [model.languages[b] for b in best], "score": gamma.max(axis=1)})

    return docs.where("doc_id is not null").select("doc_id", "text").mapInPandas(run, "doc_id long, word_no int, word string, lang string, score double")


def train(docs: DataFrame) -> LanguageModel:
    sample = training_sample(docs)
    return fit(sample["text"].tolist(), sample["lang"].tolist())


def op4_language_crf(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    out = identified(docs.select("doc_id", "text"), train(docs))
    shown = F.col("lang_pred"), F.col("lang_score").alias("score"), F.col("lang_words").alias("n_words"), F.col("lang_switches").alias("n_switches")
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), *shown)
