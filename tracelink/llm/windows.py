"""Substring dedup by super-k-mer partitioning.

A window is a run of consecutive words. Consecutive windows that share a minimiser (the smallest hash of the short word runs inside) travel
as one packed string to the bucket of that minimiser, where sorting finds equal windows and the smallest document that holds each. Before
anything is sent, each task decides what it can alone: of a window that several of its documents hold, only the smallest document's copy
travels, so a passage that a third of all documents share costs one packed string for each chunk of text. A bucket is opened in blocks of
bounded size; of an overfull one only the windows of the smallest documents so far are carried on, so no task holds a whole hot bucket.
"""

from __future__ import annotations

import hashlib
import tempfile
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Words, give_back, in_chunks, mix64, run_hash, shuffle_width, table

WINDOW, MINIMISER_WORDS = 13, 3
#: Bytes of text a task looks at together, and of packed text aimed at for a bucket.
CHUNK_BYTES, BUCKET_BYTES = 2 << 20, 4 << 20
#: Compressed bytes of a bucket that are opened together, and windows of an overfull bucket that a task holds before it uses a file.
BLOCK_BYTES, MOST_STANDING = 4 << 20, 2_000_000
#: Packed text a byte of input, about: a super-k-mer repeats the twelve words it shares with the next one.
PACKING = 3
LAST = np.iinfo(np.int64).max
#: Columns that the operator adds.
OWN = ("n_words", "n_removed")


def repeated(h: np.ndarray, at: np.ndarray, owner: np.ndarray, width: int) -> np.ndarray:
    """Which windows (starting at word ``at``, of document ``owner``) also start in a smaller owner. ``owner`` must not fall.

    Windows are sorted by a 64-bit hash; neighbours of equal hash are compared word by word (64 bits each), and the rare windows that share
    a hash without being equal are told apart by their words.
    """
    flagged = np.zeros(len(at), dtype=bool)
    if len(at) < 2:
        return flagged
    sums = run_hash(h, width, 11)[at]
    order = np.argsort(sums, kind="stable")
    s = sums[order]
    same = s[1:] == s[:-1]
    head = np.flatnonzero(np.concatenate([[True], ~same]))
    first = np.repeat(order[head], np.diff(np.append(head, len(s))))
    twins = np.flatnonzero(first != order)
    a, b = at[first[twins]], at[order[twins]]
    equal = np.ones(len(twins), dtype=bool)
    for j in range(width):
        equal &= h[a + j] == h[b + j]
    flagged[order[twins]] = owner[order[twins]] > owner[first[twins]]
    if not equal.all():
        for value in np.unique(s[twins[~equal]]):
            seen: dict[bytes, int] = {}
            for i in order[np.searchsorted(s, value, "left") : np.searchsorted(s, value, "right")]:
                low = seen.setdefault(h[at[i] : at[i] + width].tobytes(), owner[i])
                flagged[i] = owner[i] > low
    return flagged


def _sliding_least(x: np.ndarray, width: int) -> np.ndarray:
    n, span = len(x) - width + 1, 1
    while span * 2 <= width:
        x = np.minimum(x[: len(x) - span], x[span:])
        span *= 2
    return np.minimum(x[:n], x[width - span : width - span + n])


def _window_starts(words: Words, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Word places at which a window starts, and the text each is in."""
    counts = np.maximum(np.diff(words.first) - (width - 1), 0)
    text = np.repeat(np.arange(len(counts)), counts)
    at = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts) + words.first[text]
    return at, text


def _spans(at: np.ndarray, breaks: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """First window and covered end of each run of consecutive places; ``breaks`` marks where a run must end."""
    if not len(at):
        return at, at
    cut = np.flatnonzero((np.diff(at) != 1) | breaks[1:])
    return np.concatenate([[0], cut + 1]), np.append(cut, len(at) - 1)


PACKED = "bucket int, n int, meta binary, body binary"
PACKED_ARROW = pa.schema([("bucket", pa.int32()), ("n", pa.int32()), ("meta", pa.binary()), ("body", pa.binary())])


def _pack_meta(ids: np.ndarray, keys: np.ndarray, a: np.ndarray, b: np.ndarray) -> bytes:
    """Ids (as differences), text keys, word places and lengths of the entries of a block, compressed together."""
    return zstandard.ZstdCompressor(level=1).compress(np.diff(ids, prepend=0).tobytes() + keys.tobytes() + a.astype(np.int32).tobytes() + b.astype(np.int32).tobytes())


def _unpack_meta(meta: bytes, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    raw = zstandard.ZstdDecompressor().decompress(meta)
    wide, narrow = np.frombuffer(raw[: 16 * n], dtype=np.int64), np.frombuffer(raw[16 * n :], dtype=np.int32)
    return np.cumsum(wide[:n]), wide[n:], narrow[:n], narrow[n:]


def _packer(buckets: int, width: int):
    def chunk(ids: np.ndarray, keys: np.ndarray, texts: list[bytes]) -> Iterator[dict]:
        order = np.argsort(ids, kind="stable")
        ids, keys, texts = ids[order], keys[order], [texts[i] for i in order]
        words = Words(texts)
        at, text = _window_starts(words, width)
        if not len(at):
            return
        known = repeated(words.hash, at, ids[text], width)
        if known.any():
            first, last = _spans(at[known], np.diff(text[known], prepend=text[known][:1]) != 0, width)
            t = text[known][first]
            yield {"bucket": int(mix64(np.array([ids[0]], dtype=np.int64).view(np.uint64))[0] % np.uint64(buckets)), "n": len(t), "meta": _pack_meta(ids[t], keys[t], at[known][first] - words.first[t], at[known][last] + width - words.first[t]), "body": None}
        send, text = at[~known], text[~known]
        if not len(send):
            return
        short = run_hash(words.hash, MINIMISER_WORDS, 7)
        least = _sliding_least(short, width - MINIMISER_WORDS + 1)[send]
        first, last = _spans(send, (np.diff(least, prepend=least[:1]) != 0) | (np.diff(text, prepend=text[:1]) != 0), width)
        bucket = (mix64(least[first]) % np.uint64(buckets)).astype(np.int64)
        by = np.argsort(bucket, kind="stable")
        first, last, bucket = first[by], last[by], bucket[by]
        begin, stop = words.start[send[first]], words.end[send[last] + width - 1]
        raw, t = words.raw, text[first]
        pieces = [raw[i:j] for i, j in zip(begin.tolist(), stop.tolist(), strict=True)]
        a, b = send[first] - words.first[t], stop - begin
        heads = np.flatnonzero(np.diff(bucket, prepend=-1))
        press = zstandard.ZstdCompressor(level=1)
        for i, j in zip(heads.tolist(), [*heads[1:].tolist(), len(bucket)], strict=True):
            yield {"bucket": int(bucket[i]), "n": j - i, "meta": _pack_meta(ids[t[i:j]], keys[t[i:j]], a[i:j], b[i:j]), "body": press.compress(b" ".join(pieces[i:j]))}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in in_chunks(batch, pc.binary_length(batch.column(2)).to_pylist(), CHUNK_BYTES):
                some = batch.slice(part.start, part.stop - part.start)
                texts = some.column(2).cast(pa.binary()).to_pylist()
                if rows := list(chunk(some.column(0).to_numpy(), some.column(1).to_numpy(), texts)):
                    yield pa.RecordBatch.from_pylist(rows, schema=PACKED_ARROW)
        give_back()

    return run


Entries = tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]


def _entries(df: pd.DataFrame) -> Entries:
    """Ids, text keys, word places and last column of the entries of packed rows."""
    parts = [_unpack_meta(m, n) for m, n in zip(df["meta"], df["n"], strict=True)]
    ids, keys, a, b = (np.concatenate(x) for x in zip(*parts, strict=True))
    return ids, keys, a, b


def _shown(ids, keys, a, b) -> pd.DataFrame:
    return pd.DataFrame({"id": ids, "key": keys, "a": np.asarray(a, dtype=np.int32), "b": np.asarray(b, dtype=np.int32)})


def _opened(df: pd.DataFrame, width: int) -> tuple[Words, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Words of packed rows; id, key and place of each window, and where it starts among the words."""
    ids, keys, a, lengths = _entries(df)
    loose = zstandard.ZstdDecompressor()
    words = Words.of_joined(b" ".join(loose.decompress(x) for x in df["body"]), lengths)
    at, piece = _window_starts(words, width)
    return words, ids[piece], keys[piece], a[piece] + at - words.first[piece], at, piece


class _Standing:
    """Windows of an overfull bucket that no smaller document had so far: their digest (128 bits), document and place.

    Blocks come one after the other; of a window only the entries of its smallest document stay, so a passage that very many documents share
    stays as one entry. Where over ``limit`` entries are left, all are dealt by digest to parts of a file, each of which is settled alone.
    """

    PARTS = 64

    def __init__(self, width: int, limit: int):
        self.width, self.limit, self.rows, self.files = width, limit, np.zeros((5, 0), dtype=np.int64), None

    def _settled(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Entries of each digest's smallest document, and the others."""
        rows = rows[:, np.lexsort((rows[2], rows[1], rows[0]))]
        fresh = np.ones(rows.shape[1], dtype=bool)
        fresh[1:] = (rows[0, 1:] != rows[0, :-1]) | (rows[1, 1:] != rows[1, :-1])
        heads = np.flatnonzero(fresh)
        least = np.repeat(rows[2, heads], np.diff(np.append(heads, rows.shape[1])))
        return rows[:, rows[2] == least], rows[:, rows[2] != least]

    def _spans(self, rows: np.ndarray) -> pd.DataFrame:
        ids, keys, at = rows[2:, np.lexsort((rows[4], rows[3], rows[2]))]
        breaks = (np.diff(ids, prepend=ids[:1]) != 0) | (np.diff(keys, prepend=keys[:1]) != 0)
        first, last = _spans(at, breaks, self.width)
        return _shown(ids[first], keys[first], at[first], at[last] + self.width)

    def add(self, block: pd.DataFrame) -> Iterator[pd.DataFrame]:
        words, ids, keys, places, at, _ = _opened(block, self.width)
        sums = [run_hash(words.hash, self.width, seed)[at].view(np.int64) for seed in (11, 23)]
        self.rows, gone = self._settled(np.concatenate([self.rows, np.stack([*sums, ids, keys, places])], axis=1))
        if gone.shape[1]:
            yield self._spans(gone)
        if self.rows.shape[1] > self.limit:
            self.files = self.files or [tempfile.TemporaryFile() for _ in range(self.PARTS)]
            part = self.rows[0] & (self.PARTS - 1)
            for i, file in enumerate(self.files):
                file.write(np.ascontiguousarray(self.rows[:, part == i].T).tobytes())
            self.rows = self.rows[:, :0]

    def end(self) -> Iterator[pd.DataFrame]:
        part = self.rows[0] & (self.PARTS - 1)
        for i, file in enumerate(self.files or []):
            file.seek(0)
            kept = np.frombuffer(file.read(), dtype=np.int64).reshape(-1, 5).T
            file.close()
            _, gone = self._settled(np.concatenate([kept, self.rows[:, part == i]], axis=1))
            if gone.shape[1]:
                yield self._spans(gone)


def _unpacker(width: int, block_bytes: int, most_standing: int):
    def decided(block: pd.DataFrame) -> Iterator[pd.DataFrame]:
        words, ids, keys, places, at, piece = _opened(block, width)
        order = np.argsort(ids, kind="stable")
        flagged = np.zeros(len(at), dtype=bool)
        flagged[order] = repeated(words.hash, at[order], ids[order], width)
        at, piece, ids, keys, places = at[flagged], piece[flagged], ids[flagged], keys[flagged], places[flagged]
        if len(at):
            first, last = _spans(at, np.diff(piece, prepend=piece[:1]) != 0, width)
            yield _shown(ids[first], keys[first], places[first], places[last] + width)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        """A bucket in blocks of bounded size: one block is the rule; of an overfull bucket, what stands is carried from block to block."""
        held, size, standing = [], 0, None
        for group in batches:
            ready, packed = group[group["body"].isna()], group[group["body"].notna()]
            if len(ready):
                yield _shown(*_entries(ready))
            for part in in_chunks(packed, packed["body"].map(len).tolist(), block_bytes):
                block = packed.iloc[part]
                held.append(block)
                size += int(block["body"].map(len).sum())
                if size >= block_bytes:
                    standing = standing or _Standing(width, most_standing)
                    yield from standing.add(pd.concat(held))
                    held, size = [], 0
        if standing:
            if held:
                yield from standing.add(pd.concat(held))
            yield from standing.end()
        elif held:
            yield from decided(pd.concat(held))

    return run


def _keyed(docs: DataFrame, text: str, apart: bool) -> DataFrame:
    """``text, id`` (null last), ``key``, which tells rows of equal id apart (0 where ids are unique), and ``row`` with the other columns."""
    body = F.coalesce(F.col(f"`{text}`").cast("string"), F.lit(""))
    key = F.xxhash64(body) if apart else F.lit(0).cast("long")
    others = [F.col(f"`{c}`") for c in docs.columns if c not in (text, *OWN)]
    return docs.select(body.alias("text"), F.coalesce(F.col("doc_id").cast("long"), F.lit(int(LAST))).alias("id"), key.alias("key"), F.struct(*others).alias("row"))


def _repeats_ids(docs: DataFrame) -> bool:
    return not docs.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").isEmpty()


def repeated_spans(docs: DataFrame, text: str = "text", width: int = WINDOW, apart: bool = True) -> DataFrame:
    """``id, key, a, b``: word ranges [a, b) of documents, covered by windows that a document with a smaller id also has.

    ``key`` is the text's hash where ``apart`` (documents that share an id are told apart by it), else 0; a null doc_id is larger than any other.
    """
    spark = docs.sparkSession
    keyed = _keyed(docs, text, apart)
    size = keyed.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = int(min(1 << 30, max(4 * shuffle_width(spark), PACKING * size // BUCKET_BYTES)))
    packed = keyed.select("id", "key", "text").mapInArrow(_packer(buckets, width), PACKED)
    return packed.groupBy("bucket").applyInPandas(_unpacker(width, BLOCK_BYTES, MOST_STANDING), "id long, key long, a int, b int")


def drop_repeats(docs: DataFrame, text: str = "text", width: int = WINDOW) -> DataFrame:
    """Remove every word covered by a window of ``width`` words that also starts in a document with a smaller doc_id.

    Returns the columns of ``docs`` with ``text`` replaced by the kept words joined by one blank, and ``n_words``, ``n_removed`` (own
    columns of these names are replaced, columns of any other name pass through). Windows are judged on the input. Null texts become empty;
    every row stays, repeated rows too; rows of equal doc_id do not count as smaller than each other, null ids are larger than any other;
    an empty table gives no rows.
    """
    apart = _repeats_ids(docs)
    spans = repeated_spans(docs, text, width, apart).groupBy(F.col("id").alias("s_id"), F.col("key").alias("s_key")).agg(F.collect_list(F.struct("a", "b")).alias("s_spans"))
    keyed = _keyed(docs, text, apart)
    joined = keyed.join(spans, (F.col("id") == F.col("s_id")) & (F.col("key") == F.col("s_key")), "left")
    shaped = joined.select("text", F.col("s_spans.a").alias("a"), F.col("s_spans.b").alias("b"), "row")
    kept = shaped.withColumn("k", F.arrow_udf(_kept, "text string, n_words long, n_removed long")("text", "a", "b")).select("row", "k")
    return kept.select(*[F.col("k.text").alias(c) if c == text else F.col("row")[c].alias(c) for c in docs.columns if c not in OWN], *[F.col("k")[c].alias(c) for c in OWN])


KEPT = pa.struct([("text", pa.string()), ("n_words", pa.int64()), ("n_removed", pa.int64())])


def _kept(batches: Iterator[tuple[pa.Array, pa.Array, pa.Array]]) -> Iterator[pa.Array]:
    """Words of texts that no range [a, b) covers, joined by one blank; only a part of a batch is opened at a time."""
    for texts, a, b in batches:
        done = []
        for part in in_chunks(texts, pc.binary_length(texts).to_pylist(), CHUNK_BYTES):
            n = part.stop - part.start
            out, total, gone = [], [], []
            for t, starts, ends in zip(texts.slice(part.start, n).cast(pa.binary()).to_pylist(), a.slice(part.start, n), b.slice(part.start, n), strict=True):
                words = t.split()
                total.append(len(words))
                if starts.is_valid:
                    edge = np.zeros(len(words) + 1, dtype=np.int32)
                    np.add.at(edge, starts.values.to_numpy(), 1)
                    np.add.at(edge, ends.values.to_numpy(), -1)
                    words = [words[i] for i in np.flatnonzero(np.cumsum(edge[:-1]) == 0).tolist()]
                gone.append(total[-1] - len(words))
                out.append(b" ".join(words))
            done.append(pa.StructArray.from_arrays([pa.array(out, type=pa.binary()).cast(pa.string()), pa.array(total, type=pa.int64()), pa.array(gone, type=pa.int64())], fields=list(KEPT)))
        yield pa.concat_arrays(done) if done else pa.array([], type=KEPT)
    give_back()


def brute_force(docs: list[tuple[int, str | None]], width: int = WINDOW) -> dict[int, tuple[int, int, str]]:
    """Reference for tests: doc_id -> words, removed words, digest of the kept ones."""
    low: dict[tuple, int] = {}
    split = {i: (t or "").encode().split() for i, t in docs}
    for i, w in split.items():
        for k in range(len(w) - width + 1):
            key = tuple(w[k : k + width])
            low[key] = min(low.get(key, i), i)
    out = {}
    for i, w in split.items():
        gone = {k + j for k in range(len(w) - width + 1) if low[tuple(w[k : k + width])] < i for j in range(width)}
        kept = b" ".join(x for k, x in enumerate(w) if k not in gone)
        out[i] = (len(w), len(gone), hashlib.sha256(kept).hexdigest())
    return out


def op8_windows(spark, sf_dir: str) -> DataFrame:
    kept = drop_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return kept.select("doc_id", "n_words", "n_removed", F.sha2("text", 256).alias("kept_sha256"))


#: Words, windows and their smallest document in SQL, for DuckDB. ``docs`` needs doc_id and text.
def repeats_sql(docs: str, prefix: str = "sd") -> str:
    return f"""
{prefix}_words AS (SELECT doc_id, text, list_filter(string_split_regex(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda w: w <> '') AS w FROM {docs}),
{prefix}_win AS (SELECT doc_id, k, md5(array_to_string(w[k:k+12], ' ')) AS h FROM (SELECT doc_id, w, unnest(range(1, len(w) - 11)) AS k FROM {prefix}_words)),
{prefix}_low AS (SELECT h, min(doc_id) AS low FROM {prefix}_win GROUP BY h),
{prefix}_gone AS (SELECT doc_id, list(DISTINCT p) AS gone FROM (SELECT doc_id, unnest(range(k, k + 13)) AS p FROM {prefix}_win JOIN {prefix}_low USING (h) WHERE low < doc_id) GROUP BY doc_id),
{prefix}_kept AS (SELECT x.doc_id, len(w) AS n_words, coalesce(len(gone), 0) AS n_removed,
  coalesce(array_to_string(list_filter(w, lambda v, i: gone IS NULL OR NOT list_contains(gone, i)), ' '), '') AS kept FROM {prefix}_words x LEFT JOIN {prefix}_gone g USING (doc_id))"""


OP8_SQL = "WITH " + repeats_sql("documents") + " SELECT doc_id, n_words, n_removed, sha256(kept) AS kept_sha256 FROM sd_kept"
