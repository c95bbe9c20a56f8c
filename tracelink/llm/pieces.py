"""SentencePiece encoding and decoding: an Aho-Corasick automaton over the pieces drives a single-pass Viterbi.

The automaton reads each character once; at every place the output links list all pieces that end there, longest first, and each relaxes
the best score of the place. A character that no piece covers costs ten below the worst piece and is spelled in byte pieces.
"""

from __future__ import annotations

import re
from array import array
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import give_back, in_chunks, table

#: The mark that stands for a blank in pieces (fixed value), and what an uncovered character costs below the worst piece.
MARK, UNKNOWN_COST = "▁", 10.0
#: Segments a worker keeps; bytes of text or ids that are coded before a batch goes out.
CACHE_SEGMENTS, SLICE = 300_000, 2 << 20
#: Transitions over failure links that a worker keeps as direct ones.
KEPT_STEPS = 500_000
DEFAULT_MODEL = "/opt/tokenizers/piece_bpe_32k.model"

#: Below every score; (length, id) of an uncovered character.
LOWEST, NO_PIECE = float("-inf"), (1, -1)


class Automaton:
    """Aho-Corasick automaton with output links over (piece, score, id)."""

    def __init__(self, pieces: list[tuple[str, float, int]]):
        self.next: list[dict[str, int]] = [{}]
        self.piece: list[tuple[int, float, int] | None] = [None]
        for text, score, number in pieces:
            at = 0
            for c in text:
                to = self.next[at].get(c)
                if to is None:
                    to = self.next[at][c] = len(self.next)
                    self.next.append({})
                    self.piece.append(None)
                at = to
            self.piece[at] = (len(text), score, number)
        n = len(self.next)
        self.fail, self.link = [0] * n, [0] * n
        queue = list(self.next[0].values())
        for at in queue:
            for c, to in self.next[at].items():
                back = self.fail[at]
                while back and c not in self.next[back]:
                    back = self.fail[back]
                back = self.next[back].get(c, 0)
                self.fail[to] = back
                queue.append(to)
            back = self.fail[at]
            self.link[at] = back if self.piece[back] is not None else self.link[back]
        #: transitions over failure links that may still be kept (a bound of memory, not of results)
        self.room = KEPT_STEPS
        self.queue, self.unknown = queue, None

    def _cover(self, unknown: float) -> None:
        """Fix what an uncovered character costs."""
        self.unknown = unknown
        #: all pieces that end in a state, longest first, as found by walking the output links: place of their begin from the end of the
        #: scores, own score, (length, id); where no piece is the last character alone, that as an uncovered one comes last
        self.ends: list[tuple[tuple[int, float, tuple[int, int]], ...]] = [()] * len(self.next)
        for at in self.queue:
            own = ()
            if self.piece[at] is not None:
                length, score, number = self.piece[at]
                own = ((-length, score, (length, number)),)
            self.ends[at] = own + self.ends[self.link[at]] if self.link[at] else own
        none = ((-1, unknown, NO_PIECE),)
        self.ends = [e if e and e[-1][0] == -1 else e + none for e in self.ends]

    def _hop(self, at: int, c: str) -> int:
        """State after ``c`` by the failure links; kept as a direct transition while there is room."""
        came, to = at, None
        while to is None and at:
            at = self.fail[at]
            to = self.next[at].get(c)
        to = to or 0
        if self.room:
            self.room -= 1
            self.next[came][c] = to
        return to

    def best(self, text: str, unknown: float) -> list[tuple[int, int]]:
        """Best segmentation as (length, id); id -1 is one uncovered character. Ties go to the piece that begins first."""
        if unknown != self.unknown:
            self._cover(unknown)
        score, back, at = [0.0], [NO_PIECE], 0
        step, ends, put, keep = self.next, self.ends, score.append, back.append
        for c in text:
            try:
                at = step[at][c]
            except KeyError:
                at = self._hop(at, c)
            top = LOWEST
            for before, own, piece in ends[at]:
                s = score[before] + own
                if s > top:
                    top, how = s, piece
            put(top)
            keep(how)
        out, i = [], len(text)
        while i:
            length, number = back[i]
            out.append((length, number))
            i -= length
        return out[::-1]


class _Words(dict):
    """Ids, as bytes, of words that follow one blank; looks up what is missing in ``model``."""

    def __init__(self, model: PieceModel):
        self.model = model

    def __missing__(self, word: str) -> bytes:
        parts = self.model._prepare()[1].findall(" " + word)
        if len(parts) == 1:
            ids = self.model._segment(parts[0]).tobytes()
            if len(word) < 64:
                self[word] = ids
            return ids
        # line ends stand alone; what follows them has no blank before it
        return b"".join([self[p[1:]] if p[0] == " " and len(p) > 1 else self.model._bare(p) for p in parts])


@dataclass
class PieceModel:
    """Pieces of a vocabulary with their scores; byte pieces spell what no piece covers."""

    pieces: list[tuple[str, float, int]]
    byte_ids: list[int]
    spelled: list[bytes]
    _ready: tuple | None = field(default=None, repr=False)
    _cache: _Words | None = field(default=None, repr=False)
    _bares: dict[str, bytes] = field(default_factory=dict, repr=False)

    @classmethod
    def load(cls, path: str) -> PieceModel:
        """Read the vocabulary of a SentencePiece model file (on the driver; executors get the pieces)."""
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        pieces, byte_ids, spelled = [], [-1] * 256, []
        for i in range(sp.get_piece_size()):
            text = sp.id_to_piece(i)
            if sp.is_byte(i):
                value = int(text[3:5], 16)
                byte_ids[value] = i
                spelled.append(bytes((value,)))
            elif sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i):
                spelled.append(b"")
            else:
                pieces.append((text, float(sp.get_score(i)), i))
                spelled.append(text.replace(MARK, " ").encode())
        return cls(pieces, byte_ids, spelled)

    def _prepare(self) -> tuple:
        if self._ready is None:
            covered = {c for p, _, _ in self.pieces for c in p}
            unknown = min(s for _, s, _ in self.pieces) - UNKNOWN_COST
            alone = "".join(c for c in "\n\t\r" if c not in covered)
            crossed = any(re.search(f"[^{MARK}]{MARK}", p) for p, _, _ in self.pieces)
            if crossed:
                segments = re.compile(r"(?s).+")  # pieces cross blanks: nothing may be cut
            else:
                segments = re.compile(f" *[^ {re.escape(alone)}]+| +" + (f"|[{re.escape(alone)}]" if alone else ""))
            self._ready = Automaton(self.pieces), segments, not crossed, unknown
            self._cache = _Words(self)
        return self._ready

    def _segment(self, text: str) -> array:
        machine, _, _, unknown = self._prepare()
        out, at = array("i"), 0
        # a literal mark is no blank: it is spelled in bytes, so that decoding is exact
        shown = text.replace(MARK, "\ue000").replace(" ", MARK) if MARK in text else text.replace(" ", MARK)
        for length, number in machine.best(shown, unknown):
            if number >= 0:
                out.append(number)
            else:
                out.extend(self.byte_ids[b] for b in text[at : at + 1].encode("utf-8", "surrogatepass"))
            at += length
        return out

    def _bare(self, text: str) -> bytes:
        """Ids of a segment that no blank begins."""
        ids = self._bares.get(text)
        if ids is None:
            ids = self._segment(text).tobytes()
            if len(text) < 64:
                if len(self._bares) > CACHE_SEGMENTS // 4:
                    self._bares.clear()
                self._bares[text] = ids
        return ids

    def encode(self, text: str | None) -> np.ndarray:
        """Piece ids of the blank-prefixed text; none for an empty or null one."""
        if not text:
            return np.zeros(0, dtype=np.int32)
        _, segments, by_blank, _ = self._prepare()
        cache = self._cache
        if by_blank and "  " not in text and text[0] != " " and text[-1] != " ":
            ids = b"".join(map(cache.__getitem__, text.split(" ")))  # one blank before each word
        else:
            ids = b"".join([cache[s[1:]] if by_blank and s[0] == " " and s[1:2] not in ("", " ") else self._bare(s) for s in segments.findall(" " + text)])
        if len(cache) > CACHE_SEGMENTS:
            cache.clear()
        return np.frombuffer(ids, dtype=np.int32)

    def decode(self, ids) -> str:
        raw = b"".join(map(self.spelled.__getitem__, ids))
        return (raw[1:] if raw[:1] == b" " else raw).decode("utf-8", "replace")


def _slices(batch: pa.RecordBatch, sizes: list[int]) -> Iterator[pa.RecordBatch]:
    """Parts of a batch of about SLICE bytes or ids (one row at least), without copying."""
    for part in in_chunks(sizes, sizes, SLICE):
        yield batch.slice(part.start, part.stop - part.start)


def encoded(docs: DataFrame, model: PieceModel, text: str = "text") -> DataFrame:
    """Add ``pieces`` (ids) and ``n_pieces`` to every row; own columns of these names are replaced. Null and empty texts have no pieces."""
    held = docs.sparkSession.sparkContext.broadcast(model)  # the vocabulary: its size does not depend on the data
    docs = docs.drop("pieces", "n_pieces")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = held.value
        for batch in batches:
            for rows in _slices(batch, pc.binary_length(batch.column(text)).fill_null(0).to_pylist()):
                ids = [model.encode(t) for t in rows.column(text).to_pylist()]
                ends = np.concatenate([[0], np.cumsum([len(x) for x in ids])]).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(ids) if ids else np.zeros(0, dtype=np.int32)))
                yield pa.RecordBatch.from_arrays([*rows.columns, lists], names=[*rows.schema.names, "pieces"])
        give_back()

    schema = T.StructType([*docs.schema.fields, T.StructField("pieces", T.ArrayType(T.IntegerType()))])
    return docs.mapInArrow(run, schema).withColumn("n_pieces", F.size("pieces").cast("long"))


def decoded(df: DataFrame, model: PieceModel, pieces: str = "pieces") -> DataFrame:
    """Add ``decoded``: the text of the ids; null for null; null ids in a list are passed over."""
    held = df.sparkSession.sparkContext.broadcast(model)
    df = df.drop("decoded")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = held.value
        for batch in batches:
            for rows in _slices(batch, pc.list_value_length(batch.column(pieces)).fill_null(0).to_pylist()):
                lists = rows.column(pieces)
                flat = lists.flatten()
                if flat.null_count:
                    texts = [None if ids is None else model.decode(i for i in ids if i is not None) for ids in lists.to_pylist()]
                else:
                    flat, ends = flat.to_numpy(), np.cumsum(pc.list_value_length(lists).fill_null(0).to_numpy(zero_copy_only=False)).tolist()
                    texts = [model.decode(flat[a:b].tolist()) if there else None for a, b, there in zip([0, *ends], ends, lists.is_valid().to_pylist(), strict=False)]
                yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(texts, type=pa.string())], names=[*rows.schema.names, "decoded"])
        give_back()

    return df.mapInArrow(run, T.StructType([*df.schema.fields, T.StructField("decoded", T.StringType())]))


def op2_pieces(spark, sf_dir: str, model_path: str = DEFAULT_MODEL) -> DataFrame:
    model = PieceModel.load(model_path)
    docs = table(spark, sf_dir, "documents").select("doc_id", F.sha2(F.coalesce("text", F.lit("")), 256).alias("text_sha256"), "text")
    out = decoded(encoded(docs, model).drop("text"), model)
    return out.select("doc_id", "n_pieces", "pieces", F.sha2("decoded", 256).alias("decoded_sha256"), (F.sha2("decoded", 256) == F.col("text_sha256")).alias("exact"))
