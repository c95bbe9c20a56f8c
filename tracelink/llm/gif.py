"""GIF media columns: a codec (LZW code streams, palettes, disposal, transparency, interlace, timing) and the operators built on it."""

from __future__ import annotations

import struct
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import give_back, table

#: Fixed values of the format.
MAX_BITS, TABLE_LIMIT = 12, 4096
KEEP, LEAVE, BACKGROUND, PREVIOUS = 0, 1, 2, 3
#: Passes of interlaced rows: first row, step.
INTERLACE = [(0, 8), (4, 8), (2, 4), (1, 2)]

#: Payload layout: rows of 192 samples, at most this many rows a frame, so many hundredths of a second between frames.
ROW, FRAME_ROWS, FRAME_DELAY = 192, 64, 10
GREY = np.repeat(np.arange(256, dtype=np.uint8)[:, None], 3, axis=1)
#: Colours of payload samples: red tells them apart, so that a sample is read back from its pixel's colour.
COLOURS = np.stack([np.arange(256), np.arange(256) * 7 % 256, 255 - np.arange(256)], axis=1).astype(np.uint8)
#: Pixels of a canvas or an image at most; files that claim more are taken for broken.
MOST_PIXELS = 1 << 25


class BrokenImage(ValueError):
    """The bytes are no complete GIF."""


# --- LZW ---------------------------------------------------------------------------------------------------------------------------


def _widths(n: int, bits: int) -> np.ndarray:
    """Width in bits of the i-th code after a clear code: it follows from the number of table entries alone."""
    free = (1 << bits) + 2 + np.maximum(np.arange(n) - 1, 0)
    return np.clip(np.floor(np.log2(free)).astype(np.int64) + 1, bits + 1, MAX_BITS)


_WIDTHS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _layout(bits: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Widths and bit offsets of n codes after a clear code (cached for a full table)."""
    if bits not in _WIDTHS or len(_WIDTHS[bits][0]) < n:
        w = _widths(max(n, TABLE_LIMIT + 64), bits)
        _WIDTHS[bits] = w, np.concatenate([[0], np.cumsum(w)])
    w, at = _WIDTHS[bits]
    return w[:n], at[: n + 1]


def lzw_encode(samples: bytes, bits: int = 8) -> bytes:
    """Variable-width LZW code stream of samples below ``1 << bits``; the table is cleared when it is full."""
    clear, stop = 1 << bits, (1 << bits) + 1
    segments: list[list[int]] = []
    codes: list[int] = []
    add, book, free = codes.append, {}, stop + 1
    look = book.get
    prefix = -1
    for s in samples:
        if prefix < 0:
            prefix = s
            continue
        key = prefix << 8 | s
        code = look(key)
        if code is not None:
            prefix = code
            continue
        add(prefix)
        prefix = s
        book[key] = free
        free += 1
        if free == TABLE_LIMIT:
            add(prefix)
            add(clear)
            segments.append(codes)
            codes = []
            add, free, prefix = codes.append, stop + 1, -1
            book.clear()
    if prefix >= 0:
        add(prefix)
    add(stop)
    segments.append(codes)
    value, width = [np.array([clear])], [np.array([bits + 1])]
    for s in segments:
        value.append(np.array(s, dtype=np.int64))
        width.append(_layout(bits, len(s))[0])
    v, w = np.concatenate(value), np.concatenate(width)
    at = np.concatenate([[0], np.cumsum(w)])
    total = int(at[-1] + 7) // 8
    byte, v = at[:-1] >> 3, v << (at[:-1] & 7)
    out = np.zeros(total + 3, dtype=np.int64)
    for i in range(3):
        out += np.bincount(byte + i, weights=(v >> (8 * i)) & 255, minlength=total + 3).astype(np.int64)
    return out[:total].astype(np.uint8).tobytes()


def lzw_decode(stream: bytes, bits: int, most: int) -> bytes:
    """Samples of an LZW code stream, ``most`` at most; a stream that ends early gives what it has. Codes of no meaning raise BrokenImage."""
    if not 2 <= bits <= 8:
        raise BrokenImage("a code size out of range")
    clear, stop = 1 << bits, (1 << bits) + 1
    data = np.frombuffer(stream + b"\0\0\0\0", dtype=np.uint8).astype(np.int64)
    words = data[:-2] | data[1:-1] << 8 | data[2:] << 16
    whole, at, size = len(stream) * 8, 0, 0
    roots = [bytes((i,)) for i in range(clear)] + [b"", b""]
    parts: list[bytes] = []
    limit = TABLE_LIMIT
    while at + bits < whole and size < most:
        n = limit
        width, offset = _layout(bits, n)
        n = int(np.searchsorted(offset, whole - at, side="right")) - 1
        if n <= 0:
            break
        n = min(n, limit)
        width, offset = width[:n], offset[:n] + at
        codes = (words[offset >> 3] >> (offset & 7)) & ((1 << width) - 1)
        ends = np.flatnonzero((codes == clear) | (codes == stop))
        if not len(ends) and n == limit and at + int(_layout(bits, n)[1][n]) + MAX_BITS <= whole:
            limit *= 4  # an encoder that never clears goes on with full-width codes
            continue
        cut = int(ends[0]) if len(ends) else n
        run = codes[:cut].tolist()
        if run:
            mark = len(parts)
            book = roots.copy()
            grow, put = book.append, parts.append
            if run[0] >= clear:
                raise BrokenImage("a stream begins with a code beyond the table")
            last = book[run[0]]
            put(last)
            free = stop + 1
            for code in run[1:]:
                if code < free:
                    entry = book[code]
                elif code == free:
                    entry = last + last[:1]
                else:
                    raise BrokenImage("a code beyond the table")
                put(entry)
                if free < TABLE_LIMIT:
                    grow(last + entry[:1])
                    free += 1
                last = entry
            size += sum(map(len, parts[mark:]))
        if len(ends) and codes[cut] == stop:
            break
        if not len(ends):
            break
        at = int(offset[cut] + width[cut])
        limit = TABLE_LIMIT
    return b"".join(parts)[:most]


# --- container ---------------------------------------------------------------------------------------------------------------------


@dataclass
class Patch:
    """One stored image: palette indexes with place, time and composition rules."""

    index: np.ndarray
    left: int = 0
    top: int = 0
    delay: int = 0
    disposal: int = KEEP
    transparent: int | None = None
    palette: np.ndarray | None = None
    interlaced: bool = False


@dataclass
class Gif:
    width: int
    height: int
    palette: np.ndarray | None
    patches: list[Patch] = field(default_factory=list)
    background: int = 0
    loops: int | None = None


def _palette_bits(palette: np.ndarray) -> int:
    return max(1, int(len(palette) - 1).bit_length())


def _palette_bytes(palette: np.ndarray) -> bytes:
    full = np.zeros((1 << _palette_bits(palette), 3), dtype=np.uint8)
    full[: len(palette)] = palette
    return full.tobytes()


def _blocks(data: bytes) -> bytes:
    return b"".join(bytes((len(c),)) + c for c in (data[i : i + 255] for i in range(0, len(data), 255))) + b"\0"


def _row_order(height: int) -> np.ndarray:
    return np.concatenate([np.arange(first, height, step) for first, step in INTERLACE])


def write_gif(gif: Gif) -> bytes:
    packed = (0xF0 | _palette_bits(gif.palette) - 1) if gif.palette is not None else 0x70
    out = [b"GIF89a", struct.pack("<HHBBB", gif.width, gif.height, packed, gif.background, 0)]
    if gif.palette is not None:
        out.append(_palette_bytes(gif.palette))
    if gif.loops is not None:
        out.append(b"!\xff\x0bNETSCAPE2.0\x03\x01" + struct.pack("<H", gif.loops) + b"\0")
    for p in gif.patches:
        flags = p.disposal << 2 | (p.transparent is not None)
        out.append(b"!\xf9\x04" + struct.pack("<BHB", flags, p.delay, p.transparent or 0) + b"\0")
        h, w = p.index.shape
        local = 0 if p.palette is None else 0x80 | _palette_bits(p.palette) - 1
        out.append(b"," + struct.pack("<HHHHB", p.left, p.top, w, h, local | (0x40 if p.interlaced else 0)))
        if p.palette is not None:
            out.append(_palette_bytes(p.palette))
        palette = p.palette if p.palette is not None else gif.palette
        bits = max(2, _palette_bits(palette)) if palette is not None else 8
        rows = p.index[_row_order(h)] if p.interlaced else p.index
        out.append(bytes((bits,)) + _blocks(lzw_encode(np.ascontiguousarray(rows, dtype=np.uint8).tobytes(), bits)))
    out.append(b";")
    return b"".join(out)


class _Reader:
    def __init__(self, data: bytes):
        self.data, self.at = data, 0

    def take(self, n: int) -> bytes:
        got = self.data[self.at : self.at + n]
        if len(got) < n:
            raise BrokenImage("the file ends early")
        self.at += n
        return got

    def blocks(self) -> bytes:
        parts = []
        while n := self.take(1)[0]:
            parts.append(self.take(n))
        return b"".join(parts)

    def palette(self, packed: int) -> np.ndarray | None:
        if not packed & 0x80:
            return None
        n = 2 << (packed & 7)
        return np.frombuffer(self.take(3 * n), dtype=np.uint8).reshape(n, 3)


def read_gif(data: bytes) -> Gif:
    r = _Reader(data)
    if r.take(6) not in (b"GIF87a", b"GIF89a"):
        raise BrokenImage("no GIF signature")
    width, height, packed, background, _ = struct.unpack("<HHBBB", r.take(7))
    if width * height > MOST_PIXELS:
        raise BrokenImage("the canvas is too large")
    gif = Gif(width, height, r.palette(packed), background=background)
    delay, disposal, transparent = 0, KEEP, None
    while (kind := r.take(1)) != b";":
        if kind == b"!":
            label = r.take(1)[0]
            body = r.blocks()
            if label == 0xF9 and len(body) >= 4:
                flags, delay, index = struct.unpack("<BHB", body[:4])
                disposal, transparent = flags >> 2 & 7, index if flags & 1 else None
            elif label == 0xFF and body[:11] == b"NETSCAPE2.0" and len(body) >= 14:
                gif.loops = struct.unpack("<H", body[12:14])[0]
        elif kind == b",":
            left, top, w, h, flags = struct.unpack("<HHHHB", r.take(9))
            local = r.palette(flags)
            bits = r.take(1)[0]
            if w * h > MOST_PIXELS:
                raise BrokenImage("an image is too large")
            got = lzw_decode(r.blocks(), bits, w * h)
            if len(got) < w * h:
                raise BrokenImage("a code stream ends early")
            index = np.frombuffer(got, dtype=np.uint8).reshape(h, w)
            if flags & 0x40:
                rows = np.empty_like(index)
                rows[_row_order(h)] = index
                index = rows
            gif.patches.append(Patch(index, left, top, delay, disposal, transparent, local, bool(flags & 0x40)))
            delay, disposal, transparent = 0, KEEP, None
        elif kind != b"\0":
            raise BrokenImage("an unknown block")
    return gif


def composed(gif: Gif) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Canvas (height, width, 3) and cover mask after each image, by the disposal and transparency rules. Arrays are reused: copy to keep."""
    canvas = np.zeros((gif.height, gif.width, 3), dtype=np.uint8)
    cover = np.zeros((gif.height, gif.width), dtype=bool)
    for p in gif.patches:
        palette = p.palette if p.palette is not None else gif.palette if gif.palette is not None else GREY
        area = np.s_[p.top : min(p.top + p.index.shape[0], gif.height), p.left : min(p.left + p.index.shape[1], gif.width)]
        before = (canvas[area].copy(), cover[area].copy()) if p.disposal == PREVIOUS else None
        index = p.index[: cover[area].shape[0], : cover[area].shape[1]]
        colours = palette[np.minimum(index, len(palette) - 1)]
        if p.transparent is None:
            canvas[area], cover[area] = colours, True
        else:
            shown = index != p.transparent
            canvas[area][shown] = colours[shown]
            cover[area] |= shown
        yield canvas, cover
        if p.disposal == BACKGROUND:
            canvas[area], cover[area] = 0, False
        elif before is not None:
            canvas[area], cover[area] = before


def timed_frames(gif: Gif, levels: int = 2) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Start and delay in milliseconds, composed pixels of the area an image covers (cut at the canvas), colour histogram of the canvas."""
    now = 0
    for p, (canvas, _) in zip(gif.patches, composed(gif), strict=True):
        h, w = p.index.shape
        yield now, 10 * p.delay, canvas[p.top : p.top + h, p.left : p.left + w], histogram(canvas, levels)
        now += 10 * p.delay


def histogram(pixels: np.ndarray, levels: int = 2) -> np.ndarray:
    """Colour histogram of RGB pixels (n, 3) with ``levels ** 3`` bins, red slowest."""
    q = (pixels.reshape(-1, 3).astype(np.int32) * levels) >> 8
    return np.bincount((q[:, 0] * levels + q[:, 1]) * levels + q[:, 2], minlength=levels**3)


# --- operators ---------------------------------------------------------------------------------------------------------------------


def payload_of(text: str | None) -> bytes:
    raw = (text or "").encode("utf-8", "surrogatepass")
    return raw.ljust(max(ROW, -(-len(raw) // ROW) * ROW), b" ")


def payload_gif(payload: bytes) -> bytes:
    """A payload (a multiple of 192 bytes) as an animation: one sample a byte, 64 rows a frame.

    Samples that equal what the canvas shows already are stored as the transparent index, where no sample has that value (no UTF-8 byte is
    255). The last image is taken off again after its time.
    """
    samples = np.frombuffer(payload, dtype=np.uint8).reshape(-1, ROW)
    clear = 255 if not (samples == 255).any() else None
    patches: list[Patch] = []
    for i in range(0, len(samples), FRAME_ROWS):
        shown = samples[i : i + FRAME_ROWS]
        if i and clear is not None:
            shown = np.where(shown == samples[i - FRAME_ROWS : i - FRAME_ROWS + len(shown)], np.uint8(clear), shown)
        patches.append(Patch(shown, delay=FRAME_DELAY, disposal=LEAVE, transparent=clear if i else None))
    patches[-1].disposal = PREVIOUS
    return write_gif(Gif(ROW, min(FRAME_ROWS, len(samples)), COLOURS, patches, loops=0))


#: Bytes of text that go to the codec, or of pixels that come back, in one batch.
BATCH_BYTES = 8 << 20


def _batches(rows: Iterator[dict], sizes: str, columns: list[str]) -> Iterator[pd.DataFrame]:
    held, size = [], 0
    for row in rows:
        held.append(row)
        size += len(row[sizes]) if row[sizes] is not None else 0
        if size >= BATCH_BYTES:
            yield pd.DataFrame(held, columns=columns)
            held, size = [], 0
    if held:
        yield pd.DataFrame(held, columns=columns)


def texts_to_gif(docs: DataFrame, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, n_bytes, media``: each whole text, padded with blanks to a multiple of 192 bytes, as a GIF animation.

    A null text is stored as an empty one; equal texts give equal bytes; repeated rows stay; an empty table gives no rows. One row is
    coded at a time, so memory follows the longest text.
    """

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def rows() -> Iterator[dict]:
            for batch in batches:
                for i, t in zip(batch["doc_id"].tolist(), batch["text"].tolist(), strict=True):
                    payload = payload_of(t)
                    yield {"doc_id": i, "n_bytes": len((t or "").encode("utf-8", "surrogatepass")), "media": payload_gif(payload)}

        yield from _batches(rows(), "media", ["doc_id", "n_bytes", "media"])
        give_back()

    picked = docs.select(F.col(f"`{id_column}`").cast("long").alias("doc_id"), F.col(f"`{text}`").cast("string").alias("text"))
    return picked.mapInPandas(_nullable(run, "doc_id"), "doc_id long, n_bytes long, media binary")


def _nullable(run, column: str):
    """Keep integer ids exact where pandas would turn a batch with nulls into floats."""

    def wrapped(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for out in run(b.assign(**{column: b[column].astype("Int64").astype(object).where(b[column].notna(), None)}) for b in batches):
            yield out.assign(**{column: out[column].astype("Int64")})

    return wrapped


FRAME_SCHEMA = "doc_id long, frame int, start_ms long, delay_ms long, width int, height int, patch binary, histogram array<int>"


def gif_frames(media: DataFrame, id_column: str = "doc_id", column: str = "media", levels: int = 2) -> DataFrame:
    """Timed frames: one row per stored image of each GIF, composed by palette, disposal and transparency.

    ``patch`` holds the RGB bytes of the area the image covers after composition, ``histogram`` counts the colours of the whole canvas.
    Null or broken media (cut off, of odd code sizes, of more than MOST_PIXELS) give no rows; a GIF without images gives none. Repeated rows
    give their frames again; an empty table gives no rows; the other columns of ``media`` are left out.
    """

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def rows() -> Iterator[dict]:
            for batch in batches:
                for i, data in zip(batch["doc_id"].tolist(), batch["media"].tolist(), strict=True):
                    if data is None:
                        continue
                    try:
                        gif = read_gif(bytes(data))
                    except BrokenImage:
                        continue
                    for n, (start, delay, pixels, colours) in enumerate(timed_frames(gif, levels)):
                        h, w = pixels.shape[:2]
                        yield {"doc_id": i, "frame": n, "start_ms": start, "delay_ms": delay, "width": w, "height": h, "patch": pixels.tobytes(), "histogram": colours.tolist()}

        yield from _batches(rows(), "patch", ["doc_id", "frame", "start_ms", "delay_ms", "width", "height", "patch", "histogram"])

    picked = media.select(F.col(f"`{id_column}`").cast("long").alias("doc_id"), F.col(f"`{column}`").alias("media"))
    return picked.mapInPandas(_nullable(run, "doc_id"), FRAME_SCHEMA)


def gif_payloads(media: DataFrame) -> DataFrame:
    """``doc_id, n_bytes, media, payload, feature``: samples read back from the timed frames, and a text of their number, time and colours.

    Null or broken media keep their row with null payload and feature.
    """

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def rows() -> Iterator[dict]:
            for batch in batches:
                for i, n, data in zip(batch["doc_id"].tolist(), batch["n_bytes"].tolist(), batch["media"].tolist(), strict=True):
                    row = {"doc_id": i, "n_bytes": n, "media": data, "payload": None, "feature": None}
                    parts, colours, time = [], np.zeros(8, dtype=np.int64), 0
                    try:
                        for start, delay, pixels, seen in timed_frames(read_gif(bytes(data or b""))):
                            parts.append(pixels[:, :, 0].tobytes())
                            colours += seen
                            time = start + delay
                        row |= {"media": bytes(data), "payload": b"".join(parts), "feature": f"frames={len(parts)};ms={time};rgb8={','.join(map(str, colours.tolist()))}"}
                    except BrokenImage:
                        pass
                    yield row

        yield from _batches(rows(), "payload", ["doc_id", "n_bytes", "media", "payload", "feature"])

    return media.select("doc_id", "n_bytes", "media").mapInPandas(_nullable(run, "doc_id"), "doc_id long, n_bytes long, media binary, payload binary, feature string")


def op1_gif_media(spark, sf_dir: str) -> DataFrame:
    read = gif_payloads(texts_to_gif(table(spark, sf_dir, "documents")))
    payload_bytes = F.octet_length("payload").cast("long")
    return read.select(
        "doc_id", "n_bytes", payload_bytes.alias("payload_bytes"), F.sha2("payload", 256).alias("payload_sha256"),
        F.crc32(F.expr("substring(payload, length(payload) - 15, 16)")).alias("tail_crc32"),
        F.octet_length("media").cast("long").alias("media_bytes"), F.sha2("media", 256).alias("media_sha256"), "feature",
    )
