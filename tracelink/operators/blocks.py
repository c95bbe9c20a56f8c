"""All pairs of two relations without a relation of pairs: objects are packed into blocks, blocks meet blocks, and a task keeps the first k
candidates of each query as it goes. Nothing but blocks and those first k is shuffled, however many pairs there are.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import materialise, shuffle_width

#: Rows of a dense block; objects and entries at which a sparse block is closed (a single longer object fills one alone).
ROWS, OBJECTS, ENTRIES = 2048, 2048, 65_536
#: Sums are held for all pairs of two blocks where products are more than one in so many of these pairs; else products are sorted by pair.
SPARSE_PAIRS = 16
#: Similarities held at once, products expanded at once, and neighbours that a task holds before it hands them on.
CELLS, EXPANDED, HELD = 1 << 17, 1 << 20, 1 << 20
#: Neighbours up to which a task selects; beyond, all pairs are handed on.
MOST = 256
#: Candidate blocks that one task goes through for each of its query blocks, at most.
DEPTH = 64
UNIT = 1e9

FOUND = "qid long, oid long, sim double"


def _numbers(column: pa.Array, kind: type) -> np.ndarray:
    return column.to_numpy(zero_copy_only=False).astype(kind)


def _binary(parts: dict[str, np.ndarray], **more: int) -> pa.RecordBatch:
    held = [pa.array([np.ascontiguousarray(x).tobytes()], pa.binary()) for x in parts.values()] + [pa.array([v], pa.int64()) for v in more.values()]
    return pa.RecordBatch.from_arrays(held, names=[*parts, *more])


def dense_blocks(rows: DataFrame, key: str) -> DataFrame:
    """``ids, x``: rows (key, v), all v of one length, as blocks of ROWS."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, xs, n = [], [], 0
        for b in batches:
            if not b.num_rows:
                continue
            ids.append(_numbers(b.column(0), np.int64))
            xs.append(_numbers(b.column(1).flatten(), np.float64).reshape(b.num_rows, -1))
            n += b.num_rows
            if n >= ROWS:
                i, x = np.concatenate(ids), np.concatenate(xs)
                full = n // ROWS * ROWS
                for a in range(0, full, ROWS):
                    yield _binary({"ids": i[a : a + ROWS], "x": x[a : a + ROWS]})
                ids, xs, n = [i[full:]], [x[full:]], n - full
        if n:
            yield _binary({"ids": np.concatenate(ids), "x": np.concatenate(xs)})

    return rows.select(key, "v").mapInArrow(pack, "ids binary, x binary")


def _spread(spark) -> int:
    return max(shuffle_width(spark), spark.sparkContext.defaultParallelism)


def _crossed(q: DataFrame, d: DataFrame, on=None) -> DataFrame:
    """Every block of q beside every block of d; q is dealt over the tasks, and d too if it has many blocks."""
    width = _spread(q.sparkSession)
    nq, nd = q.count(), d.count()
    left = q.select([F.col(c).alias(f"q_{c}") for c in q.columns]).repartition(max(1, min(nq, 4 * width)))
    right = d.select([F.col(c).alias(f"d_{c}") for c in d.columns]).repartition(max(1, -(-nd // DEPTH), min(nd, -(-2 * width // max(1, nq)))))
    return left.join(right, on) if on is not None else left.crossJoin(right)


class Best:
    """The first k candidates of each query of a block so far, by the rounded similarity, then by id."""

    def __init__(self, ids: np.ndarray, k: int):
        self.ids, self.k = ids, k
        self.oid = np.full((len(ids), k), np.iinfo(np.int64).max)
        self.sim = np.full((len(ids), k), -np.inf)

    def floor(self) -> np.ndarray:
        return np.rint(self.sim[:, -1] * UNIT)

    def merge(self, rows: np.ndarray, oid: np.ndarray, sim: np.ndarray) -> None:
        """Take in further candidates (some for each of the rows)."""
        oid, sim = np.concatenate([self.oid[rows], oid], axis=1), np.concatenate([self.sim[rows], sim], axis=1)
        order = np.lexsort((oid, -np.rint(sim * UNIT)), axis=1)[:, : self.k]
        self.oid[rows], self.sim[rows] = np.take_along_axis(oid, order, axis=1), np.take_along_axis(sim, order, axis=1)

    def dense(self, start: int, sim: np.ndarray, ids: np.ndarray) -> None:
        """Queries from ``start`` on against candidates in order of id; -inf is no pair."""
        floor = self.floor()[start : start + len(sim)]
        level = np.rint(sim * UNIT)
        rows = np.nonzero((level.max(axis=1) >= floor) & (level.max(axis=1) > -np.inf))[0]
        if not len(rows):
            return
        level, at = level[rows], np.arange(len(rows))
        oid, out = [], []
        for _ in range(min(self.k, len(ids))):
            top = level.argmax(axis=1)
            oid.append(np.where(level[at, top] > -np.inf, ids[top], np.iinfo(np.int64).max))
            out.append(sim[rows, top])
            level[at, top] = -np.inf
            out[-1][oid[-1] == np.iinfo(np.int64).max] = -np.inf
        self.merge(rows + start, np.stack(oid, axis=1), np.stack(out, axis=1))

    def sparse(self, rows: np.ndarray, ids: np.ndarray, sim: np.ndarray) -> None:
        """Pairs of a query's row and a candidate."""
        level = np.rint(sim * UNIT)
        keep = level >= self.floor()[rows]
        rows, ids, sim, level = rows[keep], ids[keep], sim[keep], level[keep]
        if not len(rows):
            return
        order = np.lexsort((ids, -level, rows))
        rows, ids, sim = rows[order], ids[order], sim[order]
        first = np.nonzero(np.r_[True, rows[1:] != rows[:-1]])[0]
        rank = np.arange(len(rows)) - np.repeat(first, np.diff(np.r_[first, len(rows)]))
        own, slot = rows[first], np.repeat(np.arange(len(first)), np.diff(np.r_[first, len(rows)]))
        oid, out = np.full((len(own), self.k), np.iinfo(np.int64).max), np.full((len(own), self.k), -np.inf)
        top = rank < self.k
        oid[slot[top], rank[top]], out[slot[top], rank[top]] = ids[top], sim[top]
        self.merge(own, oid, out)

    def found(self) -> pa.RecordBatch:
        there = self.sim > -np.inf
        return _found(np.repeat(self.ids, there.sum(axis=1)), self.oid[there], self.sim[there])


def _found(qid: np.ndarray, oid: np.ndarray, sim: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(qid), pa.array(oid), pa.array(sim)], names=["qid", "oid", "sim"])


def _met(crossed: DataFrame, names: list[str], k: int, opened: Callable, each: Callable) -> DataFrame:
    """``qid, oid, sim`` of the first k in every task. ``opened(side, parts)`` decodes a block, ``each(best, q, d)`` compares two."""

    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[bytes, tuple] = {}
        for b in batches:
            for i in range(b.num_rows):
                parts = {c: b.column(j)[i].as_buffer() for j, c in enumerate(b.schema.names)}
                name = parts["q_ids"].to_pybytes()
                if name not in held:
                    if sum(len(x[0].ids) for x in held.values()) * k > HELD:
                        for best, _ in held.values():
                            yield best.found()
                        held = {}
                    q = opened({c: parts[f"q_{c}"] for c in names})
                    held[name] = (Best(q["ids"], k), q)
                each(*held[name], opened({c: parts[f"d_{c}"] for c in names}))
        for best, _ in held.values():
            yield best.found()

    return crossed.select([c for c in crossed.columns if c[2:] in names]).mapInArrow(meet, FOUND)


def _all(crossed: DataFrame, score: Callable) -> DataFrame:
    def meet(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                q, d = (_open_dense({c: b.column(b.schema.names.index(f"{s}_{c}"))[i].as_buffer() for c in ("ids", "x")}) for s in "qd")
                step = max(1, CELLS // len(d["ids"]))
                for a in range(0, len(q["ids"]), step):
                    sim = score(q["x"][a : a + step], d["x"])
                    yield _found(np.repeat(q["ids"][a : a + step], sim.shape[1]), np.tile(d["ids"], len(sim)), sim.ravel())

    return crossed.mapInArrow(meet, FOUND)


def _open_dense(parts: dict[str, pa.Buffer]) -> dict[str, np.ndarray]:
    ids = np.frombuffer(parts["ids"], dtype=np.int64)
    order = np.argsort(ids, kind="stable")
    return {"ids": ids[order], "x": np.frombuffer(parts["x"], dtype=np.float64).reshape(len(ids), -1)[order]}


def scan(q: DataFrame, d: DataFrame, k: int, score: Callable[[np.ndarray, np.ndarray], np.ndarray]) -> DataFrame:
    """``qid, oid, sim, rnk``: the first k candidates (oid, v) of every query (qid, v) under ``score`` of their vectors, every pair compared.

    ``score(a, b)`` gives the similarities of all rows of a to all rows of b. Equal vectors are compared once: of candidates alike the first
    k by id stand for all, and queries alike share their neighbours.
    """
    q, d = (materialise(x.where(F.col("v").isNotNull()), "scanned") for x in (q, d))
    classes = materialise(q.groupBy("v").agg(F.min("qid").alias("cid")), "alike")
    first = d.withColumn("__r", F.row_number().over(Window.partitionBy("v").orderBy("oid"))).where(F.col("__r") <= k).select("oid", "v")
    blocks = [materialise(dense_blocks(rows, key), "blocks") for rows, key in ((classes, "cid"), (first, "oid"))]
    crossed = _crossed(*blocks)

    def each(best: Best, q: dict, d: dict) -> None:
        step = max(1, CELLS // len(d["ids"]))
        for a in range(0, len(q["ids"]), step):
            best.dense(a, score(q["x"][a : a + step], d["x"]), d["ids"])

    found = _met(crossed, ["ids", "x"], k, _open_dense, each) if k <= MOST else _all(crossed, score)
    first = Window.partitionBy("cid").orderBy(F.round("sim", 9).desc(), "oid")
    found = found.withColumnRenamed("qid", "cid").withColumn("rnk", F.row_number().over(first)).where(F.col("rnk") <= k)
    return found.join(q.join(classes, "v").select("qid", "cid"), "cid").select("qid", "oid", "sim", "rnk")


# --- sparse ------------------------------------------------------------------------------------------------------------------------

SPARSE = {"ids": np.int64, "ptr": np.int64, "fid": np.int64, "w": np.float64}


def sparse_blocks(rows: DataFrame, key: str, w: str, more: list[str]) -> DataFrame:
    """``ids, ptr, fid, w, lo, hi``: signatures (key, fid, w) as blocks of whole objects, with the range of their features.

    Objects are dealt by their least feature, so that blocks of features that lie together need not meet all others. Numbers of an object
    in columns ``more`` come along.
    """
    low = F.min("fid").over(Window.partitionBy(key))
    held = materialise(rows.select(key, "fid", w, *more).withColumn("lo", low), "dealt")
    parts = max(1, min(_spread(rows.sparkSession), -(-held.count() // ENTRIES)))
    held = held.repartitionByRange(parts, "lo", key).sortWithinPartitions("lo", key, "fid")

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def block(cols: list[np.ndarray], starts: np.ndarray) -> pa.RecordBatch:
            parts = {"ids": cols[0][starts], "ptr": np.r_[starts, len(cols[0])], "fid": cols[1], "w": cols[2]}
            parts |= {c: x[starts] for c, x in zip(more, cols[3:], strict=True)}
            return _binary(parts, lo=int(cols[1].min()), hi=int(cols[1].max()))

        rest: list[np.ndarray] | None = None
        for b in batches:
            if not b.num_rows:
                continue
            cols = [_numbers(b.column(i), np.int64 if i < 2 else np.float64) for i in range(3 + len(more))]
            cols = [np.concatenate(x) for x in zip(rest, cols, strict=True)] if rest else cols
            while True:  # blocks that the rows so far close; the last object may go on
                starts = np.nonzero(np.r_[True, cols[0][1:] != cols[0][:-1]])[0]
                n = min(OBJECTS, max(1, int(np.searchsorted(starts, ENTRIES, side="right")) - 1))
                if len(starts) <= n or len(cols[0]) < ENTRIES and len(starts) <= OBJECTS:
                    break
                yield block([c[: starts[n]] for c in cols], starts[:n])
                cols = [c[starts[n] :] for c in cols]
            rest = cols
        if rest:
            yield block(rest, np.nonzero(np.r_[True, rest[0][1:] != rest[0][:-1]])[0])

    kinds = ", ".join(f"{c} binary" for c in [*SPARSE, *more])
    return held.select(key, "fid", w, *more).mapInArrow(pack, f"{kinds}, lo long, hi long")


def _open_sparse(parts: dict[str, pa.Buffer]) -> dict[str, np.ndarray]:
    out = {c: np.frombuffer(x, dtype=SPARSE.get(c, np.float64)) for c, x in parts.items()}
    out["row"] = np.repeat(np.arange(len(out["ids"])), np.diff(out["ptr"]))
    return out


def _posted(q: dict[str, np.ndarray]) -> None:
    """Posting lists of a block of queries, once."""
    if "post" not in q:
        order = np.argsort(q["fid"], kind="stable")
        fid = q["fid"][order]
        first = np.nonzero(np.r_[True, fid[1:] != fid[:-1]])[0]
        q |= {"post": fid[first], "start": first, "length": np.diff(np.r_[first, len(fid)]), "p_row": q["row"][order], "p_w": q["w"][order]}


def products(q: dict[str, np.ndarray], d: dict[str, np.ndarray], floor: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``rows, columns, sums`` of all pairs of a query and a candidate that share a feature; sums under the query's floor may be left out."""
    _posted(q)
    at = np.minimum(np.searchsorted(q["post"], d["fid"]), len(q["post"]) - 1)
    hit = np.nonzero(q["post"][at] == d["fid"])[0]
    at, n = at[hit], len(d["ids"])
    ends = np.cumsum(q["length"][at])
    dense = len(ends) and ends[-1] * SPARSE_PAIRS > len(q["ids"]) * n
    total = None
    cells, sums = [], []
    a = 0
    while a < len(hit):
        done = ends[a - 1] if a else 0
        b = max(a + 1, int(np.searchsorted(ends, done + EXPANDED, side="right")))
        length = q["length"][at[a:b]]
        place = np.arange(ends[b - 1] - done) + np.repeat(q["start"][at[a:b]] - (ends[a:b] - length - done), length)
        cell = q["p_row"][place] * n + np.repeat(d["row"][hit[a:b]], length)
        part = q["p_w"][place] * np.repeat(d["w"][hit[a:b]], length)
        if dense:
            part_sum = np.bincount(cell, weights=part, minlength=len(q["ids"]) * n)
            total = part_sum if total is None else np.add(total, part_sum, out=total)
        else:
            cells.append(cell)
            sums.append(part)
        a = b
    if total is not None:
        total = total.reshape(-1, n)
        cell = np.flatnonzero(total >= np.maximum(floor, np.finfo(float).tiny)[:, None])
        return cell // n, cell % n, total.ravel()[cell]
    if not cells:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    cell, part = np.concatenate(cells), np.concatenate(sums)
    order = np.argsort(cell, kind="stable")
    cell = cell[order]
    first = np.nonzero(np.r_[True, cell[1:] != cell[:-1]])[0]
    cell, total = cell[first], np.add.reduceat(part[order], first)
    cell, total = cell[there := total >= floor[cell // n]], total[there]
    return cell // n, cell % n, total


def ready(d: DataFrame) -> DataFrame:
    """Written blocks of candidates (oid, fid, wd), for ``multiply`` of several relations of queries."""
    return materialise(sparse_blocks(d, "oid", "wd", []), "blocks")


def multiply(q: DataFrame, d: DataFrame, k: int, held: DataFrame | None = None, meet: Callable | None = None, made: DataFrame | None = None) -> DataFrame:
    """``qid, oid, sim``: at least the first k candidates (oid, fid, wd) of every query (qid, fid, wq) by the sum of products over shared features.

    Of blocks whose features share no range none meet. With ``held`` (side, oid and numbers of the object) only pairs for which
    ``meet(a, b)`` is true count, a and b having these numbers of the pairs' queries and candidates by name. ``made``: ``ready(d)``, for use
    without ``held``.
    """
    more = [c for c in held.columns if c not in ("side", "oid")] if held is not None else []
    if held is not None:
        held = materialise(held, "numbers")
        q = q.join(held.where("side = 'Q'").select(F.col("oid").alias("qid"), *more), "qid")
        d = d.join(held.where("side = 'D'").select("oid", *more), "oid")
    left = materialise(sparse_blocks(q, "qid", "wq", more), "blocks")
    right = made if made is not None else materialise(sparse_blocks(d, "oid", "wd", more), "blocks")
    crossed = _crossed(left, right, (F.col("q_lo") <= F.col("d_hi")) & (F.col("d_lo") <= F.col("q_hi")))

    def each(best: Best, q: dict, d: dict) -> None:
        row, column, sim = products(q, d, (best.floor() - 1) / UNIT)
        if meet is not None:
            there = meet({c: q[c][row] for c in more}, {c: d[c][column] for c in more})
            row, column, sim = row[there], column[there], sim[there]
        best.sparse(row, d["ids"][column], sim)

    return _met(crossed, [*SPARSE, *more], k, _open_sparse, each)


def takes(q: DataFrame, d: DataFrame, k: int) -> bool:
    """Whether ids and features are whole numbers, as blocks hold them, and k is one that a task selects."""
    whole = lambda df, names: all(df.schema[c].dataType.typeName() in ("long", "integer", "short", "byte") for c in names)
    return k <= MOST and whole(q, ["qid", "fid"]) and whole(d, ["oid", "fid"])
