"""Dense nearest neighbours by space partitions: k-d splits, packed boxes under a tree of boxes, and k-d splits with holes.

The partition is fitted to a bounded sample on the driver; every vector is assigned to a cell; each query searches its own cell first, and
the distance to its k-th neighbour there is the radius of the ball that decides which other cells it must visit in a second pass. The kinds
differ in how space is cut and in how the cells that a ball meets are found.
"""

from __future__ import annotations

import itertools
import math
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import materialise
from .linking import top_k, unit_vectors

#: Vectors sampled for the partition, vectors aimed at for a cell, and children of a node in a tree of boxes.
SAMPLE, CELL, FANOUT = 20_000, 128, 8
#: Vectors of a cell that are compared with a query at once, and queries at once (a block of so many similarities is held).
BLOCK = 2048


def _gaps(low: np.ndarray, high: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Distance of a point to each of several boxes."""
    gap = np.maximum(np.maximum(low - x, x - high), 0)
    return np.sqrt((gap * gap).sum(axis=1))


@dataclass
class Plane:
    """A cut (axis, at) with both parts, or the number of a cell."""

    cell: int = -1
    axis: int = -1
    at: float = 0.0
    low: Plane | None = None
    high: Plane | None = None


class KdTree:
    """Median cuts along the widest axis; a ball walks down the planes it crosses."""

    def __init__(self, sample: np.ndarray, cells: int):
        numbers = itertools.count()

        def grow(x: np.ndarray, depth: int) -> Plane:
            axis = int(np.argmax(np.ptp(x, axis=0))) if len(x) > 1 else -1
            at = float(np.median(x[:, axis])) if axis >= 0 else 0.0
            low = x[:, axis] < at
            if depth == 0 or axis < 0 or not low.any() or low.all():
                return Plane(cell=next(numbers))
            return Plane(-1, axis, at, grow(x[low], depth - 1), grow(x[~low], depth - 1))

        self.root = grow(sample, max(0, math.ceil(math.log2(cells))))
        self.n = next(numbers)

    def assign(self, x: np.ndarray) -> np.ndarray:
        out = np.empty(len(x), dtype=np.int64)
        todo = [(self.root, np.arange(len(x)))]
        while todo:
            node, rows = todo.pop()
            if node.cell >= 0:
                out[rows] = node.cell
            else:
                low = x[rows, node.axis] < node.at
                todo += [(node.low, rows[low]), (node.high, rows[~low])]
        return out

    def bounded(self, order: np.ndarray, low: np.ndarray, high: np.ndarray) -> None:
        """Take the tight boxes of the cells."""
        self.boxes = {int(c): i for i, c in enumerate(order)}
        self.low, self.high = low, high

    def meets(self, x: np.ndarray, radius: float) -> list[int]:
        out, todo = [], [self.root]
        while todo:
            node = todo.pop()
            if node.cell >= 0:
                i = self.boxes.get(node.cell)
                if i is not None and _gaps(self.low[i : i + 1], self.high[i : i + 1], x)[0] <= radius:
                    out.append(node.cell)
                continue
            if x[node.axis] - radius < node.at:
                todo.append(node.low)
            if x[node.axis] + radius >= node.at:
                todo.append(node.high)
        return out


class PackedBoxes:
    """Slabs along one axis after another (sort-tile-recursive packing), and a tree of boxes over the cells, FANOUT a node."""

    def __init__(self, sample: np.ndarray, cells: int):
        axes = np.argsort(-np.ptp(sample, axis=0), kind="stable")
        self.numbers = itertools.count()

        def slabs(x: np.ndarray, at: int, left: int):
            """Cuts along the ``at``-th axis and what is below each slab; a number where one cell is left."""
            if left <= 1 or at >= len(axes) or len(x) < 2:
                return next(self.numbers)
            # as many axes as can be cut in two or more still take part
            still = min(len(axes) - at, max(1, int(math.log2(left))))
            parts = max(2, math.ceil(left ** (1 / still)))
            axis = int(axes[at])
            cuts = np.unique(np.quantile(x[:, axis], np.arange(1, parts) / parts))
            side = np.searchsorted(cuts, x[:, axis], "right")
            return axis, cuts, [slabs(x[side == i], at + 1, math.ceil(left / parts)) for i in range(len(cuts) + 1)]

        self.root = slabs(sample, 0, cells)
        self.n = next(self.numbers)
        del self.numbers

    def assign(self, x: np.ndarray) -> np.ndarray:
        out = np.empty(len(x), dtype=np.int64)
        todo = [(self.root, np.arange(len(x)))]
        while todo:
            node, rows = todo.pop()
            if isinstance(node, int):
                out[rows] = node
                continue
            axis, cuts, below = node
            side = np.searchsorted(cuts, x[rows, axis], "right")
            todo += [(b, rows[side == i]) for i, b in enumerate(below)]
        return out

    def bounded(self, order: np.ndarray, low: np.ndarray, high: np.ndarray) -> None:
        """Pack the cells, in order of their numbers (which follow the slabs), into nodes up to one root."""
        by = np.argsort(order)
        names, low, high = order[by], low[by], high[by]
        self.levels = [(low, high, names)]
        while len(low) > 1:
            heads = np.arange(0, len(low), FANOUT)
            low, high = np.minimum.reduceat(low, heads), np.maximum.reduceat(high, heads)
            self.levels.append((low, high, heads))

    def meets(self, x: np.ndarray, radius: float) -> list[int]:
        at = np.arange(len(self.levels[-1][0]))
        for level in range(len(self.levels) - 1, 0, -1):
            low, high, heads = self.levels[level]
            at = at[_gaps(low[at], high[at], x) <= radius]
            below = len(self.levels[level - 1][0])
            at = np.concatenate([np.arange(heads[i], min(heads[i] + FANOUT, below)) for i in at]) if len(at) else at
        low, high, names = self.levels[0]
        return names[at[_gaps(low[at], high[at], x) <= radius]].tolist()


@dataclass
class Brick:
    """A region: its part of space (a box), the bricks that were taken out of it, and the cell of what is left."""

    low: np.ndarray
    high: np.ndarray
    cell: int = -1
    holes: list[Brick] = field(default_factory=list)


class HoleyBricks:
    """Regions with holes: of an overfull region a box with one to two thirds of its points is taken out, found by following k-d cuts to the
    fuller side, so neither part is small though cuts never divide a box that was taken out."""

    def __init__(self, sample: np.ndarray, cells: int):
        self.aim = max(1, len(sample) / cells)
        d = sample.shape[1]
        numbers = itertools.count()

        def divide(brick: Brick, x: np.ndarray) -> None:
            while len(x) > 1.5 * self.aim:
                low, high, inside = brick.low.copy(), brick.high.copy(), np.ones(len(x), dtype=bool)
                while inside.sum() > 2 / 3 * len(x):
                    held = x[inside]
                    axis = int(np.argmax(np.ptp(held, axis=0)))
                    at = float(np.median(held[:, axis]))
                    below = inside & (x[:, axis] < at)
                    above = inside & (x[:, axis] >= at)
                    if not below.any() or not above.any():
                        break
                    if below.sum() > above.sum():
                        inside, high[axis] = below, at
                    else:
                        inside, low[axis] = above, at
                if inside.all():
                    break
                hole = Brick(low, high)
                brick.holes.append(hole)
                divide(hole, x[inside])
                x = x[~inside]
            brick.cell = next(numbers)

        self.root = Brick(np.full(d, -np.inf), np.full(d, np.inf))
        divide(self.root, sample)
        self.n = next(numbers)

    def assign(self, x: np.ndarray) -> np.ndarray:
        """A point belongs to the first hole that has it, on and on, else to what is left of the region."""
        out = np.empty(len(x), dtype=np.int64)
        todo = [(self.root, np.arange(len(x)))]
        while todo:
            brick, rows = todo.pop()
            for hole in brick.holes:
                inside = ((x[rows] >= hole.low) & (x[rows] < hole.high)).all(axis=1)
                todo.append((hole, rows[inside]))
                rows = rows[~inside]
            out[rows] = brick.cell
        return out

    def bounded(self, order: np.ndarray, low: np.ndarray, high: np.ndarray) -> None:
        self.boxes = {int(c): i for i, c in enumerate(order)}
        self.low, self.high = low, high

    def meets(self, x: np.ndarray, radius: float) -> list[int]:
        out, todo = [], [self.root]
        while todo:
            brick = todo.pop()
            todo += [h for h in brick.holes if _gaps(h.low[None], h.high[None], x)[0] <= radius]
            # a ball that lies within one hole does not reach what is left of the region
            if any((x - h.low > radius).all() and (h.high - x > radius).all() for h in brick.holes):
                continue
            i = self.boxes.get(brick.cell)
            if i is not None and _gaps(self.low[i : i + 1], self.high[i : i + 1], x)[0] <= radius:
                out.append(brick.cell)
        return out


KINDS = {"kdtree": KdTree, "rtree": PackedBoxes, "hbtree": HoleyBricks}


def knn(vectors: DataFrame, k: int, kind: str = "kdtree", id_column: str = "vec_id", column: str = "embedding") -> DataFrame:
    """Exact k nearest neighbours (by cosine, self excluded): ``qid, oid, sim, rnk``.

    Cells hold about CELL vectors of the sample's share: with more than SAMPLE vectors the number of cells still follows the number of
    vectors, as cells are cut finer than the sample fills them, down to single sampled vectors; from there on cells grow, and are compared
    in blocks, so a task's memory stays bounded. Tight boxes of the cells (one row a cell) reach the driver.
    """
    unit = materialise(unit_vectors(vectors, id_column, column), "unit")
    spark, n = vectors.sparkSession, unit.count()
    if not n:
        return unit.select(F.col("id").alias("qid"), F.col("id").alias("oid"), F.lit(0.0).alias("sim"), F.lit(0).alias("rnk"))
    drawn = unit.orderBy(F.xxhash64("id")).limit(SAMPLE).toPandas()
    sample = np.stack(drawn["v"].to_numpy())
    cut = KINDS[kind](sample, int(min(len(sample), max(1, -(-n // CELL)))))
    plan = spark.sparkContext.broadcast(cut)  # cells are no more than sampled vectors

    def assign(v: pd.Series) -> pd.Series:
        return pd.Series(plan.value.assign(np.stack(v.to_numpy())) if len(v) else np.zeros(0, dtype=np.int64))

    held = materialise(unit.withColumn("cell", F.pandas_udf(assign, "long")("v")), "cells")
    size = sample.shape[1]
    ends = held.groupBy("cell").agg(*[f(F.get("v", F.lit(j))).alias(f"{a}{j}") for j in range(size) for a, f in (("l", F.min), ("h", F.max))]).toPandas()
    cut.bounded(ends["cell"].to_numpy(), ends[[f"l{j}" for j in range(size)]].to_numpy(), ends[[f"h{j}" for j in range(size)]].to_numpy())
    tree = spark.sparkContext.broadcast(cut)
    pairs = "qid long, oid long, sim double"

    def best(ids: np.ndarray, sims: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The first k of each row by rounded similarity, then id (ids ascend along a row of equals)."""
        order = np.lexsort((ids, -np.round(sims, 9)), axis=1)[:, :k]
        return np.take_along_axis(ids, order, axis=1), np.take_along_axis(sims, order, axis=1)

    def search(queries: pd.DataFrame, cell: pd.DataFrame) -> pd.DataFrame:
        if not len(queries) or not len(cell):
            return pd.DataFrame(columns=["qid", "oid", "sim"])
        names, stored = cell["i"].to_numpy(), np.stack(cell["x"].to_numpy())
        out = []
        for a in range(0, len(queries), BLOCK):
            part = queries.iloc[a : a + BLOCK]
            own, x = part["id"].to_numpy(), np.stack(part["v"].to_numpy())
            ids, sims = np.zeros((len(part), 0), dtype=np.int64), np.zeros((len(part), 0))
            for b in range(0, len(stored), BLOCK):
                sim = x @ stored[b : b + BLOCK].T
                there = np.broadcast_to(names[b : b + BLOCK], sim.shape)
                sim[own[:, None] == there] = -9
                ids, sims = best(np.concatenate([ids, there], axis=1), np.concatenate([sims, sim], axis=1))
            out.append(pd.DataFrame({"qid": np.repeat(own, ids.shape[1]), "oid": ids.ravel(), "sim": sims.ravel()}))
        found = pd.concat(out)
        return found[found["sim"] > -2]

    stored = held.select(F.col("cell").alias("c"), F.col("id").alias("i"), F.col("v").alias("x"))
    home = held.groupBy("cell").cogroup(stored.groupBy("c")).applyInPandas(lambda a, b: search(a, b), pairs)
    # similarities that round alike are ties, so the ball takes in all that could round to the k-th one
    radius = top_k(home, k).where(F.col("rnk") == k).select(F.col("qid").alias("id"), F.sqrt(F.greatest(F.lit(0.0), 2 - 2 * (F.col("sim") - 2e-9))).alias("radius"))

    def others(v: pd.Series, cell: pd.Series, radius: pd.Series) -> pd.Series:
        met = tree.value.meets
        return pd.Series([[c for c in met(x, r + 1e-9) if c != own] for x, own, r in zip(v, cell, radius.fillna(9.0), strict=True)])

    visits = held.join(radius, "id", "left").withColumn("to", F.explode(F.pandas_udf(others, "array<long>")("v", "cell", "radius"))).select("id", "v", F.col("to").alias("cell"))
    away = visits.groupBy("cell").cogroup(stored.groupBy("c")).applyInPandas(lambda a, b: search(a, b), pairs)
    return top_k(home.union(away), k)
