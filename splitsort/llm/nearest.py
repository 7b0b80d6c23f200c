"""Approximate nearest neighbours by collision counting on single-projection sorted arrays.

Every block of vectors is cut into ranges of nearly equal norm, where the largest inner product becomes the
least distance by one extra coordinate that brings all vectors to the range's largest norm.  Each range
keeps, for each direction of a random rotation, the sorted array of its projections.  Around a query's projections windows open on all arrays at once; a
vector collides where its projection lies in the window.  Virtual rehashing widens all windows by one factor at
a time until enough vectors exceed the collision threshold; those, and only those, are verified by their inner
products.  Ranges follow by falling norm; a query leaves out those whose norm can't reach its k-th score.
Queries and rows meet in a grid of blocks, and each query keeps its best of each block.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Rows and queries of one meeting; share of the projections on which a candidate collides.
ROWS, QUERIES, THRESHOLD = 8192, 2048, 0.9
#: Windows widen by GROW from the narrowest of LEVELS; they stop at this share of the range's vectors.
GROW, LEVELS, ENOUGH, LEAST = 1.12, 28, 0.06, 200
#: Largest norm of a range by its least, but in ranges of up to LEAST vectors, which are verified whole.
EVEN = 1.05


def usable(vec: Column) -> Column:
    """Not null, not zero, and all components finite."""
    bad = F.exists(vec, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return vec.isNotNull() & ~F.coalesce(bad, F.lit(True)) & F.exists(vec, lambda x: x != 0)


def rotation(dim: int, seed: int) -> np.ndarray:
    """A random orthonormal basis of ``dim`` directions."""
    q, r = np.linalg.qr(np.random.default_rng(seed).normal(size=(dim, dim)))
    return q * np.sign(np.diag(r))


def exact_scores(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Inner products in double precision, summed component by component, alike for equal vectors."""
    total = np.zeros(len(x))
    for d in range(x.shape[1]):
        total += x[:, d] * q[d]
    return total


class Block:
    """The collision index of distinct vectors, none longer than ``norm``."""

    def __init__(self, x: np.ndarray, norm: float, seed: int, least: int = LEAST) -> None:
        self.x = x
        lift = np.sqrt(np.maximum(norm**2 - (x**2).sum(axis=1), 0.0))
        self.basis = rotation(x.shape[1] + 1, seed)
        proj = np.column_stack([x, lift]) @ self.basis
        self.order = np.argsort(proj, axis=0, kind="stable").T.copy()
        self.sorted = np.take_along_axis(proj.T, self.order, axis=1)
        self.norm = norm
        self.radius = norm / np.sqrt(x.shape[1] + 1) * GROW ** np.arange(LEVELS)
        self.allowed = proj.shape[1] - int(np.ceil(THRESHOLD * proj.shape[1]))
        self.enough = min(len(x), max(least, int(ENOUGH * len(x))))

    def windows(self, queries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ends of the windows of all queries, levels and arrays: queries x levels x arrays."""
        unit = queries / np.sqrt((queries**2).sum(axis=1, keepdims=True)) * self.norm
        at = np.column_stack([unit, np.zeros(len(queries))]) @ self.basis
        lo = np.empty((len(queries), LEVELS, len(self.sorted)), np.int32)
        hi = np.empty_like(lo)
        for j, row in enumerate(self.sorted):
            lo[:, :, j] = np.searchsorted(row, at[:, j, None] - self.radius, "left")
            hi[:, :, j] = np.searchsorted(row, at[:, j, None] + self.radius, "right")
        return lo, hi

    def candidates(self, lo: np.ndarray, hi: np.ndarray, level: int) -> tuple[np.ndarray, int]:
        """Vectors above the threshold at the first level, from ``level`` on, that gives enough of them."""
        n = len(self.x)
        while True:
            # Collisions are counted by their complement: what each array holds outside its window.
            parts = [o[:a] for o, a in zip(self.order, lo[level], strict=True)] + [o[b:] for o, b in zip(self.order, hi[level], strict=True)]
            outside = np.bincount(np.concatenate(parts), minlength=n)
            found = np.flatnonzero(outside <= self.allowed)
            if len(found) >= self.enough:
                return found, level
            if level + 1 == LEVELS:  # windows at their widest: all vectors are verified
                return np.arange(n), level
            level += 1


def norm_ranges(norms: np.ndarray, least: int = LEAST) -> list[np.ndarray]:
    """Places of all vectors by falling norm, cut where the norm has fallen by EVEN and ``least`` vectors are in."""
    order = np.argsort(-norms, kind="stable")
    falling, at, out = -norms[order], 0, []
    while at < len(order):
        end = max(at + least, int(np.searchsorted(falling, falling[at] / EVEN, "right")))
        out.append(order[at:end])
        at = end
    return out


def _meet(k: int, norm: float, seed: int):
    least = max(LEAST, 4 * k)  # a block must hold more candidates than answers

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches))
        ids, query = t.column("vec_id").to_numpy(), t.column("query").to_numpy()
        flat = t.column("v").combine_chunks().flatten().to_numpy().reshape(len(t), -1)
        rows, asked = ~query, np.flatnonzero(query)
        if not rows.any() or not len(asked):
            return
        # Equal vectors are one: a mass of copies can't crowd out a query's other neighbours.
        order = np.argsort(ids[rows], kind="stable")
        own, vec = ids[rows][order], flat[rows][order]
        _, first, same = np.unique(np.ascontiguousarray(vec + 0.0).view(f"V{8 * vec.shape[1]}").ravel(), return_index=True, return_inverse=True)
        members = np.split(own[np.argsort(same, kind="stable")], np.bincount(same).cumsum()[:-1])
        x, qs = vec[first], flat[asked]
        norms, lengths = np.sqrt((x**2).sum(axis=1)), np.sqrt((qs**2).sum(axis=1))
        best: list[list[tuple[float, int]]] = [[] for _ in qs]
        slack = 1e-9 * max(1.0, norm**2)
        for part in norm_ranges(norms, least):
            top = float(norms[part[0]])
            # No vector of this range or a later one has a larger product than top times the query's length.
            live = [i for i, b in enumerate(best) if len(b) < k or -b[-1][0] <= top * lengths[i] + slack]
            if not live:
                break
            block = Block(x[part], top, seed, least)
            whole = block.enough == len(part)
            if not whole:
                lo, hi = block.windows(qs[live])
                start = min(block.candidates(lo[i], hi[i], 0)[1] for i in range(0, len(live), -(-len(live) // 8)))
            for w, i in enumerate(live):
                q, me = qs[i], ids[asked[i]]
                found = np.arange(len(part)) if whole else block.candidates(lo[w], hi[w], start)[0]
                rough = block.x[found] @ q
                if len(rough) > k + 1:
                    found = found[rough >= np.partition(rough, -k - 1)[-k - 1] - slack]
                score = exact_scores(block.x[found], q)
                got = best[i] + [(-s, int(v)) for s, f in zip(score, part[found], strict=True) for v in members[f][: k + 1] if v != me]
                got.sort()
                best[i] = got[:k]
        out_q = [ids[a] for a, b in zip(asked, best, strict=True) for _ in b]
        out_v, out_s = [v for b in best for _, v in b], [-s for b in best for s, _ in b]
        yield pa.RecordBatch.from_arrays([pa.array(out_q, pa.int64()), pa.array(out_v, pa.int64()), pa.array(out_s, pa.float64())], ["query_id", "vec_id", "score"])

    return run


def nearest(vectors: DataFrame, is_query: Column, k: int = 20, vec_id: str = "vec_id", embedding: str = "embedding", seed: int = 4) -> DataFrame:
    """``(query_id, rank, vec_id, score)``: each query's ``k`` rows of largest inner product, ties to the smaller id.

    Every usable row is indexed and is a candidate, the query's own id excepted.  Rows whose id is null
    or whose vector is null, zero, or holds a null or non-finite component take no part; vectors meet only those of
    their own length.  With fewer than ``k`` candidates all are returned; empty in, empty out.

    Shuffles: each row once for each block of queries and each query once for each block of rows, then k
    rows for each query and block.
    """
    v = F.col(f"`{embedding}`")
    rows = vectors.select(F.col(f"`{vec_id}`").cast("long").alias("vec_id"), v.alias("v"), is_query.alias("query"))
    rows = rows.where(F.col("vec_id").isNotNull() & usable(F.col("v")))
    rows = rows.select("vec_id", F.transform("v", lambda x: x.cast("double")).alias("v"), F.coalesce("query", F.lit(False)).alias("query"))
    square = F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x)
    n, nq, top = rows.agg(F.count("*"), F.count(F.when(F.col("query"), 1)), F.max(F.sqrt(square))).first()
    nd, nq = max(1, -(-n // ROWS)), max(1, -(-nq // QUERIES))
    mine = lambda blocks, salt: F.pmod(F.xxhash64(F.lit(salt), "vec_id"), F.lit(blocks)).cast("int")
    data = rows.select(F.size("v").alias("dim"), mine(nd, 1).alias("d"), F.explode(F.sequence(F.lit(0), F.lit(nq - 1))).alias("q"), "vec_id", "v", F.lit(False).alias("query"))
    asked = rows.where("query").select(F.size("v").alias("dim"), F.explode(F.sequence(F.lit(0), F.lit(nd - 1))).alias("d"), mine(nq, 2).alias("q"), "vec_id", "v", F.lit(True).alias("query"))
    best = data.unionByName(asked).groupBy("dim", "d", "q").applyInArrow(_meet(k, float(top or 1.0), seed), "query_id long, vec_id long, score double")
    order = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    return best.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
