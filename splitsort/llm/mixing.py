"""Mixing sources to target weights by pivotal dependent rounding.

A source whose target is r times its size asks for r copies of each of its documents: floor(r) whole
ones and a fraction.  Fractions are rounded in pairs: the words of one document's fraction move to
the other or back, with chances that keep each document's expectation, until one of the two is
integral; the other meets the next document.  The words of a source are kept exactly by every such
move.  Groups of bounded size do this side by side; the one fractional document that each leaves goes
up a reduction tree, where residuals meet again, and only the last one of a source is rounded alone.
So a source misses its target by less than one document.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import apart, placed, repeat_salt, small, staged, unstage, words

#: Weights of sources by rank, repeating; most copies of a document.
WEIGHTS, MOST = (5.0, 2.0, 1.0), 3.0
#: Documents that meet in one task of the first level, and residuals of one node of the tree.
GROUP, FAN_IN = 20_000, 64


def source_targets(sizes: DataFrame, weights: tuple[float, ...] = WEIGHTS, most: float = MOST) -> DataFrame:
    """``(source, source_size)`` with ``target``: shares by weight, none above ``most`` times the size.

    Sources are ranked by code point, null last.  Handing the excess round again and again ends where
    each target is the lesser of its cap and one common price times its weight; sorted by cap over
    weight, that price follows from running sums.  Runs over one row for each source.
    """
    rank = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*map(F.lit, weights)), (rank % len(weights) + 1).cast("int"))
    t = sizes.select("source", "source_size", weight.alias("w"), (F.lit(most) * F.col("source_size")).alias("cap"))
    byratio = Window.orderBy(F.col("cap") / F.col("w"), F.col("source").asc_nulls_last())
    before, rest = byratio.rowsBetween(Window.unboundedPreceding, -1), byratio.rowsBetween(0, Window.unboundedFollowing)
    everyone = Window.partitionBy(F.lit(0))
    t = t.withColumn("total", F.sum("source_size").over(everyone).cast("double"))
    t = t.withColumn("price", (F.col("total") - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("w").over(rest))
    free = F.when(F.col("price") * F.col("w") < F.col("cap"), F.col("price"))
    t = t.withColumn("price", F.max(free).over(everyone))  # that of the first source no cap binds; later ones are lower
    return t.select("source", "source_size", F.least("cap", F.coalesce(F.col("price") * F.col("w"), "cap")).alias("target"))


def _round(p: np.ndarray, size: np.ndarray, u: np.ndarray) -> int:
    """Round the fractions ``p`` in place, pair by pair; the index left with a fraction, or -1."""
    held = -1
    for k in range(len(p)):
        if not 0.0 < p[k] < 1.0:
            continue
        if held < 0:
            held = k
            continue
        si, sk = size[held], size[k]
        up, down = min((1 - p[held]) * si, p[k] * sk), min(p[held] * si, (1 - p[k]) * sk)  # words that can move
        if u[k] * (up + down) < down:
            p[held] += up / si
            p[k] -= up / sk
            full, empty = ((1 - p[held]) * si <= 1e-9 * si), (p[k] * sk <= 1e-9 * sk)
            if full:
                p[held] = 1.0
            if empty:
                p[k] = 0.0
        else:
            p[held] -= down / si
            p[k] += down / sk
            if p[held] * si <= 1e-9 * si:
                p[held] = 0.0
            if (1 - p[k]) * sk <= 1e-9 * sk:
                p[k] = 1.0
        left = [j for j in (held, k) if 0.0 < p[j] < 1.0]
        held = left[0] if left else -1
    return held


def _pair(frame: pd.DataFrame) -> pd.DataFrame:
    # Largest first: what a large document has left over can still be settled by many small ones.
    frame = frame.sort_values(["size", "h", "uid"], ascending=[False, True, True], kind="stable")
    p = frame["p"].to_numpy(np.float64).copy()
    u = (frame["h"].to_numpy(np.int64).view(np.uint64) >> np.uint64(11)) / float(1 << 53)
    _round(p, frame["size"].to_numpy(np.float64), u)
    return frame.assign(p=p)


def _plan(rows: DataFrame, file: str, row: str, text: str, source: str, seed: int, keys: list[Column]) -> DataFrame:
    """``(file, row, size, source_size, target, copies)`` of rows that ``placed`` has named."""
    marked = rows.select(
        F.col(file).alias("f"),
        F.col(row).alias("r"),
        F.xxhash64(F.lit(seed), *keys).alias("h"),
        words(F.col(f"`{text}`")).alias("size"),
        F.col(f"`{source}`").alias("source"),
        F.monotonically_increasing_id().alias("uid"),
    )
    marked = staged(marked, "mix")
    sums = staged(marked.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("rows")), "sources")
    target = staged(source_targets(sums.select("source", "source_size")), "targets")
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0) + 1e-12
    per = target.join(sums.select(F.col("source").alias("other"), "rows"), F.col("source").eqNullSafe(F.col("other"))).select(
        F.col("source").alias("ts"),
        "source_size",
        "target",
        F.floor(rate).alias("base"),
        (rate - F.floor(rate)).alias("frac"),
        F.xxhash64("source").alias("sid"),
        F.ceil(F.col("rows") / GROUP).alias("groups"),
    )
    per = small(staged(per, "rates"), sums.count(), 100_000)
    rated = marked.join(per, F.col("source").eqNullSafe(F.col("ts")))
    chosen, dead = _pivot(rated, repeat_salt(marked.select("h"), GROUP), seed)
    n = F.when(F.col("size") > 0, F.col("base") + F.coalesce(F.col("p"), F.lit(0.0))).otherwise(0).cast("int")
    plan = rated.join(chosen, "uid", "left").select(F.col("f").alias(file), F.col("r").alias(row), "size", "source_size", "target", n.alias("copies"))
    plan = staged(plan, "copies")
    unstage(marked, sums, target, *dead)
    return plan


def _keys(docs: DataFrame) -> list[Column]:
    return [F.col(f"`{c}`").cast("string") if t.startswith("map") else F.col(f"`{c}`") for c, t in docs.dtypes]


def mix(
    docs: DataFrame, text: str = "text", source: str = "source", seed: int = 9, carry: list[str] | None = None
) -> DataFrame:
    """All rows of ``docs`` with ``size``, ``source_size``, ``target`` and whole ``copies``.

    Size counts words; null and empty texts have size 0 and are not copied.  ``copies`` is 0 to 3.  A
    null source is a source of its own, after all others.  Rows are placed and rolled for by a hash of
    their content and the seed, so reruns agree (see ``repeat_salt`` for masses of equal rows).
    ``carry`` names the columns to pass through (default: all); those with the names of the four new
    ones are replaced.  Empty in, empty out.

    Shuffles: 60 bytes for each document into its group, once, and again less at each level of the
    tree; the columns carried move once, in the join by place at the end.
    """
    new = ("size", "source_size", "target", "copies")
    names = [c for c in (docs.columns if carry is None else carry) if c not in new]
    file, row = apart(docs, "f", "r")
    rows = placed(docs, file, row)
    plan = _plan(rows, file, row, text, source, seed, _keys(docs))
    return rows.select(file, row, *[F.col(f"`{c}`") for c in names]).join(plan, [file, row]).select(*[F.col(f"`{c}`") for c in names], *new)


def mixture(docs: DataFrame, text: str = "text", source: str = "source", seed: int = 9) -> DataFrame:
    """The mix itself: each row of ``docs``, all its columns unchanged, as many times as ``mix`` gives it copies."""
    file, row, size, source_size, target, n, k = apart(docs, "f", "r", "size", "source_size", "target", "copies", "k")
    rows = placed(docs, file, row)
    plan = _plan(rows, file, row, text, source, seed, _keys(docs)).where("copies > 0").select(file, row, F.col("copies").alias(n))
    out = rows.join(plan, [file, row]).select(*[F.col(f"`{c}`") for c in docs.columns], F.explode(F.array_repeat(F.lit(True), F.col(n))).alias(k))
    return out.select(*[F.col(f"`{c}`") for c in docs.columns])


def _pivot(rated: DataFrame, salt: Column, seed: int) -> tuple[DataFrame, list[DataFrame]]:
    """``(uid, p)``: the documents whose fraction was rounded up (1.0) or down (0.0); and the tables behind it."""
    live = rated.where("frac > 1e-9 AND size > 0").select(
        "uid", "h", "size", F.col("frac").alias("p"), "sid", "groups", F.pmod(F.xxhash64("h", salt), F.col("groups")).alias("g")
    )
    shape = "uid long, h long, size long, p double, sid long, groups long, g long"
    settled, levels = None, []
    while True:
        level = staged(live.groupBy("sid", "g").applyInPandas(_pair, shape), "pairs")
        levels.append(level)
        whole = level.where("p <= 0 OR p >= 1").select("uid", "p")
        settled = whole if settled is None else settled.unionAll(whole)
        left = level.where("p > 0 AND p < 1")
        most = left.agg(F.max("groups")).first()[0]
        if most is None or most == 1:  # one residual for each source: rounded alone
            roll = F.shiftrightunsigned(F.xxhash64(F.lit(~seed), "h"), 11) / F.lit(float(1 << 53)) < F.col("p")
            return settled.unionAll(left.select("uid", F.when(roll, 1.0).otherwise(0.0).alias("p"))), levels
        live = left.withColumn("g", F.floor(F.col("g") / FAN_IN)).withColumn("groups", F.ceil(F.col("groups") / FAN_IN))
