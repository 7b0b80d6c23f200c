"""The relational operators that users of a sort engine need beside it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

BROADCAST_ROWS = 1_000_000

# --- projection, filters ---


def project(df: DataFrame, exprs: dict[str, Column]) -> DataFrame:
    return df.select(*[c.alias(n) for n, c in exprs.items()])


def where(df: DataFrame, cond: Column | str) -> DataFrame:
    return df.where(cond)


def key_range(df: DataFrame, key: str, lo, hi) -> DataFrame:
    """lo <= key < hi, in a form that reaches the scan."""
    return df.where((F.col(key) >= F.lit(lo)) & (F.col(key) < F.lit(hi)))


def by_locator(df: DataFrame, rows: DataFrame) -> DataFrame:
    """Rows of a file scan by (file_path, row_index)."""
    from ..sources import with_locator

    return with_locator(df).join(rows, ["file_path", "row_index"], "left_semi")


def dedup(df: DataFrame, cols: list[str] | None = None) -> DataFrame:
    return df.dropDuplicates(cols) if cols else df.distinct()


def sample_keys(df: DataFrame, fraction: float, seed: int = 1, by: str | None = None, shares: dict | None = None) -> DataFrame:
    return df.sampleBy(by, shares, seed) if by else df.sample(fraction, seed)


# --- joins ---


def join(a: DataFrame, b: DataFrame, on, how: str = "inner") -> DataFrame:
    return a.join(b, on, how)


def join_broadcast(a: DataFrame, b: DataFrame, on, how: str = "inner") -> DataFrame:
    """Broadcast ``b`` where its count allows; else leave the choice to Spark."""
    return a.join(F.broadcast(b) if b.count() <= BROADCAST_ROWS else b, on, how)


def join_hash(a: DataFrame, b: DataFrame, on) -> DataFrame:
    return a.join(b.hint("SHUFFLE_HASH"), on)


def join_sort_merge(a: DataFrame, b: DataFrame, on) -> DataFrame:
    return a.join(b.hint("MERGE"), on)


def join_theta(a: DataFrame, b: DataFrame, cond: Column) -> DataFrame:
    """Any condition; ``b`` must be small, since every pair is looked at."""
    n = b.count()
    if n > 10_000:
        raise ValueError(f"a theta join with {n} rows on its small side; use join_range or join_overlap")
    return a.join(F.broadcast(b), cond)


def join_range(points: DataFrame, spans: DataFrame, at: str, lo: str, hi: str, width: float) -> DataFrame:
    """Points with lo <= at < hi: spans go to the bins they touch, points to theirs."""
    p = points.withColumn("__bin", F.floor(F.col(at) / width))
    bins = F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))
    s = spans.withColumn("__bin", F.explode(bins))
    return p.join(s, "__bin").where((F.col(at) >= F.col(lo)) & (F.col(at) < F.col(hi))).drop("__bin")


def join_overlap(a: DataFrame, b: DataFrame, alo: str, ahi: str, blo: str, bhi: str, width: int) -> DataFrame:
    """Pairs of half-open intervals that overlap, each once: in the first bin both touch."""
    bins = lambda lo, hi: F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor((F.col(hi) - 1) / width)))
    x, y = a.withColumn("__bin", bins(alo, ahi)), b.withColumn("__bin", bins(blo, bhi))
    first = F.floor(F.greatest(alo, blo) / width)
    return x.join(y, "__bin").where((F.col(alo) < F.col(bhi)) & (F.col(blo) < F.col(ahi)) & (F.col("__bin") == first)).drop("__bin")


def join_asof(left: DataFrame, right: DataFrame, by: list[str], time: str, value: str) -> DataFrame:
    """Left rows with the value of the latest right row at or before their time: one sort, no pairs."""
    fields = [c for c in left.columns if c not in (*by, time)]
    a = left.select(*by, time, F.lit(1).alias("__s"), F.struct(*fields).alias("__l"), F.lit(None).cast(dict(right.dtypes)[value]).alias("__v"))
    b = right.select(*by, time, F.lit(0).alias("__s"), F.lit(None).cast(a.schema["__l"].dataType).alias("__l"), F.col(value).alias("__v"))
    w = Window.partitionBy(*by).orderBy(time, "__s").rowsBetween(Window.unboundedPreceding, 0)
    out = a.unionByName(b).withColumn(value, F.last("__v", ignorenulls=True).over(w)).where("__s = 1")
    return out.select(*by, time, *[F.col(f"__l.{c}").alias(c) for c in fields], value)


def join_cross(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.crossJoin(b)


def join_lateral(a: DataFrame, b: DataFrame, on: Column, by: list[Column], k: int) -> DataFrame:
    """The first k rows of ``b`` for each row of ``a``, repeated rows of ``a`` each with their own."""
    left = a.withColumn("__row", F.monotonically_increasing_id())
    w = Window.partitionBy("__row").orderBy(*by)
    return left.join(b, on).withColumn("__k", F.row_number().over(w)).where(F.col("__k") <= k).drop("__k", "__row")


def join_skew(a: DataFrame, b: DataFrame, on: str, salt: int = 8) -> DataFrame:
    """Equi-join with hot keys in ``a``: its rows are salted, ``b``'s rows repeated for each salt."""
    x = a.withColumn("__salt", F.pmod(F.monotonically_increasing_id(), F.lit(salt)))
    y = b.withColumn("__salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salt - 1).cast("long"))))
    return x.join(y, [on, "__salt"]).drop("__salt")


# --- aggregates ---


def agg_hash(df: DataFrame, by: list[str], aggs: dict[str, Column]) -> DataFrame:
    return df.groupBy(*by).agg(*[c.alias(n) for n, c in aggs.items()])


def agg_sorted(df: DataFrame, key: str, aggs: dict[str, Column]) -> DataFrame:
    """Aggregate on a range-partitioned key: no further shuffle."""
    return df.repartitionByRange(key).sortWithinPartitions(key).groupBy(key).agg(*[c.alias(n) for n, c in aggs.items()])


def agg_distinct(df: DataFrame, c: str, rsd: float | None = None) -> Column:
    return F.countDistinct(c) if rsd is None else F.approx_count_distinct(c, rsd)


def agg_cube(df: DataFrame, dims: list[str], aggs: dict[str, Column], rollup: bool = False) -> DataFrame:
    grouped = df.rollup(*dims) if rollup else df.cube(*dims)
    return grouped.agg(F.grouping_id().alias("gid"), *[c.alias(n) for n, c in aggs.items()])


def agg_pivot(df: DataFrame, by: list[str], col: str, values: list, agg: Column) -> DataFrame:
    return df.groupBy(*by).pivot(col, values).agg(agg)


def unpivot(df: DataFrame, ids: list[str], columns: list[str], name: str = "name", value: str = "value") -> DataFrame:
    return df.unpivot(ids, columns, name, value)


def agg_corr(df: DataFrame, by: list[str], x: str, y: str) -> DataFrame:
    return df.groupBy(*by).agg(F.corr(x, y).alias("corr"))


def agg_quantile(df: DataFrame, by: list[str], c: str, ps: list[float], exact: bool = False) -> DataFrame:
    f = F.percentile(c, ps) if exact else F.percentile_approx(c, ps)
    return df.groupBy(*by).agg(f.alias("quantiles"))


def agg_argmax(df: DataFrame, by: list[str], c: str, order: str) -> DataFrame:
    return df.groupBy(*by).agg(F.max_by(c, order).alias(c))


def agg_collect(df: DataFrame, by: list[str], c: str) -> DataFrame:
    return df.groupBy(*by).agg(F.sort_array(F.collect_list(c)).alias(c))


def agg_stats(df: DataFrame, by: list[str], c: str) -> DataFrame:
    return df.groupBy(*by).agg(F.avg(c).alias("mean"), F.stddev(c).alias("deviation"))


def agg_filtered(df: DataFrame, by: list[str], conds: dict[str, Column]) -> DataFrame:
    return df.groupBy(*by).agg(*[F.count(F.when(c, 1)).alias(n) for n, c in conds.items()])


def agg_having(df: DataFrame, by: list[str], aggs: dict[str, Column], cond: str) -> DataFrame:
    return agg_hash(df, by, aggs).where(cond)


def agg_key_histogram(idx: DataFrame, prefix: int = 1) -> DataFrame:
    return idx.groupBy(F.hex(F.substring("key", 1, prefix)).alias("prefix")).agg(F.count("*").alias("n"))


# --- windows, sorts, sets ---


def win_rank(df: DataFrame, p: list[str], o: list[Column]) -> DataFrame:
    w = Window.partitionBy(*p).orderBy(*o)
    return df.select("*", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("quarter"))


def win_share(df: DataFrame, p: list[str], o: list[Column]) -> DataFrame:
    """Each row's place as a share of its partition."""
    w = Window.partitionBy(*p).orderBy(*o)
    return df.select("*", F.percent_rank().over(w).alias("percent"), F.cume_dist().over(w).alias("cume"))


def win_ends(df: DataFrame, p: list[str], o: list[Column], c: str, n: int = 2) -> DataFrame:
    """The first, last and n-th value of each whole partition."""
    w = Window.partitionBy(*p).orderBy(*o).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return df.select("*", F.first_value(c).over(w).alias("first"), F.last_value(c).over(w).alias("last"), F.nth_value(c, n).over(w).alias("nth"))


def win_shift(df: DataFrame, p: list[str], o: list[Column], c: str, k: int = 1) -> DataFrame:
    w = Window.partitionBy(*p).orderBy(*o)
    return df.select("*", F.lag(c, k).over(w).alias("before"), F.lead(c, k).over(w).alias("after"))


def win_frame(df: DataFrame, p: list[str], o: list[Column], c: str, lo: int, hi: int) -> DataFrame:
    return df.withColumn("framed", F.sum(c).over(Window.partitionBy(*p).orderBy(*o).rowsBetween(lo, hi)))


def topk_per_group(df: DataFrame, p: list[str], o: list[Column], k: int) -> DataFrame:
    """A limited window: rows beyond k leave before the shuffle."""
    return df.withColumn("rn", F.row_number().over(Window.partitionBy(*p).orderBy(*o))).where(F.col("rn") <= k)


def page(df: DataFrame, order: list[Column], k: int, off: int) -> DataFrame:
    return df.orderBy(*order).offset(off).limit(k)


def union_all(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b)


def intersect_all(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows in both, as often as the side that has them less often."""
    return a.intersectAll(b)


def is_permutation(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows of either side that the other lacks, counted: both zero proves a permutation."""
    return a.exceptAll(b).agg(F.count("*").alias("missing")).join(b.exceptAll(a).agg(F.count("*").alias("extra")), F.lit(True))
