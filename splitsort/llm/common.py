"""What the operators of this subpackage share: tables, staging, repeats and components.

Conventions of all operators here:

* inputs are DataFrames; the caller names the id and text columns, and all other columns pass
  through untouched.  Working columns get names that no input column has (see ``apart``);
* rows are known by their place in the files (see ``placed``), so that an id may be null or repeated;
* a null text counts as the empty text unless an operator's docstring says otherwise;
* lineage is cut by written Parquet in the folder named by ``spark.checkpoint.dir``, never by a
  local checkpoint, so that a lost executor costs a re-read and nothing else.
"""

from __future__ import annotations

import contextlib
import ctypes
import gc
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

#: Words of every contract here: maximal runs of anything but space and the ASCII controls 9 to 13.
WORD = r"[^\x20\x09-\x0D]+"

#: Near duplicates of any kind are linked from this Jaccard similarity, in per cent.
PERCENT = 75

#: A broadcast side may hold at most this many rows of a few longs each (about 30 MB on the heap).
BROADCAST_ROWS = 400_000

#: Edges up to which what is left of a graph is united on the driver (16 bytes each): a round costs six shuffles however small it is.
EDGES_HERE = 200_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def widened(df: DataFrame, **kinds: str) -> StructType:
    """The schema of ``df`` with further columns, as a new object."""
    new = StructType.fromDDL(", ".join(f"{name} {kind}" for name, kind in kinds.items()))
    return StructType([*df.schema.fields, *new.fields])


def apart(df: DataFrame, *names: str) -> list[str]:
    """The names with as many underscores before them as keep them from the columns of ``df``, whatever the case."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name = "_" + name
        taken.add(name.lower())
        out.append(name)
    return out


def small_batches(spark: SparkSession, size: int = 4 << 20) -> None:
    """Bound what one Arrow batch hands to a Python worker: 64 MB by default, of which a worker holds several copies.

    A setting of the session's own stays.
    """
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    if spark.conf.get(key) == "67108864b":
        spark.conf.set(key, str(size))


def released(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The batches; after the last one the worker, which Spark keeps for other tasks, gives unused memory back."""
    yield from batches
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # not every C library can
        ctypes.CDLL(None).malloc_trim(0)


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors see: ``spark.checkpoint.dir``, or in its absence, on one machine, a new one."""
    sc = spark.sparkContext
    named = sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not named:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="splitsort-"))
        named = sc.getCheckpointDir()
    return named.rstrip("/")


@contextlib.contextmanager
def shuffles_freed(spark: SparkSession) -> Iterator[None]:
    """Within, a query's shuffle files go as soon as it has ended, not when the driver collects its garbage.

    For queries whose result is written: what is read of it later is the written table.
    """
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key)
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.set(key, before)


def staged(df: DataFrame, name: str) -> DataFrame:
    """``df`` written to the shared folder and read again: evaluated once, lineage cut."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/stage-{name}-{uuid.uuid4().hex}"
    with shuffles_freed(spark):
        df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._stage_path = path
    return out


def unstage(*frames: DataFrame) -> None:
    """Delete staged tables that nothing reads any more."""
    for df in frames:
        path = getattr(df, "_stage_path", None)
        if path:
            jvm = df.sparkSession._jvm
            where = jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(where, True)


def _plain_scan(df: DataFrame) -> bool:
    """Whether ``df`` is filters and projections over one file scan, the same at each evaluation."""
    node = df._jdf.queryExecution().analyzed()
    while node.children().size() == 1 and node.nodeName() in ("Project", "Filter", "SubqueryAlias", "View"):
        node = node.children().apply(0)
    return node.nodeName() == "LogicalRelation" and df._jdf.queryExecution().analyzed().deterministic()


def placed(docs: DataFrame, file: str, row: str) -> DataFrame:
    """``docs`` with two longs that name each row: a hash of its file's path, and its place in that file.

    Files are read again rather than copied.  What isn't a plain scan of Parquet files is written to the shared
    folder first.  Ten thousand paths have equal hashes with a chance of 3e-12.
    """
    at = [F.xxhash64("_metadata.file_path").alias(file), F.col("_metadata.row_index").alias(row)]
    if "_metadata" not in docs.columns:
        try:
            if _plain_scan(docs):
                return docs.select("*", *at)
        except AnalysisException:  # a source without row numbers
            pass
        return staged(docs, "docs").select("*", *at)
    (name,) = apart(docs, "meta")
    back = staged(docs.withColumnRenamed("_metadata", name), "docs").select("*", *at)
    return back.withColumnRenamed(name, "_metadata")


def small(df: DataFrame, rows: int, limit: int = BROADCAST_ROWS) -> DataFrame:
    """A broadcast hint only where the counted ``rows`` stay within ``limit``."""
    return F.broadcast(df) if rows <= limit else df


def doc_crc(doc_id: Column) -> Column:
    """crc32 of the decimal text of an id, unsigned; used for held-out folds.  A null id counts as empty."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary"))


def words(text: Column) -> Column:
    """Number of words (see WORD); null counts as empty."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def repeat_salt(slim: DataFrame, limit: int) -> Column:
    """A column to mix into a placement hash of ``slim``'s rows.

    Rows with different values spread by their hash alone, and the salt is then 0, so that placement
    depends on content only.  Where more than ``limit`` rows are equal in every column, one hash value
    would fill a bucket: then the salt is the row's position in the scan, which is the same in
    every rerun over the same files.  Only the key hashes are shuffled for the test.
    """
    most = (
        slim.select(F.xxhash64(*slim.columns).alias("__h")).groupBy("__h").count().agg(F.max("count")).first()[0]
    )
    return F.monotonically_increasing_id() if (most or 0) > limit else F.lit(0).cast("long")


def _united_here(edges: DataFrame) -> DataFrame:
    """``(n, p)`` of few ``edges(a, b)``, found on the driver: each node with the least one of its component."""
    found = edges.select("a", "b").toArrow()
    nodes, ends = np.unique(np.concatenate([found["a"].to_numpy(), found["b"].to_numpy()]), return_inverse=True)
    a, b = ends[: len(found)], ends[len(found) :]
    up = np.arange(len(nodes))
    while True:
        x, y = up[a], up[b]
        if (x == y).all():
            break
        np.minimum.at(up, np.maximum(x, y), np.minimum(x, y))
        while (up != up[up]).any():
            up = up[up]
    return edges.sparkSession.createDataFrame(pa.table({"n": nodes, "p": nodes[up]}))


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Connected components of ``edges(a long, b long)`` as ``(node, component)``, component = least node.

    Distributed union by randomised contraction: in each round every node hooks onto that neighbour
    (itself included) with the least hash under the round's seed; hooks are followed twice; edges are
    renamed to the hooks, loops and repeats dropped.  A constant share of nodes disappears in each
    round whatever the shape of the graph, long chains included.  Every step is an aggregate or a
    join that Spark can split, so a hub with a third of all edges is no single task; the driver sees
    one count for each round.  Once EDGES_HERE or fewer are left, it unites these itself.  Nodes without edges do not appear.
    """
    spark = edges.sparkSession
    live = staged(edges.select("a", "b").where("a <> b").distinct(), "edges")
    hooks: list[DataFrame] = []
    dead = [live]
    for k in range(max_rounds):
        n = live.count()
        if n <= EDGES_HERE:
            if n:
                hooks.append(staged(_united_here(live), "hook"))
            break
        both = live.select(F.col("a").alias("n"), F.col("b").alias("m")).unionAll(live.select("b", "a"))
        order = lambda c: F.struct(F.xxhash64(F.lit(k), c), c.alias("to"))
        hook = (
            both.groupBy("n")
            .agg(F.min(order(F.col("m"))).alias("x"))
            .select("n", F.least("x", order(F.col("n")))["to"].alias("p"))
        )
        up = hook.select(F.col("n").alias("p"), F.col("p").alias("q"))
        hook2 = staged(hook.join(up, "p", "left").select("n", F.coalesce("q", "p").alias("p")), "hook")
        hooks.append(hook2)
        renamed = (
            live.join(hook2.select(F.col("n").alias("a"), F.col("p").alias("pa")), "a")
            .join(hook2.select(F.col("n").alias("b"), F.col("p").alias("pb")), "b")
            .where("pa <> pb")
            .select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b"))
            .distinct()
        )
        live = staged(renamed, "edges")
        dead.append(live)
    else:
        raise RuntimeError(f"components: no end after {max_rounds} rounds")
    if not hooks:
        return spark.createDataFrame([], "node long, component long")
    if len(hooks) == 1 and len(dead) == 1:
        unstage(*dead)
        out = hooks[0].select(F.col("n").alias("node"), F.col("p").alias("component"))
        out._stage_path = hooks[0]._stage_path
        return out
    root = hooks[-1]
    for hook in reversed(hooks[:-1]):
        up = root.select(F.col("n").alias("p"), F.col("p").alias("q"))
        root = hook.join(up, "p", "left").select("n", F.coalesce("q", "p").alias("p"))
    root = staged(root, "roots")
    # A node whose hook chain ends in a later round is found under its last name: roots of all rounds agree.
    least = root.groupBy("p").agg(F.min(F.least("n", "p")).alias("component"))
    out = staged(root.join(least, "p").select(F.col("n").alias("node"), "component"), "components")
    unstage(*dead, *hooks, root)
    return out


def united(links: DataFrame, more: DataFrame, comp: DataFrame) -> tuple[DataFrame, DataFrame]:
    """All links as one table, and their components; the tables that these replace are deleted."""
    both = staged(links.unionAll(more), "links")
    unstage(links, more, comp)
    return both, components(both)


def open_buckets(members: DataFrame, comp: DataFrame) -> DataFrame:
    """``(band, k, node, comp)`` of the buckets of ``members(band, k, node)`` that hold several components."""
    known = members.select("band", "k", "node").join(small(comp, comp.count()), "node", "left")
    known = staged(known.select("band", "k", "node", F.coalesce("component", "node").alias("comp")), "known")
    mixed = known.groupBy("band").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"))
    mixed = staged(mixed.where("lo < hi").select("band"), "mixed")
    out = staged(known.join(small(mixed, mixed.count()), "band"), "open")
    unstage(known, mixed)
    return out


def drawn_pairs(left: DataFrame, k: int = 0) -> DataFrame:
    """Pairs of one member of each bucket's largest component, drawn by hash in round ``k``, and all members of the others."""
    order = F.struct(F.xxhash64(F.lit(k), "band", "node").alias("h"), "node")
    each = left.groupBy("band", "comp").agg(F.count("*").alias("n"), F.min(order).alias("x"))
    drawn = each.groupBy("band").agg(F.max(F.struct("n", "comp", "x.node")).alias("x")).select("band", F.col("x.node").alias("c"), F.col("x.comp").alias("d"))
    drawn = staged(drawn, "drawn")
    pairs = left.join(small(drawn, drawn.count()), "band").where("comp <> d")
    out = staged(pairs.select(F.least("node", "c").alias("a"), F.greatest("node", "c").alias("b")).distinct(), "pairs")
    unstage(drawn)
    return out


def close_pairs(left: DataFrame) -> DataFrame:
    """All pairs between components inside buckets ``(band, node, comp)`` of few members."""
    other = left.select("band", F.col("node").alias("b"), F.col("comp").alias("d"))
    pairs = left.join(other, "band").where("node < b AND comp <> d")
    return staged(pairs.select(F.col("node").alias("a"), "b").distinct(), "close")


def least_common(size: Column, other: Column) -> Column:
    """Shingles that sets of these sizes must share at the threshold."""
    return F.ceil(F.lit(PERCENT) * (size + other) / F.lit(100 + PERCENT))


def set_join(sets: DataFrame, once: bool = False) -> DataFrame:
    """Pairs ``(a, b)`` of ``sets(node, comp, sh)``, of different components, that include all links.

    Of a pair's common shingles one comes first in the common order, rarest first; from there on each side
    must hold as many as the pair has to share.  The longer set therefore shows its first shingles as far as a partner of
    three quarters its size allows, the shorter as far as one of its own size.  Only shingles that two
    components share take part; sets that hold too few of these leave at once.  With ``once`` the shingles are made and
    shuffled once, and counted where they lie: for sets that are dear to make.
    """
    tokens = sets.select("node", "comp", F.size("sh").cast("long").alias("n"), F.explode("sh").alias("t"))
    rare = None
    if once:
        t = Window.partitionBy("t")
        seen = tokens.select("*", F.count("*").over(t).alias("df"), F.min("comp").over(t).alias("lo"), F.max("comp").over(t).alias("hi"))
        seen = seen.where("lo < hi").drop("lo", "hi")
    else:
        rare = tokens.groupBy("t").agg(F.count("*").alias("df"), F.min("comp").alias("lo"), F.max("comp").alias("hi"))
        rare = staged(rare.where("lo < hi").select("t", "df"), "shared")
        seen = tokens.join(small(rare, rare.count()), "t")
    own = seen.groupBy("node", "comp", "n").agg(F.array_sort(F.collect_list(F.struct("df", "t"))).alias("ts"))
    c = F.size("ts")
    long = c - F.ceil(F.lit(PERCENT) * F.col("n") / 100) + 1  # as the longer set of a pair
    short = c - least_common(F.col("n"), F.col("n")) + 1
    own = own.where(long > 0).select("node", "comp", "n", c.alias("c"), short.alias("short"), F.posexplode(F.slice("ts", F.lit(1), F.greatest(F.lit(0), long.cast("int")))).alias("p", "x"))
    own = staged(own.select(F.col("x.t").alias("t"), "node", "comp", "n", (F.col("c") - F.col("p")).alias("rest"), (F.col("p") < F.col("short")).alias("first")), "firsts")
    other = own.where("first").select("t", F.col("node").alias("q"), F.col("comp").alias("qcomp"), F.col("n").alias("qn"), F.col("rest").alias("qrest"))
    met = own.join(other, "t").where((F.col("comp") != F.col("qcomp")) & (F.col("qn") <= F.col("n")) & (100 * F.col("qn") >= PERCENT * F.col("n")))
    met = met.where(F.least("rest", "qrest") >= least_common(F.col("n"), F.col("qn")))
    out = staged(met.select(F.least("node", "q").alias("a"), F.greatest("node", "q").alias("b")).distinct(), "met")
    unstage(rare, own)
    return out
