"""Near-duplicate detection by circulant MinHash, banding and exact Jaccard verification.

Two permutations of the 32-bit integers make all signature coordinates: the first scatters the
shingle hashes once, the second is applied to the scattered values after a circular shift by k, for
coordinate k.  Texts that agree in all rows of one band are candidates; a link counts only after the
full shingle sets were compared.

No group is ever expanded into its pairs:

1. texts with equal shingle sets collapse into one class;
2. every class is compared with the least class that shares a bucket with it, and verified links are united into components;
3. small buckets that still hold several components are compared pair by pair; in larger ones the other components
   are compared with a member of the largest one, drawn by hash, another in each bucket, a few rounds of it;
4. what is then left in larger ones is settled by an exact set join: shingles that no two components
   share count for nothing, the others are put in order, rarest first, and two sets can only reach the threshold
   if they meet in the first few of these and enough is left behind the place where they meet.
Pairs already in one component need no test: they can change nothing.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import PERCENT, apart, close_pairs, components, drawn_pairs, open_buckets, placed, released, set_join, small, small_batches, staged, united, unstage

WORDS_IN_SHINGLE = 5
#: 40 bands of 4 rows: a pair at similarity 0.75 is missed with a chance of 3e-7.
BANDS, ROWS = 40, 4
#: A pair at 0.75 agrees on fewer coordinates than this with a chance of under 1e-11, were they independent.
PLAUSIBLE = 80
#: Members of a bucket up to which all pairs are compared, and rounds of drawn members in larger ones.
SMALL, ROUNDS = 16, 3
#: Bytes that a worker takes up at once; a longer text is cut between words.
PIECE = 1 << 18
#: Bytes of a word that the table of multipliers covers; longer words get a digest.
REACH = 256
_rng = np.random.default_rng(0x5EED)
_BYTE = _rng.integers(0, 1 << 63, 256, np.uint64)
_BYTE[65:91] = _BYTE[97:123]  # A-Z as a-z
_PLACE = _rng.integers(0, 1 << 63, REACH, np.uint64) | np.uint64(1)
_GAP = np.zeros(256, bool)
_GAP[[9, 10, 11, 12, 13, 32]] = True
LOWER = {c: c + 32 for c in range(65, 91)}


def _mixed(x: np.ndarray) -> np.ndarray:
    x *= np.uint64(0x9E3779B97F4A7C15)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(32)
    return x


def word_hashes(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where the words of UTF-8 bytes start, and a 64-bit hash of each one in lower case (A-Z)."""
    word = ~_GAP[raw]
    begin = word.copy()
    begin[1:] &= ~word[:-1]
    at = np.flatnonzero(begin)
    if not len(at):
        return at, np.empty(0, np.uint64)
    span = np.diff(at, append=len(raw))
    place = np.arange(at[0], len(raw), dtype=np.int64) - np.repeat(at, span)
    term = _BYTE[raw[at[0] :]] * _PLACE[np.minimum(place, REACH - 1)]
    term[~word[at[0] :]] = 0
    out = np.add.reduceat(term, at - at[0])
    size = np.add.reduceat(word[at[0] :], at - at[0], dtype=np.int64)
    for k in np.flatnonzero(size > REACH):
        whole = raw[at[k] : at[k] + size[k]].tobytes().lower()
        out[k] = int.from_bytes(hashlib.blake2b(whole, digest_size=8).digest(), "little")
    return at, _mixed(out ^ size.astype(np.uint64))


def _pieces(raw: np.ndarray) -> Iterator[np.ndarray]:
    """A long text in stretches that end at a gap."""
    at = 0
    while len(raw) - at > PIECE:
        gaps = np.flatnonzero(_GAP[raw[at + PIECE // 2 : at + PIECE]])
        end = at + PIECE // 2 + int(gaps[-1]) if len(gaps) else at + PIECE
        while end < len(raw) and not len(gaps):  # a word longer than a piece
            gaps = np.flatnonzero(_GAP[raw[end : end + PIECE]])
            end += int(gaps[0]) if len(gaps) else PIECE
        yield raw[at:end]
        at = min(end, len(raw))
    yield raw[at:]


def _set(words: np.ndarray) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the shingles of a sequence of word hashes."""
    if not len(words):
        return words
    n = min(WORDS_IN_SHINGLE, len(words))
    m = len(words) - n + 1
    out = np.full(m, n, np.uint64)
    for j in range(n):
        out ^= words[j : j + m]
        out = _mixed(out)
    return np.unique(out)


def shingle_sets(texts: list[bytes | None]) -> Iterator[np.ndarray]:
    """The shingle set of each text; words are found and hashed for many texts at once."""
    part: list[bytes] = []

    def flush() -> Iterator[np.ndarray]:
        raw = np.frombuffer(b"\n".join(part), np.uint8)
        at, hashes = word_hashes(raw)
        ends = np.cumsum([len(t) + 1 for t in part])
        cuts = np.searchsorted(at, ends)
        a = 0
        for b in cuts.tolist():
            yield _set(hashes[a:b])
            a = b

    size = 0
    for t in texts:
        t = t or b""
        if part and size + len(t) > PIECE:
            yield from flush()
            part, size = [], 0
        if len(t) > PIECE:
            yield _set(np.concatenate([word_hashes(p)[1] for p in _pieces(np.frombuffer(t, np.uint8))]))
            continue
        part.append(t)
        size += len(t) + 1
    if part:
        yield from flush()


def shingles(text: str | None) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a text's shingles; fewer than five words are one shingle."""
    return next(shingle_sets([text.encode("utf-8", "surrogatepass") if text else None]))


def _permuted(x: np.ndarray) -> np.ndarray:
    """A fixed permutation of the 32-bit integers: odd products and shifted sums, each invertible."""
    x ^= x >> np.uint32(16)
    x *= np.uint32(0x7FEB352D)
    x ^= x >> np.uint32(15)
    x *= np.uint32(0x846CA68B)
    x ^= x >> np.uint32(16)
    return x


def signature(sh: np.ndarray, coordinates: int = BANDS * ROWS) -> np.ndarray:
    """Circulant MinHash of a set of shingle hashes."""
    # First permutation, on the folded hash; its constants differ from those of the second by the offset.
    first = _permuted((sh ^ (sh >> np.uint64(32))).astype(np.uint32) + np.uint32(0x5BD1E995))
    shift = np.arange(coordinates, dtype=np.uint32)
    out = np.full(coordinates, 0xFFFFFFFF, np.uint32)
    for at in range(0, len(first), 256):
        np.minimum(out, _permuted(first[at : at + 256, None] - shift[None, :]).min(axis=0), out=out)
    return out


def _sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Set size, digest of the set, short signature and band keys of each text; texts come last and stay here."""
    mix = np.uint64(0x9E3779B97F4A7C15)
    for batch in batches:
        sizes, same, sigs, keys = [], [], [], []
        for sh in shingle_sets(batch.column("body").to_pylist()):
            sizes.append(len(sh))
            same.append(hashlib.blake2b(sh.tobytes(), digest_size=16).digest())
            if not len(sh):
                sigs.append(None)
                keys.append(None)
                continue
            sig = signature(sh)
            sigs.append(sig.astype(np.uint8).tobytes())
            rows = sig.reshape(BANDS, ROWS).astype(np.uint64)
            key = np.arange(BANDS, dtype=np.uint64) + np.uint64(1)
            for j in range(ROWS):
                key = (key ^ rows[:, j]) * mix
                key ^= key >> np.uint64(31)
            keys.append(key.astype(np.int64))
        kept = [n for n in batch.schema.names if n != "body"]
        new = [pa.array(sizes, pa.int64()), pa.array(same, pa.binary()), pa.array(sigs, pa.binary()), pa.array(keys, pa.list_(pa.int64()))]
        yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in kept), *new], [*kept, "n_shingles", "same", "sig", "bands"])


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        nodes, at = batch.column("node"), 0
        got, size = [], 0
        for k, sh in enumerate(shingle_sets(batch.column("body").to_pylist())):
            got.append(sh.astype(np.int64))
            size += len(sh)
            if size >= PIECE or k + 1 == batch.num_rows:
                yield pa.RecordBatch.from_arrays([nodes.slice(at, len(got)), pa.array(got, pa.list_(pa.int64()))], ["node", "sh"])
                at, got, size = k + 1, [], 0


def _agreeing(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        x, y = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8).reshape(batch.num_rows, -1) for c in ("x", "y"))
        good = pa.array((x == y).sum(axis=1) >= PLAUSIBLE)
        yield pa.RecordBatch.from_arrays([batch.column("a").filter(good), batch.column("b").filter(good)], ["a", "b"])


def _alike(pairs: DataFrame, sigs: DataFrame) -> DataFrame:
    """Of ``pairs(a, b)`` those that size and signatures let reach the threshold."""
    own = lambda side, sig: sigs.select(F.col("node").alias(side), F.col("n_shingles").alias(f"n{side}"), F.col("sig").alias(sig))
    both = pairs.join(own("a", "x"), "a").join(own("b", "y"), "b")
    both = both.where(100 * F.least("na", "nb") >= PERCENT * F.greatest("na", "nb")).select("a", "b", "x", "y")
    return both.mapInArrow(_agreeing, "a long, b long")


def _sets_of(nodes: DataFrame, sketch: DataFrame, bodies: DataFrame) -> DataFrame:
    """``(node, sh)``: the full shingle sets of some ``nodes``, whose texts alone are moved."""
    wanted = sketch.join(small(nodes, nodes.count()), F.col("uid") == F.col("node"), "left_semi")
    wanted = staged(wanted.select(F.col("uid").alias("node"), "f", "r"), "wanted")
    texts = bodies.join(small(wanted, wanted.count()), ["f", "r"]).select("node", "body")
    out = staged(texts.mapInArrow(lambda b: released(_sets(b)), "node long, sh array<long>"), "sets")
    unstage(wanted)
    return out


def _verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """Of ``pairs(a, b)`` those whose full shingle sets meet 100 * intersection >= 75 * union."""
    both = pairs.join(sets.select(F.col("node").alias("a"), F.col("sh").alias("x")), "a")
    both = both.join(sets.select(F.col("node").alias("b"), F.col("sh").alias("y")), "b")
    common = F.size(F.array_intersect("x", "y"))
    return staged(both.where(100 * common >= PERCENT * (F.size("x") + F.size("y") - common)).select("a", "b"), "links")


def _linked(sketch: DataFrame, bodies: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Classes of equal sets that hold several rows, ``(same, node)``, and ``(node, component)`` over links."""
    # 1. classes of equal sets; a class is named by its least row number
    classes = sketch.where("n_shingles > 0").groupBy("same").agg(F.count("*").alias("k"), F.min("uid").alias("node"))
    classes = staged(classes.where("k > 1").select("same", "node"), "classes")
    nodes = sketch.where("n_shingles > 0").join(small(classes, classes.count()), "same", "left").where("node IS NULL OR node = uid")
    nodes = nodes.select(F.col("uid").alias("node"), "n_shingles", "sig", "bands")
    # 2. stars
    spread = nodes.select("node", F.explode("bands").alias("band"))
    heads = staged(spread.groupBy("band").agg(F.count("*").alias("k"), F.min("node").alias("head")).where("k > 1"), "heads")
    members = staged(spread.join(small(heads, heads.count()), "band").select("band", "k", "head", "node"), "members")
    unstage(heads)
    sigs = nodes.select("node", "n_shingles", "sig")
    stars = members.groupBy(F.col("node").alias("b")).agg(F.min("head").alias("a")).where("a < b").select("a", "b")
    stars = staged(_alike(stars, sigs), "stars")
    nodes = staged(stars.select(F.col("a").alias("node")).union(stars.select("b")).distinct(), "nodes")
    sets = _sets_of(nodes, sketch, bodies)
    links = _verified(stars, sets)
    unstage(nodes, sets)
    comp = components(links)
    # 3. buckets of several components: all pairs where there are few, a drawn member elsewhere
    left = open_buckets(members, comp)
    close, large = close_pairs(left.where(F.col("k") <= SMALL)), staged(left.where(F.col("k") > SMALL), "large")
    drawn = drawn_pairs(large)
    more = staged(_alike(close.union(drawn).distinct(), sigs), "alike")
    unstage(left, close, drawn)
    nodes = staged(more.select(F.col("a").alias("node")).union(more.select("b")).union(large.select("node")).distinct(), "nodes")
    sets = _sets_of(nodes, sketch, bodies)
    links, comp = united(links, _verified(more, sets), comp)
    unstage(nodes)
    for k in range(1, ROUNDS):
        left = open_buckets(large, comp)
        if left.isEmpty():
            break
        drawn = drawn_pairs(left, k)
        found = _verified(_alike(drawn, sigs), sets)
        unstage(drawn, left)
        if found.isEmpty():
            break
        links, comp = united(links, found, comp)
    # 4. the rest, exactly
    left = open_buckets(large, comp)
    if not left.isEmpty():
        rest = staged(left.select("node", "comp").distinct(), "rest")
        found = _verified(set_join(sets.join(small(rest, rest.count()), "node")), sets)
        if not found.isEmpty():
            links, comp = united(links, found, comp)
        unstage(rest)
    unstage(left, large, more, sets)
    unstage(members, stars, links)
    return classes, comp


def near_groups(docs: DataFrame, file: str, row: str, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``(file, row, n_shingles, component_id, kept)`` of all rows of ``docs``, which ``placed`` has named."""
    small_batches(docs.sparkSession)
    body = F.encode(F.col(f"`{text}`"), "UTF-8").alias("body")
    bodies = docs.select(F.col(file).alias("f"), F.col(row).alias("r"), body)
    rows = docs.select(F.monotonically_increasing_id().alias("uid"), F.col(file).alias("f"), F.col(row).alias("r"), F.col(f"`{doc_id}`").alias("id"), body)
    kinds = f"uid long, f long, r long, id {dict(docs.dtypes)[doc_id]}, n_shingles long, same binary, sig binary, bands array<long>"
    sketch = staged(rows.mapInArrow(lambda b: released(_sketch(b)), kinds), "sketch")
    classes, comp = _linked(sketch, bodies)
    # back to rows: by class, then by component
    slim = sketch.select("uid", "f", "r", "id", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("same")).alias("same"))
    slim = slim.join(small(classes, classes.count()), "same", "left").select("uid", "f", "r", "id", "n_shingles", F.coalesce("node", "uid").alias("node"))
    slim = slim.join(small(comp, comp.count()), "node", "left").select("f", "r", "uid", "id", "n_shingles", F.coalesce("component", "node").alias("c"))
    slim = staged(slim, "assigned")
    least = slim.groupBy("c").agg(F.min(F.struct("id", "uid")).alias("x"), F.count("*").alias("k")).where("k > 1").select("c", "x")
    least = staged(least, "least")
    done = slim.join(small(least, least.count()), "c", "left").select(
        F.col("f").alias(file),
        F.col("r").alias(row),
        "n_shingles",
        F.when(F.col("x").isNull(), F.col("id")).otherwise(F.col("x.id")).alias("component_id"),
        (F.col("x").isNull() | (F.col("x.uid") == F.col("uid"))).alias("kept"),
    )
    done = staged(done, "near")
    unstage(sketch, classes, comp, slim, least)
    return done


def near_duplicates(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """All rows and columns of ``docs`` with ``n_shingles``, ``component_id`` and ``kept``.

    Words are split at space and ASCII controls after lower-casing A-Z; a document's set holds its
    distinct five-word shingles, or its whole word sequence if that is shorter.  Documents are linked at a
    Jaccard similarity of 0.75 or more, confirmed on full sets.  ``component_id`` is the least id reachable over
    links, ``kept`` marks the row with that id (of several such rows, all in one component, the first in
    scan order).  Null and wordless texts have no shingles, no links, and stay.  A null id is less than
    any other.  Columns called like the three new ones are replaced; an empty table gives an empty result.

    Texts are shuffled only for documents that have a candidate; buckets move as (band, row number).
    """
    docs = docs.drop("n_shingles", "component_id", "kept")
    file, row = apart(docs, "f", "r")
    rows = placed(docs, file, row)
    done = near_groups(rows, file, row, text, doc_id)
    return rows.join(done, [file, row]).select(*[F.col(f"`{c}`") for c in docs.columns], "n_shingles", "component_id", "kept")


def without_near_duplicates(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``docs`` less the rows that ``near_duplicates`` doesn't keep; texts move only where that list is long."""
    file, row = apart(docs, "f", "r", "n_shingles", "component_id", "kept")[:2]
    rows = placed(docs, file, row)
    done = near_groups(rows, file, row, text, doc_id)
    gone = staged(done.where("NOT kept").select(file, row), "gone")
    unstage(done)
    return rows.join(small(gone, gone.count()), [file, row], "left_anti").select(*[F.col(f"`{c}`") for c in docs.columns])
