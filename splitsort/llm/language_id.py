"""Language identification by error-correcting output codes over character n-grams.

Each language has a codeword of bits; one binary linear classifier over hashed n-grams of the
lower-cased UTF-8 text predicts each bit.  A text is given the language whose codeword has the
least total logistic loss against the classifiers' margins.  The gap to the runner-up flags ambiguity.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import released, small, small_batches, widened

#: Documents of each language in the labelled sample (for fitting only), fewer where there are many languages, and the least.
DOCS_PER_LANG, SAMPLE, FEWEST = 800, 6400, 20
SLOTS, ORDERS, STEPS = 4096, (1, 2, 3), 150
#: Loss gap to the second codeword under which a prediction is ambiguous.
AMBIGUOUS = 1.0
UNKNOWN = "und"
LETTER = re.compile(r"[^\W\d_]")
PIECE = 1 << 22


@dataclass(frozen=True)
class Coder:
    langs: list[str]
    code: np.ndarray  # langs x bits, -1 or 1
    weights: np.ndarray  # slots x bits
    bias: np.ndarray  # bits


def codewords(n: int, seed: int = 8) -> np.ndarray:
    """n rows of -1 and 1: all distinct splits while n is at most 6, else the best of random codes."""
    if n <= 1:
        return np.ones((n, 1), np.int8)
    if n <= 6:
        splits = [[1] + [1 if (k >> j) & 1 else -1 for j in range(n - 1)] for k in range(2 ** (n - 1) - 1)]
        return np.array(splits, np.int8).T
    rng, bits = np.random.default_rng(seed), int(np.ceil(10 * np.log2(n)))
    best, far = None, -1
    for _ in range(50):
        code = rng.choice(np.array([-1, 1], np.int8), (n, bits))
        apart = min(int((code[i] != code[j]).sum()) for i in range(n) for j in range(i))
        if apart > far and (np.abs(code.sum(0)) < n).all():
            best, far = code, apart
    return best


def gram_counts(text: str) -> np.ndarray:
    """Counts of hashed n-grams of a whole text, in pieces of bounded size."""
    raw = np.frombuffer(text.lower().encode("utf-8", "surrogatepass"), np.uint8)
    out = np.zeros(SLOTS, np.int64)
    for at in range(0, len(raw), PIECE):
        b = raw[at : at + PIECE + max(ORDERS) - 1].astype(np.uint32)
        h = np.zeros(len(b), np.uint32)
        for n in ORDERS:
            m = min(PIECE, len(b) - n + 1)
            if m <= 0:
                break
            h = (h[: len(b) - n + 1] * np.uint32(257)) + b[n - 1 :] + np.uint32(1)
            out += np.bincount((h[:m] * np.uint32(2654435761)) >> np.uint32(20), minlength=SLOTS)
    return out


def fit(texts: list[str], langs: list[str]) -> Coder:
    return fit_counts([gram_counts(t) for t in texts], langs)


def fit_counts(counts: list[np.ndarray], langs: list[str]) -> Coder:
    names = sorted(set(langs))
    if len(names) < 2:
        return Coder(names, codewords(len(names)), np.zeros((SLOTS, 1), np.float32), np.ones(1, np.float32))
    x = np.stack(counts).astype(np.float32)
    x /= np.maximum(x.sum(1, keepdims=True), 1)
    scale = 1 / np.sqrt((x**2).mean(0) + 1e-9)
    x *= scale
    x *= (unit := 1 / np.sqrt((x**2).sum(1).mean()))
    at = np.array([names.index(v) for v in langs])
    code = codewords(len(names))
    y = code[at].astype(np.float32)
    share = np.bincount(at, minlength=len(names))
    weight = (1 / share[at])[:, None].astype(np.float32) / len(names)
    w, b = np.zeros((SLOTS, code.shape[1]), np.float32), np.zeros(code.shape[1], np.float32)
    mw, vw = np.zeros_like(w), np.zeros_like(w)
    for k in range(1, STEPS + 1):  # Adam on the weighted logistic loss
        g = -y * weight / (1 + np.exp(np.clip(y * (x @ w + b), -30, 30)))
        gw = x.T @ g + 1e-6 * w
        b -= 0.5 * g.sum(0)
        mw, vw = 0.9 * mw + 0.1 * gw, 0.99 * vw + 0.01 * gw**2
        w -= 0.1 * (mw / (1 - 0.9**k)) / (np.sqrt(vw / (1 - 0.99**k)) + 1e-8)
    return Coder(names, code, (w * scale[:, None] * unit).astype(np.float32), b)


def predict(model: Coder, text: str | None) -> tuple[str, float, bool]:
    if not text or not model.langs or not LETTER.search(text):
        return UNKNOWN, 0.0, True
    counts = gram_counts(text)
    margin = counts @ model.weights.astype(np.float64) / max(1, counts.sum()) + model.bias
    loss = np.logaddexp(0, -model.code * margin).sum(1)
    order = np.argsort(loss, kind="stable")
    share = np.exp(loss[order[0]] - loss)
    clear = len(order) == 1 or loss[order[1]] - loss[order[0]] >= AMBIGUOUS
    return model.langs[order[0]], float(1 / share.sum()), not clear


def train(docs: DataFrame, text: str = "text", lang: str = "lang", doc_id: str = "doc_id") -> Coder:
    """Fit on at most DOCS_PER_LANG documents of each language, chosen by a hash of the id; beyond 8 languages on SAMPLE
    documents in all, and beyond 320 on FEWEST of each.

    Rows with null language or text take no part.  Languages are counted first; a share of each that holds
    about four times the sample passes a hash filter, so that what the choice shuffles doesn't grow with the table.
    Whole texts are counted on the executors; only counts, SLOTS for each document, are shuffled and collected.
    """
    rows = docs.select(F.col(f"`{doc_id}`").alias("i"), F.col(f"`{lang}`").alias("l"), F.col(f"`{text}`").alias("t"))
    rows = rows.where("l IS NOT NULL AND t IS NOT NULL")
    each = rows.groupBy("l").agg(F.count("*").alias("n"))
    langs = each.count()
    most = max(FEWEST, min(DOCS_PER_LANG, SAMPLE // max(1, langs)))
    share = F.least(F.lit(1.0), F.lit(4.0 * most) / F.col("n"))
    passed = F.pmod(F.xxhash64(F.lit(9), "i"), F.lit(1 << 30)) < share * (1 << 30)
    rows = rows.join(small(each, langs, 100_000), "l").where(passed)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            c = [zlib.compress(gram_counts(t).tobytes(), 1) for t in batch.column(3).to_pylist()]
            yield pa.RecordBatch.from_arrays([*[batch.column(k) for k in range(3)], pa.array(c, pa.binary())], ["l", "h", "x", "c"])

    # Ties of the hash of the id fall by the hash of the whole text, then by its counts.
    rows = rows.select(F.col("l").cast("string").alias("l"), F.xxhash64(F.lit(8), "i").alias("h"), F.xxhash64("t").alias("x"), "t")
    rows = rows.mapInArrow(count, "l string, h long, x long, c binary")
    best = Window.partitionBy("l").orderBy("h", "x", "c")
    rows = rows.withColumn("k", F.row_number().over(best)).where(F.col("k") <= most)
    got = sorted((r["l"], r["k"], bytes(r["c"])) for r in rows.collect())
    return fit_counts([np.frombuffer(zlib.decompress(c), np.int64).astype(np.float32) for _, _, c in got], [v for v, _, _ in got])


def identify(docs: DataFrame, model: Coder, text: str = "text", names: tuple[str, ...] = ("lang_pred", "lang_score", "lang_ambiguous")) -> DataFrame:
    """All rows and columns of ``docs`` with ``lang_pred``, ``lang_score`` (0 to 1) and ``lang_ambiguous``, or other ``names``.

    Whole texts are read.  A null text, or one without a letter, is ``und`` with score 0; so is every text under a
    model of no language.  Columns called like the three new ones are replaced.  No shuffle.
    """
    docs = docs.drop(*names)
    schema = widened(docs, **dict(zip(names, ("string", "double", "boolean"), strict=True)))
    small_batches(docs.sparkSession)
    at = docs.columns.index(text)
    kinds = (pa.string(), pa.float64(), pa.bool_())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = [predict(model, t) for t in batch.column(at).to_pylist()]
            new = [pa.array([g[k] for g in got], kinds[k]) for k in range(3)]
            yield pa.RecordBatch.from_arrays([*batch.columns, *new], [*batch.schema.names, *names])

    return docs.mapInArrow(lambda b: released(run(b)), schema)
