"""Every operator and pipeline stage on awkward tables: nulls, empties, ties, repeats, long texts, clashing columns."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from splitsort.llm import exact_dedup, language_id, line_dedup, mixing, near_dedup, nearest, personal_data, quality, sentencepiece_codec, sharding

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
LONG = " ".join(f"word{i % 977} number{i}" for i in range(30_000))
ODD = [
    (1, "same text here", "en", "a", 14),
    (2, "same text here", "en", None, 14),
    (3, None, None, "b", None),
    (4, "", "en", "a", 0),
    (5, "   \n\n  ", None, "a", 7),
    (6, LONG, "en", "b", len(LONG)),
    (7, "ünïcode 日本語 👩‍🚀   x", "de", "c", 20),
    (None, "no id at all", "fr", "c", 12),
    (9, "repeated row", "en", "a", 12),
    (9, "repeated row", "en", "a", 12),
    (10, "12345 67890", "en", "a", 11),
]
#: Names that operators use for their own results.
CLASHES = ["size", "target", "shard", "slot", "kept", "keep_id", "n_lines", "ids", "spans", "lang_pred", "quality_score", "component_id", "uid", "__text2",
           "o", "f", "r", "b", "v", "k", "i", "h", "body", "line", "lines", "gone", "__uid", "__len", "__gid", "__size", "__text", "__l", "__words", "words", "distinct", "id", "node", "copies", "digit"]


def operators():
    langs = language_id.fit(["the cat and the dog", "der Hund und die Katze"], ["en", "de"])
    rules = quality.fit(*_toy(), ["words", "distinct"])
    return {
        "shard": lambda d: sharding.shard(d, shards=3),
        "near": near_dedup.near_duplicates,
        "pii": lambda d: personal_data.find(d, personal_data.default_crf()),
        "codec": sentencepiece_codec.encode_decode,
        "exact": exact_dedup.exact_dedup,
        "quality": lambda d: quality.score(d, rules),
        "lang": lambda d: language_id.identify(d, langs),
        "mix": mixing.mix,
        "lines": line_dedup.dedup_lines,
    }


def _toy():
    import numpy as np

    rng = np.random.default_rng(0)
    x = rng.random((400, 2))
    return x, (x[:, 0] > 0.5).astype(float)


@pytest.mark.parametrize("name", list(operators()))
def test_odd_rows(spark, name):
    op = operators()[name]
    df = spark.createDataFrame(ODD, SCHEMA)
    for c in CLASHES:
        df = df.withColumn(c, F.lit("mine"))
    out = op(df.repartition(3))
    assert out.count() == len(ODD)
    assert {"doc_id", "lang", "source"} <= set(out.columns) and len(set(out.columns)) == len(out.columns)
    ids = sorted((r["doc_id"] for r in out.collect()), key=lambda v: -1 if v is None else v)
    assert ids == sorted((r[0] for r in ODD), key=lambda v: -1 if v is None else v)


@pytest.mark.parametrize("name", list(operators()))
def test_empty_table(spark, name):
    out = operators()[name](spark.createDataFrame([], SCHEMA))
    assert out.isEmpty()


def test_ties_have_one_survivor(spark):
    df = spark.createDataFrame(ODD, SCHEMA)
    for out in (exact_dedup.exact_dedup(df), near_dedup.near_duplicates(df)):
        kept = [r["doc_id"] for r in out.where("kept").collect()]
        assert kept.count(9) == 1 and sum(k in (1, 2) for k in kept) == 1


def test_stages(spark, sf_dir):
    docs = spark.createDataFrame(ODD, SCHEMA)
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        for table in (docs, spark.createDataFrame([], SCHEMA)):
            out = stage(spark, table, sf_dir)
            out.collect()
            if k < len(corpus_pipeline.STAGES) - 1:
                assert out.columns == docs.columns


def test_vectors(spark):
    rows = [(0, [1.0, 0.0]), (1, [1.0, 0.0]), (2, [1.0, 0.0]), (3, None), (4, [0.0, 0.0]), (5, [float("nan"), 1.0]), (6, [None, 1.0]), (7, [0.5, 0.5]), (8, [1.0]), (None, [1.0, 1.0]), (20, [2.0, 1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("score", F.lit("mine"))
    got = [tuple(r) for r in nearest.nearest(df, F.col("vec_id") % 20 == 0, k=3).orderBy("query_id", "rank").collect()]
    assert got == [(0, 1, 20, 2.0), (0, 2, 1, 1.0), (0, 3, 2, 1.0), (20, 1, 0, 2.0), (20, 2, 1, 2.0), (20, 3, 2, 2.0)]
    assert nearest.nearest(df.limit(0), F.col("vec_id") % 20 == 0).isEmpty()
