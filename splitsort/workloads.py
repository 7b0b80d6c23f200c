"""The given tables as record files, made once for each application and table folder."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .records import BENCHMARK, TEXTS, RecordSpec, benchmark_records, sized_records, text_records
from .session import new_path
from .sources import table, write_fixed, write_klv

_made: dict[tuple, str] = {}


def dataset(spark: SparkSession, sf_dir: str, kind: str, spec: RecordSpec = BENCHMARK) -> str:
    """The folder of R1 (``benchmark``), R2 (``sized``) or R3 to R5 (``documents pages conversations``)."""
    key = (spark.sparkContext.applicationId, sf_dir, kind, spec)
    if key not in _made:
        path = new_path(spark, kind)
        if kind == "benchmark":
            write_fixed(benchmark_records(table(spark, sf_dir, "lineitem"), spec).repartition(8), path, spec)
        elif kind == "sized":
            write_fixed(sized_records(table(spark, sf_dir, "lineitem"), spec).repartition(8), path, spec)
        else:
            ids = {"documents": F.col("doc_id"), "pages": F.col("url"), "conversations": F.concat_ws("|", "conv_id", "turn")}
            body = {"documents": "text", "pages": "html", "conversations": "text"}
            rows = text_records(table(spark, sf_dir, kind), ids[kind], body[kind])
            write_klv(rows.repartition(4), path, TEXTS, anchors=100)
        _made[key] = path
    return _made[key]


def replicate(df: DataFrame, k: int, skew: float = 0.0) -> DataFrame:
    """``df`` k times over with a copy number; a share ``skew`` of the copies' salt is 0."""
    copies = df.sparkSession.range(k).withColumnRenamed("id", "copy")
    out = df.crossJoin(F.broadcast(copies))  # k is a parameter, not data
    hot = F.pmod(F.xxhash64(F.lit(5), *df.columns, "copy"), F.lit(10_000)) < F.lit(int(skew * 10_000))
    return out.withColumn("salt", F.when(hot, 0).otherwise(F.col("copy")))
