"""Order-preserving key encodings, checksums, and what is registered for SQL."""

from __future__ import annotations

from collections.abc import Iterator
from decimal import Decimal

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DecimalType, StringType


@pandas_udf(StringType())
def double_bits(x: pd.Series) -> pd.Series:
    """Sixteen hex digits whose order is that of the doubles: -0.0 equals 0.0, NaN is last."""
    v = x.to_numpy(np.float64, na_value=np.nan) + 0.0
    bits = np.where(np.isnan(v), np.uint64(0x7FF8000000000000), v.view(np.uint64))
    turned = np.where(bits >> np.uint64(63) == 1, ~bits, bits | np.uint64(1 << 63))
    return pd.Series([f"{b:016X}" for b in turned.tolist()])


def _hex(col: Column, kind: str) -> Column:
    """Upper-case hex digits in the order of the values; fixed width, or terminated."""
    if kind in ("tinyint", "smallint", "int", "bigint"):
        return F.lpad(F.hex(col.cast("long").bitwiseXOR(F.lit(-(1 << 63)))), 16, "0")
    if kind.startswith("decimal"):
        # Digits by sign: the absolute value as 38 of them, complemented below zero, so that any width fits.
        precision, scale = (int(x) for x in kind[8:-1].split(","))
        whole = F.replace(F.abs(col).cast(f"decimal({precision},{scale})").cast("string"), F.lit("."), F.lit(""))
        digits = F.lpad(whole, precision + 1 + precision % 2, "0")  # an even number with the sign
        return F.when(col < 0, F.concat(F.lit("0"), F.translate(digits, "0123456789", "9876543210"))).otherwise(F.concat(F.lit("1"), digits))
    if kind == "date":
        return _hex(F.unix_date(col), "bigint")
    if kind.startswith("timestamp"):
        return _hex(F.unix_micros(col.cast("timestamp")), "bigint")
    if kind == "boolean":
        return F.when(col, "01").otherwise("00")
    if kind in ("float", "double"):
        return double_bits(col.cast("double"))
    if kind in ("string", "binary"):
        raw = F.hex(F.encode(col, "UTF-8") if kind == "string" else col)
        escaped = F.regexp_replace(F.regexp_replace(raw, "(..)", "$1 "), r"\b00\b ", "00 FF ")
        return F.concat(F.replace(escaped, F.lit(" "), F.lit("")), F.lit("0000"))
    raise TypeError(f"{kind} can't be a sort key")


def encode_sort_key(parts: list[tuple[Column, str, bool, bool]]) -> Column:
    """A binary key whose byte order is ORDER BY's: parts are (column, type, ascending, nulls first).

    A byte before each part places nulls; descending parts are complemented.
    """
    out = []
    for col, kind, ascending, nulls_first in parts:
        body = _hex(col, kind)
        if not ascending:
            body = F.translate(body, "0123456789ABCDEF", "FEDCBA9876543210")
        out.append(F.when(col.isNull(), F.lit("00" if nulls_first else "02")).otherwise(F.concat(F.lit("01"), body)))
    return F.unhex(F.concat(*out))


@pandas_udf(DecimalType(38, 0))
def order_checksum(h: pd.Series) -> Decimal:
    """Sum of 64-bit hashes without overflow; the order of rows doesn't matter."""
    return Decimal(sum(int(x) for x in h))


def slim_range(path: str):
    """A table function (lo, hi, part, parts) over a written slim index with hex keys: the entries between.

    One call reads every parts-th file of the index, starting with number ``part``; a lateral join over a range of
    parts reads the whole index side by side.
    """

    @udtf(returnType="key string, pos bigint")
    class SlimRange:
        def eval(self, lo: str, hi: str, part: int, parts: int) -> Iterator[tuple[str, int]]:
            import pyarrow.compute as pc
            import pyarrow.dataset as ds

            from splitsort.sources import files

            f = (pc.field("key") >= lo) & (pc.field("key") < hi)
            for name, _ in files.listed(path, ".parquet")[part::parts]:
                system, local = files.opened(name)
                for batch in ds.dataset(local, format="parquet", filesystem=system).to_batches(columns=["key", "pos"], filter=f):
                    yield from zip(batch.column("key").to_pylist(), batch.column("pos").to_pylist(), strict=True)

    return SlimRange


def register_all(spark: SparkSession, index_path: str = "") -> None:
    """Formats and functions by name, for SQL; ``slim_range`` over the index at ``index_path``, if there is one."""
    from ..sources import register_formats

    register_formats(spark)
    spark.udf.register("order_checksum", order_checksum)
    spark.udf.register("double_bits", double_bits)
    if index_path:
        spark.udtf.register("slim_range", slim_range(index_path))
