"""Record layouts, and the encodings of the given tables as records.

A record is a key of fixed width followed by a value: of fixed width, or of a width that a length
field before it states.  Locators are record numbers for fixed records (so that five bytes address
2^40 of them whatever their size) and byte offsets of the value for length-prefixed ones; in memory
both are longs.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class RecordSpec:
    """Byte sizes of key, value, locator and length field; ``length_bytes`` 0 means fixed records."""

    key_bytes: int = 10
    value_bytes: int = 90
    locator_bytes: int = 5
    length_bytes: int = 0

    @property
    def record_bytes(self) -> int:
        return self.key_bytes + self.value_bytes

    @property
    def entry_bytes(self) -> int:
        """Size of one slim entry."""
        return self.key_bytes + self.locator_bytes + self.length_bytes

    def with_value(self, value_bytes: int) -> RecordSpec:
        return replace(self, value_bytes=value_bytes)


#: The sort benchmark's layout, and that of length-prefixed texts.
BENCHMARK, TEXTS = RecordSpec(), RecordSpec(value_bytes=0, length_bytes=4)


def cents(c: str) -> Column:
    return F.round(F.col(c) * 100).cast("long")


def lineitem_text() -> Column:
    """All columns of a lineitem row, joined by bars, money and rates as integer cents."""
    plain = [F.col(c).cast("string") for c in ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")]
    money = [cents(c).cast("string") for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax")]
    return F.concat_ws("|", *plain, *money, "l_returnflag", "l_linestatus", F.date_format("l_shipdate", "yyyy-MM-dd"))


def key_of(text: Column, spec: RecordSpec = BENCHMARK) -> Column:
    """The first bytes of the text's md5."""
    return F.unhex(F.substring(F.md5(text), 1, 2 * spec.key_bytes))


def benchmark_records(lineitem: DataFrame, spec: RecordSpec = BENCHMARK) -> DataFrame:
    """R1: uniform keys, values cut or padded to the layout's width."""
    text = lineitem_text()
    return lineitem.select(key_of(text, spec).alias("key"), F.encode(F.rpad(text, spec.value_bytes, " "), "UTF-8").alias("value"))


def sized_records(lineitem: DataFrame, spec: RecordSpec) -> DataFrame:
    """R2: R1's keys with values of any width made of repeated hash text."""
    text = lineitem_text()
    body = F.substring(F.repeat(F.md5(text), -(-spec.value_bytes // 32)), 1, spec.value_bytes)
    return lineitem.select(key_of(text, spec).alias("key"), F.encode(body, "UTF-8").alias("value"))


def text_records(df: DataFrame, key: Column, text: str) -> DataFrame:
    """R3 to R5: hashed key, UTF-8 bytes of a text of any length; null as empty."""
    return df.select(key_of(key.cast("string")).alias("key"), F.encode(F.coalesce(F.col(text), F.lit("")), "UTF-8").alias("value"))


def packed(number: Column, spec: RecordSpec = BENCHMARK) -> Column:
    """A record number as the ``locator_bytes`` bytes that a slim run has on disk, most significant first."""
    return F.unhex(F.lpad(F.hex(number), 2 * spec.locator_bytes, "0"))


def unpacked(locator: Column) -> Column:
    return F.conv(F.hex(locator), 16, 10).cast("long")
