"""Encoded keys order bytes as ORDER BY orders values."""

import datetime
import math
from decimal import Decimal

import pytest
from pyspark.sql import functions as F

from splitsort.functions import encode_sort_key

CASES = {
    "double": [0.0, -0.0, 1.5, -1.5, math.inf, -math.inf, math.nan, 5e-324, -1e300, None],
    "bigint": [0, 1, -1, 2**63 - 1, -(2**63), 255, 256, None],
    "string": ["", "a", "aa", "b", "é", "z", "\x00", "a\x00b", "日本", None],
    "decimal(38,2)": [Decimal("0"), Decimal("-0.01"), Decimal("123456789012345678901234567890123456.78"), Decimal("-99999999999999999999.99"), Decimal("5"), None],
    "decimal(5,0)": [Decimal("0"), Decimal("-7"), Decimal("99999"), Decimal("12"), None],
    "boolean": [True, False, None],
    "date": [datetime.date(1970, 1, 1), datetime.date(1969, 12, 31), datetime.date(2024, 2, 29), None],
}


@pytest.mark.parametrize("kind", list(CASES))
@pytest.mark.parametrize("ascending", [True, False])
@pytest.mark.parametrize("nulls_first", [True, False])
def test_order(spark, kind, ascending, nulls_first):
    df = spark.createDataFrame([(i, v) for i, v in enumerate(CASES[kind])], f"i int, v {kind}")
    v = F.col("v")
    order = {(1, 1): v.asc_nulls_first(), (1, 0): v.asc_nulls_last(), (0, 1): v.desc_nulls_first(), (0, 0): v.desc_nulls_last()}[ascending, nulls_first]
    want = [r["i"] for r in df.orderBy(order, "i").collect()]
    key = encode_sort_key([(v, kind, ascending, nulls_first)])
    got = [r["i"] for r in df.select("i", key.alias("k")).orderBy("k", "i").collect()]
    assert got == want


def test_maps_are_refused():
    with pytest.raises(TypeError):
        encode_sort_key([(F.lit(1), "map<string,int>", True, True)])
