"""Packed forms of codes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def pack_codes(coded: DataFrame) -> DataFrame:
    """coded with `packed`: two 4-bit codes in a byte, the first in the high half; an odd last code is followed by 0."""
    pairs = F.transform(F.sequence(F.lit(0), F.floor((F.size("code") - 1) / 2).cast("int")), lambda i: F.get("code", i * 2) * 16 + F.coalesce(F.get("code", i * 2 + 1), F.lit(0)))
    return coded.withColumn("packed", F.unhex(F.array_join(F.transform(pairs, lambda b: F.lpad(F.hex(b.cast("long")), 2, "0")), "")))


def unpack_codes(packed: DataFrame, m: int | None = None) -> DataFrame:
    """packed with `code`; m trims the filling of an odd number."""
    digits = F.split(F.hex("packed"), "")
    code = F.transform(F.filter(digits, lambda x: x != ""), lambda x: F.conv(x, 16, 10).cast("int"))
    return packed.withColumn("code", F.slice(code, 1, m) if m else code)
