"""Deterministic noise that any SQL engine computes alike."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

TWO_52 = 4503599627370496.0


def u01(salt: str, *ids: Column | str) -> Column:
    """A number in [0, 1) from the first 13 hexadecimal digits of md5('salt:id'); several ids are joined by ':'."""
    parts = [F.col(i) if isinstance(i, str) else i for i in ids]
    text = F.concat_ws(":", F.lit(salt), *[p.cast("string") for p in parts])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 13), 16, 10).cast("long") / F.lit(TWO_52)


def u01_sql(salt: str, *ids: str) -> str:
    """The same in DuckDB."""
    text = " || ':' || ".join([f"'{salt}'", *ids])
    return f"(('0x' || substr(md5({text}), 1, 13))::BIGINT / {TWO_52:.1f}::DOUBLE)"
