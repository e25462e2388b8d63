"""Reproducible uniforms from md5, equal in Spark and in DuckDB."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def uniform(text: Column) -> Column:
    """A number in [0, 1) from the first 52 bits of the md5 of a string."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 13), 16, 10).cast("double") / F.lit(float(2**52))


def uniform_sql(text: str) -> str:
    """The same for DuckDB."""
    return f"(('0x' || substr(md5({text}), 1, 13))::BIGINT / pow(2, 52))"


def keyed(*parts) -> Column:
    """Parts joined by colons, as text."""
    return F.concat_ws(":", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])
