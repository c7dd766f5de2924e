"""Choices by hash that Spark and any SQL engine with md5 make alike."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F


def md5_number(text: Column) -> Column:
    """The first 32 bits of the md5 as a BIGINT."""
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("bigint")


def md5_uniform(text: Column) -> Column:
    """In the open interval (0, 1)."""
    return (md5_number(text) + 0.5) / float(1 << 32)


def block_of(key: Column, blocks: int) -> Column:
    return F.pmod(md5_number(key), F.lit(blocks)).cast("int")


def md5_number_py(text: str) -> int:
    return int(hashlib.md5(text.encode()).hexdigest()[:8], 16)  # noqa: S324


def sql_number(text: str) -> str:
    """The same in DuckDB, of a SQL expression."""
    return f"('0x' || substr(md5({text}), 1, 8))::bigint"
