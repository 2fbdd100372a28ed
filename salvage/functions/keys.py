"""Reproducible orders and draws, equal in Spark and in SQL, and values that an expression names more than once."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

SEED = 42


def order_key(id_col: Column | str, seed: int = SEED) -> Column:
    """A 60-bit number from the md5 of seed and id; sorting by it is a random order that every engine repeats."""
    column = F.col(id_col) if isinstance(id_col, str) else id_col
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), column.cast("string"))), 1, 15), 16, 10).cast("bigint")


def order_key_sql(id_expr: str, seed: int = SEED) -> str:
    return f"('0x' || substr(md5('{seed}|' || {id_expr}::VARCHAR), 1, 15))::BIGINT"


def uniform(id_col: Column | str, seed: int = SEED) -> Column:
    """A draw from [0, 1) with 32 random bits."""
    column = F.col(id_col) if isinstance(id_col, str) else id_col
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), column.cast("string"))), 1, 8), 16, 10).cast("double") / F.lit(float(2**32))


def uniform_sql(id_expr: str, seed: int = SEED) -> str:
    return f"(('0x' || substr(md5('{seed}|' || {id_expr}::VARCHAR), 1, 8))::BIGINT / 4294967296.0)"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body(value)`` with ``value`` worked out once, however often and under whatever conditions ``body`` names it."""
    return F.element_at(F.transform(F.array(value), body), 1)
