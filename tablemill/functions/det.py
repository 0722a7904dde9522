"""Repeatable choices: every draw is an md5 of a seed and keys, equal in any layout of the data."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def text(*keys) -> Column:
    return F.md5(F.concat_ws("|", *[k.cast("string") if isinstance(k, Column) else F.lit(str(k)) for k in keys]))


def unit(*keys) -> Column:
    """A number in [0, 1) from the first 32 bits."""
    return F.conv(F.substring(text(*keys), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)


def pick(options: int, *keys) -> Column:
    """0-based choice among ``options``."""
    return F.floor(unit(*keys) * options).cast("int")


def sql_text(*keys: str) -> str:
    """The same for DuckDB; keys are SQL expressions."""
    return f"md5(concat_ws('|', {', '.join(keys)}))"


def sql_unit(*keys: str) -> str:
    return f"(('0x' || substr({sql_text(*keys)}, 1, 8))::BIGINT / 4294967296.0)"


def sql_pick(options: int | str, *keys: str) -> str:
    return f"floor({sql_unit(*keys)} * {options})::INT"
