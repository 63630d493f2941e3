"""Random draws and hashes that are functions of ids alone, the same in Spark and in DuckDB."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _text(salt: str, cols) -> Column:
    return F.concat_ws(":", F.lit(salt), *[(F.col(c) if isinstance(c, str) else c).cast("string") for c in cols])


def bits(salt: str, *cols, digits: int = 8) -> Column:
    """An integer from the first hex digits of md5(salt:ids)."""
    return F.conv(F.substring(F.md5(_text(salt, cols)), 1, digits), 16, 10).cast("long")


def uniform(salt: str, *cols) -> Column:
    """A number in (0, 1)."""
    return (bits(salt, *cols) + F.lit(0.5)) / F.lit(4294967296.0)


def bucket(n: int, salt: str, *cols) -> Column:
    return (bits(salt, *cols) % n).cast("int")


def sql_bits(salt: str, *cols: str, digits: int = 8) -> str:
    return f"('0x' || substr(md5(concat_ws(':', '{salt}', {', '.join(f'{c}::VARCHAR' for c in cols)})), 1, {digits}))::BIGINT"


def sql_uniform(salt: str, *cols: str) -> str:
    return f"(({sql_bits(salt, *cols)} + 0.5) / 4294967296.0)"


def sql_bucket(n: int, salt: str, *cols: str) -> str:
    return f"({sql_bits(salt, *cols)} % {n})::INTEGER"
