"""Random streams that Spark and DuckDB share: the first 8 hex digits of an MD5."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def uniform(seed: int | str, row: Column, j: int | str, run: int | str = 0) -> Column:
    """A number in [0, 1) that depends on seed, run, row and j alone."""
    text = F.concat(F.lit(f"{seed}:{run}:"), row.cast("string"), F.lit(f":{j}"))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("double") / float(1 << 32)


def normal(seed: int | str, row: Column, j: int, run: int | str = 0) -> Column:
    """A standard Gaussian by Box-Muller from streams 2j and 2j + 1."""
    u, v = uniform(seed, row, 2 * j, run), uniform(seed, row, 2 * j + 1, run)
    return F.sqrt(-2 * F.log(1 - u)) * F.cos(2 * math.pi * v)


def uniform_sql(seed: int | str, row: str, j: int | str, run: int | str = 0) -> str:
    return f"(('0x' || substr(md5('{seed}:{run}:' || ({row})::VARCHAR || ':{j}'), 1, 8))::BIGINT / 4294967296.0)"


def normal_sql(seed: int | str, row: str, j: int, run: int | str = 0) -> str:
    return f"(sqrt(-2 * ln(1 - {uniform_sql(seed, row, 2 * j, run)})) * cos(2 * pi() * {uniform_sql(seed, row, 2 * j + 1, run)}))"
