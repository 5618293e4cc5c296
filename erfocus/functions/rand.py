"""Counter-based uniforms: the same values in Spark, in Python and in SQL, whatever is retried."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = 1 << 32


def h32(text: Column) -> Column:
    """The first 32 bits of the text's MD5 as a number."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long")


def py_h32(text: str) -> int:
    return int.from_bytes(hashlib.md5(text.encode(), usedforsecurity=False).digest()[:4], "big")


def uniform(seed: int, run: int, step: int, slot: int) -> float:
    return py_h32(f"{seed}|{run}|{step}|{slot}") / SPAN


def sql_h32(text: str, engine: str) -> str:
    """The same number in SQL text for 'spark' or 'duckdb'."""
    digits = f"substr(md5({text}), 1, 8)"
    return f"cast(conv({digits}, 16, 10) as bigint)" if engine == "spark" else f"('0x' || {digits})::BIGINT"
