"""Hash numbers that any SQL engine can repeat, for choices that must not depend on layout or engine."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

DIGITS = 12


def number(*parts: Column) -> Column:
    """A number below 2**48 from the MD5 of the parts' texts joined by colons."""
    text = F.concat_ws(":", *[p.cast("string") for p in parts])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, DIGITS), 16, 10).cast("long")


def uniform(*parts: Column) -> Column:
    """Strictly between 0 and 1, on a grid that doubles hold exactly."""
    return (number(*parts).cast("double") + 0.5) / float(1 << 4 * DIGITS)


def duck_number(*parts: str) -> str:
    text = " || ':' || ".join(f"CAST({p} AS VARCHAR)" for p in parts)
    return f"CAST('0x' || substr(md5({text}), 1, {DIGITS}) AS BIGINT)"


def duck_uniform(*parts: str) -> str:
    return f"((CAST({duck_number(*parts)} AS DOUBLE) + 0.5) / {float(1 << 4 * DIGITS)})"
