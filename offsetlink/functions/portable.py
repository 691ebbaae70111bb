"""Expressions that give the same values in Spark and in DuckDB, each beside its SQL twin.

``mix`` is a cheap integer mixer for splits and orders; its streams are shifted copies of one another, so attributes and
noise use ``u32``, the first 32 bits of md5.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

# A prime modulus and two multipliers of the mixer; features are kept as ten-thousandths.
MODULUS, FIRST, SECOND = 2147483647, 48271, 16807
FIXED = 10_000


def mix(key: Column, c: int = 0) -> Column:
    return (key.cast("long") * FIRST + c) % MODULUS * SECOND % MODULUS


def mix_sql(key: str, c: int = 0) -> str:
    return f"((CAST({key} AS BIGINT) * {FIRST} + {c}) % {MODULUS} * {SECOND} % {MODULUS})"


def _text(parts) -> Column:
    return F.concat_ws("|", *(F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts))


def _text_sql(parts: tuple[str, ...]) -> str:
    return "concat_ws('|', " + ", ".join(p if p.startswith("'") else f"CAST({p} AS VARCHAR)" for p in parts) + ")"


def u32(*parts: Column | str) -> Column:
    """A uniform integer below 2**32 from the parts, joined by bars; plain strings are taken literally."""
    return F.conv(F.substring(F.md5(_text(parts).cast("binary")), 1, 8), 16, 10).cast("long")


def u32_sql(*parts: str) -> str:
    """Twin of u32: parts in single quotes are literals, others SQL expressions."""
    return f"CAST('0x' || substr(md5({_text_sql(parts)}), 1, 8) AS BIGINT)"


def uniform(*parts: Column | str) -> Column:
    return u32(*parts) / F.lit(float(1 << 32))


def uniform_sql(*parts: str) -> str:
    return f"({u32_sql(*parts)} / 4294967296.0::DOUBLE)"


def normal(*parts: Column | str) -> Column:
    """A standard normal value, rounded to nine places, from two uniforms."""
    radius = F.sqrt(-2.0 * F.log((u32("z1", *parts) + 1) / F.lit(float(1 << 32))))
    return F.round(radius * F.cos(2 * math.pi * u32("z2", *parts) / F.lit(float(1 << 32))), 9)


def normal_sql(*parts: str) -> str:
    a, b = u32_sql("'z1'", *parts), u32_sql("'z2'", *parts)
    return f"round(sqrt(-2.0::DOUBLE * ln(({a} + 1) / 4294967296.0::DOUBLE)) * cos({2 * math.pi!r}::DOUBLE * {b} / 4294967296.0::DOUBLE), 9)"


def ascii_fold(text: Column) -> Column:
    """Lower case, with everything but printable ASCII as a blank."""
    return F.lower(F.regexp_replace(F.coalesce(text, F.lit("")), r"[^\x20-\x7E]", " "))


def ascii_fold_sql(text: str) -> str:
    return rf"lower(regexp_replace(coalesce({text}, ''), '[^\x20-\x7E]', ' ', 'g'))"
