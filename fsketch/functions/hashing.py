"""Reproducible randomness from md5: the same numbers in Spark, in Python and in SQL, whatever the partitioning.

A uniform is taken from 12 hex digits of md5 over parts joined by ``|``; a normal is made of two uniforms (Box-Muller).
"""

from __future__ import annotations

import hashlib
import math

from pyspark.sql import Column
from pyspark.sql import functions as F

SCALE = float(1 << 48)


def uniform(*parts) -> Column:
    """Column of uniforms in (0, 1); parts are columns or plain values."""
    text = F.concat_ws("|", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return (F.conv(F.substring(F.md5(text), 1, 12), 16, 10).cast("long") + 0.5) / F.lit(SCALE)


def normal(*parts) -> Column:
    return F.sqrt(-2 * F.log(uniform("a", *parts))) * F.cos(2 * math.pi * uniform("b", *parts))


def py_uniform(*parts) -> float:
    text = "|".join(str(p) for p in parts)
    return (int(hashlib.md5(text.encode()).hexdigest()[:12], 16) + 0.5) / SCALE


def py_normal(*parts) -> float:
    return math.sqrt(-2 * math.log(py_uniform("a", *parts))) * math.cos(2 * math.pi * py_uniform("b", *parts))


def sql_uniform(*parts: str) -> str:
    """DuckDB text of the same uniform; parts are SQL expressions."""
    return f"((('0x' || substr(md5(concat_ws('|', {', '.join(f'({p})::VARCHAR' for p in parts)})), 1, 12))::BIGINT + 0.5) / {SCALE:.1f})"


def sql_normal(*parts: str) -> str:
    return f"(sqrt(-2 * ln({sql_uniform(chr(39) + 'a' + chr(39), *parts)})) * cos({2 * math.pi!r} * {sql_uniform(chr(39) + 'b' + chr(39), *parts)}))"
