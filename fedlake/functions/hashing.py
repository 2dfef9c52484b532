"""Uniform and noise draws from MD5, equal in Spark and DuckDB.

A draw is a function of its key, so retried tasks and other partitionings give
the same value. Every function has a ``*_sql`` twin that writes DuckDB text.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def _col(x) -> Column:
    return x if isinstance(x, Column) else F.lit(x)


def key(seed: str, *parts) -> Column:
    return F.concat_ws("#", F.lit(seed), *[_col(p).cast("string") for p in parts])


def uniform(seed: str, *parts) -> Column:
    """In [0, 1): the first 32 bits of the key's MD5."""
    return F.conv(F.substring(F.md5(key(seed, *parts).cast("binary")), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)


def uniform_sql(seed: str, *parts: str) -> str:
    joined = ", ".join(f"({p})::VARCHAR" for p in parts)
    return f"(('0x' || substr(md5(concat_ws('#', '{seed}', {joined})), 1, 8))::BIGINT / 4294967296.0::DOUBLE)"


def normal(seed: str, *parts) -> Column:
    """A standard normal draw from two uniforms (cosine branch)."""
    u, v = uniform(seed + ":u", *parts), uniform(seed + ":v", *parts)
    return F.sqrt(F.lit(-2.0) * F.log(F.lit(1.0) - u)) * F.cos(F.lit(2 * math.pi) * v)


def normal_sql(seed: str, *parts: str) -> str:
    u, v = uniform_sql(seed + ":u", *parts), uniform_sql(seed + ":v", *parts)
    return f"(sqrt(-2.0::DOUBLE * ln(1.0::DOUBLE - {u})) * cos({2 * math.pi!r}::DOUBLE * {v}))"


def laplace(scale: float, seed: str, *parts) -> Column:
    """A Laplace draw by inverting its distribution function."""
    c = uniform(seed, *parts) - F.lit(0.5)
    return F.lit(-scale) * F.signum(c) * F.log(F.greatest(F.lit(1.0) - 2.0 * F.abs(c), F.lit(1e-12)))


def laplace_sql(scale: float, seed: str, *parts: str) -> str:
    c = f"({uniform_sql(seed, *parts)} - 0.5::DOUBLE)"
    return f"({-scale!r}::DOUBLE * sign({c}) * ln(greatest(1.0::DOUBLE - 2.0::DOUBLE * abs({c}), 1e-12::DOUBLE)))"
