"""Uniforms and normals that are functions of a key: the same number in Spark, numpy and SQL, on any worker, on any retry.

u(key) is the integer of the first 13 hexadecimal digits of md5(key), divided by 2^52.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SCALE = float(1 << 52)


def uniform(key: str) -> float:
    return int(hashlib.md5(key.encode()).hexdigest()[:13], 16) / SCALE


def normal(key: str) -> float:
    return math.sqrt(-2.0 * math.log(1.0 - uniform(f"{key}-a"))) * math.cos(2.0 * math.pi * uniform(f"{key}-b"))


def uniforms(tag: str, *shape: int) -> np.ndarray:
    return np.array([uniform(f"{tag}-{'-'.join(map(str, i))}") for i in np.ndindex(*shape)]).reshape(shape)


def normals(tag: str, *shape: int) -> np.ndarray:
    return np.array([normal(f"{tag}-{'-'.join(map(str, i))}") for i in np.ndindex(*shape)]).reshape(shape)


def fast_normals(seed: int, *shape: int) -> np.ndarray:
    """For large matrices: a counter-based generator, the same on every worker, without an SQL form."""
    return np.random.Generator(np.random.Philox(seed)).standard_normal(shape)


def fast_uniforms(seed: int, *shape: int) -> np.ndarray:
    return np.random.Generator(np.random.Philox(seed)).random(shape)


def uniform_col(*parts: Column | str) -> Column:
    key = F.concat_ws("-", *[p if isinstance(p, Column) else F.lit(p) for p in parts])
    return F.conv(F.substring(F.md5(key.cast("binary")), 1, 13), 16, 10).cast("bigint") / F.lit(SCALE)


def normal_col(*parts: Column | str) -> Column:
    return F.sqrt(F.lit(-2.0) * F.ln(F.lit(1.0) - uniform_col(*parts, "a"))) * F.cos(F.lit(2.0 * math.pi) * uniform_col(*parts, "b"))


def bucket_col(n: int, *parts: Column | str) -> Column:
    """A bucket in 0..n-1 by key, equal in Spark, numpy and SQL."""
    return F.floor(uniform_col(*parts) * n).cast("int")


def uniform_sql(key: str) -> str:
    return f"(CAST('0x' || substr(md5({key}), 1, 13) AS BIGINT) / {SCALE!r}::DOUBLE)"


def normal_sql(key: str) -> str:
    a, b = uniform_sql(f"{key} || '-a'"), uniform_sql(f"{key} || '-b'")
    return f"(sqrt(-2.0::DOUBLE * ln(1.0::DOUBLE - {a})) * cos({2.0 * math.pi!r}::DOUBLE * {b}))"
