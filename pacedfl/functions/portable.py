"""Random draws as columns that any SQL engine computes alike: uniforms from md5, normals from two uniforms."""

from __future__ import annotations

import hashlib
import math

from pyspark.sql import Column, functions as F


def uniform(seed: int, tag: str, *keys: Column | str | int) -> Column:
    """Uniform in [0, 1) from md5 of 'seed:tag:key:...'."""
    parts = [F.lit(f"{seed}:{tag}"), *((F.col(k) if isinstance(k, str) else k if isinstance(k, Column) else F.lit(k)).cast("string") for k in keys)]
    return F.conv(F.substring(F.md5(F.concat_ws(":", *parts)), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def uniform_py(seed: int, tag: str, *keys) -> float:
    """The same draw on the driver."""
    return int(hashlib.md5(":".join([f"{seed}:{tag}", *map(str, keys)]).encode()).hexdigest()[:8], 16) / 4294967296.0


def gaussian(seed: int, tag: str, *keys) -> Column:
    """Standard normal from two uniforms."""
    u, v = uniform(seed, f"{tag}.a", *keys), uniform(seed, f"{tag}.b", *keys)
    return F.sqrt(-2.0 * F.log((u * 4294967296.0 + 1.0) / 4294967297.0)) * F.cos(2.0 * math.pi * v)


def r6(c: Column | str, digits: int = 6) -> Column:
    """Rounded for comparison, without a negative zero."""
    return F.round(c, digits) + F.lit(0.0)
