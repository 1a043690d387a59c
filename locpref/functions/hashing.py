"""Reproducible random draws from keyed hashes.

A draw depends on its key alone, so a task that runs again, another partitioning or
another engine gives the same one. Seeded draws are for tests and experiments: they
hide nothing from who knows the seed.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F


def hash_bits(seed: int, purpose: str, *parts: Column) -> Column:
    """52 bits of an md5 as a whole number."""
    key = F.concat_ws(":", F.lit(f"{seed}:{purpose}"), *(p.cast("string") for p in parts))
    return F.conv(F.substring(F.md5(key), 1, 13), 16, 10).cast("bigint")


def uniform(seed: int, purpose: str, *parts: Column) -> Column:
    """A double in [0, 1)."""
    return hash_bits(seed, purpose, *parts) / F.lit(float(2**52))


def gaussian(seed: int, purpose: str, *parts: Column) -> Column:
    """A standard normal draw from two uniforms."""
    radius = F.sqrt(-2.0 * F.log(1.0 - uniform(seed, f"{purpose}_r", *parts)))
    return radius * F.cos(2.0 * math.pi * uniform(seed, f"{purpose}_a", *parts))
