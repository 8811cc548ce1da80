"""Deterministic uniform draws.

A draw is a hash of a seed and the keys of what is drawn, so a retried task draws
the same, the result doesn't depend on partitioning, and Catalyst may push the
predicate down. ``xxhash64`` stays in generated code; ``md5`` is portable, other
engines can reproduce it bit by bit.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

KINDS = ("xxhash64", "md5")


def unit_draw(seed: int | Column, *keys: Column | str, kind: str = "xxhash64") -> Column:
    """Uniform in [0, 1), a function of seed (a number or an int column) and keys alone."""
    seed = seed if isinstance(seed, Column) else F.lit(seed)
    columns = [F.col(k) if isinstance(k, str) else k for k in keys]
    if kind == "xxhash64":
        return F.shiftrightunsigned(F.xxhash64(seed, *columns), 11) * F.lit(2.0**-53)
    if kind == "md5":
        text = F.concat_ws("|", seed.cast("string"), *[c.cast("string") for c in columns])
        return F.conv(F.substring(F.md5(text.cast("binary")), 1, 13), 16, 10).cast("long").cast("double") / F.lit(float(1 << 52))
    raise ValueError(f"unknown draw {kind!r}: one of {KINDS}")
