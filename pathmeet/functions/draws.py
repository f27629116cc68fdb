"""Reproducible draws in [0, 1) per node: the same after a task retry, whatever the partitioning."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def md5_draw(id: Column, seed: int) -> Column:
    """The first 32 bits of md5("id:seed") over 2^32; other engines compute the same."""
    text = F.md5(F.concat_ws(":", id.cast("string"), F.lit(str(seed))).cast("binary"))
    return F.conv(F.substring(text, 1, 8), 16, 10).cast("double") / float(1 << 32)


def fast_draw(id: Column, seed: int) -> Column:
    """53 bits of xxhash64; cheaper than md5."""
    return F.shiftrightunsigned(F.xxhash64(id, F.lit(seed)), 11).cast("double") / float(1 << 53)
