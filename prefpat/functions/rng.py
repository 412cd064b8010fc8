"""Portable random numbers.

A number depends on its key alone, not on partitions, engine or run: the first
eight hex digits of an MD5 over the joined key parts. Columns and plain Python
give the same values, and so does SQL on any engine with ``md5``.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = 4294967297.0


def u32(*parts) -> Column:
    """Uniform in 0 .. 2^32 - 1 from columns or literals."""
    joined = F.concat_ws("|", *[(p if isinstance(p, Column) else F.lit(p)).cast("string") for p in parts])
    return F.conv(F.substring(F.md5(joined), 1, 8), 16, 10).cast("long")


def u01(*parts) -> Column:
    """Uniform in (0, 1], never 0, so that its logarithm exists."""
    return (u32(*parts) + 1) / F.lit(SPAN)


def u32_py(*parts) -> int:
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:8], 16)


def u01_py(*parts) -> float:
    return (u32_py(*parts) + 1) / SPAN
