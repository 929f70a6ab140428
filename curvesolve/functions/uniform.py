"""Counter-based uniform numbers that Spark, SQL and Python compute alike."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

SPAN = 1 << 32


def hash32(*parts: Column | int | str) -> Column:
    """The first 32 bits of the md5 of the parts joined by colons, as a long."""
    cols = [p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws(":", *cols).cast("binary")), 1, 8), 16, 10).cast("long")


def uniform(*parts: Column | int | str) -> Column:
    """A number in [0, 1) that depends on the parts alone."""
    return hash32(*parts) / F.lit(float(SPAN))


def py_uniform(*parts: int | str) -> float:
    return int(hashlib.md5(":".join(map(str, parts)).encode()).hexdigest()[:8], 16) / SPAN
