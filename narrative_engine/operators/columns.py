"""Small helpers for nested column expressions."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of ``value`` evaluated once; a lambda that names an expression evaluates it anew for every element."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def uniform(*parts: Column | str) -> Column:
    """A number in [0, 1) that depends on ``parts`` alone (24 bits of their md5)."""
    key = F.concat_ws("|", *[F.lit(p) if isinstance(p, str) else p for p in parts])
    return F.conv(F.substring(F.md5(key.cast("binary")), 1, 6), 16, 10).cast("double") / F.lit(float(1 << 24))
