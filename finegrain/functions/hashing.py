"""Seeded hashes that stand for random choices: a retried or speculative task makes the same ones."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

_RANGE = 1 << 32


def portable_hash(*parts: Column | str | int) -> Column:
    """32 bits as a non-negative BIGINT: the first eight hexadecimal digits of the MD5 of the parts joined by bars.

    Any SQL engine gives the same number.
    """
    columns = [p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *columns).cast("binary")), 1, 8), 16, 10).cast("long")


def fast_hash(*parts: Column | str | int) -> Column:
    """The low 32 bits of xxHash64 of the parts; for runs at scale."""
    columns = [p if isinstance(p, Column) else F.lit(p) for p in parts]
    return F.xxhash64(*columns).bitwiseAND(F.lit(_RANGE - 1))


HASHES = {"portable": portable_hash, "fast": fast_hash}


def fraction(h: Column) -> Column:
    """A 32-bit hash as a number in [0, 1)."""
    return h / F.lit(float(_RANGE))
