"""Uniform numbers from a hash that Spark and other SQL engines compute alike, so every sample can be checked in SQL."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def u01(seed: int, *ids: Column | str) -> Column:
    """A number in [0, 1) that depends on the seed and the ids alone, not on how rows are dealt."""
    text = F.concat_ws(":", F.lit(str(seed)), *(F.col(x).cast("string") if isinstance(x, str) else x.cast("string") for x in ids))
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") / F.lit(float(1 << 32))


def u01_fast(seed: int, *ids: Column | str) -> Column:
    """The same purpose with Spark's own hash, for scans where md5 would cost more than the read."""
    return F.shiftrightunsigned(F.xxhash64(F.lit(seed), *ids), 11).cast("double") / F.lit(float(1 << 53))


def key_hash(*ids: str) -> Column:
    """A 60-bit id from a composite key."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", *(F.col(x).cast("string") for x in ids))), 1, 15), 16, 10).cast("long")


def u01_sql(seed: int, *ids: str) -> str:
    joined = " || ':' || ".join([f"'{seed}'", *(f"({x})::varchar" for x in ids)])
    return f"(('0x' || substr(md5({joined}), 1, 8))::bigint / 4294967296.0::double)"


def key_hash_sql(*ids: str) -> str:
    joined = " || ':' || ".join(f"({x})::varchar" for x in ids)
    return f"('0x' || substr(md5({joined}), 1, 15))::bigint"
