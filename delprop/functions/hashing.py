"""A uniform hash of (id, salt) that every SQL engine with md5 can repeat."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

SCALE = float(1 << 32)


def uniform(key: Column, salt: str | Column) -> Column:
    """First eight hex digits of md5('key:salt') over 2^32."""
    salt = F.lit(salt) if isinstance(salt, str) else salt
    digest = F.md5(F.concat(key.cast("string"), F.lit(":"), salt).cast("binary"))
    return F.conv(F.substring(digest, 1, 8), 16, 10).cast("double") / F.lit(SCALE)


def uniform_of(key: object, salt: str) -> float:
    return int(hashlib.md5(f"{key}:{salt}".encode()).hexdigest()[:8], 16) / SCALE


def uniform_sql(key: str, salt: str) -> str:
    """The same for DuckDB; ``key`` and ``salt`` are SQL expressions."""
    return f"(('0x' || substr(md5({key} || ':' || {salt}), 1, 8))::BIGINT / 4294967296.0)"


def identity(*keys: Column) -> Column:
    """A 60-bit id from the key columns, without a sort or a counter."""
    digest = F.md5(F.concat_ws("|", *[k.cast("string") for k in keys]).cast("binary"))
    return F.conv(F.substring(digest, 1, 15), 16, 10).cast("bigint")
