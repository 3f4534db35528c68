"""Digests, positions and draws: two dialects of the same roles, as column expressions and as numpy kernels.

``fast`` is xxhash64 throughout and has a numpy twin, equal bit for bit. ``portable`` uses the first 60
bits of md5 over text, which other engines compute alike; it exists for comparison with them.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

LN2 = 0.6931471805599453


def md5_60(text: Column) -> Column:
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def joined(*parts: Column | str | int) -> Column:
    return F.concat_ws(":", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])


class Fast:
    """xxhash64 of the digest and small integers."""

    name = "fast"

    @staticmethod
    def digest(payload: Column) -> Column:
        return F.xxhash64(payload)

    @staticmethod
    def mix(digest: Column, *salt: Column | int) -> Column:
        return F.xxhash64(digest, *[(s if isinstance(s, Column) else F.lit(s)).cast("long") for s in salt])

    @classmethod
    def below(cls, m: Column | int, digest: Column, *salt: Column | int) -> Column:
        return F.pmod(cls.mix(digest, *salt), m if isinstance(m, Column) else F.lit(m))

    @classmethod
    def draw(cls, digest: Column, step: Column) -> Column:
        """Uniform in [0, 1)."""
        return F.shiftrightunsigned(cls.mix(digest, 77, step), 11) * F.lit(2.0**-53)

    @classmethod
    def check(cls, digest: Column) -> Column:
        return cls.mix(digest, 1_000_003)


class Portable:
    """md5 over ``digest:salt:...``; 60-bit values, never negative."""

    name = "portable"

    @staticmethod
    def digest(payload: Column) -> Column:
        return md5_60(payload)

    @staticmethod
    def mix(digest: Column, *salt: Column | int) -> Column:
        return md5_60(joined(digest, *salt))

    @classmethod
    def below(cls, m: Column | int, digest: Column, *salt: Column | int) -> Column:
        return F.pmod(cls.mix(digest, *salt), m if isinstance(m, Column) else F.lit(m))

    @classmethod
    def draw(cls, digest: Column, step: Column) -> Column:
        return cls.mix(digest, 77, step) / F.lit(2.0**60)

    @classmethod
    def check(cls, digest: Column) -> Column:
        return cls.mix(digest, 1_000_003)


DIALECTS = {d.name: d for d in (Fast, Portable)}


# The numpy twin of ``Fast``. Constants are those of the published 64-bit xxHash.
P1, P2, P3, P4, P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def rotated(x: np.ndarray, by: int) -> np.ndarray:
    return (x << np.uint64(by)) | (x >> np.uint64(64 - by))


def hash_long(value: np.ndarray, seed: np.ndarray) -> np.ndarray:
    """One step of Spark's xxhash64 chain over a long."""
    h = seed + P5 + np.uint64(8)
    h = h ^ (rotated(value * P2, 31) * P1)
    h = rotated(h, 27) * P1 + P4
    h = (h ^ (h >> np.uint64(33))) * P2
    h = (h ^ (h >> np.uint64(29))) * P3
    return h ^ (h >> np.uint64(32))


def mix_np(digest: np.ndarray, *salt: int | np.ndarray) -> np.ndarray:
    """Unsigned twin of ``Fast.mix``."""
    with np.errstate(over="ignore"):
        h = hash_long(np.asarray(digest, np.int64).view(np.uint64), np.full(len(digest), 42, np.uint64))
        for s in salt:
            s = np.asarray(s, np.int64)
            h = hash_long(np.broadcast_to(s, h.shape).astype(np.int64).view(np.uint64), h)
    return h


def below_np(m: int, digest: np.ndarray, *salt: int | np.ndarray) -> np.ndarray:
    return mix_np(digest, *salt).view(np.int64) % np.int64(m)


def draw_np(digest: np.ndarray, step: int | np.ndarray) -> np.ndarray:
    return (mix_np(digest, 77, step) >> np.uint64(11)).astype(np.float64) * 2.0**-53


def check_np(digest: np.ndarray) -> np.ndarray:
    return mix_np(digest, 1_000_003)


def portable_np(digest: np.ndarray, *salt: int) -> np.ndarray:
    """Twin of ``Portable.mix``: md5 knows no vectors, so this is for oracles and small sets."""
    end = "".join(f":{s}" for s in salt).encode()
    md5 = hashlib.md5
    first = b"".join([md5(b"%d%b" % (x, end)).digest()[:8] for x in np.asarray(digest, np.int64).tolist()])
    return (np.frombuffer(first, ">u8") >> np.uint64(4)).astype(np.int64)


def mixed_np(dialect: str, digest: np.ndarray, *salt: int) -> np.ndarray:
    """Signed twin of ``mix`` in either dialect; ``% m`` gives the position."""
    return portable_np(digest, *salt) if dialect == "portable" else mix_np(digest, *salt).view(np.int64)


def canonical(df: DataFrame, columns: list[str] | None = None) -> Column:
    """One text per row that tells all rows apart: each field with its length, nulls with a mark of their own."""

    def text(name: str, kind: T.DataType) -> Column:
        return spelled(F.col(f"`{name}`"), kind)

    fields = [f for f in df.schema.fields if columns is None or f.name in columns]
    if columns is not None:
        fields.sort(key=lambda f: columns.index(f.name))
    parts = []
    for f in fields:
        t = text(f.name, f.dataType)
        parts.append(F.when(t.isNull(), F.lit("~")).otherwise(F.concat(F.length(t).cast("string"), F.lit("="), t)))
    return F.concat_ws(";", *parts)


def spelled(c: Column, kind: T.DataType) -> Column:
    if isinstance(kind, T.TimestampNTZType):
        return F.unix_micros(c.cast("timestamp")).cast("string")
    if isinstance(kind, T.TimestampType):
        return F.unix_micros(c).cast("string")
    if isinstance(kind, T.BinaryType):
        return F.hex(c)
    if isinstance(kind, T.ArrayType):
        return F.array_join(F.transform(c, lambda x: F.coalesce(spelled(x, kind.elementType), F.lit("~"))), ",")
    if isinstance(kind, T.MapType):
        entries = F.array_sort(F.map_entries(c))
        pair = lambda e: F.concat_ws("=", spelled(e["key"], kind.keyType), F.coalesce(spelled(e["value"], kind.valueType), F.lit("~")))
        return F.array_join(F.transform(entries, pair), ",")
    if isinstance(kind, T.StructType):
        inner = F.concat_ws(",", *[F.coalesce(spelled(c[f.name], f.dataType), F.lit("~")) for f in kind.fields])
        return F.when(c.isNotNull(), inner)
    return c.cast("string")
