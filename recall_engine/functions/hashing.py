"""Reproducible sampling keys: a keyed hash of pair and stratum, the same under any partitioning."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

HEX_DIGITS = 13


def key(pair_id: Column, stratum: Column, seed: int, family: str = "xxhash64") -> Column:
    """Sorts as an unsigned hash. ``md5`` gives a hexadecimal string that any engine can compute."""
    if family == "md5":
        return F.md5(F.concat_ws("|", F.lit(str(seed)), pair_id, stratum.cast("string")))
    # Flipping the sign bit makes the signed order the unsigned one.
    return F.xxhash64(F.lit(seed).cast("long"), pair_id, stratum.cast("int")).bitwiseXOR(F.lit(-(1 << 63)))


def key_sql(stratum: str, seed: int) -> str:
    """The xxhash64 key of pair_id as an SQL expression: many keys then take one call to build."""
    return f"xxhash64({seed}L, pair_id, CAST({stratum} AS INT)) ^ (-9223372036854775808L)"


def below(key_column: Column, share: Column, family: str = "xxhash64") -> Column:
    """Whether the key lies in the lowest ``share`` (0 to 1, double) of its range."""
    if family == "md5":
        return (share >= 1.0) | (F.conv(F.substring(key_column, 1, HEX_DIGITS), 16, 10).cast("double") < share * float(16**HEX_DIGITS))
    return (share >= 1.0) | (key_column.cast("double") < share * float(1 << 64) - float(1 << 63))


def concatenated(pair_id: Column, stratum: Column) -> Column:
    """Plain XXH64, seed 42, of 8 bytes of the id and one of the stratum, both big-endian."""
    bytes_ = F.unhex(F.concat(F.lpad(F.hex(pair_id.cast("long")), 16, "0"), F.lpad(F.hex(stratum.cast("long")), 2, "0")))
    return F.xxhash64(bytes_)
