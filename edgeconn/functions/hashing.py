"""Seeded hashes as column expressions.

``md5`` gives the same draws in any SQL engine that has it; ``xxhash64`` is the
fast one for large graphs. Both are pure functions of their arguments, so a
task that runs again draws the same sample.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def hash_key(kind: str, *parts: Column) -> Column:
    """An orderable hash: hex text for md5, a long for xxhash64."""
    if kind == "md5":
        return F.md5(F.concat_ws(":", *(p.cast("string") for p in parts)))
    if kind == "xxhash64":
        return F.xxhash64(*parts)
    raise ValueError(f"no such hash: {kind}")


def hash_below(kind: str, p: float, *parts: Column) -> Column:
    """True with probability p: of md5 the first eight hex digits count."""
    if kind == "md5":
        return F.substring(hash_key(kind, *parts), 1, 8) < F.lit(hex_bound(p)) if p < 1 else F.lit(True)
    unsigned = hash_key(kind, *parts).cast("double") / 2.0**64 + 0.5
    return unsigned < p


def hex_bound(p: float) -> str:
    """Eight hex digits under which a share p of 32-bit numbers lies."""
    return f"{min(max(int(p * (1 << 32)), 0), (1 << 32) - 1):08x}"


def hash_mod(kind: str, n: int, *parts: Column) -> Column:
    """A cell from 0 to n - 1."""
    if kind == "md5":
        return (F.conv(F.substring(hash_key(kind, *parts), 1, 8), 16, 10).cast("long") % n).cast("int")
    return F.pmod(hash_key(kind, *parts), F.lit(n)).cast("int")
