"""Reproducible randomness: every random choice is a hash of (seed, epoch, batch, ... , ids).

`priority` is md5 text, equal in any SQL engine; `fast_priority` is xxhash64 for large runs. Leaving a field out of the hash
means that the choice is shared along it, e.g. without the hop all layers share one sample.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

MIX_PRIME = 2147483647


def _col(x) -> Column:
    return x if isinstance(x, Column) else F.lit(x)


def priority(*parts) -> Column:
    """md5 over the parts joined with ':'; constants may be plain numbers."""
    return F.md5(F.concat_ws(":", *(_col(p).cast("string") for p in parts)))


def fast_priority(*parts) -> Column:
    return F.xxhash64(*(_col(p) for p in parts))


def mix(a, b) -> Column:
    """Portable pseudo-random number in 0 .. 2**31-2 from an id and a seed."""
    once = F.pmod(F.pmod(_col(a), F.lit(MIX_PRIME)) * 1103515245 + _col(b) * 16807 + 7, F.lit(MIX_PRIME))
    return F.pmod(once * 69621, F.lit(MIX_PRIME))


def mix_int(a: int, b: int) -> int:
    """The same for plain numbers."""
    return ((a % MIX_PRIME) * 1103515245 + b * 16807 + 7) % MIX_PRIME * 69621 % MIX_PRIME
