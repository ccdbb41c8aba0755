"""Hashes as Column expressions.

``hashing="md5"`` gives the same integers in every SQL engine, so samples, sites and register sketches can be
checked elsewhere; ``"fast"``, the default everywhere, is the cheaper choice for production. Nulls must be
dropped first: ``xxhash64`` of a null is its seed.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

TWO32 = 1 << 32


def keyed(prefix: str, *cols: Column) -> Column:
    return F.concat_ws("|", F.lit(prefix), *[c.cast("string") for c in cols])


def md5_bits(digest: Column, chunk: int) -> Column:
    """The chunk-th 32 bits (0 to 3) of an md5 in hexadecimal, as a long."""
    return F.conv(F.substring(digest, 8 * chunk + 1, 8), 16, 10).cast("long")


def below(digest: Column, limit: int) -> Column:
    """Whether the first 32 bits of a hexadecimal md5 are below ``limit``: digits compare as the numbers do."""
    if limit >= TWO32:
        return F.lit(True)
    return F.substring(digest, 1, 8) < F.lit(f"{limit:08x}")


def two_words(value: Column, seed: int = 0, hashing: str = "fast") -> tuple[Column, Column]:
    """128 bits of a value as two longs; bits of the first choose register and rank, of the second counters."""
    if hashing == "md5":
        d = F.md5(keyed(str(seed), value))
        return tuple(F.conv(F.substring(d, at, 16), 16, -10).cast("long") for at in (1, 17))
    return F.xxhash64(F.lit(seed), value), F.xxhash64(F.lit(~seed), value)


def value_key(*cols: Column) -> Column:
    """One long for one or several columns of any hashable type; maps are sorted into entries by the caller."""
    return F.xxhash64(*cols)


def rank32(bits: Column) -> Column:
    """Position of the first one in 32 bits, from 1; 33 if there is none."""
    return F.when(bits == 0, F.lit(33)).otherwise(33 - F.length(F.bin(bits))).cast("int")


def register_and_rank(value: Column, b: int, seed: int = 0, hashing: str = "fast") -> tuple[Column, Column]:
    if hashing == "md5":
        d = F.md5(keyed(str(seed), value))
        return (md5_bits(d, 0) % (1 << b)).cast("int"), rank32(md5_bits(d, 1))
    h = two_words(value, seed)[0]
    return F.shiftrightunsigned(h, 32).bitwiseAND(F.lit((1 << b) - 1)).cast("int"), rank32(h.bitwiseAND(F.lit(TWO32 - 1)))
