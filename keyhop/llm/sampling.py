"""Bounded, repeatable samples for fitting classifiers, and what else the operators share."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_RANGE = 1 << 32


def hash_share(col: Column, salt: str) -> Column:
    """A number in [0, 2^32) that depends on the value of ``col`` alone."""
    return F.pmod(F.xxhash64(F.lit(salt), col), F.lit(_RANGE))


def sample(df: DataFrame, id_col: str, rows: int, salt: str, total: int | None = None) -> DataFrame:
    """About ``rows`` rows of ``df`` (never more), chosen by a hash of the id; all rows where there are fewer.

    Repeatable for the same table at any partitioning: should more than ``rows`` pass the hash, those of
    the smallest hashes (of equal ones the smallest rows) are taken.
    """
    total = df.count() if total is None else total
    if total <= rows:
        return df
    limit = int(_RANGE * rows / total * 0.95)
    share = hash_share(F.col(id_col), salt)
    return df.where(share < limit).orderBy(share, *df.columns).limit(rows)


def crc_mod(id_col: Column, modulus: int) -> Column:
    """crc32 of the id's text modulo ``modulus``; a null id gives null."""
    return F.pmod(F.crc32(id_col.cast("string")), F.lit(modulus))


def fresh_name(df: DataFrame, name: str) -> str:
    """``name``, or with underscores added until no column of ``df`` has it in any case."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name
