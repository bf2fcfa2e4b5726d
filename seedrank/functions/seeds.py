"""Random seeds as hashes: a retried task, another process or another engine draws the same ones."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 52


def _text(*parts) -> Column:
    return F.concat_ws("|", *[p if isinstance(p, Column) else F.lit(str(p)) for p in parts])


def uniform(*parts, algo: str = "md5") -> Column:
    """A number in (0, 1) from the hash of the parts; ``md5`` is portable, ``xxhash64`` fast."""
    if algo == "md5":
        number = F.conv(F.substring(F.md5(_text(*parts).cast("binary")), 1, BITS // 4), 16, 10).cast("bigint")
    elif algo == "xxhash64":
        number = F.shiftrightunsigned(F.xxhash64(_text(*parts)), 64 - BITS)
    else:
        raise ValueError(f"unknown hash: {algo}")
    return (number + F.lit(0.5)) / F.lit(float(2**BITS))


def salted(salt: str, run: Column) -> Column:
    """The salt of one replication: every run draws seeds of its own."""
    return F.concat_ws("#", F.lit(salt), run.cast("string"))


def key_seed(key: Column, salt, algo: str = "md5") -> Column:
    """One seed for a key, shared by all its assignments."""
    return uniform(salt, key, algo=algo)


def pair_seed(key: Column, assignment: Column, salt, algo: str = "md5") -> Column:
    """A seed of its own for each (key, assignment)."""
    return uniform(salt, assignment, key, algo=algo)


def gap_seed(key: Column, level: Column, salt, algo: str = "md5") -> Column:
    """A seed for one gap of a key's sorted weight vector."""
    return uniform(salt, F.lit("gap"), level.cast("string"), key, algo=algo)


def draw_seed(key: Column, draw: Column, salt, algo: str = "md5") -> Column:
    """A seed for one of several independent draws of a key."""
    return uniform(salt, F.lit("draw"), draw.cast("string"), key, algo=algo)
