"""Uniform numbers from hashes, and rank families.

A rank is a random number whose law depends on the weight: the heavier an item, the smaller.  All
randomness comes from a hash of a seed and the item's id, so copies of an item, retries of a task
and other engines give the same ranks.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Size of the grid of uniform numbers: 13 hexadecimal digits.
GRID = float(1 << 52)


def _col(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def hash_uniform(seed: str, *ids: Column | str) -> Column:
    """A number in (0, 1) for each combination of ids, the same in every engine that has MD5."""
    text = F.concat_ws("|", F.lit(seed), *[_col(c).cast("string") for c in ids])
    bits = F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("bigint")
    return (bits.cast("double") + 0.5) / F.lit(GRID)


def uniform_of(*parts) -> float:
    """The same number as ``hash_uniform`` of a seed and ids, for numeric code on the rows of a sketch."""
    import hashlib

    return (int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:13], 16) + 0.5) / GRID


def fast_uniform(seed: str, *ids: Column | str) -> Column:
    """As ``hash_uniform`` by a cheaper hash that other engines lack; for very large inputs."""
    bits = F.shiftrightunsigned(F.xxhash64(F.lit(seed), *[_col(c) for c in ids]), 12)
    return (bits.cast("double") + 0.5) / F.lit(GRID)


def rand_uniform(seed: int) -> Column:
    """Pseudo-random; it depends on the partitioning, so keep what is built from it before using it twice."""
    return F.rand(seed)


@dataclass(frozen=True)
class RankFamily:
    """A law of ranks: cdf(weight, r) = Pr(rank <= r) and its inverse in the uniform number."""

    name: str
    cdf: Callable[[Column, Column], Column]
    inverse: Callable[[Column, Column], Column]

    def rank(self, u: Column, w: Column) -> Column:
        return self.inverse(w, u)


def rank_exp(u: Column, w: Column) -> Column:
    """Exponential with rate w; the k smallest are a weighted sample without replacement."""
    return -F.log(u) / w


def rank_priority(u: Column, w: Column) -> Column:
    return u / w


def rank_uniform(u: Column, w: Column | None = None) -> Column:
    return u


EXP = RankFamily("exp", lambda w, r: -F.expm1(-w * r), lambda w, u: -F.log(u) / w)
PRIORITY = RankFamily("priority", lambda w, r: F.least(F.lit(1.0), w * r), lambda w, u: u / w)
UNIFORM = RankFamily("uniform", lambda w, r: F.least(F.lit(1.0), r), lambda w, u: u)
FAMILIES = {f.name: f for f in (EXP, PRIORITY, UNIFORM)}


def family_of(family: str | RankFamily) -> RankFamily:
    return family if isinstance(family, RankFamily) else FAMILIES[family]


def remap_rank(rank: Column, w: Column, source: str | RankFamily, target: str | RankFamily) -> Column:
    """The rank of another family that is as likely to be undercut: order is kept among items of one weight."""
    source, target = family_of(source), family_of(target)
    level = source.cdf(w, rank)
    return target.inverse(w, 1 - level if target.name == "exp" else level)  # exponential ranks fall with their uniform number


def redrawn_rank(u: Column, w: Column, tau: Column, family: str = "exp") -> Column:
    """A rank drawn from the law below ``tau``: what the ranks of a sketch's items are, given tau alone."""
    if family == "exp":
        return -F.log1p(u * F.expm1(-w * tau)) / w
    if family == "priority":
        return u * F.least(1 / w, tau)
    if family == "uniform":
        return u * F.least(F.lit(1.0), tau)
    raise ValueError(f"no redraw for the family {family}")


def piece_rank(seed: str, pieces: list[Column | str], w: Column) -> Column:
    """Exponential rank of a piece of an item; the least over an item's pieces is exponential with their total weight."""
    return rank_exp(hash_uniform(seed, *pieces), w)
