"""Mini copies: uniform samples that keep foreign keys intact, by a hash of the root's key."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PRIME = 2147483647
RATE = 1e-3


@dataclass(frozen=True)
class Link:
    """child.column refers to parent.key."""

    child: str
    column: str
    parent: str
    key: str


def chosen(key: Column, rate: float, seed: int = 0) -> Column:
    """Whether a key is in the sample: a portable hash, the same on every engine and partitioning."""
    m = F.pmod(key.cast("long") + seed, F.lit(PRIME))
    m = F.pmod(m * 1103515245 + 12345, F.lit(PRIME))
    return F.pmod(m * m, F.lit(PRIME)) < int(rate * PRIME)


def mini(tables: dict[str, DataFrame], root: str, key: str, links: list[Link], rate: float = RATE, seed: int = 0) -> dict[str, DataFrame]:
    """A sample of every table that hangs on the root: the root by hash, each child by a semi-join with its parent's sample."""
    out = {root: tables[root].filter(chosen(F.col(key), rate, seed))}
    left = list(links)
    while left:
        ready = [x for x in left if x.parent in out]
        if not ready:
            raise ValueError(f"no path from {root} to {[x.child for x in left]}")
        for x in ready:
            parents = out[x.parent].select(F.col(x.key).alias(x.column))
            out[x.child] = tables[x.child].join(parents, x.column, "left_semi")
            left.remove(x)
    return out
