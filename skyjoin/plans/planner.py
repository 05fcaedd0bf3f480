"""From statistics of a query to its execution: samples, order, cells, wedges with their margin."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.match import FORBID, REQUIRE, Participant, match_all, order_participants, reach
from ..operators.regions import Region
from ..operators.sampling import PRIME
from .jobs import Job, by_wedges
from .stats import partitions, wedges


@dataclass(frozen=True)
class Profile:
    """Rows that pass all single-catalog conditions, their standard error, and rows per square degree where they are densest."""

    rows: float
    error: float
    densest: float


def picked(p: Participant, rate: float) -> Column:
    """Whether a detection's key is in the sample: by hash, the same in every run and partitioning."""
    return F.pmod(F.xxhash64(*p.key), F.lit(PRIME)) < int(rate * PRIME) if rate < 1 else F.lit(True)


def profile(p: Participant, rate: float, region: Region | None = None) -> Profile:
    """One aggregate over a sample of a catalog, with its own conditions (and the region, if it is the owner's) applied."""
    df = p.rows().filter(picked(p, rate))
    ra, dec = (F.expr(c).cast("double") for c in p.position) if len(p.position) == 2 else (F.lit(0.0), F.lit(0.0))
    if region is not None and len(p.position) == 2:
        df = region.bounds().filter(df, *p.position)
    # Bands of a degree by sectors of about a degree: the densest of them stands for the fields where cells fill.
    band = F.floor(dec)
    sector = F.floor(ra * F.greatest(F.cos(F.radians(band + 0.5)), F.lit(0.01)))
    row = df.groupBy(band.alias("b"), sector.alias("s")).agg(F.count("*").alias("n")).agg(F.sum("n").alias("n"), F.max("n").alias("most")).first()
    n, most = row.n or 0, row.most or 0
    return Profile(n / rate, math.sqrt(max(n, 1) * (1 - rate)) / rate, most / rate if len(p.position) == 2 else 0.0)


def profiles(parts: list[Participant], rate: float, region: Region | None = None) -> dict[str, Profile]:
    """A profile of each catalog; the region counts for the first required one listed."""
    owner = next((p.alias for p in parts if p.mode == REQUIRE), None)
    return {p.alias: profile(p, rate, region if p.alias == owner else None) for p in parts}


def static_rows(parts: list[Participant]) -> dict[str, float]:
    """Whole tables' counts, without the query's conditions: the baseline of estimates."""
    return {p.alias: float(p.df.count()) for p in parts}


@dataclass(frozen=True)
class MatchPlan:
    """What statistics decide: order, density for the cells, wedges of the anchor, and the margin that partners need beside a wedge."""

    order: list[str]
    rows: dict[str, float]
    density: float | None
    anchor: str
    bounds: list[float]
    margin_deg: float


def plan_match(parts: list[Participant], limit: float, rate: float = 1e-3, region: Region | None = None, n: int | None = None, multiple: int = 3, method: str = "count") -> MatchPlan:
    """A plan from samples. n: wedges, else a multiple of the workers."""
    found = profiles(parts, rate, region)
    rows = {a: f.rows for a, f in found.items()}
    order = order_participants(parts, rows)
    anchor = order[0]
    bound = [p.bound() for p in order]
    need, taking = [p for p in bound if p.mode == REQUIRE], [p for p in bound if p.mode != FORBID]
    margin = max((reach(bound[0], p, need, taking, math.log(limit)) for p in taking if p.alias != anchor.alias), default=0.0)
    # A detection that blocks a tuple is near its combined position, which lies among its members.
    margin += max((reach(bound[0], p, need, [*taking, p], math.log(limit)) for p in bound if p.mode == FORBID), default=0.0)
    sample = anchor.rows().filter(picked(anchor, rate)) if found[anchor.alias].rows * rate > 100 * (n or 1) else anchor.rows()
    bounds = wedges(sample, n or partitions(anchor.df, multiple), method, anchor.position[0])
    return MatchPlan([p.alias for p in order], rows, max(f.densest for f in found.values()) or None, anchor.alias, bounds, margin)


def execute(parts: list[Participant], limit: float, mode: str = "join", rate: float = 1e-3, n: int | None = None, region: Region | None = None, root: str | None = None, plan: MatchPlan | None = None, **how) -> DataFrame:
    """A match by its plan. mode join: one distributed zone join. wedges: one match a wedge of the anchor's right ascension, a union of
    disjoint parts, or with root a job that stages each wedge there."""
    plan = plan or plan_match(parts, limit, rate, region, n)
    if mode == "join":
        return match_all(parts, limit, order="estimated", rows=plan.rows, density=plan.density, region=region, **how)
    if mode != "wedges":
        raise ValueError(f"unknown mode {mode}")
    if any(len(p.position) != 2 for p in parts):
        raise ValueError("wedges need positions as two angles")
    anchor = next(p for p in parts if p.alias == plan.anchor)
    rest = [p for p in parts if p.alias != plan.anchor]
    if any((p.position != anchor.position) for p in rest):
        raise ValueError("wedges need positions under the same names")

    def match(cut: DataFrame, others: list[DataFrame]) -> DataFrame:
        from dataclasses import replace

        frames = dict(zip([anchor.alias, *[p.alias for p in rest]], [cut, *others], strict=True))
        return match_all([replace(p, df=frames[p.alias]) for p in parts], limit, order="estimated", rows=plan.rows, density=plan.density, region=region, **how)

    step = by_wedges(anchor.df, [p.df for p in rest], plan.bounds, plan.margin_deg, match, *anchor.position)
    count = len(plan.bounds) - 1
    if root is not None:
        return Job(anchor.df.sparkSession, root, step, count).run()
    out = step(0)
    for k in range(1, count):
        out = out.unionByName(step(k))
    return out
