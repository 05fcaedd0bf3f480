"""Probabilistic n-way matching of catalogs that must, may or must not take part, in any order, as one declarative plan.

Every catalog becomes a table of one-member states (functions.evidence); matching two state tables is a zone join of their
best positions within the widest acceptable chord, a merge of states, and an exact bound on what can still be reached. The
result has a struct column for each catalog (null where an optional one is absent) and one for the virtual match relation.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from ..functions.evidence import ln_bayes, ln_bound, ln_term, merged_deficit, search_chord, weight
from ..functions.plan import checkpointed, sealed
from ..functions.sphere import PER_RADIAN, angle_of, chord2, declination, length, right_ascension, sky_to_xyz
from .regions import Region
from .zones import CROWDED_LEVELS_OVER_RADIUS, CROWDED_OVER_RADIUS, LEAST_OVER_RADIUS, LEVEL_STEP, OVER_RADIUS, Grid, choose_grid, pair_table, reached, sky_columns, weight_levels, zone_table

REQUIRE, ALLOW, FORBID = "require", "allow", "forbid"
STATE = ("__ax", "__ay", "__az", "__W", "__D", "__S")
#: Cells wider than this (degrees) are worth a look at the density of the catalogs; a side of more rows is not broadcast.
WIDE_CELL, BROADCAST_ROWS = 120.0 / 3600, 50_000
#: States of another side that a detection may carry along on average, by the measured density.
MOST_NEAR = 64.0


@dataclass(frozen=True)
class Participant:
    """A catalog and how it takes part. error: arc seconds, as a number or SQL text; where: SQL text on its detections."""

    alias: str
    df: DataFrame
    mode: str = REQUIRE
    key: tuple[str, ...] = ("key",)
    position: tuple[str, ...] = ("ra", "dec")
    error: float | str = "sigma_as"
    columns: tuple[str, ...] = ()
    where: str | None = None
    site: str = ""
    weights: tuple[float, float] | None = field(default=None)
    grid: Grid | None = None  # df has zone and cell of this grid already, as a zone cache gives it

    def bound(self) -> Participant:
        """With (least, largest) weight filled in: free for a constant error, one aggregate else."""
        if self.weights:
            return self
        if not isinstance(self.error, str):
            if self.error <= 0:
                raise ValueError(f"{self.alias}: an error must be positive")
            w = (PER_RADIAN / self.error) ** 2
            return replace(self, weights=(w, w))
        e = F.expr(self.error).cast("double")
        low, high = self.rows().filter(e > 0).agg(F.min(e), F.max(e)).first()
        return replace(self, weights=((PER_RADIAN / high) ** 2, (PER_RADIAN / low) ** 2) if low else (1.0, 1.0))

    def rows(self) -> DataFrame:
        return self.df.filter(self.where) if self.where else self.df


def states(p: Participant, region: Region | None = None, grown: float = 0.0) -> DataFrame:
    """One-member states of a participant; rows without a position or a positive error are left out."""
    df = p.rows()
    columns = list(dict.fromkeys([*p.key, *p.columns]))
    if len(p.position) == 2 and region is not None:  # bounds first: they reach the file's statistics
        df = region.grown_bounds(grown).filter(df, *p.position)
    e = (F.expr(p.error) if isinstance(p.error, str) else F.lit(float(p.error))).cast("double")
    df = sky_columns(df.withColumn("__e", e).filter((F.col("__e") > 0) & ~F.isnan("__e")), p.position)
    if region is not None:
        df = df.filter(region.grow(grown).contains("__x", "__y", "__z"))
    df = sealed(df, {"__wt": weight("__e")})
    new = {f"__a{c}": F.col("__wt") * F.col(f"__{c}") for c in "xyz"} | {"__W": F.col("__wt"), "__D": F.lit(0.0), "__S": ln_term("__wt")}
    member = [F.lit(True).alias(f"{p.alias}__"), *[F.col(c).alias(f"{p.alias}__{c}") for c in columns]]
    return sealed(df, new).select(*member, *STATE, *(["zone", "cell"] if p.grid else []))


def _size() -> Column:
    return F.greatest(length("__ax", "__ay", "__az"), F.lit(1e-300))


def positioned(df: DataFrame) -> DataFrame:
    """State rows with their best position: length __n, unit vector and angles."""
    df = sealed(df, {"__n": _size()})
    df = sealed(df, {f"__{c}": F.col(f"__a{c}") / F.col("__n") for c in "xyz"})
    return sealed(df, {"__ra": right_ascension("__x", "__y"), "__dec": declination("__x", "__y", "__z")})


def _members(df: DataFrame) -> list[str]:
    """Member columns stay flat, as alias__column, until the end: alias__ alone says whether the member is there."""
    return [c for c in df.columns if not c.startswith("__") and "__" in c]


def _aliases(df: DataFrame) -> list[str]:
    return [c[:-2] for c in _members(df) if c.endswith("__")]


@dataclass(frozen=True)
class Side:
    """A state table with the weights of its members; rows: an estimate, if there is one; grid: that of its columns zone and cell, if it has them.

    made: of two catalogs, their sides and the weights that were to come when they were paired.
    """

    df: DataFrame
    weights: tuple[tuple[float, float], ...]
    rows: float | None = None
    site: str = ""
    grid: Grid | None = None
    made: tuple[Side, Side, list[tuple[float, bool]]] | None = None


#: Counts of a step: is given a table and a name, gives the table back (Trace.seen).
Seen = Callable[[DataFrame, str], DataFrame]


class Trace:
    """Rows by step of a match, counted while it runs: candidates of equal cells, pairs kept, null-extended rows.

    names: the steps to count, all by default. Counting candidates makes a whole row of each of them, before the chord is looked at.
    """

    def __init__(self, names: tuple[str, ...] | None = None) -> None:
        self.names = names
        self.steps: list[tuple[str, Observation]] = []

    def seen(self, df: DataFrame, name: str) -> DataFrame:
        if self.names is not None and name not in self.names:
            return df
        watch = Observation(f"{len(self.steps)}-{name}")
        self.steps.append((name, watch))
        return df.observe(watch, F.count(F.lit(1)).alias("rows"))

    def counts(self) -> list[tuple[str, int]]:
        """(step, rows) in the order of the plan, after the match has run."""
        return [(name, int(watch.get.get("rows", 0))) for name, watch in self.steps]


def _right(part: Side) -> DataFrame:
    """A side as the right one of a pair table."""
    return positioned(part.df).withColumnsRenamed({c: c.replace("__", "__r") for c in (*STATE, "__n")})


def _merged(left: Callable[[str], Column] = F.col) -> tuple[dict[str, Column], Column]:
    """State columns of two merged sides, and the length of their sum. left: how columns of the left side are written."""
    own = {c: left(c) for c in (*STATE, "__n", "__x", "__y", "__z")}
    sums = {f"__a{c}": own[f"__a{c}"] + F.col(f"__ra{c}") for c in "xyz"}
    total = F.sqrt(sum((v * v for v in sums.values()), F.lit(0.0)))
    c2 = chord2([own[f"__{c}"] for c in "xyz"], ("__rx", "__ry", "__rz"))
    deficit = merged_deficit(own["__D"], own["__n"], "__rD", "__rn", c2, total)
    return sums | {"__W": own["__W"] + F.col("__rW"), "__D": deficit, "__S": own["__S"] + F.col("__rS")}, total


def _least(left: Side, right: Side) -> float:
    """The least cell in radii: small where both sides' rows were measured."""
    return LEAST_OVER_RADIUS if left.rows is None or right.rows is None else CROWDED_OVER_RADIUS


def _shuffled(*sides: Side) -> bool:
    """Whether the smaller of the sides is known to be too large for a broadcast."""
    return all(s.rows is not None and s.rows > BROADCAST_ROWS for s in sides)


def combine(left: Side, right: Side, rest: list[tuple[float, bool]], ln_limit: float, grid: Grid | None = None, prune: str = "bound", density: float | None = None, seen: Seen | None = None) -> Side:
    """Merged states of two sides that can still reach the limit with `rest`, the largest weights to come."""
    if grid is None and density and prune == "bound" and seen is None and (out := combine_carried(left, right, rest, ln_limit, density)):
        return out
    least = _least(left, right)
    coming = [w for w, _ in rest]
    chord = search_chord(list(left.weights), list(right.weights), coming, ln_limit)
    small = "left" if left.rows is None or right.rows is None or left.rows <= right.rows else "right"
    levels, by = None, None
    wide = {name: s.weights[0][1] / s.weights[0][0] > LEVEL_STEP**2 * (1 + 1e-9) for name, s in (("right", right), ("left", left)) if len(s.weights) == 1}
    zoned = right.grid is not None and not wide.get("right") and not wide.get("left")
    if grid is None and any(wide.values()):  # very uneven errors: classes of them, each with its radius
        small = next(name for name in ("right", "left") if wide.get(name))
        least = CROWDED_LEVELS_OVER_RADIUS if least == CROWDED_OVER_RADIUS else least
        if small == "right":
            levels = weight_levels(*right.weights[0], lambda a, b: search_chord(list(left.weights), [(a, b)], coming, ln_limit), density, least)
        else:
            levels = weight_levels(*left.weights[0], lambda a, b: search_chord([(a, b)], list(right.weights), coming, ln_limit), density, least)
        by = F.col("__rW" if small == "right" else "__W")
    use = right.grid if zoned else grid or choose_grid(angle_of(chord), density, least=least)
    pairs = pair_table(positioned(left.df), _right(right), chord, use, "left" if zoned else small, levels=levels, level_weight=by, zoned=zoned, seen=seen, shuffled=_shuffled(left, right))
    carried = ["__near"] if "__near" in pairs.columns else []
    merged = sealed(pairs, _merged()[0]).select(*_members(left.df), *_members(right.df), *STATE, *carried)
    bound = ln_bound("__D", "__W", "__S", [] if prune == "pairwise" else rest)
    merged = merged.filter(bound >= ln_limit - 1e-9) if prune != "none" else merged
    rows = None
    if density and left.rows is not None and right.rows is not None:  # at most: all that lies within the radius, at the highest density
        rows = max(left.rows, right.rows) * (1 + density * math.pi * angle_of(chord) ** 2)
    single = len(left.weights) == len(right.weights) == 1
    return Side(seen(merged, "kept") if seen else merged, left.weights + right.weights, rows, left.site, made=(left, right, rest) if single else None)


def combine_carried(left: Side, right: Side, rest: list[tuple[float, bool]], ln_limit: float, density: float) -> Side | None:
    """combine() of a large table of pairs with a smaller side, without a shuffle of the pairs: they are paired again, and the sharper
    member carries along the states of the other side that can reach the limit with it, found by a zone join of its own before.

    Nothing is lost: members of an acceptable tuple merge in any order, so the sharper member reaches the limit with the other side
    and the largest weights of what is missing. None where the rows weren't measured, or where a detection has many such states.
    """
    pairs, other = (right, left) if (right.rows or 0.0) >= (left.rows or 0.0) else (left, right)
    if pairs.made is None or pairs.rows is None or other.rows is None or (len(other.weights) > 1 and other.made is None):
        return None
    *sides, then = pairs.made
    k = 0 if sides[0].weights[0][0] >= sides[1].weights[0][0] else 1
    sharp, most = sides[k], sides[1 - k].weights[0][1]
    coming = [w for w, _ in rest]
    chord = search_chord(list(sharp.weights), list(other.weights), [*coming, most], ln_limit)
    each = other.rows / max(s.rows or 1.0 for s in other.made[:2]) if other.made else 1.0
    if any("map<" in kind or kind == "variant" for _, kind in sharp.df.dtypes) or sharp.grid or density * math.pi * angle_of(chord) ** 2 * max(1.0, each) > MOST_NEAR:
        return None
    new, _ = _merged()
    held = ln_bound(new["__D"], new["__W"], new["__S"], [*rest, (most, True)]) >= ln_limit - 1e-9
    small = "left" if sharp.rows is None or sharp.rows <= other.rows else "right"
    near = pair_table(positioned(sharp.df), _right(other), chord, choose_grid(angle_of(chord), density, least=_least(sharp, other)), small, held, shuffled=_shuffled(sharp, other))
    values = [c for c in _members(other.df) if not c.endswith("__")]
    state = F.struct(*values, *[F.col(c.replace("__", "__r")).alias(c) for c in STATE])
    # By all columns: equal rows of a catalog become one that carries each state as often.
    sides[k] = replace(sharp, df=near.groupBy(*sharp.df.columns).agg(F.collect_list(state).alias("__near")))
    df = sealed(combine(*sides, then, ln_limit, density=density).df, {"__n": _size()})
    df = sealed(df, {f"__{c}": F.col(f"__a{c}") / F.col("__n") for c in "xyz"})
    df = df.select(*[c for c in df.columns if c != "__near"], F.explode("__near").alias("__one"))
    one = {c: F.col("__one")[c] for c in (*values, *STATE)}
    flags = [F.lit(True).alias(c) for c in _members(other.df) if c.endswith("__")]
    df = df.select(*[c for c in df.columns if c != "__one"], *flags, *[one[c].alias(c) for c in values], *[one[c].alias(c.replace("__", "__r")) for c in STATE])
    df = sealed(df, {"__rn": F.greatest(length("__rax", "__ray", "__raz"), F.lit(1e-300))})
    df = sealed(df, {f"__r{c}": F.col(f"__ra{c}") / F.col("__rn") for c in "xyz"})
    apart = search_chord(list(left.weights), list(right.weights), coming, ln_limit)
    df = df.filter(chord2(("__x", "__y", "__z"), ("__rx", "__ry", "__rz")) <= apart * apart)
    merged = sealed(df, _merged()[0]).select(*_members(left.df), *_members(right.df), *STATE)
    rows = max(left.rows, right.rows) * (1 + density * math.pi * angle_of(apart) ** 2)
    return Side(merged.filter(ln_bound("__D", "__W", "__S", rest) >= ln_limit - 1e-9), left.weights + right.weights, rows, left.site)


def below(df: DataFrame, ln_limit: float) -> DataFrame:
    """State rows whose members' keys reach the limit in no row: what a limit on every step would lose here."""
    keys = [c for c in _members(df) if not c.endswith("__")]
    best = F.max("__lnb").over(Window.partitionBy(*keys))
    return with_ln_b(df).withColumn("__best", best).filter(F.col("__best") < ln_limit).drop("__lnb", "__best")


def with_ln_b(df: DataFrame) -> DataFrame:
    return sealed(df, {"__lnb": ln_bayes("__D", length("__ax", "__ay", "__az"), "__S")})


def allow(prefix: Side, part: Side, rest: list[tuple[float, bool]], ln_limit: float, grid: Grid | None = None, density: float | None = None) -> Side:
    """The prefix extended where the extension (with what may follow) reaches the limit, else once as it was: one outer zone join.

    Detections are copied along cell borders, so that a tuple meets all of them in its own cell.
    """
    chord = search_chord(list(prefix.weights), list(part.weights), [w for w, _ in rest], ln_limit)
    new, _ = _merged()
    held = ln_bound(new["__D"], new["__W"], new["__S"], rest) >= ln_limit - 1e-9
    use = grid or choose_grid(angle_of(chord), density, least=_least(prefix, part))
    pairs = pair_table(positioned(prefix.df), _right(part), chord, use, "right", held, "left", shuffled=_shuffled(prefix, part))
    members = _members(part.df)
    found = F.col(next(c for c in members if c.endswith("__"))).isNotNull()
    pairs = sealed(pairs, {c: F.when(found, v).otherwise(F.col(c)) for c, v in new.items()})
    flags = {c: F.coalesce(c, F.lit(False)) for c in members if c.endswith("__")}
    out = pairs.withColumns(flags).select(*_members(prefix.df), *members, *STATE).filter(ln_bound("__D", "__W", "__S", rest) >= ln_limit - 1e-9)
    return Side(out, prefix.weights + part.weights, prefix.rows)


def forbid(prefix: Side, part: Side, ln_limit: float, grid: Grid | None = None, density: float | None = None, flag: bool = False) -> DataFrame:
    """The prefix without tuples that some detection of part would extend to the limit: one anti zone join. flag: all, with column blocked."""
    chord = search_chord(list(prefix.weights), list(part.weights), [], ln_limit)
    use = grid or choose_grid(angle_of(chord), density, least=_least(prefix, part))
    columns = prefix.df.columns
    if not flag:
        new, total = _merged()
        held = ln_bayes(new["__D"], total, new["__S"]) >= ln_limit
        return pair_table(positioned(prefix.df), _right(part), chord, use, "right", held, "left_anti", shuffled=_shuffled(prefix, part)).select(*columns)
    # Names of the two sides must differ at every level below, or the inner side's are taken.
    own = {c: f"__o{c.removeprefix('__')}" for c in (*STATE, "__n", "__x", "__y", "__z", "__ra", "__dec", "zone", "cell")}
    outer = lambda c: F.col(own[c]).outer()
    new, total = _merged(outer)
    held = ln_bayes(new["__D"], total, new["__S"]) >= ln_limit
    left = zone_table(positioned(prefix.df), use).withColumnsRenamed(own)
    right = reached(positioned(part.df), use, angle_of(chord)).withColumnsRenamed({c: f"__r{c.removeprefix('__')}" for c in (*STATE, "__n", "__x", "__y", "__z", "zone", "cell")})
    near = chord2([outer(f"__{c}") for c in "xyz"], ("__rx", "__ry", "__rz")) <= chord * chord
    hit = right.where((outer("zone") == F.col("__rzone")) & (outer("cell") == F.col("__rcell")) & near & held).exists()
    return left.select(*[F.col(own.get(c, c)).alias(c) for c in columns], hit.alias("blocked"))


def finish(df: DataFrame, alias: str, ln_limit: float | None) -> DataFrame:
    """Members as structs (null if absent), and the virtual relation: position, error, ln_bf, bf; other columns stay."""
    aliases, flat = _aliases(df), _members(df)
    # Angles aren't sealed: what isn't asked for is not worked out.
    df = sealed(df if "__lnb" in df.columns else with_ln_b(df), {"__n": _size()})
    df = df.withColumns({f"__{c}": F.col(f"__a{c}") / F.col("__n") for c in "xyz"})
    df = df.withColumns({"__ra": right_ascension("__x", "__y"), "__dec": declination("__x", "__y", "__z")})
    ln_b = F.col("__lnb")
    if ln_limit is not None:
        df = df.filter(ln_b >= ln_limit)
    virtual = F.struct(
        F.col("__ra").alias("ra"), F.col("__dec").alias("dec"), F.col("__x").alias("cx"), F.col("__y").alias("cy"), F.col("__z").alias("cz"),
        (PER_RADIAN / F.sqrt("__n")).alias("sigma_as"), ln_b.alias("ln_bf"), F.exp(ln_b).alias("bf"),
    )
    own = {a: [c for c in flat if c.startswith(f"{a}__") and c != f"{a}__"] for a in aliases}
    structs = [F.when(F.col(f"{a}__"), F.struct(*[F.col(c).alias(c[len(a) + 2 :]) for c in columns])).alias(a) for a, columns in own.items()]
    return df.select(*structs, virtual.alias(alias), *[c for c in df.columns if c == "blocked"])


def order_participants(parts: list[Participant], rows: dict[str, float] | None = None) -> list[Participant]:
    """Required catalogs from few rows to many, then optional, then excluded ones."""
    rank = {REQUIRE: 0, ALLOW: 1, FORBID: 2}
    return sorted(parts, key=lambda p: (rank[p.mode], (rows or {}).get(p.alias, 0.0)))


def reach(p: Participant, q: Participant, need: list[Participant], taking: list[Participant], ln_limit: float) -> float:
    """Degrees that no two members of an accepted tuple are farther apart, whether optional ones take part or not."""
    others = [[o.weights[1] for o in own if o.alias not in (p.alias, q.alias)] for own in (need, taking)]
    return angle_of(max(search_chord([p.weights], [q.weights], rest, ln_limit) for rest in others))


def match_all(
    parts: list[Participant],
    limit: float,
    alias: str = "x",
    plan: str = "sequential",
    order: str = "listed",
    rows: dict[str, float] | None = None,
    region: Region | None = None,
    region_on: str = "owner",
    rescue: bool = True,
    payload: str = "carry",
    grid: Grid | None = None,
    prune: str = "bound",
    extra_evidence: Column | None = None,
    prior_area: float | None = None,
    dropouts: bool = False,
    density: float | None = None,
    trace: Trace | None = None,
    rate: float = 1e-3,
) -> DataFrame:
    """All tuples whose Bayes factor reaches limit.

    plan: sequential, cascading (pairs of catalogs, then pairs of matches) or colocated (catalogs of a site first). order: listed,
    reversed or estimated (rows by alias, and where they aren't given, from samples of the catalogs at this rate with all their own
    conditions, and the density of their fields with them). The region tests the first required catalog listed (owner), the combined position, or comes
    last (post); other catalogs are cut to the region grown by the reach. payload rejoin fetches columns by key at the end.
    prior_area: the isotropic prior is over that many steradians instead of the whole sphere. density: rows per square degree of the
    densest field, for the cells. trace: counts rows by step. prune: bound, none, pairwise (every step alone must reach the limit), or
    lost, of three required catalogs: only the tuples that pairwise would lose, each from its weak pair without a look at the others.
    """
    if limit is None or limit <= 0:
        raise ValueError("a positive limit is required")
    if len(parts) < 2 or not any(p.mode == REQUIRE for p in parts):
        raise ValueError("a match needs two catalogs, one of them required")
    if len({p.alias for p in parts}) != len(parts):
        raise ValueError("aliases must differ")
    if prune == "lost" and (plan != "sequential" or len(parts) != 3 or any(p.mode != REQUIRE or p.columns for p in parts)):
        raise ValueError("lost tuples are of three required catalogs in sequence, by their keys")
    ln_limit = math.log(limit)
    full = {p.alias: p for p in parts}
    if payload == "rejoin":
        parts = [replace(p, columns=()) for p in parts]
    parts = [p.bound() for p in parts]
    owner = next(p.alias for p in parts if p.mode == REQUIRE)  # the region's
    if order == "estimated" and rows is None:
        from ..plans.planner import profiles

        found = profiles(parts, rate, region)
        rows = {a: f.rows for a, f in found.items()}
        density = density or max((f.densest for f in found.values()), default=0.0) or None
    listed = order_participants(parts, rows if order == "estimated" else None)
    if order == "reversed":
        listed = order_participants(list(reversed(parts)))
    need, may, without = ([p for p in listed if p.mode == m] for m in (REQUIRE, ALLOW, FORBID))
    if prior_area is not None and may:
        raise ValueError("another prior area needs a fixed number of members: no optional catalog")
    if prior_area is not None:  # every detection but one gains the same factor
        ln_limit -= (len(need) - 1) * math.log(4 * math.pi / prior_area)
    taking = need + may
    if density is None and grid is None and rows is None and region is None and all(len(p.position) == 2 and p.grid is None for p in parts):
        # Wide cells of a crowded field hold many more candidates than pairs: look at the whole catalogs first.
        if OVER_RADIUS * max(reach(p, q, need, taking, ln_limit) for p in need for q in parts if q.alias != p.alias) > WIDE_CELL:
            from ..plans.planner import profiles

            found = profiles(parts, 1.0)
            rows = {a: f.rows for a, f in found.items()}
            density = max(f.densest for f in found.values()) or None

    def apart(p: Participant, q: Participant) -> float:
        return reach(p, q, need, taking, ln_limit)

    def grown(p: Participant) -> float:
        """How far outside the region a detection can matter."""
        if region_on == "owner":
            return 0.0 if p.alias == owner else apart(p, next(q for q in need if q.alias == owner))
        return max((apart(p, q) for q in taking if q.alias != p.alias), default=0.0)

    def side(p: Participant) -> Side:
        cut = region is not None and region_on != "post" and p.mode != FORBID
        df = states(p, region, grown(p)) if cut else states(p)
        return Side(df, (p.weights,), (rows or {}).get(p.alias), p.site, p.grid)

    may_rest = [(p.weights[1], False) for p in may] if rescue else []

    seen = trace.seen if trace else None

    def rest_of(done: set[str]) -> list[tuple[float, bool]]:
        return [(p.weights[1], True) for p in need if p.alias not in done] + may_rest

    def names(s: Side) -> set[str]:
        return set(_aliases(s.df))

    if plan == "sequential":
        now = side(need[0])
        for p in need[1:]:
            part = side(p)
            now = combine(now, part, rest_of(names(now) | {p.alias}), ln_limit, grid, prune, density, seen)
            now = replace(now, df=below(now.df, ln_limit)) if prune == "lost" and p is need[1] else now
    else:
        groups = [[side(p)] for p in need]
        if plan == "colocated":
            sites: dict[str, list[Side]] = {}
            for p, g in zip(need, groups, strict=True):
                sites.setdefault(p.site, []).extend(g)
            heads = []
            for own in sites.values():
                now = own[0]
                for s in own[1:]:
                    now = combine(now, s, rest_of(names(now) | names(s)), ln_limit, grid, prune, density, seen)
                heads.append(now)
        elif plan == "cascading":
            heads = [g[0] for g in groups]
        else:
            raise ValueError(f"unknown plan {plan}")
        while len(heads) > 1:
            nxt = [combine(a, b, rest_of(names(a) | names(b)), ln_limit, grid, prune, density, seen) for a, b in zip(heads[::2], heads[1::2], strict=False)]
            heads = nxt + ([heads[-1]] if len(heads) % 2 else [])
        now = heads[0]
    if not rescue:
        now = replace(now, df=with_ln_b(now.df).filter(F.col("__lnb") >= ln_limit).drop("__lnb"))
    for k, p in enumerate(may):
        now = allow(now, side(p), [(q.weights[1], False) for q in may[k + 1 :]], ln_limit, grid, density)
        now = replace(now, df=seen(now.df, "kept")) if seen else now
    df = with_ln_b(now.df).filter(F.col("__lnb") >= ln_limit)
    for k, p in enumerate(without):
        df = df.withColumnRenamed("blocked", "__blocked") if dropouts and k else df
        df = forbid(Side(df, now.weights, now.rows), side(p), ln_limit, grid, density, dropouts)
        df = df.withColumn("blocked", F.col("blocked") | F.col("__blocked")).drop("__blocked") if dropouts and k else df
    flag = "blocked" in df.columns
    out = finish(df, alias, None)
    if region is not None and region_on == "combined":
        out = out.filter(region.contains(f"{alias}.cx", f"{alias}.cy", f"{alias}.cz"))
    if region is not None and region_on == "post":
        pos = full[owner].position
        v = sky_to_xyz(*[F.col(owner)[c] for c in pos]) if len(pos) == 2 else [F.col(owner)[c] for c in pos]
        out = out.filter(region.contains(*v))
    if payload == "rejoin":
        for a, p in full.items():
            if p.mode != FORBID:
                out = rejoin(out, a, p)
    if extra_evidence is not None:
        total = F.col(alias)["ln_bf"] + extra_evidence
        out = out.withColumn(alias, F.col(alias).withField("ln_total", total)).filter(F.col(alias)["ln_total"] >= ln_limit)
    return out.select(*[a for a in full if a in out.columns], alias, *(["blocked"] if flag else []))


def rejoin(match: DataFrame, alias: str, p: Participant) -> DataFrame:
    """The lazy join: a member's columns fetched by its key, for the accepted rows alone."""
    columns = list(dict.fromkeys([*p.key, *p.columns]))
    side = p.rows().select(F.struct(*columns).alias("__full"), *[F.col(k).alias(f"__k{i}") for i, k in enumerate(p.key)])
    left = match.withColumns({f"__j{i}": F.col(alias)[k] for i, k in enumerate(p.key)})
    on = [F.col(f"__j{i}") == F.col(f"__k{i}") for i in range(len(p.key))]
    keep = [c for c in match.columns if c != alias]
    return left.join(side, on, "left").select(*keep, F.col("__full").alias(alias))


def self_match(p: Participant, limit: float, symmetric: bool = False, grid: Grid | None = None) -> DataFrame:
    """Pairs of detections of one catalog: a and b with the smaller key first (or both ways)."""
    p = p.bound()
    ln_limit = math.log(limit)
    a, b = (Side(states(replace(p, alias=n)), (p.weights,)) for n in ("a", "b"))
    pairs = combine(a, b, [], ln_limit, grid).df
    first, second = (F.struct(*[F.col(f"{n}__{k}").alias(k) for k in p.key]) for n in ("a", "b"))
    return finish(pairs.filter(first != second if symmetric else first < second), "x", ln_limit)


def objects_of(pairs: DataFrame, nodes: DataFrame, rounds: int = 50) -> DataFrame:
    """(key, object) by the least key reachable over pairs (a, b); nodes (key) may be alone. Iterated with checkpoints."""
    both = pairs.select("a", "b").unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct()
    now = nodes.select("key", F.col("key").alias("object"))
    for _ in range(rounds):
        near = both.join(now, both.b == now.key).groupBy("a").agg(F.min("object").alias("m"))
        low = now.join(near, now.key == near.a, "left").select("key", F.least("object", F.coalesce("m", "object")).alias("object"), F.col("object").alias("before"))
        jump = now.select(F.col("key").alias("k"), F.col("object").alias("o"))
        now = checkpointed(low.join(jump, low.object == jump.k, "left").select("key", F.least("object", F.coalesce("o", "object")).alias("object"), "before"))
        if now.filter("object <> before").isEmpty():
            return now.select("key", "object")
        now = now.drop("before")
    raise RuntimeError("grouping did not settle")


def resolve(match: DataFrame, policy: str, anchor: list[Column], other: list[Column], ln_b: Column) -> DataFrame:
    """all tuples, the best of each anchor, or mutual best ones; ties go to the smaller keys."""
    if policy == "all":
        return match
    out = match.withColumn("__r1", F.row_number().over(Window.partitionBy(*anchor).orderBy(ln_b.desc(), *other)))
    if policy == "best":
        return out.filter("__r1 = 1").drop("__r1")
    if policy != "mutual":
        raise ValueError(f"unknown policy {policy}")
    out = out.withColumn("__r2", F.row_number().over(Window.partitionBy(*other).orderBy(ln_b.desc(), *anchor)))
    return out.filter("__r1 = 1 AND __r2 = 1").drop("__r1", "__r2")


def classify_dropouts(match: DataFrame, alias: str, footprint: Region | None = None, mask: Region | None = None, limit_mag: float | None = None) -> DataFrame:
    """verdict of each survivor: true_dropout, not_observed, masked (or blocked); upper_limit where a limit is known."""
    x = (F.col(alias)["cx"], F.col(alias)["cy"], F.col(alias)["cz"])
    seen = footprint.contains(*x) if footprint is not None else F.lit(True)
    hidden = mask.contains(*x) if mask is not None else F.lit(False)
    blocked_ = F.col("blocked") if "blocked" in match.columns else F.lit(False)
    verdict = F.when(blocked_, "blocked").when(~seen, "not_observed").when(hidden, "masked").otherwise("true_dropout")
    return match.withColumn("verdict", verdict).withColumn("upper_limit", F.when(verdict == "true_dropout", F.lit(limit_mag).cast("double")))
