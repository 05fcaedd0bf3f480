"""Regions of the sphere: unions of convexes, a convex an intersection of half-spaces. Boolean operations are exact.

A region is a small immutable value; it compiles to a column expression. Text forms: "circle [J2000] ra dec radius_arcmin",
"box ra1 dec1 ra2 dec2", "polygon ra dec ra dec ...", "convex x y z c ...", and "union(...)", "intersect(...)", "not(...)" of them.
"""

from __future__ import annotations

import json
import math
import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.sphere import EQUINOXES, _c, chord2


def _unit(ra: float, dec: float) -> tuple[float, float, float]:
    a, d = math.radians(ra), math.radians(dec)
    return math.cos(d) * math.cos(a), math.cos(d) * math.sin(a), math.sin(d)


@dataclass(frozen=True)
class Cap:
    """Directions v with v . (x, y, z) >= c, or > c if strict."""

    x: float
    y: float
    z: float
    c: float
    strict: bool = False

    @staticmethod
    def circle(ra: float, dec: float, radius_deg: float) -> Cap:
        return Cap(*_unit(ra, dec), math.cos(math.radians(radius_deg)))

    def holds(self, x: Column, y: Column, z: Column) -> Column:
        dot = x * self.x + y * self.y + z * self.z
        return dot > self.c if self.strict else dot >= self.c

    def has(self, v: tuple[float, float, float]) -> bool:
        dot = v[0] * self.x + v[1] * self.y + v[2] * self.z
        return dot > self.c if self.strict else dot >= self.c

    def complement(self) -> Cap:
        return Cap(-self.x, -self.y, -self.z, -self.c, not self.strict)

    @property
    def radius(self) -> float:
        return math.acos(max(-1.0, min(1.0, self.c)))

    def grow(self, angle: float) -> Cap:
        r = self.radius + angle
        return Cap(self.x, self.y, self.z, -2.0 if r >= math.pi else math.cos(r), False)

    def apart(self, other: Cap) -> bool:
        """Whether the two caps surely share nothing."""
        gap = math.acos(max(-1.0, min(1.0, self.x * other.x + self.y * other.y + self.z * other.z)))
        total = self.radius + other.radius
        return gap > total + 1e-15 or ((self.strict or other.strict) and gap >= total - 1e-15)


@dataclass(frozen=True)
class Convex:
    caps: tuple[Cap, ...]

    def empty(self) -> bool:
        if any(c.c > 1 or (c.strict and c.c >= 1) for c in self.caps):
            return True
        return any(a.apart(b) for i, a in enumerate(self.caps) for b in self.caps[:i])

    def simplified(self) -> Convex:
        """Without whole-sphere and repeated caps."""
        return Convex(tuple(dict.fromkeys(c for c in self.caps if c.c > -1 or (c.strict and c.c >= -1))))


@dataclass(frozen=True)
class Region:
    convexes: tuple[Convex, ...]

    @staticmethod
    def circle(ra: float, dec: float, radius_deg: float) -> Region:
        return Region((Convex((Cap.circle(ra, dec, radius_deg),)),))

    @staticmethod
    def sky() -> Region:
        return Region((Convex(()),))

    @staticmethod
    def nothing() -> Region:
        return Region(())

    @staticmethod
    def box(ra1: float, dec1: float, ra2: float, dec2: float) -> Region:
        """From ra1 eastwards to ra2, below 180 degrees wide, between two declinations."""
        width = (ra2 - ra1) % 360
        if not 0 < width < 180 or dec1 >= dec2:
            raise ValueError("a box is less than 180 degrees wide and not empty")
        sides = [Cap(0, 0, 1, math.sin(math.radians(dec1))), Cap(0, 0, -1, -math.sin(math.radians(dec2)))]
        sides += [Cap(*_unit(ra1 + 90, 0), 0.0), Cap(*_unit(ra2 - 90, 0), 0.0)]
        return Region((Convex(tuple(sides)),))

    @staticmethod
    def polygon(points: list[tuple[float, float]]) -> Region:
        """A convex polygon of at least three corners, in either direction."""
        v = [_unit(*p) for p in points]
        if len(v) < 3:
            raise ValueError("a polygon has three corners at least")
        caps = []
        centre = [sum(p[k] for p in v) for k in range(3)]
        for a, b in zip(v, v[1:] + v[:1], strict=True):
            n = (a[1] * b[2] - a[2] * b[1], a[2] * b[0] - a[0] * b[2], a[0] * b[1] - a[1] * b[0])
            size = math.sqrt(sum(k * k for k in n))
            if not size:
                raise ValueError("two corners of a polygon are the same")
            sign = 1 if sum(p * q for p, q in zip(n, centre, strict=True)) >= 0 else -1
            caps.append(Cap(*(sign * k / size for k in n), 0.0))
        if not all(c.has(p) or abs(c.x * p[0] + c.y * p[1] + c.z * p[2]) < 1e-12 for c in caps for p in v):
            raise ValueError("the polygon is not convex: give a union of convex ones")
        return Region((Convex(tuple(caps)),))

    def __or__(self, other: Region) -> Region:
        return Region(tuple(dict.fromkeys(c for c in self.convexes + other.convexes if not c.empty())))

    def __and__(self, other: Region) -> Region:
        both = (Convex(a.caps + b.caps).simplified() for a in self.convexes for b in other.convexes)
        return Region(tuple(dict.fromkeys(c for c in both if not c.empty())))

    def __invert__(self) -> Region:
        out = Region.sky()
        for convex in self.convexes:
            out = out & Region(tuple(Convex((c.complement(),)) for c in convex.caps))
        return out

    def __sub__(self, other: Region) -> Region:
        return self & ~other

    def contains(self, x, y, z) -> Column:
        x, y, z = _c(x), _c(y), _c(z)
        out = F.lit(False)
        for convex in self.convexes:
            own = F.lit(True)
            for cap in convex.caps:
                own = own & cap.holds(x, y, z)
            out = out | own
        return out

    def has(self, ra: float, dec: float) -> bool:
        v = _unit(ra, dec)
        return any(all(c.has(v) for c in convex.caps) for convex in self.convexes)

    def grow(self, angle_deg: float) -> Region:
        """A region that holds all within an angle of this one."""
        if not angle_deg:
            return self
        return Region(tuple(Convex(tuple(c.grow(math.radians(angle_deg)) for c in convex.caps)).simplified() for convex in self.convexes))

    def bounds(self) -> Bounds:
        """Ranges of declination and right ascension that hold the region, from each convex's smallest cap."""
        if not self.convexes:
            return Bounds(1.0, -1.0, ())
        low, high, ranges = 90.0, -90.0, []
        for convex in self.convexes:
            if not convex.caps:
                return Bounds(-90.0, 90.0, ((0.0, 360.0),))
            cap = min(convex.caps, key=lambda c: c.radius)
            r = math.degrees(cap.radius) + 1e-9
            dec, ra = math.degrees(math.asin(max(-1.0, min(1.0, cap.z)))), math.degrees(math.atan2(cap.y, cap.x)) % 360
            low, high = min(low, max(-90.0, dec - r)), max(high, min(90.0, dec + r))
            if abs(dec) + r >= 90:
                ranges.append((0.0, 360.0))
            else:
                half = math.degrees(math.asin(min(1.0, math.sin(math.radians(r)) / math.cos(math.radians(dec))))) + 1e-9
                a, b = ra - half, ra + half
                ranges += [(0.0, b), (a + 360, 360.0)] if a < 0 else [(a, 360.0), (0.0, b - 360)] if b > 360 else [(a, b)]
        return Bounds(low, high, tuple(ranges))

    def grown_bounds(self, angle_deg: float) -> Bounds:
        return self.grow(angle_deg).bounds()

    def area(self, method: str = "grid", bands: int = 600) -> float:
        """Steradians: exact for one circle, else by counting equal-area cells (relative error about 1 / bands)."""
        if not self.convexes:
            return 0.0
        if len(self.convexes) == 1 and not self.convexes[0].caps:
            return 4 * math.pi
        if method == "exact" or (len(self.convexes) == 1 and len(self.convexes[0].caps) == 1):
            if len(self.convexes) != 1 or len(self.convexes[0].caps) != 1:
                raise ValueError("only a circle has a closed form here")
            return 2 * math.pi * (1 - self.convexes[0].caps[0].c)
        import numpy as np

        b = self.bounds()
        z0, z1 = math.sin(math.radians(b.low)), math.sin(math.radians(b.high))
        z = z0 + (np.arange(bands) + 0.5) / bands * (z1 - z0)
        wide = min(360.0, sum(e - s for s, e in b.ranges)) if len(b.ranges) < 2 else 360.0
        start = b.ranges[0][0] if wide < 360 else 0.0
        a = np.radians(start + (np.arange(2 * bands) + 0.5) / (2 * bands) * wide)
        s = np.sqrt(1 - z * z)[:, None]
        x, y, zz = s * np.cos(a), s * np.sin(a), np.broadcast_to(z[:, None], (bands, 2 * bands))
        inside = np.zeros(x.shape, bool)
        for convex in self.convexes:
            own = np.ones(x.shape, bool)
            for c in convex.caps:
                own &= x * c.x + y * c.y + zz * c.z >= c.c
            inside |= own
        return float(inside.mean() * (z1 - z0) * math.radians(wide))

    def to_json(self) -> str:
        return json.dumps([[[c.x, c.y, c.z, c.c, c.strict] for c in convex.caps] for convex in self.convexes])

    @staticmethod
    def from_json(text: str) -> Region:
        return Region(tuple(Convex(tuple(Cap(*c) for c in caps)) for caps in json.loads(text)))


@dataclass(frozen=True)
class Bounds:
    low: float
    high: float
    ranges: tuple[tuple[float, float], ...]

    def filter(self, df: DataFrame, ra: str, dec: str) -> DataFrame:
        """Plain comparisons with literals, so that they reach file statistics where ra and dec are stored."""
        df = df.filter(F.expr(dec).between(self.low, self.high))
        if any(e - s >= 360 for s, e in self.ranges):
            return df
        out = (F.expr(ra) < 0.0) | (F.expr(ra) >= 360.0)  # not wrapped yet: decided by the exact test
        for s, e in self.ranges:
            out = out | F.expr(ra).between(s, e)
        return df.filter(out)


_TOKEN = re.compile(r"\s*([A-Za-z_]\w*|[-+]?(?:\d+\.?\d*|\.\d+)(?:[eE][-+]?\d+)?|[(),])")


def parse_region(text: str, store: RegionStore | None = None) -> Region:
    """The region of a text form; an unknown equinox, shape or leftover text is an error."""
    tokens, at = [], 0
    while at < len(text.rstrip()):
        m = _TOKEN.match(text, at)
        if not m:
            raise ValueError(f"region: unexpected text at {text[at : at + 12]!r}")
        tokens.append(m[1])
        at = m.end()
    place = 0

    def peek() -> str:
        return tokens[place] if place < len(tokens) else ""

    def take() -> str:
        nonlocal place
        place += 1
        return tokens[place - 1] if place <= len(tokens) else ""

    def numbers() -> list[float]:
        if re.match(r"[A-Za-z]", peek()):
            if peek().upper() not in EQUINOXES:
                raise ValueError(f"region: unknown equinox {peek()}")
            take()
        out = []
        while peek() and re.match(r"[-+.\d]", peek()):
            out.append(float(take()))
        return out

    def arguments() -> list[Region]:
        if take() != "(":
            raise ValueError("region: ( expected")
        out = [one()]
        while peek() == ",":
            take()
            out.append(one())
        if take() != ")":
            raise ValueError("region: ) expected")
        return out

    def one() -> Region:
        kind = take()
        word = kind.lower()
        if word in ("union", "intersect", "not"):
            own = arguments()
            if word == "not":
                if len(own) != 1:
                    raise ValueError("region: not() takes one region")
                return ~own[0]
            out = own[0]
            for r in own[1:]:
                out = out | r if word == "union" else out & r
            return out
        if word == "stored" and store is not None:
            take()
            name = take()
            take()
            return store.load(name)
        n = numbers()
        if word == "circle" and len(n) == 3:
            return Region.circle(n[0], n[1], n[2] / 60)
        if word == "box" and len(n) == 4:
            return Region.box(*n)
        if word == "polygon" and len(n) >= 6 and len(n) % 2 == 0:
            return Region.polygon(list(zip(n[::2], n[1::2], strict=True)))
        if word == "convex" and n and len(n) % 4 == 0:
            return Region((Convex(tuple(Cap(*n[i : i + 4]) for i in range(0, len(n), 4))),))
        raise ValueError(f"region: {kind!r} with {len(n)} numbers is no shape")

    out = one()
    if place != len(tokens):
        raise ValueError(f"region: unexpected {peek()!r}")
    return out


class RegionStore:
    """Named regions in a table."""

    def __init__(self, spark: SparkSession, table: str):
        self.spark, self.table = spark, table

    def save(self, name: str, region: Region) -> None:
        self.spark.createDataFrame([(name, region.to_json())], "name string, caps string").write.mode("append").saveAsTable(self.table)

    def load(self, name: str) -> Region:
        rows = self.spark.table(self.table).filter(F.col("name") == name).limit(1).collect()
        if not rows:
            raise KeyError(f"no stored region {name}")
        return Region.from_json(rows[0].caps)


def region_join(points: DataFrame, caps: DataFrame, max_radius_deg: float | None = None, how: str = "inner") -> DataFrame:
    """points (with __x .. __dec) joined to a table of circles (with the same columns and cap_deg) that hold them.

    A zone join at the widest circle, given or found by one aggregate, then each circle's own radius: no nested loop for many points
    and circles. A wider circle than a given maximum is an error. how: inner (pairs), left_semi or left_anti (points alone).
    """
    from ..functions.sphere import chord_of
    from .zones import choose_grid, pair_table

    widest = caps.agg(F.max("cap_deg")).first()[0] or 0.0
    if max_radius_deg is not None and widest > max_radius_deg:
        raise ValueError(f"a circle of {widest} degrees is wider than {max_radius_deg}")
    radius = max(widest, 1e-9)
    own = (2 * F.sin(F.radians("cap_deg") / 2)) * (2 * F.sin(F.radians("cap_deg") / 2))
    if how == "inner":
        return pair_table(caps, points, chord_of(radius), choose_grid(radius / 4), "left").filter(F.col("__c2") <= own)
    if how not in ("left_semi", "left_anti"):
        raise ValueError(f"unknown join {how}")
    held = chord2(("__x", "__y", "__z"), ("__rx", "__ry", "__rz")) <= own
    return pair_table(points, caps, chord_of(radius), choose_grid(radius / 4), "right", held, how)


def pixels(region: Region, level: int, spark: SparkSession) -> DataFrame:
    """A bitmap of a region: the equal-area cells whose centres it holds. A baseline of limited resolution."""
    n = 1 << level
    grid = spark.range(2 * n * n).withColumn("band", F.floor(F.col("id") / (2 * n))).withColumn("sector", F.col("id") % (2 * n))
    z = (F.col("band") + 0.5) / n * 2 - 1
    a = (F.col("sector") + 0.5) / (2 * n) * 2 * math.pi
    s = F.sqrt(1 - z * z)
    return grid.filter(region.contains(s * F.cos(a), s * F.sin(a), z)).select("band", "sector")


def pixel_of(x, y, z, level: int) -> tuple[Column, Column]:
    n = 1 << level
    band = F.least(F.lit(n - 1), F.floor((_c(z) + 1) / 2 * n)).cast("long")
    turn = F.pmod(F.degrees(F.atan2(_c(y), _c(x))) + 360.0, F.lit(360.0)) / 360.0
    return band, F.least(F.lit(2 * n - 1), F.floor(turn * 2 * n)).cast("long")
