"""Zone join: candidate pairs of two catalogs by an equality on (zone, cell), exact for any radius, poles and wrap included."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.plan import sealed
from ..functions.sphere import angle_of, cell_id, cells_of, chord2, ra_window, right_ascension, declination, zone_id

#: Least cell size in arc seconds, rows of a cell aimed at, cell size as a multiple of the radius (border replication 1.44), and its least.
LEAST_CELL, POPULATION, OVER_RADIUS, LEAST_OVER_RADIUS = 30.0, 16.0, 10.0, 4.0
#: That least where the density was measured and cells are crowded: nine copies of the smaller side, three candidates a pair instead of eleven.
CROWDED_OVER_RADIUS = 1.0
#: And where errors fall into levels: four copies, and levels of a factor of 2 where cells of POPULATION rows are too small for them.
CROWDED_LEVELS_OVER_RADIUS, CROWDED_LEVEL_STEP = 2.0, 2.0
#: Errors of a level differ by this factor at most; levels of a catalog.
LEVEL_STEP, MOST_LEVELS = 8.0, 8


@dataclass(frozen=True)
class Grid:
    """Zones of equal height (degrees), cells of about that width; cells=False leaves zones alone."""

    height: float
    cells: bool = True


def choose_grid(radius_deg: float, density: float | None = None, cells: bool = True, least: float = LEAST_OVER_RADIUS) -> Grid:
    """Cell size from the radius, and from the rows per square degree of the densest field if it is known.

    Without a density, cells are OVER_RADIUS radii wide. With one they aim at POPULATION rows, so that a dense field has small cells, of
    `least` radii at least (border replication 2.25 for 4), and a sparse one wide cells.
    """
    height = max(OVER_RADIUS * radius_deg, LEAST_CELL / 3600)
    if density:
        height = max(least * radius_deg, 1.0 / 3600, min(math.sqrt(POPULATION / density), max(1.0, height)))
    return Grid(min(height, 180.0), cells)


@dataclass(frozen=True)
class Level:
    """Rows of one class of errors: their least weight, the chord that their pairs are within, and their grid."""

    least: float
    chord: float
    grid: Grid


def weight_levels(low: float, high: float, chord: Callable[[float, float], float], density: float | None = None, least_cell: float = LEAST_OVER_RADIUS) -> list[Level]:
    """Levels from the sharpest rows to the least certain ones. chord(least, largest weight); one level for errors within LEVEL_STEP.

    A level's radius is that of its own worst row, so a few very uncertain rows don't widen the search of all others.
    """

    def level(least: float, top: float) -> Level:
        # No wider than without a density: a sparse field's wide cells would be all levels' candidates.
        radius = angle_of(reach := chord(least, top))
        return Level(least, reach, Grid(min(choose_grid(radius, density, least=least_cell).height, choose_grid(radius).height)))

    for step in (CROWDED_LEVEL_STEP, LEVEL_STEP) if density and least_cell < LEAST_OVER_RADIUS else (LEVEL_STEP,):
        out, tops, top = [], [], high
        while low < top / step**2 * (1 - 1e-12) and len(out) < MOST_LEVELS - 1:
            least = top / step**2
            # Where sharper rows have cells of the same size, these join their level.
            if step < LEVEL_STEP and out and (wider := level(least, tops[-1])).grid == out[-1].grid:
                out[-1] = wider
            else:
                out.append(level(least, top))
                tops.append(top)
            top = least
        if low >= top / step**2 * (1 - 1e-12):
            break
    return [*out, level(low, top)]


def sky_columns(df: DataFrame, position: tuple[str, ...]) -> DataFrame:
    """df with __x, __y, __z and __ra, __dec from two angles or three vector components; rows without a position go."""
    from ..functions.sphere import normalize, sky_to_xyz

    if len(position) == 2:
        ra, dec = (F.expr(p).cast("double") for p in position)
        ok = ra.isNotNull() & dec.isNotNull() & ~F.isnan(ra) & ~F.isnan(dec) & (F.abs(dec) <= 90.0)
        x, y, z = sky_to_xyz(ra, dec)
        return sealed(df.filter(ok), {"__ra": F.pmod(ra, F.lit(360.0)), "__dec": dec, "__x": x, "__y": y, "__z": z})
    parts = [F.expr(p).cast("double") for p in position]
    squares = parts[0] * parts[0] + parts[1] * parts[1] + parts[2] * parts[2]
    x, y, z = normalize(*parts)
    df = sealed(df.filter(squares.isNotNull() & ~F.isnan(squares) & (squares > 0)), {"__x": x, "__y": y, "__z": z})
    return sealed(df, {"__ra": right_ascension("__x", "__y"), "__dec": declination("__x", "__y", "__z")})


def zone_table(df: DataFrame, grid: Grid) -> DataFrame:
    """df (with __ra, __dec) with its zone and cell: narrow, no shuffle."""
    return _zoned(df, grid.height, grid.cells)


def _zoned(df: DataFrame, height, cells: bool = True) -> DataFrame:
    df = sealed(df, {"zone": zone_id("__dec", height)})
    return df.withColumn("cell", cell_id("__ra", "zone", height) if cells else F.lit(0).cast("long"))


def reached(df: DataFrame, grid: Grid, radius_deg: float) -> DataFrame:
    """df with one row for each (zone, cell) that a circle around the row can reach; each at most once."""
    return _reached(df, grid.height, F.lit(float(radius_deg)), grid.cells)


def _reached(df: DataFrame, height, radius: Column, cells: bool = True) -> DataFrame:
    low = zone_id(F.greatest(F.lit(-90.0), F.col("__dec") - radius), height)
    high = zone_id(F.least(F.lit(90.0), F.col("__dec") + radius), height)
    df = df.withColumn("zone", F.explode(F.sequence(low, high)))
    if not cells:
        return df.withColumn("cell", F.lit(0).cast("long"))
    df = sealed(df, {"__cells": cells_of("zone", height), "__half": ra_window("__dec", radius)})
    n, half = F.col("__cells"), F.col("__half")
    df = sealed(df, {"__first": F.floor((F.col("__ra") - half) * n / 360.0), "__last": F.floor((F.col("__ra") + half) * n / 360.0)})
    first, last = F.col("__first"), F.col("__last")
    every = (last - first + 1 >= n) | (half >= 180.0)
    cells = F.when(every, F.sequence(F.lit(0).cast("long"), n - 1)).otherwise(F.transform(F.sequence(first, F.when(every, first).otherwise(last)), lambda c: F.pmod(c, n)))
    return df.withColumn("cell", F.explode(cells)).drop("__cells", "__half", "__first", "__last")


def pair_table(
    left: DataFrame,
    right: DataFrame,
    chord: float,
    grid: Grid | None = None,
    replicate: str = "left",
    extra: Column | None = None,
    how: str = "inner",
    levels: list[Level] | None = None,
    level_weight: Column | None = None,
    zoned: bool = False,
    seen: Callable[[DataFrame, str], DataFrame] | None = None,
    shuffled: bool = False,
) -> DataFrame:
    """Pairs of rows of left and right within a chord, with __c2. Columns of the two sides must differ but for __x.. and so on.

    The side named by replicate, the smaller one, is copied along cell borders; the other keeps one row each, so that no pair
    comes twice. __x, __y, __z, __ra, __dec of the right side become __rx .... extra: a further condition of a pair.

    how: inner, left (rows of left without a pair stay once, with nulls; __c2 is null then), left_semi or left_anti: right is copied.
    levels: of the copied side, by its column level_weight, each with its own chord and grid; the other side has a row a level.
    zoned: right has zone and cell of this grid already. seen: is given the rows of equal cells under the name candidates.
    shuffled: neither side may be broadcast, whatever the size of its files says: copies and derived columns aren't in it.
    """
    radius = angle_of(chord)
    grid = grid or choose_grid(radius)
    right = right.withColumnsRenamed({f"__{c}": f"__r{c}" for c in ("x", "y", "z", "ra", "dec")})
    if how != "inner" and (replicate == "left" or levels):
        raise ValueError("an outer or anti pair table copies the right side, on one level")
    if levels and len(levels) > 1:
        heights, chords = (F.array(*[F.lit(float(v)) for v in values]) for values in ([v.grid.height for v in levels], [v.chord for v in levels]))
        radii = F.array(*[F.lit(angle_of(v.chord)) for v in levels])
        of = lambda values: F.element_at(values, F.col("__level") + 1)

    def placed(df: DataFrame, copies: bool, prefix: str) -> DataFrame:
        named = df.withColumns({"__ra": F.col(f"{prefix}ra"), "__dec": F.col(f"{prefix}dec")}) if prefix != "__" else df
        if levels and len(levels) > 1:
            number = sum((F.when(level_weight < v.least, 1).otherwise(0) for v in levels[:-1]), F.lit(0)) if copies else F.explode(F.array(*[F.lit(k) for k in range(len(levels))]))
            named = sealed(named.withColumn("__level", number) if not copies else sealed(named, {"__level": number}), {"__h": of(heights), "__radius": of(radii)})
            out = (_reached(named, F.col("__h"), F.col("__radius"), grid.cells) if copies else _zoned(named, F.col("__h"), grid.cells)).drop("__h", "__radius")
        elif zoned and prefix != "__":
            out = named
        else:
            out = reached(named, grid, radius) if copies else zone_table(named, grid)
        return out.drop("__ra", "__dec") if prefix != "__" else out

    a = placed(left, replicate == "left", "__")
    b = placed(right, replicate != "left", "__r").withColumnsRenamed({"zone": "__rzone", "cell": "__rcell", "__level": "__rlevel"})
    b = b.hint("merge") if shuffled else b
    c2 = chord2(("__x", "__y", "__z"), ("__rx", "__ry", "__rz"))
    cell = (F.col("zone") == F.col("__rzone")) & (F.col("cell") == F.col("__rcell"))
    near = c2 <= chord * chord
    if levels and len(levels) > 1:
        cell = cell & (F.col("__level") == F.col("__rlevel"))
        near = c2 <= of(chords) * of(chords)
    near = near & extra if extra is not None else near
    helpers = ("zone", "cell", "__rzone", "__rcell", "__level", "__rlevel")
    if how == "inner":
        out = a.join(b, cell)
        out = seen(out, "candidates") if seen else out
        return out.filter(near).withColumn("__c2", c2).drop(*helpers)
    out = a.join(b, cell & near, how)
    return (out.withColumn("__c2", c2) if how == "left" else out).drop(*helpers)


def by_error(df: DataFrame, sigma: str, classes: int = 3, base: float = 8.0, least: float = 1.0) -> list[tuple[DataFrame, float]]:
    """df split by error into classes, each with its largest error (the last without bound: None as infinity)."""
    edges = [least * base**k for k in range(classes - 1)]
    out, low = [], None
    for e in [*edges, math.inf]:
        part = df if low is None else df.filter(F.col(sigma) > low)
        out.append((part.filter(F.col(sigma) <= e) if math.isfinite(e) else part, e))
        low = e
    return out
