"""Baselines that the zone match is compared with."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.evidence import ln_bayes_flat
from ..functions.plan import sealed
from ..functions.sphere import PER_RADIAN, chord2, chord_of, separation_as
from .zones import Grid, choose_grid, pair_table, sky_columns


def _two(a: DataFrame, b: DataFrame, position: tuple[str, ...]) -> tuple[DataFrame, DataFrame]:
    """Both sides with positions, a's columns prefixed a_ and b's b_."""
    out = []
    for name, df in (("a_", a), ("b_", b)):
        s = sky_columns(df, position)
        out.append(s.withColumnsRenamed({c: name + c for c in s.columns if not c.startswith("__")}))
    return out[0], out[1]


def match_within(a: DataFrame, b: DataFrame, radius_as: float, position: tuple[str, ...] = ("ra", "dec"), grid: Grid | None = None) -> DataFrame:
    """Pairs closer than a fixed radius, with sep_as: no errors, no evidence."""
    x, y = _two(a, b, position)
    pairs = pair_table(x, y, chord_of(radius_as / 3600), grid or choose_grid(radius_as / 3600))
    out = sealed(pairs, {"sep_as": separation_as("__c2")}).filter(F.col("sep_as") <= radius_as)
    return out.select(*[c for c in out.columns if not c.startswith("__")])


def nearest_match(a: DataFrame, b: DataFrame, radius_as: float, **how) -> DataFrame:
    """Each row of a with its nearest row of b within a radius; ties go to the smaller key."""
    w = Window.partitionBy("a_key").orderBy("sep_as", "b_key")
    return match_within(a, b, radius_as, **how).withColumn("r", F.row_number().over(w)).filter("r = 1").drop("r")


def _widest_chord(variance: float, limit: float) -> float:
    """A chord that no pair of at most this variance (square radians, of both errors together) exceeds if it reaches the limit."""
    # 2 v (ln(2 / limit) - ln v) rises up to ln v = ln(2 / limit) - 1: sharper pairs may reach farther than very uncertain ones.
    v = min(max(variance, 1e-300), 2 / limit / math.e)
    return min(2.0, math.sqrt(2 * v * (math.log(2 / limit) - math.log(v))) * (1 + 1e-9) + 1e-12)


def brute_pairs(a: DataFrame, b: DataFrame, limit: float, position: tuple[str, ...] = ("ra", "dec")) -> DataFrame:
    """All pairs of neighbouring bands of height, then the exact filter: quadratic within a band, no zones or cells, as a yardstick.

    The bands are as high as the widest chord that the largest errors allow, so no pair above the limit lies farther apart than one band.
    """
    x, y = _two(a, b, position)
    y = y.withColumnsRenamed({f"__{c}": f"__r{c}" for c in ("x", "y", "z", "ra", "dec")})
    worst = [s.agg(F.max(c)).first()[0] for s, c in ((x, "a_sigma_as"), (y, "b_sigma_as"))]
    worst = [float(v) for v in worst if v is not None]
    height = _widest_chord(sum((v / PER_RADIAN) ** 2 for v in worst), limit)
    band = lambda z: F.floor((F.col(z) + 1) / height).cast("long")
    x = x.withColumn("__band", F.explode(F.array(*[band("__z") + k for k in (-1, 0, 1)])))
    c2 = chord2(("__x", "__y", "__z"), ("__rx", "__ry", "__rz"))
    pairs = x.join(y.withColumn("__rband", band("__rz")), (F.col("__band") == F.col("__rband")) & (c2 <= height * height))
    both = sealed(pairs, {"__c2": chord2(("__x", "__y", "__z"), ("__rx", "__ry", "__rz"))})
    w = [206264.80624709636**2 / (F.col(s) * F.col(s)) for s in ("a_sigma_as", "b_sigma_as")]
    out = sealed(both, {"ln_bf": ln_bayes_flat("__c2", *w)}).filter(F.col("ln_bf") >= math.log(limit))
    return out.select(*[c for c in out.columns if not c.startswith("__")])
