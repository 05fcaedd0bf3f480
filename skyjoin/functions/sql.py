"""The engine's functions for SQL text: scalar functions, an aggregate and table functions, registered in a session."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from .plan import importable
from .sphere import PER_RADIAN

SCALARS = {
    "sky_separation(ra1 DOUBLE, dec1 DOUBLE, ra2 DOUBLE, dec2 DOUBLE)": f"""2 * asin(least(1e0, sqrt(pow(sin(radians(dec2 - dec1) / 2), 2)
      + cos(radians(dec1)) * cos(radians(dec2)) * pow(sin(radians(ra2 - ra1) / 2), 2)))) * {PER_RADIAN!r}""",
    "in_circle(ra DOUBLE, dec DOUBLE, ra0 DOUBLE, dec0 DOUBLE, radius_arcmin DOUBLE)": """sin(radians(dec)) * sin(radians(dec0))
      + cos(radians(dec)) * cos(radians(dec0)) * cos(radians(ra - ra0)) >= cos(radians(radius_arcmin / 60))""",
    "ln_bayes_pair(sep_as DOUBLE, sigma1 DOUBLE, sigma2 DOUBLE)": f"""ln(2 * pow({PER_RADIAN!r}, 2) / (sigma1 * sigma1 + sigma2 * sigma2))
      - sep_as * sep_as / (2 * (sigma1 * sigma1 + sigma2 * sigma2))""",
    "flux_magnitude(flux DOUBLE, zero_point DOUBLE)": "zero_point - 2.5e0 * log10(flux)",
}


def _combined(ra: pd.Series, dec: pd.Series, sigma_as: pd.Series) -> list[float]:
    w, a, d = (PER_RADIAN / sigma_as) ** 2, np.radians(ra), np.radians(dec)
    x, y, z = (float((w * v).sum()) for v in (np.cos(d) * np.cos(a), np.cos(d) * np.sin(a), np.sin(d)))
    n = math.sqrt(x * x + y * y + z * z)
    return [math.degrees(math.atan2(y, x)) % 360.0, math.degrees(math.atan2(z, math.hypot(x, y))), PER_RADIAN / math.sqrt(n), float(len(ra))]


class RegionCells:
    """The equal-area cells of a level whose centres a region (as text) holds."""

    def eval(self, text: str, level: int):
        from skyjoin.operators.regions import parse_region

        region, n = parse_region(text), 1 << level
        low, high = region.bounds().low, region.bounds().high
        for band in range(n):
            z = (band + 0.5) / n * 2 - 1
            dec = math.degrees(math.asin(z))
            if low - 1e-9 <= dec <= high + 1e-9:
                for sector in range(2 * n):
                    if region.has((sector + 0.5) / (2 * n) * 360.0, dec):
                        yield band, sector


class Nearby:
    """The (zone, cell) pairs of a grid of this height in degrees that a circle around a position can reach."""

    def eval(self, ra: float, dec: float, radius_deg: float, height: float):
        for zone in range(math.floor((max(-90.0, dec - radius_deg) + 90) / height), math.floor((min(90.0, dec + radius_deg) + 90) / height) + 1):
            edge = min(90.0, max(abs(zone * height - 90), abs(zone * height - 90 + height)))
            n = max(1, math.floor(360 * math.cos(math.radians(edge)) / height))
            inner = math.cos(math.radians(dec - radius_deg)) * math.cos(math.radians(dec + radius_deg))
            half = math.degrees(math.atan2(math.sin(math.radians(radius_deg)), math.sqrt(inner))) if abs(dec) + radius_deg < 90 and inner > 0 else 180.0
            first, last = math.floor((ra - half) * n / 360), math.floor((ra + half) * n / 360)
            for cell in range(n) if last - first + 1 >= n or half >= 180 else range(first, last + 1):
                yield zone, cell % n


def register(spark: SparkSession) -> SparkSession:
    """Registers all of them as temporary functions: sky_separation, in_circle, ln_bayes_pair, flux_magnitude, combine_positions (an
    aggregate: array of ra, dec, error and number), region_cells(text, level) and nearby(ra, dec, radius, height)."""
    importable(spark)
    for head, body in SCALARS.items():
        kind = "BOOLEAN" if head.startswith("in_") else "DOUBLE"
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURNS {kind} RETURN {body}")

    @F.pandas_udf("array<double>")
    def combine_positions(ra: pd.Series, dec: pd.Series, sigma_as: pd.Series) -> list[float]:
        return _combined(ra, dec, sigma_as)

    spark.udf.register("combine_positions", combine_positions)
    spark.udtf.register("region_cells", F.udtf(RegionCells, returnType="band int, sector int"))
    spark.udtf.register("nearby", F.udtf(Nearby, returnType="zone int, cell bigint"))
    return spark
