"""Spherical geometry as column expressions. Angles are degrees, errors arc seconds, inside formulas radians."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Arc second in radians, and arc seconds of a radian.
ARCSEC = math.pi / 648000
PER_RADIAN = 648000 / math.pi


def _c(value) -> Column:
    return value if isinstance(value, Column) else F.col(value) if isinstance(value, str) else F.lit(float(value))


def sky_to_xyz(ra, dec) -> tuple[Column, Column, Column]:
    a, d = F.radians(_c(ra)), F.radians(_c(dec))
    return F.cos(d) * F.cos(a), F.cos(d) * F.sin(a), F.sin(d)


def right_ascension(x, y) -> Column:
    return F.pmod(F.degrees(F.atan2(_c(y), _c(x))) + 360.0, F.lit(360.0))


def declination(x, y, z) -> Column:
    return F.degrees(F.atan2(_c(z), F.sqrt(_c(x) * _c(x) + _c(y) * _c(y))))


def xyz_to_sky(x, y, z) -> tuple[Column, Column]:
    return right_ascension(x, y), declination(x, y, z)


def length(x, y, z) -> Column:
    return F.sqrt(_c(x) * _c(x) + _c(y) * _c(y) + _c(z) * _c(z))


def normalize(x, y, z) -> tuple[Column, Column, Column]:
    n = length(x, y, z)
    return _c(x) / n, _c(y) / n, _c(z) / n


def chord2(a, b) -> Column:
    """Squared chord between two triples of unit-vector columns."""
    parts = [(_c(p) - _c(q)) * (_c(p) - _c(q)) for p, q in zip(a, b, strict=True)]
    return parts[0] + parts[1] + parts[2]


def separation_as(c2) -> Column:
    """Angle of a squared chord; exact for small angles, unlike the arc cosine of a scalar product."""
    return 2 * F.asin(F.least(F.lit(1.0), F.sqrt(_c(c2)) / 2)) * PER_RADIAN


def position_angle(ra1, dec1, ra2, dec2) -> Column:
    """Direction from the first to the second position, degrees from north through east."""
    a, d1, d2 = F.radians(_c(ra2) - _c(ra1)), F.radians(_c(dec1)), F.radians(_c(dec2))
    y = F.sin(a) * F.cos(d2)
    x = F.cos(d1) * F.sin(d2) - F.sin(d1) * F.cos(d2) * F.cos(a)
    return F.pmod(F.degrees(F.atan2(y, x)) + 360.0, F.lit(360.0))


def chord_of(angle_deg: float) -> float:
    return 2 * math.sin(math.radians(min(180.0, angle_deg)) / 2)


def angle_of(chord: float) -> float:
    return math.degrees(2 * math.asin(min(1.0, chord / 2)))


def ra_window(dec, radius) -> Column:
    """Half-width in right ascension of a circle of radius degrees around a declination; 180 where it holds a pole."""
    d, r = F.radians(_c(dec)), F.radians(_c(radius))
    inner = F.cos(d - r) * F.cos(d + r)
    open_ = F.abs(_c(dec)) + _c(radius) < 90.0
    return F.when(open_ & (inner > 0), F.degrees(F.atan2(F.sin(r), F.sqrt(F.greatest(inner, F.lit(1e-300)))))).otherwise(F.lit(180.0))


def zone_id(dec, height) -> Column:
    return F.floor((_c(dec) + 90.0) / _c(height)).cast("int")


def cells_of(zone, height) -> Column:
    """Cells of a zone: as many as fit its narrowest parallel at about the zone's height."""
    h = _c(height)
    # Each edge from its own number: a sum of the other edge and the height is off by more than the rounding of one product.
    low, high = _c(zone) * h - 90.0, (_c(zone) + 1) * h - 90.0
    worst = F.least(F.lit(90.0), F.greatest(F.abs(low), F.abs(high)))
    return F.greatest(F.lit(1), F.floor(360.0 * F.cos(F.radians(worst)) / h)).cast("long")


def cell_id(ra, zone, height) -> Column:
    n = cells_of(zone, height)
    return F.least(n - 1, F.floor(_c(ra) * n / 360.0))


def sphere_cell(ra, dec, level: int) -> Column:
    """An equal-area quad-tree cell: 2**level bands of equal height in z by 2**(level + 1) sectors, bits interleaved.

    A cell's parent is its number without the last two bits, so ranges of numbers are regions of the sky.
    """
    n = 1 << level
    band = F.least(F.lit(n - 1), F.floor((F.sin(F.radians(_c(dec))) + 1) / 2 * n)).cast("long")
    sector = F.least(F.lit(2 * n - 1), F.floor(F.pmod(_c(ra), F.lit(360.0)) / 360.0 * 2 * n)).cast("long")
    out = F.lit(0).cast("long")
    for bit in range(level + 1):
        out = out + F.shiftleft(F.shiftright(sector, bit).bitwiseAND(F.lit(1)), 2 * bit)
        if bit < level:
            out = out + F.shiftleft(F.shiftright(band, bit).bitwiseAND(F.lit(1)), 2 * bit + 1)
    return out


# Rotation from equatorial (J2000) to galactic axes.
GALACTIC = (
    (-0.0548755604162154, -0.8734370902348850, -0.4838350155487132),
    (0.4941094278755837, -0.4448296299600112, 0.7469822444972189),
    (-0.8676661490190047, -0.1980763734312015, 0.4559837761750669),
)
EQUINOXES = ("J2000",)


def equatorial_galactic(x, y, z, inverse: bool = False) -> tuple[Column, Column, Column]:
    v = (_c(x), _c(y), _c(z))
    rows = list(zip(*GALACTIC, strict=True)) if inverse else GALACTIC
    return tuple(r[0] * v[0] + r[1] * v[1] + r[2] * v[2] for r in rows)


def magnitude(flux, zero_point: float = 0.0) -> Column:
    return F.lit(zero_point) - 2.5 * F.log10(_c(flux))


def flux(mag, zero_point: float = 0.0) -> Column:
    return F.pow(F.lit(10.0), (F.lit(zero_point) - _c(mag)) / 2.5)


def colour(blue, red) -> Column:
    return _c(blue) - _c(red)


def propagate(ra, dec, pm_ra_mas, pm_dec_mas, years) -> tuple[Column, Column]:
    """An extension for moving objects: the position some years later along a great circle; pm_ra is along the parallel."""
    x, y, z = sky_to_xyz(ra, dec)
    a, d = F.radians(_c(ra)), F.radians(_c(dec))
    east = (-F.sin(a), F.cos(a), F.lit(0.0))
    north = (-F.sin(d) * F.cos(a), -F.sin(d) * F.sin(a), F.cos(d))
    u, v = (_c(k) * ARCSEC / 1000 * _c(years) for k in (pm_ra_mas, pm_dec_mas))
    size = F.greatest(F.sqrt(u * u + v * v), F.lit(1e-300))
    moved = [p * F.cos(size) + (e * u + n * v) / size * F.sin(size) for p, e, n in zip((x, y, z), east, north, strict=True)]
    return xyz_to_sky(*moved)
