"""Unit-vector geometry as Columns: everything stays in whole-stage codegen.

Angles are degrees unless said.  A half-space is (n, l): a point p is inside
where n . p > l (``edge="open"``, the default everywhere) or >= l ("closed").
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

from arcfield.functions.frames import matrix


def col(c: str | Column) -> Column:
    return F.col(c) if isinstance(c, str) else c


def num(v: float | Column) -> Column:
    return v if isinstance(v, Column) else F.lit(float(v))


def unit_of(ra: float, dec: float) -> tuple[float, float, float]:
    """Unit vector of one position, on the driver."""
    a, d = math.radians(ra), math.radians(dec)
    return math.cos(d) * math.cos(a), math.cos(d) * math.sin(a), math.sin(d)


def to_unit(ra, dec) -> Column:
    ra, dec = F.radians(col(ra)), F.radians(col(dec))
    return F.struct((F.cos(dec) * F.cos(ra)).alias("x"), (F.cos(dec) * F.sin(ra)).alias("y"), F.sin(dec).alias("z"))


def to_sky(x, y, z) -> Column:
    """struct(ra in [0, 360), dec) of a vector of any length but zero."""
    x, y, z = col(x), col(y), col(z)
    norm = F.sqrt(x * x + y * y + z * z)
    ra = F.degrees(F.atan2(y, x))
    ra = F.when(ra < 0, ra + 360.0).otherwise(ra)
    return F.struct(F.when(ra >= 360.0, 0.0).otherwise(ra).alias("ra"), F.degrees(F.asin(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), z / norm)))).alias("dec"))


def dot(n, p=("x", "y", "z")) -> Column:
    return col(p[0]) * num(n[0]) + col(p[1]) * num(n[1]) + col(p[2]) * num(n[2])


def dot_inside(n, offset, p=("x", "y", "z"), edge: str = "open") -> Column:
    d = dot(n, p)
    return d > num(offset) if edge == "open" else d >= num(offset)


def chord2(q, p=("x", "y", "z")) -> Column:
    dx, dy, dz = (col(a) - (col(b) if isinstance(b, str) else num(b)) for a, b in zip(p, q))
    return dx * dx + dy * dy + dz * dz


def chord_limit(r: float) -> float:
    """Squared chord of an arc of ``r`` degrees, at most half a turn."""
    return 4 * math.sin(math.radians(min(r, 180.0)) / 2) ** 2


def chord_within(q, r, p=("x", "y", "z")) -> Column:
    """Arc distance to ``q`` below ``r``, without any inverse function."""
    limit = F.lit(chord_limit(r)) if not isinstance(r, Column) else 4 * F.pow(F.sin(F.radians(F.least(r, F.lit(180.0))) / 2), 2)
    return chord2(q, p) < limit


def arc_below(d2: Column, angle: Column, exact: Column) -> Column:
    """``exact``, a test whether the arc of squared chord ``d2`` is below ``angle`` degrees (or at most that), computed only where the two are nearly equal.

    Elsewhere one sine and a few products decide; the margin of 1e-9 is far
    above the rounding errors of chords, sums and inverse sines.
    """
    half = F.sin(F.radians(angle) / 2)
    limit, plain = 4 * half * half, (angle > 1e-3) & (angle < 170.0)
    return F.when((d2 > limit * (1 + 1e-9)) & plain, False).when((d2 < limit * (1 - 1e-9)) & plain, True).otherwise(exact)


def arc_deg(q, p=("x", "y", "z")) -> Column:
    """Arc distance by the half chord: exact for small angles."""
    return F.degrees(2 * F.asin(F.least(F.lit(1.0), F.sqrt(chord2(q, p)) / 2)))


def arc_deg_acos(q, p=("x", "y", "z")) -> Column:
    """Baseline: arc distance by the arc cosine, which loses digits for small angles."""
    return F.degrees(F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), dot(q, p)))))


def buffer_offset(offset: float, theta: float) -> float:
    """Offset of the circle widened by ``theta``; -1 is the whole sphere, 1 nothing."""
    angle = math.acos(max(-1.0, min(1.0, offset))) + math.radians(theta)
    return -1.0 if angle >= math.pi else 1.0 if angle <= 0 else math.cos(angle)


def buffer_offset_col(offset, theta: float) -> Column:
    angle = F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), col(offset)))) + math.radians(theta)
    return F.when(angle >= math.pi, -1.0).when(angle <= 0, 1.0).otherwise(F.cos(angle))


def negate(x, y, z, offset) -> Column:
    return F.struct((-col(x)).alias("x"), (-col(y)).alias("y"), (-col(z)).alias("z"), (-col(offset)).alias("l"))


def rotate(src: str, dst: str, p=("x", "y", "z")) -> Column:
    """struct(x, y, z) of ``p`` in frame ``dst``; the matrix is literal."""
    m = matrix(src, dst)
    return F.struct(*[dot(tuple(float(v) for v in row), p).alias(k) for k, row in zip("xyz", m)])


def dot_inside_nd(vector, normal: list[float], offset: float) -> Column:
    """Half-space test in any number of dimensions."""
    products = F.zip_with(col(vector), F.array(*[F.lit(float(v)) for v in normal]), lambda a, b: a.cast("double") * b)
    return F.aggregate(products, F.lit(0.0), lambda s, v: s + v) > num(offset)


def quad_inside(coefficients: dict[str, float], p=("x", "y", "z")) -> Column:
    """f(p) > 0 for a quadric given by terms such as {"xx": 1, "xy": 2, "z": -1, "": -0.5}."""
    by = dict(zip("xyz", p))
    total = F.lit(0.0)
    for term, c in coefficients.items():
        t = F.lit(float(c))
        for k in term:
            t = t * col(by[k])
        total = total + t
    return total > 0


def propagate(years, ra="ra", dec="dec", pm_ra="pm_ra", pm_dec="pm_dec") -> Column:
    """struct(ra, dec) after ``years`` of proper motion; ``pm_*`` in degrees a year, ``pm_ra`` along the circle of latitude."""
    years = num(years)
    d = F.greatest(F.lit(-90.0), F.least(F.lit(90.0), col(dec) + col(pm_dec) * years))
    step = F.when(F.cos(F.radians(col(dec))) > 1e-12, col(pm_ra) * years / F.cos(F.radians(col(dec)))).otherwise(0.0)
    return F.struct(F.pmod(col(ra) + step, F.lit(360.0)).alias("ra"), d.alias("dec"))


def half_width(r: Column | float, dec: Column, kind: str = "exact") -> Column:
    """Half-width in right ascension that a circle of ``r`` about declination ``dec`` can reach.

    "flat" ignores the latitude and "secant" divides by its cosine: both lose
    neighbours away from the equator.  "exact" loses none.
    """
    r = num(r)
    if kind == "flat":
        return r
    if kind == "secant":
        return F.least(F.lit(180.0), r / (F.cos(F.radians(dec)) + 1e-6))
    if kind != "exact":
        raise ValueError(kind)
    reach = F.degrees(F.asin(F.least(F.lit(1.0), F.sin(F.radians(r)) / F.cos(F.radians(dec)))))
    return F.when(F.abs(dec) + r >= 90.0, 180.0).otherwise(F.least(F.lit(180.0), reach + 1e-9))


def band_half_width(r: Column | float, dec: Column, low: Column, high: Column) -> Column:
    """Half-width of the circle inside the declination band [low, high] alone."""
    r = num(r)
    rr, d = F.radians(r), F.radians(dec)
    widest = F.degrees(F.asin(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), F.sin(d) / F.cos(rr)))))
    b = F.radians(F.greatest(low, F.least(high, widest)))
    ratio = (F.cos(rr) - F.sin(d) * F.sin(b)) / (F.cos(d) * F.cos(b))
    width = F.degrees(F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), ratio)))) + 1e-9
    pole = (r >= 90.0) | (F.abs(dec) + r >= 90.0 - 1e-9) | (F.cos(b) < 1e-12) | (F.cos(d) < 1e-12)
    return F.when(pole, 180.0).otherwise(F.least(F.lit(180.0), width))
