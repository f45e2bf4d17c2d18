"""Equal-area iso-latitude pixels (12 base pixels, nside = 2**order) and rows-by-cosine grids, as Columns."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def ring_pixel(z: Column, ra: Column, order: int) -> Column:
    """Pixel number in ring order, from the north pole."""
    n = 2**order
    tt = F.pmod(ra / 90.0, F.lit(4.0))
    za = F.abs(z)
    jp, jm = F.floor(n * (0.5 + tt - z * 0.75)), F.floor(n * (0.5 + tt + z * 0.75))
    ir = n + 1 + jp - jm
    shift = F.when(ir % 2 == 0, 1).otherwise(0)
    ip = F.pmod(F.floor((jp + jm - n + shift + 1) / 2), F.lit(4 * n))
    belt = 2 * n * (n - 1) + (ir - 1) * 4 * n + ip
    tp = tt - F.floor(tt)
    tmp = n * F.sqrt(3 * (1 - za))
    cp, cm = F.floor(tp * tmp), F.floor((1 - tp) * tmp)
    ring = cp + cm + 1
    at = F.pmod(F.floor(tt * ring), 4 * ring)
    cap = F.when(z > 0, 2 * ring * (ring - 1) + at).otherwise(12 * n * n - 2 * ring * (ring + 1) + at)
    return F.when(za <= 2.0 / 3.0, belt).otherwise(cap).cast("long")


def ring_of(pixel: Column, order: int) -> Column:
    """Ring number, 1 at the north pole to 4 nside - 1."""
    n = 2**order
    cap = 2 * n * (n - 1)
    north = F.floor((1 + F.sqrt(1 + 2 * pixel)) / 2)
    south = 4 * n - F.floor((1 + F.sqrt(1 + 2 * (12 * n * n - 1 - pixel))) / 2)
    return F.when(pixel < cap, north).when(pixel >= 12 * n * n - cap, south).otherwise(F.floor((pixel - cap) / (4 * n)) + n).cast("int")


def ring_latitude(ring: Column, order: int) -> Column:
    """z of a ring's pixel centres."""
    n = 2**order
    return F.when(ring < n, 1 - ring * ring / F.lit(3.0 * n * n)).when(ring > 3 * n, (4 * n - ring) * (4 * n - ring) / F.lit(3.0 * n * n) - 1).otherwise((2 * n - ring) * 2 / F.lit(3.0 * n))


def pixel_center(pixel: Column, order: int) -> tuple[Column, Column]:
    """(z, ra) of a pixel's centre, for pixels in ring order."""
    n = 2**order
    ring, cap = ring_of(pixel, order), 2 * n * (n - 1)
    north, south = pixel < cap, pixel >= 12 * n * n - cap
    # pixels of a ring, the first one's number, and how far its centre lies from the zero meridian, in pixels
    many = F.when(north, 4 * ring).when(south, 4 * (4 * n - ring)).otherwise(4 * n)
    first = F.when(north, 2 * ring * (ring - 1)).when(south, 12 * n * n - 2 * (4 * n - ring) * (4 * n - ring + 1)).otherwise(cap + (ring - n) * 4 * n)
    lead = F.when(north | south | (F.pmod(ring - n, F.lit(2)) == 0), 0.5).otherwise(0.0)
    return ring_latitude(ring, order), (pixel - first + lead) * 360.0 / many


def nested_pixel(z: Column, ra: Column, order: int) -> Column:
    """Pixel number in nested order: the base pixel, then two bits a level."""
    n = 2**order
    tt = F.pmod(ra / 90.0, F.lit(4.0))
    za = F.abs(z)
    jp, jm = F.floor(n * (0.5 + tt - z * 0.75)), F.floor(n * (0.5 + tt + z * 0.75))
    ifp, ifm = F.floor(jp / n), F.floor(jm / n)
    face = F.when(ifp == ifm, F.pmod(ifp, F.lit(4)) + 4).when(ifp < ifm, F.pmod(ifp, F.lit(4))).otherwise(F.pmod(ifm, F.lit(4)) + 8)
    bx, by = F.pmod(jm, F.lit(n)), n - 1 - F.pmod(jp, F.lit(n))
    nt = F.least(F.lit(3), F.floor(tt))
    tp, tmp = tt - nt, n * F.sqrt(3 * (1 - za))
    cp, cm = F.least(F.lit(n - 1), F.floor(tp * tmp)), F.least(F.lit(n - 1), F.floor((1 - tp) * tmp))
    face = F.when(za <= 2.0 / 3.0, face).when(z >= 0, nt).otherwise(nt + 8).cast("long")
    x = F.when(za <= 2.0 / 3.0, bx).when(z >= 0, n - 1 - cm).otherwise(cp).cast("long")
    y = F.when(za <= 2.0 / 3.0, by).when(z >= 0, n - 1 - cp).otherwise(cm).cast("long")
    out = face * (n * n)
    for k in range(order):
        out = out + F.shiftleft(F.shiftright(x, k).bitwiseAND(F.lit(1).cast("long")), 2 * k) + F.shiftleft(F.shiftright(y, k).bitwiseAND(F.lit(1).cast("long")), 2 * k + 1)
    return out


def igloo_id(dec: Column, ra: Column, rows: int) -> Column:
    """Cells of a grid of ``rows`` latitude rows, columns by the cosine of the row's middle."""
    row = F.least(F.lit(rows - 1), F.floor((dec + 90.0) * rows / 180.0))
    mid = (row + 0.5) * 180.0 / rows - 90.0
    columns = F.greatest(F.lit(1), F.round(2 * rows * F.cos(F.radians(mid))))
    return (row * (4 * rows) + F.floor(ra * columns / 360.0)).cast("long")


def pixel_density(df: DataFrame, order: int) -> DataFrame:
    """(pixel, objects, per_sr): density on equal areas."""
    area = 4 * math.pi / (12 * 4**order)
    return df.groupBy(ring_pixel(F.col("z"), F.col("ra"), order).alias("pixel")).agg(F.count("*").alias("objects")).withColumn("per_sr", F.col("objects") / area)


def ring_moments(df: DataFrame, order: int, m: int) -> DataFrame:
    """(ring, objects, c, s): cosine and sine sums of degree ``m`` along each ring, one aggregate."""
    ring = ring_of(ring_pixel(F.col("z"), F.col("ra"), order), order)
    return df.groupBy(ring.alias("ring")).agg(F.count("*").alias("objects"), F.sum(F.cos(m * F.radians("ra"))).alias("c"), F.sum(F.sin(m * F.radians("ra"))).alias("s"))
