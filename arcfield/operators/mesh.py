"""Hierarchical triangular mesh: eight octant faces, each split in four again and again.

A triangle's id is its path in base four behind a leading mark (faces 8..15),
so the triangles below it are one range of ids.  Depth goes to 29, where the
mark still fits a signed 64-bit long.
"""

from __future__ import annotations

import heapq
import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from arcfield.deploy import save, ship
from arcfield.functions.measure import arc_deg, chord_within, unit_of
from arcfield.operators.regions import compiled, packed
from arcfield.operators.spec import Convex, circle_vec

DEPTH, MAX_DEPTH = 20, 29
_POLES = np.array([[0, 0, 1], [1, 0, 0], [0, 1, 0], [-1, 0, 0], [0, -1, 0], [0, 0, -1]], float)
# Corners of faces 8..15 (south, then north), wound counter-clockwise from outside
_FACES = [(2, 1, 5), (3, 2, 5), (4, 3, 5), (1, 4, 5), (1, 2, 0), (2, 3, 0), (3, 4, 0), (4, 1, 0)]


def faces() -> list[np.ndarray]:
    return [_POLES[list(f)] for f in _FACES]


def children(t: np.ndarray) -> list[np.ndarray]:
    """Three corner triangles, then the middle one."""
    mid = t[[1, 2, 0]] + t[[2, 0, 1]]
    mid /= np.sqrt((mid * mid).sum(1))[:, None]
    return [np.stack((t[0], mid[2], mid[1])), np.stack((t[1], mid[0], mid[2])), np.stack((t[2], mid[1], mid[0])), mid]


def ids_of(points: np.ndarray, depth: int = DEPTH) -> np.ndarray:
    """Mesh ids of many unit vectors at once: a vectorised descent."""
    if not 0 <= depth <= MAX_DEPTH:
        raise ValueError(f"depth {depth} is outside 0..{MAX_DEPTH}")
    p = np.asarray(points, float)
    face = np.select([(p[:, 2] < 0) & (p[:, 0] >= 0) & (p[:, 1] >= 0), (p[:, 2] < 0) & (p[:, 0] < 0) & (p[:, 1] >= 0), (p[:, 2] < 0) & (p[:, 0] < 0), p[:, 2] < 0, (p[:, 0] >= 0) & (p[:, 1] >= 0), (p[:, 0] < 0) & (p[:, 1] >= 0), p[:, 0] < 0], list(range(7)), 7)
    ids = 8 + face.astype(np.int64)
    t = np.stack(faces())[face]
    for _ in range(depth):
        mid = t[:, [1, 2, 0]] + t[:, [2, 0, 1]]
        mid /= np.sqrt((mid * mid).sum(2))[:, :, None]
        # outside the middle triangle across the edge that faces corner k
        corner = [np.einsum("ij,ij->i", np.cross(mid[:, (k + 2) % 3], mid[:, (k + 1) % 3]), p) >= 0 for k in range(3)]
        pick = np.select(corner, [0, 1, 2], 3)
        options = [np.stack((t[:, 0], mid[:, 2], mid[:, 1]), 1), np.stack((t[:, 1], mid[:, 0], mid[:, 2]), 1), np.stack((t[:, 2], mid[:, 1], mid[:, 0]), 1), mid]
        t = np.where((pick == 0)[:, None, None], options[0], np.where((pick == 1)[:, None, None], options[1], np.where((pick == 2)[:, None, None], options[2], options[3])))
        ids = 4 * ids + pick
    return ids


def _half(a, b):
    """The unit vector half way between two."""
    x, y, z = a[0] + b[0], a[1] + b[1], a[2] + b[2]
    size = math.sqrt(x * x + y * y + z * z)
    return x / size, y / size, z / size


_CORNERS = [tuple(tuple(map(float, p)) for p in t) for t in faces()]


def id_of(x: float, y: float, z: float, depth: int = DEPTH) -> int:
    """``ids_of`` of one unit vector in plain arithmetic, which is quickest for one."""
    p = (x, y, z)
    if z < 0:
        face = (0 if x >= 0 else 1) if y >= 0 else (2 if x < 0 else 3)
    else:
        face = (4 if x >= 0 else 5) if y >= 0 else (6 if x < 0 else 7)
    a, b, c = _CORNERS[face]
    out = 8 + face
    for _ in range(depth):
        m0, m1, m2 = _half(b, c), _half(c, a), _half(a, b)
        if _dot(_cross(m2, m1), p) >= 0:
            pick, b, c = 0, m2, m1
        elif _dot(_cross(m0, m2), p) >= 0:
            pick, a, b, c = 1, b, m0, m2
        elif _dot(_cross(m1, m0), p) >= 0:
            pick, a, b, c = 2, c, m1, m0
        else:
            pick, a, b, c = 3, m0, m1, m2
        out = 4 * out + pick
    return out


def corners_of(mesh_id: int) -> np.ndarray:
    path = []
    while mesh_id >= 16:
        path.append(mesh_id & 3)
        mesh_id >>= 2
    t = faces()[mesh_id - 8]
    for k in reversed(path):
        t = children(t)[k]
    return t


def centers(c: str = "mesh_id", corners: bool = False):
    """Arrow column: the centre (x, y, z) of each triangle, or its corners one after the other."""

    @F.pandas_udf("array<double>")
    def call(ids: pd.Series) -> pd.Series:
        return pd.Series([None if pd.isna(i) else (corners_of(int(i)).ravel() if corners else center_of(int(i))) for i in ids], dtype=object)

    return call(F.col(c))


def center_of(mesh_id: int) -> np.ndarray:
    c = corners_of(mesh_id).sum(0)
    return c / np.sqrt(c @ c)


def level_of(mesh_id: int) -> int:
    return (mesh_id.bit_length() - 4) // 2


def range_of(mesh_id: int, depth: int = DEPTH) -> tuple[int, int]:
    """First and last leaf id at ``depth`` below a triangle."""
    s = 2 * (depth - level_of(mesh_id))
    return mesh_id << s, ((mesh_id + 1) << s) - 1


def mesh_id(depth: int = DEPTH):
    """Arrow function of x, y, z: the ids of a batch at once."""

    @F.pandas_udf("long")
    def call(x: pd.Series, y: pd.Series, z: pd.Series) -> pd.Series:
        return pd.Series(ids_of(np.column_stack((x, y, z)), depth))

    return call


def mesh_id_row(depth: int = DEPTH):
    """Baseline: one pickled call a row."""
    return F.udf(lambda x, y, z: id_of(x, y, z, depth), "long")


def mesh_parent(c: str | Column, k: int) -> Column:
    return F.shiftright(c, 2 * k)


def mesh_level(c: str | Column) -> Column:
    return ((F.length(F.bin(c)) - 4) / 2).cast("int")


def mesh_contains(a: Column, b: Column) -> Column:
    """Triangle ``b`` lies in ``a``: its id begins with a's."""
    gap = mesh_level(b) - mesh_level(a)
    return (gap >= 0) & (F.floor(b / F.pow(F.lit(4.0), F.greatest(gap, F.lit(0)))).cast("long") == a)


def mesh_path(c: str) -> Column:
    """Readable path: the face and the child numbers."""
    return F.concat(F.when(F.substring(F.bin(c), 2, 1) == "0", "S").otherwise("N"), F.substring(F.conv(F.col(c).cast("string"), 10, 4), 2, 64))


def with_mesh(df: DataFrame, depth: int = DEPTH) -> DataFrame:
    ship(df.sparkSession)
    return df.withColumn("mesh_id", mesh_id(depth)("x", "y", "z"))


def write_mesh(df: DataFrame, path: str, depth: int = DEPTH) -> None:
    """Rows range-partitioned and sorted by mesh id, so that ranges skip files and row groups."""
    with_mesh(df, depth).repartitionByRange("mesh_id").sortWithinPartitions("mesh_id").write.mode("overwrite").parquet(path)


def _cross(a, b):
    return a[1] * b[2] - a[2] * b[1], a[2] * b[0] - a[0] * b[2], a[0] * b[1] - a[1] * b[0]


def _dot(a, b) -> float:
    return a[0] * b[0] + a[1] * b[1] + a[2] * b[2]


def _angle(c: float) -> float:
    return math.acos(max(-1.0, min(1.0, c)))


def _apart(t, n) -> float:
    """Angle from a direction to a triangle (three tuples), 0 inside; plain arithmetic, which is quickest for one triangle."""
    a, b, c = t
    sides = _cross(a, b), _cross(b, c), _cross(c, a)
    if all(_dot(s, n) >= 0 for s in sides):
        return 0.0
    best = max(_dot(a, n), _dot(b, n), _dot(c, n))
    for p, q, s in ((a, b, sides[0]), (b, c, sides[1]), (c, a, sides[2])):
        # the foot of the direction on this edge's circle lies between its ends
        if _dot(_cross(s, p), n) >= 0 and _dot(_cross(q, s), n) >= 0:
            off = _dot(s, n)
            best = max(best, math.sqrt(max(0.0, 1 - off * off / _dot(s, s))))
    return _angle(best)


def _judge(t: np.ndarray, convex: Convex) -> str:
    """A triangle against a convex: "out" only if surely outside, "full" only if surely inside."""
    t = [tuple(map(float, p)) for p in t]
    c = tuple(t[0][k] + t[1][k] + t[2][k] for k in range(3))
    size = math.sqrt(_dot(c, c))
    c = tuple(v / size for v in c)
    spread = max(_angle(_dot(c, p)) for p in t)
    full = True
    for h in convex:
        n, limit = h[:3], _angle(h[3])
        gap = _angle(_dot(n, c))
        if gap - spread >= limit + 1e-12 or gap + spread >= limit and _apart(t, n) >= limit + 1e-12:
            return "out"
        # inside where the triangle keeps off the rest of the sphere, a cap about the opposite direction
        if gap + spread > limit - 1e-12 and _apart(t, (-n[0], -n[1], -n[2])) <= math.pi - limit + 1e-12:
            full = False
    return "full" if full else "part"


def cover(region: list[Convex], max_ranges: int = 20, depth: int = DEPTH, max_level: int = 14) -> list[tuple[int, int, bool]]:
    """(low, high, full) leaf ranges that hold the region; full ranges need no further test.

    The largest undecided triangle is split first; splitting stops when the
    merged ranges pass one and a half times the budget, and the last set that
    fits is returned.
    """
    sure: list[int] = []
    heap: list[tuple[int, int]] = []

    def place(i: int, t: np.ndarray) -> None:
        kinds = [_judge(t, c) for c in region]
        if "full" in kinds:
            sure.append(i)
        elif "part" in kinds:
            heapq.heappush(heap, (level_of(i), i))
            shapes[i] = t

    shapes: dict[int, np.ndarray] = {}
    for k, t in enumerate(faces()):
        place(8 + k, t)

    def merged() -> list[tuple[int, int, bool]]:
        rows = sorted([(*range_of(i, depth), True) for i in sure] + [(*range_of(i, depth), False) for _, i in heap])
        out: list[list] = []
        for a, b, f in rows:
            if out and out[-1][1] + 1 == a and out[-1][2] == f:
                out[-1][1] = b
            else:
                out.append([a, b, f])
        return [tuple(r) for r in out]

    best = merged()
    while heap and heap[0][0] < min(depth, max_level):
        _, i = heapq.heappop(heap)
        for k, t in enumerate(children(shapes.pop(i))):
            place(4 * i + k, t)
        now = merged()
        if len(now) <= max_ranges:
            best = now
        elif len(now) > 1.5 * max_ranges:
            break
    return best


def _dots(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return (a * b).sum(-1)


def _arc(c: np.ndarray) -> np.ndarray:
    return np.arccos(np.clip(c, -1.0, 1.0))


def _apart_many(t: np.ndarray, n: np.ndarray) -> np.ndarray:
    """``_apart`` of many triangles and directions."""
    best, inside = np.full(len(t), -1.0), np.ones(len(t), bool)
    for k in range(3):
        p, q = t[:, k], t[:, (k + 1) % 3]
        s = np.cross(p, q)
        off = _dots(s, n)
        inside &= off >= 0
        best = np.maximum(best, _dots(p, n))
        foot = (_dots(np.cross(s, p), n) >= 0) & (_dots(np.cross(q, s), n) >= 0)
        best = np.where(foot, np.maximum(best, np.sqrt(np.maximum(0.0, 1 - off * off / _dots(s, s)))), best)
    return np.where(inside, 0.0, _arc(best))


def cover_many(convexes: np.ndarray, max_ranges: int = 20, depth: int = DEPTH, max_level: int = 14) -> tuple[np.ndarray, ...]:
    """Covers of many convexes at once: arrays (convex, low, high, full), a convex's ranges apart from each other.

    ``convexes`` is (count, constraints, 4); a row with offset -2 constrains
    nothing.  All undecided triangles of a convex are split together; the last
    level whose merged ranges fit ``max_ranges`` is returned.
    """
    limits = _arc(convexes[:, :, 3])
    used = convexes[:, :, 3] > -2
    never = (used & (convexes[:, :, 3] >= 1)).any(1)
    own = np.repeat(np.flatnonzero(~never), 8)
    ids, t = np.tile(np.arange(8, 16), (~never).sum()), np.tile(np.stack(faces()), ((~never).sum(), 1, 1))
    sure = held = np.zeros((0, 4), np.int64)
    done = []
    for level in range(min(depth, max_level) + 1):
        c = t.sum(1)
        c /= np.sqrt(_dots(c, c))[:, None]
        spread = _arc(np.stack([_dots(c, t[:, k]) for k in range(3)]).min(0))
        out, full = np.zeros(len(t), bool), np.ones(len(t), bool)
        for k in range(convexes.shape[1]):
            n, limit, here = convexes[own, k, :3], limits[own, k], used[own, k]
            gap = _arc(_dots(n, c))
            unsure = here & (gap + spread >= limit) & (gap - spread < limit + 1e-12)
            off = gap - spread >= limit + 1e-12
            off[unsure] = _apart_many(t[unsure], n[unsure]) >= limit[unsure] + 1e-12
            out |= here & off
            part = here & (gap + spread > limit - 1e-12)
            near = part & ~out
            part[near] = _apart_many(t[near], -n[near]) <= math.pi - limit[near] + 1e-12
            full &= ~part
        shift = 2 * (depth - level)
        rows = np.column_stack((own, ids << shift, ((ids + 1) << shift) - 1, full))
        sure = np.concatenate((sure, rows[full & ~out]))
        open_ = ~out & ~full
        now = np.concatenate((sure, rows[open_]))
        now = now[np.lexsort((now[:, 1], now[:, 0]))]
        if len(now):
            head = np.ones(len(now), bool)
            head[1:] = (now[1:, 0] != now[:-1, 0]) | (now[1:, 1] != now[:-1, 2] + 1) | (now[1:, 3] != now[:-1, 3])
            first = np.flatnonzero(head)
            now = np.column_stack((now[first, 0], now[first, 1], now[np.append(first[1:], len(now)) - 1, 2], now[first, 3]))
        count = np.bincount(now[:, 0], minlength=len(convexes))
        passed = count > max_ranges
        if level == 0:
            passed[:] = False  # the faces always do
        last = np.ones(len(convexes), bool)
        last[own[open_]] = level == min(depth, max_level)
        done += [held[passed[held[:, 0]]], now[(last & ~passed)[now[:, 0]]]]
        live = ~(passed | last)
        held, sure, go = now[live[now[:, 0]]], sure[live[sure[:, 0]]], open_ & live[own]
        own, ids, t = own[go], ids[go], t[go]
        if not len(own):
            break
        mid = t[:, [1, 2, 0]] + t[:, [2, 0, 1]]
        mid /= np.sqrt((mid * mid).sum(2))[:, :, None]
        t = np.concatenate([np.stack((t[:, k], mid[:, (k + 2) % 3], mid[:, (k + 1) % 3]), 1) for k in range(3)] + [mid])
        own, ids = np.tile(own, 4), np.concatenate([4 * ids + k for k in range(4)])
    rows = np.concatenate(done)
    return rows[:, 0], rows[:, 1], rows[:, 2], rows[:, 3].astype(bool)


def in_cover(ranges: list[tuple[int, int, bool]], exact: Column, column: str = "mesh_id") -> Column:
    """Literal ranges the scan can use; the exact test only where a range is not full."""
    out = F.lit(False)
    for a, b, full in ranges:
        hit = F.col(column).between(a, b)
        out = out | (hit if full else hit & exact)
    return out


def mesh_select(df: DataFrame, region: list[Convex], max_ranges: int = 20, depth: int = DEPTH) -> DataFrame:
    """Points of a mesh table in a region."""
    return df.where(in_cover(cover(region, max_ranges, depth), compiled(region)))


def mesh_nearby_xyz(df: DataFrame, x: float, y: float, z: float, r: float, depth: int = DEPTH) -> DataFrame:
    q = (x, y, z)
    ranges = cover(circle_vec(x, y, z, 60 * r), depth=depth)
    near = F.lit(False)
    for a, b, _ in ranges:
        near = near | F.col("mesh_id").between(a, b)
    return df.where(near).where(chord_within(q, r)).withColumn("distance_deg", arc_deg(q))


def mesh_nearby_eq(df: DataFrame, ra: float, dec: float, r: float, kind: str | None = None, depth: int = DEPTH) -> DataFrame:
    """``kind`` restricts to one object class."""
    df = df if kind is None else df.where(F.col("class") == kind)
    return mesh_nearby_xyz(df, *unit_of(ra, dec), r, depth)


def mesh_nearest_xyz(df: DataFrame, x: float, y: float, z: float, k: int = 1, start: float = 1.0, depth: int = DEPTH) -> DataFrame:
    r = start
    while r < 180.0 and mesh_nearby_xyz(df, x, y, z, r, depth).limit(k).count() < k:
        r *= 2
    return mesh_nearby_xyz(df, x, y, z, min(r, 180.0), depth).orderBy("distance_deg", "obj_id").limit(k)


def mesh_nearest_eq(df: DataFrame, ra: float, dec: float, k: int = 1, kind: str | None = None, depth: int = DEPTH) -> DataFrame:
    df = df if kind is None else df.where(F.col("class") == kind)
    return mesh_nearest_xyz(df, *unit_of(ra, dec), k, depth=depth)


def region_cover_rows(halfspaces: DataFrame, max_ranges: int = 20, depth: int = DEPTH) -> DataFrame:
    """(region_id, lo, hi, full) of regions given as half-space rows: those of one convex many at once, others one by one."""
    ship(halfspaces.sparkSession)

    def work(batches):
        for pdf in batches:
            ids, regions = pdf["region_id"].to_numpy(), []
            for hs in pdf["h"]:
                region: dict[int, list] = {}
                for h in sorted((h["convex_id"], h["halfspace_id"], h["x"], h["y"], h["z"], h["l"]) for h in hs):
                    region.setdefault(h[0], []).append(h[2:])
                regions.append(list(region.values()))
            one = [k for k, region in enumerate(regions) if len(region) == 1]
            for first in range(0, len(one), 2000):
                part = one[first : first + 2000]
                many = np.full((len(part), max(len(regions[k][0]) for k in part), 4), -2.0)
                for i, k in enumerate(part):
                    many[i, : len(regions[k][0])] = regions[k][0]
                own, lo, hi, full = cover_many(many, max_ranges, depth)
                yield pd.DataFrame({"region_id": ids[np.array(part)[own]], "lo": lo, "hi": hi, "full": full})
            rows = [(ids[k], *c) for k, region in enumerate(regions) if len(region) > 1 for c in cover(region, max_ranges, depth)]
            yield pd.DataFrame(rows, columns=["region_id", "lo", "hi", "full"])

    grouped = halfspaces.groupBy("region_id").agg(F.collect_list(F.struct("convex_id", "halfspace_id", "x", "y", "z", "l")).alias("h"))
    return grouped.mapInPandas(work, "region_id long, lo long, hi long, full boolean")


def cover_rows(circles: DataFrame, max_ranges: int = 20, depth: int = DEPTH) -> DataFrame:
    """(region_id, lo, hi, full) of a column of circles (obj_id, x, y, z, radius), in parallel by rows."""
    ship(circles.sparkSession)

    def work(batches):
        for pdf in batches:
            for first in range(0, len(pdf), 2000):
                part = pdf.iloc[first : first + 2000]
                circle = np.column_stack((part["x"], part["y"], part["z"], np.cos(np.radians(part["radius"]))))
                own, lo, hi, full = cover_many(circle[:, None, :], max_ranges, depth)
                yield pd.DataFrame({"region_id": part["obj_id"].to_numpy()[own], "lo": lo, "hi": hi, "full": full})

    # a small file is one task; covers cost far more than moving circles
    spread = circles.select("obj_id", "x", "y", "z", "radius").repartition(4 * circles.sparkSession.sparkContext.defaultParallelism)
    return spread.mapInPandas(work, "region_id long, lo long, hi long, full boolean")


def in_ranges(points: DataFrame, rows: DataFrame, depth: int = DEPTH) -> DataFrame:
    """Points of a mesh table (obj_id, mesh_id, x, y, z) by the cover ranges (region_id, lo, hi, full and what they carry) that hold them, once a range.

    A range meets points on its ancestors at the level where it spans at most
    five, so neither a wide range nor a narrow one makes a frequent key.
    """
    rows = save(rows.withColumn("level", F.greatest(F.lit(0), F.lit(depth) - F.ceil(F.log2(F.col("hi") - F.col("lo") + 1) / 2)).cast("int")), "covers")
    shift = 2 * (F.lit(depth) - F.col("level"))
    rows = rows.withColumn("ancestor", F.explode(F.sequence(F.call_function("shiftright", "lo", shift), F.call_function("shiftright", "hi", shift))))
    levels = sorted(r[0] for r in rows.select("level").distinct().collect())  # at most depth + 1
    keys = [F.struct(F.lit(k).alias("level"), F.shiftright("mesh_id", 2 * (depth - k)).alias("ancestor")) for k in levels] or [F.struct(F.lit(0).alias("level"), F.col("mesh_id").alias("ancestor"))]
    p = points.select("obj_id", "mesh_id", "x", "y", "z", F.inline(F.array(*keys)))
    return p.join(rows, ["level", "ancestor"]).where(F.col("mesh_id").between(F.col("lo"), F.col("hi"))).drop("mesh_id", "lo", "hi", "level", "ancestor")


def region_join(points: DataFrame, halfspaces: DataFrame, edge: str = "open", max_ranges: int = 20, depth: int = DEPTH) -> DataFrame:
    """(obj_id, region_id) for any number of regions: covers find candidates, the constraints decide those of ranges that are not full.

    Ranges of a region are apart and carry its constraints, so a pair arises
    once and none is shuffled.
    """
    convexes = halfspaces.groupBy("region_id", "convex_id").agg(F.collect_list(F.struct("x", "y", "z", "l")).alias("c"))
    regions = convexes.groupBy("region_id").agg(F.collect_list("c").alias("region"))
    rows = region_cover_rows(halfspaces, max_ranges, depth).join(regions, "region_id")
    hit = in_ranges(points if "mesh_id" in points.columns else with_mesh(points, depth), rows, depth)
    return hit.where(F.col("full") | packed(F.col("region"), edge)).select("obj_id", "region_id")


def mesh_join(points: DataFrame, circles: DataFrame, max_ranges: int = 20, depth: int = DEPTH) -> DataFrame:
    """(obj_id, region_id) by covers of circles, which carry them, then the exact distance; ranges of a circle are apart, so a pair arises once."""
    c = circles.select(F.col("obj_id").alias("region_id"), *[F.col(k).alias(f"c{k}") for k in "xyz"], "radius")
    hit = in_ranges(points, cover_rows(circles, max_ranges, depth).join(c, "region_id"), depth)
    d = (F.col("x") - F.col("cx")) ** 2 + (F.col("y") - F.col("cy")) ** 2 + (F.col("z") - F.col("cz")) ** 2
    inside = d < 4 * F.pow(F.sin(F.radians(F.least("radius", F.lit(180.0))) / 2), 2)
    return hit.where(inside).select("obj_id", "region_id")


def mesh_neighbors(df: DataFrame, r: float, depth: int = DEPTH) -> DataFrame:
    """Baseline: half pairs by a cover a point."""
    pairs = mesh_join(with_mesh(df, depth), df.withColumn("radius", F.lit(float(r))), 12, depth)
    return pairs.where("region_id < obj_id").select(F.col("region_id").alias("obj_id"), F.col("obj_id").alias("neighbor_id"))


def mesh_overlap(circles: DataFrame, ra: float, dec: float, r: float, covers: DataFrame | None = None, depth: int = DEPTH) -> DataFrame:
    """Circles that meet a query circle through covers of both sides: one index for all sizes.

    ``covers`` are stored ``cover_rows``; without them every circle is covered anew.
    """
    q = unit_of(ra, dec)
    mine = cover(circle_vec(*q, 60 * r), depth=depth)
    rows = cover_rows(circles, depth=depth) if covers is None else covers
    hit = F.lit(False)
    for a, b, _ in mine:
        hit = hit | ((F.col("lo") <= b) & (F.col("hi") >= a))
    found = rows.where(hit).select("region_id").distinct()
    reach = F.least(F.lit(180.0), F.col("radius") + r)
    return circles.join(found, circles.obj_id == found.region_id, "left_semi").where(chord_within(q, reach))


def area_stats(level: int) -> dict[str, float]:
    """Smallest, mean and largest triangle area of a level, in steradians."""
    todo = [np.stack(faces())]
    t = todo[0]
    for _ in range(level):
        mid = t[:, [1, 2, 0]] + t[:, [2, 0, 1]]
        mid /= np.sqrt((mid * mid).sum(2))[:, :, None]
        t = np.concatenate([np.stack((t[:, k], mid[:, (k + 2) % 3], mid[:, (k + 1) % 3]), 1) for k in range(3)] + [mid])
    a, b, c = t[:, 0], t[:, 1], t[:, 2]
    top = np.abs(np.einsum("ij,ij->i", a, np.cross(b, c)))
    dots = 1 + np.einsum("ij,ij->i", a, b) + np.einsum("ij,ij->i", b, c) + np.einsum("ij,ij->i", c, a)
    area = 2 * np.arctan2(top, dots)
    return {"level": level, "triangles": len(area), "smallest": float(area.min()), "mean": float(area.mean()), "largest": float(area.max()), "total": float(area.sum())}
