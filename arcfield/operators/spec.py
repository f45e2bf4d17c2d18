"""Region text: parsing, constructors and canonical rendering.

A region is a list of convexes, a convex a list of half-spaces (x, y, z, l)
with unit normals; a point is inside a convex where every n . p > l.
"""

from __future__ import annotations

import math

import numpy as np

Half = tuple[float, float, float, float]
Convex = list[Half]


class SpecError(ValueError):
    """Text that is no region."""


class DegenerateEdge(SpecError):
    """Vertices that are equal or antipodal: the edge between them is undefined."""


def _vec(ra: float, dec: float) -> np.ndarray:
    if not -90.0 <= dec <= 90.0:
        raise SpecError(f"declination {dec} is outside [-90, 90]")
    a, d = math.radians(ra), math.radians(dec)
    return np.array([math.cos(d) * math.cos(a), math.cos(d) * math.sin(a), math.sin(d)])


def _unit(v) -> np.ndarray:
    v = np.asarray(v, float)
    n = float(np.sqrt(v @ v))
    if n < 1e-12:
        raise SpecError("a vector of length zero has no direction")
    return v / n


def _half(n, offset: float) -> Half:
    return float(n[0]), float(n[1]), float(n[2]), float(offset)


def circle_vec(x: float, y: float, z: float, arcmin: float) -> list[Convex]:
    if arcmin < 0:
        raise SpecError("a radius is not negative")
    return [[_half(_unit((x, y, z)), math.cos(math.radians(min(180.0, arcmin / 60.0))))]]


def circle_sky(ra: float, dec: float, arcmin: float) -> list[Convex]:
    return circle_vec(*_vec(ra, dec), arcmin)


def rect_sky(ra1: float, dec1: float, ra2: float, dec2: float) -> list[Convex]:
    """Between two parallels and two meridians; the way goes east from ``ra1``; over 180 degrees it takes two convexes."""
    low, high = sorted((dec1, dec2))
    _vec(0, low), _vec(0, high)
    span = (ra2 - ra1) % 360.0
    caps = []
    if low > -90.0:
        caps.append((0.0, 0.0, 1.0, math.sin(math.radians(low))))
    if high < 90.0:
        caps.append((0.0, 0.0, -1.0, -math.sin(math.radians(high))))
    if span == 0.0 and ra1 != ra2:
        return [caps]
    if span == 0.0:
        raise SpecError("a rectangle has a width")

    def wedge(a: float, b: float) -> Convex:
        a, b = math.radians(a), math.radians(b)
        return [(-math.sin(a), math.cos(a), 0.0, 0.0), (math.sin(b), -math.cos(b), 0.0, 0.0), *caps]

    if span <= 180.0:
        return [wedge(ra1, ra1 + span)]
    # the closing edge of the first half is left open by nobody: both halves share the meridian line
    mid = ra1 + span / 2
    return [wedge(ra1, mid), wedge(mid, ra1 + span)]


def _edge(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    n = np.cross(a, b)
    if float(np.sqrt(n @ n)) < 1e-12:
        raise DegenerateEdge("an edge between equal or antipodal vertices is undefined")
    return _unit(n)


def poly_vec(vertices, winding: str = "auto", antipodal: str | None = None) -> list[Convex]:
    """Great-circle polygon; a concave one becomes several convexes by ear clipping."""
    v = [_unit(p) for p in vertices]
    if len(v) < 3:
        raise SpecError("a polygon has three vertices or more")
    if antipodal == "equator":
        # unless told otherwise such outlines have their inside on the right, as in the published north-eastern one
        v = v if winding == "ccw" else v[::-1]
        for i, p in enumerate(v):
            q = v[(i + 1) % len(v)]
            if float(p @ q) < -1 + 1e-12:
                # that edge runs along the equator, so its pole is the side of the other vertices; they come in
                # the order of the outline, which has its inside on the left of every other edge
                order = [v[(i + 1 + k) % len(v)] for k in range(len(v))]
                rest = sum(order[1:-1])
                if abs(float(p[2])) > 1e-12 or abs(float(rest[2])) < 1e-12:
                    raise DegenerateEdge("an edge between antipodal vertices follows the equator only if both lie on it and the others do not")
                sides = [_edge(c, d) for c, d in zip(order, order[1:])]
                distinct = [s for k, s in enumerate(sides) if all(float(s @ t) < 1 - 1e-12 for t in sides[:k])]
                return [[_half(np.array([0.0, 0.0, math.copysign(1.0, rest[2])]), 0.0), *[_half(s, 0.0) for s in distinct]]]
        v = v if winding == "ccw" else v[::-1]
    mean = sum(v)
    if winding == "auto":
        area = sum(float(np.cross(v[i], v[(i + 1) % len(v)]) @ mean) for i in range(len(v)))
        winding = "ccw" if area >= 0 else "cw"
    if winding == "cw":
        v = v[::-1]
    n = len(v)
    turns = [float(_edge(v[i - 1], v[i]) @ v[(i + 1) % n]) for i in range(n)]
    if all(t >= -1e-12 for t in turns):
        return [[_half(_edge(v[i], v[(i + 1) % n]), 0.0) for i in range(n)]]
    out, left = [], list(range(n))
    while len(left) > 3:
        for k, j in enumerate(left):
            i, m = left[k - 1], left[(k + 1) % len(left)]
            a, b, c = v[i], v[j], v[m]
            if float(np.cross(a, b) @ c) <= 1e-15:
                continue
            sides = [_edge(a, b), _edge(b, c), _edge(c, a)]
            if any(all(float(s @ v[q]) > 1e-12 for s in sides) for q in left if q not in (i, j, m)):
                continue
            out.append([_half(s, 0.0) for s in sides])
            left.pop(k)
            break
        else:
            raise SpecError("the outline crosses itself")
    a, b, c = (v[q] for q in left)
    return [*out, [_half(s, 0.0) for s in (_edge(a, b), _edge(b, c), _edge(c, a))]]


def poly_sky(points, winding: str = "auto", antipodal: str | None = None) -> list[Convex]:
    return poly_vec([_vec(*p) for p in points], winding, antipodal)


def hull_vec(vertices) -> list[Convex]:
    """Convex hull of points that fit a hemisphere: the planar hull of their gnomonic projection."""
    v = [_unit(p) for p in vertices]
    if len(v) < 3:
        raise SpecError("a hull has three points or more")
    axis = _unit(sum(v))
    if min(float(axis @ p) for p in v) <= 1e-9:
        raise SpecError("the points do not fit a hemisphere about their mean")
    e1 = _unit(np.cross(axis, (1.0, 0.0, 0.0) if abs(axis[0]) < 0.9 else (0.0, 1.0, 0.0)))
    e2 = np.cross(axis, e1)
    flat = sorted({(float(p @ e1 / (p @ axis)), float(p @ e2 / (p @ axis))) for p in v})

    def chain(points):
        out = []
        for p in points:
            while len(out) > 1 and (out[-1][0] - out[-2][0]) * (p[1] - out[-2][1]) - (out[-1][1] - out[-2][1]) * (p[0] - out[-2][0]) <= 1e-15:
                out.pop()
            out.append(p)
        return out

    ring = chain(flat)[:-1] + chain(flat[::-1])[:-1]
    if len(ring) < 3:
        raise DegenerateEdge("the points lie on one great circle")
    corner = [_unit(axis + x * e1 + y * e2) for x, y in ring]
    return [[_half(_edge(corner[i], corner[(i + 1) % len(corner)]), 0.0) for i in range(len(corner))]]


def hull_sky(points) -> list[Convex]:
    return hull_vec([_vec(*p) for p in points])


def convex_of(quads) -> Convex:
    """Half-spaces from (x, y, z, d); all four scale by the normal's length."""
    out = []
    for x, y, z, d in quads:
        n = math.sqrt(x * x + y * y + z * z)
        if n < 1e-12:
            raise SpecError("a half-space has a direction")
        out.append((x / n, y / n, z / n, d / n))
    return out


def region_of(convexes) -> list[Convex]:
    return [convex_of(c) for c in convexes]


def _numbers(tokens: list[str], step: int, least: int, exact: int | None = None) -> list[float]:
    try:
        values = [float(t) for t in tokens]
    except ValueError as e:
        raise SpecError(str(e)) from None
    if any(not math.isfinite(v) for v in values):
        raise SpecError("a number is not finite")
    if len(values) % step or len(values) < least or exact is not None and len(values) != exact:
        raise SpecError(f"{len(values)} numbers do not fit the shape")
    return values


def _groups(values: list[float], k: int) -> list[tuple[float, ...]]:
    return [tuple(values[i : i + k]) for i in range(0, len(values), k)]


def _convex_quads(tokens: list[str]) -> Convex:
    if tokens and tokens[0].upper() == "CARTESIAN":
        tokens = tokens[1:]
    return convex_of(_groups(_numbers(tokens, 4, 4), 4))


def parse_area(text: str | None, antipodal: str | None = None) -> list[Convex]:
    """Convexes of an area text: CIRCLE, RECT, POLY, CHULL, CONVEX or REGION; keywords in any case."""
    words = (text or "").split()
    if not words:
        raise SpecError("no text")
    shape, rest = words[0].upper(), words[1:]
    if shape == "CONVEX":
        return [_convex_quads(rest)]
    if shape == "REGION":
        marks = [i for i, w in enumerate(rest) if w.upper() == "CONVEX"]
        if not marks or marks[0] != 0:
            raise SpecError("a region is a list of convexes")
        return [_convex_quads(rest[i + 1 : j]) for i, j in zip(marks, [*marks[1:], len(rest)])]
    if shape not in ("CIRCLE", "RECT", "POLY", "CHULL"):
        raise SpecError(f"unknown shape {words[0][:20]!r}")
    frame = rest[0].upper() if rest else ""
    if frame not in ("J2000", "CARTESIAN") or shape == "RECT" and frame != "J2000":
        raise SpecError("unknown frame")
    sky, rest = frame == "J2000", rest[1:]
    if shape == "CIRCLE":
        return circle_sky(*_numbers(rest, 3, 3, 3)) if sky else circle_vec(*_numbers(rest, 4, 4, 4))
    if shape == "RECT":
        return rect_sky(*_numbers(rest, 4, 4, 4))
    k = 2 if sky else 3
    points = _groups(_numbers(rest, k, 3 * k), k)
    if shape == "POLY":
        return poly_sky(points, antipodal=antipodal) if sky else poly_vec(points, antipodal=antipodal)
    return hull_sky(points) if sky else hull_vec(points)


def buffered(convexes: list[Convex], theta: float) -> list[Convex]:
    """Every constraint moved out by ``theta`` degrees; one that becomes the whole sphere is dropped."""
    from arcfield.functions.measure import buffer_offset

    out = []
    for convex in convexes:
        moved = [(x, y, z, buffer_offset(offset, theta)) for x, y, z, offset in convex]
        out.append([h for h in moved if h[3] > -1.0])
    return out


def region_text(convexes: list[Convex]) -> str:
    """Canonical text; parses back to the same numbers."""
    return "REGION " + " ".join("CONVEX " + " ".join(repr(float(v)) for h in c for v in h) for c in convexes)
