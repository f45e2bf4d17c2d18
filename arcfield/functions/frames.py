"""Constant rotations between the equatorial, ecliptic and galactic frames."""

from __future__ import annotations

import numpy as np

# J2000 obliquity; galactic pole and longitude of the celestial pole (degrees).
OBLIQUITY = 23.4392911
POLE_RA, POLE_DEC, POLE_LON = 192.85948, 27.12825, 122.93192


def _turn(axis: int, angle: float) -> np.ndarray:
    c, s = np.cos(np.radians(angle)), np.sin(np.radians(angle))
    i, j = ((1, 2), (2, 0), (0, 1))[axis]
    m = np.eye(3)
    m[i, i] = m[j, j] = c
    m[i, j], m[j, i] = s, -s
    return m


_FROM_EQUATORIAL = {
    "equatorial": np.eye(3),
    "ecliptic": _turn(0, OBLIQUITY),
    "galactic": _turn(2, 180.0 - POLE_LON) @ _turn(1, 90.0 - POLE_DEC) @ _turn(2, POLE_RA),
}


def matrix(src: str, dst: str) -> np.ndarray:
    """Rotation that takes unit vectors of ``src`` to ``dst``."""
    return _FROM_EQUATORIAL[dst] @ _FROM_EQUATORIAL[src].T
