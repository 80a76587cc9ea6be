"""Reflections, translations and rotations of n dimensions, as driver-side arrays.

A composite is kept as a pair (A, b) of matrix and shift, which stands for the (n + 1)-square matrix of
homogeneous coordinates; homogeneous() writes that out.
"""

from __future__ import annotations

import functools

import numpy as np

from ..functions.rng import uniform_of

#: Whole degrees left out of the search.
SPECIAL = (30, 45, 60, 90, 120, 135, 150)


def angles(include_special: bool = False, step: int = 1) -> list[int]:
    """Whole degrees strictly between 0 and 180."""
    return [a for a in range(step, 180, step) if include_special or a not in SPECIAL]


def translation(n: int, seed: str = "smp") -> np.ndarray:
    """n shifts in (0, 1), drawn once for all candidates."""
    return np.array([uniform_of(seed, "shift", "t", j) for j in range(n)])


def reflection(n: int, axis: int, kind: str = "single") -> np.ndarray:
    """Signs of the attributes; axis is 1-based. single: that axis alone is negated; complement: all others."""
    if not 1 <= axis <= n:
        raise ValueError(f"axis {axis} of {n}")
    signs = np.ones(n)
    signs[axis - 1] = -1
    if kind == "complement":
        return -signs
    if kind != "single":
        raise ValueError(f"reflection is single or complement, not {kind}")
    return signs


def plane_rotation(n: int, i: int, j: int, degrees: float) -> np.ndarray:
    """Rotation in the plane of axes i < j (0-based)."""
    c, s = np.cos(np.radians(degrees)), np.sin(np.radians(degrees))
    out = np.eye(n)
    out[[i, j], [i, j]] = c
    out[j, i], out[i, j] = s, -s
    return out


def rotations(n: int, degrees: tuple[float, ...], planes: tuple[tuple[int, int], ...] | None = None) -> np.ndarray:
    """(angles, n, n): for each angle the product of the rotations in all planes, in order (all i < j by default).

    A plane's factor from the right mixes two columns only, for all angles at once."""
    c, s = np.cos(np.radians(degrees))[:, None], np.sin(np.radians(degrees))[:, None]
    out = np.broadcast_to(np.eye(n), (len(degrees), n, n)).copy()
    for i, j in planes if planes is not None else [(i, j) for i in range(n) for j in range(i + 1, n)]:
        a, b = out[:, :, i].copy(), out[:, :, j]
        out[:, :, i], out[:, :, j] = a * c + b * s, b * c - a * s
    return out


@functools.lru_cache(maxsize=32)
def cached_rotations(n: int, degrees: tuple[float, ...]) -> np.ndarray:
    return rotations(n, degrees)


def rotation(n: int, degrees: float, planes: tuple[tuple[int, int], ...] | None = None) -> np.ndarray:
    return rotations(n, (degrees,), planes)[0]


def rotation_by_plane(n: int, by_plane: dict[tuple[int, int], float]) -> np.ndarray:
    """The general form, an angle for each plane, planes in the dictionary's order."""
    return chain([plane_rotation(n, i, j, d) for (i, j), d in reversed(by_plane.items())])


def chain(matrices: list[np.ndarray]) -> np.ndarray:
    """One matrix for transformations applied one after another, the first of the list first."""
    out = np.eye(len(matrices[0]))
    for m in matrices:
        out = m @ out
    return out


def compose(rotation_: np.ndarray, shift: np.ndarray, signs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(A, b) of: negate by signs, add the shift, rotate."""
    return rotation_ * signs, rotation_ @ shift


def homogeneous(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    n = len(b)
    out = np.eye(n + 1)
    out[:n, :n], out[:n, n] = a, b
    return out


def orthogonality_error(a: np.ndarray) -> float:
    return float(np.abs(a @ a.T - np.eye(len(a))).max())
