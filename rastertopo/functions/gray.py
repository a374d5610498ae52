"""Array kernels on grayscale images: connectivity numbers by comparison, homotopic kernels, crests, topological watershed.

The outside has level 0. ``conn`` is the pair of the upper sections (adjacency n) and of the lower ones (dual)."""

from __future__ import annotations

import numpy as np

from .kernels import label
from .lut import OFFSETS, PAIRS, dual, numbers


def sides(f: np.ndarray) -> np.ndarray:
    """The levels of the 8 neighbours: array (8, rows, columns)."""
    p, (h, w) = np.pad(f, 1), f.shape
    return np.stack([p[1 + r : 1 + r + h, 1 + c : 1 + c + w] for r, c in OFFSETS])


def gray_numbers(f: np.ndarray, conn: str = "8/4") -> tuple[np.ndarray, ...]:
    """T of the higher, at least as high, lower and at most as high neighbours."""
    near, weights = sides(f), (1 << np.arange(8))[:, None, None]
    up, down = np.array(numbers(conn)[0]), np.array(numbers(dual(conn))[0])
    at = lambda table, test: table[(test * weights).sum(0)]
    return at(up, near > f), at(up, near >= f), at(down, near < f), at(down, near <= f)


def _subfields(shape):
    r, c = np.indices(shape)
    return [(r % 2 == a) & (c % 2 == b) for a in (0, 1) for b in (0, 1)]


def _lowest(f: np.ndarray) -> np.ndarray:
    near = sides(f)
    return np.where(near < f, near, -1).max(0)


def gray_kernel(f: np.ndarray, conn: str = "8/4", keep: np.ndarray | None = None, height: int | None = None) -> tuple[np.ndarray, int]:
    """The homotopic kernel: destructible pixels sink to the highest strictly lower neighbour until none is left; the
    image and the number of sinkings. ``keep`` pixels stay. With ``height``, peaks at most that high above their
    highest neighbour sink to it, too (the leveling kernel), which loses these peaks only."""
    f, count, fields = f.copy(), 0, _subfields(f.shape)
    free = ~keep if keep is not None else np.ones(f.shape, bool)
    while True:
        before = count
        for here in fields:
            _, above_eq, below, _ = gray_numbers(f, conn)
            goes = here & free & (above_eq == 1) & (below == 1)
            if height is not None:
                top = sides(f).max(0)
                goes |= here & free & (above_eq == 0) & (f > top) & (f - top <= height)
            f = np.where(goes, _lowest(f), f)
            count += int(goes.sum())
        if count == before:
            return f, count


def gray_skeleton(f: np.ndarray, conn: str = "8/4") -> np.ndarray:
    """The kernel that keeps peaks and the ends of crests: pixels with one neighbour at least as high."""
    ends = (sides(f) >= f).sum(0) <= 1
    return gray_kernel(f, conn, keep=ends & (f > 0))[0]


def restore_crests(f: np.ndarray, conn: str = "8/4", rounds: int = 1) -> np.ndarray:
    """Constructible pixels next to a separating one rise to the lowest strictly higher neighbour: broken crests meet again."""
    for _ in range(rounds):
        for here in _subfields(f.shape):
            above, _, below, below_eq = gray_numbers(f, conn)
            crest = (sides(below >= 2) > 0).any(0)
            near = sides(f)
            to = np.where(near > f, near, 1 << 30).min(0)
            f = np.where(here & crest & (above == 1) & (below_eq == 1), to, f)
    return f


def watershed(f: np.ndarray, conn: str = "8/4") -> np.ndarray:
    """The topological watershed: a pixel sinks by one while it touches exactly one component of what is lower; so every
    lower section keeps its components, and basins grow until only their divides stand."""
    f, m = np.pad(f, 1), PAIRS[conn][1]  # the outside is part of every lower section
    fields = _subfields(f.shape)
    pads = [(r, c) for k, (r, c) in enumerate(OFFSETS) if m == 8 or k % 2 == 0]
    h, w = f.shape
    changed = True
    while changed:
        changed = False
        for k in range(int(f.max(initial=0)), 0, -1):
            for here in fields:
                at = here & (f == k)
                if not at.any():
                    continue
                p = np.pad(label(f < k, m), 1, constant_values=-1)
                near = np.stack([p[1 + r : 1 + r + h, 1 + c : 1 + c + w] for r, c in pads])
                high, low = near.max(0), np.where(near >= 0, near, 1 << 30).min(0)
                goes = at & (high >= 0) & (high == low)
                if goes.any():
                    f = np.where(goes, k - 1, f)
                    changed = True
    return f[1:-1, 1:-1]
