"""One loop for the class of topology-changing operators: characterise points, modify them, look at their neighbours again.

A rule says which points may change, what becomes of them and which go first. The loop keeps a frontier: after a point
changed, only its neighbours (all eight, or the four beside it) are characterised anew. With four, a point whose state
depends on a diagonal neighbour may be missed, so a point is looked at once more before it changes, and a full scan
follows whenever the frontier is empty, until a scan finds nothing. Points of one parity subfield are never adjacent, so they may change together."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

from . import gray as G
from . import kernels as K
from .lut import OFFSETS

#: Which neighbours are looked at again.
RECHECK = {8: OFFSETS, 4: [o for o in OFFSETS if 0 in o]}


def stabilise(image: np.ndarray, characterise: Callable, modify: Callable, priority: np.ndarray | None = None, recheck: int = 8, work: K.Work | None = None) -> np.ndarray:
    """``characterise(x, at)``: which of the flat places change; ``modify(x, at)``: their new values. Least priority first."""
    if recheck not in RECHECK:
        raise ValueError("recheck is 4 or 8")
    x = np.pad(image, 1)
    h, w = x.shape
    level = np.zeros(x.shape, np.int64)
    if priority is not None:
        level[1:-1, 1:-1] = priority
    level = level.ravel()
    inside = np.zeros(x.shape, bool)
    inside[1:-1, 1:-1] = True
    inside = inside.ravel()
    places = np.flatnonzero(inside)
    shifts = np.array([r * w + c for r, c in RECHECK[recheck]])
    ready = np.zeros(h * w, bool)

    def look(at: np.ndarray) -> None:
        if work:
            work.characterised += len(at)
        ready[at] = characterise(x, at)

    while True:
        look(places)
        found = bool(ready.any())
        while ready.any():
            lowest = level[ready].min()
            for sub in range(4):
                here = np.flatnonzero(ready)
                here = here[(level[here] == lowest) & (((here // w - 1) % 2 * 2 + (here % w - 1) % 2) == sub)]
                if recheck == 4 and len(here):
                    # A diagonal neighbour may have changed since the point was looked at.
                    look(here)
                    here = here[ready[here]]
                if not len(here):
                    continue
                x.ravel()[here] = modify(x, here)
                if work:
                    work.changed += len(here)
                again = np.unique(np.concatenate([here, (here[:, None] + shifts).ravel()]))
                look(again[inside[again]])
        if not found or recheck == 8:
            return x[1:-1, 1:-1].copy()


def masks_at(x: np.ndarray, at: np.ndarray) -> np.ndarray:
    shifts = np.array([r * x.shape[1] + c for r, c in OFFSETS])
    return (x.ravel()[at[:, None] + shifts] * (1 << np.arange(8))).sum(1)


def thinning(image: np.ndarray, keep: np.ndarray | None, conn: str) -> tuple[Callable, Callable]:
    """Simple object points go, but for those to keep."""
    table = K.simple_table(conn)
    stay = np.pad(keep, 1).ravel() if keep is not None else np.zeros((image.shape[0] + 2) * (image.shape[1] + 2), bool)
    return (lambda x, at: x.ravel()[at] & ~stay[at] & table[masks_at(x, at)]), (lambda x, at: np.zeros(len(at), bool))


def gray_sinking(conn: str) -> tuple[Callable, Callable]:
    """Destructible points of a grayscale image sink to the highest strictly lower neighbour."""

    def sides(x, at):
        shifts = np.array([r * x.shape[1] + c for r, c in OFFSETS])
        return x.ravel()[at[:, None] + shifts]

    up, down = np.array(G.numbers(conn)[0]), np.array(G.numbers(G.dual(conn))[0])
    weights = 1 << np.arange(8)

    def characterise(x, at):
        near, own = sides(x, at), x.ravel()[at][:, None]
        return (up[((near >= own) * weights).sum(1)] == 1) & (down[((near < own) * weights).sum(1)] == 1)

    def modify(x, at):
        near, own = sides(x, at), x.ravel()[at][:, None]
        return np.where(near < own, near, -1).max(1)

    return characterise, modify


def skeleton(image: np.ndarray, conn: str = "8/4", recheck: int = 8, work: K.Work | None = None) -> np.ndarray:
    """The ultimate skeleton by the generic loop, nearest to the background first."""
    return stabilise(image, *thinning(image, None, conn), K.distance(~np.pad(image, 1))[1:-1, 1:-1], recheck, work)


def gray_kernel(f: np.ndarray, conn: str = "8/4", recheck: int = 8, work: K.Work | None = None) -> np.ndarray:
    """The homotopic kernel by the generic loop: only the frontier is characterised, lowest points first."""
    return stabilise(f, *gray_sinking(conn), None, recheck, work)
