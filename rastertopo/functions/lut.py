"""Neighbourhood masks and the tables of connectivity numbers of the plane's two dual adjacency pairs.

Bit k of a mask is the neighbour ``OFFSETS[k]``, clockwise from the north. ``conn`` is "8/4" (object 8-adjacent,
background 4-adjacent) or "4/8".
"""

from __future__ import annotations

OFFSETS = ((-1, 0), (-1, 1), (0, 1), (1, 1), (1, 0), (1, -1), (0, -1), (-1, -1))
EDGES = (0, 2, 4, 6)
PAIRS = {"8/4": (8, 4), "4/8": (4, 8)}


def dual(conn: str) -> str:
    return {"8/4": "4/8", "4/8": "8/4"}[conn]


def components_near(mask: int, n: int) -> int:
    """The n-components of a mask's neighbours that are n-adjacent to the centre. For n = 4 only those with an edge neighbour count."""
    left, count = {k for k in range(8) if mask >> k & 1}, 0
    while left:
        part, grow = set(), [left.pop()]
        while grow:
            k = grow.pop()
            part.add(k)
            r, c = OFFSETS[k]
            near = {j for j in left if abs(OFFSETS[j][0] - r) + abs(OFFSETS[j][1] - c) == 1 or n == 8 and max(abs(OFFSETS[j][0] - r), abs(OFFSETS[j][1] - c)) == 1}
            left -= near
            grow += near
        count += n == 8 or any(k in EDGES for k in part)
    return count


def numbers(conn: str) -> tuple[list[int], list[int]]:
    """For each mask: the connectivity number of the object, and of the background (with the dual adjacency)."""
    n, m = PAIRS[conn]
    return [components_near(x, n) for x in range(256)], [components_near(255 - x, m) for x in range(256)]


def simple(conn: str) -> list[bool]:
    """Whether the centre of each mask is a simple point: both connectivity numbers are 1."""
    return [a == 1 == b for a, b in zip(*numbers(conn))]
