"""Array kernels on one image: exact and approximate distances, homotopic thinning, smoothing, components.

Images are boolean arrays (rows, columns); everything outside is background. Distances are squared integers; ``FAR``
stands for no feature at all. Kernels that count their work add to a ``Work`` object.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np

from .lut import OFFSETS, dual, simple

FAR = 1 << 40


@dataclass
class Work:
    """What a kernel did: simple-point tests, pixels changed, level steps, distance pixels, envelope operations, queue pushes."""

    characterised: int = 0
    changed: int = 0
    steps: int = 0
    distance_pixels: int = 0
    envelope: int = 0
    pushed: int = 0
    queue_high: int = 0
    seconds: dict = field(default_factory=dict)

    def timed(self, phase: str, began: float) -> None:
        self.seconds[phase] = self.seconds.get(phase, 0.0) + time.perf_counter() - began


_TABLES: dict[str, np.ndarray] = {}


def simple_table(conn: str) -> np.ndarray:
    if conn not in _TABLES:
        _TABLES[conn] = np.array(simple(conn))
    return _TABLES[conn]


def masks(image: np.ndarray) -> np.ndarray:
    """The 8-bit neighbourhood mask of every pixel."""
    p = np.pad(image, 1).astype(np.uint8)
    h, w = image.shape
    out = np.zeros((h, w), np.uint8)
    for k, (r, c) in enumerate(OFFSETS):
        out |= p[1 + r : 1 + r + h, 1 + c : 1 + c + w] << np.uint8(k)
    return out


# ---- distances ----


def column_gaps(features: np.ndarray) -> np.ndarray:
    """For each pixel the vertical distance to the nearest feature of its column (FAR if none): one scan down, one up."""
    h = features.shape[0]
    rows = np.arange(h)[:, None]
    above = np.maximum.accumulate(np.where(features, rows, -FAR), axis=0)
    below = np.minimum.accumulate(np.where(features, rows, FAR)[::-1], axis=0)[::-1]
    gaps = np.minimum(rows - above, below - rows)
    return np.where(gaps > FAR // 2, FAR, gaps)


def lower_envelope(gaps: np.ndarray, work: Work | None = None) -> np.ndarray:
    """Squared distances along a row from the gaps of its columns: the lower envelope of parabolas.

    A stack holds the columns whose parabola is lowest somewhere, with the place from which it is; each column is
    pushed and popped once at most."""
    m = len(gaps)
    sites = np.nonzero(gaps < FAR)[0].tolist()
    if not sites:
        return np.full(m, FAR)
    # A gap below FAR is a number of rows, whose square fits 64 bits up to 2**31 rows.
    squares = [g * g if g < FAR else 0 for g in gaps.tolist()]
    stack, starts, operations = [], [], 0
    for u in sites:
        start = 0
        while stack:
            i = stack[-1]
            # The first place where u's parabola is below i's.
            start = (u * u - i * i + squares[u] - squares[i]) // (2 * (u - i)) + 1
            if start > starts[-1]:
                break
            stack.pop()
            starts.pop()
            operations += 1
            start = 0
        if start < m:
            stack.append(u)
            starts.append(max(start, 0))
            operations += 1
    if work:
        work.envelope += operations
    owner = np.repeat(stack, np.diff([*starts, m]))
    return (np.arange(m) - owner) ** 2 + np.array(squares, np.int64)[owner]


def distance(features: np.ndarray, work: Work | None = None) -> np.ndarray:
    """The exact squared Euclidean distance to the nearest feature: columns, then rows."""
    gaps = column_gaps(features)
    if work:
        work.distance_pixels += features.size
    return np.stack([lower_envelope(g, work) for g in gaps]) if features.size else np.zeros(features.shape, np.int64)


def capped_distance(features: np.ndarray, radius: int) -> np.ndarray:
    """Exact squared distances up to radius squared, FAR beyond: each row takes the least over 2 * radius + 1 columns."""
    h, w = features.shape
    gaps = column_gaps(features)
    base = np.where(gaps <= radius, gaps * gaps, FAR)
    out = base.copy()
    for d in range(1, min(radius, w - 1) + 1):
        np.minimum(out[:, d:], base[:, :-d] + d * d, out=out[:, d:])
        np.minimum(out[:, :-d], base[:, d:] + d * d, out=out[:, :-d])
    return np.where(out <= radius * radius, out, FAR)


def nearest_feature(features: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Row and column of the nearest feature (ties: lowest column, then lowest row), -1 if there is none."""
    h, w = features.shape
    rows = np.arange(h)[:, None]
    above = np.maximum.accumulate(np.where(features, rows, -FAR), axis=0)
    below = np.minimum.accumulate(np.where(features, rows, FAR)[::-1], axis=0)[::-1]
    use_above = rows - above <= below - rows
    source = np.where(use_above, above, below)
    gaps = np.minimum(np.minimum(rows - above, below - rows), 1 << 19)
    place = np.arange(w)
    cost = (place[:, None] - place[None, :]) ** 2
    col = np.stack([np.argmin(cost + (g * g)[None, :], axis=1) for g in gaps])
    row = np.take_along_axis(source, col, 1)
    none = ~features.any()
    return (np.full((h, w), -1), np.full((h, w), -1)) if none else (row, col)


def _square(r: np.ndarray, c: np.ndarray) -> np.ndarray:
    return r.astype(np.int64) ** 2 + c.astype(np.int64) ** 2


def scan4_distance(features: np.ndarray) -> np.ndarray:
    """Vector raster scan over the 4-neighbourhood: two sweeps of (row, column) vectors to the presumed nearest feature."""
    h, w = features.shape
    big = 1 << 19
    vr, vc = np.where(features, 0, big), np.where(features, 0, big)

    def rows_pass(order, step):
        previous = None
        for r in order:
            if previous is not None:
                cr, cc = vr[previous] + 1, vc[previous]
                better = cr * cr + cc * cc < vr[r] ** 2 + vc[r] ** 2
                vr[r], vc[r] = np.where(better, cr, vr[r]), np.where(better, cc, vc[r])
            for cols in (range(1, w), range(w - 2, -1, -1)):
                back = -1 if cols.step == 1 else 1
                rr, rc = vr[r].tolist(), vc[r].tolist()
                for c in cols:
                    a, b = rr[c + back], rc[c + back] + 1
                    if a * a + b * b < rr[c] * rr[c] + rc[c] * rc[c]:
                        rr[c], rc[c] = a, b
                vr[r], vc[r] = rr, rc
            previous = r

    rows_pass(range(h), 1)
    rows_pass(range(h - 1, -1, -1), -1)
    out = _square(vr, vc)
    return np.where((vr >= big) | (vc >= big), FAR, out)


def scan3x3_distance(features: np.ndarray) -> np.ndarray:
    """Two sweeps that hand squared distances on within a 3 x 3 window, from the steps made so far (strong data dependence)."""
    h, w = features.shape
    big = 1 << 19
    vr, vc = np.where(features, 0, big).tolist(), np.where(features, 0, big).tolist()

    def relax(r, c, near):
        best = vr[r][c] ** 2 + vc[r][c] ** 2
        for dr, dc in near:
            y, x = r + dr, c + dc
            if 0 <= y < h and 0 <= x < w:
                a, b = vr[y][x] + abs(dr), vc[y][x] + abs(dc)
                if a * a + b * b < best:
                    best, vr[r][c], vc[r][c] = a * a + b * b, a, b

    ahead = ((-1, -1), (-1, 0), (-1, 1), (0, -1))
    for r in range(h):
        for c in range(w):
            relax(r, c, ahead)
    for r in range(h - 1, -1, -1):
        for c in range(w - 1, -1, -1):
            relax(r, c, [(-a, -b) for a, b in ahead])
    vr, vc = np.array(vr), np.array(vc)
    return np.where((vr >= big) | (vc >= big), FAR, _square(vr, vc)) if features.size else np.zeros((h, w), np.int64)


def propagated_distance(features: np.ndarray, near: int = 4, exact: bool = False, work: Work | None = None) -> np.ndarray:
    """Ordered propagation of nearest sources from bucket to bucket of increasing squared distance.

    ``near`` 4 or 8: the neighbours that a pixel hands its source to. ``exact`` goes on with ever larger neighbourhoods
    until no pixel gets nearer: an error needs a source cell thinner than the neighbourhood, at a distance that grows with it."""
    h, w = features.shape
    out = np.where(features, 0, FAR)
    rows, cols = np.indices((h, w))
    sr, sc = np.where(features, rows, -1), np.where(features, cols, -1)
    if not features.any():
        return out
    offsets = [OFFSETS[k] for k in ((0, 2, 4, 6) if near == 4 else range(8))]
    buckets: dict[int, list[np.ndarray]] = {0: [np.flatnonzero(features)]}
    flat, fr, fc = out.ravel(), sr.ravel(), sc.ravel()
    level = 0
    while buckets:
        level = min(buckets)
        at = np.unique(np.concatenate(buckets.pop(level)))
        at = at[flat[at] == level]
        if work:
            work.pushed += len(at)
            work.queue_high = max(work.queue_high, sum(len(x) for b in buckets.values() for x in b) + len(at))
        for dr, dc in offsets:
            y, x = at // w + dr, at % w + dc
            ok = (y >= 0) & (y < h) & (x >= 0) & (x < w)
            y, x, r, c = y[ok], x[ok], fr[at[ok]], fc[at[ok]]
            d = (y - r) ** 2 + (x - c) ** 2
            to = y * w + x
            better = d < flat[to]
            to, d, r, c = to[better], d[better], r[better], c[better]
            flat[to], fr[to], fc[to] = d, r, c
            if work:
                work.distance_pixels += len(ok)
            for value in np.unique(d):
                buckets.setdefault(int(value), []).append(to[d == value])
    reach = 2
    while exact:
        changed = False
        source_r, source_c = fr.reshape(h, w), fc.reshape(h, w)
        best = flat.reshape(h, w)
        for dr in range(-reach, reach + 1):
            for dc in range(-reach, reach + 1):
                if max(abs(dr), abs(dc)) != reach or abs(dr) >= h or abs(dc) >= w:
                    continue
                to = (slice(max(dr, 0), h + min(dr, 0)), slice(max(dc, 0), w + min(dc, 0)))
                frm = (slice(max(-dr, 0), h + min(-dr, 0)), slice(max(-dc, 0), w + min(-dc, 0)))
                d = (rows[to] - source_r[frm]) ** 2 + (cols[to] - source_c[frm]) ** 2
                better = d < best[to]
                if better.any():
                    changed = True
                    best[to] = np.where(better, d, best[to])
                    source_r[to] = np.where(better, source_r[frm], source_r[to])
                    source_c[to] = np.where(better, source_c[frm], source_c[to])
        # A pixel may still miss its source if the band it would come through is farther than reach; stop when that is impossible.
        if not changed and reach * reach >= int(np.sqrt(best.max())) + 1:
            break
        reach += 1
        if reach > max(h, w):
            break
    return flat.reshape(h, w)


# ---- homotopic operators ----


def thin(image: np.ndarray, keep: np.ndarray | None, priority: np.ndarray, conn: str = "8/4", max_steps: int | None = None, work: Work | None = None) -> np.ndarray:
    """Constrained homotopic thinning in the canonical order.

    Until no pixel can go: of the deletable pixels take the least priority, and delete those of that priority in the
    four parity subfields in turn. Two pixels of a subfield are never adjacent, so this equals deleting one by one."""
    table = simple_table(conn)
    x = np.pad(image, 1)
    h, w = x.shape
    free = np.zeros_like(x)
    free[1:-1, 1:-1] = ~keep if keep is not None else True
    level_of = np.full(x.shape, FAR)
    level_of[1:-1, 1:-1] = priority
    flat, level_flat = x.ravel(), level_of.ravel()
    places = np.flatnonzero((x & free).ravel())
    shifts = np.array([r * w + c for r, c in OFFSETS])
    weights = (1 << np.arange(8)).astype(np.uint8)
    rows, cols = places // w - 1, places % w - 1
    sub = ((rows % 2) * 2 + cols % 2).astype(np.int8)
    sub_of = np.zeros(h * w, np.int8)
    sub_of[places] = sub
    free_flat = np.zeros(h * w, bool)
    free_flat[places] = True
    ok = np.zeros(h * w, bool)

    def test(at: np.ndarray) -> None:
        began = time.perf_counter()
        m = (flat[at[:, None] + shifts] * weights).sum(1, dtype=np.uint8)
        ok[at] = table[m]
        if work:
            work.characterised += len(at)
            work.timed("characterise", began)

    test(places)
    # Levels in order; a level's heap entry is found anew each time, as lower levels may come back.
    open_places = places
    step = 0
    while max_steps is None or step < max_steps:
        live = open_places[ok[open_places] & flat[open_places]]
        if not len(live):
            break
        levels = level_flat[live]
        level = levels.min()
        step += 1
        if work:
            work.steps += 1
        for s in range(4):
            now = open_places[(level_flat[open_places] == level) & (sub_of[open_places] == s)]
            now = now[ok[now] & flat[now]]
            if len(now):
                flat[now] = False
                if work:
                    work.changed += len(now)
                again = (now[:, None] + shifts).ravel()
                again = again[free_flat[again] & flat[again]]
                if work:
                    # A pixel tested twice counts once.
                    again = np.unique(again)
                    work.pushed += len(again)
                if len(again):
                    test(again)
        open_places = open_places[flat[open_places]]
    return x[1:-1, 1:-1].copy()


def thicken(image: np.ndarray, allow: np.ndarray | None, priority: np.ndarray, conn: str = "8/4", max_steps: int | None = None, work: Work | None = None) -> np.ndarray:
    """Constrained homotopic thickening: thinning of the complement with the dual adjacency. The array's border stays as it is."""
    keep = np.ones(image.shape, bool)
    keep[1:-1, 1:-1] = ~allow[1:-1, 1:-1] if allow is not None else False
    h, w = image.shape
    # The complement is object outside, too: the border ring is kept, so the outside stays one component.
    return ~thin_framed(~image, keep, priority, dual(conn), max_steps, work)


def thin_framed(image, keep, priority, conn, max_steps, work):
    """Thinning of an image whose border ring is kept; the outside never matters, as no pixel of the ring is tested."""
    return thin(image, keep, priority, conn, max_steps, work)


def union_keep(*parts) -> np.ndarray | None:
    out = None
    for p in parts:
        if p is not None:
            out = p if out is None else out | p
    return out


def measured_distance(features: np.ndarray, radius: int, work: Work | None) -> np.ndarray:
    began = time.perf_counter()
    out = capped_distance(features, radius)
    if work:
        work.distance_pixels += features.size
        work.timed("distance", began)
    return out


def cut(image: np.ndarray, n: int, c: np.ndarray | None = None, conn: str = "8/4", work: Work | None = None) -> np.ndarray:
    """Homotopic cutting of radius n: thin to the erosion (and C), then thicken within the dilation, inside the image."""
    inner = measured_distance(~image, n, work)
    y = thin(image, union_keep(inner == FAR, c), inner, conn, None, work)
    outer = measured_distance(y, n, work)
    return thicken(y, (outer < FAR) & image & ~y, outer, conn, None, work)


def fill(image: np.ndarray, n: int, d: np.ndarray | None = None, conn: str = "8/4", work: Work | None = None) -> np.ndarray:
    """Homotopic filling of radius n: thicken to the dilation (without D), then thin to the erosion and the image."""
    outer = measured_distance(image, n, work)
    allow = (outer < FAR) & ~image
    z = thicken(image, allow & ~d if d is not None else allow, outer, conn, None, work)
    inner = measured_distance(~z, n, work)
    return thin(z, (inner == FAR) | image, inner, conn, None, work)


def hasf(image: np.ndarray, n: int, c=None, d=None, conn: str = "8/4", work: Work | None = None) -> np.ndarray:
    """The homotopic alternating sequential filter: cut and fill of radius 1, 2, ..., n."""
    for radius in range(1, n + 1):
        image = fill(cut(image, radius, c, conn, work), radius, d, conn, work)
    return image


def asf(image: np.ndarray, n: int) -> np.ndarray:
    """The plain alternating sequential filter: opening and closing of radius 1, ..., n, without regard to topology."""
    for r in range(1, n + 1):
        image = closing(opening(image, r), r)
    return image


def erosion(image: np.ndarray, r: int) -> np.ndarray:
    return image & (capped_distance(np.pad(~image, r + 1, constant_values=True), r)[r + 1 : -r - 1, r + 1 : -r - 1] == FAR)


def dilation(image: np.ndarray, r: int) -> np.ndarray:
    return capped_distance(image, r) < FAR


def opening(image: np.ndarray, r: int) -> np.ndarray:
    return dilation(erosion(image, r), r)


def closing(image: np.ndarray, r: int) -> np.ndarray:
    wide = np.pad(image, r + 1)
    return erosion(dilation(wide, r), r)[r + 1 : -r - 1, r + 1 : -r - 1]


def zone_thin(image: np.ndarray, keep: np.ndarray | None, priority: np.ndarray, conn: str = "8/4", half_rows: int = 3, work: Work | None = None) -> np.ndarray:
    """Thinning by row bands: the halves of all zones of 2 * half_rows rows work in turn, each on the state before its phase.

    Two active halves are half_rows rows apart, so what they delete never meets. Within a half, pixels go one by one in
    the order of priority, row, column. The result keeps the topology; it isn't that of the canonical order."""
    table, x = simple_table(conn), np.pad(image, 1)
    h, w = x.shape
    free = np.zeros_like(x)
    free[1:-1, 1:-1] = ~keep if keep is not None else True
    flat = x.ravel()
    shifts = [r * w + c for r, c in OFFSETS]
    order = np.full(x.shape, FAR)
    order[1:-1, 1:-1] = priority
    order = order.ravel()
    half_of = (np.arange(h) - 1) // half_rows % 2
    waiting = np.flatnonzero((x & free).ravel())
    changed = True
    while changed:
        changed = False
        for phase in (0, 1):
            mine = waiting[(half_of[waiting // w] == phase) & flat[waiting]]
            # One after the other within the phase: halves of the same phase don't see each other.
            for p in mine[np.lexsort((mine, order[mine]))].tolist():
                if work:
                    work.characterised += 1
                m = 0
                for k, s in enumerate(shifts):
                    m |= int(flat[p + s]) << k
                if table[m]:
                    flat[p] = False
                    changed = True
                    if work:
                        work.changed += 1
        waiting = waiting[flat[waiting]]
    return x[1:-1, 1:-1].copy()


# ---- components and signatures ----


def label(image: np.ndarray, n: int) -> np.ndarray:
    """n-components: each object pixel gets the least index (row-major) of its component, others -1."""
    h, w = image.shape
    out = np.where(image, np.arange(h * w).reshape(h, w), FAR)
    pads = [(r, c) for k, (r, c) in enumerate(OFFSETS) if n == 8 or k % 2 == 0]
    while True:
        p = np.pad(out, 1, constant_values=FAR)
        new = out
        for r, c in pads:
            new = np.minimum(new, p[1 + r : 1 + r + h, 1 + c : 1 + c + w])
        new = np.where(image, new, FAR)
        # Jump to the label of the label.
        flat = new.ravel()
        ok = flat < FAR
        flat = flat.copy()
        flat[ok] = flat[flat[ok]]
        new = flat.reshape(h, w)
        if (new == out).all():
            return np.where(image, out, -1)
        out = new


def signature(image: np.ndarray, conn: str = "8/4") -> tuple[int, int]:
    """The numbers of object and of background components; the outside belongs to the background."""
    n, m = (8, 4) if conn == "8/4" else (4, 8)
    count = lambda x: len(np.unique(x[x >= 0]))
    return count(label(image, n)), count(label(~np.pad(image, 1), m))


def component_rows(image: np.ndarray, n: int) -> np.ndarray:
    """For each n-component of the object the row of its first run: components of runs, joined by least labels and jumps."""
    h, w = image.shape
    edge = np.diff(np.pad(image, ((0, 0), (1, 1))).astype(np.int8), axis=1)
    rows, start = np.nonzero(edge == 1)
    end = np.nonzero(edge == -1)[1] - 1
    if not len(rows):
        return rows
    # Rows lie so far apart in one order of keys that a run meets only those of the row below.
    pitch, reach = w + 3, 1 if n == 8 else 0
    starts, ends = rows * pitch + start, rows * pitch + end
    low, high = np.searchsorted(ends, starts + pitch - reach), np.searchsorted(starts, ends + pitch + reach, "right")
    count = high - low
    a = np.repeat(np.arange(len(rows)), count)
    b = np.arange(len(a)) - np.repeat(np.cumsum(count) - count, count) + np.repeat(low, count)
    root = np.arange(len(rows))
    while True:
        x, y = root[a], root[b]
        apart = x != y
        if not apart.any():
            return rows[root == np.arange(len(rows))]
        a, b, x, y = a[apart], b[apart], x[apart], y[apart]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while ((further := root[root]) != root).any():
            root = further


def signatures(image: np.ndarray, owner: np.ndarray, images: int, conn: str = "8/4") -> np.ndarray:
    """The signature of each of several images stacked by rows: object components, and background components but for the
    one outside. ``owner`` gives the image of each row; background rows lie between images."""
    n, m = (8, 4) if conn == "8/4" else (4, 8)
    objects = component_rows(image, n)
    # The frame joins all outsides to the component of its first row.
    holes = component_rows(np.pad(~image, 1, constant_values=True), m)[1:] - 1
    return np.stack([np.bincount(owner[x], minlength=images) for x in (objects, holes)], 1)
