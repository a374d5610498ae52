"""Array kernels against definitions, fixtures and invariants."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from hypothesis.extra.numpy import arrays

from rastertopo.functions import gray as G
from rastertopo.functions import kernels as K
from rastertopo.functions import lut

IMAGES = arrays(bool, st.tuples(st.integers(1, 12), st.integers(1, 12)))
QUICK = settings(max_examples=25, deadline=None)

GLYPH = """
..........
.########.
.########.
.#########
.###..###.
.###..###.
.########.
.########.
.##.####..
..........
"""
SMOOTHED = {
    ("8/4", 1): "..........|..######..|.########.|.#########|.####.###.|.###..###.|.########.|.########.|..#.####..|..........",
    ("8/4", 2): "..........|..######..|.########.|.#########|.###..###.|.###.####.|.########.|..######..|....###...|..........",
    ("4/8", 1): "..........|..######..|.########.|.#########|.####.###.|.###..###.|.########.|.########.|..#.####..|..........",
    ("4/8", 2): "..........|..######..|.########.|.#########|.###..###.|.###.####.|.########.|.########.|..#.####..|..........",
}


def picture(text):
    return np.array([[c == "#" for c in line] for line in text.replace("|", "\n").split()])


def brute(f):
    r, c = np.indices(f.shape)
    out = np.full(f.shape, K.FAR)
    for a, b in np.argwhere(f):
        out = np.minimum(out, (r - a) ** 2 + (c - b) ** 2)
    return out


def test_lookup_tables():
    assert sum(lut.simple("8/4")) == sum(lut.simple("4/8")) == 116
    t, b = lut.numbers("8/4")
    t2, b2 = lut.numbers("4/8")
    assert all(t[m] == b2[255 - m] and b[m] == t2[255 - m] for m in range(256))


@pytest.mark.parametrize("conn", ["8/4", "4/8"])
def test_simple_is_the_global_definition(conn):
    """Removing the centre of a 3 x 3 picture keeps the components of both sides exactly for simple masks (within a frame)."""
    for mask, simple in enumerate(lut.simple(conn)):
        x = np.zeros((5, 5), bool)
        for k, (r, c) in enumerate(lut.OFFSETS):
            x[2 + r, 2 + c] = mask >> k & 1
        with_centre = x.copy()
        with_centre[2, 2] = True
        if simple:
            assert K.signature(with_centre, conn) == K.signature(x, conn)


def test_distance_fixture():
    f = np.zeros((5, 6), bool)
    f[1, 1] = f[3, 4] = True
    assert K.distance(f).tolist() == [[2, 1, 2, 5, 9, 10], [1, 0, 1, 4, 4, 5], [2, 1, 2, 2, 1, 2], [5, 4, 4, 1, 0, 1], [10, 9, 5, 2, 1, 2]]


@QUICK
@given(IMAGES)
def test_distances(f):
    exact = brute(f)
    assert (K.distance(f) == exact).all()
    assert (K.distance(f.T).T == exact).all()
    assert (K.capped_distance(f, 3) == np.where(exact <= 9, exact, K.FAR)).all()
    assert (K.propagated_distance(f, 8, exact=True) == exact).all()
    for approximate in (K.scan4_distance(f), K.scan3x3_distance(f), K.propagated_distance(f, 4), K.propagated_distance(f, 8)):
        assert (approximate >= exact).all() and ((approximate >= K.FAR) == (exact >= K.FAR)).all()
    row, col = K.nearest_feature(f)
    if f.any():
        r, c = np.indices(f.shape)
        assert ((r - row) ** 2 + (c - col) ** 2 == exact).all() and f[row, col].all()


@QUICK
@given(IMAGES)
def test_envelope_work_is_linear(f):
    work = K.Work()
    K.distance(f, work)
    assert work.envelope <= 2 * f.size


@QUICK
@given(IMAGES, st.sampled_from(["8/4", "4/8"]), st.integers(1, 3))
def test_filter_keeps_topology(x, conn, n):
    wide = np.pad(x, 2 * n + 2)
    out = K.hasf(wide, n, conn=conn)
    assert K.signature(out, conn) == K.signature(wide, conn)
    assert (K.cut(wide, n, conn=conn) <= wide).all() and (K.fill(wide, n, conn=conn) >= wide).all()


@QUICK
@given(IMAGES, IMAGES, st.sampled_from(["8/4", "4/8"]))
def test_constraints_hold(x, marks, conn):
    m = np.zeros_like(x)
    h, w = min(x.shape[0], marks.shape[0]), min(x.shape[1], marks.shape[1])
    m[:h, :w] = marks[:h, :w]
    wide, m = np.pad(x, 6), np.pad(m, 6)
    out = K.hasf(wide, 2, wide & m, ~wide & m, conn)
    assert (out[wide & m]).all() and not (out[~wide & m]).any()


@QUICK
@given(IMAGES, st.sampled_from(["8/4", "4/8"]))
def test_thinning_is_stable_and_constrained(x, conn):
    wide = np.pad(x, 1)
    d = K.distance(~wide)
    keep = d > 1
    out = K.thin(wide, keep, d, conn)
    assert (out >= (wide & keep)).all() and (out <= wide).all()
    assert not (K.simple_table(conn)[K.masks(out)] & out & ~keep).any()
    banded = K.zone_thin(wide, keep, d, conn)
    assert K.signature(banded, conn) == K.signature(wide, conn) == K.signature(out, conn)


def test_unsafe_deletion_loses_a_bar():
    bar = np.zeros((6, 8), bool)
    bar[2:4, 1:7] = True
    simple = K.simple_table("8/4")[K.masks(bar)] & bar
    assert (bar & ~simple).sum() == 0
    assert K.thin(bar, None, K.distance(~bar)).sum() == 1


@pytest.mark.parametrize("key", SMOOTHED)
def test_glyph(key):
    conn, n = key
    g = np.pad(picture(GLYPH), n + 1)
    out = K.hasf(g, n, conn=conn)
    assert (out[n + 1 : -n - 1, n + 1 : -n - 1] == picture(SMOOTHED[key])).all()
    assert K.signature(out, conn) == K.signature(g, conn) == (1, 2)
    assert K.signature(K.asf(g, n)) == (1, 1)


@QUICK
@given(IMAGES, st.integers(1, 3))
def test_morphology(x, r):
    wide = np.pad(x, 2 * r + 2)
    assert (K.opening(wide, r) <= wide).all() and (K.closing(wide, r) >= wide).all()
    assert (K.opening(K.opening(wide, r), r) == K.opening(wide, r)).all()
    assert (K.erosion(wide, r) == ~K.dilation(~np.pad(wide, r + 1), r)[r + 1 : -r - 1, r + 1 : -r - 1]).all()


GRAY5 = np.array([[0, 0, 0, 0, 0], [0, 3, 3, 3, 0], [0, 3, 1, 3, 0], [0, 3, 3, 2, 0], [0, 0, 0, 0, 0]])


def test_gray_fixture():
    t = G.gray_numbers(GRAY5)
    at = lambda r, c: tuple(int(x[r, c]) for x in t)
    assert [at(1, 1), at(1, 2), at(2, 2), at(3, 3), at(0, 0)] == [(0, 1, 1, 1), (0, 2, 2, 1), (1, 1, 0, 0), (1, 1, 1, 1), (1, 1, 0, 1)]
    kernel, steps = G.gray_kernel(GRAY5)
    assert kernel[2, 2] == 1 and steps == 8


@QUICK
@given(arrays(np.int64, st.tuples(st.integers(2, 9), st.integers(2, 9)), elements=st.integers(0, 4)), st.sampled_from(["8/4", "4/8"]))
def test_gray_operators_keep_sections(f, conn):
    for out in (G.gray_kernel(f, conn)[0], G.gray_skeleton(f, conn), G.restore_crests(f, conn)):
        for k in range(1, 5):
            assert K.signature(out >= k, conn) == K.signature(f >= k, conn)
    shed = G.watershed(f, conn)
    for k in range(1, 5):
        assert K.signature(shed >= k, conn)[1] == K.signature(f >= k, conn)[1]
