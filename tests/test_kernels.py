import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from hypothesis.extra import numpy as hnp

from rasterchain import dtypes, schedule, streamk
from rasterchain import kernels as K

images = hnp.arrays(np.int64, hnp.array_shapes(min_dims=2, max_dims=2, min_side=1, max_side=12), elements=st.integers(0, 40))
both = pytest.mark.parametrize("lo", [K.MIN, K.MAX], ids=["min", "max"])


def brute(a, s, lo):
    out = np.empty_like(a)
    for y in range(a.shape[0]):
        for x in range(a.shape[1]):
            w = a[max(0, y - s) : y + s + 1, max(0, x - s) : x + s + 1]
            out[y, x] = w.min() if lo is K.MIN else w.max()
    return out


@both
@given(images, st.integers(0, 6))
@settings(max_examples=40, deadline=None)
def test_methods_agree_with_brute_force(lo, a, s):
    for method in ("auto", "chain", "segments", "prefix_suffix", "queue", "direct"):
        assert (K.filtered(a, s, lo, method) == brute(a, s, lo)).all(), method
    assert (K.chords(a, np.ones((2 * s + 1,) * 2, bool), lo) == brute(a, s, lo)).all()


@pytest.mark.parametrize("dtype", dtypes.NUMPY)
@both
def test_types_and_strides(dtype, lo):
    rng = np.random.default_rng(0)
    step = dtypes.stride(dtype)
    for w in (1, 2, 3, step - 1, step, step + 1, 2 * step + 3):
        a = rng.integers(0, 100, (5, max(w, 1))).astype(dtypes.NUMPY[dtype])
        a[0, 0], a[-1, -1] = dtypes.highest(a.dtype), dtypes.lowest(a.dtype)
        expected = brute(a, 1, lo)
        for k in (1, 3, step):
            assert (K.cols3_inplace(K.rows3_inplace(a.copy(), k, lo), lo) == expected).all()
        assert (K.sep3(a, lo, "xy") == expected).all() and (K.sep3(a, lo, "yx") == expected).all()
        assert (np.array(list(streamk.min3_rows(iter(a), lo))) == expected).all()
        assert (K.chain3(a, 7, lo, 2, 3) == brute(a, 7, lo)).all()


@given(images)
@settings(max_examples=40, deadline=None)
def test_laws(a):
    e, d = K.filtered(a, 1, K.MIN), K.filtered(a, 1, K.MAX)
    assert (e <= a).all() and (a <= d).all()
    assert (d == -K.filtered(-a, 1, K.MIN)).all()
    o, c = K.opened(a, 2), K.closed(a, 2)
    assert (o <= a).all() and (a <= c).all()
    assert (K.opened(o, 2) == o).all() and (K.closed(c, 2) == c).all()
    assert (K.filtered(K.filtered(a, 2), 3) == K.filtered(a, 5)).all()
    m, _ = K.hmax(a, 3)
    assert (m <= a).all() and (a - m <= 3).all() and (a - m >= 0).all()
    f, _ = K.hfill(a)
    assert (f >= a).all()
    r, _ = K.raobj(a)
    assert (r >= 0).all()
    assert (K.reconstruct(f, a, K.MIN)[0] == f).all()
    g = K.granulometry(a, 4)
    assert all(x >= y for x, y in zip(g, g[1:], strict=False))
    assert (K.asf(a, 3) == K.asf(a, 3, fused=True)).all()
    dist, res, _ = K.residuals(a)
    flat, length = K.lipschitz(dist)
    assert (flat == K.lipschitz_closed(dist)).all() and (K.lipschitz_step(flat) == flat).all()
    d2, r2, _ = K.residuals(a, conditional=False, early=False)
    assert (dist == d2).all() and (res == r2).all()


@given(images, st.integers(0, 1000), st.sampled_from([K.MIN, K.MAX]))
@settings(max_examples=40, deadline=None)
def test_heap_reconstruction_of_any_marker(a, seed, lo):
    mask = np.random.default_rng(seed).integers(0, 40, a.shape)
    assert (K.reconstruct(a, mask, lo)[0] == K.reconstruct_heap(a, mask, lo)).all()


def test_holes_and_border_objects():
    a = np.full((9, 9), 5)
    a[4, 4] = 1
    assert (K.hfill(a)[0] == 5).all()
    a = np.full((9, 9), 5)
    a[4, 0:5] = 1
    assert (K.hfill(a)[0] == a).all()  # the pit reaches the border
    b = np.zeros((9, 9), int)
    b[0:3, 4], b[5:7, 5:7] = 7, 7
    r = K.raobj(b)[0]
    assert (r[0:3] == 0).all() and (r[5:7, 5:7] == 7).all()


@pytest.mark.parametrize("shape", [(1, 9), (9, 1)])
def test_peaks_on_thin_images(shape):
    a = np.zeros(9, int)
    a[2], a[6] = 2, 5
    assert K.hmax(a.reshape(shape), 3)[0].max() == 2 and (K.hmax(a.reshape(shape), 3)[0].ravel()[[2]] == 0).all()


def test_serpentine_is_the_longest_path():
    h = w = 9
    a = np.ones((h, w), int)
    for y in range(1, h, 2):
        a[y] = 0
        a[y, -1 if y % 4 == 1 else 0] = 1
    marker = np.zeros_like(a)
    marker[0, 0] = 1
    out, k = K.reconstruct(marker, a)
    assert (out == a).all() and k > 2 * w


def test_saturation_differs_only_below_h():
    a = np.array([[1, 9, 1], [1, 1, 1]], np.uint8)
    assert K.hmax(a, 4, "real")[0].tolist() == [[1, 5, 1], [1, 1, 1]]
    low = np.array([[1, 0, 2]], np.uint8)
    assert K.hmax(low, 4, "real")[0].max() == -2 and K.hmax(low, 4, "saturate")[0].max() == 0
    assert K.hmax(a, 4, "saturate")[0].tolist() == [[1, 5, 1], [1, 1, 1]]


def test_streaming_chain_holds_the_schedule():
    a = np.random.default_rng(2).integers(0, 99, (20, 7))
    kinds = ["MIN3", "MAX3", "MAX3", "MIN3"]
    expected = a
    for k in kinds:
        expected = K.sep3(expected, K.MIN if k == "MIN3" else K.MAX)
    counter = {}
    assert (np.array(list(streamk.pipeline(iter(a), kinds, counter))) == expected).all()
    assert counter["comparisons"] == 4 * a.size * len(kinds)
    assert (streamk.blocks(a, kinds, 3) == expected).all()
    mask = np.random.default_rng(3).integers(0, 99, a.shape)
    geo = np.array([r for r, _ in streamk.geo3_rows(zip(a, mask, strict=True))])
    assert (geo == K.geodesic(a, mask)).all()
    d, r, _ = K.residuals(a, early=False)
    rows = ((row, np.zeros(7, int), np.zeros(7, int)) for row in a)
    for j in range(1, max(a.shape) + 1):
        rows = streamk.residual_rows(rows, j)
    got = list(rows)
    assert (np.array([x[1] for x in got]) == d).all() and (np.array([x[2] for x in got]) == r).all()
    assert (np.array(list(streamk.lip3_rows(iter(d)))) == K.lipschitz_step(d)).all()


def test_schedule():
    assert [schedule.assign(j, 3) for j in (1, 3, 4, 7)] == [(1, 0), (3, 0), (1, 1), (1, 2)]
    order = schedule.run_order(9, 5, 4)
    seen = {}
    for j, row in order:
        assert j == 1 or seen.get(j - 1, 0) >= min(row + 2, 5)
        seen[j] = row + 1
    assert len(order) == 45


def test_three_axes():
    a = np.random.default_rng(1).integers(0, 50, (4, 5, 6))
    out = K.sep3(a)
    assert out[2, 2, 2] == a[1:4, 1:4, 1:4].min() and out[0, 0, 0] == a[:2, :2, :2].min()


@pytest.mark.parametrize("lo", [K.MIN, K.MAX])
@pytest.mark.parametrize("rows,pixels", [(1024, 1 << 20), (1, 1), (3, 40)])
def test_sweeps_reach_the_limit(lo, rows, pixels):
    rng = np.random.default_rng(8)
    for shape in ((1, 1), (1, 17), (23, 1), (31, 14)):
        for kind in (np.int64, np.float64, np.uint8):
            a, m = (rng.integers(0, 20, shape).astype(kind) for _ in range(2))
            m = np.where(rng.random(shape) < 0.3, m, 0 if lo is K.MAX else 19).astype(kind)
            want = K.reconstruct(a, m, lo)[0]
            first = K.geodesic(a, m, lo)
            assert (K.rebuilt(a, m, lo) == want).all() and (K.settled(first, m, lo, rows=rows, pixels=pixels) == want).all()
            if shape[0] > 3:  # a strip between settled neighbours
                part = K.settled(first[2:-1], m[2:-1], lo, want[1], want[-1], rows, pixels)
                assert (part == want[2:-1]).all()
