"""Operators over strips, as the planner takes them for images beyond its limit, against whole images."""

import numpy as np
import pytest

from rasterchain import kernels as K
from rasterchain.operators import morphology as M
from rasterchain.plans import planner
from test_execution import arrays, frame

OPERATORS = {
    "hmax": lambda df, s: M.hmax(df, 7, strategy=s),
    "dome": lambda df, s: M.dome(df, 7, strategy=s),
    "hfill": lambda df, s: M.hfill(df, strategy=s),
    "raobj": lambda df, s: M.raobj(df, strategy=s),
    "open_rec": lambda df, s: M.open_rec(df, 2, strategy=s),
    "open": lambda df, s: M.open_(df, 2, strategy=s),
    "close": lambda df, s: M.close(df, 2, strategy=s),
    "asf": lambda df, s: M.asf(df, 2, strategy=s),
}


@pytest.fixture
def small_limits(monkeypatch):
    monkeypatch.setattr(planner, "TASK_BYTES", 100)
    monkeypatch.setattr(planner, "STRIP_BYTES", 8 * 9 * 8)


@pytest.mark.parametrize("name", sorted(OPERATORS))
def test_strips_equal_whole_images(spark, name, small_limits):
    rng = np.random.default_rng(2)
    df = frame(spark, {4: rng.integers(0, 30, (21, 9)), 6: rng.integers(0, 30, (17, 9))})
    plan = planner.planned(df)
    assert plan.strategy == "frontier" and plan.strip_rows < 21
    got, want = arrays(OPERATORS[name](df, "auto")), arrays(OPERATORS[name](df, "task"))
    assert set(got) == set(want) and all((got[i] == a).all() for i, a in want.items())


@pytest.mark.parametrize("family", ["open", "close"])
def test_spectra_of_strips(spark, family, small_limits):
    df = frame(spark, {1: np.random.default_rng(3).integers(0, 30, (19, 9))})
    got, want = (sorted(map(tuple, M.pattern_spectrum(df, 2, family, strategy=s).collect())) for s in ("auto", "task"))
    assert got == want


def test_small_images_stay_whole(spark):
    df = frame(spark, {1: np.arange(12).reshape(3, 4)})
    assert planner.planned(df).strategy == "task"
    assert "applyInArrow" not in M.hfill(df, strategy="auto")._jdf.queryExecution().analyzed().toString()


def test_whole_images_need_no_chain_length(spark):
    serpentine = np.array([[9 if y % 2 == 0 or x == (28 if y % 4 == 1 else 0) else 0 for x in range(29)] for y in range(41)])
    noisy = np.random.default_rng(5).integers(0, 30, (40, 29))
    images = {1: noisy, 2: np.pad(serpentine, ((9, 0), (0, 0)), constant_values=9)}
    got = arrays(M.open_rec(frame(spark, images), 1, strategy="auto"))
    for i, a in images.items():
        want, k = K.open_rec(a, 1)
        assert (got[i] == want).all()
        assert (K.rebuilt(K.filtered(a, 1), a) == want).all() and (i == 1 or k > 500)  # a long way, in few sweeps
