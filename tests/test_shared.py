import numpy as np
import pytest

from rasterchain import kernels as K
from rasterchain.exec.shared import SharedChain


@pytest.mark.parametrize("workers", [1, 3])
@pytest.mark.parametrize("kind", [np.uint8, np.float64])
def test_shared_chain(workers, kind):
    a = np.random.default_rng(workers).integers(0, 200, (37, 21)).astype(kind)
    with SharedChain(a.shape, kind, workers) as chain:
        for n, together, lo in ((1, 1, K.MIN), (7, 3, K.MAX), (20, 16, K.MIN), (0, 4, K.MIN)):
            got, took = chain.run(a, n, lo, together)
            assert (got == K.chain3(a, n, lo)).all() and took >= 0


def test_more_processes_than_rows():
    a = np.arange(12).reshape(2, 6)
    with SharedChain(a.shape, a.dtype, 5) as chain:
        assert (chain.run(a, 2)[0] == K.chain3(a, 2)).all()


@pytest.mark.parametrize("shape", [(1, 1), (1, 50), (50, 1), (33, 70)])
def test_column_tiles(shape):
    a = np.random.default_rng(8).integers(0, 99, shape)
    for n in (1, 5, 40):
        want = a
        for _ in range(n):
            want = K.sep3(want, K.MIN)
        for cols in (None, 1, 7, 64):
            assert (K.chain3(a, n, K.MIN, block_rows=9, together=4, block_cols=cols) == want).all()
