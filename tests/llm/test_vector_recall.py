"""Links of 12,000 vectors against brute force: differences in all directions, and in few."""

import numpy as np
import pytest

from rasterchain.llm import multi_index


def planted(rank, dim=32, n=12_000, seed=0):
    """Vectors within a space of so many dimensions; a quarter have partners near the threshold."""
    rng = np.random.default_rng(seed)
    space = np.linalg.qr(rng.normal(size=(dim, rank)))[0].T if rank < dim else np.eye(dim)
    x = rng.normal(size=(n, rank))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    some = rng.choice(n * 3 // 4, n // 4, replace=False)
    step = rng.normal(size=(n // 4, rank))
    step -= (step * x[some]).sum(1, keepdims=True) * x[some]
    step /= np.linalg.norm(step, axis=1, keepdims=True)
    cosine = rng.uniform(0.931, 0.96, (n // 4, 1))
    x[n * 3 // 4 :] = cosine * x[some] + np.sqrt(1 - cosine**2) * step
    labels = rng.integers(0, 3, n)
    labels[n * 3 // 4 :] = labels[some]
    return x @ space, labels


@pytest.mark.parametrize("rank", [4, 8, 32])
def test_recall(spark, rank):
    import pandas as pd

    x, labels = planted(rank)
    # ids of either sign
    ids = np.arange(len(x)) - 5000
    df = spark.createDataFrame(pd.DataFrame({"vec_id": ids, "embedding": x.tolist(), "label": labels}), "vec_id bigint, embedding array<double>, label int")
    got = multi_index.near_vectors(df.repartition(5)).toPandas().set_index("vec_id").loc[ids]
    want = np.zeros(len(x), np.int64)
    component = np.arange(len(x))
    for lab in range(3):
        mine = np.flatnonzero(labels == lab)
        near = x[mine] @ x[mine].T >= 0.93
        want[mine] = near.sum(1) - 1
        while True:
            new = np.array([component[mine[row]].min() for row in near])
            if (new == component[mine]).all():
                break
            component[mine] = new
    assert want.sum() >= 3000
    assert (got.n_links.to_numpy() <= want).all()
    assert got.n_links.sum() >= 0.997 * want.sum()
    assert (got.component_id.to_numpy() == ids[component]).mean() > 0.99


def test_copies_are_one_stored_vector(spark):
    rng = np.random.default_rng(1)
    v, far = rng.normal(size=16), rng.normal(size=16)
    rows = [(i - 3, v.tolist(), 1) for i in range(3000)] + [(5000, (v + 0.01).tolist(), 1), (5001, far.tolist(), 1), (None, v.tolist(), 1), (5002, v.tolist(), 2)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>, label int")
    assert multi_index.distinct_vectors(multi_index.prepared(df, "vec_id", "embedding", "label")).count() == 4
    got = {r["vec_id"]: (r["n_links"], r["component_id"], r["kept"]) for r in multi_index.near_vectors(df).collect()}
    assert got[0] == (3001, -3, False) and got[-3] == (3001, -3, True) and got[5000] == (3001, -3, False)
    assert got[5001] == (0, 5001, True) and got[5002] == (0, 5002, True) and got[None] == (3001, None, False)


def test_partitions_do_not_change_links(spark):
    x, labels = planted(8, n=2000, seed=3)
    df = spark.createDataFrame([(i, v.tolist(), int(k)) for i, (v, k) in enumerate(zip(x, labels, strict=True))], "vec_id bigint, embedding array<double>, label int")
    one, two = (sorted(map(tuple, multi_index.near_vectors(df.repartition(n)).collect())) for n in (1, 7))
    assert one == two
