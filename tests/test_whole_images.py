"""Images with ids of any size, texts as whole strips, passages wherever they stand, and cells outside a frame."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from rasterchain import kernels as K
from rasterchain import rasters
from rasterchain.chain import erosion
from rasterchain.exec import rounds
from rasterchain.exec.task import reduce_images
from rasterchain.layout import to_pixels, to_strips
from rasterchain.operators import morphology as M
from rasterchain.relational import QUERIES
from rasterchain.sources import files
from helpers import DATA
from test_execution import arrays, frame

IDS = (2**60 + 5, 7, -(2**63), 2**63 - 1, -3, 0)


@pytest.fixture(scope="module")
def many():
    rng = np.random.default_rng(9)
    return {i: rng.integers(0, 60, (14 + k, 9)) for k, i in enumerate(IDS)}


def test_ids_of_any_size(spark, many):
    df = frame(spark, many)
    out = arrays(M.chain(df, erosion(3), strategy="rounds", strip_rows=5, per_round=2))
    assert set(out) == set(IDS) and all((out[i] == K.filtered(a, 3)).all() for i, a in many.items())
    marker = {i: a - 9 for i, a in many.items()}
    for strategy in ("rounds", "frontier"):
        out = arrays(M.reconstruct(frame(spark, marker, many), strategy=strategy, strip_rows=4))
        assert set(out) == set(IDS) and all((out[i] == K.reconstruct(marker[i], a)[0]).all() for i, a in many.items())


def test_images_from_files_in_strips(spark, many, tmp_path):
    for k, a in enumerate(many.values()):
        (tmp_path / f"{k}.pgm").write_bytes(files.encode(a, "pgm"))
    df = files.read_images(spark, str(tmp_path)).drop("path")
    one, two = arrays(M.chain(df, erosion(2))), arrays(M.chain(df, erosion(2), strategy="rounds", strip_rows=4, per_round=1))
    assert len(one) == len(many) and all((one[i] == two[i]).all() for i in one) and set(one) == set(two)


def test_plan_of_rounds_does_not_grow(spark):
    serpentine = files.synthetic(spark, "serpentine", 6, 8)
    df = serpentine.selectExpr("img", "y", "x", "if(x = 0 and y = 0, 1L, 0L) as v", "v as m")
    done, lengths = rounds.until_stable(to_strips(df, 4), per_round=4)
    want, k = K.reconstruct(np.array([[int(y == x == 0) for x in range(6)] for y in range(8)]), arrays(serpentine)[0])
    assert k == 20 and lengths.collect()[0]["chain_len"] == k and (arrays(to_pixels(done))[0] == want).all()
    assert "Union" not in done._jdf.queryExecution().analyzed().toString() + lengths._jdf.queryExecution().analyzed().toString()


def test_texts_as_strips_equal_their_pixels(spark):
    texts = ["one two\nthree \t four " * 9, "é中😀 x", "", None, "y" * 64, "z" * 65]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    for ink in (False, True):
        pixels = arrays(rasters.wrapped_text(df, "doc_id", "text", 64, ink))
        strips = rasters.text_strips(df, "doc_id", "text", 64, ink)
        assert "Exchange" not in strips._jdf.queryExecution().executedPlan().toString()
        got = arrays(to_pixels(strips))
        assert set(got) == set(pixels) == {0, 1, 4, 5} and all((got[i] == a).all() for i, a in pixels.items())
        sums = {r["img"]: r["s"] for r in reduce_images(strips, lambda c: [(int(c["v"].sum()),)], "s bigint").collect()}
        assert sums == {i: a.sum() for i, a in pixels.items()}


@pytest.mark.parametrize("block", [1 << 22, 5])
def test_passages_wherever_they_stand(spark, block, monkeypatch):
    monkeypatch.setattr(rasters, "BLOCK", block)
    docs = spark.createDataFrame([(1, "aXaXa b aXa"), (2, "none"), (3, None), (4, "q b q")], "doc_id bigint, text string")
    quotes = spark.createDataFrame([("aXa",), ("b",), ("b",), ("",), (None,), ("aXa b",)], "quote string")
    got = {r["doc_id"]: sorted((s["a"], s["b"]) for s in r["spans"]) for r in rasters.quoted(docs, quotes).collect()}
    assert got == {1: [(0, 3), (2, 5), (2, 7), (6, 7), (8, 11)], 4: [(2, 3)]}
    assert rasters.quoted(docs, quotes.where("quote = 'zz'")).count() == 0


def test_cells_outside_a_frame(spark):
    cells = spark.createDataFrame([(0, 0, 0, 5), (0, -1, 2, 6)], "img bigint, y int, x int, v bigint")
    frame_of = spark.createDataFrame([(0, 2, 3)], "img bigint, height int, width int")
    with pytest.raises(Exception, match="before the frame"):
        rasters.densify(cells, frame_of).collect()


def test_gaps_of_rows_are_filled(spark):
    cells = spark.createDataFrame([(0, 0, 0, 5), (0, 0, 3, 6), (0, 2, 1, 7), (0, 2, 1, 8), (0, 2, 4, 9), (0, 9, 0, 1), (1, 0, 0, None), (None, 0, 0, 3), (3, 0, 0, 4)], "img bigint, y int, x int, v bigint")
    frame_of = spark.createDataFrame([(0, 3, 4), (1, 1, 2), (2, 2, 1), (None, 1, 2)], "img bigint, height int, width int")
    df = rasters.densify(cells, frame_of, 2)
    got = sorted(((-1 if r.img is None else r.img), r.y, r.x, r.v) for r in df.collect())
    full = {(i, y, x): [2] for i, h, w in ((-1, 1, 2), (0, 3, 4), (1, 1, 2), (2, 2, 1)) for y in range(h) for x in range(w)}
    full |= {(0, 0, 0): [5], (0, 0, 3): [6], (0, 2, 1): [7, 8]}  # cells beyond a frame, or of no image, are left out
    assert got == sorted((*k, v) for k, vs in full.items() for v in vs)
    assert dict(df.dtypes) == {"img": "bigint", "y": "int", "x": "int", "v": "bigint"}


def test_densifying_joins_nothing(spark):
    cells = spark.createDataFrame([(0, 0, 0, 5)], "img bigint, y int, x int, v bigint")
    df = rasters.densify(cells, spark.createDataFrame([(0, 2, 3)], "img bigint, height int, width int"))
    assert "Join" not in df._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("name", ["raster_event_value", "raster_events"])
def test_event_rasters_join_nothing(spark, name):
    plan = QUERIES[name](spark, DATA)._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan and "Window" in plan


@pytest.mark.parametrize("rows", [1, 3, 5, 4096])
def test_rows_begun_in_blocks(spark, rows, monkeypatch):
    monkeypatch.setattr(rasters, "ROWS", rows, raising=False)
    cells = spark.createDataFrame([(0, 4, 1, 5), (0, 5, 0, 6), (1, 0, 1, 7)], "img bigint, y int, x int, v bigint")
    frame_of = spark.createDataFrame([(0, 10, 2), (1, 1, 2), (2, 3, 1), (3, 0, 4)], "img bigint, height bigint, width bigint")
    full = {(i, y, x): 0 for i, h, w in ((0, 10, 2), (1, 1, 2), (2, 3, 1)) for y in range(h) for x in range(w)} | {(0, 4, 1): 5, (0, 5, 0): 6, (1, 0, 1): 7}
    df = rasters.densify(cells, frame_of)
    assert sorted(map(tuple, df.collect())) == sorted((*k, v) for k, v in full.items())


@pytest.mark.parametrize("name", ["raster_event_value", "raster_events"])
def test_no_task_begins_all_rows_of_event_rasters(spark, name):
    # what explode makes of one row is held at once; the frame is one row, so blocks of its rows are dealt to the tasks first
    plan = QUERIES[name](spark, DATA)._jdf.queryExecution().optimizedPlan().toString()
    made = plan[plan.index("Union") :]
    assert made.count("Generate explode") == 2 and "Repartition " in made[: made.rindex("Generate explode")]


@pytest.mark.parametrize("name", ["raster_event_value", "raster_events"])
def test_rows_of_event_rasters_are_filled_in_many_tasks(spark, name):
    # cells are small beside their pixels: by their bytes, Spark would join the tasks that make all pixels to a few
    assert QUERIES[name](spark, DATA).select(F.spark_partition_id()).distinct().count() > 2 * spark.sparkContext.defaultParallelism
