import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from rasterchain import kernels as K
from rasterchain.chain import erosion
from rasterchain.exec import frontier, rounds
from rasterchain.exec.task import map_images
from rasterchain.layout import map_strips, to_pixels, to_strips
from rasterchain.operators import morphology as M
from rasterchain.sources import files
from rasterchain.streaming import rows as streaming


def frame(spark, arrays: dict[int, np.ndarray], mask: dict[int, np.ndarray] | None = None):
    rows = [(i, y, x, int(v), *([int(mask[i][y, x])] if mask else [])) for i, a in arrays.items() for (y, x), v in np.ndenumerate(a)]
    return spark.createDataFrame(rows, "img bigint, y int, x int, v bigint" + (", m bigint" if mask else ""))


def arrays(df) -> dict[int, np.ndarray]:
    out = {}
    for img, g in df.toPandas().groupby("img"):
        a = np.full((g.y.max() + 1, g.x.max() + 1), -999)
        a[g.y, g.x] = g.v
        out[img] = a
    return out


@pytest.fixture(scope="module")
def two():
    rng = np.random.default_rng(4)
    return {3: rng.integers(0, 60, (23, 9)), 8: rng.integers(0, 60, (7, 31))}


@pytest.mark.parametrize("rows,k", [(4, 2), (5, 5), (64, 8)])
def test_rounds_equal_task(spark, two, rows, k):
    df = frame(spark, two)
    out = arrays(to_pixels(rounds.run_chain(to_strips(df, rows), erosion(6), k)))
    assert all((out[i] == K.filtered(a, 6)).all() for i, a in two.items())


def test_reconstruction_by_every_strategy(spark, two):
    rng = np.random.default_rng(5)
    marker = {i: rng.integers(0, 60, a.shape) for i, a in two.items()}  # crosses the mask
    df = frame(spark, marker, two)
    strips = to_strips(df, 5)
    done, lengths = rounds.until_stable(strips, per_round=3)
    got, front = arrays(to_pixels(done)), arrays(to_pixels(frontier.until_stable(strips)[0]))
    length = {r["img"]: r["chain_len"] for r in lengths.collect()}
    for i, a in two.items():
        expected, k = K.reconstruct(marker[i], a)
        assert (got[i] == expected).all() and (front[i] == expected).all() and length[i] == k


def test_order_of_rows_does_not_matter(spark, two):
    df = frame(spark, two).orderBy(F.rand(1)).repartition(7)
    out = arrays(M.erode(df, 2))
    assert all((out[i] == K.filtered(a, 2)).all() for i, a in two.items())


def test_gaps_and_nulls_are_errors(spark, two):
    df = frame(spark, two)
    with pytest.raises(Exception, match="not dense"):
        M.erode(df.where("not (img = 3 and x = 2 and y = 2)"), 1).collect()
    with pytest.raises(Exception, match="without a value"):
        M.erode(df.withColumn("v", F.when(F.col("x") > 0, F.col("v"))), 1).collect()
    with pytest.raises(Exception, match="outside the range"):
        M.chain(df.withColumn("v", F.col("v") + 300), erosion(1), "u8").collect()


def test_empty_input(spark):
    df = spark.createDataFrame([], "img bigint, y int, x int, v bigint")
    assert M.hmax(df, 4).count() == 0 and M.erode(df, 2, strategy="sql").count() == 0


def test_task_plan_has_one_exchange(spark, two):
    plan = map_images(frame(spark, two), lambda c: c)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1


def test_strips_map_without_exchange(spark, two):
    out = map_strips(to_strips(frame(spark, two), 64), lambda a, m: K.filtered(a, 1))
    assert all((arrays(to_pixels(out))[i] == K.filtered(a, 1)).all() for i, a in two.items())


def test_files(spark, two, tmp_path):
    df = frame(spark, two)
    for fmt in ("pgm", "npy"):
        folder = tmp_path / fmt
        folder.mkdir()
        for r in files.encoded(df, fmt).collect():
            (folder / f"{r['img']}.{fmt}").write_bytes(r["content"])
        back = arrays(files.read_images(spark, str(folder), fmt).select(F.regexp_extract("path", r"(\d+)\.\w+$", 1).cast("bigint").alias("img"), "y", "x", "v"))
        assert all((back[i] == a).all() for i, a in two.items())
    files.write_strips(to_strips(df, 6), str(tmp_path / "strips"))
    back = arrays(to_pixels(files.read_strips(spark, str(tmp_path / "strips"))))
    assert all((back[i] == a).all() for i, a in two.items())
    assert files.decode(b"P2\n# note\n2 1\n9\n3 4\n", "pgm").tolist() == [[3, 4]]
    (tmp_path / "m.csv").write_text("0,5,6\n1,7,8\n")
    assert arrays(files.read_matrix(spark, str(tmp_path / "m.csv")))[0].tolist() == [[5, 6], [7, 8]]
    for fmt in ("json", "orc"):
        rows = df.groupBy("img", "y").agg(F.transform(F.array_sort(F.collect_list(F.struct("x", "v"))), lambda p: p["v"]).alias("row"))
        rows.write.format(fmt).save(str(tmp_path / f"m_{fmt}"))
        back = arrays(files.read_matrix(spark, str(tmp_path / f"m_{fmt}"), fmt))
        assert all((back[i] == a).all() for i, a in two.items())
    for kind in ("ramp", "checker", "noise", "serpentine"):
        assert files.synthetic(spark, kind, 8, 8).count() == 64


def test_stream_state_takes_rows_in_any_order_once():
    a = np.random.default_rng(6).integers(0, 50, (12, 5))
    expected = K.sep3(K.sep3(K.sep3(a, K.MIN), K.MAX), K.MIN)
    state, out = streaming.ChainState(["MIN3", "MAX3", "MIN3"], 12), {}
    for y in [1, 0, 0, 5, 4, 3, 2, 2, 11, 10, 9, 8, 7, 6, 3]:
        for k, row in state.add(y, a[y]):
            assert k not in out
            out[k] = row
    assert (np.array([out[k] for k in range(12)]) == expected).all()


def test_late_events_are_dropped(spark, tmp_path):
    folder = tmp_path / "events"
    schema = "ts timestamp, user_id bigint"

    def put(name, rows):
        spark.createDataFrame([(pd.Timestamp(t).to_pydatetime(), u) for t, u in rows], schema).coalesce(1).write.mode("append").parquet(str(folder))

    out, progress = str(tmp_path / "out"), str(tmp_path / "progress")

    def drain():
        s = spark.readStream.schema(schema).parquet(str(folder))
        q = streaming.window_cells(s, "1 day").writeStream.outputMode("append").format("parquet").option("path", out).option("checkpointLocation", progress).trigger(availableNow=True).start()
        q.awaitTermination()
        return sum(int(o["numRowsDroppedByWatermark"]) for p in q.recentProgress for o in p["stateOperators"])

    put("a", [("2024-01-01 05:00", 1), ("2024-01-01 06:00", 1), ("2024-01-03 12:00", 1)])
    assert drain() == 0
    put("b", [("2024-01-01 07:00", 1), ("2024-01-04 12:00", 1)])  # the first day has closed
    assert drain() == 1
    closed = spark.read.parquet(out).toPandas()
    assert closed[closed.w_start == 1704067200].v.sum() == 2
