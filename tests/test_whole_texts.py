"""Rasters of texts hold every character, however long a text is."""

import numpy as np

from rasterchain import layout, rasters, workloads


def conversations(spark, tmp_path):
    rows = [(1, 0, "user", "a" * 700 + "z"), (1, 2, "bot", "b" * 256 + "~"), (2, 0, "user", "short"), (3, 0, "user", ""), (3, 1, "bot", None), (4, 1, "bot", "é" * 300 + "中")]
    spark.createDataFrame(rows, "conv_id long, turn int, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    want = {}
    for img in (1, 2, 4):
        texts = {t: x for i, t, _, x in rows if i == img}
        a = np.zeros((max(texts) + 1, max(map(len, texts.values()))), int)
        for t, x in texts.items():
            a[t, : len(x)] = [min(ord(c), 255) for c in x]
        want[img] = a
    return want


def images(df):
    return {(r["img"], r["y"], r["x"]): r["v"] for r in df.collect()}


def cells(want):
    return {(i, y, x): v for i, a in want.items() for (y, x), v in np.ndenumerate(a)}


def test_turns_hold_whole_texts(spark, tmp_path):
    want = conversations(spark, tmp_path)
    assert images(rasters.turns(spark, str(tmp_path))) == cells(want)


def test_turns_dilate_over_whole_texts(spark, tmp_path):
    want = conversations(spark, tmp_path)
    grown = {}
    for i, a in want.items():
        p = np.pad(a, 1)
        grown[i] = np.max([p[y : y + a.shape[0], x : x + a.shape[1]] for y in range(3) for x in range(3)], axis=0)
    assert images(workloads.QUERIES["turns_dilate"](spark, str(tmp_path))) == cells(grown)


def test_turns_are_made_where_their_texts_are(spark, tmp_path):
    conversations(spark, tmp_path)
    out = workloads.QUERIES["turns_dilate"](spark, str(tmp_path))
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert "Generate" not in plan and "Join" not in plan  # no pixel is dealt out


def test_turn_strips_equal_turns(spark, tmp_path, monkeypatch):
    rows = [(1, 0, "u", "ab"), (1, 0, "u", "Zzz"), (1, 3, "u", "x"), (2, None, "u", "lost but long"), (2, 1, "u", "é中"), (3, None, "u", "none"), (None, 1, "u", "ab"), (None, 0, "u", "c")]
    spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    monkeypatch.setattr(layout, "BATCH", 5)
    want = images(rasters.turns(spark, str(tmp_path)))
    assert want[1, 0, 0] == ord("a") and want[2, 0, 12] == 0 and want[None, 1, 1] == 0
    assert images(layout.to_pixels(rasters.turn_strips(spark, str(tmp_path)))) == want


def test_ink_lost_by_an_opening_is_counted_where_texts_are(spark, tmp_path):
    texts = ["x" * 192, "x" * 191 + " ", "a b " * 60, "", None, " \t\n", ("x" * 60 + "    ") * 3, "x"]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    want = {}
    for i, t in enumerate(texts):
        a = rasters.codes(t, 64, ink=True) > 0 if t else np.zeros((0, 64), bool)
        kept = np.zeros_like(a)
        for y, x in np.ndindex(*a.shape):  # a place is kept if a whole window over it is ink
            for dy, dx in np.ndindex(3, 3):
                cy, cx = y + dy - 1, x + dx - 1
                if 0 <= cy < a.shape[0] and 0 <= cx < 64:
                    kept[y, x] |= a[max(0, cy - 1) : cy + 2, max(0, cx - 1) : cx + 2].all()
        if (a & ~kept).any():
            want[i] = int((a & ~kept).sum())
    out = workloads.QUERIES["ink_except_opened"](spark, str(tmp_path))
    assert {r["img"]: r["n"] for r in out.collect()} == want and {2, 7} <= set(want) and 0 not in want
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert "Generate" not in plan and "Except" not in plan and "Join" not in plan
