"""Filters as window functions: no Python, and partitions of one row or one column of an image."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

AXES = ("x", "y")


def _lo(name: str):
    return F.min if name == "min" else F.max


def extremum(df: DataFrame, s: int, lo: str = "min", axes: tuple[str, ...] = AXES, value: str = "v") -> DataFrame:
    """Window extremum of half side s along the axes in turn; all coordinates but that one partition."""
    coordinates = [c for c in ("img", "z", "y", "x") if c in df.columns]
    for axis in axes:
        w = Window.partitionBy(*[c for c in coordinates if c != axis]).orderBy(axis).rangeBetween(-s, s)
        df = df.withColumn(value, _lo(lo)(value).over(w))
    return df


def geodesic(df: DataFrame, n: int, by: str = "dilation") -> DataFrame:
    """n geodesic filters on (v, m)."""
    clamp, lo = (F.least, "max") if by == "dilation" else (F.greatest, "min")
    for _ in range(n):
        df = extremum(df, 1, lo).withColumn("v", clamp("v", "m"))
    return df


def lag_lead(df: DataFrame, lo: str = "min") -> DataFrame:
    """The 3x3 filter from the neighbours before and after."""
    pick = F.least if lo == "min" else F.greatest  # both skip nulls, so the frame clips
    for axis, other in (("x", "y"), ("y", "x")):
        w = Window.partitionBy("img", other).orderBy(axis)
        df = df.withColumn("v", pick(F.lag("v").over(w), F.col("v"), F.lead("v").over(w)))
    return df


def direct(df: DataFrame, s: int, lo: str = "min") -> DataFrame:
    """Every value sent to all places whose window holds it, then an aggregate: (2s + 1) squared rows a pixel."""
    offsets = F.expr(f"sequence(-{s}, {s})")
    sent = df.select("img", F.col("y").alias("y0"), F.col("x").alias("x0"), "v").withColumn("dy", F.explode(offsets)).withColumn("dx", F.explode(offsets))
    moved = sent.select("img", (F.col("y0") + F.col("dy")).alias("y"), (F.col("x0") + F.col("dx")).alias("x"), "v").groupBy("img", "y", "x").agg(_lo(lo)("v").alias("v"))
    return df.select("img", "y", "x").join(moved, ["img", "y", "x"])


def rows_of(df: DataFrame) -> DataFrame:
    """Pixels to rows: (img, y, row)."""
    return df.groupBy("img", "y").agg(F.transform(F.array_sort(F.collect_list(F.struct("x", "v"))), lambda p: p["v"]).alias("row"))


def pixels_of(rows: DataFrame) -> DataFrame:
    return rows.select("img", "y", F.posexplode("row").alias("x", "v")).select("img", "y", "x", "v")


def rows3(rows: DataFrame, lo: str = "min") -> DataFrame:
    """The 3x3 filter on rows by array functions: along the row in place, then with the rows above and below."""
    pick = "array_min" if lo == "min" else "array_max"
    flat = rows.withColumn("row", F.expr(f"transform(row, (v, i) -> {pick}(slice(row, greatest(i, 1), 2 + if(i = 0, 0, 1))))"))
    w = Window.partitionBy("img").orderBy("y")
    both = flat.withColumns({"up": F.lag("row").over(w), "down": F.lead("row").over(w)})
    least = "least" if lo == "min" else "greatest"
    return both.withColumn("row", F.expr(f"transform(row, (v, i) -> {least}(v, coalesce(up[i], v), coalesce(down[i], v)))")).drop("up", "down")


def qdt_raw(df: DataFrame, s_max: int) -> DataFrame:
    """(img, y, x, d, r) by the largest loss over erosions of all sizes up to s_max; the smallest of equal ones."""
    every = df.select("img", "y", "x", F.lit(0).alias("s"), "v")
    for s in range(1, s_max + 1):
        every = every.unionByName(extremum(df, s).select("img", "y", "x", F.lit(s).alias("s"), "v"))
    w = Window.partitionBy("img", "y", "x").orderBy("s")
    loss = every.withColumn("loss", F.lag("v").over(w) - F.col("v")).where("loss > 0")
    best = loss.groupBy("img", "y", "x").agg(F.max_by("s", F.struct("loss", -F.col("s"))).alias("d"), F.max("loss").alias("r"))
    return df.select("img", "y", "x").join(best, ["img", "y", "x"], "left").select("img", "y", "x", F.coalesce("d", F.lit(0)).cast("int").alias("d"), F.coalesce("r", F.lit(0)).alias("r"))
