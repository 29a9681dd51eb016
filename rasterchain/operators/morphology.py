"""The operators on pixel frames (img, y, x, v[, m]).

Every function is lazy and returns a frame of the same form unless it says otherwise.
kind is the Spark type of the result: bigint for whole numbers, double for real ones.
strategy: task (whole images), sql (window functions), rounds or frontier (strips), or auto:
the planner looks at the size of the images and takes whole images where their state fits a
task, and strips beyond that. Then fixed chains run in rounds, and reconstructions by their
front; both ship edge rows only, and give the same result.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rasterchain import dtypes
from rasterchain import kernels as K
from rasterchain.chain import Chain, alternating, closing, dilation, erosion, opening
from rasterchain.chain import run as run_chain_on
from rasterchain.exec import frontier, rounds, sqlwin
from rasterchain.exec.task import map_images, reduce_images
from rasterchain.layout import bordered_strips, map_strips, saved_strips, to_pixels, to_strips
from rasterchain.plans import planner
from rasterchain.plans.rewrite import optimize


def _kind(df: DataFrame) -> str:
    if "v" not in df.columns:
        return "bigint"  # strips of texts
    return "double" if df.schema["v"].dataType.simpleString() in ("double", "float") else "bigint"


def _cast(dtype: str | None):
    return (lambda a: a) if dtype is None else lambda a: dtypes.checked(a, dtype)


def _filter(df: DataFrame, s: int, lo, method: str, strategy: str) -> DataFrame:
    if "payload" in df.columns:  # strips that hold whole images
        return to_pixels(map_strips(df, lambda a, _: K.filtered(a, s, lo, method)))
    if strategy == "sql":
        return sqlwin.extremum(df, s, "min" if lo is K.MIN else "max").select("img", "y", "x", "v")
    return map_images(df, lambda c: {"v": K.filtered(c["v"], s, lo, method)}, f"v {_kind(df)}")


def erode(df: DataFrame, s: int, method: str = "auto", strategy: str = "task") -> DataFrame:
    return _filter(df, s, K.MIN, method, strategy)


def dilate(df: DataFrame, s: int, method: str = "auto", strategy: str = "task") -> DataFrame:
    return _filter(df, s, K.MAX, method, strategy)


def _in_strips(df: DataFrame, strategy: str, filters: Chain | None = None) -> planner.PhysicalChoice | None:
    """What the planner says of strips for these images, None for whole images in a task."""
    if strategy == "task":
        return None
    found = planner.planned(df, filters)
    return None if strategy == "auto" and found.strategy == "task" else found


def _chained(df: DataFrame, filters: Chain, plan: planner.PhysicalChoice) -> DataFrame:
    per_round = max(1, min(plan.filters_per_round or filters.n_filters, plan.strip_rows))
    return chain(df, filters, strategy="rounds", strip_rows=plan.strip_rows, per_round=per_round)


def _rebuilt(df: DataFrame, by: str, plan: planner.PhysicalChoice) -> DataFrame:
    return reconstruct(df, by, strategy="frontier", strip_rows=plan.strip_rows)


def _beside(df: DataFrame, other: DataFrame, v) -> DataFrame:
    """Pixels of df and of another frame (as v and m), put together."""
    return df.select("img", "y", "x", "v").join(other.select("img", "y", "x", F.col("v").alias("m")), ["img", "y", "x"]).select("img", "y", "x", v.alias("v"), "m")


def open_(df: DataFrame, s: int, strategy: str = "task") -> DataFrame:
    if plan := _in_strips(df, strategy, opening(s)):
        return _chained(df, opening(s), plan)
    return map_images(df, lambda c: {"v": K.opened(c["v"], s)}, f"v {_kind(df)}")


def close(df: DataFrame, s: int, strategy: str = "task") -> DataFrame:
    if plan := _in_strips(df, strategy, closing(s)):
        return _chained(df, closing(s), plan)
    return map_images(df, lambda c: {"v": K.closed(c["v"], s)}, f"v {_kind(df)}")


def top_hat(df: DataFrame, s: int) -> DataFrame:
    return map_images(df, lambda c: {"v": c["v"] - K.opened(c["v"], s)}, f"v {_kind(df)}")


def black_hat(df: DataFrame, s: int) -> DataFrame:
    return map_images(df, lambda c: {"v": K.closed(c["v"], s) - c["v"]}, f"v {_kind(df)}")


def chain(df: DataFrame, filters: Chain, dtype: str | None = None, fuse: bool = False, strategy: str = "task", strip_rows: int = 64, per_round: int = 8) -> DataFrame:
    """A fixed chain, in one task an image or in rounds over strips; fuse rewrites it first."""
    plan = optimize(filters, fuse)
    kind = _kind(df)
    if strategy == "rounds":
        return to_pixels(rounds.run_chain(to_strips(df, strip_rows, dtype or ("f64" if kind == "double" else "i64")), optimize(filters), per_round), kind)
    cast = _cast(dtype)
    return map_images(df, lambda c: {"v": run_chain_on(cast(c["v"]), plan, c.get("m"))}, f"v {kind}")


def barrier_chain(df: DataFrame, filters: Chain, strip_rows: int = 64) -> DataFrame:
    """One filter at a time over the whole image, all tasks on it, with a barrier after each."""
    return chain(df, filters, strategy="rounds", strip_rows=strip_rows, per_round=1)


def geo_dilate(df: DataFrame, s: int, strategy: str = "task") -> DataFrame:
    """s geodesic dilations of v under m."""
    return sqlwin.geodesic(df, s).select("img", "y", "x", "v") if strategy == "sql" else map_images(df, lambda c: {"v": K.reconstruct(c["v"], c["m"], K.MAX, s)[0]}, f"v {_kind(df)}")


def geo_erode(df: DataFrame, s: int, strategy: str = "task") -> DataFrame:
    """s geodesic erosions of v over m."""
    return sqlwin.geodesic(df, s, "erosion").select("img", "y", "x", "v") if strategy == "sql" else map_images(df, lambda c: {"v": K.reconstruct(c["v"], c["m"], K.MIN, s)[0]}, f"v {_kind(df)}")


def reconstruct(df: DataFrame, by: str = "dilation", method: str = "chain", strategy: str = "task", strip_rows: int = 16, per_round: int = 8) -> DataFrame:
    """Marker v, mask m. method heap floods in order of value; strategies rounds and frontier work on strips."""
    lo, kind = (K.MAX if by == "dilation" else K.MIN), _kind(df)
    if strategy in ("rounds", "frontier"):
        strips = saved_strips(df, strip_rows, "f64" if kind == "double" else "i64")
        done, _ = rounds.until_stable(strips, by, per_round) if strategy == "rounds" else frontier.until_stable(strips, by)
        return to_pixels(done, kind)
    if method == "heap":
        return map_images(df, lambda c: {"v": K.reconstruct_heap(c["v"], c["m"], lo)}, f"v {kind}")
    return map_images(df, lambda c: {"v": K.reconstruct(c["v"], c["m"], lo)[0]}, f"v {kind}")


def dilate_rec(df: DataFrame, **options) -> DataFrame:
    return reconstruct(df, "dilation", **options)


def erode_rec(df: DataFrame, **options) -> DataFrame:
    return reconstruct(df, "erosion", **options)


def hmax(df: DataFrame, h, arith: str = "real", dtype: str | None = None, strategy: str = "task") -> DataFrame:
    if arith == "real" and dtype is None and (plan := _in_strips(df, strategy)):
        return _rebuilt(df.select("img", "y", "x", (F.col("v") - h).alias("v"), F.col("v").alias("m")), "dilation", plan)
    cast = _cast(dtype)
    return map_images(df, lambda c: {"v": K.hmax(cast(c["v"]), h, arith)[0]}, f"v {_kind(df)}")


def dome(df: DataFrame, h, strategy: str = "task") -> DataFrame:
    if plan := _in_strips(df, strategy):
        low = _rebuilt(df.select("img", "y", "x", (F.col("v") - h).alias("v"), F.col("v").alias("m")), "dilation", plan)
        return _beside(df, low, F.col("v") - F.col("m")).drop("m")
    return map_images(df, lambda c: {"v": c["v"] - K.hmax(c["v"], h)[0]}, f"v {_kind(df)}")


def hmin(df: DataFrame, h) -> DataFrame:
    return map_images(df, lambda c: {"v": -K.hmax(-c["v"], h)[0]}, f"v {_kind(df)}")


def basin(df: DataFrame, h) -> DataFrame:
    return map_images(df, lambda c: {"v": -K.hmax(-c["v"], h)[0] - c["v"]}, f"v {_kind(df)}")


def border_marker(df: DataFrame, inside: str = "max") -> DataFrame:
    """The image on its frame, its greatest (least) value inside; the image itself as mask. One small aggregate, joined back."""
    ends = df.groupBy("img").agg(F.max("x").alias("_x"), F.max("y").alias("_y"), (F.max if inside == "max" else F.min)("v").alias("_v"))
    edge = (F.col("x") == 0) | (F.col("y") == 0) | (F.col("x") == F.col("_x")) | (F.col("y") == F.col("_y"))
    return df.join(ends, "img").select("img", "y", "x", F.when(edge, F.col("v")).otherwise(F.col("_v")).alias("v"), F.col("v").alias("m"))


def hfill_marker(df: DataFrame) -> DataFrame:
    return border_marker(df, "max").drop("m")


def raobj_marker(df: DataFrame) -> DataFrame:
    return border_marker(df, "min").drop("m")


def hfill(df: DataFrame, strategy: str = "task") -> DataFrame:
    if plan := _in_strips(df, strategy):
        kind = _kind(df)
        strips = saved_strips(df.select("img", "y", "x", "v"), plan.strip_rows, "f64" if kind == "double" else "i64")
        return to_pixels(frontier.until_stable(bordered_strips(strips, "max"), "erosion")[0], kind)
    return map_images(df, lambda c: {"v": K.hfill(c["v"])[0]}, f"v {_kind(df)}")


def raobj(df: DataFrame, strategy: str = "task") -> DataFrame:
    if plan := _in_strips(df, strategy):
        return _beside(df, _rebuilt(border_marker(df, "min"), "dilation", plan), F.col("v") - F.col("m")).drop("m")
    return map_images(df, lambda c: {"v": K.raobj(c["v"])[0]}, f"v {_kind(df)}")


def open_rec(df: DataFrame, s: int, strategy: str = "task") -> DataFrame:
    if plan := _in_strips(df, strategy):
        marker = _beside(_chained(df, erosion(s), plan), df, F.col("v"))
        return _rebuilt(marker, "dilation", plan)
    # the length is not asked for, so any order of filters will do
    return map_images(df, lambda c: {"v": K.rebuilt(K.filtered(c["v"], s, K.MIN), c["v"])}, f"v {_kind(df)}")


def close_rec(df: DataFrame, s: int) -> DataFrame:
    return map_images(df, lambda c: {"v": -K.open_rec(-c["v"], s)[0]}, f"v {_kind(df)}")


def qdt_raw(df: DataFrame, index: str = "step", conditional: bool = True) -> DataFrame:
    """(img, y, x, d, r). index step counts filters from 1, definition the size before the loss, from 0."""
    back = 0 if index == "step" else 1

    def fn(c):
        d, r, _ = K.residuals(c["v"], conditional)
        return {"d": (d - back).clip(0), "r": r}

    return map_images(df, fn, f"d int, r {_kind(df)}")


def lipschitz_step(df: DataFrame) -> DataFrame:
    """df has d."""
    return map_images(df.select("img", "y", "x", "d"), lambda c: {"d": K.lipschitz_step(c["d"])}, "d int")


def lipschitz(df: DataFrame, closed_form: bool = False) -> DataFrame:
    return map_images(df.select("img", "y", "x", "d"), lambda c: {"d": K.lipschitz_closed(c["d"]) if closed_form else K.lipschitz(c["d"])[0]}, "d int")


def qdt(df: DataFrame, closed_form: bool = False) -> DataFrame:
    """Quasi-distance: (img, y, x, d), both phases in one pass over the images."""

    def fn(c):
        d = K.residuals(c["v"])[0]
        return {"d": K.lipschitz_closed(d) if closed_form else K.lipschitz(d)[0]}

    return map_images(df, fn, "d int")


def granulometry(df: DataFrame, s_max: int, family: str = "open", strategy: str = "task") -> DataFrame:
    """(img, s, g)."""
    if plan := _in_strips(df, strategy, opening(max(1, s_max))):
        total = lambda at, k: at.groupBy("img").agg(F.sum("v").alias("g")).select("img", F.lit(k).alias("s"), "g")
        first, then = (erosion, dilation) if family == "open" else (dilation, erosion)
        sums, low = [total(df, 0)], df
        for k in range(1, s_max + 1):  # the first filters of all sizes are shared
            low = _chained(low, first(1), plan)
            sums.append(total(_chained(low, then(k), plan), k))
        return reduce(DataFrame.union, sums)
    return reduce_images(df, lambda c: list(enumerate(K.granulometry(c["v"], s_max, family))), f"s int, g {_kind(df)}")


def pattern_spectrum(df: DataFrame, s_max: int, family: str = "open", signed: bool = True, strategy: str = "task") -> DataFrame:
    """(img, s, ps) for sizes 0 to s_max; closings give negative values unless signed is off."""
    if _in_strips(df, strategy, opening(max(1, s_max))):
        ps = F.col("g") - F.lead("g").over(Window.partitionBy("img").orderBy("s"))
        return granulometry(df, s_max + 1, family, strategy).select("img", "s", (ps if signed else F.abs(ps)).alias("ps")).where(F.col("s") <= s_max)

    def fn(c):
        g = K.granulometry(c["v"], s_max + 1, family)
        return [(s, a - b if signed else abs(a - b)) for s, (a, b) in enumerate(zip(g, g[1:], strict=False))]

    return reduce_images(df, fn, f"s int, ps {_kind(df)}")


def asf(df: DataFrame, s: int, first: str = "open", fused: bool = False, strategy: str = "task") -> DataFrame:
    if plan := _in_strips(df, strategy, alternating(s, first)):
        return _chained(df, alternating(s, first), plan)
    return map_images(df, lambda c: {"v": K.asf(c["v"], s, first, fused)}, f"v {_kind(df)}")


def regional_maxima(df: DataFrame) -> DataFrame:
    """1 on regional maxima of whole-numbered images, 0 elsewhere."""
    return map_images(df, lambda c: {"v": (c["v"] - K.hmax(c["v"], 1)[0] > 0).astype(int)}, "v bigint")


def label(df: DataFrame) -> DataFrame:
    return map_images(df, lambda c: {"v": K.labelled(c["v"])}, "v bigint")


#: Operators whose chain length can be asked for: functions of an image and the parameter.
LENGTHS = {
    "hmax": lambda a, h: K.hmax(a, h)[1],
    "hfill": lambda a, _: K.hfill(a)[1],
    "raobj": lambda a, _: K.raobj(a)[1],
    "open_rec": lambda a, s: K.open_rec(a, s)[1],
}


def chain_length(df: DataFrame, operator: str, parameter=None) -> DataFrame:
    """(img, chain_len): filters of the operator's reconstruction that changed the image."""
    fn = LENGTHS[operator]
    return reduce_images(df, lambda c: [(fn(c["v"], parameter),)], "chain_len int")


def qdt_lengths(df: DataFrame) -> DataFrame:
    """(img, n_residual, n_eta): erosions with a loss, and pull-downs that changed something."""

    def fn(c):
        d, _, n = K.residuals(c["v"])
        return [(n, K.lipschitz(d)[1])]

    return reduce_images(df, fn, "n_residual int, n_eta int")
