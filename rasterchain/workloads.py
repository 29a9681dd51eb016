"""Experiment workloads: queries by name, and the SQL that checks them.

Each query runs an operator on a raster made of a whole table. Where SQL is too slow on
whole tables a query has none, and its operator is tested against brute force.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rasterchain import kernels as K
from rasterchain import oracles as O
from rasterchain import rasters as R
from rasterchain.chain import Chain, FilterSpec, alternating, erosion
from rasterchain.exec import sqlwin
from rasterchain.exec.task import map_images, reduce_images
from rasterchain.operators import morphology as M

Query = Callable[..., DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
S = R.SQL
E, P, STRIP, RELIEF = "emb_tiles", "part_size", "emb_strip", "order_relief"


def add(name: str, query: Query, oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle is not None:
        ORACLES[name] = oracle


def on(raster: str, fn: Callable[[DataFrame], DataFrame]) -> Query:
    return lambda spark, d: fn(R.RASTERS[raster](spark, d))


def pick(src: str, v: str = "v", columns: str = "img, y, x") -> str:
    return f"select {columns}, {v} v from {src}" if v else f"select {columns} from {src}"


def whole(src: str, kind: str = "bigint") -> str:
    return f"select img, y, x, v::{kind} v from {src}"


def with_mask(df: DataFrame, marker) -> DataFrame:
    return df.select("img", "y", "x", marker.alias("v"), F.col("v").alias("m"))


# --- erosions and dilations, by every method -----------------------------------------------

for s in (1, 3):
    add(f"erode_s{s}_emb", on(E, lambda df, s=s: M.erode(df, s, strategy="sql")), whole(O.win(S[E], s)))
    add(f"dilate_s{s}_emb", on(E, lambda df, s=s: M.dilate(df, s)), whole(O.win(S[E], s, "max")))
add("erode_s3_price", on("price_cells", lambda df: M.erode(df, 3)), whole(O.win(S["price_cells"], 3), "double"))
add("erode_signed_balances", on("balances", lambda df: M.erode(df, 1)), whole(O.win(S["balances"], 1), "double"))
for order in ("xy", "yx"):
    add(f"erode_order_{order}", on(P, lambda df, order=order: map_images(df, lambda c: {"v": K.sep3(c["v"], K.MIN, order)})), whole(O.win(S[P], 1)))
add("erode_inplace_rows", on(P, lambda df: map_images(df, lambda c: {"v": K.rows3_inplace(c["v"].copy(), 4)})), whole(O.win(S[P], 1, axes=("x",))))
add("erode_inplace_cols", on(P, lambda df: map_images(df, lambda c: {"v": K.cols3_inplace(c["v"].copy())})), whole(O.win(S[P], 1, axes=("y",))))


def _streamed(c):
    from rasterchain import streamk

    return {"v": np.array(list(streamk.pipeline(iter(c["v"]), ["MIN3"])))}


add("erode_stream_rows", on(STRIP, lambda df: map_images(df, _streamed)), whole(O.win(S[STRIP], 1)))
add("erode_rows_hof", on(P, lambda df: sqlwin.pixels_of(sqlwin.rows3(sqlwin.rows_of(df)))), whole(O.win(S[P], 1)))
add("erode_lag_lead", on(P, lambda df: sqlwin.lag_lead(df).select("img", "y", "x", "v")), whole(O.win(S[P], 1)))
add("erode_direct_part", on(P, lambda df: sqlwin.direct(df, 2)), f"select a.img, a.y, a.x, min(b.v) v from {S[P]} a join {S[P]} b on a.img = b.img and abs(a.y - b.y) <= 2 and abs(a.x - b.x) <= 2 group by all")
for s in (3, 13):
    for method in ("queue", "prefix_suffix", "segments"):
        add(f"erode_s{s}_{method.split('_')[0]}", on(STRIP, lambda df, s=s, method=method: M.erode(df, s, method)), whole(O.win(S[STRIP], s)))


def diamond(r: int) -> np.ndarray:
    return np.abs(np.arange(-r, r + 1))[:, None] + np.abs(np.arange(-r, r + 1))[None, :] <= r


add("erode_chord_diamond", on(P, lambda df: map_images(df, lambda c: {"v": K.chords(c["v"], diamond(3))})), f"select a.img, a.y, a.x, min(b.v) v from {S[P]} a join {S[P]} b on a.img = b.img and abs(a.y - b.y) + abs(a.x - b.x) <= 3 group by all")
add("erode_auto_emb", on(STRIP, lambda df: M.erode(df, 20)), whole(O.win(S[STRIP], 20)))
_VOXELS = "(with c as (select round(l_discount * 100)::int z, l_quantity::int - 1 y, (12 * (year(l_shipdate) - 1995) + month(l_shipdate) - 1)::int x, count(*) v from lineitem group by all), g as (select z::int z, y::int y, x::int x from unnest(range(0, 11)) a(z), unnest(range(0, 50)) b(y), unnest(range(0, 83)) c(x)) select 0::bigint img, g.z, g.y, g.x, coalesce(c.v, 0) v from g left join c using (z, y, x))"
add("erode3d_voxels", lambda spark, d: sqlwin.extremum(R.voxels(spark, d), 1, axes=("x", "y", "z")), f"select * from {O.win(_VOXELS, 1, axes=('x', 'y', 'z'), others=('img', 'z', 'y', 'x'))}")

# --- fixed chains --------------------------------------------------------------------------

for n in (4, 16, 64):
    add(f"chain_erode_{n}_emb", on(STRIP, lambda df, n=n: M.chain(df, erosion(n))), whole(O.win(S[STRIP], n)))
for dtype in ("u8", "u16", "f32", "f64"):
    add(f"chain512_{dtype}", on(STRIP, lambda df, dtype=dtype: M.chain(df, erosion(512), dtype)), whole(O.win(S[STRIP], 512)))
add("chain_whole_array_16_emb", on(STRIP, lambda df: map_images(df, lambda c: {"v": K.filtered(c["v"], 16, K.MIN, "chain")})), whole(O.win(S[STRIP], 16)))
add("chain_barrier_rounds_4_emb", on(STRIP, lambda df: M.barrier_chain(df, erosion(4), 128)), whole(O.win(S[STRIP], 4)))
add("chain_fused_64_emb", on(STRIP, lambda df: M.chain(df, erosion(64), fuse=True)), whole(O.win(S[STRIP], 64)))
add("chain_rounds_64_emb", on(STRIP, lambda df: M.chain(df, erosion(64), strategy="rounds", strip_rows=64, per_round=32)), whole(O.win(S[STRIP], 64)))


def _mixed(df: DataFrame) -> DataFrame:
    return M.chain(with_mask(df, F.col("v")), Chain.of("MIN3", "MAX3", "MIN3", FilterSpec("GEO_MIN3")))


_three = O.win(O.win(O.win(S[P], 1), 1, "max"), 1)
add("chain_mixed_part", on(P, _mixed), f"select img, y, x, greatest(a.v, b.v) v from {O.win(_three, 1)} a join {S[P]} b using (img, y, x)")

# --- geodesic filters and reconstruction ---------------------------------------------------

for s in (1, 5):
    add(f"geo_erode_s{s}_part", on(P, lambda df, s=s: M.geo_erode(with_mask(df, F.col("v") + 10), s, "sql" if s == 1 else "task")), pick(O.recursion(O.marked(S[P], "v + 10"), "erosion", s)))
    add(f"geo_dilate_s{s}_emb", on(E, lambda df, s=s: M.geo_dilate(with_mask(df, F.col("v") - 4), s, "sql" if s == 1 else "task")), pick(O.recursion(O.marked(S[E], "v - 4"), "dilation", s)))
add("erode_rec_order", on(RELIEF, lambda df: M.erode_rec(with_mask(df, F.col("v") + 300))), whole(O.recursion(O.marked(S[RELIEF], "v + 300"), "erosion")))
_h4 = O.marked(S[E], "v - 4")
add("dilate_rec_emb", on(E, lambda df: M.dilate_rec(with_mask(df, F.col("v") - 4))), whole(O.reach(_h4)))
for name, options in (("frontier", {"strategy": "frontier"}), ("rounds", {"strategy": "rounds"}), ("heap", {"method": "heap"})):
    add(f"dilate_rec_{name}", on(E, lambda df, options=options: M.dilate_rec(with_mask(df, F.col("v") - 4), **options)), whole(O.reach(_h4)))
add("hmax_emb", on(E, lambda df: M.hmax(df, 4)), whole(O.reach(_h4)))
add("hmax_part", on("part_price", lambda df: M.hmax(df, 4.0)), whole(O.recursion(O.marked(S["part_price"], "v - 4.0")), "double"))
add("hmax_saturate_emb", on(E, lambda df: M.hmax(df, 4, "saturate", "u8")), whole(O.reach(O.marked(S[E], "greatest(v - 4, 0)"))))
add("dome_emb", on(E, lambda df: M.dome(df, 4)), f"select img, y, x, (a.v - b.v)::bigint v from {S[E]} a join {O.reach(_h4)} b using (img, y, x)")
add("hfill_marker_emb", on(E, M.hfill_marker), whole(O.border(S[E], "max")))
add("raobj_marker_emb", on(E, M.raobj_marker), whole(O.border(S[E], "min")))
_fill = O.negated(O.reach(O.border(O.negated(S[E]), "min")))
add("hfill_emb", on(E, M.hfill), whole(_fill))
add("hfill_order", on(RELIEF, lambda df: M.hfill(df, strategy="auto")), whole(O.recursion(O.border(S[RELIEF], "max"), "erosion")))
for name, raster in (("emb", E), ("part", P)):
    add(f"raobj_{name}", on(raster, M.raobj), f"select img, y, x, (a.v - b.v)::bigint v from {S[raster]} a join {O.reach(O.border(S[raster], 'min'))} b using (img, y, x)")


def eroded_marker(src: str, s: int) -> str:
    return f"(select img, y, x, e.v v, f.v m from {O.win(src, s)} e join {src} f using (img, y, x))"


add("open_rec_emb", on(E, lambda df: M.open_rec(df, 1)), whole(O.reach(eroded_marker(S[E], 1))))
add("open_rec75_strip", on(STRIP, lambda df: M.open_rec(df, 75, strategy="auto")), whole(O.recursion(eroded_marker(S[STRIP], 75))))
_neg = O.negated(S[P])
add("hmin_part", on(P, lambda df: M.hmin(df, 8)), whole(O.negated(O.reach(O.marked(_neg, "v - 8")))))
add("basin_part", on(P, lambda df: M.basin(df, 8)), f"select img, y, x, (a.v - b.v)::bigint v from {O.negated(O.reach(O.marked(_neg, 'v - 8')))} a join {S[P]} b using (img, y, x)")
add("close_rec_part", on(P, lambda df: M.close_rec(df, 1)), whole(O.negated(O.reach(eroded_marker(_neg, 1)))))
add("top_hat_part", on(P, lambda df: M.top_hat(df, 2)), f"select img, y, x, a.v - b.v v from {S[P]} a join {O.opening(S[P], 2)} b using (img, y, x)")
add("black_hat_part", on(P, lambda df: M.black_hat(df, 2)), f"select img, y, x, a.v - b.v v from {O.closing(S[P], 2)} a join {S[P]} b using (img, y, x)")

# --- quasi-distance ------------------------------------------------------------------------

_res = O.residual(S[E], 64)
_r = "select img, y, x, {d} d, r::bigint r from " + _res
add("qdt_raw_emb", on(E, M.qdt_raw), _r.format(d="d"))
add("qdt_raw_definition", on(E, lambda df: M.qdt_raw(df, "definition")), _r.format(d="greatest(d - 1, 0)"))
add("qdt_residual_emb", on(E, lambda df: M.qdt_raw(df).select("img", "y", "x", "r")), f"select img, y, x, r::bigint r from {_res}")
add("qdt_unconditional", on(E, lambda df: M.qdt_raw(df, conditional=False)), _r.format(d="d"))
add("qdt_raw_sql_part", on(P, lambda df: sqlwin.qdt_raw(df, 12)), f"select img, y, x, d, r::bigint r from {O.residual(S[P], 12)}")
_dp = f"(select img, y, x, d v from {O.residual(S[P], 50)})"
add("lipschitz_step_part", on(P, lambda df: M.lipschitz_step(M.qdt_raw(df))), f"select img, y, x, least(a.v, b.v + 1)::int d from {_dp} a join {O.win(_dp, 1)} b using (img, y, x)")
_de = "(select img, y, x, d v from q)"
_qdt = f"with q as materialized (select * from {_res}) select * from {O.lipschitz(_de, 64)}"
add("qdt_emb", on(E, M.qdt), _qdt)
add("qdt_closed_form_emb", on(E, lambda df: M.qdt(df, closed_form=True)), _qdt)

# --- openings, granulometries, alternating filters -----------------------------------------

add("open_s2_part", on(P, lambda df: M.open_(df, 2)), whole(O.opening(S[P], 2)))
add("close_s2_part", on(P, lambda df: M.close(df, 2)), whole(O.closing(S[P], 2)))
for name, family in (("granulometry_part", "open"), ("granulometry_close_part", "close")):
    add(name, on(P, lambda df, family=family: M.granulometry(df, 6, family)), f"select img, s, g::bigint g from {O.levels(S[P], range(7), family)}")


def spectrum(src: str, s_max: int, family: str = "open") -> str:
    return f"(select img, s, (g - n)::bigint ps from (select *, lead(g) over (partition by img order by s) n from {O.levels(src, range(s_max + 2), family)}) where s <= {s_max})"


add("pattern_spectrum_part", on(P, lambda df: M.pattern_spectrum(df, 10)), f"select * from {spectrum(S[P], 10)}")
add("pattern_spectrum_close_part", on(P, lambda df: M.pattern_spectrum(df, 4, "close", signed=False)), f"select img, s, abs(ps) ps from {spectrum(S[P], 4, 'close')}")
add("pattern_spectrum_docs", lambda spark, d: M.pattern_spectrum(R.ink_strips(spark, d), 3), f"select * from {spectrum(S['ink'], 3)}")
add("asf3_part", on(P, lambda df: M.asf(df, 3)), whole(O.asf(S[P], 3)))
add("asf3_close_first", on(P, lambda df: M.asf(df, 3, "close")), whole(O.asf(S[P], 3, "close")))
add("asf3_fused_part", on(P, lambda df: M.chain(df, alternating(3), fuse=True)), whole(O.asf(S[P], 3)))
add("asf11_order", on(RELIEF, lambda df: M.asf(df, 11, fused=True, strategy="auto")), whole(O.asf(S[RELIEF], 11)))
add("regional_maxima_emb", on(E, M.regional_maxima), f"select img, y, x, (a.v > b.v)::bigint v from {S[E]} a join {O.reach(O.marked(S[E], 'v - 1'))} b using (img, y, x)")
add("label_ink", lambda spark, d: reduce_images(R.ink_strips(spark, d), lambda c: [(len(np.unique(K.labelled(c["v"]))) - int((c["v"] == 0).any()), int((c["v"] > 0).sum()))], "components bigint, ink bigint"))
_bin = f"(select img, y, x, (v >= 40)::bigint v from {S[P]})"
_ids = f"(select img, y, x, case when v > 0 then y * (max(x) over () + 1) + x + 1 else 0 end v, case when v > 0 then 1000000000 else 0 end m from {_bin})"
add("label_part", on(P, lambda df: M.label(df.withColumn("v", (F.col("v") >= 40).cast("bigint")))), whole(O.recursion(_ids)))

# --- chain lengths, measures, sweeps -------------------------------------------------------


def length(src: str) -> str:
    return f"select img, max(k)::int chain_len from {src} group by img"


add("chain_len_hmax", on(E, lambda df: M.chain_length(df, "hmax", 4)), length(O.recursion(_h4)))
add("chain_len_hfill", on(E, lambda df: M.chain_length(df, "hfill")), length(O.recursion(O.border(S[E], "max"), "erosion")))
add("chain_len_raobj", on(E, lambda df: M.chain_length(df, "raobj")), length(O.recursion(O.border(S[E], "min"))))
add("chain_len_open_rec", on(E, lambda df: M.chain_length(df, "open_rec", 1)), length(O.recursion(eroded_marker(S[E], 1))))
_erosions = " union all ".join(f"select img, y, x, {s} s, v from {O.win(S[E], s) if s else S[E]}" for s in range(65))
_pulled = " union all ".join(f"select img, y, x, {j} j, v + {j} v from {O.win(_de, j) if j else _de}" for j in range(65))
add("chain_len_qdt", on(E, M.qdt_lengths), f"""with q as materialized (select * from {_res}), e as ({_erosions})
  , l as (select img, s, lag(v) over (partition by img, y, x order by s) - v loss from e)
  , n as (select img, count(distinct s) filter (loss > 0) n_residual from l group by img)
  , p as (select img, y, x, arg_min(j, v * 1000 + j) j from ({_pulled}) group by all)
  select img, n_residual::int n_residual, max(j)::int n_eta from n join p using (img) group by all""")


def _chain_len_rounds(spark, d) -> DataFrame:
    from rasterchain.exec import rounds
    from rasterchain.layout import to_strips

    return rounds.until_stable(to_strips(with_mask(R.emb_tiles(spark, d), F.col("v") - 4), 16), per_round=8)[1]


add("chain_len_rounds", _chain_len_rounds, length(O.recursion(_h4)))


def sweep(raster: str, params: tuple, fn: Callable) -> Query:
    """One pass over the images for all parameters."""
    out = "param int, sum_v bigint, chain_len int"
    return on(raster, lambda df: reduce_images(df, lambda c: [(p, *fn(c["v"], p)) for p in params], out).select("param", "sum_v", "chain_len"))


def _summed(pair) -> tuple[int, int]:
    return int(pair[0].sum()), pair[1]


add("sweep_hmax", sweep(P, (1, 2, 4, 8, 16, 32), lambda a, h: _summed(K.hmax(a, h))), " union all ".join(f"select {h}::int param, sum(v)::bigint sum_v, max(k)::int chain_len from {O.recursion(O.marked(S[P], f'v - {h}'))}" for h in (1, 2, 4, 8, 16, 32)))
add("sweep_open_rec", sweep(P, (1, 2, 5, 10, 15, 25, 75), lambda a, s: _summed(K.open_rec(a, s))), " union all ".join(f"select {s}::int param, sum(v)::bigint sum_v, max(k)::int chain_len from {O.recursion(eroded_marker(S[P], s))}" for s in (1, 2, 5, 10, 15, 25, 75)))
add("sweep_asf", sweep(P, (1, 2, 3, 5), lambda a, s: (int(K.asf(a, s).sum()), 2 * s * (s + 1))), " union all ".join(f"select {s}::int param, sum(v)::bigint sum_v, {2 * s * (s + 1)}::int chain_len from {O.asf(S[P], s)}" for s in (1, 2, 3, 5)))
add("dims_width_emb", on("emb_wide", lambda df: M.chain(df, erosion(32))), whole(O.win(S["emb_wide"], 32)))
add("dims_height_emb", on(STRIP, lambda df: M.chain(df, erosion(32))), whole(O.win(S[STRIP], 32)))


def _mosaic(df: DataFrame) -> DataFrame:
    """Tiles two by two; incomplete mosaics are left out of no row: absent tiles are 0."""
    cells = df.select(F.floor(F.col("img") / 4).alias("img"), (F.col("y") + 64 * F.expr("int(img % 4 / 2)")).cast("int").alias("y"), (F.col("x") + 64 * (F.col("img") % 2)).cast("int").alias("x"), "v")
    frame = cells.select("img").distinct().select("img", F.lit(128).alias("height"), F.lit(128).alias("width"))
    return R.densify(cells, frame)


_mosaic_sql = f"(with c as (select img // 4 img, y + 64 * ((img % 4) // 2) y, x + 64 * (img % 2) x, v from {S[E]}), g as (select img, y::int y, x::int x from (select distinct img from c), unnest(range(0, 128)) a(y), unnest(range(0, 128)) b(x)) select g.img, g.y, g.x, coalesce(c.v, 0) v from g left join c on c.img = g.img and c.y = g.y and c.x = g.x)"
add("dims_square_emb", on(E, lambda df: M.chain(_mosaic(df), erosion(32))), whole(O.win(_mosaic_sql, 32)))

# --- many images ---------------------------------------------------------------------------


def _sums(fn: Callable) -> Callable[[DataFrame], DataFrame]:
    return lambda df: reduce_images(df, lambda c: [(int(fn(c["v"]).sum()),)], "sum_v bigint")


def _sum_sql(src: str) -> str:
    return f"select img, sum(v)::bigint sum_v from {src} group by img"


add("doc_hmax", lambda spark, d: reduce_images(R.glyph_strips(spark, d), lambda c: [_summed(K.hmax(c["v"], 32))], "sum_v bigint, chain_len int"))
add("doc_open", lambda spark, d: _sums(lambda a: K.opened(a, 1))(R.glyph_strips(spark, d)), _sum_sql(O.opening(S["glyph"], 1)))
add("page_open", lambda spark, d: _sums(lambda a: K.opened(a, 1))(R.page_strips(spark, d)), _sum_sql(O.opening(S["page_bytes"], 1)))
add("turns_dilate", lambda spark, d: M.dilate(R.turn_strips(spark, d), 1), whole(O.win(S["turns"], 1, "max")))


def _quote(spark, d) -> DataFrame:
    return reduce_images(R.quote_strips(spark, d), lambda c: [_summed(K.reconstruct(c["v"], c["m"]))], "sum_v bigint, chain_len int")


_places = "select distinct doc_id img, i - 1 a, i - 1 + length(quote) b from (select doc_id, d.text, b.text quote from documents d join benchmark b on length(b.text) > 0 and contains(d.text, b.text)), unnest(range(1, length(text) - length(quote) + 2)) r(i) where substr(text, i, length(quote)) = quote"
_quotes = f"(with s as ({_places}), i as (select * from {S['ink']} where img in (select img from s)), k as (select distinct img, unnest(range(a, b)) p from s) select i.img, y, x, case when k.p is null then 0 else v end v, v m from i left join k on k.img = i.img and k.p = y * 64 + x)"
add("quote_reconstruct", _quote, f"select img, sum(v)::bigint sum_v, max(k)::int chain_len from {O.recursion(_quotes)} group by img")


def _by_label(spark, d) -> DataFrame:
    ps = M.pattern_spectrum(R.ink_strips(spark, d), 3)
    labels = R.table(spark, d, "labels").select(F.col("doc_id").alias("img"), "quality")
    return ps.join(labels, "img").groupBy("quality", "s").agg(F.round(F.avg("ps"), 4).alias("avg_ps"))


add("spectrum_by_label", _by_label, f"select quality, s, round(avg(ps), 4) avg_ps from {spectrum(S['ink'], 3)} join labels on img = doc_id group by all")

# --- operations around the filters ---------------------------------------------------------

from rasterchain import relational  # noqa: E402

QUERIES |= relational.QUERIES
ORACLES |= relational.ORACLES
