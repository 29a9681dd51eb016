"""Relational operations around the filters: joins, aggregates, windows, sets, functions and streams, as queries."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rasterchain import kernels as K
from rasterchain import oracles as O
from rasterchain import rasters as R
from rasterchain.chain import erosion
from rasterchain.exec.saving import shared_folder
from rasterchain.exec.task import reduce_images
from rasterchain.functions import sql as fsql
from rasterchain.layout import to_pixels, to_strips
from rasterchain.operators import morphology as M
from rasterchain.plans.rewrite import read_window
from rasterchain.schedule import assign
from rasterchain import measures
from rasterchain.streaming import rows as streaming

S = R.SQL
E, P, STRIP = "emb_tiles", "part_size", "emb_strip"


def stats(df: DataFrame) -> DataFrame:
    return df.groupBy("img").agg(F.count("*").alias("n"), F.sum("v").alias("sum_v"), F.min("v").alias("min_v"), F.max("v").alias("max_v"), F.min_by(F.struct("y", "x"), F.struct(-F.col("v"), "y", "x")).alias("at")).select("img", "n", "sum_v", "min_v", "max_v", F.col("at.y").alias("max_y"), F.col("at.x").alias("max_x"))


def levels(df: DataFrame, approx: bool = False) -> DataFrame:
    return df.groupBy("img").agg((F.approx_count_distinct("v") if approx else F.countDistinct("v")).alias("levels"))


def histogram(df: DataFrame) -> DataFrame:
    return df.groupBy("img", "v").agg(F.count("*").alias("n"))


def crop(df: DataFrame, x0: int, y0: int, x1: int, y1: int) -> DataFrame:
    return df.where(F.col("x").between(x0, x1) & F.col("y").between(y0, y1))


def crop_erode(df: DataFrame, s: int, x0: int, y0: int, x1: int, y1: int) -> DataFrame:
    """A window of an erosion: reads the window widened by s, filters, and cuts. Pixels keep their places."""
    a, b, c, d = read_window(erosion(s), x0, y0, x1, y1)
    part = crop(df, a, b, c, d).select("img", (F.col("y") - b).alias("y"), (F.col("x") - a).alias("x"), "v")
    return crop(M.erode(part, s).select("img", (F.col("y") + b).alias("y"), (F.col("x") + a).alias("x"), "v"), x0, y0, x1, y1)


def join_rects(df: DataFrame, rects: DataFrame, cell: int = 64) -> DataFrame:
    """Pixels in rectangles (rect, img, x0, y0, x1, y1), met by the grid cells that a rectangle covers."""
    span = lambda a, b: F.explode(F.sequence(F.floor(F.col(a) / cell), F.floor(F.col(b) / cell)))
    covered = rects.withColumn("cy", span("y0", "y1")).withColumn("cx", span("x0", "x1"))
    placed = df.withColumns({"cy": F.floor(F.col("y") / cell), "cx": F.floor(F.col("x") / cell)})
    return placed.join(covered, ["img", "cy", "cx"]).where("x between x0 and x1 and y between y0 and y1").drop("cy", "cx")


def asof(facts: DataFrame, windows: DataFrame, key: str, at: str, start: str, value: str) -> DataFrame:
    """facts with the value and start of the latest window of their key that began at or before them; null if none did."""
    w = windows.select(key, F.col(start).alias("_at"), F.lit(0).alias("_kind"), F.struct(F.col(start).alias("start"), F.col(value).alias("value")).alias("_w"))
    f = facts.select(key, F.col(at).alias("_at"), F.lit(1).alias("_kind"), F.struct(*facts.columns).alias("_f"))
    both = f.unionByName(w, allowMissingColumns=True)
    last = F.last("_w", ignorenulls=True).over(Window.partitionBy(key).orderBy("_at", "_kind"))
    return both.withColumn("_last", last).where("_kind = 1").select("_f.*", F.col("_last.start").alias("window_start"), F.col("_last.value").alias("window_value"))


def densities(spark, d) -> DataFrame:
    return R.ship_by_region(spark, d).select(F.col("img").alias("region"), F.col("x").alias("month"), "v")


def _marked_totals(df: DataFrame) -> DataFrame:
    """Totals are marked by -1, not null."""
    return df.select(F.coalesce("region", F.lit(-1)).cast("bigint").alias("region"), F.coalesce("month", F.lit(-1)).cast("int").alias("month"), "n")


def rects(spark) -> DataFrame:
    return spark.sql("select * from values (1, 0L, 0, 0, 15, 63), (2, 0L, 10, 100, 40, 200), (3, 0L, 0, 0, 63, 499) as t(rect, img, x0, y0, x1, y1)")


def domes(df: DataFrame, h: int) -> DataFrame:
    return M.dome(df, h)


def _rank(columns: list[Column]) -> Column:
    return F.row_number().over(Window.partitionBy("img").orderBy(*columns))


QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def add(name: str, query, oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle is not None:
        ORACLES[name] = oracle


def on(raster: str, fn):
    return lambda spark, d: fn(R.RASTERS[raster](spark, d))


for _name, _raster, _kind in (("raster_ship", "ship_density", "bigint"), ("raster_region", "ship_by_region", "bigint"), ("raster_events", "event_heat", "bigint"), ("raster_event_value", "event_value", "bigint"), ("raster_weekly", "ship_weekly", "bigint"), ("raster_orders", "order_surface", "double"), ("quantise_emb", E, "bigint"), ("threshold_ink", "ink", "bigint"), ("relief_cumsum", "order_relief", "bigint")):
    add(_name, R.RASTERS[_raster], f"select img, y, x, v::{_kind} v from {S[_raster]}")


def _props(spark, d) -> DataFrame:
    e = R.table(spark, d, "events")
    k = F.get_json_object("props", "$.k").cast("int")
    return e.select(F.lit(0).cast("bigint").alias("img"), k.alias("y"), F.expr("int(floor((unix_micros(cast(ts as timestamp)) - unix_micros(timestamp'2024-01-01')) / 86400000000))").alias("x")).where("y is not null").groupBy("img", "y", "x").agg(F.count("*").alias("v"))


add("raster_props", _props, "select 0::bigint img, (props->>'$.k')::int y, ((epoch_us(ts) - epoch_us(timestamp '2024-01-01')) // 86400000000)::int x, count(*) v from events where props->>'$.k' is not null group by all")
add("densify_events", lambda spark, d: R.event_heat(spark, d).groupBy("img", "y").agg(F.count("*").alias("n"), F.sum("v").alias("sum_v")), f"select img, y, count(*) n, sum(v)::bigint sum_v from {S['event_heat']} group by all")
add("roundtrip_layout", on(E, lambda df: to_pixels(to_strips(df, 16, "u8"))), f"select img, y, x, v from {S[E]}")
add("crop_erode", on(STRIP, lambda df: crop_erode(df, 3, 10, 100, 40, 200)), f"select img, y, x, v from {O.win(S[STRIP], 3)} where x between 10 and 40 and y between 100 and 200")
add("image_stats", on("ship_by_region", stats), f"select img, count(*) n, sum(v)::bigint sum_v, min(v) min_v, max(v) max_v, arg_max(y, v * 1000000 - y * 1000 - x) max_y, arg_max(x, v * 1000000 - y * 1000 - x) max_x from {S['ship_by_region']} group by img")
add("level_count", on(E, levels), f"select img, count(distinct v) levels from {S[E]} group by img")
add("level_count_approx", on(E, lambda df: levels(df, approx=True)))
add("level_percentiles", on(E, lambda df: df.groupBy("img").agg(F.percentile_approx("v", 0.5, 100000).alias("median"))), f"select img, quantile_disc(v, 0.5) median from {S[E]} group by img")
add("histogram_ship", on("ship_density", histogram), f"select img, v, count(*) n from {S['ship_density']} group by all")
add("density_rollup", lambda spark, d: _marked_totals(densities(spark, d).rollup("region", "month").agg(F.sum("v").alias("n"))), f"select coalesce(img, -1)::bigint region, coalesce(x, -1)::int as month, sum(v)::bigint n from {S['ship_by_region']} group by rollup (img, x)")
add("density_cube", lambda spark, d: _marked_totals(densities(spark, d).cube("region", "month").agg(F.sum("v").alias("n"))), f"select coalesce(img, -1)::bigint region, coalesce(x, -1)::int as month, sum(v)::bigint n from {S['ship_by_region']} group by cube (img, x)")


def _grouping_sets(spark, d) -> DataFrame:
    return _marked_totals(densities(spark, d).groupingSets([[F.col("region")], [F.col("month")]], "region", "month").agg(F.sum("v").alias("n")))


add("density_grouping_sets", _grouping_sets, f"select coalesce(img, -1)::bigint region, coalesce(x, -1)::int as month, sum(v)::bigint n from {S['ship_by_region']} group by grouping sets ((img), (x))")


def _mask_join(spark, d) -> DataFrame:
    a = R.emb_tiles(spark, d)
    return a.join(M.erode(a, 1, strategy="sql").withColumnRenamed("v", "m"), ["img", "y", "x"]).select("img", "y", "x", "v", "m")


add("mask_join", _mask_join, f"select img, y, x, a.v, b.v m from {S[E]} a join {O.win(S[E], 1)} b using (img, y, x)")
add("roi_stats", lambda spark, d: join_rects(R.emb_strip(spark, d), rects(spark)).groupBy("rect").agg(F.count("*").alias("n"), F.sum("v").alias("sum_v")), f"select rect, count(*) n, sum(v)::bigint sum_v from {S[STRIP]} join (values (1, 0, 0, 15, 63), (2, 10, 100, 40, 200), (3, 0, 0, 63, 499)) t(rect, x0, y0, x1, y1) on x between x0 and x1 and y between y0 and y1 group by rect")


def _asof(spark, d) -> DataFrame:
    e = R.table(spark, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("at_us"), "event_type")
    hour = 21600000000
    w = e.where("event_type = 'purchase'").groupBy("user_id", (F.floor(F.col("at_us") / hour) * hour).cast("bigint").alias("start")).agg(F.count("*").alias("n"))
    return asof(e.select("event_id", "user_id", "at_us"), w, "user_id", "at_us", "start", "n").withColumns({c: F.coalesce(c, F.lit(-1).cast("bigint")) for c in ("window_start", "window_value")})


add("asof_window", _asof, "with e as (select event_id, user_id, epoch_us(ts) at_us, event_type from events), w as (select user_id, (at_us // 21600000000 * 21600000000)::bigint start, count(*) n from e where event_type = 'purchase' group by all) select event_id, e.user_id, at_us, coalesce(start, -1) window_start, coalesce(n, -1) window_value from e asof left join w on e.user_id = w.user_id and e.at_us >= w.start")


def _active(spark, d) -> DataFrame:
    a = R.emb_tiles(spark, d)
    moving = M.chain_length(a, "hmax", 4).where("chain_len > 12").select("img")
    return stats(a.join(moving, "img", "left_semi")).select("img", "n", "sum_v")


add("active_images", _active, f"select img, count(*) n, sum(v)::bigint sum_v from {S[E]} where img in (select img from {O.recursion(O.marked(S[E], 'v - 4'))} group by img having max(k) > 12) group by img")
add("unlabelled_docs", lambda spark, d: R.table(spark, d, "documents").select("doc_id", "lang").join(R.table(spark, d, "labels"), "doc_id", "left_anti"), "select doc_id, lang from documents where doc_id not in (select doc_id from labels)")
_dome = f"(select img, y, x, (a.v - b.v)::bigint v from {S[E]} a join {O.reach(O.marked(S[E], 'v - 4'))} b using (img, y, x))"
add("top_domes", on(E, lambda df: domes(df, 4).withColumn("rk", _rank([F.desc("v"), F.col("y"), F.col("x")])).where("rk <= 5").select("img", "y", "x", "v", "rk")), f"select img, y, x, v, rk::int rk from (select *, row_number() over (partition by img order by v desc, y, x) rk from {_dome}) where rk <= 5")
add("topk_domes", on(E, lambda df: domes(df, 4).orderBy(F.desc("v"), "img", "y", "x").limit(20)), f"select img, y, x, v from {_dome} order by v desc, img, y, x limit 20")


def _ink_sets(spark, d) -> DataFrame:
    """Ink less the opened ink; both are sets of places of one image, so the difference is taken where its text is read."""
    def lost(c):
        n = int(((c["v"] > 0) & (K.opened(c["v"], 1) == 0)).sum())
        return [(n,)] if n else []

    return reduce_images(R.ink_strips(spark, d), lost, "n bigint")


add("ink_except_opened", _ink_sets, f"select img, count(*) n from (select img, y, x from {S['ink']} where v > 0 except select img, y, x from {O.opening(S['ink'], 1)} where v > 0) group by img")
add("ink_set_ops", on("part_size", lambda df: df.where("v > 25").select("img", "y", "x").intersect(df.where("v < 40").select("img", "y", "x")).union(df.where("v = 1").select("img", "y", "x"))), f"select img, y, x from {S[P]} where v > 25 and v < 40 union all select img, y, x from {S[P]} where v = 1")
_G = O.levels(S[P], range(7))
add("spectrum_map", on(P, lambda df: fsql.spectrum_map(M.pattern_spectrum(df, 5)).select("img", F.element_at("spectrum", 0).alias("ps0"), F.element_at("spectrum", 3).alias("ps3"), F.size("spectrum").alias("n"))), f"with g as (select * from {_G}) select 0::bigint img, ((select g from g where s = 0) - (select g from g where s = 1))::bigint ps0, ((select g from g where s = 3) - (select g from g where s = 4))::bigint ps3, 6::int n")


def _rows(df: DataFrame) -> DataFrame:
    from rasterchain.exec.sqlwin import rows_of

    return rows_of(df)


add("udf_row_min3", on(P, lambda df: _rows(df).select("img", "y", F.posexplode(fsql.rc_row_min3("row")).alias("x", "v"))), f"select img, y, x, v from {O.win(S[P], 1, axes=('x',))}")
add("udaf_spectrum", on(P, lambda df: df.groupBy("img").agg(fsql.rc_granulometry("y", "x", "v", F.lit(6)).alias("g")).select("img", F.posexplode("g").alias("s", "g"))), f"select img, s, g::bigint g from {_G}")


def _udtf(spark, d) -> DataFrame:
    fsql.register_sql(spark)
    R.part_size(spark, d).createOrReplaceTempView("rc_part_size")
    return spark.sql(f"select img, y, x, v from rc_chain('{fsql.chain_json(erosion(2))}', table(rc_part_size) partition by img)")


add("udtf_chain", _udtf, f"select img, y, x, v from {O.win(S[P], 2)}")


def _sql_erode(spark, d) -> DataFrame:
    fsql.register_sql(spark)
    R.part_size(spark, d).createOrReplaceTempView("rc_part_size")
    spark.sql("create or replace temporary function rc_clamp(v bigint, m bigint) returns bigint return least(v, m)")
    return spark.sql("select img, y, x, rc_clamp(max(h) over (partition by img, x order by y rows between 1 preceding and 1 following), m) v from (select img, y, x, v as m, max(v - 8) over (partition by img, y order by x rows between 1 preceding and 1 following) h from rc_part_size)")


add("sql_hmax_step", _sql_erode, f"select img, y, x, v from {O.recursion(O.marked(S[P], 'v - 8'), 'dilation', 1)}")

# --- measures ------------------------------------------------------------------------------


def _text_sizes(spark, d) -> DataFrame:
    """(img, w, h) of the glyph raster of each document, from the lengths of its texts."""
    text = R.table(spark, d, "documents").where("length(text) > 0")
    return text.select(F.col("doc_id").cast("bigint").alias("img"), F.lit(64).alias("w"), F.expr("int((length(text) + 63) div 64)").alias("h"))


_text_wh = "(select doc_id::bigint img, 64 w, ((length(text) + 63) // 64)::int h from documents where length(text) > 0)"


def _comparisons(spark, d) -> DataFrame:
    """Comparisons of an erosion of each document's raster."""
    each = F.explode(F.array(*[F.struct(F.lit(m).alias("method"), F.lit(s).alias("s"), F.lit(measures.comparisons(m, s)).alias("n")) for m in measures.METHODS for s in (1, 2, 5)])).alias("e")
    return _text_sizes(spark, d).select("img", "w", "h", each).select("img", "e.method", "e.s", (F.col("e.n").cast("bigint") * F.col("w") * F.col("h")).alias("comparisons"))


add("measure_comparisons", _comparisons, f"select img, m as method, s::int s, ((case m when 'direct' then (2 * s + 1) * (2 * s + 1) - 1 when 'queue' then 6 else 4 * s end)::bigint * w * h)::bigint comparisons from {_text_wh}, (values ('direct'), ('proposed'), ('queue'), ('library'), ('gpu')) a(m), (values (1), (2), (5)) b(s)")


def _sizes(spark, d) -> DataFrame:
    return R.emb_tiles(spark, d).groupBy("img").agg((F.max("x") + 1).alias("w"), (F.max("y") + 1).alias("h"))


def _memory(spark, d) -> DataFrame:
    t = 4
    formulas = {"proposed": 2 * F.col("w") * t, "queue": (3 * F.col("w") + 3) * t, "library": F.col("w") * F.col("h"), "gpu": F.col("w") * F.col("h")}
    each = F.explode(F.array(*[F.struct(F.lit(m).alias("method"), e.cast("bigint").alias("n")) for m, e in formulas.items()])).alias("e")
    return _sizes(spark, d).select("img", each).select("img", "e.method", F.col("e.n").alias("n_values"))


_wh = f"(select img, max(x) + 1 w, max(y) + 1 h from {S[E]} group by img)"
add("measure_memory", _memory, f"select img, m as method, (case m when 'proposed' then 2 * w * 4 when 'queue' then (3 * w + 3) * 4 else w * h end)::bigint n_values from {_wh}, (values ('proposed'), ('queue'), ('library'), ('gpu')) t(m)")


def _passes(spark, d) -> DataFrame:
    """Passes of a chain with as many filters as a document's raster has rows, so that it spans the raster."""
    each = F.explode(F.array(*[F.lit(t) for t in (1, 4, 24, 64)])).alias("t")
    return _text_sizes(spark, d).select("img", F.col("h").alias("n"), each).select("img", "n", "t", measures.passes(F.col("n"), F.col("t")).alias("passes"))


add("measure_passes", _passes, f"select img, h::int n, t::int t, ceil(h / t)::int passes from {_text_wh}, (values (1), (4), (24), (64)) b(t)")
add("measure_sync", lambda spark, d: _sizes(spark, d).select("img", (F.lit(512) * F.col("h")).cast("bigint").alias("sync_ops")), f"select img, (512 * h)::bigint sync_ops from {_wh}")


def _mismatch(spark, d) -> DataFrame:
    a = R.emb_strip(spark, d)
    return measures.mismatches(M.chain(a, erosion(8)), M.chain(a, erosion(8), strategy="rounds", strip_rows=100, per_round=4))


add("measure_mismatch", _mismatch, "select 0::bigint n_bad")


def _schedule(spark, d) -> DataFrame:
    """Worker and pass of every filter of a chain with as many filters as a document's raster has rows."""
    chains = _text_sizes(spark, d).select("img", F.explode(F.expr("sequence(1, h)")).alias("j"))
    worker, number = assign(F.col("j"), 6)
    return chains.select("img", "j", worker.cast("int").alias("worker"), number.cast("int").alias("pass"))


add("schedule_modulo", _schedule, f"select img, j::int j, (1 + (j - 1) % 6)::int worker, ((j - 1) // 6)::int pass from (select img, unnest(range(1, h + 1)) j from {_text_wh})")

# --- streams, run to their end -------------------------------------------------------------


def _folder(spark) -> str:
    return shared_folder(spark, "stream")


def _stream(spark, d: str, name: str) -> DataFrame:
    static = R.table(spark, d, name)
    # a pattern, so that the table may be one file or a folder
    return spark.readStream.schema(static.schema).parquet(f"{d}/{name}.parque[t]")


def drained(stream: DataFrame, spark, mode: str) -> DataFrame:
    """Runs a stream over what there is, into a table of the shared folder, and reads it."""
    folder = _folder(spark)
    out = f"{folder}/out"
    if mode == "append":
        writer = stream.writeStream.outputMode("append").format("parquet").option("path", out)
    else:
        writer = stream.writeStream.outputMode("complete").foreachBatch(lambda b, i: b.write.mode("overwrite").parquet(out))
    query = writer.option("checkpointLocation", f"{folder}/progress").trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.parquet(out)


def _stream_chain(spark, d) -> DataFrame:
    height = R.table(spark, d, "embeddings").count()
    row = F.transform("embedding", lambda e: F.least(F.greatest(F.floor((e.cast("double") + 0.5) * 256), F.lit(0)), F.lit(255)).cast("bigint"))
    rows = _stream(spark, d, "embeddings").select(F.lit(0).cast("bigint").alias("img"), F.col("vec_id").cast("int").alias("y"), row.alias("row"))
    out = drained(streaming.chain(rows, ["MIN3"] * 4, height), spark, "append")
    return out.select("img", "y", F.posexplode("row").alias("x", "v"))


add("stream_chain_emb", _stream_chain, f"select img, y, x, v from {O.win(S[STRIP], 4)}")
add("stream_tumbling_heat", lambda spark, d: drained(streaming.window_cells(_stream(spark, d, "events"), "1 day"), spark, "complete"), "select w_start, w_start + 86400 w_end, y, ((t - w_start) // 3600)::int x, count(*) v from (select (epoch_us(ts) // 1000000) t, (epoch_us(ts) // 1000000 // 86400 * 86400)::bigint w_start, user_id::int y from events) group by all")
add("stream_sliding_heat", lambda spark, d: drained(streaming.window_cells(_stream(spark, d, "events"), "1 day", "6 hours"), spark, "complete"), "select w_start, w_start + 86400 w_end, y, ((t - w_start) // 3600)::int x, count(*) v from (select t, ((t // 21600 - o) * 21600)::bigint w_start, y from (select (epoch_us(ts) // 1000000) t, user_id::int y from events), (values (0), (1), (2), (3)) v(o)) group by all")
_session = "with e as (select user_id, epoch_us(ts) t, case when epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by ts) < 7200000000 then 0 else 1 end b from events), g as (select *, sum(b) over (partition by user_id order by t rows unbounded preceding) k from e) select user_id, min(t) s_start, max(t) + 7200000000 s_end, count(*) n from g group by user_id, k"
add("stream_session_heat", lambda spark, d: drained(streaming.session_cells(_stream(spark, d, "events"), "2 hours"), spark, "complete"), f"select user_id, s_start, s_end, n from ({_session})")


def _stream_hmax(spark, d) -> DataFrame:
    """Peaks of contrast 1 of each day's raster, by the batch operator on windows as they come."""
    cells = streaming.window_cells(_stream(spark, d, "events"), "1 day")
    folder = _folder(spark)

    def hmax(batch: DataFrame) -> DataFrame:
        px = batch.select(F.col("w_start").alias("img"), "y", "x", "v")
        frame = px.groupBy("img").agg((F.max("y") + 1).alias("height"), F.lit(24).alias("width"))
        return M.hmax(R.densify(px, frame), 1)

    q = streaming.each_window(cells, hmax, lambda df, i: df.write.mode("overwrite").parquet(f"{folder}/out")).outputMode("complete").option("checkpointLocation", f"{folder}/progress").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{folder}/out")


_day = "(with c as (select w_start img, y, x, count(*) v from (select (epoch_us(ts) // 1000000 // 86400 * 86400)::bigint w_start, user_id::int y, (epoch_us(ts) // 1000000 % 86400 // 3600)::int x from events) group by all), f as (select img, max(y) + 1 h from c group by img), g as (select img, y::int y, x::int x from f, unnest(range(0, h)) a(y), unnest(range(0, 24)) b(x)) select g.img, g.y, g.x, coalesce(c.v, 0) v from g left join c using (img, y, x))"
add("stream_hmax", _stream_hmax, f"select img, y, x, v::bigint v from {O.recursion(O.marked(_day, 'v - 1'))}")
