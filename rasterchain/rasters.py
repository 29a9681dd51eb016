"""Rasters made of the given tables, as pixel frames (img, y, x, v), and their twins in DuckDB SQL.

Facts are aggregated before anything else, so what is shuffled are distinct cells. Rasters
of counts are made dense with an outer join onto the cells of their frame.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rasterchain.layout import STRIP, strip_row

Raster = Callable[[SparkSession, str], DataFrame]
ORIGIN = "1995-01-01"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def pixels(df: DataFrame, img, y, x, v, dtype: str = "bigint") -> DataFrame:
    col = lambda e: e if isinstance(e, Column) else F.lit(e) if not isinstance(e, str) else F.expr(e)
    return df.select(col(img).cast("bigint").alias("img"), col(y).cast("int").alias("y"), col(x).cast("int").alias("x"), col(v).cast(dtype).alias("v"))


#: Rows of a frame that are begun at a time.
ROWS = 4096
#: Tasks that fill rows, for each that may run at once.
TASKS = 8


def densify(cells: DataFrame, frame: DataFrame, fill=0) -> DataFrame:
    """cells (img, y, x, v) on every pixel of frame (img, height, width), absent ones with fill.

    The frame has one row an image. Cells are dealt to the rows of their image, and each fills the gap up to the
    next one: no pixel of the frame is joined, dealt out or held, and no task begins all rows of an image. Cells before
    the frame's origin are an error; frames are as large as their cells need.
    """
    inside = lambda c: F.when(F.col(c) < 0, F.raise_error(F.lit(f"a cell lies before the frame: {c} below 0")).cast("int")).otherwise(F.col(c)).cast("int").alias(c)
    session, dtype = cells.sparkSession, cells.schema["v"].dataType
    zero = F.lit(fill).cast(dtype)
    own = cells.select(F.col("img").cast("bigint"), inside("y"), inside("x"), F.coalesce("v", zero).alias("v"), F.lit(None).cast("int").alias("width")).where("img is not null and y is not null and x is not null")
    # each row of a frame begins with a mark that stands before its pixels and knows its width; what explode makes of one
    # row is held at once, so marks are made by blocks, dealt to all tasks
    firsts = frame.where("height > 0 and width > 0").select(F.col("img").cast("bigint"), F.col("height").cast("int"), F.col("width").cast("int"), F.explode(F.expr(f"sequence(0, int(height) - 1, {ROWS})")).alias("first"))
    blocks = firsts.repartition(session.sparkContext.defaultParallelism)
    starts = blocks.select("img", F.explode(F.expr(f"sequence(first, first + least({ROWS}, height - first) - 1)")).alias("y"), F.lit(-1).alias("x"), zero.alias("v"), "width")
    # tasks by number: by the bytes of cells, far less than their pixels, Spark would join them to a few long ones
    tasks = max(int(session.conf.get("spark.sql.shuffle.partitions")), TASKS * session.sparkContext.defaultParallelism)
    row = Window.partitionBy("img", "y").orderBy("x")
    placed = starts.unionByName(own).repartition(tasks, "img", "y").select("img", "y", "x", "v", F.first("width").over(row).alias("width"), F.lead("x").over(row).alias("next"))
    ends = placed.withColumn("end", F.least("next", "width") - 1).where("x < width and (x >= 0 or end >= 0)")  # least skips nulls
    filled = ends.withColumn("p", F.explode(F.expr("sequence(greatest(x, 0), greatest(x, end))")))
    return filled.select("img", "y", F.col("p").alias("x"), F.when(F.col("p") == F.col("x"), F.col("v")).otherwise(zero).alias("v"))


def _elements(spark, d) -> DataFrame:
    return table(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("i", "e"))


def _quantised(levels: int) -> Column:
    return F.least(F.greatest(F.floor((F.col("e").cast("double") + 0.5) * levels), F.lit(0)), F.lit(levels - 1))


def emb_tiles(spark, d) -> DataFrame:
    return pixels(_elements(spark, d), "floor(vec_id / 64)", "vec_id % 64", "i", _quantised(32))


def emb_strip(spark, d) -> DataFrame:
    return pixels(_elements(spark, d), 0, "vec_id", "i", _quantised(256))


def emb_wide(spark, d) -> DataFrame:
    return pixels(_elements(spark, d), 0, "i", "vec_id", _quantised(256))


def _frame(cells: DataFrame, height: Column, width: Column) -> DataFrame:
    return cells.groupBy("img").agg(height.cast("int").alias("height"), width.cast("int").alias("width"))


def _least(n: int, axis: str) -> Column:
    """The extent of an axis: n, or more where cells lie beyond."""
    return F.greatest(F.lit(n), F.max(axis) + 1)


def _days(c: str) -> str:
    return f"datediff({c}, date'{ORIGIN}')"


def ship_density(spark, d, week: int = 1) -> DataFrame:
    cells = pixels(table(spark, d, "lineitem"), 0, "cast(l_quantity as int) - 1", f"floor({_days('l_shipdate')} / {week})", 1).groupBy("img", "y", "x").agg(F.count("*").alias("v"))
    return densify(cells, _frame(cells, _least(50, "y"), F.max("x") + 1))


def ship_weekly(spark, d) -> DataFrame:
    return ship_density(spark, d, 7)


def ship_by_region(spark, d) -> DataFrame:
    li = table(spark, d, "lineitem").select("l_suppkey", "l_quantity", "l_shipdate")
    nation = table(spark, d, "nation").join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    supp = table(spark, d, "supplier").join(nation, F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "r_regionkey")
    joined = li.join(supp, F.col("l_suppkey") == F.col("s_suppkey"))
    cells = pixels(joined, "r_regionkey", "cast(l_quantity as int) - 1", "12 * (year(l_shipdate) - 1995) + month(l_shipdate) - 1", 1).groupBy("img", "y", "x").agg(F.count("*").alias("v"))
    return densify(cells, _frame(cells, _least(50, "y"), _least(83, "x")))


def price_cells(spark, d) -> DataFrame:
    li = table(spark, d, "lineitem")
    img = F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2)
    cells = pixels(li, img, "round(l_discount * 100)", "cast(l_quantity as int) - 1", "l_extendedprice", "double").groupBy("img", "y", "x").agg(F.max("v").alias("v"))
    return densify(cells, _frame(cells, _least(11, "y"), _least(50, "x")), 0.0)


def event_heat(spark, d) -> DataFrame:
    cells = pixels(table(spark, d, "events"), 0, "user_id", "floor((unix_micros(cast(ts as timestamp)) - unix_micros(timestamp'2024-01-01')) / 3600000000)", 1).groupBy("img", "y", "x").agg(F.count("*").alias("v"))
    return densify(cells, _frame(cells, F.max("y") + 1, _least(720, "x")))


def event_value(spark, d) -> DataFrame:
    cells = pixels(table(spark, d, "events"), 0, "user_id", "floor((unix_micros(cast(ts as timestamp)) - unix_micros(timestamp'2024-01-01')) / 3600000000)", "round(value * 100)").groupBy("img", "y", "x").agg(F.sum("v").alias("v"))
    return densify(cells, _frame(cells, F.max("y") + 1, _least(720, "x")))


def _order_cells(spark, d) -> DataFrame:
    return pixels(table(spark, d, "orders"), 0, "floor(o_custkey / 15)", f"floor({_days('o_orderdate')} / 7)", "o_totalprice", "double").groupBy("img", "y", "x").agg(F.max("v").alias("v"))


def order_surface(spark, d) -> DataFrame:
    cells = _order_cells(spark, d)
    return densify(cells, _frame(cells, F.max("y") + 1, F.max("x") + 1), 0.0)


def order_relief(spark, d) -> DataFrame:
    """Cents of order_surface less their mean, summed along x and y, in units of ten thousand."""
    cells = _order_cells(spark, d)
    ends = cells.groupBy("img").agg((F.max("y") + 1).alias("h"), (F.max("x") + 1).alias("w"), F.sum(F.when(F.col("y").isNotNull() & F.col("x").isNotNull(), F.round(F.col("v") * 100).cast("bigint"))).alias("c"))
    # pixels without a cell count as 0; one row, sent to all tasks
    mean = F.broadcast(ends.select("img", F.expr("floor(coalesce(c, 0) / (bigint(h) * w))").cast("bigint").alias("mean")))
    c = order_surface(spark, d).join(mean, "img").withColumn("c", F.round(F.col("v") * 100).cast("bigint") - F.col("mean"))
    # along x first: pixels are dealt by row as they are made
    across = c.withColumn("c", F.sum("c").over(Window.partitionBy("img", "y").orderBy("x")))
    down = across.withColumn("c", F.sum("c").over(Window.partitionBy("img", "x").orderBy("y")))
    return down.select("img", "y", "x", F.expr("(c - pmod(c, 1000000L)) div 1000000L").cast("bigint").alias("v"))


def part_price(spark, d) -> DataFrame:
    return pixels(table(spark, d, "part"), 0, "floor(p_partkey / 50)", "p_partkey % 50", "p_retailprice", "double")


def part_size(spark, d) -> DataFrame:
    return pixels(table(spark, d, "part"), 0, "floor(p_partkey / 50)", "p_partkey % 50", "p_size")


def wrapped_text(df: DataFrame, img: str, text: str, width: int, ink: bool = False, extra: tuple[str, ...] = ()) -> DataFrame:
    """Texts wrapped at a width; the last row is filled with 0. Null and empty texts have no pixels."""
    chars = df.where(F.length(text) > 0).select(F.col(img).alias("img"), *extra, F.posexplode(F.split(text, "")).alias("p", "c")).where("c != ''")
    value = F.when(F.col("c").rlike(r"^[\x20\x09-\x0D]"), 0).otherwise(255) if ink else F.least(F.ascii("c"), F.lit(255))
    full = chars.select("img", F.col("p"), value.cast("bigint").alias("v"), *extra)
    rest = df.where(F.length(text) > 0).select(F.col(img).alias("img"), F.explode(F.expr(f"if(length({text}) % {width} = 0, array(), sequence(length({text}), (floor((length({text}) - 1) / {width}) + 1) * {width} - 1))")).alias("p"))
    padded = full.unionByName(rest.select("img", "p", F.lit(0).cast("bigint").alias("v"), *[F.lit(None).alias(c) for c in extra]))
    return padded.select(F.col("img").cast("bigint"), F.floor(F.col("p") / width).cast("int").alias("y"), (F.col("p") % width).cast("int").alias("x"), "v", *extra)


def glyph(spark, d) -> DataFrame:
    return wrapped_text(table(spark, d, "documents"), "doc_id", "text", 64)


def ink(spark, d) -> DataFrame:
    return wrapped_text(table(spark, d, "documents"), "doc_id", "text", 64, ink=True)


def page_bytes(spark, d) -> DataFrame:
    return wrapped_text(table(spark, d, "pages"), "page_id", "html", 128)


def turns(spark, d) -> DataFrame:
    """One row a turn, as wide as the longest turn of its conversation; shorter turns and turns that a conversation lacks are filled with 0."""
    t = table(spark, d, "conversations").select(F.col("conv_id").alias("img"), F.col("turn").alias("y"), F.posexplode(F.split("text", "")).alias("x", "c")).where("c != ''")
    cells = t.groupBy(F.col("img").cast("bigint").alias("img"), F.col("y").cast("int").alias("y"), "x").agg(F.max(F.least(F.ascii("c"), F.lit(255))).cast("bigint").alias("v"))
    return densify(cells, _frame(cells, F.max("y") + 1, F.max("x") + 1))


def balances(spark, d) -> DataFrame:
    cells = pixels(table(spark, d, "customer"), 0, "floor(c_custkey / 50)", "c_custkey % 50", "c_acctbal", "double")
    return densify(cells, _frame(cells, F.max("y") + 1, _least(50, "x")), 0.0)


def voxels(spark, d) -> DataFrame:
    """(img, z, y, x, v): months by quantity by discount, dense."""
    li = table(spark, d, "lineitem")
    cells = li.select(F.expr("cast(round(l_discount * 100) as int)").alias("z"), F.expr("cast(l_quantity as int) - 1").alias("y"), F.expr("12 * (year(l_shipdate) - 1995) + month(l_shipdate) - 1").alias("x")).groupBy("z", "y", "x").agg(F.count("*").alias("v"))
    ends = cells.agg(*[_least(n, c).alias(c) for c, n in (("z", 11), ("y", 50), ("x", 83))])  # one row
    every = lambda c: F.explode(F.sequence(F.lit(0), F.col(c) - 1))
    grid = ends.select("y", "x", every("z").alias("_z")).select("x", "_z", every("y").alias("_y")).select(F.col("_z").alias("z"), F.col("_y").alias("y"), every("x").alias("x"))
    return grid.join(cells, ["z", "y", "x"], "left").select(F.lit(0).cast("bigint").alias("img"), "z", "y", "x", F.coalesce("v", F.lit(0)).cast("bigint").alias("v"))


def codes(text: str, width: int, ink: bool = False) -> np.ndarray:
    """A text wrapped at a width as bytes: code points up to 255, or ink (255) and white space (0); the last row is filled with 0."""
    c = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")
    out = np.zeros(-(-len(c) // width) * width, np.uint8)
    out[: len(c)] = np.where((c == 32) | (c >= 9) & (c <= 13), 0, 255) if ink else np.minimum(c, 255)
    return out.reshape(-1, width)


def text_strips(df: DataFrame, img: str, text: str, width: int, ink: bool = False) -> DataFrame:
    """Texts as strips that hold a whole image each, made where the text is read: no exchange. Null and empty texts have none.

    Only a table that is read by fewer tasks than may run at once is dealt out first.
    """
    rows, tasks = df.select(F.col(img).cast("bigint"), text), df.sparkSession.sparkContext.defaultParallelism
    if rows.rdd.getNumPartitions() < tasks:
        rows = rows.repartition(tasks)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                if t:
                    a = codes(t, width, ink)
                    yield strip_row(i, 0, 1, 0, a, "u8")

    return rows.mapInArrow(run, STRIP)


def glyph_strips(spark, d) -> DataFrame:
    return text_strips(table(spark, d, "documents"), "doc_id", "text", 64)


def ink_strips(spark, d) -> DataFrame:
    return text_strips(table(spark, d, "documents"), "doc_id", "text", 64, ink=True)


def page_strips(spark, d) -> DataFrame:
    return text_strips(table(spark, d, "pages"), "page_id", "html", 128)


def turn_strips(spark, d) -> DataFrame:
    """turns as strips that hold a whole conversation each: its texts are brought together, its pixels are made in the task."""
    t = table(spark, d, "conversations").where("length(text) > 0").select(F.col("conv_id").cast("bigint").alias("img"), F.col("turn").cast("int").alias("y"), "text")

    def image(img: int | None, held: list[tuple[int | None, str]]) -> Iterator[pa.RecordBatch]:
        placed = [(y, t) for y, t in held if y is not None]
        if not placed:
            return
        if placed[0][0] < 0:
            raise ValueError("a cell lies before the frame: y below 0")
        # texts without a place widen their image, as they do in turns
        a = np.zeros((placed[-1][0] + 1, max(len(t) for _, t in held)), np.uint8)
        for y, t in placed if img is not None else []:
            np.maximum(a[y, : len(t)], codes(t, len(t))[0], out=a[y, : len(t)])
        yield strip_row(img, 0, 1, 0, a, "u8")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = ((i, y, t) for b in batches for i, y, t in zip(*(c.to_pylist() for c in b.columns), strict=True))
        for img, group in groupby(rows, key=lambda r: r[0]):
            yield from image(img, [r[1:] for r in group])

    return t.repartition("img").sortWithinPartitions("img", "y").mapInArrow(run, STRIP)


#: Characters of passages that are searched in one pass over the documents.
BLOCK = 1 << 22


def quoted(docs: DataFrame, passages: DataFrame) -> DataFrame:
    """(doc_id, text, spans array of (a, b)): documents that hold a whole passage, with all places where one stands.

    docs has doc_id and text, passages has quote. Passages are searched in blocks of bounded
    size, each by one automaton in one pass over the documents, however many passages there are.
    """
    some = passages.where("length(quote) > 0").select("quote").distinct()
    total = some.agg(F.coalesce(F.sum(F.length("quote")), F.lit(0))).first()[0]
    n = -(-total // BLOCK)

    def search(quotes: list[str]):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            import ahocorasick

            words = ahocorasick.Automaton()
            for q in quotes:
                words.add_word(q, len(q))
            words.make_automaton()
            for b in batches:
                found = [[{"a": end + 1 - size, "b": end + 1} for end, size in words.iter(t)] if t else [] for t in b.column(1).to_pylist()]
                hit = pa.array([bool(f) for f in found])
                yield pa.RecordBatch.from_arrays([b.column(0).filter(hit), b.column(1).filter(hit), pa.array([f for f in found if f], pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())])))], names=["doc_id", "text", "spans"])

        return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, text string, spans array<struct<a: bigint, b: bigint>>")

    if not n:
        return docs.select(F.col("doc_id").cast("bigint"), "text", F.array().cast("array<struct<a: bigint, b: bigint>>").alias("spans")).limit(0)
    blocks = [search([r["quote"] for r in some.where(F.pmod(F.xxhash64("quote"), F.lit(n)) == k).collect()]) for k in range(n)]
    if n == 1:
        return blocks[0]
    return reduce(DataFrame.union, blocks).groupBy("doc_id", "text").agg(F.flatten(F.collect_list("spans")).alias("spans"))


def quote_strips(spark, d) -> DataFrame:
    """Strips with masks: mask = ink of documents that quote a whole passage; marker = its ink within the passages."""
    found = quoted(table(spark, d, "documents"), table(spark, d, "benchmark").select(F.col("text").alias("quote")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, t, spans in zip(*(c.to_pylist() for c in b.columns), strict=True):
                mask = codes(t, 64, ink=True)
                inside = np.zeros(mask.size, bool)
                for s in spans:
                    inside[s["a"] : s["b"]] = True
                yield strip_row(i, 0, 1, 0, np.where(inside.reshape(mask.shape), mask, 0).astype(np.uint8), "u8", mask)

    return found.mapInArrow(run, STRIP)


RASTERS: dict[str, Raster] = {f.__name__: f for f in (emb_tiles, emb_strip, emb_wide, ship_density, ship_weekly, ship_by_region, price_cells, event_heat, event_value, order_surface, order_relief, part_price, part_size, glyph, ink, page_bytes, turns, balances)}


def _dense_sql(cells: str, height: str, width: str, fill: str = "0") -> str:
    return f"(with c as ({cells}), f as (select img, ({height})::int h, ({width})::int w from c group by img), g as (select img, y::int y, x::int x from f, unnest(range(0, h)) a(y), unnest(range(0, w)) b(x)) select g.img, g.y, g.x, coalesce(c.v, {fill}) v from g left join c using (img, y, x))"


_E = "(select vec_id, unnest(embedding)::double e, generate_subscripts(embedding, 1) - 1 i from embeddings)"
_LI = "(date_diff('day', date '1995-01-01', l_shipdate::date))"
_MONTH = "12 * (year(l_shipdate) - 1995) + month(l_shipdate) - 1"
_HOUR = "floor((epoch_us(ts) - epoch_us(timestamp '2024-01-01')) / 3600000000)"


def _q(n: int) -> str:
    return f"greatest(0, least({n - 1}, floor((e + 0.5) * {n})))::bigint"


def _wrap_sql(t: str, img: str, text: str, width: int, ink: bool = False) -> str:
    v = "case when regexp_matches(c, '^[\\x20\\x09-\\x0D]') then 0 else 255 end" if ink else "least(unicode(c), 255)"
    return f"(with t as (select {img} img, {text} t from {t} where length({text}) > 0), c as (select img, unnest(string_split(t, '')) c, generate_subscripts(string_split(t, ''), 1) - 1 p from t), a as (select img, p, ({v})::bigint v from c union all select img, unnest(range(length(t), ((length(t) - 1) // {width} + 1) * {width})) p, 0::bigint v from t) select img::bigint img, (p // {width})::int y, (p % {width})::int x, v from a)"


_SURFACE = _dense_sql(f"select 0::bigint img, (o_custkey // 15)::int y, (date_diff('day', date '1995-01-01', o_orderdate::date) // 7)::int x, max(o_totalprice) v from orders group by all", "max(y) + 1", "max(x) + 1", "0.0")

#: DuckDB twins, each a parenthesised select of img, y, x, v.
SQL: dict[str, str] = {
    "emb_tiles": f"(select (vec_id // 64)::bigint img, (vec_id % 64)::int y, i::int x, {_q(32)} v from {_E})",
    "emb_strip": f"(select 0::bigint img, vec_id::int y, i::int x, {_q(256)} v from {_E})",
    "emb_wide": f"(select 0::bigint img, i::int y, vec_id::int x, {_q(256)} v from {_E})",
    "ship_density": _dense_sql(f"select 0::bigint img, l_quantity::int - 1 y, {_LI}::int x, count(*) v from lineitem group by all", "50", "max(x) + 1"),
    "ship_weekly": _dense_sql(f"select 0::bigint img, l_quantity::int - 1 y, ({_LI} // 7)::int x, count(*) v from lineitem group by all", "50", "max(x) + 1"),
    "ship_by_region": _dense_sql(f"select r_regionkey::bigint img, l_quantity::int - 1 y, ({_MONTH})::int x, count(*) v from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by all", "50", "83"),
    "price_cells": _dense_sql("select case l_returnflag when 'A' then 0 when 'N' then 1 else 2 end::bigint img, round(l_discount * 100)::int y, l_quantity::int - 1 x, max(l_extendedprice) v from lineitem group by all", "11", "50", "0.0"),
    "event_heat": _dense_sql(f"select 0::bigint img, user_id::int y, {_HOUR}::int x, count(*) v from events group by all", "max(y) + 1", "720"),
    "event_value": _dense_sql(f"select 0::bigint img, user_id::int y, {_HOUR}::int x, sum(round(value * 100)::bigint)::bigint v from events group by all", "max(y) + 1", "720"),
    "order_surface": _SURFACE,
    "order_relief": f"(with c as (select *, round(v * 100)::bigint c from {_SURFACE}), k as (select floor(sum(c) / count(*))::bigint k from c), d as (select img, y, x, sum(c - k) over (partition by img, x order by y) c from c, k), a as (select img, y, x, (sum(c) over (partition by img, y order by x))::bigint c from d) select img, y, x, ((c - ((c % 1000000) + 1000000) % 1000000) // 1000000)::bigint v from a)",
    "part_price": "(select 0::bigint img, (p_partkey // 50)::int y, (p_partkey % 50)::int x, p_retailprice v from part)",
    "part_size": "(select 0::bigint img, (p_partkey // 50)::int y, (p_partkey % 50)::int x, p_size::bigint v from part)",
    "glyph": _wrap_sql("documents", "doc_id", "text", 64),
    "ink": _wrap_sql("documents", "doc_id", "text", 64, True),
    "page_bytes": _wrap_sql("pages", "page_id", "html", 128),
    "turns": _dense_sql("select conv_id::bigint img, turn::int y, (i - 1)::int x, max(least(unicode(c), 255))::bigint v from (select conv_id, turn, unnest(string_split(text, '')) c, generate_subscripts(string_split(text, ''), 1) i from conversations where length(text) > 0) group by all", "max(y) + 1", "max(x) + 1"),
    "balances": _dense_sql("select 0::bigint img, (c_custkey // 50)::int y, (c_custkey % 50)::int x, c_acctbal v from customer", "max(y) + 1", "50", "0.0"),
}
