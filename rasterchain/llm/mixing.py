"""Mixing sources to target weights by capped water-filling. DataFrame functions only.

A source's share of all words follows its weight; no source is repeated more than
max_epochs times, and what a clamped source cannot take goes to the others in proportion to
their weights, until none is above its clamp. A source then takes each text as often as the
whole part of target / size says, and once more those texts whose seeded hash lies below a
cut: the cut is where the running size, in hash order, comes nearest to what is left. One
more text is then added or left out if that brings the sum nearer still. The cut is found by
counting sizes in hash bins, then in finer bins of one bin, so no source is ever ordered in
one task.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rasterchain.llm.common import WORD, broadcast_if_small, checkpoint, text_or_empty

BIN_BITS = 10
#: The seeded hash of a text is the first 15 hexadecimal digits of an MD5.
HASH_BITS = 60
FIELDS = ("size", "source_size", "target", "copies", "taken")


def measured(docs: DataFrame, id_col: str, text_col: str, source_col: str, seed: int) -> DataFrame:
    """docs with _size (words), _source and _hash."""
    size = F.regexp_count(text_or_empty(text_col), F.lit(WORD)).cast("long")
    digest = F.md5(F.concat_ws("|", F.lit(str(seed)), F.coalesce(F.col(id_col).cast("string"), F.lit("null")), text_or_empty(text_col)))
    hashed = F.conv(F.substring(digest, 1, HASH_BITS // 4), 16, 10).cast("long")
    return docs.withColumns({"_size": size, "_source": F.col(source_col), "_hash": hashed})


def targets(rows: DataFrame, weights: tuple[int, ...] = (1, 2, 3), max_epochs: int = 3) -> DataFrame:
    """(_source, source_size, weight, target) from rows with _source and _size: one row a source.

    Sources come in order of code points, null last, and weights repeat in that order. Sizes
    are summed before anything is ordered; what is ordered is one row a source.
    """
    sources = rows.groupBy("_source").agg(F.sum("_size").alias("source_size"))
    rank = F.row_number().over(Window.orderBy(F.col("_source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*[F.lit(w) for w in weights]), (rank % len(weights) + 1).cast("int")).cast("long")
    s = sources.withColumn("weight", weight).withColumn("cap", max_epochs * F.col("source_size"))
    # by rising cap / weight; the level holds for all whose cap is above it
    order = Window.orderBy(F.col("cap") / F.col("weight"), F.col("_source").asc_nulls_last())
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    every = Window.partitionBy()
    s = s.withColumns({"capped": F.coalesce(F.sum("cap").over(before), F.lit(0)), "rest": F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0)), "total": F.sum("source_size").over(every)})
    # the first source, in this order, that its cap does not bind sets the level
    s = s.withColumn("free", F.col("cap") * F.col("rest") >= (F.col("total") - F.col("capped")) * F.col("weight"))
    level = F.min(F.when(F.col("free"), F.struct(F.col("capped"), F.col("rest")))).over(every)
    s = s.withColumn("level", level)
    spread = (F.col("total") - F.col("level.capped")).cast("double") * F.col("weight") / F.col("level.rest")
    return s.select("_source", "source_size", "weight", F.least(F.col("cap").cast("double"), F.coalesce(spread, F.col("cap").cast("double"))).alias("target"))


def cuts(rows: DataFrame, goals: DataFrame) -> DataFrame:
    """(_source, source_size, target, whole, cut, odd) from rows with _source, _hash and _size.

    Texts with _hash < cut are taken once more than whole times, but for the text with hash
    odd, for which it is the other way round.
    """
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long")
    g = goals.withColumn("whole", whole).withColumn("need", F.col("target") - F.col("whole") * F.col("source_size"))
    part = g.select("_source", "need").withColumn("low", F.lit(0).cast("long"))
    width = HASH_BITS
    # each round narrows the place of the cut to one bin; the last one looks at single texts
    for last in (False, False, True):
        within = _of_source(rows, part).where((F.col("_hash") >= F.col("low")) & (F.col("_hash") < F.col("low") + F.lit(1 << width)))
        width -= BIN_BITS
        key = F.col("_hash") if last else F.shiftright(F.col("_hash"), width)
        bins = within.groupBy("_source", key.alias("bin")).agg(F.sum("_size").alias("n"), F.max("need").alias("need"), F.max("low").alias("low"))
        run = bins.withColumn("upto", F.sum("n").over(Window.partitionBy("_source").orderBy("bin")))
        if last:
            # before or after the text that crosses the need, whichever is nearer
            nearer = (F.col("upto") <= F.col("need")) | (F.col("upto") - F.col("need") < F.col("need") - (F.col("upto") - F.col("n")))
            part = checkpoint(run.groupBy("_source").agg(F.coalesce(F.max(F.when(nearer, F.col("bin") + 1)), F.min("low")).alias("cut")))
        else:
            crossing = F.min(F.when(F.col("upto") > F.col("need"), F.struct(F.col("bin"), (F.col("upto") - F.col("n")).alias("done"))))
            found = run.groupBy("_source").agg(crossing.alias("x"), F.max("need").alias("need"))
            # a source of which nothing more is needed, or all, has no crossing: its cut lies above all texts
            part = checkpoint(found.select("_source", F.when(F.col("x").isNull(), F.lit(0.0)).otherwise(F.col("need") - F.col("x.done")).alias("need"), F.coalesce(F.shiftleft(F.col("x.bin"), width), F.lit(1 << HASH_BITS)).alias("low")))
    part = g.join(part, g["_source"].eqNullSafe(part["_source"]), "left").select(g["_source"], "source_size", "target", "whole", "need", F.coalesce("cut", F.when(F.col("need") > 0, F.lit(1 << HASH_BITS)).otherwise(F.lit(0)).cast("long")).alias("cut"))
    part = checkpoint(part)
    below = F.col("_hash") < F.col("cut")
    short = _of_source(rows, part).groupBy("_source").agg((F.max("need") - F.coalesce(F.sum(F.when(below, F.col("_size"))), F.lit(0))).alias("short"), F.max("cut").alias("cut"))
    near = _of_source(rows, checkpoint(short)).where((below == (F.col("short") < 0)) & (F.abs(F.abs("short") - F.col("_size")) < F.abs("short")))
    odd = near.groupBy("_source").agg(F.min_by("_hash", F.struct(F.abs(F.abs("short") - F.col("_size")), F.col("_hash"))).alias("odd"))
    return part.join(odd, part["_source"].eqNullSafe(odd["_source"]), "left").select(part["_source"], "source_size", "target", "whole", "cut", "odd")


def _of_source(rows: DataFrame, part: DataFrame) -> DataFrame:
    return rows.join(broadcast_if_small(part), rows["_source"].eqNullSafe(part["_source"])).drop(part["_source"])


def mixed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights: tuple[int, ...] = (1, 2, 3), max_epochs: int = 3, seed: int = 17) -> DataFrame:
    """docs with size, source_size, target, copies and taken (copies times size), one row per input row.

    Null texts have size 0; null is a source of its own, the last. Rows that are equal in id
    and text share a hash and so are taken equally often. Reruns agree, whatever the
    partitions. A source without words has target 0. An empty table gives an empty result.
    Columns of docs that have the names of results are replaced.
    """
    rows = measured(docs.drop(*[c for c in docs.columns if c in FIELDS and c not in (id_col, text_col, source_col)]), id_col, text_col, source_col, seed)
    return _taken(rows, rows, weights, max_epochs)


def _taken(rows: DataFrame, sizes: DataFrame, weights: tuple[int, ...] = (1, 2, 3), max_epochs: int = 3) -> DataFrame:
    """The mix of measured rows. sizes are the same rows, measured in full; of rows only the columns are computed that the result is read for."""
    small = checkpoint(sizes.groupBy("_source", "_hash").agg(F.sum("_size").alias("_size")))
    goals = checkpoint(targets(small, weights, max_epochs))
    plan = checkpoint(cuts(small, goals)).withColumnRenamed("_source", "_of")
    joined = rows.join(broadcast_if_small(plan), F.col("_source").eqNullSafe(F.col("_of")), "left")
    more = (F.col("_hash") < F.col("cut")) != F.coalesce(F.col("_hash") == F.col("odd"), F.lit(False))
    copies = F.least(F.col("whole") + more.cast("long"), F.lit(max_epochs))
    out = joined.withColumn("copies", copies).withColumn("taken", F.col("copies") * F.col("_size")).withColumn("size", F.col("_size"))
    return out.drop("_size", "_source", "_hash", "_of", "whole", "cut", "odd")


def sampled(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: each row of docs as often as it is taken, with the columns of docs."""
    return mixed(docs, **options).withColumn("_n", F.explode(F.expr("if(copies > 0, sequence(1L, copies), cast(array() as array<bigint>))"))).select(*docs.columns)


def op8_mixing(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source")
    # the texts are read once; what is kept of them is a number and a hash
    rows = checkpoint(measured(docs, "doc_id", "text", "source", 17).drop("text", "source"))
    return _taken(rows, rows).select("doc_id", "size", "source_size", "target", "taken")


#: DuckDB SQL for op8_mixing, with running sums over each source in place of bins.
OP8_SQL = r"""
with d as (select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::bigint size,
    ('0x' || substr(md5('17|' || coalesce(doc_id::varchar, 'null') || '|' || coalesce(text, '')), 1, 15))::bigint h from documents)
, s as (select source, sum(size)::bigint source_size, 3 * sum(size)::bigint cap, ((row_number() over (order by source nulls last) - 1) % 3 + 1)::bigint w from d group by source)
, o as (select *, coalesce(sum(cap) over before, 0)::bigint capped, (sum(w) over () - coalesce(sum(w) over before, 0))::bigint rest, (sum(source_size) over ())::bigint total
    from s window before as (order by cap / w, source nulls last rows between unbounded preceding and 1 preceding))
, l as (select capped, rest from o where cap * rest >= (total - capped) * w order by capped, rest limit 1)
, t as (select o.source, o.source_size, least(cap::double, coalesce((total - l.capped)::double * w / l.rest, cap::double)) target from o left join l on true)
, n as (select *, case when source_size > 0 then floor(target / source_size) else 0 end::bigint whole from t)
, b as (select source, h, sum(size)::bigint size from d group by all)
, r as (select b.*, target - whole * source_size need, sum(size) over (partition by b.source order by h) upto from b join n on b.source is not distinct from n.source)
, c as (select source, max(need) need, coalesce(max(case when upto <= need or upto - need < need - (upto - size) then h + 1 end), 0) cut from r group by source)
, k as (select c.source, cut, any_value(need) - coalesce(sum(case when h < cut then size end), 0) short from c join b on b.source is not distinct from c.source group by all)
, x as (select k.source, arg_min(h, {'a': abs(abs(short) - size), 'h': h}) odd from k join b on b.source is not distinct from k.source
    where (h < cut) = (short < 0) and abs(abs(short) - size) < abs(short) group by k.source)
select d.doc_id, d.size, n.source_size, n.target, d.size * least(3, whole + ((d.h < cut) <> coalesce(d.h = odd, false))::bigint) taken
from d join n on d.source is not distinct from n.source join c on d.source is not distinct from c.source left join x on d.source is not distinct from x.source
"""
