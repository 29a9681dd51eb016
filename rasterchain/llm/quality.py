"""Quality rules with thresholds that adapt to each language and source. DataFrame functions only.

Signals of a text are measured in its own row, without a shuffle. For each signal, language
and source a relative-error quantile sketch is kept: values fall into buckets whose bounds
grow by a constant factor, and a bucket holds a count. Such sketches merge by adding counts,
so tasks pre-aggregate them and reruns agree exactly.

Every group is read with PRIOR rows' weight of its language's sketch added to its own, and
every language with as much of the sketch of all rows: a group of few rows follows its
language, one of many its own rows, and nothing changes at any size. Thresholds are fences
around the quartiles, SPREAD quartile distances away on the sketch's logarithmic scale. Values of
zero (no symbols, no repeated line) are never outside. A text is kept if each of its signals
lies within the fences of its group or of its language, so that a group which is mostly
copies of one text, whose quartiles meet, does not reject its other texts.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from rasterchain.llm.common import WORD, broadcast_if_small, checkpoint, saved, text_or_empty

#: Base rules of the operator.
MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
SYMBOLS = r"[#*$%&|<>]"

#: Relative width of the sketch's buckets.
GAMMA = 1.01
#: Rows' weight that a language's sketch adds to a group's, and that of all rows to a language's.
PRIOR = 20
#: Distance of the fences from the quartiles, in quartile distances.
SPREAD = 3

#: Signals that the fences judge: name, dividend and divisor.
SIGNALS = (
    ("symbols", "n_symbols", "word_chars"),
    ("dup_lines", "n_dup_lines", "n_lines"),
    ("repeats", "n_repeat_words", "n_words"),
    ("word_length", "word_chars", "n_words"),
    ("letters", "word_chars - n_symbols", "n_words"),
)
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "base_failed")


def measured(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines (long) and base_failed.

    Null and empty texts have zeros and fail. Columns of docs with these names are replaced.
    """
    text = text_or_empty(text_col)
    out = docs.withColumns({
        "_w": F.transform(F.filter(F.split(text, r"[\x20\x09-\x0D]+"), lambda w: w != ""), lambda w: F.xxhash64(w)),
        "_l": F.filter(F.split(text, "\n"), lambda x: x.rlike(WORD)),
    })
    # hashes of all three-word windows, and of those found twice or more
    out = out.withColumn("_t", F.expr("if(size(_w) < 3, cast(array() as array<bigint>), transform(slice(_w, 1, size(_w) - 2), (x, i) -> xxhash64(x, _w[i + 1], _w[i + 2])))"))
    out = out.withColumn("_s", F.expr("sort_array(_t)"))
    out = out.withColumn("_d", F.expr("array_distinct(filter(_s, (x, i) -> i > 0 and x = _s[i - 1]))"))
    # places of the latter: looked up in a short list, else by sorting (hash, place)
    out = out.withColumn("_b", F.expr("if(size(_d) <= 24, null, sort_array(transform(_t, (x, i) -> named_struct('h', x, 'p', i))))"))
    out = out.withColumn("_p", F.expr("""case when size(_d) = 0 then cast(array() as array<int>)
        when size(_d) <= 24 then filter(transform(_t, (x, i) -> if(array_contains(_d, x), i, -1)), i -> i >= 0)
        else sort_array(transform(filter(_b, (b, j) -> (j > 0 and _b[j - 1].h = b.h) or (j + 1 < size(_b) and get(_b, j + 1).h = b.h)), b -> b.p)) end"""))
    n_words, n_repeat = F.size("_w").cast("long"), F.expr("aggregate(_p, named_struct('n', 0L, 'z', -3), (a, p) -> named_struct('n', a.n + least(3, p - a.z), 'z', p), a -> a.n)")
    found = {
        "n_words": n_words,
        "word_chars": F.length(F.regexp_replace(text, r"[\x20\x09-\x0D]+", "")).cast("long"),
        "n_symbols": (F.length(text) - F.length(F.regexp_replace(text, SYMBOLS, ""))).cast("long"),
        "n_dup_lines": (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long"),
        "n_repeat_words": n_repeat,
        "n_lines": F.size("_l").cast("long"),
    }
    # made by a generator, through which no filter on the measures is pushed: pushed down, it would measure again for each use
    out = out.withColumn("_m", F.explode(F.array(F.struct(*[e.alias(c) for c, e in found.items()]))))
    failed = (F.col("_m.n_words") < MIN_WORDS) | (100 * F.col("_m.n_repeat_words") > MAX_REPEAT_PERCENT * F.col("_m.n_words"))
    return out.withColumns({c: F.col(f"_m.{c}") for c in found} | {"base_failed": failed}).drop("_w", "_l", "_t", "_s", "_d", "_b", "_p", "_m")


def bucket(top: str, bottom: str) -> Column:
    """The sketch's bucket of a ratio; null for zero and where there is no divisor."""
    some = (F.expr(bottom) > 0) & (F.expr(top) > 0)
    return F.when(some, F.ceil(F.log(F.expr(f"({top}) / ({bottom})")) / math.log(GAMMA)).cast("int"))


def sketches(signals: DataFrame, lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """(lang, source, signal, bucket, n): quantile sketches, merged by adding n."""
    each = F.explode(F.array(*[F.struct(F.lit(name).alias("signal"), bucket(t, b).alias("bucket")) for name, t, b in SIGNALS]))
    # texts that fail the base rules say nothing of their group
    passed = signals.where(~F.col("base_failed"))
    return passed.select(F.col(lang_col).alias("lang"), F.col(source_col).alias("source"), each.alias("x")).where("x.bucket is not null").groupBy("lang", "source", "x.signal", "x.bucket").agg(F.count("*").alias("n"))


def blended(own: DataFrame, above: DataFrame, keys: list[str], shared: list[str]) -> DataFrame:
    """(keys, signal, bucket, n): own counts and PRIOR rows of the sketch above, brought to a common denominator.

    shared are the keys that above has too. Counts become products of up to three counts;
    they are whole numbers, so that sums agree in any order.
    """
    wide = above.withColumn("of", F.sum("n").over(Window.partitionBy(*shared, "signal"))).select(*[F.col(k).alias(f"_{k}") for k in (*shared, "signal", "bucket")], (F.col("n") * PRIOR).cast("decimal(38,0)").alias("_n"), F.col("of").cast("decimal(38,0)").alias("_of"))
    one = own.select(*keys, "signal").distinct()
    same = lambda names: [F.col(k).eqNullSafe(F.col(f"_{k}")) for k in names]
    of = wide.groupBy(*[f"_{k}" for k in (*shared, "signal")]).agg(F.max("_of").alias("_of"))
    mine = own.join(of, same([*shared, "signal"])).select(*keys, "signal", "bucket", (F.col("n").cast("decimal(38,0)") * F.col("_of")).cast("decimal(38,0)").alias("n"))
    lent = one.join(wide, same([*shared, "signal"])).select(*keys, "signal", F.col("_bucket").alias("bucket"), F.col("_n").alias("n"))
    return mine.union(lent).groupBy(*keys, "signal", "bucket").agg(F.sum("n").cast("decimal(38,0)").alias("n"))


def bounds(sketch: DataFrame, keys: list[str], spread: int) -> DataFrame:
    """(keys, signal, lo, hi): the buckets between which a group's values lie."""
    w = Window.partitionBy(*keys, "signal")
    run = sketch.withColumns({"below": F.sum("n").over(w.orderBy("bucket")), "total": F.sum("n").over(w)})
    at = {f"b{q}": F.min(F.when(4 * F.col("below") >= q * F.col("total"), F.col("bucket"))) for q in (1, 3)}
    picked = run.groupBy(*keys, "signal").agg(*[c.alias(name) for name, c in at.items()])
    # a quartile may be off by the sketch's bucket
    reach = F.lit(spread) * (F.col("b3") - F.col("b1")) + 1
    return picked.select(*keys, "signal", (F.col("b1") - reach).alias("lo"), (F.col("b3") + reach).alias("hi"))


def fences(sketch: DataFrame, spread: int = SPREAD) -> DataFrame:
    """(lang, source, lo_* and hi_* of each signal) as buckets; sketch should be materialised. One row a group."""
    of_lang = sketch.groupBy("lang", "signal", "bucket").agg(F.sum("n").alias("n"))
    every = sketch.groupBy("signal", "bucket").agg(F.sum("n").alias("n"))
    lang = checkpoint(blended(of_lang, every, ["lang"], []))
    group = bounds(blended(sketch, lang, ["lang", "source"], ["lang"]), ["lang", "source"], spread)
    wider = bounds(lang, ["lang"], spread).select(F.col("lang").alias("_lang"), F.col("signal").alias("_signal"), F.col("lo").alias("_lo"), F.col("hi").alias("_hi"))
    both = group.join(wider, F.col("lang").eqNullSafe(F.col("_lang")) & (F.col("signal") == F.col("_signal")))
    columns = []
    for name, _, _ in SIGNALS:
        mine = F.col("signal") == name
        columns += [F.max(F.when(mine, F.least("lo", "_lo"))).alias(f"lo_{name}"), F.max(F.when(mine, F.greatest("hi", "_hi"))).alias(f"hi_{name}")]
    return both.groupBy("lang", "source").agg(*columns)


def judged(signals: DataFrame, limits: DataFrame, lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """signals with kept: false if base_failed, else true if every signal lies within the fences of its group."""
    ends = [f"{side}_{name}" for name, _, _ in SIGNALS for side in ("lo", "hi")]
    own = limits.select(F.col("lang").alias("_lang"), F.col("source").alias("_source"), F.struct(*ends).alias("_own"))
    out = signals.join(broadcast_if_small(own), F.col(lang_col).eqNullSafe(F.col("_lang")) & F.col(source_col).eqNullSafe(F.col("_source")), "left")
    inside = F.lit(True)
    for name, t, b in SIGNALS:
        inside = inside & F.coalesce(bucket(t, b).between(F.col(f"_own.lo_{name}"), F.col(f"_own.hi_{name}")), F.lit(True))
    return out.withColumn("kept", ~F.col("base_failed") & inside).drop("_lang", "_source", "_own")


def ruled(signals: DataFrame, lang_col: str = "lang", source_col: str = "source", spread: int = SPREAD) -> DataFrame:
    """signals (measured rows) with kept. They are written once, so that no text is measured twice."""
    signals = saved(signals)
    limits = checkpoint(fences(checkpoint(sketches(signals, lang_col, source_col)), spread))
    return judged(signals, limits, lang_col, source_col)


def quality_rules(docs: DataFrame, text_col: str = "text", lang_col: str = "lang", source_col: str = "source", spread: int = SPREAD) -> DataFrame:
    """docs with the measures and kept (boolean); nothing is dropped here.

    Null languages and sources form groups of their own. The thresholds are a checkpointed
    table of one row a group. If docs lacks its text column's content (null), base_failed holds.
    Repeated rows count each time; an empty table gives an empty result.
    """
    return ruled(measured(docs, text_col), lang_col, source_col, spread)


def op3_quality(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "lang", "source", "text")
    return ruled(measured(docs).drop("text")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def _sql() -> str:
    """DuckDB SQL for op3_quality: the same measures, sketches, fences and verdicts."""

    def at(t: str, b: str) -> str:
        return f"case when {b} > 0 and {t} > 0 then ceil(ln(({t})::double / ({b})) / {math.log(GAMMA)!r})::int end"

    each = " union all ".join(f"select lang, source, '{name}' signal, {at(t, b)} bucket from m where not base_failed" for name, t, b in SIGNALS)

    def ends(source: str, keys: str) -> str:
        q = ", ".join(f"min(case when 4 * below >= {q} * total then bucket end) b{q}" for q in (1, 3))
        return f"select {keys}, signal, b1 - {SPREAD} * (b3 - b1) - 1 lo, b3 + {SPREAD} * (b3 - b1) + 1 hi from (select {keys}, signal, {q} from (select *, sum(n) over (partition by {keys}, signal order by bucket) below, sum(n) over (partition by {keys}, signal) total from {source}) group by {keys}, signal)"

    tests, joins = [], []
    for name, t, b in SIGNALS:
        joins.append(f"left join o o_{name} on o_{name}.signal = '{name}' and o_{name}.lang is not distinct from m.lang and o_{name}.source is not distinct from m.source")
        tests.append(f"coalesce({at(t, b)} between o_{name}.lo and o_{name}.hi, true)")
    return rf"""
with w as (
  select doc_id, lang, source, coalesce(text, '') t, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') ws,
         list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) ls from documents
), g as (select doc_id, i, ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2] k from w, unnest(range(1, len(ws) - 1)) r(i))
, d as (select doc_id, i, count(*) over (partition by doc_id, k) c from g)
, p as (select distinct doc_id, i + o j from d, (values (0), (1), (2)) v(o) where c > 1)
, n as (select doc_id, count(*) r from p group by doc_id)
, m as (select doc_id, lang, source, len(ws)::bigint n_words, length(regexp_replace(t, '[\x20\x09-\x0D]+', '', 'g'))::bigint word_chars,
  (length(t) - length(regexp_replace(t, '{SYMBOLS}', '', 'g')))::bigint n_symbols,
  (len(ls) - len(list_distinct(ls)))::bigint n_dup_lines, len(ls)::bigint n_lines, coalesce(r, 0)::bigint n_repeat_words,
  len(ws) < {MIN_WORDS} or 100 * coalesce(r, 0) > {MAX_REPEAT_PERCENT} * len(ws) base_failed from w left join n using (doc_id))
, s as (select lang, source, signal, bucket, count(*)::hugeint n from ({each}) where bucket is not null group by all)
, a as (select signal, bucket, sum(n) n from s group by all)
, ta as (select signal, sum(n) k from a group by all)
, sl as (select lang, signal, bucket, sum(n) n from s group by all)
, l as (select lang, signal, bucket, sum(n) n from (
    select lang, signal, bucket, n * k n from sl join ta using (signal)
    union all select lang, signal, bucket, {PRIOR} * n from (select distinct lang, signal from sl) join a using (signal)) group by all)
, tl as (select lang, signal, sum(n) k from l group by all)
, g2 as (select lang, source, signal, bucket, sum(n) n from (
    select s.lang, source, s.signal, bucket, n * k n from s join tl on tl.lang is not distinct from s.lang and tl.signal = s.signal
    union all select x.lang, x.source, x.signal, l.bucket, {PRIOR} * l.n from (select distinct lang, source, signal from s) x join l on l.lang is not distinct from x.lang and l.signal = x.signal) group by all)
, fl as ({ends("l", "lang")})
, fg as ({ends("g2", "lang, source")})
, o as (select fg.lang, fg.source, fg.signal, least(fg.lo, fl.lo) lo, greatest(fg.hi, fl.hi) hi from fg join fl on fg.lang is not distinct from fl.lang and fg.signal = fl.signal)
select m.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, not base_failed and {" and ".join(tests)} kept from m {" ".join(joins)}
"""


OP3_SQL = _sql()
