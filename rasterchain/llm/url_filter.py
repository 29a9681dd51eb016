"""URL filters by equality joins of hashed host-suffix and path-prefix expressions.

A url stands for the expressions made of one of its host's suffixes (whole labels) and one of
its path's prefixes; a rule is one such expression. Both sides meet on the first bytes of the
expression's SHA-256, which are then confirmed by the whole digest. Suffixes and prefixes are
tried at the lengths that rules have. Of the rules that fit, the longest decides.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rasterchain.llm.common import broadcast_if_small, checkpoint

#: Rules of the query (fixed values): verdict, host, path.
RULES = (
    ("allow", "org", "/"),
    ("block", "example.org", "/es/"),
    ("block", "example.org", "/en/1"),
    ("allow", "com", "/fr/"),
    ("block", "com", "/de/"),
)
#: Hexadecimal digits of the digest that meet first.
SHORT = 8
DEFAULT = "allow"


def url_host(url: Column) -> Column:
    """After the first :// up to /, ?, # or the end, A-Z lower-cased; empty if there is none."""
    rest = F.substring_index(F.substring_index(F.substring_index(_after_scheme(url), "/", 1), "?", 1), "#", 1)
    return F.translate(rest, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def url_path(url: Column) -> Column:
    """What follows the host up to ?, # or the end; empty if there is none."""
    rest = F.substring_index(F.substring_index(_after_scheme(url), "?", 1), "#", 1)
    slash = F.instr(rest, "/")
    return F.when(slash > 0, F.substr(rest, slash)).otherwise(F.lit(""))


def _after_scheme(url: Column) -> Column:
    at = F.instr(url, "://")
    return F.when(at > 0, F.substr(url, at + 3)).otherwise(F.lit(""))


def rule_table(spark, rules=RULES) -> DataFrame:
    """(verdict, host, path), as filter_urls takes it."""
    return spark.createDataFrame(list(rules), "verdict string, host string, path string")


def filter_urls(pages: DataFrame, rules: DataFrame, url_col: str = "url", default: str = DEFAULT) -> DataFrame:
    """pages with host, path, rule and verdict, one row per input row.

    Null urls and urls without :// have an empty host and path, which no rule fits; they and
    all others without a rule get the default verdict and a null rule. A rule fits its host
    and every subdomain, if the url's path begins with the rule's. Of equally long rules, the
    longer host decides, then block before allow. Rules with a null part or an empty host are ignored;
    repeated rules count once. Columns of pages with these names are replaced.
    """
    keep = [c for c in pages.columns if c not in ("host", "path", "rule", "verdict")]
    digest = F.sha2(F.concat("host", F.lit("\n"), "path"), 256)
    known = checkpoint(rules.where("host is not null and host != '' and path is not null and verdict is not null").groupBy("host", "path").agg(F.max(F.struct((F.col("verdict") == "block").alias("b"), F.col("verdict"))).getField("verdict").alias("of")).withColumns({"digest": digest, "short": F.substring(digest, 1, SHORT)}))
    # as many as there are different lengths (of paths, and of hosts in labels), not rules
    lengths = [r["n"] for r in known.select(F.length("path").alias("n")).distinct().orderBy("n").collect()]
    depths = [r["n"] for r in known.select(F.size(F.split("host", r"\.")).alias("n")).distinct().orderBy("n").collect()]
    rows = pages.select(F.struct(*[F.col(c) for c in keep]).alias("row"), F.coalesce(F.col(url_col), F.lit("")).alias("url")).select("row", url_host(F.col("url")).alias("host"), url_path(F.col("url")).alias("path"))
    # the verdict hangs on host and path alone: each pair is expanded once, and no row needs a number
    pairs = rows.where("host != ''").select("host", "path").distinct()
    dots = F.length("host") - F.length(F.replace(F.col("host"), F.lit("."), F.lit("")))
    hosts = F.transform(F.filter(F.array(*[F.lit(n) for n in depths]).cast("array<int>"), lambda x: x <= dots + 1), lambda x: F.call_function("substring_index", "host", F.lit("."), -x))
    paths = F.transform(F.filter(F.array(*[F.lit(n) for n in lengths]).cast("array<int>"), lambda x: x <= F.length("path")), lambda x: F.substring("path", F.lit(1), x))
    one = pairs.select("host", "path", F.explode(hosts).alias("h"))
    each = one.select("host", "path", "h", F.explode(paths).alias("p")).select(F.col("host").alias("of_host"), F.col("path").alias("of_path"), F.sha2(F.concat("h", F.lit("\n"), "p"), 256).alias("full"))
    short = each.select("of_host", "of_path", "full", F.substring("full", 1, SHORT).alias("at"))
    met = short.join(broadcast_if_small(known.withColumnRenamed("short", "at")), "at").where("full = digest")
    order = F.struct(F.length("host") + F.length("path"), F.length("host"), F.col("of") == "block")
    best = met.groupBy("of_host", "of_path").agg(F.max_by(F.struct(F.concat("host", "path").alias("rule"), F.col("of").alias("verdict")), order).alias("best"))
    return rows.join(best, (F.col("host") == F.col("of_host")) & (F.col("path") == F.col("of_path")), "left").select("row.*", "host", "path", F.col("best.rule").alias("rule"), F.coalesce("best.verdict", F.lit(default)).alias("verdict"))


def op2_url_filter(spark, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    return filter_urls(pages, rule_table(spark)).select("page_id", "host", "path", "rule", "verdict")


#: DuckDB SQL for op2_url_filter.
OP2_SQL = """
with rules(verdict, rhost, rpath) as (values ('allow', 'org', '/'), ('block', 'example.org', '/es/'), ('block', 'example.org', '/en/1'), ('allow', 'com', '/fr/'), ('block', 'com', '/de/'))
, r as (select page_id, row_number() over () n, case when instr(url, '://') > 0 then substr(url, instr(url, '://') + 3) else '' end rest from pages)
, p as (select page_id, n, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') host,
    regexp_extract(rest, '^[^/?#]*(/[^?#]*)', 1) path from r)
, m as (select n, arg_max({'rule': rhost || rpath, 'verdict': verdict}, length(rhost || rpath)) b from p join rules
    on (host = rhost or ends_with(host, '.' || rhost)) and starts_with(path, rpath) group by n)
select page_id, host, path, b.rule as rule, coalesce(b.verdict, 'allow') verdict from p left join m using (n)
"""
