"""URL filters: a sort-merge range join of reversed-host keys with a stack of active nested rules.

The key of a host is its labels from the last to the first, each ended by a dot (``a.example.net`` is
``net.example.a.``). A rule's host and all its subdomains are the keys of one interval, from ``net.example.`` to
just before ``net.example/``. Such intervals nest or are apart, so one sweep over the sorted keys keeps a stack:
level d holds the rules of the interval with d labels that is open now; an interval's end empties its level. A url
takes the longest rule on the stack whose path its own path starts with.

Spark's own functions only. One shuffle, by (top label, salt): the rules go to each salt, the urls are dealt out by a
hash of the whole row, so a host with a third of all rows spreads over all tasks.
"""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from relayout.llm.shared import parts, table

#: Fixed values of the query: host, path, verdict.
RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))


def split_url(url: Column) -> tuple[Column, Column]:
    """Host with A-Z lower-cased, and path; both empty for null and where ``://`` is missing."""
    there = F.coalesce(F.instr(url, "://") > 0, F.lit(False))
    rest = F.substring(url, F.instr(url, "://") + 3, F.length(url))
    host = F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), string.ascii_uppercase, string.ascii_lowercase)
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return F.when(there, host).otherwise(""), F.when(there, path).otherwise("")


def host_key(host: Column) -> Column:
    return F.concat(F.array_join(F.reverse(F.split(host, r"\.")), "."), F.lit("."))


def judge_urls(pages: DataFrame, rules: DataFrame, url: str = "url", default: str = "allow", salts: int | None = None) -> DataFrame:
    """pages with host, path, rule (null if none fits) and verdict; columns of these names are replaced.

    rules: (host, path, verdict). The longest rule (host and path together) wins; of two alike, ``block``. A null or
    empty url has an empty host and path and takes the default. Rules with a null or empty host never fit; a null
    path is empty. Repeated rules count once, repeated pages are each judged. Empty tables: no rows, or only defaults.
    """
    salts = salts or parts(pages.sparkSession)
    own = [c for c in pages.columns if c not in ("host", "path", "rule", "verdict")]
    host, path = split_url(F.col(url))
    hashed = [F.col(c) for c, kind in pages.dtypes if "map<" not in kind and kind not in ("variant", "void")]
    rows = pages.select(
        F.struct(*own).alias("page"),
        host.alias("host"),
        path.alias("path"),
        F.pmod(F.xxhash64(*hashed), F.lit(salts)).cast("int").alias("salt"),
    )
    rows = rows.select("*", host_key(F.col("host")).alias("key"), F.lit(2).alias("kind"))

    rules = rules.filter(F.coalesce(F.col("host"), F.lit("")) != "").select(
        F.col("host"), F.coalesce(F.col("path"), F.lit("")).alias("path"), F.col("verdict")
    )
    rules = rules.groupBy("host").agg(
        F.collect_set(
            F.struct(
                (F.length("host") + F.length("path")).alias("size"), F.col("verdict"), F.concat("host", "path").alias("rule"), F.col("path")
            )
        ).alias("held")
    )
    rules = rules.select("held", host_key(F.col("host")).alias("low"), F.size(F.split("host", r"\.")).alias("level"))
    deepest = rules.agg(F.max("level")).first()[0] or 0
    nothing = F.filter("held", lambda _: F.lit(False))
    high = F.concat(F.expr("substring(low, 1, length(low) - 1)"), F.lit("/"))
    events = rules.select(
        "level",
        F.explode(
            F.array(
                F.struct(F.col("low").alias("key"), F.lit(1).alias("kind"), F.col("held").alias("held")),
                F.struct(high.alias("key"), F.lit(0).alias("kind"), nothing.alias("held")),
            )
        ).alias("e"),
        F.split("low", r"\.")[0].alias("top"),
    ).select("level", "e.*", "top", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"))

    both = rows.withColumn("top", F.split("key", r"\.")[0]).unionByName(events, allowMissingColumns=True)
    sweep = Window.partitionBy("top", "salt").orderBy("key", "kind").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    stack = [F.last(F.when(F.col("level") == d, F.col("held")), ignorenulls=True).over(sweep) for d in range(1, deepest + 1)]
    swept = both.select("page", "host", "path", "kind", *(s.alias(f"level_{d}") for d, s in enumerate(stack))).filter("kind = 2")
    if stack:
        none = F.array().cast("array<struct<size:int,verdict:string,rule:string,path:string>>")
        active = F.flatten(F.array(*(F.coalesce(F.col(f"level_{d}"), none) for d in range(deepest))))
        best = F.array_max(F.filter(active, lambda r: F.startswith(F.col("path"), r["path"])))
        swept = swept.withColumn("best", best)
        rule, verdict = F.col("best.rule"), F.coalesce(F.col("best.verdict"), F.lit(default))
    else:
        rule, verdict = F.lit(None).cast("string"), F.lit(default)
    return swept.select(*(F.col("page")[c].alias(c) for c in own), "host", "path", rule.alias("rule"), verdict.alias("verdict"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = ", ".join(f"('{h}', '{p}', '{v}')" for h, p, v in RULES)
    rules = spark.sql(f"SELECT * FROM VALUES {rows} AS t(host, path, verdict)")
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    return judge_urls(pages, rules).select("page_id", "host", "path", "rule", "verdict")


ORACLE = """
WITH cut AS (
  SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages
), parsed AS (
  SELECT page_id, regexp_extract(rest, '^([^/?#]*)', 1) AS raw_host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM cut
), hosts AS (
  SELECT page_id, path, translate(raw_host, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host FROM parsed
), rules(h, p, v) AS (VALUES ('net', '/', 'block'), ('example.net', '/en/', 'allow'), ('example.com', '/de/', 'block'), ('org', '/fr/', 'allow'))
SELECT page_id, any_value(host) AS host, any_value(path) AS path, max_by(h || p, length(h || p)) AS rule,
       coalesce(max_by(v, length(h || p)), 'allow') AS verdict
FROM hosts LEFT JOIN rules ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p)
GROUP BY page_id
"""
