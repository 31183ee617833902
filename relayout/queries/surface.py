"""The relational surface around the methods: scans, joins, aggregates, windows, set operations, functions, streams."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from relayout.functions import sqlfun
from relayout.plans.layout import Splits
from relayout.queries import core, query, sql
from relayout.sources import tables as src
from relayout.streaming import volumes

T = src.table

# ---- scans --------------------------------------------------------------------------------------

_ORDER = {"region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey", "lineitem": "l_orderkey", "events": "event_id", "documents": "doc_id", "embeddings": "vec_id", "pages": "page_id", "benchmark": "item_id", "labels": "doc_id", "conversations": "conv_id"}
for _name, _key in _ORDER.items():
    query(f"scan_{_name}", f"SELECT count(*) AS n, CAST(sum({_key}) AS BIGINT) AS keys FROM {_name}")(lambda s, d, t=_name, k=_key: src.read(s, f"{d}/{t}.parquet").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col(k).cast("long")).alias("keys")))
query("scan_entries_emb", core.SELECT_EMB)(lambda s, d: core.emb(s, d))
query("scan_entries_lineitem", "SELECT l_suppkey - 1 AS i, l_partkey - 1 AS j, sum(l_quantity) AS v FROM lineitem GROUP BY 1, 2")(lambda s, d: src.supp_part(s, d))
query("project_cells", "SELECT o_orderkey AS i, o_custkey AS j, CAST(floor(o_totalprice * 1000) AS BIGINT) AS v FROM orders")(lambda s, d: T(s, d, "orders").select(F.col("o_orderkey").alias("i"), F.col("o_custkey").alias("j"), src.fixed(F.col("o_totalprice")).alias("v")))
query("filter_window", f"WITH {sql.EMB} SELECT * FROM emb WHERE i BETWEEN 10 AND 99 AND j < 7")(lambda s, d: core.emb(s, d).filter((F.col("i") >= 10) & (F.col("i") < 100) & (F.col("j") < 7)))
query("filter_predicates", """SELECT doc_id, CASE WHEN n_chars > 5000 THEN 'long' WHEN n_chars > 500 THEN 'medium' ELSE 'short' END AS size FROM documents
  WHERE lang IN ('de', 'fr') AND text IS NOT NULL AND source IS NOT DISTINCT FROM 'src3' AND regexp_matches(text, '^[A-Z]')""")(
    lambda s, d: T(s, d, "documents").filter(F.col("lang").isin("de", "fr") & F.col("text").isNotNull() & F.col("source").eqNullSafe("src3") & F.col("text").rlike("^[A-Z]")).select("doc_id", F.when(F.col("n_chars") > 5000, "long").when(F.col("n_chars") > 500, "medium").otherwise("short").alias("size"))
)

# ---- joins --------------------------------------------------------------------------------------

for _how in ("inner", "left", "right", "full"):
    query(f"join_{_how}", f"SELECT o_orderkey, c_custkey, c_nationkey FROM orders {_how.upper()} JOIN customer ON o_custkey = c_custkey")(
        lambda s, d, how=_how: T(s, d, "orders").join(T(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey"), how).select("o_orderkey", "c_custkey", "c_nationkey")
    )
query("join_broadcast", f"WITH {sql.TRADE} SELECT src, CAST([3, 2, 4, 1, 0][dst + 1] AS INTEGER) AS site, vol FROM tr")(lambda s, d: core.region(s, d).join(F.broadcast(core.frame(s, list(enumerate(core.SIGMA)), "dst int, site int")), "dst").select("src", "site", "vol"))


def bounds(spark: SparkSession) -> DataFrame:
    return Splits(500, bounds=(0, 60, 61, 200, 450, 500)).frame(spark)


def spans(df: DataFrame, k: Column, x: str) -> DataFrame:
    """(k, lo, hi): the range of x in each group."""
    return df.groupBy(k.cast("long").alias("k")).agg(F.min(x).cast("long").alias("lo"), (F.max(x) + 1).cast("long").alias("hi"))


BOUNDS = "b(k, lo, hi) AS (VALUES (0, 0, 60), (1, 60, 61), (2, 61, 200), (3, 200, 450), (4, 450, 500))"
query("join_range", f"WITH {BOUNDS} SELECT vec_id, CAST(k AS BIGINT) AS k FROM embeddings JOIN b ON vec_id >= lo AND vec_id < hi")(lambda s, d: T(s, d, "embeddings").join(F.broadcast(bounds(s)), (F.col("vec_id") >= F.col("lo")) & (F.col("vec_id") < F.col("hi"))).select("vec_id", "k"))


@query("join_asof", "SELECT e.event_id, max(p.event_id) AS before FROM (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase') e LEFT JOIN (SELECT max(event_id) AS event_id, user_id, ts FROM events WHERE event_type = 'click' GROUP BY user_id, ts) p ON p.user_id = e.user_id AND p.ts = (SELECT max(ts) FROM events q WHERE q.event_type = 'click' AND q.user_id = e.user_id AND q.ts <= e.ts) GROUP BY e.event_id")
def join_asof(spark: SparkSession, d: str) -> DataFrame:
    """Of each purchase the user's last click so far: one sort by user and time, no range join."""
    e = T(spark, d, "events").filter(F.col("event_type").isin("click", "purchase"))
    so_far = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    last = F.max(F.when(F.col("event_type") == "click", F.struct("ts", "event_id"))).over(so_far)
    return e.withColumn("last", last).filter("event_type = 'purchase'").select("event_id", F.col("last.event_id").alias("before"))


@query("join_interval", """WITH b AS (SELECT date_diff('day', DATE '1970-01-01', CAST(ts AS DATE)) AS k, min(event_id) AS lo, max(event_id) + 1 AS hi FROM events GROUP BY 1),
  size AS (SELECT coalesce(max(event_id) + 1, 0) AS m FROM events), q AS (SELECT k * 700 AS lo2, least(k * 700 + 700, m) AS hi2, k AS k2 FROM (SELECT unnest(range((m + 699) // 700)) AS k, m FROM size)) SELECT k AS ka, k2 AS kb FROM b JOIN q ON lo < hi2 AND lo2 < hi""")
def join_interval(spark: SparkSession, d: str) -> DataFrame:
    """Days' ranges of events against blocks of 700: which blocks a day's events lie in. Days are few."""
    events = T(spark, d, "events")
    m = events.agg(F.coalesce(F.max("event_id") + 1, F.lit(0))).first()[0]
    days_ = spans(events, F.datediff(F.to_date("ts"), F.lit("1970-01-01").cast("date")), "event_id")
    blocks = Splits(m, 700).frame(spark).toDF("k2", "lo2", "hi2")
    return blocks.join(F.broadcast(days_), (F.col("lo") < F.col("hi2")) & (F.col("lo2") < F.col("hi"))).select(F.col("k").alias("ka"), F.col("k2").alias("kb"))
query("join_cross", "WITH a AS (SELECT month(o_orderdate) AS k, min(o_custkey) AS lo, max(o_custkey) + 1 AS hi FROM orders GROUP BY 1), b AS (SELECT l_linenumber AS k, min(l_partkey) AS lo, max(l_partkey) + 1 AS hi FROM lineitem GROUP BY 1) SELECT CAST(a.k AS BIGINT) AS ka, CAST(b.k AS BIGINT) AS kb, CAST((a.hi - a.lo) * (b.hi - b.lo) AS BIGINT) AS area FROM a, b")(
    lambda s, d: spans(T(s, d, "orders"), F.month("o_orderdate"), "o_custkey").toDF("ka", "la", "ha").crossJoin(spans(T(s, d, "lineitem"), F.col("l_linenumber"), "l_partkey").toDF("kb", "lb", "hb")).select("ka", "kb", ((F.col("ha") - F.col("la")) * (F.col("hb") - F.col("lb"))).alias("area"))
)
query("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority LIKE '1%')")(lambda s, d: T(s, d, "customer").join(T(s, d, "orders").filter("o_orderpriority LIKE '1%'"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"))
query("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority LIKE '1%')")(lambda s, d: T(s, d, "customer").join(T(s, d, "orders").filter("o_orderpriority LIKE '1%'"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"))

# ---- aggregates ---------------------------------------------------------------------------------

query("agg_volume", "SELECT l_suppkey % 16 AS site, CAST(sum(l_quantity) AS BIGINT) AS vol, count(*) AS n, min(l_quantity) AS least, max(l_quantity) AS most FROM lineitem GROUP BY 1")(lambda s, d: T(s, d, "lineitem").groupBy((F.col("l_suppkey") % 16).alias("site")).agg(F.sum("l_quantity").cast("long").alias("vol"), F.count(F.lit(1)).alias("n"), F.min("l_quantity").alias("least"), F.max("l_quantity").alias("most")))
query("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")(lambda s, d: T(s, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users")))
for _kind, _fn in {"rollup": "rollup", "cube": "cube"}.items():
    query(f"agg_{_kind}", f"WITH {sql.TRADE} SELECT src, dst, CAST(sum(vol) AS BIGINT) AS vol FROM tr GROUP BY {_kind}(src, dst)")(lambda s, d, f=_fn: getattr(core.region(s, d), f)("src", "dst").agg(F.sum("vol").alias("vol")))


@query("agg_sets", f"WITH {sql.TRADE} SELECT src, dst, CAST(sum(vol) AS BIGINT) AS vol FROM tr GROUP BY GROUPING SETS ((src), (dst), ())")
def agg_sets(spark: SparkSession, d: str) -> DataFrame:
    return spark.sql("SELECT src, dst, sum(vol) AS vol FROM {t} GROUP BY GROUPING SETS ((src), (dst), ())", t=core.region(spark, d))


query("agg_pivot", f"WITH {sql.TRADE} SELECT src, " + ", ".join(f"CAST(sum(vol) FILTER (WHERE dst = {k}) AS BIGINT) AS to_{k}" for k in range(5)) + " FROM tr GROUP BY src")(lambda s, d: core.region(s, d).groupBy("src").pivot("dst", list(range(5))).sum("vol").toDF("src", *(f"to_{k}" for k in range(5))))
query("agg_argmax", f"WITH {sql.TRADE} SELECT dst, arg_max(src, vol) AS best, arg_min(src, vol) AS worst FROM tr GROUP BY dst")(lambda s, d: core.region(s, d).groupBy("dst").agg(F.max_by("src", "vol").alias("best"), F.min_by("src", "vol").alias("worst")))
query("agg_percentile", f"WITH {sql.TRADE} SELECT quantile_cont(vol, 0.5) AS median, quantile_cont(vol, 0.9) AS p90 FROM tr")(lambda s, d: core.region(s, d).agg(F.percentile("vol", 0.5).alias("median"), F.percentile("vol", 0.9).alias("p90")))

# ---- windows, order, sets -----------------------------------------------------------------------


def by():  # noqa: ANN201
    return Window.partitionBy("dst").orderBy(F.desc("vol"), "src")


query("win_rank", f"WITH {sql.TRADE} SELECT dst, src, CAST(row_number() OVER w AS INTEGER) AS place, CAST(rank() OVER w AS INTEGER) AS rnk, CAST(ntile(2) OVER w AS INTEGER) AS half FROM tr WINDOW w AS (PARTITION BY dst ORDER BY vol DESC, src)")(lambda s, d: core.region(s, d).select("dst", "src", F.row_number().over(by()).alias("place"), F.rank().over(by()).alias("rnk"), F.ntile(2).over(by()).alias("half")))
query("win_lead", f"WITH {sql.TRADE} SELECT dst, src, lead(vol) OVER w AS nxt, lag(vol) OVER w AS prev, first_value(src) OVER w AS top FROM tr WINDOW w AS (PARTITION BY dst ORDER BY vol DESC, src)")(lambda s, d: core.region(s, d).select("dst", "src", F.lead("vol").over(by()).alias("nxt"), F.lag("vol").over(by()).alias("prev"), F.first("src").over(by()).alias("top")))
DAY = "e AS (SELECT CAST(date_trunc('day', ts) AS DATE) AS day, count(*) AS n FROM events GROUP BY 1)"


def days(spark: SparkSession, d: str) -> DataFrame:
    return T(spark, d, "events").groupBy(F.to_date("ts").alias("day")).agg(F.count(F.lit(1)).alias("n"))


query("win_running", f"WITH {DAY} SELECT day, CAST(sum(n) OVER (ORDER BY day) AS BIGINT) AS upto FROM e")(lambda s, d: days(s, d).select("day", F.sum("n").over(Window.orderBy("day")).alias("upto")))
query("win_moving", f"WITH {DAY} SELECT day, CAST(sum(n) OVER (ORDER BY day ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS three FROM e")(lambda s, d: days(s, d).select("day", F.sum("n").over(Window.orderBy("day").rowsBetween(-2, 0)).alias("three")))
query("sort_parcels", f"WITH {sql.TRADE} SELECT src, dst, vol FROM tr ORDER BY vol DESC, src, dst LIMIT 10 OFFSET 3")(lambda s, d: core.region(s, d).select("src", "dst", "vol").orderBy(F.desc("vol"), "src", "dst").offset(3).limit(10))
query("topk_parcels", f"WITH {sql.TRADE} SELECT src, dst, vol FROM tr ORDER BY vol DESC, src, dst LIMIT 5")(lambda s, d: core.region(s, d).select("src", "dst", "vol").orderBy(F.desc("vol"), "src", "dst").limit(5))
query("topk_per_site", f"WITH {sql.TRADE} SELECT dst, src, vol FROM tr QUALIFY row_number() OVER (PARTITION BY dst ORDER BY vol DESC, src) <= 2")(lambda s, d: core.region(s, d).withColumn("k", F.row_number().over(by())).filter("k <= 2").select("dst", "src", "vol"))
_X, _Y = "SELECT k * 4 % 30 AS x FROM range(20) t(k)", "SELECT k * 6 % 36 AS x FROM range(20) t(k)"
for _name, (_sql, _df) in {
    "union": ("UNION", lambda a, b: a.union(b).distinct()), "union_all": ("UNION ALL", lambda a, b: a.unionByName(b)), "intersect": ("INTERSECT", lambda a, b: a.intersect(b)),
    "intersect_all": ("INTERSECT ALL", lambda a, b: a.intersectAll(b)), "except": ("EXCEPT", lambda a, b: a.subtract(b)), "except_all": ("EXCEPT ALL", lambda a, b: a.exceptAll(b)),
}.items():
    query(f"setop_{_name}", f"({_X}) {_sql} ({_Y})")(lambda s, d, f=_df: f(s.range(20).select((F.col("id") * 4 % 30).alias("x")), s.range(20).select((F.col("id") * 6 % 36).alias("x"))))

# ---- functions ----------------------------------------------------------------------------------

query("fn_string", "SELECT page_id, split_part(split_part(url, '://', 2), '/', 1) AS host, left(url, 5) AS head, strlen(html) AS bytes, concat_ws('|', page_id::VARCHAR, left(url, 4)) AS tag FROM pages")(
    lambda s, d: T(s, d, "pages").select("page_id", F.split_part(F.split_part("url", F.lit("://"), F.lit(2)), F.lit("/"), F.lit(1)).alias("host"), F.left("url", F.lit(5)).alias("head"), F.octet_length("html").cast("long").alias("bytes"), F.concat_ws("|", F.col("page_id").cast("string"), F.left("url", F.lit(4))).alias("tag"))
)
query("fn_date", "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS month, CAST(date_diff('day', DATE '1990-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days FROM orders")(lambda s, d: T(s, d, "orders").select("o_orderkey", F.trunc(F.to_date("o_orderdate"), "month").alias("month"), F.datediff(F.to_date("o_orderdate"), F.lit("1990-01-01").cast("date")).alias("days")))
query("fn_math", "SELECT o_orderkey, o_orderkey % 7 AS m, o_orderkey // 7 AS q, CAST(floor(o_totalprice / 100) AS BIGINT) AS f, greatest(o_orderkey, o_custkey) AS g FROM orders")(lambda s, d: T(s, d, "orders").select("o_orderkey", F.pmod("o_orderkey", F.lit(7)).alias("m"), F.expr("o_orderkey div 7").alias("q"), F.floor(F.col("o_totalprice") / 100).alias("f"), F.greatest("o_orderkey", "o_custkey").alias("g")))
query("fn_array", "SELECT vec_id, CAST(list_sum(list_transform(embedding[1:8], lambda x: CAST(floor(CAST(x AS DOUBLE) * 1000) AS BIGINT))) AS BIGINT) AS head, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")(
    lambda s, d: T(s, d, "embeddings").select("vec_id", F.aggregate(F.transform(F.slice("embedding", 1, 8), src.fixed), F.lit(0).cast("long"), lambda a, x: a + x).alias("head"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"))
)
query("fn_map", "SELECT n_nationkey, CAST([3, 2, 4, 1, 0][n_regionkey + 1] AS INTEGER) AS site FROM nation")(lambda s, d: T(s, d, "nation").select("n_nationkey", F.create_map(*(F.lit(x) for kv in enumerate(core.SIGMA) for x in kv))[F.col("n_regionkey")].alias("site")))
query("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS VARCHAR) AS k FROM events")(lambda s, d: T(s, d, "events").select("event_id", F.get_json_object("props", "$.k").alias("k")))
query("udf_owner", f"WITH {sql.EMB} SELECT i, j, {sql.own('i', 'j', 8, 8, 4, 4)} AS site FROM emb")(lambda s, d: sqlfun.owner_by_name(s, core.emb(s, d)))
query("udaf_gain", f"WITH g AS ({core.GAIN_VOLUME}) SELECT CAST(sum(gain) AS BIGINT) AS total_gain FROM g WHERE site = {core.SIGMA}[role + 1]")(lambda s, d: sqlfun.gain_by_udaf(s, core.region(s, d), core.SIGMA))
query("udtf_overlay", "SELECT lo, coalesce(lead(lo) OVER (ORDER BY lo), 500) AS hi, lo // 7 AS ka, lo // 12 AS kb FROM (SELECT DISTINCT lo FROM (SELECT k * 7 AS lo FROM range(72) a(k) UNION ALL SELECT k * 12 FROM range(42) b(k)))")(lambda s, d: sqlfun.overlay_by_name(s, 500, 7, 12))
query("udtf_assignment", core.BEST_SQL)(lambda s, d: sqlfun.assignment_by_name(s, core.region(s, d)))


@query("sql_report", f"WITH {sql.TRADE} SELECT src, CAST(sum(vol) AS BIGINT) AS sent, CAST(sum(vol) FILTER (WHERE src <> dst) AS BIGINT) AS remote FROM tr GROUP BY src HAVING sum(vol) > 0")
def sql_report(spark: SparkSession, d: str) -> DataFrame:
    core.region(spark, d).createOrReplaceTempView("relayout_parcels")
    return spark.sql("SELECT src, sum(vol) AS sent, sum(vol) FILTER (WHERE src <> dst) AS remote FROM relayout_parcels GROUP BY src HAVING sum(vol) > 0")


# ---- streams (their batch form; tests run the streams against it) ---------------------------------

SRC, DST = "user_id % 5", "CASE event_type WHEN 'click' THEN 0 WHEN 'purchase' THEN 1 WHEN 'view' THEN 2 ELSE 3 END"
query("stream_tumbling", f"SELECT time_bucket(INTERVAL '1 day', ts) AS start, CAST({SRC} AS INTEGER) AS src, CAST({DST} AS INTEGER) AS dst, count(*) AS n FROM events GROUP BY 1, 2, 3")(lambda s, d: volumes.windowed(volumes.events(T(s, d, "events")), "1 day").withColumn("start", F.col("start").cast("timestamp_ntz")))
query("stream_sliding", f"""SELECT start, CAST(src AS INTEGER) AS src, CAST(dst AS INTEGER) AS dst, count(*) AS n FROM (SELECT time_bucket(INTERVAL '12 hours', ts) - k * INTERVAL '12 hours' AS start, {SRC} AS src, {DST} AS dst FROM events, range(2) t(k)) GROUP BY 1, 2, 3""")(
    lambda s, d: volumes.windowed(volumes.events(T(s, d, "events")), "1 day", "12 hours").withColumn("start", F.col("start").cast("timestamp_ntz"))
)
query("stream_session", """WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL '2 hours' THEN 0 ELSE 1 END AS fresh FROM events),
  g AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e) SELECT user_id, min(ts) AS start, count(*) AS n FROM g GROUP BY user_id, k""")(
    lambda s, d: volumes.sessions(volumes.events(T(s, d, "events")), "2 hours").withColumn("start", F.col("start").cast("timestamp_ntz"))
)
