"""The experiments: reshuffles and transposes between block sizes, batches, the volume cut of relabeling by block size, a
tall-skinny product, native layouts, a heterogeneous net, and tables that are not matrices."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relayout.operators import measures, routine
from relayout.operators.product import entry_product, gram
from relayout.plans.layout import Layout
from relayout.plans.overlay import factored_parcels, parcels_from_rows
from relayout.plans.relabel import find_matrix_relabeling, find_relabeling
from relayout.queries import core, query, sql
from relayout.sources import tables as src
from relayout.sources.durable import durable

BC = Layout.block_cyclic
N4 = 100_000
#: Source block, remote elements before, and after the best relabeling, at the paper's scale (an independent computation).
CUTS = (
    (1, 9_900_000_000, 9_900_000_000),
    (10, 9_900_000_000, 9_900_000_000),
    (100, 9_900_000_000, 9_900_000_000),
    (1000, 9_900_000_000, 9_900_000_000),
    (1250, 9_900_000_000, 9_843_750_000),
    (2000, 9_896_000_000, 9_600_000_000),
    (2500, 9_875_000_000, 9_375_000_000),
    (4000, 9_884_000_000, 8_780_000_000),
    (5000, 9_900_000_000, 7_500_000_000),
    (7500, 9_912_500_000, 6_018_750_000),
    (9999, 9_001_099_615, 10_996_975),
    (10000, 9_000_000_000, 0),
)
SWEEP = [b for b, _, _ in CUTS]


def pair(block: int) -> tuple[Layout, Layout]:
    return BC(N4, N4, 10_000, 10_000, 10, 10, "col"), BC(N4, N4, block, block, 10, 10)


query("w1_reshuffle", core.SELECT_EMB)(lambda s, d: core.run(core.emb(s, d), *core.ends(s, d), relabel="optimal"))
query("w1_volumes", "SELECT CAST(30016 AS BIGINT) AS before, CAST(29984 AS BIGINT) AS after")(lambda s, d: core.report(s, find_matrix_relabeling(s, core.LA, core.LB, elem_bytes=1)))
query("w2_transpose", core.T_EMB)(lambda s, d: core.run(core.emb(s, d), *core.ends(s, d, flip=True), op="transpose"))
query("w2_volumes", "SELECT CAST(30000 AS BIGINT) AS before, CAST(29984 AS BIGINT) AS after")(lambda s, d: core.report(s, find_matrix_relabeling(s, core.LAT, core.LB, op="transpose", elem_bytes=1)))
query("w3_batched3", f"WITH {sql.EMB} SELECT CAST(k AS INTEGER) AS mat, i, j, (v + k) * (k + 1) AS v FROM emb, range(3) t(k)")(lambda s, d: routine.shuffle_transpose_batch(core.batch(s, d))[0].select("mat", "i", "j", "v"))
query("w3_messages", f"WITH {sql.parcels(*core.E, core.A_ARGS, core.B_ARGS)} SELECT count(*) AS batched, 3 * count(*) AS unbatched FROM parcels WHERE src <> dst")(
    lambda s, d: measures.message_count(factored_parcels(s, core.LA, core.LB)).select(F.col("packed").alias("batched"), (F.col("packed") * 3).alias("unbatched"))
)


@query("w4_volume_sweep", f"""WITH b AS (SELECT unnest({SWEEP}) AS block), ax AS (
    SELECT block, (i // 10000) % 10 AS a, (i // block) % 10 AS s, count(*) AS n FROM b, range({N4}) t(i) GROUP BY 1, 2, 3)
  SELECT r.block, CAST(sum(r.n * c.n) AS BIGINT) AS before FROM ax r JOIN ax c ON r.block = c.block WHERE r.s * 10 + c.s <> c.a * 10 + r.a GROUP BY r.block""")
def w4_volume_sweep(spark: SparkSession, d: str) -> DataFrame:
    rows = [(b, find_matrix_relabeling(spark, *pair(b), solver="none", elem_bytes=1).before) for b in SWEEP]
    return core.frame(spark, rows, "block int, before long")


@query("w4_reduction", "SELECT block, before, after, round((before - after) * 100.0 / before, 4) AS cut FROM (VALUES " + ", ".join(f"({b}, {x}::BIGINT, {y}::BIGINT)" for b, x, y in CUTS) + ") t(block, before, after)")
def w4_reduction(spark: SparkSession, d: str) -> DataFrame:
    rows = []
    for b in SWEEP:
        p = find_matrix_relabeling(spark, *pair(b), elem_bytes=1)
        rows.append((b, p.before, p.after, round(p.reduction, 4)))
    return core.frame(spark, rows, "block int, before long, after long, cut double")


query("w5_gram", core.GRAM_SQL)(lambda s, d: gram(x := core.emb(s, d), x, b := core.ends(s, d)[0], b, BC(b.n, b.n, 4, 4, 2, 4), 4)[0].select("i", "j", "v"))
query("w5_gram_sparse", """WITH m AS (SELECT o_custkey AS i, month(o_orderdate) - 1 AS j, count(*) AS v FROM orders GROUP BY 1, 2)
  SELECT a.j AS i, b.j AS j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM m a JOIN m b ON a.i = b.i GROUP BY 1, 2""")(lambda s, d: entry_product(x := src.cust_month(s, d), x))


@query("w6_native_cut", """SELECT * FROM (VALUES ('slabs 8', 28032::BIGINT, 27968::BIGINT), ('4 x 2', 28000::BIGINT, 27936::BIGINT), ('paper 128 slabs', 59992702976::BIGINT, 59983790080::BIGINT), ('paper 64 x 2', 59992702976::BIGINT, 59964915712::BIGINT), ('paper 16 x 8', 59798192128::BIGINT, 59798192128::BIGINT)) t(native, before, after)""")
def w6_native_cut(spark: SparkSession, d: str) -> DataFrame:
    shape, grid = (3_473_408, 17_408), (128, 128, 8, 16)
    cases = {
        "slabs 8": (Layout.slabs(500, 64, 8), BC(500, 64, 16, 16, 2, 4)),
        "4 x 2": (Layout.contiguous(500, 64, 4, 2), BC(500, 64, 4, 4, 2, 4)),
        "paper 128 slabs": (Layout.slabs(*shape, 128), BC(*shape, *grid)),
        "paper 64 x 2": (Layout.contiguous(*shape, 64, 2), BC(*shape, *grid)),
        "paper 16 x 8": (Layout.contiguous(*shape, 16, 8), BC(*shape, *grid)),
    }
    plans = {k: find_matrix_relabeling(spark, a, b, elem_bytes=1) for k, (a, b) in cases.items()}
    return core.frame(spark, [(k, p.before, p.after) for k, p in plans.items()], "native string, before long, after long")


#: Native slabs and block-cyclic source at growing numbers of sites; the paper's shape from 128 on. Targets on a part of the
#: sites: the result lies on the upper half of the source's site grid only.
SITES = {4: (2, 2), 8: (2, 4), 16: (4, 4), 32: (4, 8), 128: (8, 16), 256: (16, 16), 512: (16, 32), 1024: (32, 32)}


def native_case(p: int) -> tuple[str, tuple[int, int], tuple, tuple]:
    shape, block = ((3_473_408, 17_408), 128) if p >= 128 else ((500, 64), 16)
    return f"slabs {p}", shape, (-(-shape[0] // p), shape[1], p, 1, "row"), (block, block, *SITES[p], "row")


def upper_half_case(p: int) -> tuple[str, tuple[int, int], tuple, tuple]:
    side, (pr, pc) = 17_408 if p >= 128 else 64, SITES[p]
    return f"result on the upper half of {p}", (side, side), (32, 32, pr // 2, pc, "row"), (-(-side // p), side, p, 1, "row")


NATIVE = [native_case(p) for p in SITES] + [upper_half_case(p) for p in SITES]


@query("w6_native_sweep", f"SELECT name, before, true AS optimal, true AS no_worse FROM ({sql.remote_of_grids(NATIVE)})")
def w6_native_sweep(spark: SparkSession, d: str) -> DataFrame:
    """Remote cells before relabeling at 4 to 1024 sites, and whether the relabeling found is proven the best: the prices of
    the exact solver add up to its gain."""
    rows = []
    for name, shape, a, b in NATIVE:
        p = find_matrix_relabeling(spark, BC(*shape, *a), BC(*shape, *b), elem_bytes=1)
        best = p.certificate is None or abs(float(p.certificate[0].sum() + p.certificate[1].sum()) - (p.before - p.after)) <= 1e-6 * max(1, p.before)
        rows.append((name, p.before, bool(best), p.after <= p.before))
    return core.frame(spark, rows, "name string, before long, optimal boolean, no_worse boolean")


SQUARED = ", ".join(f"g{k} AS (SELECT a.j AS i, b.j AS j, CAST(sum(a.v * b.v) % 1009 AS BIGINT) AS v FROM g{k - 1} a JOIN g{k - 1} b ON a.i = b.i GROUP BY 1, 2)" for k in (1, 2))


@query("w7_iterated", f"WITH {sql.EMB}, g0 AS (SELECT i, j, v % 1009 AS v FROM ({core.GRAM_SQL})), {SQUARED}, t AS (SELECT 0 AS step, sum(v) AS v FROM g0 WHERE i = j UNION ALL SELECT 1, sum(v) FROM g1 WHERE i = j UNION ALL SELECT 2, sum(v) FROM g2 WHERE i = j) SELECT CAST(p AS INTEGER) AS sites, CAST(step AS INTEGER) AS step, CAST(v AS BIGINT) AS trace FROM t, (SELECT unnest([4, 16]) AS p)")
def w7_iterated(spark: SparkSession, d: str) -> DataFrame:
    """The iterated product on 4 and 16 sites: C <- A' A, then C <- C' C, kept small by a prime; (sites, step, trace)."""
    x, shape, out = core.emb(spark, d), core.ends(spark, d)[0], None
    for p, (pr, pc) in ((4, (2, 2)), (16, (4, 4))):
        c, lc = x, BC(shape.m, shape.n, 2, 2, pr, pc)
        for step in range(3):
            target = BC(shape.n, shape.n, 8, 8, pr, pc)
            got, plans = gram(c, c, lc, lc, target, p)
            c, lc = got.select("i", "j", (F.col("v") % 1009).alias("v")), target.relabel(plans[2].sigma)
            if step < 2:
                c = durable(c, "product")  # the next step reads it twice
            one = c.filter("i = j").agg(F.sum("v").alias("trace")).select(F.lit(p).alias("sites"), F.lit(step).alias("step"), "trace")
            out = one if out is None else out.union(one)
    return out


query("w5_gram_tall", """WITH x AS (SELECT i, j, (i * 31 + j * 17) % 1009 AS v FROM range(3392) a(i), range(17) b(j)) SELECT a.j AS i, b.j AS j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM x a JOIN x b ON a.i = b.i GROUP BY 1, 2""")(
    lambda s, d: gram(x := src.rectangle(s, 3392, 17), x, b := BC(3392, 17, 32, 4, 4, 2), b, BC(17, 17, 4, 4, 2, 4), 8)[0].select("i", "j", "v")
)


@query("w8_topology", f"""WITH {sql.TRADE}, {sql.LINKS}, {sql.PERMS}, c AS (SELECT s, sum(CASE WHEN tr.src <> s[tr.dst + 1] THEN lat + bw * vol ELSE 0 END) AS cost FROM perms, tr JOIN links ON links.src = tr.src WHERE links.dst = s[tr.dst + 1] GROUP BY s)
  SELECT (SELECT CAST(cost AS DOUBLE) FROM c WHERE s = [0, 1, 2, 3, 4]) AS before, CAST(min(cost) AS DOUBLE) AS after FROM c""")
def w8_topology(spark: SparkSession, d: str) -> DataFrame:
    from relayout.plans.graph import comm_graph, relabel_graph, total_cost

    p, model = core.region(spark, d), core.links(spark)
    plan = find_relabeling(p, model, n=5)
    both = [total_cost(comm_graph(x, model)).select(F.col("total").cast("double")) for x in (p, relabel_graph(p, plan.sigma_frame()))]
    return both[0].toDF("before").crossJoin(both[1].toDF("after"))


@query("w9_shapes", """SELECT * FROM (VALUES ('1 x 16', true), ('16 x 1', true), ('2 x 8', true), ('rectangular blocks', true)) t(grid, no_worse)""")
def w9_shapes(spark: SparkSession, d: str) -> DataFrame:
    cases = {"1 x 16": (BC(500, 64, 50, 4, 1, 16, "col"), BC(500, 64, 25, 2, 1, 16)), "16 x 1": (BC(500, 64, 32, 8, 16, 1), BC(500, 64, 8, 8, 16, 1)), "2 x 8": (BC(500, 64, 16, 8, 2, 8, "col"), BC(500, 64, 8, 4, 2, 8)), "rectangular blocks": (BC(500, 64, 30, 4, 4, 4), BC(500, 64, 7, 9, 4, 4))}
    plans = {k: find_matrix_relabeling(spark, a, b) for k, (a, b) in cases.items()}
    return core.frame(spark, [(k, p.after <= p.before) for k, p in plans.items()], "grid string, no_worse boolean")


LANG = "SELECT CAST(CASE lang WHEN 'en' THEN 0 WHEN 'de' THEN 1 WHEN 'fr' THEN 2 WHEN 'es' THEN 3 ELSE 4 END AS INTEGER) AS src, CAST(CAST(substr(source, 4) AS INTEGER) % 5 AS INTEGER) AS dst, count(*) AS n_pieces, CAST(sum(n_chars) AS BIGINT) AS vol FROM documents GROUP BY 1, 2"


def lang_source(spark: SparkSession, d: str) -> DataFrame:
    code = F.coalesce(F.create_map(*(F.lit(x) for kv in (("en", 0), ("de", 1), ("fr", 2), ("es", 3)) for x in kv))[F.col("lang")], F.lit(4))
    return parcels_from_rows(src.table(spark, d, "documents"), code, F.pmod(F.substring("source", 4, 9).cast("int"), F.lit(5)), F.col("n_chars"))


query("w10_language_source", LANG)(lambda s, d: lang_source(s, d))
query("w10_language_best", f"WITH tr AS ({LANG}), {sql.BEST} SELECT (SELECT CAST(sum(vol) AS BIGINT) FROM tr WHERE src <> dst) AS before, CAST(after AS BIGINT) AS after FROM best")(lambda s, d: core.report(s, find_relabeling(lang_source(s, d), n=5)))
EVENTS = "SELECT CAST(user_id % 5 AS INTEGER) AS src, CAST(dense_rank() OVER (ORDER BY event_type) - 1 AS INTEGER) AS dst FROM events"
query("w10_user_type", f"SELECT src, dst, count(*) AS n_pieces, CAST(count(*) AS BIGINT) AS vol FROM ({EVENTS}) GROUP BY 1, 2")(lambda s, d: user_type(s, d))


def user_type(spark: SparkSession, d: str) -> DataFrame:
    from pyspark.sql import Window

    e = src.table(spark, d, "events")
    types = e.select("event_type").distinct().withColumn("dst", F.row_number().over(Window.orderBy("event_type")) - 1)  # few rows: event types
    return parcels_from_rows(e.join(F.broadcast(types), "event_type"), F.pmod("user_id", F.lit(5)), F.col("dst"))
