"""Layouts, overlays, costs, graphs, gains, solvers, the routine and its variants, baselines and measures."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relayout.operators import measures, routine, tiles
from relayout.operators.product import entry_product, gram
from relayout.plans import assign, cost, graph
from relayout.plans.layout import Layout, Splits
from relayout.plans.overlay import cell_parcels, factored_parcels, grid_overlay, parcels, tensor_parcels
from relayout.plans.relabel import Plan, find_matrix_relabeling, find_relabeling, gains
from relayout.queries import query, sql
from relayout.sources import tables as src

BC = Layout.block_cyclic
CELL = ("i", "j", "v")
#: Of the queries that plan from descriptors alone, without a table: source in 2 x 2 blocks, target in 8 x 8, four by
#: four sites. Those that read the embeddings take the shape from the table (ends).
E = (500, 64)
LB, LA = BC(*E, 2, 2, 4, 4), BC(*E, 8, 8, 4, 4)
LAT = BC(64, 500, 8, 8, 4, 4)
B_ARGS, A_ARGS = (2, 2, 4, 4, "row"), (8, 8, 4, 4, "row")


def ends(spark: SparkSession, d: str, flip: bool = False) -> tuple[Layout, Layout]:
    """Source and target layouts of all the embeddings; flip: the target is that of the transpose."""
    m, n = src.emb_shape(spark, d)
    return BC(m, n, 2, 2, 4, 4), BC(*((n, m) if flip else (m, n)), 8, 8, 4, 4)


def frame(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


# ---- layouts ------------------------------------------------------------------------------------

GENERAL = Layout.grid_of((0, 7, 10, 51), (0, 4, 8), [[0, 1], [2, 0], [1, 2]], 3)
BLOCK = ("bi", "bj", "r_lo", "r_hi", "c_lo", "c_hi", "site")


def loaded(spark: SparkSession, d: str, name: str, layout: Callable[[int, int], Layout], n: int | None = None, flip: bool = False) -> DataFrame:
    """Blocks of a layout over all rows of a table, and how many rows each holds; flip: the layout is that of the transpose."""
    cells = src.points(spark, d, name)
    at = layout(*src.shape(cells, n))
    return measures.block_load(at, cells.toDF("j", "i") if flip else cells).select(*BLOCK, "n_rows")


query("layout_blocks", f"""WITH {sql.POINTS['quantity_lines']} SELECT CAST(bi AS BIGINT) AS bi, CAST(bj AS BIGINT) AS bj, CAST(r_lo AS BIGINT) AS r_lo, CAST(r_hi AS BIGINT) AS r_hi, CAST(c_lo AS BIGINT) AS c_lo, CAST(c_hi AS BIGINT) AS c_hi, CAST(site AS INTEGER) AS site, CAST(coalesce(sum(n), 0) AS BIGINT) AS n_rows
  FROM (VALUES (0,0,0,7,0,4,0),(0,1,0,7,4,8,1),(1,0,7,10,0,4,2),(1,1,7,10,4,8,0),(2,0,10,51,0,4,1),(2,1,10,51,4,8,2)) t(bi,bj,r_lo,r_hi,c_lo,c_hi,site)
  LEFT JOIN (SELECT i, j, count(*) AS n FROM points GROUP BY 1, 2) ON i >= r_lo AND i < r_hi AND j >= c_lo AND j < c_hi GROUP BY ALL""")(lambda s, d: measures.block_load(GENERAL, src.counted(src.points(s, d, "quantity_lines"))).select(*BLOCK, "n_rows"))
query("layout_block_cyclic", sql.loaded("customer_months", 7, 5, 3, 4, "col", 12))(lambda s, d: loaded(s, d, "customer_months", lambda m, n: BC(m, n, 7, 5, 3, 4, "col"), 12))
query("layout_contiguous", sql.loaded("supplier_parts", "greatest(1, (m + 3) // 4)", "greatest(1, (n + 1) // 2)", 4, 2))(lambda s, d: loaded(s, d, "supplier_parts", lambda m, n: Layout.contiguous(m, n, 4, 2)))


@query("layout_quantile", """SELECT CAST(t - 1 AS BIGINT) AS bi, CASE WHEN t = 1 THEN 0 ELSE lag(hi) OVER (ORDER BY t) END AS r_lo, hi AS r_hi
  FROM (SELECT t, max(l_orderkey) + 1 AS hi FROM (SELECT l_orderkey, ntile(8) OVER (ORDER BY l_orderkey) AS t FROM lineitem) GROUP BY t)""")
def layout_quantile(spark: SparkSession, d: str) -> DataFrame:
    return Layout.from_quantiles(src.table(spark, d, "lineitem"), "l_orderkey", 8, exact=True).blocks(spark).select("bi", "r_lo", "r_hi")


@query("owner_of_cell", f"WITH {sql.EMB} SELECT i, j, {sql.own('i', 'j', 2, 2, 4, 4)} AS site FROM emb")
def owner_of_cell(spark: SparkSession, d: str) -> DataFrame:
    return src.emb_entries(spark, d).select("i", "j", ends(spark, d)[0].owner_of(F.col("i"), F.col("j")).alias("site"))


query("layout_transposed", f"SELECT bj AS bi, bi AS bj, c_lo AS r_lo, c_hi AS r_hi, r_lo AS c_lo, r_hi AS c_hi, site, n_rows FROM ({sql.loaded('supplier_months', 7, 5, 3, 4, n=12)})")(lambda s, d: loaded(s, d, "supplier_months", lambda m, n: BC(m, n, 7, 5, 3, 4).transposed(), 12, flip=True))
query("layout_window", f"""SELECT bi, bj, greatest(r_lo, 10) - 10 AS r_lo, least(r_hi, 101) - 10 AS r_hi, greatest(c_lo, 3) - 3 AS c_lo, least(c_hi, 50) - 3 AS c_hi, site
  FROM ({sql.blocks(*E, 7, 5, 3, 4)}) WHERE r_hi > 10 AND r_lo < 101 AND c_hi > 3 AND c_lo < 50""")(lambda s, d: BC(*E, 7, 5, 3, 4).window(10, 101, 3, 50).blocks(s).select(*BLOCK))
query("layout_relabelled", f"SELECT bi, bj, CAST([3, 1, 0, 2][site + 1] AS INTEGER) AS site, n_rows FROM ({sql.loaded('user_hours', 50, 16, 2, 2, n=24)})")(lambda s, d: loaded(s, d, "user_hours", lambda m, n: BC(m, n, 50, 16, 2, 2).relabel([3, 1, 0, 2]), 24).select("bi", "bj", "site", "n_rows"))

# ---- overlays and parcels -----------------------------------------------------------------------

@query("axis_overlay", """WITH points AS (SELECT o_custkey AS i FROM orders WHERE o_custkey >= 0), size AS (SELECT CAST(coalesce(max(i) + 1, 0) AS BIGINT) AS m FROM points),
  s AS (SELECT unnest(range(0, m, 7)) AS lo, m FROM size UNION SELECT unnest(range(0, m, 12)), m FROM size),
  p AS (SELECT row_number() OVER (ORDER BY lo) - 1 AS k, lo, coalesce(lead(lo) OVER (ORDER BY lo), m) AS hi, lo // 7 AS ka, lo // 12 AS kb FROM s)
  SELECT p.*, coalesce(n, 0) AS n_rows FROM p LEFT JOIN (SELECT i // 7 AS ka, i // 12 AS kb, count(*) AS n FROM points GROUP BY 1, 2) h USING (ka, kb)""")
def axis_query(spark: SparkSession, d: str) -> DataFrame:
    """Blocks of 7 customers over blocks of 12, and the orders of each piece."""
    keys = src.table(spark, d, "orders").filter("o_custkey >= 0").select(F.col("o_custkey").cast("long").alias("i"))
    m = keys.agg(F.coalesce(F.max("i") + 1, F.lit(0))).first()[0]
    return measures.axis_load((Splits(m, 7), 0, m), (Splits(m, 12), 0, m), keys).select("k", "lo", "hi", "ka", "kb", "n_rows")
_A, _B = BC(60, 24, 7, 5, 2, 3, "col"), BC(60, 24, 4, 6, 3, 2)
query("grid_overlay", f"""WITH {sql.cells(60, 24)}, {sql.POINTS['minute_hours']}, held AS (SELECT i, j, count(*) AS n FROM points GROUP BY 1, 2)
  SELECT min(i) AS r_lo, max(i) + 1 AS r_hi, min(j) AS c_lo, max(j) + 1 AS c_hi, {sql.own('min(i)', 'min(j)', 4, 6, 3, 2)} AS src, {sql.own('min(i)', 'min(j)', 7, 5, 2, 3, 'col')} AS dst, CAST(coalesce(sum(n), 0) AS BIGINT) AS n_rows
  FROM cells LEFT JOIN held USING (i, j) GROUP BY i // 7, j // 5, i // 4, j // 6""")(lambda s, d: measures.grid_load(_A, _B, src.counted(src.points(s, d, "minute_hours"))).select("r_lo", "r_hi", "c_lo", "c_hi", "src", "dst", "n_rows"))
_PARCELS = f"WITH {sql.parcels(*E, A_ARGS, B_ARGS)} SELECT * FROM parcels"
query("volumes_factored", _PARCELS)(lambda s, d: factored_parcels(s, LA, LB))
query("parcel_volumes", _PARCELS)(lambda s, d: parcels(grid_overlay(s, LA, LB)))
query("trade_volumes_region", f"WITH {sql.TRADE} SELECT * FROM tr")(lambda s, d: src.trade(s, d, "region"))
query("trade_volumes_nation", """SELECT CAST(s_nationkey AS INTEGER) AS src, CAST(c_nationkey AS INTEGER) AS dst, count(*) AS n_pieces, CAST(sum(l_quantity) AS BIGINT) AS vol
  FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2""")(lambda s, d: src.trade(s, d, "nation"))
query("tensor_volumes", """SELECT CAST((((x // 3) % 2) * 2 + (y // 4) % 2) * 3 + (z // 2) % 3 AS INTEGER) AS src, CAST((((x // 5) % 2) * 3 + (y // 2) % 3) * 2 + (z // 5) % 2 AS INTEGER) AS dst,
  count(DISTINCT (x // 3, y // 4, z // 2, x // 5, y // 2, z // 5)) AS n_pieces, CAST(count(*) * 8 AS BIGINT) AS vol FROM range(20) a(x), range(15) b(y), range(12) c(z) GROUP BY 1, 2""")(
    lambda s, d: tensor_parcels(s, [(Splits(20, 5), 2), (Splits(15, 2), 3), (Splits(12, 5), 2)], [(Splits(20, 3), 2), (Splits(15, 4), 2), (Splits(12, 2), 3)])
)
query("tiles_roundtrip", f"WITH {sql.EMB} SELECT * FROM emb")(lambda s, d: tiles.from_tiles(tiles.to_tiles(src.emb_entries(s, d), ends(s, d)[1])).select(*CELL))

# ---- costs and graphs ---------------------------------------------------------------------------


def region(spark: SparkSession, d: str) -> DataFrame:
    return src.trade(spark, d, "region")


def links(spark: SparkSession) -> cost.LinkCost:
    return cost.LinkCost(cost.region_links(spark))


def weighed(model: Callable[[SparkSession], cost.Cost]) -> Callable[[SparkSession, str], DataFrame]:
    return lambda s, d: graph.comm_graph(region(s, d), model(s)).select("src", "dst", F.col("weight").cast("double").alias("weight"))


def weight_sql(expr: str) -> str:
    return f"WITH {sql.TRADE}, {sql.LINKS} SELECT tr.src, tr.dst, CAST({expr} AS DOUBLE) AS weight FROM tr JOIN links ON tr.src = links.src AND tr.dst = links.dst"


FAR = "tr.src <> tr.dst"
query("cost_volume", weight_sql(f"CASE WHEN {FAR} THEN vol ELSE 0 END"))(weighed(lambda s: cost.VolumeCost()))
query("cost_items", weight_sql(f"CASE WHEN {FAR} THEN n_pieces ELSE 0 END"))(weighed(lambda s: cost.ItemCost()))
query("cost_links", weight_sql(f"CASE WHEN {FAR} THEN lat + bw * vol ELSE 0 END"))(weighed(links))
query("cost_transform", weight_sql(f"CASE WHEN {FAR} THEN 0.5 * vol ELSE 0 END"))(weighed(lambda s: cost.TransformCost(0.5, "remote")))
query("cost_locality", weight_sql(f"CASE WHEN {FAR} THEN ceil(vol / n_pieces / 64) * 64 * n_pieces * 1.5 ELSE 0 END"))(weighed(lambda s: cost.LocalityCost()))
query("cost_composite", weight_sql(f"(CASE WHEN {FAR} THEN vol ELSE 0 END) + 0.5 * (2.0 * vol)"))(weighed(lambda s: cost.VolumeCost() + 0.5 * cost.TransformCost(2.0)))
query("comm_graph", f"WITH {sql.TRADE} SELECT src, dst, vol, n_pieces, CASE WHEN src <> dst THEN vol ELSE 0 END AS weight FROM tr")(lambda s, d: graph.comm_graph(region(s, d)))


@query("graph_neighbours", f"""WITH {sql.POINTS['supplier_parts']}, parcels AS (SELECT DISTINCT {sql.own('i', 'j', 8, 8, 4, 4)} AS src, {sql.own('i', 'j', 16, 16, 4, 4, 'col')} AS dst FROM points) SELECT a.site, string_agg(DISTINCT p.src::VARCHAR, ',' ORDER BY p.src::VARCHAR) AS senders, any_value(b.r) AS receivers
  FROM (SELECT CAST(x AS INTEGER) AS site FROM range(16) t(x)) a JOIN parcels p ON p.dst = a.site JOIN (SELECT src, string_agg(DISTINCT dst::VARCHAR, ',' ORDER BY dst::VARCHAR) AS r FROM parcels GROUP BY src) b ON b.src = a.site GROUP BY a.site""")
def graph_neighbours(spark: SparkSession, d: str) -> DataFrame:
    m, n = src.shape(cells := src.points(spark, d, "supplier_parts"))
    g = graph.comm_graph(cell_parcels(cells, BC(m, n, 16, 16, 4, 4, "col"), BC(m, n, 8, 8, 4, 4)))
    text = lambda c: F.array_join(F.sort_array(F.transform(c, lambda x: x.cast("string"))), ",").alias(c)
    both = graph.left_neighbours(g).join(graph.right_neighbours(g), F.col("dst") == F.col("src"))
    return both.select(F.col("dst").alias("site"), text("senders"), text("receivers"))


query("total_cost", f"WITH {sql.TRADE} SELECT CAST(sum(vol) AS BIGINT) AS total FROM tr WHERE src <> dst")(lambda s, d: graph.total_cost(graph.comm_graph(region(s, d))))
SIGMA = [3, 2, 4, 1, 0]
query("relabelled_graph", f"WITH {sql.TRADE} SELECT src, CAST({SIGMA}[dst + 1] AS INTEGER) AS dst, n_pieces, vol FROM tr")(lambda s, d: graph.relabel_graph(region(s, d), frame(s, list(enumerate(SIGMA)), "role int, site int")).select("src", "dst", "n_pieces", "vol"))


@query("relabel_identity", "SELECT CAST(0 AS BIGINT) AS differ")
def relabel_identity(spark: SparkSession, d: str) -> DataFrame:
    p = region(spark, d)
    same = graph.relabel_graph(p, graph.identity(spark, 5)).select(p.columns)
    return same.exceptAll(p).union(p.exceptAll(same)).agg(F.count(F.lit(1)).alias("differ"))


# ---- gains and solvers --------------------------------------------------------------------------

GAIN_LINKS = f"""WITH {sql.TRADE}, {sql.LINKS}, k AS (SELECT tr.dst AS role, l.dst AS site, sum(CASE WHEN l.src <> l.dst THEN lat + bw * vol ELSE 0 END) AS price FROM tr JOIN links l ON l.src = tr.src GROUP BY 1, 2)
  SELECT k.role, k.site, CAST(o.price - k.price AS DOUBLE) AS gain FROM k JOIN k o ON o.role = k.role AND o.site = o.role"""
query("gain_general", GAIN_LINKS)(lambda s, d: graph.gain_matrix(region(s, d), links(s), 5).select("role", "site", F.col("gain").cast("double").alias("gain")))
GAIN_VOLUME = f"WITH {sql.TRADE} SELECT t.dst AS role, t.src AS site, CAST(t.vol - coalesce(o.vol, 0) AS BIGINT) AS gain FROM tr t LEFT JOIN tr o ON o.src = o.dst AND o.dst = t.dst"
query("gain_volume", GAIN_VOLUME)(lambda s, d: graph.gain_matrix_volume(region(s, d)))
query("total_gain", f"WITH g AS ({GAIN_VOLUME}) SELECT CAST(sum(gain) AS BIGINT) AS total_gain FROM g WHERE site = {SIGMA}[role + 1]")(lambda s, d: graph.total_gain(graph.gain_matrix_volume(region(s, d)), frame(s, list(enumerate(SIGMA)), "role int, site int")))


@query("gain_identity", "SELECT * FROM (VALUES ('volume', true), ('items', true), ('links', true), ('composite', true)) t(cost, holds)")
def gain_identity(spark: SparkSession, d: str) -> DataFrame:
    p, out = region(spark, d), None
    models = {"volume": cost.VolumeCost(), "items": cost.ItemCost(), "links": links(spark), "composite": cost.VolumeCost() + 2 * links(spark)}
    for name, model in models.items():
        delta = graph.gain_matrix(p, model, 5)
        rows = None
        for sigma in (SIGMA, [1, 2, 3, 4, 0], [0, 1, 3, 2, 4]):
            f = frame(spark, list(enumerate(sigma)), "role int, site int")
            before, after = (graph.total_cost(graph.comm_graph(x, model)).select(F.col("total").cast("double").alias("total")) for x in (p, graph.relabel_graph(p, f)))
            won = graph.total_gain(delta, f)
            one = before.toDF("b").crossJoin(after.toDF("a")).crossJoin(won).select((F.abs(F.col("b") - F.col("a") - F.col("total_gain")) < 1e-6).alias("ok"))
            rows = one if rows is None else rows.union(one)
        one = rows.agg(F.lit(name).alias("cost"), F.bool_and("ok").alias("holds"))
        out = one if out is None else out.union(one)
    return out


BEST_SQL = f"WITH {sql.TRADE}, {sql.BEST} SELECT (SELECT CAST(sum(vol) AS BIGINT) FROM tr WHERE src <> dst) AS before, CAST(after AS BIGINT) AS after FROM best"


def report(spark: SparkSession, plan: Plan) -> DataFrame:
    return frame(spark, [(plan.before, plan.after)], "before long, after long")


for _name, _solver in {"best_relabeling_bruteforce": "brute", "relabel_exact_region": "exact", "relabel_flow_region": "flow", "relabel_auction_region": "auction", "relabel_report": "auto"}.items():
    query(_name, BEST_SQL)(lambda s, d, k=_solver: report(s, find_relabeling(region(s, d), solver=k, n=5)))
query("relabel_greedy_region", sql.greedy("gain"))(lambda s, d: report(s, find_relabeling(region(s, d), solver="greedy", n=5)))
query("relabel_greedy_retained", sql.greedy("retained"))(lambda s, d: report(s, find_relabeling(region(s, d), solver="retained", n=5)))
query("relabel_greedy_rounds", sql.greedy("retained"))(lambda s, d: report(s, find_relabeling(region(s, d), solver="rounds", n=5)))
query("relabel_random_swap", "SELECT true AS no_worse")(lambda s, d: frame(s, [((p := find_relabeling(region(s, d), solver="swap", n=5)).after <= p.before,)], "no_worse boolean"))


@query("lp_certificate", "SELECT true AS covers, true AS tight")
def lp_certificate(spark: SparkSession, d: str) -> DataFrame:
    gain = gains(region(spark, d), None, 5)
    sigma, (u, v) = assign.solve_exact(gain)
    delta = frame(spark, [(x, y, float(gain[x, y])) for x in range(5) for y in range(5)], "role int, site int, gain double")
    return assign.certify(delta, sigma, u, v)


query("lp_feasible_identity", "SELECT true AS feasible")(lambda s, d: assign.feasible(graph.identity(s, 5).crossJoin(graph.identity(s, 5).select(F.col("site").alias("y"))).select("role", F.col("y").alias("site"), (F.col("role") == F.col("y")).cast("double").alias("x")), 5))
query("matching_valid", "SELECT true AS valid")(lambda s, d: assign.matching_valid(find_relabeling(region(s, d), n=5).sigma_frame(), 5))
query("lap_convert", f"WITH g AS ({GAIN_VOLUME}) SELECT role, site, CAST((SELECT max(gain) FROM g) - gain AS BIGINT) AS cost FROM g")(lambda s, d: graph.to_min(graph.gain_matrix_volume(region(s, d)), "shift"))
_R8A, _R8B = BC(*E, 16, 16, 2, 4, "col"), BC(*E, 8, 8, 2, 4)
query("relabel_grid_2x4", "SELECT 28000 * 8::BIGINT AS before, 27936 * 8::BIGINT AS after")(lambda s, d: report(s, find_matrix_relabeling(s, Layout.contiguous(*E, 4, 2), BC(*E, 4, 4, 2, 4))))

# ---- the routine --------------------------------------------------------------------------------


def emb(spark: SparkSession, d: str) -> DataFrame:
    return src.emb_entries(spark, d)


def run(b: DataFrame, lb: Layout, la: Layout, a: DataFrame | None = None, **how: object) -> DataFrame:
    return routine.shuffle_transpose(a, la, b, lb, **how)[0].select(*CELL)


SELECT_EMB = f"WITH {sql.EMB} SELECT i, j, v FROM emb"
T_EMB = f"WITH {sql.EMB} SELECT j AS i, i AS j, v FROM emb"
query("reshuffle_emb", SELECT_EMB)(lambda s, d: run(emb(s, d), *ends(s, d)))
query("transpose_emb", T_EMB)(lambda s, d: run(emb(s, d), *ends(s, d, flip=True), op="transpose"))
query("scale_emb", f"WITH {sql.EMB} SELECT i, j, v * 2 AS v FROM emb")(lambda s, d: run(emb(s, d), *ends(s, d), alpha=2))
query("transform_before_send", f"WITH {sql.EMB} SELECT j AS i, i AS j, v * 2 AS v FROM emb")(lambda s, d: run(emb(s, d), *ends(s, d, flip=True), op="transpose", alpha=2, transform="send"))


def other(spark: SparkSession, d: str) -> DataFrame:
    """A second matrix of the same shape; half of its cells are missing."""
    return emb(spark, d).filter("(i + j) % 2 = 0").select("i", "j", (F.col("i") - F.col("j")).alias("v"))


OTHER = "a AS (SELECT i, j, i - j AS v FROM emb WHERE (i + j) % 2 = 0)"
query("axpby_emb", f"WITH {sql.EMB}, {OTHER} SELECT emb.i, emb.j, 2 * emb.v + coalesce(3 * a.v, 0) AS v FROM emb LEFT JOIN a ON a.i = emb.i AND a.j = emb.j")(lambda s, d: run(emb(s, d), *ends(s, d), a=other(s, d), alpha=2, beta=3))
query("axpby_transpose", f"WITH {sql.EMB}, {OTHER} SELECT coalesce(emb.j, a.j) AS i, coalesce(emb.i, a.i) AS j, coalesce(2 * emb.v, 0) + coalesce(3 * a.v, 0) AS v FROM emb FULL JOIN a ON a.j = emb.j AND a.i = emb.i")(
    lambda s, d: run(emb(s, d), *ends(s, d, flip=True), a=other(s, d).select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), alpha=2, beta=3, op="transpose")
)
query("axpby_self", f"WITH {sql.EMB} SELECT i, j, v * 3 AS v FROM emb")(lambda s, d: run(x := emb(s, d), *ends(s, d), a=x, alpha=2, beta=1))
query("submatrix_emb", f"WITH {sql.EMB} SELECT i - 100 AS i, j - 8 AS j, v FROM emb WHERE i >= 100 AND i < 300 AND j >= 8 AND j < 40")(lambda s, d: run(routine.submatrix(emb(s, d), (100, 300, 8, 40)), ends(s, d)[0].window(100, 300, 8, 40), BC(200, 32, 8, 8, 4, 4)))
query("col_major_tiles", T_EMB)(lambda s, d: tiles.from_tiles(tiles.transpose_tiles(tiles.to_tiles(emb(s, d), ends(s, d)[1], order="col"))).select(*CELL))
query("strided_tiles", SELECT_EMB)(lambda s, d: tiles.from_tiles(tiles.to_tiles(emb(s, d), ends(s, d)[1], pad=3)).select(*CELL))


def tiled(spark: SparkSession, d: str, flip: bool = False, order: str = "row", pad: int = 0, to: str = "row", to_pad: int = 0, **how: object) -> DataFrame:
    """The embeddings as tiles of the source layout, through the routine to tiles of the target's, and as cells again."""
    lb, la = ends(spark, d, flip)
    return tiles.from_tiles(tiles.shuffle_tiles(tiles.to_tiles(emb(spark, d), lb, order=order, pad=pad), lb, la, op="transpose" if flip else "identity", order=to, pad=to_pad, **how)[0]).select(*CELL)


query("reshuffle_tiles", SELECT_EMB)(lambda s, d: tiled(s, d))
query("transpose_tiles", f"WITH {sql.EMB} SELECT j AS i, i AS j, v * 2 AS v FROM emb")(lambda s, d: tiled(s, d, True, alpha=2))
query("reshuffle_tiles_col_major", SELECT_EMB)(lambda s, d: tiled(s, d, order="col", to="row"))
query("transpose_tiles_strided", T_EMB)(lambda s, d: tiled(s, d, True, order="row", pad=3, to="col", to_pad=5))
query("axpby_tiles", f"WITH {sql.EMB} SELECT i, j, 2 * v + 3 * (v + 1) AS v FROM emb")(lambda s, d: tiles.from_tiles(tiles.shuffle_tiles(tiles.to_tiles(emb(s, d), (x := ends(s, d))[0]), *x, 2, 3, tiles.to_tiles(emb(s, d).withColumn("v", F.col("v") + 1), x[1], order="col"))[0]).select(*CELL))
query("reshuffle_decimal", f"WITH {sql.EMB} SELECT i, j, CAST(v AS DECIMAL(18, 2)) AS v FROM emb")(lambda s, d: run(emb(s, d).withColumn("v", F.col("v").cast("decimal(18,2)")), *ends(s, d)))
query("reshuffle_int", f"WITH {sql.EMB} SELECT i, j, CAST(v AS INTEGER) AS v FROM emb")(lambda s, d: run(emb(s, d).withColumn("v", F.col("v").cast("int")), *ends(s, d)))
query("bypass_split", f"WITH {sql.EMB} SELECT {sql.own('i', 'j', 8, 8, 4, 4)} <> {sql.own('i', 'j', 2, 2, 4, 4)} AS moves, count(*) AS cells FROM emb GROUP BY 1")(
    lambda s, d: routine.rows_of(routine.Task(None, (both := ends(s, d))[1], emb(s, d), both[0]), list(range(16)), False).groupBy((F.col("src") != F.col("pid")).alias("moves")).agg(F.count(F.lit(1)).alias("cells"))
)
query("messages_packed", f"WITH {sql.parcels(*E, A_ARGS, B_ARGS)} SELECT count(*) AS packed FROM parcels WHERE src <> dst")(lambda s, d: measures.message_count(factored_parcels(s, LA, LB)).select("packed"))
query("messages_unpacked", f"WITH {sql.parcels(*E, A_ARGS, B_ARGS)} SELECT CAST(sum(n_pieces) AS BIGINT) AS unpacked FROM parcels WHERE src <> dst")(lambda s, d: measures.message_count(factored_parcels(s, LA, LB)).select("unpacked"))


def batch(spark: SparkSession, d: str) -> list[routine.Task]:
    b, (lb, la) = emb(spark, d), ends(spark, d)
    return [routine.Task(None, la, b.withColumn("v", F.col("v") + k), lb, alpha=k + 1) for k in range(3)]


query("batched_emb", f"WITH {sql.EMB} SELECT CAST(k AS INTEGER) AS mat, i, j, (v + k) * (k + 1) AS v FROM emb, range(3) t(k)")(lambda s, d: routine.shuffle_transpose_batch(batch(s, d))[0].select("mat", *CELL))
BATCH = {"customer_months": 12, "supplier_months": 12, "user_hours": 24}


@query("batch_messages", "WITH p AS (" + " UNION ALL ".join(f"(WITH {sql.POINTS[k]} SELECT DISTINCT '{k}' AS mat, {sql.own('i', 'j', *B_ARGS)} AS src, {sql.own('i', 'j', *A_ARGS)} AS dst FROM points)" for k in BATCH)
       + ") SELECT count(DISTINCT (src, dst)) AS batched, count(*) AS apart FROM p WHERE src <> dst")
def batch_messages(spark: SparkSession, d: str) -> DataFrame:
    """Three tables' cells, from blocks of 2 x 2 to 8 x 8."""
    moved = []
    for name, n in BATCH.items():
        m, n = src.shape(cells := src.points(spark, d, name), n)
        moved.append(cell_parcels(cells, BC(m, n, 8, 8, 4, 4), BC(m, n, 2, 2, 4, 4)))
    return measures.batch_messages(moved)


@query("subset_sites", SELECT_EMB)
def subset_sites(spark: SparkSession, d: str) -> DataFrame:
    m, n = src.emb_shape(spark, d)
    return run(emb(spark, d), ends(spark, d)[0], Layout.grid_of((0, m // 2, m), (0, n), [[14], [15]], 16))


def spec(spark: SparkSession, d: str) -> dict[str, int]:
    return dict(zip(("m", "n"), src.emb_shape(spark, d), strict=True)) | {"mb": 2, "nb": 2, "pr": 4, "pc": 4}


query("wrap_redistribute", f"WITH {sql.EMB} SELECT i - 20 AS i, j, v FROM emb WHERE i >= 20 AND i < 420")(lambda s, d: routine.redistribute(emb(s, d), x := spec(s, d), x | {"m": 400, "mb": 8, "nb": 8}, (20, 420, 0, 64))[0].select(*CELL))
query("wrap_transpose", f"WITH {sql.EMB}, {OTHER} SELECT emb.j AS i, emb.i AS j, 2 * emb.v + coalesce(3 * a.v, 0) AS v FROM emb LEFT JOIN a ON a.i = emb.i AND a.j = emb.j")(
    lambda s, d: routine.transpose_add(2, emb(s, d), x := spec(s, d), 3, other(s, d).select(F.col("j").alias("i"), F.col("i").alias("j"), "v"), x | {"m": x["n"], "n": x["m"], "mb": 8, "nb": 8})[0].select(*CELL)
)
query("custom_op", f"WITH {sql.EMB} SELECT i, j, abs(v) % 7 AS v FROM emb")(lambda s, d: run(emb(s, d), *ends(s, d), op=lambda v: F.pmod(F.abs(v), F.lit(7))))


@query("conj_transpose_emb", """WITH c AS (SELECT vec_id AS i, unnest(range(0, 32)) AS j, unnest(list_transform(range(0, 32), lambda k: CAST(embedding[2 * k + 1] AS DOUBLE))) AS re, unnest(list_transform(range(0, 32), lambda k: CAST(embedding[2 * k + 2] AS DOUBLE))) AS im
  FROM embeddings) SELECT j AS i, i AS j, 2 * re AS re, -2 * im AS im FROM c""")
def conj_transpose_emb(spark: SparkSession, d: str) -> DataFrame:
    m, n = src.emb_shape(spark, d)
    out = run(src.emb_complex(spark, d), BC(m, n // 2, 2, 2, 4, 4), BC(n // 2, m, 8, 8, 4, 4), op="conj_transpose", alpha=2)
    return out.select("i", "j", "v.re", "v.im")


@query("tensor_permute", """SELECT m, s, p, CAST(sum(l_quantity) AS BIGINT) AS v FROM (SELECT month(l_shipdate) - 1 AS m, l_suppkey - 1 AS s, l_partkey % 10 AS p, l_quantity FROM lineitem) GROUP BY 1, 2, 3""")
def tensor_permute(spark: SparkSession, d: str) -> DataFrame:
    """(supplier, part, month) to (month, supplier, part), from blocks on 4 x 2 x 2 sites to others on 2 x 4 x 2."""
    line = src.table(spark, d, "lineitem")
    idx = F.array((F.col("l_suppkey") - 1).cast("long"), F.pmod("l_partkey", F.lit(10)), (F.month("l_shipdate") - 1).cast("long"))
    t = line.select(idx.alias("idx"), "l_quantity").groupBy("idx").agg(F.sum("l_quantity").cast("long").alias("v"))
    n = line.agg(F.max("l_suppkey")).first()[0] or 1
    lb, la = [(Splits(n, 3), 4), (Splits(10, 2), 2), (Splits(12, 3), 2)], [(Splits(12, 4), 2), (Splits(n, 5), 4), (Splits(10, 5), 2)]
    out = routine.reshuffle_tensor(t, [2, 0, 1], la, lb)[0]
    return out.select(F.get("idx", 0).alias("m"), F.get("idx", 1).alias("s"), F.get("idx", 2).alias("p"), "v")


ORDER_PARCELS = "p AS (SELECT o_custkey % 5 AS src, o_orderkey % 5 AS dst, count(*) AS vol FROM orders GROUP BY 1, 2)"
query("relabel_buckets_orders", f"""WITH {ORDER_PARCELS}, {sql.PERMS} SELECT CAST((SELECT sum(vol) FROM p WHERE src <> dst) AS BIGINT) AS before,
  CAST((SELECT sum(vol) FROM p) - max(kept) AS BIGINT) AS after FROM (SELECT s, sum(CASE WHEN p.src = perms.s[p.dst + 1] THEN vol ELSE 0 END) AS kept FROM perms, p GROUP BY s)""")(
    lambda s, d: report(s, routine.relabel_repartition(src.table(s, d, "orders"), F.pmod("o_custkey", F.lit(5)), F.pmod("o_orderkey", F.lit(5)), 5)[1])
)
GRAM_SQL = f"WITH {sql.EMB} SELECT a.j AS i, b.j AS j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM emb a JOIN emb b ON a.i = b.i GROUP BY 1, 2"
query("gram_emb", GRAM_SQL)(lambda s, d: gram(x := emb(s, d), x, b := ends(s, d)[0], b, BC(b.n, b.n, 8, 8, 4, 4), 8)[0].select(*CELL))

# ---- baselines ----------------------------------------------------------------------------------

query("base_reshuffle", SELECT_EMB)(lambda s, d: routine.block_cyclic_reshuffle(emb(s, d), *ends(s, d)).select(*CELL))
query("base_transpose", T_EMB)(lambda s, d: routine.block_cyclic_reshuffle(emb(s, d), *ends(s, d, flip=True), transpose=True).select(*CELL))
query("base_all_to_all", SELECT_EMB)(lambda s, d: routine.exchange_all(emb(s, d), ends(s, d)[1]).select(*CELL))
query("base_no_relabel", SELECT_EMB)(lambda s, d: run(emb(s, d), *ends(s, d), relabel="none"))


@query("base_unbatched", f"WITH {sql.EMB} SELECT CAST(k AS INTEGER) AS mat, i, j, (v + k) * (k + 1) AS v FROM emb, range(3) t(k)")
def base_unbatched(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for k, t in enumerate(batch(spark, d)):
        one = run(t.b, t.lb, t.la, alpha=t.alpha).withColumn("mat", F.lit(k))
        out = one if out is None else out.union(one)
    return out.select("mat", *CELL)


@query("base_item_relabel", f"""WITH {sql.TRADE}, {sql.PERMS}, x AS (SELECT s, sum(CASE WHEN src = s[dst + 1] THEN n_pieces ELSE 0 END) AS kept, sum(CASE WHEN src <> s[dst + 1] THEN vol ELSE 0 END) AS after FROM perms, tr GROUP BY s)
  SELECT (SELECT CAST(sum(vol) AS BIGINT) FROM tr WHERE src <> dst) AS before, CAST(min(after) AS BIGINT) AS after FROM x WHERE kept = (SELECT max(kept) FROM x)""")
def base_item_relabel(spark: SparkSession, d: str) -> DataFrame:
    """The older model: all items equal, judged by volume afterwards."""
    return report(spark, find_relabeling(region(spark, d), cost.ItemCost(), n=5))


query("base_gram_entries", GRAM_SQL)(lambda s, d: entry_product(x := emb(s, d), x))
query("base_gram_tiles", GRAM_SQL)(lambda s, d: tiles.tile_product(x := tiles.to_tiles(emb(s, d), Layout.slabs(*src.emb_shape(s, d), 8)), x))
query("base_spark_repartition", SELECT_EMB)(lambda s, d: emb(s, d).repartitionByRange(16, "i", "j"))


@query("solver_compare", f"""WITH e AS ({BEST_SQL}), g AS ({sql.greedy('gain')}), r AS ({sql.greedy('retained')})
  SELECT 'exact' AS solver, after FROM e UNION ALL SELECT 'greedy', after FROM g UNION ALL SELECT 'retained', after FROM r""".replace("WITH e AS (WITH ", "WITH e AS (WITH "))
def solver_compare(spark: SparkSession, d: str) -> DataFrame:
    p = region(spark, d)
    return frame(spark, [(k, find_relabeling(p, solver=k, n=5).after) for k in ("exact", "greedy", "retained")], "solver string, after long")


# ---- measures -----------------------------------------------------------------------------------

query("m_volume", f"WITH {sql.TRADE} SELECT CAST(sum(vol) AS BIGINT) AS remote FROM tr WHERE src <> dst")(lambda s, d: measures.volume_remote(region(s, d)))
query("m_volume_after", f"WITH {sql.TRADE}, {sql.BEST} SELECT CAST(after AS BIGINT) AS remote FROM best")(lambda s, d: measures.volume_remote(p := region(s, d), find_relabeling(p, n=5).sigma))
query("m_reduction", f"SELECT before, after, round((before - after) * 100.0 / before, 4) AS reduction FROM ({BEST_SQL})")(lambda s, d: measures.reduction_pct(p := region(s, d), find_relabeling(p, n=5).sigma))
query("m_messages", f"WITH {sql.TRADE} SELECT count(*) AS packed, CAST(sum(n_pieces) AS BIGINT) AS unpacked FROM tr WHERE src <> dst")(lambda s, d: measures.message_count(region(s, d)))
query("m_site_load", f"""WITH {sql.TRADE} SELECT site, CAST(sum(sent) AS BIGINT) AS sent, CAST(sum(received) AS BIGINT) AS received
  FROM (SELECT src AS site, vol AS sent, 0 AS received FROM tr WHERE src <> dst UNION ALL SELECT dst, 0, vol FROM tr WHERE src <> dst) GROUP BY site""")(lambda s, d: measures.site_load(region(s, d)))
query("m_overlay", f"WITH {sql.parcels(*E, A_ARGS, B_ARGS)} SELECT CAST(sum(n_pieces) AS BIGINT) AS pieces FROM parcels")(lambda s, d: factored_parcels(s, LA, LB).agg(F.sum("n_pieces").alias("pieces")))
query("m_residual", "SELECT CAST(0 AS BIGINT) AS residual")(lambda s, d: measures.max_residual(run(x := emb(s, d), *ends(s, d)), x))
query("m_ratio", f"SELECT round((e.before - g.after) / (e.before - e.after), 6) AS ratio FROM ({BEST_SQL}) e, ({sql.greedy('gain')}) g")(
    lambda s, d: frame(s, [(round(((e := find_relabeling(p := region(s, d), n=5)).before - find_relabeling(p, solver='greedy', n=5).after) / (e.before - e.after), 6),)], "ratio double")
)
query("m_gain_bound", f"WITH {sql.TRADE} SELECT CAST(sum(greatest(top - own, 0)) AS BIGINT) AS bound FROM (SELECT dst, max(vol) AS top, sum(CASE WHEN src = dst THEN vol ELSE 0 END) AS own FROM tr GROUP BY dst)")(lambda s, d: measures.gain_bound(region(s, d)))
