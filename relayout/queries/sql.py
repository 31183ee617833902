"""Pieces of the oracles, written independently of the library: cells and owners by integer arithmetic."""

from __future__ import annotations

EMB = "emb AS (SELECT i, j, CAST(floor(CAST(x AS DOUBLE) * 1000) AS BIGINT) AS v FROM (SELECT vec_id AS i, unnest(range(0, len(embedding))) AS j, unnest(embedding) AS x FROM embeddings))"

TRADE = """tr AS (
  SELECT CAST(ns.n_regionkey AS INTEGER) AS src, CAST(nc.n_regionkey AS INTEGER) AS dst, count(*) AS n_pieces, CAST(sum(l_quantity) AS BIGINT) AS vol
  FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
  JOIN nation ns ON s_nationkey = ns.n_nationkey JOIN nation nc ON c_nationkey = nc.n_nationkey GROUP BY 1, 2)"""

LINKS = "links AS (SELECT CAST(a AS INTEGER) AS src, CAST(b AS INTEGER) AS dst, abs(a - b) * 1000.0::DOUBLE AS lat, abs(a - b)::DOUBLE AS bw FROM range(5) x(a), range(5) y(b))"

PERMS = "perms AS (SELECT a, b, c, d, e, [a, b, c, d, e] AS s FROM range(5) p(a), range(5) q(b), range(5) r(c), range(5) t(d), range(5) u(e) WHERE len(list_distinct([a, b, c, d, e])) = 5)"


def own(i: str, j: str, mb: int, nb: int, pr: int, pc: int, order: str = "row") -> str:
    r, c = f"(({i} // {mb}) % {pr})", f"(({j} // {nb}) % {pc})"
    return f"CAST({r} * {pc} + {c} AS INTEGER)" if order == "row" else f"CAST({c} * {pr} + {r} AS INTEGER)"


def blocks(m: int, n: int, mb: int, nb: int, pr: int, pc: int, order: str = "row") -> str:
    return f"""SELECT bi, bj, bi * {mb} AS r_lo, least((bi + 1) * {mb}, {m}) AS r_hi, bj * {nb} AS c_lo, least((bj + 1) * {nb}, {n}) AS c_hi,
  {own(f'(bi * {mb})', f'(bj * {nb})', mb, nb, pr, pc, order)} AS site FROM range({-(-m // mb)}) x(bi), range({-(-n // nb)}) y(bj)"""


#: Tables as sparse matrices, a row for each cell that a table's row is in.
POINTS = {name: f"points AS (SELECT * FROM ({rows}) WHERE i >= 0 AND j >= 0)" for name, rows in {
    "customer_months": "SELECT o_custkey AS i, month(o_orderdate) - 1 AS j FROM orders",
    "supplier_months": "SELECT l_suppkey AS i, month(l_shipdate) - 1 AS j FROM lineitem",
    "supplier_parts": "SELECT l_suppkey AS i, l_partkey AS j FROM lineitem",
    "quantity_lines": "SELECT CAST(floor(l_quantity) AS BIGINT) AS i, l_linenumber AS j FROM lineitem WHERE l_quantity >= 0 AND l_quantity < 51",
    "user_hours": "SELECT user_id AS i, hour(ts) AS j FROM events",
    "minute_hours": "SELECT minute(ts) AS i, hour(ts) AS j FROM events",
}.items()}


def loaded(points: str, mb: str | int, nb: str | int, pr: int, pc: int, order: str = "row", n: str | int = "coalesce(max(j) + 1, 0)") -> str:
    """Blocks over all rows of a table, and how many rows each holds; mb, nb may be expressions of the extents m and n."""
    many = lambda size, k: f"SELECT unnest(range(({size} + {k} - 1) // {k})) AS b FROM size"
    return f"""WITH {POINTS[points]}, size AS (SELECT m, n, {mb} AS mb, {nb} AS nb FROM (SELECT CAST(coalesce(max(i) + 1, 0) AS BIGINT) AS m, CAST({n} AS BIGINT) AS n FROM points)),
  held AS (SELECT i // mb AS bi, j // nb AS bj, count(*) AS n_rows FROM points, size GROUP BY 1, 2)
  SELECT x.b AS bi, y.b AS bj, x.b * mb AS r_lo, least((x.b + 1) * mb, m) AS r_hi, y.b * nb AS c_lo, least((y.b + 1) * nb, n) AS c_hi, {own('x.b', 'y.b', 1, 1, pr, pc, order)} AS site, coalesce(n_rows, 0) AS n_rows
  FROM size, ({many('m', 'mb')}) x, ({many('n', 'nb')}) y LEFT JOIN held ON held.bi = x.b AND held.bj = y.b"""


def cells(m: int, n: int) -> str:
    return f"cells AS (SELECT i, j FROM range({m}) x(i), range({n}) y(j))"


def parcels(m: int, n: int, a: tuple, b: tuple, elem: int = 8, flip: bool = False, name: str = "parcels") -> str:
    """Parcels counted cell by cell; a, b: (mb, nb, pr, pc, order). flip: b describes B, and op is the transpose."""
    x, y = ("j", "i") if flip else ("i", "j")
    piece = f"i // {a[0]}, j // {a[1]}, {x} // {b[0]}, {y} // {b[1]}"
    return f"""{cells(m, n)}, {name} AS (SELECT {own(x, y, *b)} AS src, {own('i', 'j', *a)} AS dst, count(DISTINCT ({piece})) AS n_pieces,
  CAST(count(*) * {elem} AS BIGINT) AS vol FROM cells GROUP BY 1, 2)"""


def remote_of_grids(cases: list[tuple]) -> str:
    """(name, before) of pairs of block-cyclic layouts, from counts of each axis, so that any shape can be checked. A case:
    name, shape, and of A and B (mb, nb, pr, pc, order)."""
    one = []
    for name, (m, n), a, b in cases:
        axis = lambda size, k, q: f"(SELECT (i // {a[k]}) % {a[k + 2]} AS a, (i // {b[k]}) % {b[k + 2]} AS b, count(*) AS n FROM range({size}) t(i) GROUP BY 1, 2) {q}"
        site = lambda x, q: f"r.{q} * {x[3]} + c.{q}" if x[4] == "row" else f"c.{q} * {x[2]} + r.{q}"
        one.append(f"SELECT '{name}' AS name, CAST(sum(CASE WHEN {site(a, 'a')} <> {site(b, 'b')} THEN r.n * c.n ELSE 0 END) AS BIGINT) AS before FROM {axis(m, 0, 'r')}, {axis(n, 1, 'c')}")
    return " UNION ALL ".join(one)


#: The smallest remote volume over all relabelings of five sites.
BEST = f"{PERMS}, best AS (SELECT (SELECT CAST(sum(vol) AS BIGINT) FROM tr) - max(kept) AS after FROM (SELECT perms.s, CAST(sum(CASE WHEN tr.src = perms.s[tr.dst + 1] THEN vol ELSE 0 END) AS BIGINT) AS kept FROM perms, tr GROUP BY perms.s))"


def greedy(order: str) -> str:
    """Gains in a strict order, taken one pair a step by a recursive query. order: gain or retained."""
    by = "gain" if order == "gain" else "v"
    return f"""WITH RECURSIVE {TRADE}, g AS (
  SELECT x AS role, y AS site, coalesce(t.vol, 0) AS v, coalesce(t.vol, 0) - coalesce(d.vol, 0) AS gain
  FROM range(5) p(x) CROSS JOIN range(5) q(y) LEFT JOIN tr t ON t.src = y AND t.dst = x LEFT JOIN tr d ON d.src = x AND d.dst = x
), o AS (SELECT *, row_number() OVER (ORDER BY {by} DESC, role, site) AS k FROM g
), step AS (
  SELECT CAST(0 AS BIGINT) AS k, CAST([] AS BIGINT[]) AS roles, CAST([] AS BIGINT[]) AS sites, CAST(0 AS HUGEINT) AS won
  UNION ALL
  SELECT nk, CASE WHEN f THEN list_append(roles, r) ELSE roles END, CASE WHEN f THEN list_append(sites, y) ELSE sites END, CASE WHEN f THEN won + gain ELSE won END
  FROM (SELECT step.*, o.k AS nk, NOT list_contains(roles, o.role) AND NOT list_contains(sites, o.site) AS f, o.role AS r, o.site AS y, o.gain FROM step JOIN o ON o.k = step.k + 1) z
) SELECT CAST(b AS BIGINT) AS before, CAST(b - greatest(won, 0) AS BIGINT) AS after
  FROM (SELECT sum(vol) AS b FROM tr WHERE src <> dst), (SELECT won FROM step ORDER BY k DESC LIMIT 1)"""
