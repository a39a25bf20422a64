"""The definitions in plain SQL, by brute force, for checks against another engine. Nothing here shares code with the operators."""

from __future__ import annotations


def point_sql(name: str, normalise: bool = True) -> tuple[str, int]:
    """SELECT id, x0.. of a fixture, and its dimension."""
    cents = lambda c: f"CAST(round({c} * 100) AS BIGINT)"
    if name.startswith("line"):
        d = int(name[4:])
        cols = ["l_quantity", "l_extendedprice", "date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE))", "l_discount", "l_tax"][:d]
        base = f"SELECT (l_orderkey * 8 + l_linenumber) * 16777216 + {cents('l_extendedprice')} AS id, {', '.join(f'CAST({c} AS DOUBLE) AS v{i}' for i, c in enumerate(cols))} FROM lineitem"
    elif name == "orders2":
        base, d = "SELECT o_orderkey AS id, o_totalprice AS v0, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS DOUBLE) AS v1 FROM orders", 2
    elif name == "part2":
        base, d = "SELECT p_partkey AS id, CAST(p_size AS DOUBLE) AS v0, p_retailprice AS v1 FROM part", 2
    elif name in ("customer2", "customer3"):
        spent = f"SELECT o_custkey, CAST(sum({cents('o_totalprice')}) AS DOUBLE) AS s, CAST(count(*) AS DOUBLE) AS n FROM orders GROUP BY o_custkey"
        cols, d = ("c_acctbal AS v0, s AS v1, n AS v2", 3) if name == "customer3" else ("s AS v0, n AS v1", 2)
        base = f"SELECT c_custkey AS id, {cols} FROM customer JOIN ({spent}) ON o_custkey = c_custkey"
    elif name == "supplier3":
        base, d = f"SELECT s_suppkey AS id, s_acctbal AS v0, s AS v1, n AS v2 FROM supplier JOIN (SELECT l_suppkey, CAST(sum({cents('l_extendedprice')}) AS DOUBLE) AS s, CAST(count(*) AS DOUBLE) AS n FROM lineitem GROUP BY l_suppkey) ON l_suppkey = s_suppkey", 3
    elif name == "users4":
        base, d = f"SELECT user_id AS id, s AS v0, n AS v1, s / n AS v2, m AS v3 FROM (SELECT user_id, CAST(sum({cents('value')}) AS DOUBLE) AS s, CAST(count(*) AS DOUBLE) AS n, max(value) AS m FROM events WHERE user_id IS NOT NULL GROUP BY user_id)", 4
    elif name.startswith("emb"):
        d, normalise = int(name[3:]), False
        base = f"SELECT vec_id AS id, {', '.join(f'CAST(embedding[{i + 1}] AS DOUBLE) AS v{i}' for i in range(d))} FROM embeddings"
    elif name == "doc3":
        base, d = "SELECT doc_id AS id, CAST(n_chars AS DOUBLE) AS v0, CAST(len(w) AS DOUBLE) AS v1, CAST(len(list_distinct(w)) AS DOUBLE) / len(w) AS v2 FROM (SELECT doc_id, n_chars, string_split(coalesce(text, ''), ' ') AS w FROM documents)", 3
    elif name == "conv2":
        base, d = "SELECT conv_id AS id, CAST(count(*) AS DOUBLE) AS v0, CAST(sum(length(text)) AS DOUBLE) / count(*) AS v1 FROM conversations GROUP BY conv_id", 2
    elif name == "page2":
        base, d = "SELECT page_id AS id, CAST(length(html) AS DOUBLE) AS v0, CAST(length(html) - length(replace(html, '<', '')) AS DOUBLE) AS v1 FROM pages", 2
    else:
        raise KeyError(name)
    scaled = [f"(v{i} - min(v{i}) OVER ()) / nullif(max(v{i}) OVER () - min(v{i}) OVER (), 0) AS x{i}" if normalise else f"v{i} AS x{i}" for i in range(d)]
    return f"SELECT id, {', '.join(scaled)} FROM ({base})", d


def lattice_sql(d: int, steps: int) -> str:
    cells = ", ".join(f"CAST((range // {steps**i}) % {steps} AS DOUBLE) / {float(steps - 1)} AS x{i}" for i in range(d))
    return f"SELECT range AS id, {cells} FROM range({steps**d})"


def draw_sql(seed: int, id_: str = "id") -> str:
    return f"((({id_} % 2147483647) * 2654435761 + {seed}) % 4294967296)"


def sets_sql(d: int, n_sets: int, m: int, extent: float | None, seed: int = 0, points: str = "pts") -> str:
    """set_id, q, x0..: drawn in a cube of volume `extent`, or nearest neighbours where that is None."""
    anchors = f"SELECT row_number() OVER (ORDER BY {draw_sql(seed)}, id) - 1 AS set_id, id AS anchor, {', '.join(f'x{i} AS a{i}' for i in range(d))} FROM {points} ORDER BY {draw_sql(seed)}, id LIMIT {n_sets}"
    if extent is None:
        near = f"SELECT set_id, id, {', '.join(f'x{i}' for i in range(d))}, row_number() OVER (PARTITION BY set_id ORDER BY CAST(id <> anchor AS INTEGER), {' + '.join(f'(x{i} - a{i}) * (x{i} - a{i})' for i in range(d))}, id) AS r FROM {points}, ({anchors})"
    else:
        half = extent ** (1 / d) / 2
        inside = " AND ".join(f"x{i} >= a{i} - CAST({half!r} AS DOUBLE) AND x{i} <= a{i} + CAST({half!r} AS DOUBLE)" for i in range(d))
        near = f"SELECT set_id, id, {', '.join(f'x{i}' for i in range(d))}, row_number() OVER (PARTITION BY set_id ORDER BY CAST(id <> anchor AS INTEGER), {draw_sql(seed)}, id) AS r FROM {points} JOIN ({anchors}) ON {inside}"
    return f"SELECT CAST(set_id AS BIGINT) AS set_id, id AS q, {', '.join(f'x{i}' for i in range(d))} FROM ({near}) WHERE r <= {m}"


def d2_sql(a: str, b: str, d: int) -> str:
    return "(" + " + ".join(f"({a}.x{i} - {b}.x{i}) * ({a}.x{i} - {b}.x{i})" for i in range(d)) + ")"


def dominates_sql(o: str, q: str, r: str, d: int) -> str:
    pairs = [(f"abs({o}.x{i} - {r}.x{i})", f"abs({q}.x{i} - {r}.x{i})") for i in range(d)]
    return "(" + " AND ".join(f"{x} <= {y}" for x, y in pairs) + ") AND (" + " OR ".join(f"{x} < {y}" for x, y in pairs) + ")"


def with_sql(fixture: str, sets: str, d: int, candidates: str | None = None) -> str:
    pool = f", pool AS ({candidates})" if candidates else ", pool AS (SELECT * FROM pts)"
    return f"WITH pts AS MATERIALIZED ({point_sql(fixture)[0]}), q AS MATERIALIZED ({sets}){pool}, ids AS (SELECT set_id, count(*) AS m FROM q GROUP BY set_id) "


def eps_sql(d: int, eps: float, closed: bool = True, keep_queries: bool = False, limit: str | None = None) -> str:
    limit = limit or f"CAST({eps!r} AS DOUBLE) * CAST({eps!r} AS DOUBLE)"
    drop = "" if keep_queries else " AND NOT EXISTS (SELECT 1 FROM q z WHERE z.set_id = h.set_id AND z.q = h.id)"
    return f"SELECT h.set_id, h.id FROM (SELECT q.set_id, p.id, count(*) AS n FROM pool p JOIN q ON {d2_sql('p', 'q', d)} {'<=' if closed else '<'} {limit} GROUP BY q.set_id, p.id) h JOIN ids ON ids.set_id = h.set_id WHERE h.n = ids.m{drop}"


def knn_sql(d: int, k: int | str, keep_queries: bool = False, mono: bool = True) -> str:
    own = "CAST(EXISTS (SELECT 1 FROM q z WHERE z.set_id = s.set_id AND z.q = p.id) AS INTEGER)" if mono else "0"
    other = "q.q <> c.id AND " if mono else ""
    cand = f"SELECT s.set_id, s.m, p.*, {own} AS own FROM pool p CROSS JOIN ids s"
    keep = "" if keep_queries else "WHERE own = 0"
    names = ", ".join(f"c.x{i}" for i in range(d))
    ref = f"SELECT c.set_id, c.m, c.id, c.own, {names}, max({{'d': {d2_sql('c', 'q', d)}, 'q': q.q}}) AS r FROM (SELECT * FROM ({cand}) {keep}) c JOIN q ON {other}q.set_id = c.set_id GROUP BY c.set_id, c.m, c.id, c.own, {names}"
    away = "o.id <> c.id AND " if mono else ""
    return f"SELECT c.set_id, c.id FROM ({ref}) c LEFT JOIN pts o ON {away}({d2_sql('o', 'c', d)} < c.r.d OR ({d2_sql('o', 'c', d)} = c.r.d AND o.id < c.r.q)) WHERE c.m <= {k} GROUP BY c.set_id, c.id, c.own HAVING count(o.id) <= {k} - 1 - c.own"


def sky_sql(d: int, mono: bool = True) -> str:
    cand = "SELECT s.set_id, p.* FROM pool p CROSS JOIN ids s" + (" WHERE NOT EXISTS (SELECT 1 FROM q z WHERE z.set_id = s.set_id AND z.q = p.id)" if mono else "")
    away = "o.id <> c.id AND " if mono else ""
    return f"SELECT set_id, id FROM ({cand}) EXCEPT SELECT DISTINCT c.set_id, c.id FROM ({cand}) c JOIN q ON q.set_id = c.set_id JOIN pts o ON {away}o.id <> q.q AND {dominates_sql('o', 'q', 'c', d)}"


def knn_bounded_sql(d: int, k: int, near: int) -> str:
    """knn_sql for larger tables: an object with k of the `near` points that lie nearest to one member ahead of its furthest member is
    no result, whatever the other points are; only the objects that are left are compared with all points."""
    names = ", ".join(f"c.x{i}" for i in range(d))
    ref = f"SELECT c.set_id, c.m, c.id, {names}, max({{'d': {d2_sql('c', 'q', d)}, 'q': q.q}}) AS r FROM (SELECT s.set_id, s.m, p.* FROM pool p CROSS JOIN ids s WHERE NOT EXISTS (SELECT 1 FROM q z WHERE z.set_id = s.set_id AND z.q = p.id)) c JOIN q ON q.set_id = c.set_id GROUP BY c.set_id, c.m, c.id, {names}"
    ahead = lambda o: f"o.id <> c.id AND ({d2_sql(o, 'c', d)} < c.r.d OR ({d2_sql(o, 'c', d)} = c.r.d AND o.id < c.r.q))"
    some = f"SELECT set_id, id, {', '.join(f'x{i}' for i in range(d))} FROM (SELECT a.set_id, p.*, row_number() OVER (PARTITION BY a.set_id ORDER BY {d2_sql('p', 'a', d)}, p.id) AS r FROM pts p CROSS JOIN (SELECT * FROM q QUALIFY row_number() OVER (PARTITION BY set_id ORDER BY q) = 1) a) WHERE r <= {near}"
    left = f"SELECT c.set_id, c.m, c.id, {names}, any_value(c.r) AS r FROM ({ref}) c LEFT JOIN ({some}) o ON o.set_id = c.set_id AND {ahead('o')} WHERE c.m <= {k} GROUP BY c.set_id, c.m, c.id, {names} HAVING count(o.id) <= {k} - 1"
    return f"SELECT c.set_id, c.id FROM ({left}) c LEFT JOIN pts o ON {ahead('o')} GROUP BY c.set_id, c.id HAVING count(o.id) <= {k} - 1"
