"""DuckDB SQL for the catalogue's queries, built from shared pieces."""

from __future__ import annotations

EMB = "SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings"
SUPP = """
    SELECT s_suppkey AS id, list_concat([(s_acctbal - m) / s], [CASE WHEN n_regionkey = r THEN 1.0::DOUBLE ELSE 0.0 END FOR r IN [0, 1, 2, 3, 4]]) AS e
    FROM supplier JOIN nation ON n_nationkey = s_nationkey, (SELECT avg(s_acctbal) AS m, stddev_samp(s_acctbal) AS s FROM supplier)
"""
PART = """
    SELECT p_partkey AS id, [(p_size - m1) / s1, (p_retailprice - m2) / s2] AS e FROM part,
        (SELECT avg(p_size) AS m1, stddev_samp(p_size) AS s1, avg(p_retailprice) AS m2, stddev_samp(p_retailprice) AS s2 FROM part)
"""
EVERY = 20
#: The columns stay apart here: the table is too large for list arithmetic over all pairs.
LINE_KNN = f"""
    WITH z AS (SELECT avg(l_quantity) m1, stddev_samp(l_quantity) s1, avg(l_extendedprice) m2, stddev_samp(l_extendedprice) s2,
        avg(l_discount) m3, stddev_samp(l_discount) s3, avg(l_tax) m4, stddev_samp(l_tax) s4 FROM lineitem),
    pt AS MATERIALIZED (SELECT CAST(concat('0x', substr(md5(concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey)), 1, 15)) AS BIGINT) AS id,
        (l_quantity - m1) / s1 AS a, (l_extendedprice - m2) / s2 AS b, (l_discount - m3) / s3 AS c, (l_tax - m4) / s4 AS d FROM lineitem, z),
    best AS (SELECT q.id AS q_id, min({{'d': (q.a - p.a) * (q.a - p.a) + (q.b - p.b) * (q.b - p.b) + (q.c - p.c) * (q.c - p.c) + (q.d - p.d) * (q.d - p.d), 'id': p.id}}, 10) AS n
        FROM pt q, pt p WHERE q.id % {EVERY} = 0 AND p.id % {EVERY} <> 0 GROUP BY q.id)
    SELECT q_id, CAST(rank AS INTEGER) AS rank, n[rank].id AS vec_id, round(sqrt(n[rank].d), 6) AS dist FROM best, range(1, 11) t(rank) WHERE rank <= len(n)
"""


def knn(points: str, k: int, where: str = "TRUE") -> str:
    """Common table expressions ending in knn(q_id, rank, vec_id, dist): each query's k nearest other points."""
    return f"""
    pt AS ({points}),
    knn AS (
        SELECT q_id, rank, vec_id, dist FROM (
            SELECT q.id AS q_id, b.id AS vec_id, list_distance(q.e, b.e) AS dist, row_number() OVER (PARTITION BY q.id ORDER BY list_distance(q.e, b.e), b.id) AS rank
            FROM pt q JOIN pt b ON q.id <> b.id WHERE q.id % {EVERY} = 0 AND ({where})
        ) WHERE rank <= {k}
    )"""


def exact_knn(points: str, k: int, where: str = "TRUE") -> str:
    return f"WITH {knn(points, k, where)} SELECT q_id, CAST(rank AS INTEGER) AS rank, vec_id, round(dist, 6) AS dist FROM knn"


def folded(points: str, drop: str, cap: int | None = None, top: int | None = None) -> str:
    """CTEs ending in edges(src, dst, dist, rank): the ordered filter over all others, or over the ``top`` nearest.

    ``drop`` is a condition over d_pu and d_uv.
    """
    test = drop.replace("d_pu", "c.d").replace("d_uv", "m.row[v]")
    full = f"len(f.s) >= {cap} OR " if cap else ""
    last = f"least({top}, (SELECT count(*) FROM pt) - 1)" if top else "(SELECT count(*) FROM pt) - 1"
    return f"""
    pt AS MATERIALIZED (SELECT row_number() OVER (ORDER BY id) AS i, id, e FROM ({points})),
    pr AS MATERIALIZED (SELECT a.i AS p, b.i AS u, list_distance(a.e, b.e) AS d FROM pt a, pt b),
    mat AS MATERIALIZED (SELECT p AS i, list(d ORDER BY u) AS row FROM pr GROUP BY p),
    cand AS MATERIALIZED (SELECT p, u, d, row_number() OVER (PARTITION BY p ORDER BY d, u) AS rn FROM pr WHERE p <> u),
    fold(p, rn, s) AS (
        SELECT i, CAST(0 AS BIGINT), CAST([] AS BIGINT[]) FROM pt
        UNION ALL
        SELECT f.p, f.rn + 1, CASE WHEN {full}len([v FOR v IN f.s IF {test}]) > 0 THEN f.s ELSE list_append(f.s, c.u) END
        FROM fold f JOIN cand c ON c.p = f.p AND c.rn = f.rn + 1 JOIN mat m ON m.i = c.u WHERE f.rn < {last}
    ),
    kept AS (SELECT p, s FROM fold WHERE rn = {last}),
    edges AS MATERIALIZED (
        SELECT a.id AS src, b.id AS dst, m.row[x.u] AS dist, x.rank AS rank
        FROM (SELECT p, unnest(s) AS u, unnest(range(1, len(s) + 1)) AS rank FROM kept) x JOIN pt a ON a.i = x.p JOIN pt b ON b.i = x.u JOIN mat m ON m.i = x.p
    )"""


def edges(points: str, drop: str, cap: int | None = None, top: int | None = None) -> str:
    return f"WITH RECURSIVE {folded(points, drop, cap, top)} SELECT src, dst, round(dist, 6) AS dist, CAST(rank AS INTEGER) AS rank FROM edges"


def adaptive(points: str, top: int, m: int, tau: float, start: float, step: float, count: int) -> str:
    """The first alpha whose kept set (at most m) has at least half of m, else the last one's set."""
    return f"""
    WITH RECURSIVE
    pt AS MATERIALIZED (SELECT row_number() OVER (ORDER BY id) AS i, id, e FROM ({points})),
    pr AS MATERIALIZED (SELECT a.i AS p, b.i AS u, list_distance(a.e, b.e) AS d FROM pt a, pt b),
    mat AS MATERIALIZED (SELECT p AS i, list(d ORDER BY u) AS row FROM pr GROUP BY p),
    cand AS MATERIALIZED (SELECT p, u, d, row_number() OVER (PARTITION BY p ORDER BY d, u) AS rn FROM pr WHERE p <> u),
    al AS (SELECT CAST(k AS INTEGER) AS k, {start}::DOUBLE + k * {step}::DOUBLE AS a FROM range({count}) t(k)),
    fold(p, k, a, rn, s) AS (
        SELECT i, k, a, CAST(0 AS BIGINT), CAST([] AS BIGINT[]) FROM pt, al
        UNION ALL
        SELECT f.p, f.k, f.a, f.rn + 1,
            CASE WHEN len(f.s) >= {m} OR len([v FOR v IN f.s IF (c.d - {tau}::DOUBLE) / (m.row[v] + {tau}::DOUBLE) > f.a]) > 0 THEN f.s ELSE list_append(f.s, c.u) END
        FROM fold f JOIN cand c ON c.p = f.p AND c.rn = f.rn + 1 JOIN mat m ON m.i = c.u WHERE f.rn < {top}
    ),
    done AS (SELECT *, 2 * len(s) >= {m} AS ok FROM fold WHERE rn = {top}),
    pick AS (SELECT p, coalesce(min(CASE WHEN ok THEN k END), {count - 1}) AS k FROM done GROUP BY p)
    SELECT t.id AS p, round(d.a, 6) AS alpha_used, CAST(d.k + 1 AS INTEGER) AS steps, CAST(len(d.s) AS INTEGER) AS n_kept,
        array_to_string([(SELECT any_value(x.id) FROM pt x WHERE x.i = v) FOR v IN d.s], ',') AS kept
    FROM done d JOIN pick USING (p, k) JOIN pt t ON t.i = d.p"""


def adaptive_joined(points: str, top: int, m: int, tau: float, start: float, step: float, count: int) -> str:
    """The same with kept ids joined as rows and put together again, for engines without subqueries in lists."""
    head = adaptive(points, top, m, tau, start, step, count).split("    SELECT t.id AS p")[0]
    return head + """
    SELECT t.id AS p, round(min(d.a), 6) AS alpha_used, CAST(min(d.k) + 1 AS INTEGER) AS steps, CAST(count(*) AS INTEGER) AS n_kept,
        string_agg(CAST(x.id AS VARCHAR), ',' ORDER BY d.at) AS kept
    FROM (SELECT p, k, a, unnest(s) AS v, unnest(range(1, len(s) + 1)) AS at FROM done JOIN pick USING (p, k)) d JOIN pt t ON t.i = d.p JOIN pt x ON x.i = d.v GROUP BY t.id"""


# -- graphs and search, step by step ---------------------------------------------

CENTRE = "centre AS MATERIALIZED (SELECT list(m ORDER BY c) AS m FROM (SELECT c, avg(e[c]) AS m FROM pt, range(1, 65) t(c) GROUP BY c))"


def beam(name: str, asked: str, lists: str, width: int) -> str:
    """CTEs ending in ``name``_end(q, queue, seen, hops, scanned): beam search over ``lists(p, s)``, all ids being places.

    ``asked`` has q, start and row: the query's distances by place. A queue entry
    is (d, v, x), x telling whether it was expanded.
    """
    return f"""
    {name}(q, hops, queue, seen, scanned) AS (
        SELECT q, 0, [{{'d': row[start], 'v': start, 'x': false}}], [start], 0 FROM {asked}
        UNION ALL
        SELECT t.q, t.hops + 1,
            list_sort(list_concat([{{'d': z.d, 'v': z.v, 'x': z.x OR z.v = t.u}} FOR z IN t.queue], [{{'d': a.row[w], 'v': w, 'x': false}} FOR w IN k.s IF NOT list_contains(t.seen, w)]))[1:{width}],
            list_concat(t.seen, [w FOR w IN k.s IF NOT list_contains(t.seen, w)]), t.scanned + len(k.s)
        FROM (SELECT *, [z.v FOR z IN queue IF NOT z.x][1] AS u FROM {name}) t JOIN {lists} k ON k.p = t.u JOIN {asked} a ON a.q = t.q
    ),
    {name}_end AS MATERIALIZED (SELECT q, arg_max(queue, hops) AS queue, arg_max(seen, hops) AS seen, max(hops) AS hops, arg_max(scanned, hops) AS scanned FROM {name} GROUP BY q)"""


def chosen(name: str, cand: str, alphas: list[float], m: int, tau: float, drop: str | None = None) -> str:
    """CTEs ending in ``name``(p, s): the ordered filter over ``cand(p, rn, u, d)`` with cap ``m``, at the first alpha that keeps half of ``m``, else the last.

    ``drop`` is another rule's condition over d_pu and d_uv, without alphas.
    """
    test = drop.replace("d_pu", "c.d").replace("d_uv", "x.row[v]") if drop else f"(c.d - {tau}::DOUBLE) / (x.row[v] + {tau}::DOUBLE) > f.a"
    values = ", ".join(f"({k}, {a!r}::DOUBLE)" for k, a in enumerate(alphas))
    return f"""
    {name}_al(k, a) AS (VALUES {values}),
    {name}_fold(p, k, a, rn, s) AS (
        SELECT p, k, a, CAST(0 AS BIGINT), CAST([] AS BIGINT[]) FROM (SELECT DISTINCT p FROM {cand}), {name}_al
        UNION ALL
        SELECT f.p, f.k, f.a, f.rn + 1, CASE WHEN len(f.s) >= {m} OR len([v FOR v IN f.s IF {test}]) > 0 THEN f.s ELSE list_append(f.s, c.u) END
        FROM {name}_fold f JOIN {cand} c ON c.p = f.p AND c.rn = f.rn + 1 JOIN mat x ON x.i = c.u
    ),
    {name}_done AS MATERIALIZED (SELECT p, k, arg_max(s, rn) AS s FROM {name}_fold GROUP BY p, k),
    {name} AS MATERIALIZED (SELECT p, coalesce(arg_min(s, k) FILTER (WHERE 2 * len(s) >= {m}), arg_max(s, k)) AS s FROM {name}_done GROUP BY p)"""


PLACES = """
    pt AS MATERIALIZED (SELECT row_number() OVER (ORDER BY id) AS i, id, e FROM ({points})),
    pr AS MATERIALIZED (SELECT a.i AS p, b.i AS u, list_distance(a.e, b.e) AS d FROM pt a, pt b),
    mat AS MATERIALIZED (SELECT p AS i, list(d ORDER BY u) AS row FROM pr GROUP BY p)"""


def local_graph(points: str, k: int, m: int, width: int, c: int, alphas: list[float], tau: float, drop: str | None = None, backward: bool = True) -> str:
    """Edges of a local graph from its phases: K-NN graph, entry from the first place, candidates by search, selection, backward edges pruned once."""
    head = f"""
    WITH RECURSIVE {PLACES.format(points=points)}, {CENTRE},
    kn AS MATERIALIZED (SELECT p, list(u ORDER BY d, u) AS s FROM (SELECT *, row_number() OVER (PARTITION BY p ORDER BY d, u) AS rn FROM pr WHERE p <> u) WHERE rn <= {k} GROUP BY p),
    to_centre AS MATERIALIZED (SELECT 0 AS q, CAST(1 AS BIGINT) AS start, list(list_distance(e, m) ORDER BY i) AS row FROM pt, centre),
    {beam("first", "to_centre", "kn", width)},
    to_each AS MATERIALIZED (SELECT i AS q, (SELECT queue[1].v FROM first_end) AS start, row FROM mat),
    {beam("every", "to_each", "kn", width)},
    cand AS MATERIALIZED (SELECT * FROM (
        SELECT x.p, x.u, pr.d, row_number() OVER (PARTITION BY x.p ORDER BY pr.d, x.u) AS rn
        FROM (SELECT q AS p, unnest(seen) AS u FROM every_end UNION SELECT p, unnest(s) FROM kn) x JOIN pr ON pr.p = x.p AND pr.u = x.u WHERE x.p <> x.u) WHERE rn <= {c}),
    {chosen("forward", "cand", alphas, m, tau, drop)}"""
    if backward:
        head += f""",
    both_ways AS MATERIALIZED (SELECT x.p, x.u, pr.d, row_number() OVER (PARTITION BY x.p ORDER BY pr.d, x.u) AS rn, count(*) OVER (PARTITION BY x.p) AS n
        FROM (SELECT p, unnest(s) AS u FROM forward UNION SELECT unnest(s) AS p, p AS u FROM forward) x JOIN pr ON pr.p = x.p AND pr.u = x.u),
    over AS MATERIALIZED (SELECT * FROM both_ways WHERE n > {m}),
    {chosen("pruned", "over", alphas, m, tau, drop)},
    final AS (SELECT p, s FROM pruned UNION ALL SELECT p, list(u ORDER BY rn) FROM both_ways WHERE n <= {m} GROUP BY p)"""
    else:
        head += ", final AS (SELECT p, s FROM forward)"
    return head + """
    SELECT a.id AS src, b.id AS dst, round(x.row[t.u], 6) AS dist, CAST(t.rank AS INTEGER) AS rank
    FROM (SELECT p, unnest(s) AS u, unnest(range(1, len(s) + 1)) AS rank FROM final) t JOIN pt a ON a.i = t.p JOIN pt b ON b.i = t.u JOIN mat x ON x.i = t.p"""


def _found(points: str, drop: str, name: str, width: int, first: bool = False) -> str:
    """CTEs ending in ``name``_end: beams of all queries over the full graph of a rule, from the point nearest to the mean (or the first)."""
    start = "(SELECT min(i) FROM pt)" if first else "(SELECT arg_min(i, list_distance(e, m)) FROM pt, centre)"
    return f"""{name}_asked AS MATERIALIZED (SELECT i AS q, {start} AS start, row FROM mat JOIN pt USING (i) WHERE id % {EVERY} = 0), {beam(name, f"{name}_asked", "kept", width)}"""


def beam_rows(points: str, drop: str, k: int, width: int) -> str:
    """Each query's k best with distance computations, hops and edges scanned."""
    return f"""
    WITH RECURSIVE {folded(points, drop)}, {CENTRE}, {_found(points, drop, "b", width)}
    SELECT q.id AS q_id, v.id AS vec_id, round(t.z.d, 6) AS dist, CAST(t.ndc AS BIGINT) AS ndc, CAST(t.hops AS BIGINT) AS hops, CAST(t.scanned AS BIGINT) AS edges_scanned
    FROM (SELECT q, unnest(queue[1:{k}]) AS z, len(seen) AS ndc, hops, scanned FROM b_end) t JOIN pt q ON q.i = t.q JOIN pt v ON v.i = t.z.v"""


def beam_curve(points: str, drop: str, k: int, widths: list[int]) -> str:
    """CTEs ending in curve(width, recall, ndc, hops, edges_scanned): means over queries, the query itself being among its own neighbours."""
    beams = ", ".join(_found(points, drop, f"b{w}", w) for w in widths)
    truth = f"truth AS MATERIALIZED (SELECT p AS q, list(u ORDER BY d, u) AS near FROM (SELECT *, row_number() OVER (PARTITION BY p ORDER BY d, u) AS rn FROM pr) WHERE rn <= {k} GROUP BY p)"
    each = " UNION ALL ".join(
        f"SELECT {w} AS width, q, len([z FOR z IN queue[1:{k}] IF list_contains(near, z.v)]) / CAST({k} AS DOUBLE) AS recall, len(seen) AS ndc, hops, scanned FROM b{w}_end JOIN truth USING (q)" for w in widths
    )
    return f"""WITH RECURSIVE {folded(points, drop)}, {CENTRE}, {beams}, {truth},
    curve AS MATERIALIZED (SELECT width, avg(recall) AS recall, avg(ndc) AS ndc, avg(hops) AS hops, avg(scanned) AS edges_scanned FROM ({each}) GROUP BY width)"""


AT_RECALL = """, run AS (SELECT *, max(recall) OVER (ORDER BY ndc, recall) AS r FROM curve),
    pair AS (SELECT *, lag(r) OVER (ORDER BY ndc, recall) AS pr_, lag(ndc) OVER (ORDER BY ndc, recall) AS pn, lag(hops) OVER (ORDER BY ndc, recall) AS ph FROM run),
    cut AS (SELECT *, CASE WHEN pr_ IS NULL THEN NULL WHEN pr_ >= r THEN 1.0 ELSE ({target} - pr_) / (r - pr_) END AS w FROM pair WHERE r >= {target} AND coalesce(pr_, -1) < {target})
    SELECT round(coalesce(pn + w * (ndc - pn), ndc), 6) AS ndc, round(coalesce(ph + w * (hops - ph), hops), 6) AS hops FROM cut"""
