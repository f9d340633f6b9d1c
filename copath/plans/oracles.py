"""Plain SQL for what the miner computes, to check it against another engine: all sets of items at every position."""

from __future__ import annotations

from copath.sources.graphs import oracle_graph

#: Most items that a vertex of a graph has.
MOST = {"trade": 3, "lineage": 3, "copart": 1, "users": 3, "eventchain": 3, "corpus": 5, "dialog": 2}


def theta(share: float, table: str = "vs") -> str:
    return f"(SELECT ceil({share} * count(*) - 0.000000001) FROM {table})"


def one_hop(more: str = "") -> str:
    return f", e1 AS (SELECT es.src, es.label, t.item AS b, es.dst FROM es JOIN ats AS t ON t.v = es.dst {more})"


def text1(h: str, e: str, star: str = "") -> str:
    return f"concat('{{', {h}.item, '}}|', {e}.label, '{star}|{{', {e}.b, '}}')"


P1 = f", p1 AS (SELECT DISTINCT {text1('h', 'x')} AS p, x.src AS v FROM e1 AS x JOIN ats AS h ON h.v = x.src)"
P2 = f", p2 AS (SELECT DISTINCT {text1('h', 'x')} AS pre, concat({text1('h', 'x')}, '|', y.label, '|{{', y.b, '}}') AS p, x.src AS v FROM e1 AS x JOIN e1 AS y ON y.src = x.dst JOIN ats AS h ON h.v = x.src)"


def steps(hops: int) -> str:
    """r: pairs joined by 1 to ``hops`` edges of one label."""
    out = ", r1 AS (SELECT src, label, dst FROM es)"
    for k in range(2, hops + 1):
        out += f", r{k} AS (SELECT DISTINCT a.src, a.label, es.dst FROM r{k - 1} AS a JOIN es ON es.src = a.dst AND es.label = a.label)"
    return out + f", r AS ({' UNION '.join(f'SELECT src, label, dst FROM r{k}' for k in range(1, hops + 1))})"


def reach(hops: int) -> str:
    """ps: reach patterns of single items and their sources."""
    return steps(hops) + f", rb AS (SELECT r.src, r.label, t.item AS b FROM r JOIN ats AS t ON t.v = r.dst), ps AS (SELECT DISTINCT {text1('h', 'x', '*')} AS p, x.src AS v FROM rb AS x JOIN ats AS h ON h.v = x.src)"


def patterns(graph: str, share: float, kind: str, hops: int = 2) -> str:
    """text and support of frequent patterns of single items of one kind: 1, 2 or reach."""
    cte = {"1": one_hop() + P1, "2": one_hop() + P1 + P2, "reach": reach(hops)}[kind]
    table = {"1": "p1", "2": "p2", "reach": "ps"}[kind]
    return oracle_graph(graph) + cte + f" SELECT p AS text, CAST(count(*) AS DOUBLE) AS support FROM {table} GROUP BY p HAVING count(*) >= {theta(share)}"


def item_sets(most: int) -> str:
    """sets(v, txt, ls): every set of a vertex's items of up to ``most`` items."""
    names = "abcdefgh"
    parts = []
    for k in range(1, most + 1):
        own = names[:k]
        text = " , ',', ".join(f"{x}.item" for x in own)
        joins = " ".join(f"JOIN ats AS {y} ON {y}.v = {x}.v AND {x}.item < {y}.item" for x, y in zip(own, own[1:]))
        parts.append(f"SELECT a.v, concat({text}) AS txt, [{', '.join(f'{x}.item' for x in own)}] AS ls FROM ats AS a {joins}")
    return f", sets AS ({' UNION ALL '.join(parts)})"


#: Sources drawn from every stratum: a share of each, or each by its own hash.
def sampled(share: float, rho: float, mode: str = "quota") -> str:
    strata = f", f AS (SELECT item FROM ats GROUP BY item HAVING count(*) >= {theta(share)}), st AS (SELECT v, string_agg(item, ',' ORDER BY item) AS items FROM ats WHERE item IN (SELECT item FROM f) GROUP BY v)"
    draw = "md5(concat(CAST(v AS VARCHAR), '/42'))"
    if mode == "threshold":
        return strata + f", sv AS (SELECT v FROM st WHERE CAST(concat('0x', substr({draw}, 1, 8)) AS BIGINT) < {rho} * 4294967296)"
    return strata + f", k AS (SELECT v, row_number() OVER (PARTITION BY items ORDER BY {draw}, v) AS r, count(*) OVER (PARTITION BY items) AS n FROM st), sv AS (SELECT v FROM k WHERE r <= ceil(n * {rho} - 0.000000001))"


def matches(graph: str, share: float, hops: int = 2, two: bool = True, most: int | None = None, psi: float | None = None, rho: float | None = None, mode: str = "quota") -> str:
    """Common tables: frequent patterns s(p, n, star, h, l0, m, l1, t) with their sets as lists, and mt(p, v).

    What is too rare by itself is left out before heads are joined; no pattern with it could be frequent.
    """
    th, scale = theta(share), rho or 1.0
    often = f"count(*) / {scale} >= {th}"
    cte = oracle_graph(graph) + item_sets(min(most or 99, MOST[graph]))
    own, hit = "", ""
    if rho:
        cte += sampled(share, rho, mode)
        own, hit = " WHERE v IN (SELECT v FROM sv)", " AND src IN (SELECT v FROM sv)"
    cte += f", hs AS (SELECT v, txt, ls FROM sets WHERE txt IN (SELECT txt FROM sets{own} GROUP BY txt HAVING {often}){own.replace('WHERE', 'AND')})"
    cte += ", q1 AS (SELECT DISTINCT es.src, es.label, t.txt, t.ls FROM es JOIN sets AS t ON t.v = es.dst)"
    keep = lambda table, keys: f"(SELECT {keys} FROM {table} WHERE true{hit} GROUP BY {keys} HAVING {often})"
    cte += f", c1 AS (SELECT q1.* FROM q1 JOIN {keep('q1', 'label, txt')} USING (label, txt))"
    parts = ["SELECT src, concat('|', label, '|{', txt, '}') AS code, false AS star, label AS l0, ls AS m, CAST(NULL AS VARCHAR) AS l1, CAST(NULL AS VARCHAR[]) AS t FROM c1"]
    damp = ""
    if psi is not None:
        dm = f"(SELECT power(CAST(max(c) AS DOUBLE), {psi}) FROM (SELECT count(*) AS c FROM es GROUP BY dst) AS d)"
        ends = "SELECT label, item, count(*) AS n FROM es JOIN ats ON v = dst GROUP BY label, item"
        total = " + ".join(f"power({dm}, {j})" for j in range(max(hops, 1)))
        cte += f", gone AS (SELECT label, list(item) AS items FROM ({ends}) AS z WHERE n * {dm} < {th} GROUP BY label), gonestar AS (SELECT label, list(item) AS items FROM ({ends}) AS z WHERE n * ({total}) < {th} GROUP BY label)"
        damp = " LEFT JOIN {0} AS x ON x.label = {1} WHERE x.items IS NULL OR NOT list_has_any({2}, x.items)"
    if two:
        cte += ", c2 AS (SELECT DISTINCT es.src, es.label AS l0, a.txt AS mt, a.ls AS m, q1.label AS l1, q1.txt AS tt, q1.ls AS t FROM es JOIN (SELECT DISTINCT label, txt FROM c1) AS f1 ON f1.label = es.label JOIN sets AS a ON a.v = es.dst AND a.txt = f1.txt JOIN q1 ON q1.src = es.dst)"
        cte += f", f2 AS (SELECT c2.* FROM c2 JOIN {keep('c2', 'l0, mt, l1, tt')} USING (l0, mt, l1, tt))"
        parts.append("SELECT src, concat('|', l0, '|{', mt, '}|', l1, '|{', tt, '}') AS code, false AS star, l0, m, l1, t FROM f2" + damp.format("gone", "l1", "t"))
    if hops:
        cte += steps(hops) + ", rs AS (SELECT DISTINCT r.src, r.label, t.txt, t.ls FROM r JOIN sets AS t ON t.v = r.dst)"
        cte += f", fr AS (SELECT rs.* FROM rs JOIN {keep('rs', 'label, txt')} USING (label, txt))"
        parts.append("SELECT src, concat('|', fr.label, '*|{', txt, '}') AS code, true AS star, fr.label AS l0, ls AS m, NULL AS l1, NULL AS t FROM fr" + damp.format("gonestar", "fr.label", "ls"))
    cte += f", code AS ({' UNION ALL '.join(parts)}), al AS (SELECT concat('{{', hs.txt, '}}', code) AS p, hs.v, star, hs.ls AS h, l0, m, l1, t FROM code JOIN hs ON hs.v = code.src)"
    cte += f", s AS (SELECT p, count(*) / {scale} AS n, any_value(star) AS star, any_value(h) AS h, any_value(l0) AS l0, any_value(m) AS m, any_value(l1) AS l1, any_value(t) AS t FROM al GROUP BY p HAVING {often})"
    return cte + ", mt AS (SELECT al.p, al.v FROM al JOIN s ON s.p = al.p)"


def supports(length: str, *args, **more) -> str:
    """text and support of the patterns that a condition on s picks."""
    return matches(*args, **more) + f" SELECT p AS text, CAST(n AS DOUBLE) AS support FROM s WHERE {length}"


_OVER = "({0}.star = {1}.star AND {0}.l0 = {1}.l0 AND list_has_all({0}.h, {1}.h) AND list_has_all({0}.m, {1}.m) AND ({1}.l1 IS NULL OR coalesce({0}.l1 = {1}.l1 AND list_has_all({0}.t, {1}.t), false)))"


def rule_tables(graph: str, share: float, hops: int = 2, two: bool = True, most: int | None = None, dominated: bool = False, **more) -> str:
    """The tables of ``matches`` and ru(x, y, n, nx, ny, nv): rules in both directions. Vertices that match the same patterns are counted together."""
    scale = more.get("rho") or 1.0
    cte = matches(graph, share, hops, two, most, **more)
    cte += ", nm AS (SELECT p, row_number() OVER (ORDER BY p) AS i FROM s), ls AS (SELECT list(i ORDER BY i) AS ps FROM mt JOIN nm ON nm.p = mt.p GROUP BY v), cl AS (SELECT row_number() OVER () AS k, ps, w FROM (SELECT ps, count(*) AS w FROM ls GROUP BY ps) AS z), un AS (SELECT k, w, unnest(ps) AS i FROM cl)"
    cte += f", pr AS (SELECT a.i AS x, b.i AS y, sum(a.w) / {scale} AS n FROM un AS a JOIN un AS b ON a.k = b.k AND a.i < b.i GROUP BY a.i, b.i HAVING sum(a.w) / {scale} >= {theta(share)})"
    keep = "" if dominated else f" WHERE NOT {_OVER.format('a', 'b')} AND NOT {_OVER.format('b', 'a')}"
    cte += f", ok AS (SELECT a.p AS x, b.p AS y, pr.n, a.n AS nx, b.n AS ny FROM pr JOIN nm AS na ON na.i = pr.x JOIN nm AS nb ON nb.i = pr.y JOIN s AS a ON a.p = na.p JOIN s AS b ON b.p = nb.p{keep})"
    return cte + ", ru AS (SELECT z.*, (SELECT count(*) FROM vs) AS nv FROM (SELECT x, y, n, nx, ny FROM ok UNION ALL SELECT y AS x, x AS y, n, ny AS nx, nx AS ny FROM ok) AS z)"


MEASURED = "x, y, CAST(n AS DOUBLE) AS abs_support, round(CAST(n AS DOUBLE) / nv, 6) AS rel_support, round(CAST(n AS DOUBLE) / nx, 6) AS confidence, round(CAST(n AS DOUBLE) * nv / (CAST(nx AS DOUBLE) * ny), 6) AS lift"


def rules(graph: str, share: float, hops: int = 2, two: bool = True, most: int | None = None, **more) -> str:
    return rule_tables(graph, share, hops, two, most, **more) + f" SELECT {MEASURED} FROM ru"


def correlated(graph: str, share: float, most: int, edges: int, reduced: bool = False) -> str:
    """Pairs of frequent path-shaped subgraphs by the number of vertices that both have at some position."""
    cte = oracle_graph(graph)
    one = "ats"
    if reduced:
        cte += ", fq AS (SELECT item, count(*) AS c FROM ats GROUP BY item), red AS (SELECT v, item FROM (SELECT v, ats.item, row_number() OVER (PARTITION BY v ORDER BY c DESC, ats.item) AS r FROM ats JOIN fq ON fq.item = ats.item) AS z WHERE r = 1)"
        one = "red"
    cte += f", one AS (SELECT concat('{{', a.item, '}}|', es.label, '|{{', b.item, '}}') AS t, concat('|', es.label, '|{{', b.item, '}}') AS more, es.src, es.dst FROM es JOIN {one} AS a ON a.v = es.src JOIN {one} AS b ON b.v = es.dst)"
    images = ["SELECT t, 0 AS pos, src AS v FROM one", "SELECT t, 1 AS pos, dst AS v FROM one"]
    if edges > 1:
        cte += ", dbl AS (SELECT concat(a.t, b.more) AS t, a.src AS x, a.dst AS y, b.dst AS z FROM one AS a JOIN one AS b ON b.src = a.dst)"
        images += [f"SELECT t, {i} AS pos, {c} AS v FROM dbl" for i, c in enumerate("xyz")]
    cte += f", im AS ({' UNION '.join(images)}), fr AS (SELECT t FROM (SELECT t, pos, count(*) AS n FROM im GROUP BY t, pos) AS z GROUP BY t HAVING min(n) >= {theta(share)}), tv AS (SELECT DISTINCT t, v FROM im WHERE t IN (SELECT t FROM fr))"
    return cte + f" SELECT a.t AS x, b.t AS y, count(*) AS correlation FROM tv AS a JOIN tv AS b ON a.v = b.v AND a.t < b.t GROUP BY a.t, b.t ORDER BY correlation DESC, x, y LIMIT {most}"


def stats(graph: str) -> str:
    return oracle_graph(graph) + " SELECT (SELECT count(*) FROM vs) AS n_vertices, (SELECT count(*) FROM es) AS n_edges, (SELECT count(DISTINCT label) FROM es) AS n_labels, (SELECT count(DISTINCT item) FROM ats) AS n_items, round((SELECT CAST(count(*) AS DOUBLE) FROM ats) / (SELECT count(*) FROM vs), 6) AS mean_items, (SELECT max(c) FROM (SELECT count(*) AS c FROM es GROUP BY dst) AS d) AS max_in_degree, round((SELECT CAST(count(*) AS DOUBLE) FROM es) / (SELECT count(*) FROM vs), 6) AS mean_in_degree"
