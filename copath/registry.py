"""Queries of the methods, variants, baselines, measures and workloads, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from copath.config import MinerConfig
from copath.functions import measures
from copath.functions.patterns import parse
from copath.operators import accuracy, balance, bounds, comparators, matching, sampling, sketches
from copath.plans import oracles as O  # noqa: E741, N812
from copath.plans import workloads as W  # noqa: N812
from copath.plans.miner import mine_rules, resolve_theta
from copath.sources import graphs
from copath.sources.graphs import build, graph_stats, oracle_graph

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
#: Thresholds as shares of all vertices.
SHARE = {"trade": 0.1, "copart": 0.16, "users": 0.4, "eventchain": 0.05, "lineage": 0.05, "corpus": 0.05, "dialog": 0.05}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


def named(g, df: DataFrame, items: bool = True, labels: bool = True) -> DataFrame:
    for wanted, column, names in ((items, "item", g.items), (labels, "label", g.labels)):
        if wanted:
            table = graphs.name_table(df.sparkSession, column, names)
            df = df.join(table, column).withColumn(column, F.col("name")).drop("name")
    return df


def config(graph: str, **changes) -> MinerConfig:
    return MinerConfig(SHARE[graph], relative=True).but(**changes)


def measured(rules: DataFrame) -> DataFrame:
    return rules.select("x", "y", "abs_support", *[F.round(m, 6).alias(m) for m in ("rel_support", "confidence", "lift")])


# Graphs and their statistics.
for _g in ("trade", "lineage", "copart", "users", "eventchain", "corpus", "dialog"):
    query(f"graph_stats_{_g}", O.stats(_g))(lambda s, d, g=_g: graph_stats(build(s, d, g)))
query("graph_stats_web")(lambda s, d: graph_stats(build(s, d, "web")))
query("graph_stats_vecnn")(lambda s, d: graph_stats(build(s, d, "vecnn")))
query("lsh_neighbours_vecnn")(graphs.lsh_neighbours)
query("graph_stats_uniform")(lambda s, d: graph_stats(graphs.generated(s, 20_000, "uniform")))
query("graph_stats_exponential")(lambda s, d: graph_stats(graphs.generated(s, 20_000, "exponential")))

# Bounds.
query("in_degree_max_trade", oracle_graph("trade") + " SELECT label, max(c) AS n FROM (SELECT label, dst, count(*) AS c FROM es GROUP BY label, dst) AS d GROUP BY label")(
    lambda s, d: (lambda g: named(g, s.createDataFrame(list(bounds.largest_in_degrees(g).items()), "label int, n long"), items=False))(build(s, d, "trade"))
)
query("edge_item_counts_trade", oracle_graph("trade") + " SELECT label, item, count(*) AS n FROM es JOIN ats ON v = dst GROUP BY label, item")(lambda s, d: (lambda g: named(g, bounds.edge_item_counts(g)))(build(s, d, "trade")))
query("vertex_label_counts_trade", oracle_graph("trade") + " SELECT label, item, count(*) AS n FROM (SELECT DISTINCT src, label FROM es) AS x JOIN ats ON v = src GROUP BY label, item")(lambda s, d: (lambda g: named(g, bounds.vertex_label_counts(g)))(build(s, d, "trade")))


def _ok(kind: str, graph: str, psi: float | None):
    def f(s, d):
        g = build(s, d, graph)
        t = bounds.target_tables(g, resolve_theta(g, config(graph)), psi)
        pairs = t.ends if kind == "tail" else {(label, item): n for (item, label), n in t.starts.items()}
        rows = [(i, g.labels[label], g.items[item]) for i in (1, 2) for label, item in pairs if (t.tail_ok(i, label, item) if kind == "tail" else t.step_ok(i, item, label))]
        return s.createDataFrame(rows, "i int, label string, item string")

    return f


def _ok_sql(kind: str, graph: str, psi: float = 1.0) -> str:
    own = "SELECT label, item, count(*) AS n FROM es JOIN ats ON v = dst GROUP BY label, item" if kind == "tail" else "SELECT label, item, count(*) AS n FROM (SELECT DISTINCT src, label FROM es) AS x JOIN ats ON v = src GROUP BY label, item"
    dm = f"(SELECT power(CAST(max(c) AS DOUBLE), {psi}) FROM (SELECT count(*) AS c FROM es GROUP BY dst) AS d)"
    return oracle_graph(graph) + f", c AS ({own}) SELECT 1 AS i, label, item FROM c WHERE n >= {O.theta(SHARE[graph])} UNION ALL SELECT 2 AS i, label, item FROM c WHERE n * {dm} >= {O.theta(SHARE[graph])}"


query("tail_ok_trade", _ok_sql("tail", "trade"))(_ok("tail", "trade", None))
query("step_ok_trade", _ok_sql("step", "trade"))(_ok("step", "trade", None))
query("tail_ok_damped_lineage", _ok_sql("tail", "lineage", 0.4))(_ok("tail", "lineage", 0.4))

# Item sets.
_ITEMS = (
    oracle_graph("trade")
    + f", t AS (SELECT {O.theta(0.05)} AS k) SELECT concat('{{', a.item, '}}') AS text, CAST(count(*) AS DOUBLE) AS support FROM ats AS a GROUP BY a.item HAVING count(*) >= (SELECT k FROM t)"
    + " UNION ALL SELECT concat('{', a.item, ',', b.item, '}') AS text, CAST(count(*) AS DOUBLE) AS support FROM ats AS a JOIN ats AS b ON a.v = b.v AND a.item < b.item GROUP BY a.item, b.item HAVING count(*) >= (SELECT k FROM t)"
    + " UNION ALL SELECT concat('{', a.item, ',', b.item, ',', c.item, '}') AS text, CAST(count(*) AS DOUBLE) AS support FROM ats AS a JOIN ats AS b ON a.v = b.v AND a.item < b.item JOIN ats AS c ON b.v = c.v AND b.item < c.item GROUP BY a.item, b.item, c.item HAVING count(*) >= (SELECT k FROM t)"
)
query("itemsets_trade", _ITEMS)(lambda s, d: mine_rules(build(s, d, "trade"), MinerConfig(0.05, relative=True, max_len=0, max_items=3, min_len=0, reach=False)).patterns().select("text", "support"))


@query("itemsets_fpgrowth_trade", _ITEMS)
def _fp(s, d):
    g = build(s, d, "trade")
    names = F.array(*[F.lit(x) for x in g.items])
    sets = comparators.itemsets_mllib(g, resolve_theta(g, MinerConfig(0.05, relative=True)), g.n).where("size(items) <= 3")
    text = F.concat(F.lit("{"), F.array_join(F.transform("items", lambda i: F.element_at(names, (i + 1).cast("int"))), ","), F.lit("}"))
    return sets.select(text.alias("text"), F.col("support").cast("double").alias("support"))


query(
    "item_rules_trade",
    oracle_graph("trade") + f", s AS (SELECT item, count(*) AS n FROM ats GROUP BY item HAVING count(*) >= {O.theta(0.05)}), pr AS (SELECT a.item AS a, b.item AS b, count(*) AS n FROM ats AS a JOIN ats AS b ON a.v = b.v AND a.item <> b.item GROUP BY a.item, b.item HAVING count(*) >= {O.theta(0.05)}), ru AS (SELECT concat('{{', a, '}}') AS x, concat('{{', b, '}}') AS y, pr.n, sa.n AS nx, sb.n AS ny, (SELECT count(*) FROM vs) AS nv FROM pr JOIN s AS sa ON sa.item = a JOIN s AS sb ON sb.item = b) SELECT {O.MEASURED} FROM ru",
)(lambda s, d: measured(mine_rules(build(s, d, "trade"), MinerConfig(0.05, relative=True, max_len=0, max_items=1, min_len=0, reach=False)).rules()))


# Patterns.
def _patterns(graph: str, kind: str, hops: int = 2, **more):
    def f(s, d):
        cfg = config(graph, max_len={"1": 1, "2": 2, "reach": 1}[kind], max_reach=hops, reach=kind == "reach", **more)
        p = mine_rules_patterns(build(s, d, graph), cfg)
        return p.where(F.col("kind") == ("reach" if kind == "reach" else "fixed")).where(F.col("len") == (2 if kind == "2" else 1)).select("text", "support")

    return f


def mine_rules_patterns(g, cfg: MinerConfig) -> DataFrame:
    """Patterns alone: a run whose rules nobody asks for."""
    from copath.plans.miner import mine_patterns

    return mine_patterns(g, cfg).patterns()


for _g, _kind, _h in (("trade", "1", 2), ("trade", "2", 2), ("trade", "reach", 2), ("copart", "1", 2), ("copart", "2", 2), ("users", "1", 2), ("users", "reach", 2), ("lineage", "1", 2), ("lineage", "2", 2), ("eventchain", "1", 2), ("eventchain", "2", 2), ("eventchain", "reach", 4), ("corpus", "1", 2), ("corpus", "reach", 2), ("dialog", "1", 2), ("dialog", "2", 2)):
    _name = f"reach{_h}_{_g}" if _kind == "reach" else f"unit_len{_kind}_{_g}"
    query(_name, O.patterns(_g, SHARE[_g], _kind, _h))(_patterns(_g, _kind, _h, max_items=1))
for _name, _kind, _where, _h, _two in (("multi_len1_trade", "1", "l1 IS NULL", 0, False), ("multi_len2_trade", "2", "l1 IS NOT NULL", 0, True), ("multi_reach2_trade", "reach", "star", 2, False)):
    query(_name, O.supports(_where, "trade", SHARE["trade"], _h, _two))(_patterns("trade", _kind))

# Rules: exact in its forms, the plain baseline, and other graphs; any number of items at a position.
_RULES = O.rules("trade", SHARE["trade"])
for _name, _more in {"rules_trade": {}, "rules_lattice_trade": {"rule_form": "lattice"}, "rules_bitmap_trade": {"rule_form": "bitmap"}, "rules_single_pass_trade": {"rule_form": "single_pass"}, "rules_prefix_only_trade": {"policy": "prefix_only"}, "rules_per_label_bound_trade": {"bound": "per_label"}, "rules_psi1_trade": {"psi": 1.0}, "rules_placed_trade": {"placement": "greedy", "parallelism": 8}}.items():
    query(_name, _RULES)(lambda s, d, more=_more: measured(mine_rules(build(s, d, "trade"), config("trade", **more)).rules()))
for _g, _h in (("copart", 2), ("lineage", 2), ("eventchain", 4), ("corpus", 2), ("dialog", 2)):
    query(f"rules_{_g}", O.rules(_g, SHARE[_g], _h))(lambda s, d, g=_g, h=_h: measured(mine_rules(build(s, d, g), config(g, max_reach=h)).rules()))
#: Nearly every pair of users is joined by two hops, so that at length two (6,494 patterns of single items on 150 vertices) nearly all pairs of patterns are rules.
DENSE = {"max_len": 1, "max_items": 1}
query("rules_users", O.rules("users", SHARE["users"], 2, False, 1))(lambda s, d: measured(mine_rules(build(s, d, "users"), config("users", max_reach=2, **DENSE)).rules()))
for _name, _more in {"rules_single_items_trade": {}, "rules_prefix_only_single_items_trade": {"policy": "prefix_only"}}.items():
    query(_name, O.rules("trade", SHARE["trade"], 2, True, 1))(lambda s, d, more=_more: measured(mine_rules(build(s, d, "trade"), config("trade", max_items=1, **more)).rules()))
query("rules_web")(lambda s, d: measured(mine_rules(build(s, d, "web"), MinerConfig(0.02, relative=True)).rules()))
query("rules_vecnn")(lambda s, d: measured(mine_rules(build(s, d, "vecnn"), MinerConfig(0.01, relative=True)).rules()))
query("rules_multi_trade", O.rules("trade", 0.2, 2, True, 2))(lambda s, d: measured(mine_rules(build(s, d, "trade"), config("trade", theta=0.2, max_items=2)).rules()))
query("rules_keep_dominated_trade", O.rule_tables("trade", SHARE["trade"], dominated=True) + f" SELECT {O.MEASURED} FROM ru")(lambda s, d: measured(mine_rules(build(s, d, "trade"), config("trade", keep_dominated=True)).rules()))
query("rules_drop_implied_trade", O.rule_tables("trade", SHARE["trade"]) + f" SELECT {O.MEASURED} FROM ru WHERE replace(x, '*', '') <> replace(y, '*', '')")(lambda s, d: measured(mine_rules(build(s, d, "trade"), config("trade", drop_implied=True)).rules()))
query("rules_empty_sets_trade")(lambda s, d: measured(mine_rules(build(s, d, "trade"), config("trade", theta=0.3, allow_empty=True)).rules()))


# Measures, filters, reports on rules.
def _rules(s, d, names=measures.BASIC):
    return mine_rules(build(s, d, "trade"), config("trade")).rules(names)


_R = O.rule_tables("trade", SHARE["trade"])
query("measures_trade", _R + " SELECT x, y, round(CAST(n AS DOUBLE) / (nx + ny - n), 6) AS jaccard, round(CAST(n AS DOUBLE) / nv - (CAST(nx AS DOUBLE) / nv) * (CAST(ny AS DOUBLE) / nv), 6) AS leverage, round(CAST(n AS DOUBLE) / sqrt(CAST(nx AS DOUBLE) * ny), 6) AS cosine, round((CAST(n AS DOUBLE) / nx + CAST(n AS DOUBLE) / ny) / 2, 6) AS kulczynski, CASE WHEN n < nx THEN round((1 - CAST(ny AS DOUBLE) / nv) / (1 - CAST(n AS DOUBLE) / nx), 6) END AS conviction FROM ru")(
    lambda s, d: _rules(s, d, tuple(measures.MEASURES)).select("x", "y", *[F.round(m, 6).alias(m) for m in ("jaccard", "leverage", "cosine", "kulczynski", "conviction")])
)
query("filter_rules_trade", f"SELECT * FROM ({_R} SELECT {O.MEASURED} FROM ru) AS z WHERE confidence >= 0.9 AND lift >= 1.5")(lambda s, d: measured(measures.filter_rules(measured(_rules(s, d)), min_conf=0.9, min_lift=1.5)))
query("top_rules_lift", f"SELECT * FROM ({_R} SELECT {O.MEASURED} FROM ru) AS z ORDER BY lift DESC, x, y LIMIT 20")(lambda s, d: measures.top_rules(measured(_rules(s, d)), "lift", 20))
query("top_rules_per_head", f"SELECT x, y, abs_support, rel_support, confidence, lift, CAST(rank AS BIGINT) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY x ORDER BY confidence DESC, x, y) AS rank FROM ({_R} SELECT {O.MEASURED} FROM ru) AS z) AS w WHERE rank <= 3")(lambda s, d: measures.top_rules(measured(_rules(s, d)), "confidence", 3, per="x").withColumn("rank", F.col("rank").cast("long")))
_SIDE = "CASE WHEN strpos(x, '*') > 0 THEN 'reach' ELSE concat('length_', CAST((length(x) - length(replace(x, '|', ''))) // 2 AS VARCHAR)) END"
query("rule_side_types_trade", _R + f" SELECT {_SIDE} AS side, count(*) AS n FROM ru GROUP BY 1")(lambda s, d: accuracy.rule_side_types(_rules(s, d)))
query("best_consequents_trade", f"SELECT x, y, abs_support, rel_support, confidence, lift FROM (SELECT *, row_number() OVER (PARTITION BY x ORDER BY confidence DESC, y) AS r FROM ({_R} SELECT {O.MEASURED} FROM ru) AS z) AS w WHERE r <= 3")(lambda s, d: (lambda m: measures.best_consequents(m, m, 3))(measured(_rules(s, d))))
query("either_support_trade", O.rule_tables("trade", SHARE["trade"], 0, False, 1) + " SELECT x, y, nx + ny - n AS n FROM ru WHERE x < y")(lambda s, d: _either(s, d))
query("sketched_support_trade")(lambda s, d: _sketched(s, d))
query("rules_lost_by_damping_lineage", f"SELECT 'missed' AS side, x, y FROM (SELECT x, y FROM ({O.rules('lineage', SHARE['lineage'])}) AS a EXCEPT SELECT x, y FROM ({O.rules('lineage', SHARE['lineage'], psi=0.2)}) AS b) AS c UNION ALL SELECT 'kept' AS side, x, y FROM ({O.rules('lineage', SHARE['lineage'], psi=0.2)}) AS e")(lambda s, d: (lambda g: accuracy.differences(*(mine_rules(g, config("lineage", **more)).rules() for more in ({}, {"psi": 0.2}))))(build(s, d, "lineage")))


def _named_pairs(s, d):
    r = mine_rules(build(s, d, "trade"), config("trade", max_items=1, max_len=1, reach=False))
    names = r.patterns().select("pid", "text")
    name = lambda df: df.join(names.select(F.col("pid").alias("x"), F.col("text").alias("tx")), "x").join(names.select(F.col("pid").alias("y"), F.col("text").alias("ty")), "y")
    return r, lambda df, n: name(df).select(F.least("tx", "ty").alias("x"), F.greatest("tx", "ty").alias("y"), n)


def _either(s, d):
    r, name = _named_pairs(s, d)
    return name(sketches.either_support(r.matches, r.pairs), "n")


def _sketched(s, d):
    """Estimates beside the counts that they stand for."""
    r, name = _named_pairs(s, d)
    return name(sketches.sketched_support(r.matches, r.pairs).join(r.pairs, ["x", "y"]), "estimate").join(name(r.pairs, "n"), ["x", "y"])


query(
    "pattern_counts_trade",
    _R + f" SELECT 'fixed' AS kind, CAST(0 AS INTEGER) AS len, (SELECT count(*) FROM (SELECT txt FROM sets GROUP BY txt HAVING count(*) >= {O.theta(SHARE['trade'])}) AS z) AS n UNION ALL SELECT CASE WHEN star THEN 'reach' ELSE 'fixed' END AS kind, CASE WHEN l1 IS NULL THEN 1 ELSE 2 END AS len, count(*) AS n FROM s GROUP BY 1, 2 UNION ALL SELECT 'rule' AS kind, 0 AS len, (SELECT count(*) FROM ok) AS n",
)(lambda s, d: accuracy.count_outputs(mine_rules(build(s, d, "trade"), config("trade"))))
_KIND = "CASE WHEN strpos({}, '*') > 0 THEN 'reach' ELSE 'fixed' END"
query("rules_cube_trade", f"SELECT kind_x, kind_y, count(*) AS n, round(avg(c), 6) AS mean_confidence FROM ({_R} SELECT {_KIND.format('x')} AS kind_x, {_KIND.format('y')} AS kind_y, CAST(n AS DOUBLE) / nx AS c FROM ru) AS z GROUP BY CUBE (kind_x, kind_y)")(lambda s, d: accuracy.rules_cube(_rules(s, d)))


# Approximations.
for _name, _g, _more in (("rules_damped_trade", "trade", {"psi": 0.4}), ("rules_damped_lineage", "lineage", {"psi": 0.2}), ("rules_sampled_trade", "trade", {"rho": 0.4}), ("rules_damped_sampled_trade", "trade", {"psi": 0.4, "rho": 0.4}), ("rules_threshold_sampled_trade", "trade", {"rho": 0.4, "sample_mode": "threshold"})):
    _sql = {"mode" if k == "sample_mode" else k: x for k, x in _more.items()}
    query(_name, O.rules(_g, SHARE[_g], **_sql))(lambda s, d, g=_g, more=_more: measured(mine_rules(build(s, d, g), config(g, **more)).rules()))
query("rules_stratum_weight_trade")(lambda s, d: measured(mine_rules(build(s, d, "trade"), config("trade", rho=0.4, estimator="stratum_weight")).rules()))


@query("lost_patterns_lineage", O.oracle_graph("lineage") + O.one_hop() + O.P1 + O.P2 + f", ends AS (SELECT label, b, count(*) AS n FROM e1 GROUP BY label, b), f AS (SELECT p, max(pre) AS pre, count(*) AS n FROM p2 GROUP BY p HAVING count(*) >= {O.theta(0.02)}) SELECT f.p AS text, CAST(f.n AS DOUBLE) AS support, round(CAST(f.n AS DOUBLE) / ends.n, 6) AS c, ends.n * (SELECT power(CAST(max(c) AS DOUBLE), 0.2) FROM (SELECT count(*) AS c FROM es GROUP BY dst) AS d) < {O.theta(0.02)} AS lost FROM f JOIN ends ON concat('|', ends.label, '|{{', ends.b, '}}') = substr(f.p, length(f.pre) + 1)")
def _lost(s, d):
    from copath.plans.miner import mine_patterns

    g = build(s, d, "lineage")
    r = mine_patterns(g, config("lineage", theta=0.02, reach=False, max_items=1))
    rows = [(p.text(g.items, g.labels), float(n), round(c, 6), bool(x)) for p, n, c, x in bounds.damping_loss(list(r.catalogue.support.items()), r.targets, 0.2) if len(p.hops) == 2]
    return s.createDataFrame(rows, "text string, support double, c double, lost boolean")


def _common(g, theta):
    return [r.item for r in g.attrs.groupBy("item").count().where(F.col("count") >= theta).collect()]


_COMMON = f", f AS (SELECT item FROM ats GROUP BY item HAVING count(*) >= {O.theta(0.1)}), st AS (SELECT v, string_agg(item, ',' ORDER BY item) AS items FROM ats WHERE item IN (SELECT item FROM f) GROUP BY v)"
_SAMPLED = _COMMON + ", k AS (SELECT v, items, row_number() OVER (PARTITION BY items ORDER BY md5(concat(CAST(v AS VARCHAR), '/42')), v) AS r, count(*) OVER (PARTITION BY items) AS n FROM st), sv AS (SELECT v FROM k WHERE r <= ceil(n * 0.4 - 0.000000001))"


@query("strata_trade", oracle_graph("trade") + _COMMON + " SELECT items, count(*) AS n FROM st GROUP BY items")
def _strata(s, d):
    g = build(s, d, "trade")
    names = F.array(*[F.lit(x) for x in g.items])
    st = sampling.strata(g, _common(g, resolve_theta(g, config("trade"))))
    return st.groupBy("items").agg(F.count("*").alias("n")).select(F.array_join(F.transform("items", lambda i: F.element_at(names, (i + 1).cast("int"))), ",").alias("items"), "n")


@query("sampled_support_trade", oracle_graph("trade") + _SAMPLED + O.one_hop() + O.P1 + f" SELECT p AS text, count(*) / 0.4 AS support FROM p1 WHERE v IN (SELECT v FROM sv) GROUP BY p HAVING count(*) / 0.4 >= {O.theta(0.1)}")
def _sampled(s, d):
    return mine_rules_patterns(build(s, d, "trade"), config("trade", rho=0.4, max_len=1, reach=False, max_items=1)).where("len = 1").select("text", "support")


@query("support_interval_trade", oracle_graph("trade") + _SAMPLED + O.one_hop() + O.P1 + f", cnt AS (SELECT p, count(*) AS n FROM p1 WHERE v IN (SELECT v FROM sv) GROUP BY p HAVING count(*) / 0.4 >= {O.theta(0.1)}), q AS (SELECT p, n, (SELECT count(*) FROM sv) AS m, (SELECT count(*) FROM st) AS big FROM cnt) SELECT p AS text, round(big * (CAST(n AS DOUBLE) / m), 4) AS estimate, round(big * (CAST(n AS DOUBLE) / m - 1.959963984540054 * sqrt(m * (CAST(n AS DOUBLE) / m) * (1 - CAST(n AS DOUBLE) / m) / (m - 1) / m)), 4) AS lo, round(big * (CAST(n AS DOUBLE) / m + 1.959963984540054 * sqrt(m * (CAST(n AS DOUBLE) / m) * (1 - CAST(n AS DOUBLE) / m) / (m - 1) / m)), 4) AS hi FROM q")
def _interval(s, d):
    g = build(s, d, "trade")
    common = _common(g, resolve_theta(g, config("trade")))
    m = sampling.sample_sources(g, common, 0.4).count()
    big = sampling.strata(g, common).count()
    p = mine_rules_patterns(g, config("trade", rho=0.4, max_len=1, reach=False, max_items=1)).where("len = 1")
    est, lo, hi = sampling.support_interval(F.round(F.col("support") * 0.4), F.lit(float(m)), F.lit(float(big)))
    return p.select("text", F.round(est, 4).alias("estimate"), F.round(lo, 4).alias("lo"), F.round(hi, 4).alias("hi"))


# Placement.
_COST = oracle_graph("trade") + f", ta AS (SELECT label, item FROM (SELECT label, item, count(*) AS n FROM es JOIN ats ON v = dst GROUP BY label, item) AS x WHERE n >= {O.theta(0.1)} UNION SELECT label, item FROM (SELECT label, item, count(*) AS n FROM (SELECT DISTINCT src, label FROM es) AS x JOIN ats ON v = src GROUP BY label, item) AS y WHERE n >= {O.theta(0.1)}), tl AS (SELECT DISTINCT label FROM (SELECT label, item, count(*) AS n FROM (SELECT DISTINCT src, label FROM es) AS x JOIN ats ON v = src GROUP BY label, item) AS y WHERE n >= {O.theta(0.1)}), o AS (SELECT src, count(*) AS d FROM es WHERE label IN (SELECT label FROM tl) GROUP BY src), w AS (SELECT v, count(*) AS a FROM ats WHERE item IN (SELECT item FROM ta) GROUP BY v) SELECT vs.v, coalesce(o.d, 0) * coalesce(w.a, 0) AS cost FROM vs LEFT JOIN o ON o.src = vs.v LEFT JOIN w ON w.v = vs.v"


def _costs(s, d):
    g = build(s, d, "trade")
    return balance.vertex_cost(g, bounds.target_tables(g, resolve_theta(g, config("trade"))))


query("vertex_cost_trade", _COST)(_costs)
for _name, _how in {"greedy": balance.balance_greedy, "hash": balance.balance_hash, "snake": balance.balance_snake}.items():
    query(f"balance_{_name}_trade")(lambda s, d, how=_how: balance.balance_report(how(_costs(s, d), 32)))

# Single patterns and rules.
_X, _Y = "{kind:order}|shipped_by|{kind:supplier}|located_in|{kind:nation}", "{kind:order}|contains|{kind:part}"
query("match_fixed_trade", oracle_graph("trade") + O.one_hop() + O.P1 + O.P2 + f" SELECT v FROM p2 WHERE p = '{_X}'")(lambda s, d: (lambda g: matching.match_fixed(g, parse(_X, g.items, g.labels)))(build(s, d, "trade")))
query("match_reach_trade", oracle_graph("trade") + O.reach(2) + " SELECT v FROM ps WHERE p = '{kind:customer}|located_in*|{kind:region}'")(lambda s, d: (lambda g: matching.match_reach(g, parse("{kind:customer}|located_in*|{kind:region}", g.items, g.labels)))(build(s, d, "trade")))
query("rule_sources_trade", oracle_graph("trade") + O.one_hop() + O.P1 + O.P2 + f" SELECT p2.v FROM p2 JOIN p1 ON p1.v = p2.v WHERE p2.p = '{_X}' AND p1.p = '{_Y}'")(lambda s, d: (lambda g: matching.rule_sources(g, parse(_X, g.items, g.labels), parse(_Y, g.items, g.labels)))(build(s, d, "trade")))

# Studies.
_BIAS = (
    oracle_graph("trade")
    + ", hit AS (SELECT m.item AS grp, x.item, count(DISTINCT m.v) AS n FROM ats AS m JOIN es ON es.src = m.v AND es.label = 'places' JOIN ats AS x ON x.v = es.dst AND x.item LIKE 'prio:%' WHERE m.item IN ('seg:BUILDING', 'seg:AUTOMOBILE') GROUP BY m.item, x.item HAVING count(DISTINCT m.v) >= 2), sz AS (SELECT item AS grp, count(*) AS n_group FROM ats WHERE item IN ('seg:BUILDING', 'seg:AUTOMOBILE') GROUP BY item)"
    + ' SELECT sz.grp AS "group", n_group, count(*) AS n_rules, CAST(sum(n) AS BIGINT) AS sum_support, round(sum(CAST(n AS DOUBLE) / n_group), 6) AS sum_confidence, CAST(0 AS BIGINT) AS sum_support_unset FROM sz JOIN hit ON hit.grp = sz.grp GROUP BY sz.grp, n_group'
)
query("bias_segment_priority", _BIAS)(lambda s, d: matching.bias_check(build(s, d, "trade"), ["seg:BUILDING", "seg:AUTOMOBILE"], "places", "prio:", 2, unset="bal:"))
_LANGS = "('lang:en', 'lang:de', 'lang:fr', 'lang:es')"
query(
    "bias_lang_toxic",
    oracle_graph("corpus")
    + f", mem AS (SELECT v, item AS grp FROM ats WHERE item IN {_LANGS}), tip AS (SELECT DISTINCT es.src AS v, x.item FROM es JOIN ats AS x ON x.v = es.dst AND x.item LIKE 'toxic:%' WHERE es.label = 'next_in_source'), hit AS (SELECT grp, item, count(*) AS n, count(*) FILTER (WHERE mem.v NOT IN (SELECT v FROM ats WHERE item LIKE 'quality:%')) AS u FROM mem JOIN tip ON tip.v = mem.v GROUP BY grp, item), sz AS (SELECT grp, count(*) AS n_group FROM mem GROUP BY grp)"
    + ' SELECT sz.grp AS "group", n_group, count(item) AS n_rules, CAST(coalesce(sum(n), 0) AS BIGINT) AS sum_support, round(coalesce(sum(CAST(n AS DOUBLE) / n_group), 0), 6) AS sum_confidence, CAST(coalesce(sum(u), 0) AS BIGINT) AS sum_support_unset FROM sz LEFT JOIN hit ON hit.grp = sz.grp GROUP BY sz.grp, n_group',
)(lambda s, d: matching.bias_check(build(s, d, "corpus"), ["lang:en", "lang:de", "lang:fr", "lang:es"], "next_in_source", "toxic:", 1, unset="quality:"))
_EX = ("{lang:en}|same_text|{lang:en}", "{lang:en}|same_text|{quality:1}")
query("rule_exceptions_corpus", oracle_graph("corpus") + " , mx AS (SELECT DISTINCT es.src AS v FROM es JOIN ats AS h ON h.v = es.src AND h.item = 'lang:en' JOIN ats AS t ON t.v = es.dst AND t.item = 'lang:en' WHERE es.label = 'same_text'), my AS (SELECT DISTINCT es.src AS v FROM es JOIN ats AS h ON h.v = es.src AND h.item = 'lang:en' JOIN ats AS t ON t.v = es.dst AND t.item = 'quality:1' WHERE es.label = 'same_text') SELECT mx.v, es.dst AS tail FROM mx LEFT JOIN es ON es.src = mx.v AND es.label = 'same_text' WHERE mx.v NOT IN (SELECT v FROM my)")(
    lambda s, d: (lambda g: matching.rule_exceptions(g, *[parse(x, g.items, g.labels) for x in _EX]))(build(s, d, "corpus"))
)
query(
    "missing_items_corpus",
    oracle_graph("corpus")
    + ", mx AS (SELECT DISTINCT es.src AS v FROM es JOIN ats AS h ON h.v = es.src AND h.item = 'lang:en' JOIN ats AS t ON t.v = es.dst AND t.item = 'lang:en' WHERE es.label = 'same_text'), my AS (SELECT DISTINCT es.src AS v FROM es JOIN ats AS h ON h.v = es.src AND h.item = 'lang:en' JOIN ats AS t ON t.v = es.dst AND t.item = 'quality:1' WHERE es.label = 'same_text'), ex AS (SELECT mx.v, es.dst AS tail FROM mx LEFT JOIN es ON es.src = mx.v AND es.label = 'same_text' WHERE mx.v NOT IN (SELECT v FROM my))"
    + " SELECT CASE WHEN tail IS NULL THEN 'no_end' WHEN tail IN (SELECT v FROM ats WHERE item LIKE 'quality:%') THEN 'other' ELSE 'gap' END AS reason, count(DISTINCT v) AS n FROM ex GROUP BY 1",
)(lambda s, d: (lambda g: matching.missing_item_report(g, *[parse(x, g.items, g.labels) for x in _EX], "quality:"))(build(s, d, "corpus")))
query("label_bands_places", oracle_graph("lineage") + " SELECT label, count(*) AS n FROM es WHERE label LIKE 'places%' GROUP BY label")(lambda s, d: (lambda g: named(g, g.edges, items=False).where("label LIKE 'places%'").groupBy("label").agg(F.count("*").alias("n")))(graphs.split_label_by_out_degree(build(s, d, "trade"), "places")))

# Comparator.
query("correlated_pairs_copart", O.correlated("copart", 0.1, 100, 1))(lambda s, d: (lambda g: comparators.correlated_pairs(g, resolve_theta(g, config("copart", theta=0.1)), 100, max_edges=1))(build(s, d, "copart")))
query("correlated_pairs_trade_reduced", O.correlated("trade", 0.05, 100, 2, reduced=True))(lambda s, d: (lambda g: comparators.correlated_pairs(g, resolve_theta(g, config("trade", theta=0.05)), 100))(graphs.reduce_items(build(s, d, "trade"), "most")))
query("correlated_pairs_near_trade")(lambda s, d: (lambda g: comparators.correlated_pairs(g, resolve_theta(g, config("trade", theta=0.2)), 100, h=1, max_edges=1))(graphs.reduce_items(build(s, d, "trade"), "most")))
query("reduce_items_trade", oracle_graph("trade") + " SELECT v, min(item) AS item FROM ats GROUP BY v")(lambda s, d: (lambda g: named(g, graphs.reduce_items(g).attrs, labels=False).select("v", "item"))(build(s, d, "trade")))
query("sample_graph_trade")(lambda s, d: graph_stats(graphs.sample_graph(build(s, d, "trade"), 0.4)))

# Experiments.
for _g, _shares, _more in (("trade", (0.05, 0.1), {}), ("lineage", (0.1,), {}), ("copart", (0.16, 0.17), {}), ("users", (0.3, 0.4), DENSE)):
    query(f"exp_theta_sweep_{_g}")(lambda s, d, g=_g, shares=_shares, more=_more: W.theta_sweep(s, d, g, shares, **more))
for _g, _share in (("trade", 0.1), ("eventchain", 0.1), ("copart", 0.17)):
    query(f"exp_length_sweep_{_g}")(lambda s, d, g=_g, share=_share: W.length_sweep(s, d, g, share, (1, 2) if g == "copart" else (1, 2, 3, 4)))
for _g, _share, _more in (("trade", 0.1, {"max_items": 1}), ("copart", 0.17, {}), ("users", 0.4, DENSE), ("eventchain", 0.1, {"max_items": 1})):
    query(f"exp_factor_sweep_{_g}")(lambda s, d, g=_g, share=_share, more=_more: W.factor_sweep(s, d, g, share, (0.2, 0.8) if g in ("users", "eventchain") else (0.2, 0.4, 0.6, 0.8), **more))
for _g, _share in (("trade", 0.1), ("copart", 0.17)):
    query(f"exp_memory_{_g}")(lambda s, d, g=_g, share=_share: W.memory(s, d, g, share))
for _name, _f in {
    "exp_graph_size": W.graph_size,
    "exp_memory_by_size": W.memory_by_size,
    "exp_threads": W.thread_sweep,
    "exp_placement": W.placements,
    "exp_coverage": W.coverage,
    "exp_step_shares": W.step_shares,
    "exp_comparator": W.comparator,
}.items():
    query(_name)(_f)
query("exp_knowledge_rules", O.rule_tables("trade", 0.05, 0, True, 1) + " SELECT x, y, CAST(n AS DOUBLE) AS abs_support, round(CAST(n AS DOUBLE) / nx, 6) AS confidence, round(CAST(n AS DOUBLE) * nv / (CAST(nx AS DOUBLE) * ny), 6) AS lift FROM ru WHERE length(x) - length(replace(x, '|', '')) = 4 AND length(y) - length(replace(y, '|', '')) = 2 AND split_part(x, '|', 2) <> split_part(y, '|', 2)")(W.knowledge_rules)
for _g, _share in (("eventchain", 0.05), ("users", 0.4)):
    _two, _four = (O.rule_tables(_g, _share, h, False, 1) + f" SELECT {h} AS hops, x, y, CAST(n AS DOUBLE) AS abs_support, round(CAST(n AS DOUBLE) / nx, 6) AS confidence, round(CAST(n AS DOUBLE) * nv / (CAST(nx AS DOUBLE) * ny), 6) AS lift FROM ru WHERE strpos(x, '*') > 0" for h in (2, 4))
    query(f"exp_social_reach_{_g}", f"SELECT * FROM ({_two}) AS a UNION ALL SELECT * FROM ({_four}) AS b")(lambda s, d, g=_g, share=_share: W.social_reach(s, d, g, share))

# Builders around the graphs.
query("asof_event_order_edges", "SELECT event_id, o_orderkey FROM (SELECT e.event_id, o.o_orderkey, row_number() OVER (PARTITION BY e.event_id ORDER BY o.o_orderdate DESC, o.o_orderkey DESC) AS r FROM events AS e JOIN orders AS o ON o.o_custkey = e.user_id AND o.o_orderdate <= e.ts) AS z WHERE r = 1")(W.asof_edges)
query("session_edges", "SELECT user_id, count(*) AS n_sessions, CAST(sum(k) AS BIGINT) AS n_events FROM (SELECT user_id, sid, count(*) AS k FROM (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS sid FROM (SELECT user_id, ts, event_id, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) IS NULL OR ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) >= INTERVAL 6 HOUR THEN 1 ELSE 0 END AS fresh FROM events) AS a) AS b GROUP BY user_id, sid) AS c GROUP BY user_id")(W.session_counts)
