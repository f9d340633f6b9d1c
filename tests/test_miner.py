"""The miner against a worked example, exhaustive search, and its own invariants."""

import random
from collections import Counter

import pytest

from copath.config import MinerConfig
from copath.functions.patterns import Pattern, as_row, dominates, is_unit, parse
from copath.operators import accuracy, bounds, comparators, matching, sampling
from copath.plans.miner import mine_item_rules, mine_rules, resolve_theta
from copath.sources.graphs import TOY_EDGES, TOY_ITEMS, from_rows, generated, graph_stats, split_label_by_out_degree, toy


@pytest.fixture(scope="module")
def g(spark):
    return toy(spark)


@pytest.fixture(scope="module")
def mined(g):
    return mine_rules(g, MinerConfig(theta=2))


def pair_set(r):
    return {tuple(sorted((r.catalogue.names[x.x], r.catalogue.names[x.y]), key=repr)) + (x.n,) for x in r.pairs.collect()}


def rows_of(g):
    return [r.v for r in g.vertices.collect()], [(r.v, r.item) for r in g.attrs.collect()], [(r.src, r.label, r.dst) for r in g.edges.collect()]


def test_worked_example(g, mined):
    counts = Counter((p.kind, len(p.hops), p.unit) for p in mined.catalogue.support)
    assert counts == {("fixed", 0, True): 8, ("fixed", 0, False): 1, ("fixed", 1, True): 11, ("fixed", 1, False): 6, ("fixed", 2, True): 17, ("fixed", 2, False): 25, ("reach", 1, True): 13, ("reach", 1, False): 10}
    assert mined.pairs.count() == 2083
    rule = mined.rules().where("x = '{CS}|Follows|{Art}' AND y = '{CS}|BelongTo|{Uni}'").first()
    assert (rule.abs_support, rule.confidence, rule.lift) == (2, 1, 6) and abs(rule.rel_support - 1 / 6) < 1e-12


def test_rules_equal_exhaustive_search(g, mined):
    frequent, pairs = comparators.brute_force(*rows_of(g), 2, 2, 2)
    assert {p: len(s) for p, s in frequent.items()} == mined.catalogue.support
    assert {tuple(sorted(k, key=repr)) + (n,) for k, n in pairs.items()} == pair_set(mined)


@pytest.mark.parametrize("more", [{"rule_form": "lattice"}, {"rule_form": "bitmap"}, {"rule_form": "merged"}, {"rule_form": "single_pass"}, {"policy": "prefix_only"}, {"bound": "per_label"}, {"psi": 1.0}, {"rho": 1.0}, {"placement": "greedy", "parallelism": 3}], ids=str)
def test_forms_and_policies_agree(g, mined, more):
    r = mine_rules(g, MinerConfig(theta=2, **more))
    assert r.catalogue.support == mined.catalogue.support
    assert pair_set(r) == pair_set(mined)
    if more.get("policy"):
        assert sum(x[2] for x in r.catalogue.rounds) > sum(x[2] for x in mined.catalogue.rounds)


@pytest.mark.parametrize("seed", range(3))
def test_random_graphs_equal_exhaustive_search(spark, seed):
    rng = random.Random(seed)
    n = rng.randint(5, 9)
    attrs = [(v, f"i{rng.randrange(4)}") for v in range(n) for _ in range(rng.randint(0, 3))] or [(0, "i0")]
    edges = [(rng.randrange(n), f"l{rng.randrange(2)}", rng.randrange(n)) for _ in range(2 * n)]
    g = from_rows(spark, range(n), attrs, edges)
    theta, k = rng.randint(1, 3), rng.choice((1, 2, 3))
    for empty in (False, True):
        cfg = MinerConfig(theta=theta + empty, max_len=k, max_items=2, allow_empty=empty, rule_form="lattice" if empty else "auto")
        r = mine_rules(g, cfg)
        frequent, pairs = comparators.brute_force(*rows_of(g), k, k, theta + empty, max_items=2, allow_empty=empty)
        assert {p: len(s) for p, s in frequent.items()} == r.catalogue.support
        assert len(pairs) == r.pairs.count()
        assert r.matches.count() == sum(len(s) for p, s in frequent.items() if p.hops)


def test_merged_ends_need_one_witness(spark):
    g = from_rows(spark, [1, 2, 3], [(1, "s"), (2, "a"), (3, "b")], [(1, "l", 2), (1, "l", 3)])
    texts = {r.text for r in mine_rules(g, MinerConfig(theta=1, max_len=1)).patterns().collect()}
    assert {"{s}|l|{a}", "{s}|l|{b}", "{s}|l*|{a}"} <= texts and "{s}|l|{a,b}" not in texts


def test_invariants(mined):
    support = mined.catalogue.support
    for p, n in support.items():
        assert all(support[q] >= n for q in p.without_one_item())
        if p.hops and not p.reach:
            assert support[Pattern(p.head, p.hops[:-1])] >= n
            reach = Pattern(p.head, p.hops, True)
            assert len(p.hops) > 1 or support.get(reach, 0) >= n
    for x in mined.rules().collect():
        assert x.confidence <= 1 and x.abs_support <= min(x.support_x, x.support_y)
    both = {(x.x, x.y): x for x in mined.rules().collect()}
    assert all(both[y, x].lift == pytest.approx(r.lift) for (x, y), r in both.items())


def test_bounds_hold(g, mined):
    t = bounds.target_tables(g, 2)
    assert t.degree == 2
    for p, n in mined.catalogue.support.items():
        if p.hops and not p.reach:
            label, tail = p.hops[-1]
            assert all(n <= t.ends[label, x] * t.degree ** (len(p.hops) - 1) for x in tail)


def test_higher_threshold_and_longer_reach(g, mined):
    high = mine_rules(g, MinerConfig(theta=3))
    assert set(high.catalogue.support) <= set(mined.catalogue.support)
    far = mine_rules(g, MinerConfig(theta=2, max_reach=0))
    assert all(far.catalogue.support[p] >= n for p, n in mined.catalogue.support.items() if p.reach)


def test_damping_never_adds(g, mined):
    for psi in (0.0, 0.4):
        r = mine_rules(g, MinerConfig(theta=2, psi=psi))
        row = accuracy.accuracy(mined.rules(), r.rules()).first()
        assert row.precision == 1
        assert r.catalogue.support.items() <= mined.catalogue.support.items()
    short = mine_rules(g, MinerConfig(theta=2, psi=0.0, max_len=1))
    assert pair_set(short) == pair_set(mine_rules(g, MinerConfig(theta=2, max_len=1)))


def test_sampling(spark):
    g = generated(spark, 400, labels=3, items=4)
    common = list(range(len(g.items)))
    for rho in (0.3, 0.7):
        s = sampling.sample_sources(g, common, rho)
        assert sorted(s.collect()) == sorted(sampling.sample_sources(g, common, rho).collect())
        st = sampling.strata(g, common)
        sizes = {tuple(r["items"]): r["count"] for r in st.groupBy("items").count().collect()}
        got = {tuple(r["items"]): r["count"] for r in st.join(s, "v").groupBy("items").count().collect()}
        assert got == {k: -(-int(n * rho * 1000) // 1000) if (n * rho) % 1 else int(n * rho) for k, n in sizes.items()}
        w = sampling.stratum_weights(g, common, s).groupBy().sum("weight").first()[0]
        assert w == pytest.approx(sum(sizes.values()))
    lo, hi = sampling.interval(30, 100, 1000)
    assert lo < 300 < hi and hi - lo == pytest.approx(2 * 1.959964 * 1000 * (0.3 * 0.7 / 99) ** 0.5, rel=1e-6)


def test_extensions(g):
    base = MinerConfig(theta=2)
    exact = mine_rules(g, base).pairs.count()
    assert mine_rules(g, base.but(keep_dominated=True)).pairs.count() > exact
    assert mine_rules(g, base.but(drop_implied=True)).pairs.count() < exact
    # A pattern dominates its own head item set, also if it is a reach pattern.
    assert mine_rules(g, base.but(min_len=0)).pairs.count() == len(comparators.brute_force(*rows_of(g), 2, 2, 2, min_len=0)[1])
    r = mine_item_rules(g, base)
    assert {x.x for x in r.rules().collect()} == {"{CS}", "{Male}"}
    assert resolve_theta(g, MinerConfig(0.2, relative=True)) == 3


def test_edge_cases(spark):
    none = from_rows(spark, [1, 2], [(1, "a"), (2, "a")], [(1, "l", 9)])
    assert mine_rules(none, MinerConfig(theta=1)).pairs.count() == 0
    loop = from_rows(spark, [1], [(1, "a")], [(1, "l", 1), (1, "l", 1)])
    r = mine_rules(loop, MinerConfig(theta=1))
    assert {x.text for x in r.patterns().collect()} == {"{a}", "{a}|l|{a}", "{a}|l|{a}|l|{a}", "{a}|l*|{a}"}
    assert mine_rules(loop, MinerConfig(theta=5)).patterns().count() == 0
    late = mine_rules(loop, MinerConfig(theta=1, deadline_s=0.0))
    assert late.status == "did_not_finish" and late.pairs.count() == 0 and late.rules().count() == 0
    with pytest.raises(ValueError):
        MinerConfig(theta=1, psi=2)


def test_text_round_trip():
    items, labels = ["a,b", "c|d", "e{}", "f*\\"], ["l*", "m|"]
    for p in (Pattern((0, 3), ((0, (1, 2)), (1, (0,)))), Pattern((1,), ((0, (3,)),), True), Pattern((2,))):
        assert parse(p.text(items, labels), items, labels) == p


def test_dominance_columns(spark, mined):
    from pyspark.sql import functions as F

    from copath.functions.patterns import STRUCT

    some = random.Random(1).sample(sorted(mined.catalogue.support, key=repr), 25)
    rows = [(as_row(p), as_row(q), p.dominates(q), p.unit) for p in some for q in some]
    df = spark.createDataFrame(rows, f"p {STRUCT}, q {STRUCT}, want boolean, unit boolean")
    assert df.where((dominates(F.col("p"), F.col("q")) != F.col("want")) | (is_unit(F.col("p")) != F.col("unit"))).count() == 0


def test_single_patterns(g, mined):
    for p, n in random.Random(2).sample(sorted(mined.catalogue.support.items(), key=repr), 8):
        assert matching.match(g, p, 2).count() == n
    x, y = (parse(t, g.items, g.labels) for t in ("{Male}|Follows|{Female}", "{CS}|BelongTo|{Uni}"))
    assert sorted(r.v for r in matching.rule_sources(g, x, y).collect()) == [8, 9]
    wide = parse("{Female}|Follows|{Male}", g.items, g.labels), parse("{Female}|Likes|{Museum}", g.items, g.labels)
    assert {r.v for r in matching.rule_exceptions(g, *wide).collect()} == {11}


def test_graph_tools(spark, g):
    assert len(TOY_ITEMS) == 12 and len(TOY_EDGES.split(";")) == 15
    s = graph_stats(g).first()
    assert (s.n_vertices, s.n_edges, s.n_labels, s.n_items, s.max_in_degree) == (12, 15, 4, 8, 2)
    split = split_label_by_out_degree(g, "Follows")
    assert {"Follows_1", "Follows_2_4"} <= set(split.labels) and split.edges.count() == 15
    sets = comparators.itemsets_mllib(g, 2, 12).collect()
    assert len(sets) == 9


def test_per_label_bound_keeps_late_labels(spark):
    # Few B edges, reached by ten A edges each: {customer}|A|{nation}|B|{region} has 100 sources.
    attrs = [(v, "customer") for v in range(100)] + [(100 + k, "nation") for k in range(10)] + [(110 + k, "region") for k in range(2)]
    edges = [(v, "A", 100 + v % 10) for v in range(100)] + [(100 + k, "B", 110 + k % 2) for k in range(10)]
    g = from_rows(spark, [v for v, _ in attrs], attrs, edges)
    cfg = MinerConfig(theta=80, bound="per_label")
    frequent, pairs = comparators.brute_force(*rows_of(g), 2, 2, 80)
    r = mine_rules(g, cfg)
    assert any(len(p.hops) == 2 and n == 100 for p, n in r.catalogue.support.items())
    assert {p: len(s) for p, s in frequent.items()} == r.catalogue.support
    assert {tuple(sorted(k, key=repr)) + (n,) for k, n in pairs.items()} == pair_set(r)


def test_deadline_cancels_a_running_job(spark):
    """A job that would take minutes ends soon after the limit; the session goes on."""
    import time

    rng = random.Random(1)
    n = 3000
    g = from_rows(spark, range(n), [(v, f"i{k}") for v in range(n) for k in rng.sample(range(12), 7)], [(rng.randrange(n), "l", rng.randrange(n)) for _ in range(20 * n)])
    began = time.monotonic()
    r = mine_rules(g, MinerConfig(theta=30, policy="prefix_only", deadline_s=6.0))
    assert r.status == "did_not_finish" and time.monotonic() - began < 60 and r.pairs.count() == 0
    assert spark.range(5).count() == 5 and spark.sparkContext.getLocalProperty("spark.jobGroup.id") is None


def test_stratum_weights_remove_the_quota_bias(spark):
    """Strata of few vertices are sampled whole: the ratio overrates them, their own weights don't."""
    small = [(v, f"x{v // 2}") for v in range(100)]
    g = from_rows(spark, range(300), [(v, "a") for v in range(300)] + small, [(v, "l", (v + 1) % 300) for v in range(300)])
    by = lambda r: {x.text: x.support for x in r.patterns().collect()}
    cfg = MinerConfig(theta=2, max_len=1, reach=False, max_items=1)
    exact, ratio = by(mine_rules(g, cfg, with_rules=False)), by(mine_rules(g, cfg.but(rho=0.4), with_rules=False))
    weighted = by(mine_rules(g, cfg.but(rho=0.4, estimator="stratum_weight"), with_rules=False))
    assert exact["{x3}"] == 2 == weighted["{x3}"] and ratio["{x3}"] == 2.5
    assert weighted["{a}"] == pytest.approx(300) and weighted["{a}|l|{a}"] == pytest.approx(300)


def test_runs_leave_only_what_they_keep(spark, g):
    from copath.plans import store

    def tables():
        files, where = store._file(spark, store.shared_dir(spark))
        return {f.getPath().getName() for f in files.listStatus(where)}

    before = tables()
    r = mine_rules(g, MinerConfig(theta=2))
    left = tables() - before
    kept = {t._copath_path.rsplit("/", 1)[1] for t in [r.pairs, *r.found.tables] if t is not None and hasattr(t, "_copath_path")}
    assert left == kept and r.stored_bytes > 0 and r.matches.count() > 0


def test_runs_leave_no_shuffle_files(spark, g):
    def shuffles():
        files = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
        return {files.apply(i).getName() for i in range(files.size()) if files.apply(i).getName().startswith("shuffle_")}

    before = shuffles()
    mine_rules(g, MinerConfig(theta=2, max_len=1))
    assert not shuffles() - before


def test_edges_of_a_source_lie_together(spark):
    edges = from_rows(spark, range(64), [(v, "a") for v in range(64)], [(v, "l", (v + k) % 64) for v in range(64) for k in range(1, 9)]).edges
    files = len(edges.inputFiles())
    n = edges.selectExpr("src", "input_file_name() AS f").distinct().count()
    # Two ranges that follow each other share one source at most.
    assert edges.count() == 512 and n < 64 + max(1, files)


def test_experiments_share_counts_and_leave_nothing(spark, g, monkeypatch):
    from copath.operators import kinds
    from copath.plans import store, workloads

    def tables():
        files, where = store._file(spark, store.shared_dir(spark))
        return {f.getPath().getName() for f in files.listStatus(where)}

    made = []
    attr_sets = type(g).attr_sets
    monkeypatch.setattr(type(g), "attr_sets", lambda self: made.append(1) or attr_sets(self))
    monkeypatch.setattr(workloads, "build", lambda *_: toy(spark))
    before = tables()
    rows = workloads.thread_sweep(spark, "", "toy", 2 / g.n, (1, 2), ("exact",)).collect()
    assert len(rows) == 2 and len({r.n_rules for r in rows}) == 1 and rows[0].n_rules > 0
    assert tables() == before and len(made) == 1
    assert kinds.kinds_of(kinds.indexed(toy(spark)), True).attrs.where("item = -1").count() > 0


def test_factor_sweeps_tell_failures_from_results(spark, g, monkeypatch):
    """No limit of time cuts a sweep's runs; of runs that a given limit stops, no accuracy is told."""
    from copath.plans import workloads

    monkeypatch.setattr(workloads, "build", lambda *_: toy(spark))
    monkeypatch.setattr(workloads, "CAP", 0.0)
    rows = workloads.factor_sweep(spark, "", "toy", 2 / g.n, (0.8,), max_items=1, max_len=1).collect()
    assert [r.option for r in rows] == ["exact", "damped", "sampled", "both"] and all(r.status == "finished" for r in rows)
    assert rows[0].n_rules > 0 and rows[1].n_rules == rows[0].n_rules and rows[1].recall == rows[1].precision == 1
    late = workloads.factor_sweep(spark, "", "toy", 2 / g.n, (0.8,), max_items=1, max_len=1, deadline_s=0.0).collect()
    assert all((r.status, r.recall, r.precision, r.n_rules) == ("did_not_finish", None, None, 0) for r in late)


def test_runs_of_a_sweep_share_edges_and_keep_masks(spark, monkeypatch):
    """Edges meet the kinds of their ends once for all runs, and codes go to the rules without a row for each code and vertex; the same results."""
    from copath.operators import growth
    from copath.operators.kinds import Kinds, indexed

    met = []
    meet = Kinds.meet
    monkeypatch.setattr(Kinds, "meet", lambda self, labels: met.append(labels) or meet(self, labels))
    shop = lambda: from_rows(spark, range(12), [*[(v, f"o{v % 2}") for v in range(6)], *[(v, i) for v in range(6, 12) for i in ("p", f"c{v % 3}")]], [(v, label, 6 + (v + k) % 6) for v in range(6) for k, label in enumerate("ab")])
    own, cfg = indexed(shop()), MinerConfig(theta=2, max_len=1)
    with monkeypatch.context() as m:
        m.setattr(growth.Codes, "rows", lambda self: 1 / 0)
        both = [mine_rules(own, cfg), mine_rules(own, cfg.but(rho=0.5))]
    assert len(met) == 1
    for r, c in zip(both, (cfg, cfg.but(rho=0.5, rule_form="bitmap"))):
        # One run with its own counts, and with codes listed by vertex.
        with monkeypatch.context() as m:
            m.setattr(growth.Codes, "masks", lambda *_: None)
            want = mine_rules(shop(), c)
        assert r.catalogue.support == want.catalogue.support and pair_set(r) == pair_set(want) and pair_set(r)
        assert {tuple(x) for x in r.matches.collect()} == {tuple(x) for x in want.matches.collect()} and r.stored_rows() == want.stored_rows()
    assert sorted(sampling.strata(own, [0, 1]).collect()) == sorted(sampling.strata(shop(), [0, 1]).collect()) != []


def test_sampled_runs_count_their_sources(spark):
    g = from_rows(spark, range(20), [(v, "a") for v in range(20)], [(v, "l", (v + 1) % 20) for v in range(20)])
    r = mine_rules(g, MinerConfig(theta=2, max_len=1, rho=0.4), with_rules=False, with_matches=False)
    assert r.sampled == sampling.sample_sources(g, [0], 0.4).count() == 8
    assert r.catalogue.support == mine_rules(g, MinerConfig(theta=2, max_len=1, rho=0.4)).catalogue.support and r.matches.isEmpty()


def test_codes_of_the_same_vertices_are_one(spark, monkeypatch):
    # Every p has k, so that {k}, {p} and {k,p} are the same ends, and a reach pattern is its only hop.
    g = from_rows(spark, range(8), [(v, "s") for v in (0, 1, 2)] + [(v, i) for v in (3, 4, 5) for i in "kp"] + [(v, "q") for v in (6, 7)], [(0, "l", 3), (1, "l", 4), (2, "l", 5), (0, "l", 6), (1, "l", 7), (0, "m", 5)])
    asked = []
    monkeypatch.setattr("copath.operators.growth.explicit", lambda kinds, edges, codes: asked.extend(codes))
    r = mine_rules(g, MinerConfig(theta=2, max_len=1))
    assert not asked
    # No vertex has k and q.
    wanted = {Pattern((g.items.index("s"),), ((0, s),), reach): n for s, n in (((0,), 3), ((1,), 3), ((0, 1), 3), ((2,), 2)) for reach in (False, True)}
    assert {p: n for p, n in r.catalogue.support.items() if p.hops} == wanted
    assert len({cid for _, cid, _ in r.found.merged().names}) == 2
    assert r.found.merged().held.count() == 5 and r.matches.count() == 22


def test_labels_that_no_edge_follows_are_walked_once(spark, monkeypatch):
    """A reach pattern over such a label is its hop, and more than 64 codes of one vertex take several masks."""
    from copath.operators import growth

    attrs = [*[(v, "order") for v in range(6)], (6, "part"), (7, "part"), (7, "red"), (8, "box")]
    shop = from_rows(spark, range(9), attrs, [*[(v, "has", 6 + v % 2) for v in range(6)], (0, "has", 7), (6, "in", 8), (7, "in", 8)])
    frequent, pairs = comparators.brute_force(*rows_of(shop), 2, 2, 2)

    def onward(*_):
        raise AssertionError("no walk of two hops has one label")

    with monkeypatch.context() as m:
        m.setattr(growth, "onward", onward)
        r = mine_rules(shop, MinerConfig(theta=2))
    assert {p: len(s) for p, s in frequent.items()} == r.catalogue.support
    assert {tuple(sorted(k, key=repr)) + (n,) for k, n in pairs.items()} == pair_set(r)

    many = from_rows(spark, range(4), [(0, "a"), (1, "a"), *[(2, f"i{k:03}") for k in range(70)], (3, "i069")], [(0, "x", 2), (1, "x", 2), (1, "x", 3)])
    found = mine_rules(many, MinerConfig(theta=2, max_items=1, max_len=1, reach=False), with_rules=False).catalogue.support
    assert sum(bool(p.hops) for p in found) == 70 and all(n == 2 for n in found.values())


def test_ends_are_bounded_by_the_labels_before_them():
    t = bounds.Targets(4, 100, {(1, 7): 1, (1, 8): 2, (0, 9): 4}, {})
    paths = bounds.Walks([{0}, {1}], {0: {1}}, [{0: 1}, {1: 2}])
    assert paths.ends(t, 1) == [(0, 9), (1, 8)]
    assert bounds.Walks([{0}, {1}], {0: {1}}, [{0: 1}, {1: 2}], exact=False).ends(t, 1) == [(0, 9), (1, 7), (1, 8)]
