"""Experiments: sweeps over thresholds, lengths, factors and graph sizes, and the studies of rules."""

from __future__ import annotations

import time
from functools import wraps
from math import ceil

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from copath.config import MinerConfig
from copath.operators import accuracy, comparators, sampling
from copath.operators.kinds import indexed
from copath.plans import meter
from copath.plans.miner import MiningResult, mine_rules
from copath.plans.store import cut, scope
from copath.sources import graphs
from copath.sources.graphs import PropertyGraph, build
from copath.streaming import edges as stream

#: The five methods that are compared.
METHODS = {"prefix_only": {"policy": "prefix_only"}, "exact": {}, "damped": {"psi": 0.4}, "sampled": {"rho": 0.4}, "both": {"psi": 0.4, "rho": 0.4}}
LOG = "graph string, method string, parameter string, value double, status string, seconds double, candidates long, n_patterns long, n_rules long"


def run(g: PropertyGraph, cfg: MinerConfig, graph: str, method: str, parameter: str, value: float, more: dict | None = None) -> tuple[tuple, MiningResult]:
    began = time.monotonic()
    r = mine_rules(g, cfg.but(**(METHODS.get(method, {}) if more is None else more)))
    n = r.pairs.count()
    return (graph, method, parameter, float(value), r.status, time.monotonic() - began, sum(x[2] for x in r.catalogue.rounds), len(r.catalogue.support), n), r


#: Seconds after which one run of an experiment is given up.
CAP = 60.0


def scoped(experiment):
    """An experiment that returns figures alone: its graphs, and what its runs keep, are dropped at its end."""

    @wraps(experiment)
    def f(spark: SparkSession, *args, **kwargs) -> DataFrame:
        with scope(spark):
            return experiment(spark, *args, **kwargs)

    return f


def logged(g: PropertyGraph, *args, **kwargs) -> tuple:
    """The line of a run, none of whose tables stay."""
    with scope(g.vertices.sparkSession):
        return run(g, *args, **kwargs)[0]


@scoped
def theta_sweep(spark: SparkSession, sf_dir: str, graph: str, shares: tuple[float, ...], methods=tuple(METHODS), **more) -> DataFrame:
    """Run time, candidates and output of every method over thresholds, with the speed-up over the first (a least one where that didn't finish)."""
    g, rows = indexed(build(spark, sf_dir, graph)), []
    for t in shares:
        lines = [logged(g, MinerConfig(t, relative=True, deadline_s=CAP, **more), graph, m, "theta", t) for m in methods]
        rows += [(*line, accuracy.speedup(lines[0][5], line[5])) for line in lines]
    return spark.createDataFrame(rows, LOG + ", speed_up double")


@scoped
def length_sweep(spark: SparkSession, sf_dir: str, graph: str, share: float, lengths=(1, 2, 3, 4), methods=("prefix_only", "exact", "both"), max_items: int | None = None) -> DataFrame:
    """The same over the longest path; a method that once runs out of time isn't tried on longer ones."""
    g, rows, over = indexed(build(spark, sf_dir, graph)), [], set()
    for k in lengths:
        for m in methods:
            if m not in over:
                rows.append(logged(g, MinerConfig(share, relative=True, max_items=max_items, max_len=k, deadline_s=CAP), graph, m, "max_len", k))
                if rows[-1][4] != "finished":
                    over.add(m)
    return spark.createDataFrame(rows, LOG)


#: Approximations by what their factor stands for.
OPTIONS = {"damped": ("psi",), "sampled": ("rho",), "both": ("psi", "rho")}


@scoped
def factor_sweep(spark: SparkSession, sf_dir: str, graph: str, share: float, factors=(0.2, 0.4, 0.6, 0.8), **more) -> DataFrame:
    """Every approximation over its factor: recall and precision against the exact rules, seconds, candidates, rules.

    Every run goes to its end, as rules that lack say nothing on accuracy. Given a ``deadline_s``, runs that it stopped, and all if it stopped the exact one, have neither figure.
    """
    g, cfg = indexed(build(spark, sf_dir, graph)), MinerConfig(share, relative=True, **more)
    line, exact = run(g, cfg, graph, "exact", "factor", 1.0)
    whole = exact.status == "finished"
    truth = cut(texts(exact))
    own = 1.0 if whole else None
    rows = [(graph, "exact", 1.0, own, own, *line[5:7], line[8], line[4])]
    for f in factors:
        for option, names in OPTIONS.items():
            with scope(spark):
                line, r = run(g, cfg, graph, option, "factor", f, dict.fromkeys(names, f))
                got = accuracy.accuracy(truth, texts(r)).first() if whole and r.status == "finished" else None
            rows.append((graph, option, float(f), got and got.recall, got and got.precision, *line[5:7], line[8], line[4]))
    return spark.createDataFrame(rows, "graph string, option string, factor double, recall double, precision double, seconds double, candidates long, n_rules long, status string")


def texts(r: MiningResult) -> DataFrame:
    """x, y of each unordered rule."""
    return r.rules().select(F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y")).distinct()


@scoped
def graph_size(spark: SparkSession, sf_dir: str, sizes=(2_000, 8_000, 32_000), kinds=("uniform", "exponential"), methods=("exact", "damped", "sampled"), vocabulary=(500, 20)) -> DataFrame:
    """Run time over the size of generated graphs, with as many labels and as many items as ``vocabulary`` says."""
    rows = []
    for kind in kinds:
        for words in vocabulary:
            for n in sizes:
                g = graphs.generated(spark, n, kind, labels=words, items=words)
                rows += [run(g, MinerConfig(0.01, relative=True, deadline_s=CAP), f"{kind}_{words}", m, "n_vertices", n)[0] for m in (methods if words < 100 else ("exact",))]
    return spark.createDataFrame(rows, LOG)


@scoped
def thread_sweep(spark: SparkSession, sf_dir: str, graph: str = "trade", share: float = 0.1, threads=(1, 2, 4, 8), methods=("exact", "both")) -> DataFrame:
    """Run time over the number of tasks at a time, with the speed-up over the fewest."""
    g = indexed(build(spark, sf_dir, graph))
    rows = [logged(g, MinerConfig(share, relative=True, parallelism=n), graph, m, "threads", n, METHODS[m]) for m in methods for n in threads]
    log = spark.createDataFrame(rows, LOG)
    first = log.where(F.col("value") == threads[0]).select("method", F.col("seconds").alias("slowest"))
    return log.join(first, "method").withColumn("speed_up", F.col("slowest") / F.col("seconds")).drop("slowest")


@scoped
def placements(spark: SparkSession, sf_dir: str, graph: str = "trade", share: float = 0.1, parts: int = 32) -> DataFrame:
    """Run time of the exact method under each placement of its sources, with the placed load; by Spark's own hashing as ``none``."""
    g, rows = indexed(build(spark, sf_dir, graph)), []
    for how in (None, "hash", "snake", "greedy"):
        with scope(spark):
            line, r = run(g, MinerConfig(share, relative=True, placement=how, parallelism=parts), graph, "exact", "parts", parts, {})
        b = r.balance
        rows.append((graph, how or "none", line[5], r.steps.get("rules", 0.0), float(b.imbalance) if b else None, int(b.max_load) if b else None, line[8]))
    return spark.createDataFrame(rows, "graph string, placement string, seconds double, rules_seconds double, imbalance double, max_load long, n_rules long")


def memory(spark: SparkSession, sf_dir: str, graph: str, share: float, methods=tuple(METHODS)) -> DataFrame:
    """Peak heap of each method, the bytes of all tables that it wrote, and the rows that it keeps."""
    g, rows = build(spark, sf_dir, graph), []
    for m in methods:
        meter.reset_peak(spark)
        line, r = run(g, MinerConfig(share, relative=True, deadline_s=CAP), graph, m, "theta", share)
        rows.append((graph, m, line[4], meter.peak_mb(spark), r.stored_bytes / (1 << 20), r.stored_rows()))
    return spark.createDataFrame(rows, "graph string, method string, status string, peak_heap_mb double, stored_mb double, stored_rows long")


def memory_by_size(spark: SparkSession, sf_dir: str, sizes=(2_000, 8_000, 32_000), kinds=("uniform", "exponential"), words: int = 20) -> DataFrame:
    """The same for the exact method on generated graphs."""
    rows = []
    for kind in kinds:
        for n in sizes:
            g = graphs.generated(spark, n, kind, labels=words, items=words)
            meter.reset_peak(spark)
            _, r = run(g, MinerConfig(0.01, relative=True), kind, "exact", "n_vertices", n)
            rows.append((kind, n, meter.peak_mb(spark), r.stored_bytes / (1 << 20), r.stored_rows()))
    return spark.createDataFrame(rows, "graph string, n_vertices long, peak_heap_mb double, stored_mb double, stored_rows long")


@scoped
def coverage(spark: SparkSession, sf_dir: str, graph: str = "trade", share: float = 0.1, rho: float = 0.4, seeds=(1, 2, 3, 4, 5)) -> DataFrame:
    """seed, n_patterns, covered: how many exact supports lie in the intervals that samples give, for patterns of one hop."""
    g = indexed(build(spark, sf_dir, graph))
    cfg = MinerConfig(share, relative=True, max_len=1, reach=False, max_items=1)
    patterns = lambda cfg: mine_rules(g, cfg, with_rules=False, with_matches=False)
    exact = {p: n for p, n in patterns(cfg).catalogue.support.items() if p.hops}
    theta = max(1, ceil(share * g.n - 1e-9))
    common = [r.item for r in g.attrs.groupBy("item").count().where(F.col("count") >= theta).collect()]
    population = sampling.strata(g, common).count()
    rows = []
    for seed in seeds:
        r = patterns(cfg.but(rho=rho, seed=seed))
        m, got = r.sampled, r.catalogue.support
        spans = [(n, sampling.interval(round(got[p] * rho), m, population)) for p, n in exact.items() if p in got]
        rows.append((seed, len(spans), sum(lo <= n <= hi for n, (lo, hi) in spans) / max(1, len(spans))))
    return spark.createDataFrame(rows, "seed int, n_patterns int, covered double")


@scoped
def step_shares(spark: SparkSession, sf_dir: str, names=("trade", "lineage", "copart", "eventchain"), shares=(0.1, 0.1, 0.17, 0.1)) -> DataFrame:
    """graph, step, share of the run time; and the candidates and frequent patterns of each step."""
    out = None
    for graph, share in zip(names, shares):
        r = mine_rules(build(spark, sf_dir, graph), MinerConfig(share, relative=True))
        part = spark.createDataFrame([(graph, k, float(v)) for k, v in r.shares().items()], "graph string, step string, share double")
        log = r.profile().groupBy(F.regexp_replace("step", "_.*", "").alias("step")).agg(F.sum("generated").alias("generated"), F.sum("frequent").alias("frequent"))
        part = part.join(log, "step", "left")
        out = part if out is None else out.unionByName(part)
    return out


def comparator(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The miner on one item a vertex against correlated subgraph pairs that are asked for as many results, at two thresholds."""
    rows = []
    for graph, shares, edges in (("copart", (0.16, 0.17), 1), ("trade", (0.05, 0.2), 2)):
        full = build(spark, sf_dir, graph)
        g = graphs.reduce_items(full, "most")
        line, _ = run(g, MinerConfig(shares[0], relative=True, max_len=edges, reach=False), graph, "exact", "theta", shares[0])
        rows.append(line)
        for share in shares:
            began = time.monotonic()
            n = comparators.correlated_pairs(g, ceil(share * g.n), line[-1], max_edges=edges).count()
            rows.append((graph, "correlated_pairs", "theta", share, "finished", time.monotonic() - began, 0, 0, n))
    return spark.createDataFrame(rows, LOG)


def knowledge_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rules that join a two-hop fact with a one-hop fact through different vertices."""
    r = mine_rules(build(spark, sf_dir, "trade"), MinerConfig(0.05, relative=True, max_items=1)).rules()
    two = r.where("len_x = 2 AND len_y = 1 AND kind_y = 'fixed' AND split_part(x, '|', 2) != split_part(y, '|', 2)")
    return two.select("x", "y", "abs_support", F.round("confidence", 6).alias("confidence"), F.round("lift", 6).alias("lift"))


def social_reach(spark: SparkSession, sf_dir: str, graph: str = "eventchain", share: float = 0.05, most: tuple[int, ...] = (2, 4)) -> DataFrame:
    """Reach rules of up to four hops beside those of two."""
    g, out = build(spark, sf_dir, graph), None
    for hops in most:
        r = mine_rules(g, MinerConfig(share, relative=True, max_items=1, max_len=1, max_reach=hops)).rules()
        part = r.where("kind_x = 'reach'").select(F.lit(hops).alias("hops"), "x", "y", "abs_support", F.round("confidence", 6).alias("confidence"), F.round("lift", 6).alias("lift"))
        out = part if out is None else out.union(part)
    return out


def asof_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """event_id, o_orderkey: each event and its user's latest order before it, by one sort of both kinds of rows for each user."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet").select(F.col("user_id").alias("k"), F.col("ts").alias("at"), F.lit(1).alias("kind"), "event_id", F.lit(None).cast("long").alias("o_orderkey"))
    users = e.select("k").distinct()
    o = spark.read.parquet(f"{sf_dir}/orders.parquet").select(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("at"), F.lit(0).alias("kind"), F.lit(None).cast("long").alias("event_id"), "o_orderkey").join(users, "k", "left_semi")
    w = Window.partitionBy("k").orderBy("at", "kind", F.col("o_orderkey").asc_nulls_last(), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    both = e.unionByName(o).withColumn("latest", F.last("o_orderkey", ignorenulls=True).over(w))
    return both.where("kind = 1 AND latest IS NOT NULL").select("event_id", F.col("latest").alias("o_orderkey"))


def session_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """user_id, n_sessions, n_events with a gap of six hours."""
    s = stream.sessions(spark.read.parquet(f"{sf_dir}/events.parquet"), "6 hours", None)
    return s.groupBy("user_id").agg(F.count("*").alias("n_sessions"), F.sum("n_events").alias("n_events"))
