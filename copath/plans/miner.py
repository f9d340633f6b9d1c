"""A mining run: item sets, bounds, patterns, rules, measures, and a log of its rounds."""

from __future__ import annotations

import time
from dataclasses import dataclass, field
from math import ceil

from pyspark.sql import DataFrame, Row
from pyspark.sql import functions as F

from copath.config import MinerConfig
from copath.functions import measures
from copath.functions.patterns import STRUCT, Pattern, as_row
from copath.operators import balance, growth, plain, rules
from copath.operators.bounds import Targets, target_labels, target_tables, useful, walks
from copath.operators.kinds import ANY, kinds_of
from copath.operators.matches import MASKS, Matches
from copath.operators.sampling import sample_sources, stratum_weights
from copath.plans import meter
from copath.plans.store import cut, scope
from copath.sources.graphs import PropertyGraph


@dataclass
class MiningResult:
    graph: PropertyGraph
    cfg: MinerConfig
    theta: float
    catalogue: growth.Catalogue
    targets: Targets | None
    found: Matches
    pairs: DataFrame
    scale: float = 1.0
    steps: dict[str, float] = field(default_factory=dict)
    balance: Row | None = None
    stored_bytes: int = 0
    #: Source vertices of a sampled run.
    sampled: int | None = None

    @property
    def matches(self) -> DataFrame:
        """(pid, v): the source vertices of each pattern."""
        return self.found.rows().select("pid", "v")

    @property
    def status(self) -> str:
        return "finished" if self.catalogue.finished else "did_not_finish"

    def patterns(self) -> DataFrame:
        """pid, kind, len, n_items, text, support, pattern."""
        g, c = self.graph, self.catalogue
        rows = [(c.ids[p], p.kind, len(p.hops), p.n_items, p.text(g.items, g.labels), float(n), as_row(p)) for p, n in c.support.items()]
        return g.vertices.sparkSession.createDataFrame(rows, f"pid int, kind string, len int, n_items int, text string, support double, pattern {STRUCT}")

    def rules(self, names: tuple[str, ...] = measures.BASIC) -> DataFrame:
        """x, y, abs_support and measures, in both directions; x and y as canonical texts."""
        pairs = self.pairs
        both = pairs.select("x", "y", "n").union(pairs.select(F.col("y").alias("x"), F.col("x").alias("y"), "n"))
        named = self.patterns().select("pid", "text", "support", "kind", "len")
        rows = len(self.catalogue.support)
        side = lambda s: growth.checked(named.select(F.col("pid").alias(s), *[F.col(k).alias(f"{k}_{s}") for k in ("text", "support", "kind", "len")]), rows)
        out = both.join(side("x"), "x").join(side("y"), "y")
        out = out.select(F.col("text_x").alias("x"), F.col("text_y").alias("y"), (F.col("n") / self.scale).alias("abs_support"), "support_x", "support_y", F.lit(self.graph.n).alias("n_vertices"), "kind_x", "kind_y", "len_x", "len_y")
        return measures.score(out, names)

    def profile(self) -> DataFrame:
        """step, iter, generated, frequent, seconds of each round."""
        rows = [(s, i, n, k, float(t)) for s, i, n, k, t in self.catalogue.rounds]
        return self.graph.vertices.sparkSession.createDataFrame(rows, "step string, iter int, generated long, frequent long, seconds double")

    def shares(self) -> dict[str, float]:
        """Share of the run time of each step."""
        total = sum(self.steps.values()) or 1.0
        return {k: v / total for k, v in self.steps.items()}

    def stored_rows(self) -> int:
        """Rows of the match table and of the rules: the data-dependent part of what a run keeps."""
        return (self.found.held if self.found.direct is None else self.found.direct).count() + self.pairs.count()


def resolve_theta(g: PropertyGraph, cfg: MinerConfig) -> int:
    """The threshold as a count."""
    return max(1, ceil(cfg.theta * g.n - 1e-9)) if cfg.relative else ceil(cfg.theta)


def mine_rules(g: PropertyGraph, cfg: MinerConfig, with_rules: bool = True, with_matches: bool = True) -> MiningResult:
    """``with_matches``: whether the sources of patterns are kept; rules need them."""
    spark, theta = g.vertices.sparkSession, resolve_theta(g, cfg)
    c = growth.Catalogue(theta)
    run = _Run(g, cfg, theta, c, with_rules or with_matches)
    with meter.parallelism(spark, cfg.parallelism), meter.deadline(spark, cfg.deadline_s) as late, scope(spark) as tables:
        c.late = late
        try:
            run.patterns()
            if with_rules and not late():
                run.rules()
        except Exception:
            # Cancelled jobs end in an error; any other one is the caller's.
            if not late():
                raise
        c.finished = not late()
        result = run.result()
        tables.keep(result.pairs, *result.found.tables)
        result.stored_bytes = tables.bytes()
    return result


class _Run:
    """The steps of a run, each with the time that it took."""

    def __init__(self, g: PropertyGraph, cfg: MinerConfig, theta: int, c: growth.Catalogue, with_matches: bool = True):
        self.g, self.cfg, self.theta, self.c = g, cfg, theta, c
        self.scale, self.targets, self.balance, self.sampled = 1.0, None, None, None
        self.with_matches = with_matches
        self.steps: dict[str, float] = {}
        self.clock = time.monotonic()
        self.matches = self.pairs = None

    def tick(self, name: str) -> None:
        now = time.monotonic()
        self.steps[name] = self.steps.get(name, 0.0) + now - self.clock
        self.clock = now

    def patterns(self) -> None:
        g, cfg, c = self.g, self.cfg, self.c
        kinds = kinds_of(g, cfg.allow_empty)
        sources, weight = None, F.lit(1).cast("long")
        if cfg.rho is not None and cfg.rho < 1:
            # Strata are sets of items that are frequent in the whole graph.
            counts = kinds.attrs.where(F.col("item") != ANY).join(kinds.weights, "sid").groupBy("item").agg(F.sum("n").alias("n"))
            common = [r.item for r in counts.where(F.col("n") >= self.theta).collect()]
            sources, self.scale = cut(sample_sources(g, common, cfg.rho, cfg.seed, cfg.sample_mode, kinds)), cfg.rho
            self.sampled = sources.count()
            if cfg.estimator == "stratum_weight":
                sources, self.scale, weight = cut(stratum_weights(g, common, sources, kinds)), 1.0, F.col("weight")
        own = (kinds.own if sources is None else kinds.own.join(sources, "v")).select("v", "sid", weight.alias("w"))
        weights = kinds.weights.select(F.col("sid").alias("v"), F.col("n").alias("w")) if sources is None else cut(own.groupBy(F.col("sid").alias("v")).agg(F.sum("w").alias("w")))
        of_kinds = growth.frequent_itemsets(kinds.attrs.withColumnRenamed("sid", "v"), weights, c, self.scale, cfg, len(g.items))
        heads = cut(of_kinds.select(F.col("v").alias("sid"), "pid"))
        self.tick("itemsets")
        # Sources without a frequent head start no pattern.
        own = own.join(kinds.small(heads.select("sid").distinct()), "sid", "left_semi").select("v", "sid", "w")
        every = not cfg.max_len or cfg.min_len == 0
        pruned, hops = cfg.policy == "pruned", cfg.hops if cfg.reach else 1
        if cfg.max_len:
            self.targets = target_tables(g, self.theta, cfg.psi, cfg.bound, kinds, cfg.max_len if pruned else None, hops)
        if not pruned and cfg.max_len:
            self.plainly(plain.Work(kinds.own.join(kinds.attrs, "sid").select("v", "item"), g.edges, own.select("v", "w")), every)
            return
        nothing = Pattern(())
        if cfg.max_len and not every:
            # Nor does one without a target item and an edge of a target label.
            own = useful(kinds, own, self.targets).select("v", "sid", "w")
        own, paths = cut(own), None
        if cfg.max_len:
            paths = walks(kinds, own, heads, target_labels(self.targets, cfg.max_len, hops), c.theta * self.scale, cfg.max_len, hops, cfg.rho is None)
            # A fixed pattern asks for items wherever it passes; equal labels may lead through vertices that have none.
            edges = kinds.edges(paths.labels)
            steps = edges.where("sid IS NOT NULL")
        codes = growth.Codes(c, growth.Sources(own, heads), self.scale, cfg, kinds, paths)
        if every:
            codes.heads[nothing] = {c.ids[p] for p in c.of(0)}
            codes.frames.append(own.select(F.lit(codes.number(nothing)).alias("cid"), "v"))
        if cfg.max_len:
            ends = paths.ends(self.targets, hops)
            tips = {(label, growth.end_set(x)): k for k, (label, x) in enumerate(ends)}
            first = growth.ends_of(kinds, steps, tips)
            self.tick("bounds")
            growth.grow_fixed(kinds, steps, self.targets, paths, codes, tips, first)
            self.tick("fixed")
            if cfg.reach:
                growth.grow_reach(kinds, edges, self.targets, paths, codes, tips, first)
                self.tick("reach")
        if not self.with_matches:
            return
        # Placed sources bring their codes one by one.
        masks = None if cfg.placement else codes.masks(MASKS)
        if masks:
            self.matches = Matches(None, codes.sources, codes.patterns(), masks=masks[0], at=masks[1])
            return
        held = codes.rows()
        self.matches = Matches(own.select(F.lit(0).alias("cid"), "v").limit(0) if held is None else held, codes.sources, codes.patterns())
        if cfg.placement:
            n = cfg.parallelism or int(own.sparkSession.conf.get("spark.sql.shuffle.partitions"))
            plan = balance.PLANS[cfg.placement](cut(balance.vertex_cost(g, self.targets)), n)
            self.balance = balance.balance_report(plan.join(own, "v", "left_semi")).first()
            self.matches.plan = plan.select("v", "part"), n

    def plainly(self, work: plain.Work, every: bool) -> None:
        g, cfg, c = self.g, self.cfg, self.c
        at = plain.head_matches(work, c)
        sets, n_sets = plain.item_sets(work.attrs, cfg.max_items)
        self.tick("bounds")
        fixed, reach = plain.grow_fixed(work, c, sets, n_sets, len(g.labels), at, self.scale, cfg), None
        self.tick("fixed")
        if cfg.reach:
            reach = plain.grow_reach(work, c, sets, n_sets, len(g.labels), at, self.scale, cfg)
            self.tick("reach")
        parts = [x for x in (at if every else None, fixed, reach) if x is not None]
        self.matches = Matches(direct=cut(growth.union(parts) if parts else at.limit(0)))

    def rules(self) -> None:
        cfg = self.cfg if self.cfg.max_len else self.cfg.but(min_len=0)
        if self.matches.direct is not None:
            cfg = cfg.but(rule_form="single_pass")
        self.pairs = rules.mine(self.matches, self.c, self.scale, cfg)
        self.tick("rules")

    def result(self) -> MiningResult:
        none = lambda schema: self.g.vertices.sparkSession.createDataFrame([], schema)
        matches = Matches(direct=none("pid int, v long, w long")) if self.matches is None else self.matches
        pairs = none("x int, y int, n long") if self.pairs is None else self.pairs
        return MiningResult(self.g, self.cfg, self.theta, self.c, self.targets, matches, pairs, self.scale, self.steps, self.balance, sampled=self.sampled)


def mine_patterns(g: PropertyGraph, cfg: MinerConfig) -> MiningResult:
    """A run that ends with the patterns; its pairs are empty."""
    return mine_rules(g, cfg, with_rules=False)


def mine_item_rules(g: PropertyGraph, cfg: MinerConfig) -> MiningResult:
    """Classic rules between item sets: paths of length zero on both sides."""
    return mine_rules(g, cfg.but(max_len=0, min_len=0, reach=False))
