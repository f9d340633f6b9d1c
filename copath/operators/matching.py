"""Source vertices of single patterns, evaluated backwards by semi joins, so that rows never exceed vertices."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copath.functions.patterns import Pattern
from copath.operators.growth import propagate
from copath.plans.store import cut
from copath.sources.graphs import PropertyGraph


def covering(g: PropertyGraph, items: tuple[int, ...]) -> DataFrame:
    """(v): vertices that carry all the items; no items: all vertices."""
    if not items:
        return g.vertices
    own = g.attrs.where(F.col("item").isin(list(items)))
    return own.select("v") if len(items) == 1 else own.groupBy("v").count().where(F.col("count") == len(items)).select("v")


def match_fixed(g: PropertyGraph, p: Pattern) -> DataFrame:
    """(v): starts of walks that satisfy the pattern."""
    front = covering(g, p.sets[-1])
    for (label, _), before in zip(reversed(p.hops), reversed(p.sets[:-1])):
        step = g.edges.where(F.col("label") == label).join(front.select(F.col("v").alias("dst")), "dst", "left_semi")
        front = step.select(F.col("src").alias("v")).distinct()
        if before:
            front = front.join(covering(g, before), "v", "left_semi")
    return front


def match_reach(g: PropertyGraph, p: Pattern, max_reach: int = 0) -> DataFrame:
    """(v): vertices with the head that get to a vertex with the tail by one or more edges of the label (0: any number)."""
    label, tail = p.hops[0]
    seeds = covering(g, tail).select(F.lit(0).alias("tid"), F.lit(label).alias("label"), "v")
    return propagate(g.edges, seeds, max_reach).select("v").join(covering(g, p.head), "v", "left_semi")


def match(g: PropertyGraph, p: Pattern, max_reach: int = 0) -> DataFrame:
    return match_reach(g, p, max_reach) if p.reach else match_fixed(g, p)


def rule_sources(g: PropertyGraph, x: Pattern, y: Pattern, max_reach: int = 0) -> DataFrame:
    """(v): vertices that start both patterns; one walk may serve both."""
    return match(g, x, max_reach).join(match(g, y, max_reach), "v", "left_semi")


def rule_exceptions(g: PropertyGraph, x: Pattern, y: Pattern, max_reach: int = 0) -> DataFrame:
    """(v, tail): sources of x that don't start y, with the ends that y's last label leads to from there (null: none)."""
    missed = cut(match(g, x, max_reach).join(match(g, y, max_reach), "v", "left_anti"))
    if len(y.hops) != 1:
        return missed.withColumn("tail", F.lit(None).cast("long"))
    ends = g.edges.where(F.col("label") == y.hops[0][0]).select(F.col("src").alias("v"), F.col("dst").alias("tail"))
    return missed.join(ends, "v", "left")


def missing_item_report(g: PropertyGraph, x: Pattern, y: Pattern, prefix: str, max_reach: int = 0) -> DataFrame:
    """Exceptions of a rule by reason: the end carries no item of the family ``prefix`` at all (a gap in the data), another one, or there is no end."""
    family = [i for i, s in enumerate(g.items) if s.startswith(prefix)]
    known = g.attrs.where(F.col("item").isin(family)).select(F.col("v").alias("tail"), F.lit(1).alias("known")).distinct()
    out = rule_exceptions(g, x, y, max_reach).join(known, "tail", "left")
    reason = F.when(F.col("tail").isNull(), "no_end").when(F.col("known").isNull(), "gap").otherwise("other")
    return out.groupBy(reason.alias("reason")).agg(F.count_distinct("v").alias("n"))


def bias_check(g: PropertyGraph, groups: list[str], label: str, prefix: str, theta: int = 1, unset: str | None = None) -> DataFrame:
    """For each group item: rules {group} => {} label {item of the family}; number, sums of support and of confidence, and of
    the support of vertices that lack every item of the family ``unset``."""
    item_id = {s: i for i, s in enumerate(g.items)}
    family = [i for i, s in enumerate(g.items) if s.startswith(prefix)]
    members = g.attrs.where(F.col("item").isin([item_id[x] for x in groups])).select("v", F.col("item").alias("grp"))
    lacks = [i for i, s in enumerate(g.items) if unset and s.startswith(unset)]
    has = g.attrs.where(F.col("item").isin(lacks)).select("v", F.lit(1).alias("has")).distinct()
    ends = g.edges.where(F.col("label") == g.labels.index(label)).join(g.attrs.where(F.col("item").isin(family)).select(F.col("v").alias("dst"), "item"), "dst").select(F.col("src").alias("v"), "item").distinct()
    hit = members.join(ends, "v").join(has, "v", "left").groupBy("grp", "item").agg(F.count("*").alias("n"), F.count_if(F.col("has").isNull()).alias("n_unset")).where(F.col("n") >= theta)
    size = members.groupBy("grp").agg(F.count("*").alias("n_group"))
    names = F.broadcast(g.attrs.sparkSession.createDataFrame([(item_id[x], x) for x in groups], "grp int, group string"))
    out = size.join(hit, "grp", "left").groupBy("grp", "n_group").agg(F.count("item").alias("n_rules"), F.coalesce(F.sum("n"), F.lit(0)).alias("sum_support"), F.round(F.coalesce(F.sum(F.col("n") / F.col("n_group")), F.lit(0.0)), 6).alias("sum_confidence"), F.coalesce(F.sum("n_unset"), F.lit(0)).alias("sum_support_unset"))
    return out.join(names, "grp").select("group", "n_group", "n_rules", "sum_support", "sum_confidence", "sum_support_unset")
