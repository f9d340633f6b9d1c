"""Upper bounds on pattern supports from counts of edges and vertices, exact or damped; and the graph reduced by them."""

from __future__ import annotations

from dataclasses import dataclass
from math import log

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copath.functions.patterns import Pattern
from copath.operators.kinds import Kinds, kinds_of
from copath.plans.meter import together
from copath.sources.graphs import PropertyGraph


def edge_item_counts(g: PropertyGraph) -> DataFrame:
    """(label, item, n): edges with the label that end at a vertex with the item."""
    return g.edges.join(g.attrs, g.edges.dst == g.attrs.v).groupBy("label", "item").agg(F.count("*").alias("n"))


def vertex_label_counts(g: PropertyGraph) -> DataFrame:
    """(item, label, n): vertices with the item and an outgoing edge with the label."""
    return g.edges.select(F.col("src").alias("v"), "label").distinct().join(g.attrs, "v").groupBy("item", "label").agg(F.count("*").alias("n"))


def largest_in_degree(g: PropertyGraph) -> int:
    return g.edges.groupBy("dst").count().agg(F.max("count")).first()[0] or 0


def largest_in_degrees(g: PropertyGraph) -> dict[int, int]:
    """Largest in-degree under each label."""
    return {r.label: r.n for r in g.edges.groupBy("label", "dst").count().groupBy("label").agg(F.max("count").alias("n")).collect()}


@dataclass
class Walks:
    """Labels that the hops of frequent patterns can have: at[i] those of hop i + 1, after[label] those that follow one somewhere.

    grow[i][label]: how many sources an edge at hop i + 1 has at most, the product of the largest in-degrees under the labels before it.
    """

    at: list[set[int]]
    after: dict[int, set[int]]
    grow: list[dict[int, int]]
    exact: bool = True

    def enough(self, i: int, label: int, n: int, theta: float) -> bool:
        """Whether n ends may have enough sources at hop i + 1. Estimates from samples may be over any bound."""
        return label in self.at[i] and (not self.exact or n * self.grow[i][label] >= theta - 1e-9)

    @property
    def labels(self) -> list[int]:
        return sorted(set().union(*self.at))

    def hops(self, label: int, most: int) -> int:
        """How many hops of one label a walk takes at most (0: no limit known): one if no edge of the label follows another."""
        return most if label in self.after.get(label, ()) else 1

    def ends(self, t: Targets, hops: int) -> list[tuple[int, int]]:
        """(label, item): the ends that a frequent pattern can have, reach patterns of ``hops`` hops among them."""
        fixed = {(label, x) for i in range(len(self.at)) for (label, x), n in t.ends.items() if self.enough(i, label, n, t.theta) and t.tail_ok(i + 1, label, x)}
        return sorted(fixed.union(self.reach_ends(t, hops)))

    def reach_ends(self, t: Targets, hops: int) -> list[tuple[int, int]]:
        """Those of reach patterns. Estimates from samples may pass where the bound of one hop doesn't."""
        return sorted((label, x) for label, x in t.ends if label in self.at[0] and t.reach_tail_ok(label, x, self.hops(label, hops) if self.exact else hops))


def walks(k: Kinds, own: DataFrame, heads: DataFrame, labels: list[int], least: float, max_len: int, hops: int, exact: bool = True) -> Walks:
    """First labels that a head has enough sources with, of own(v, sid, w) and heads(sid, pid); labels that follow a label, from all edges."""
    outs = k.outs.where(F.col("label").isin(labels))
    # Where all vertices count, those that ``useful`` drops have no part in a head that is frequent with a label.
    by_kind = k.starts.where(F.col("label").isin(labels)) if exact else outs.join(own, "v").groupBy("label", "sid").agg(F.sum("w").alias("n"))
    enough = by_kind.join(heads, "sid").groupBy("label", "pid").agg(F.sum("n").alias("n")).where(F.col("n") >= least - 1e-9)
    at, after = [{r.label for r in enough.select("label").distinct().collect()}], {}
    if at[0] and (max_len > 1 or hops != 1):
        first = labels if max_len > 2 else sorted(at[0])
        for a, b in k.followers if k.shared else k.follow(k.ins.where(F.col("label").isin(first)), outs):
            if a in first and b in labels:
                after.setdefault(a, set()).add(b)
    far = k.far_by_label if max_len > 1 and after else {}
    grow = [dict.fromkeys(at[0], 1)]
    for _ in range(max_len - 1):
        grow.append({})
        for a in at[-1]:
            for b in after.get(a, ()):
                grow[-1][b] = max(grow[-1].get(b, 0), grow[-2][a] * far[a])
        at.append(set(grow[-1]))
    return Walks(at, after, grow, exact)


@dataclass
class Targets:
    """Counts and degrees, at vocabulary size; tests of single ends and starts against theta.

    A length-i pattern that ends in (label, item) has at most edges * d^(i-1) sources, d the largest in-degree;
    one with an item before its i-th label has at most vertices * d^(i-1). Damping replaces d^(i-1) by d^(psi (i-1)) in
    the first bound only, so that it loses patterns but never adds one.
    """

    theta: float
    degree: int
    ends: dict[tuple[int, int], int]
    starts: dict[tuple[int, int], int]
    psi: float = 1.0
    by_label: dict[int, int] | None = None

    def _grow(self, hops: int, psi: float, labels=None) -> float:
        """log of d^(psi * hops), or of the product of the labels' own degrees (labels unknown: the largest one each hop)."""
        if self.by_label is not None and labels is None:
            return psi * hops * log(max([1, *self.by_label.values()]))
        if self.by_label is not None:
            return psi * sum(log(max(1, self.by_label.get(x, 0))) for x in labels)
        return psi * hops * log(max(1, self.degree))

    def tail_ok(self, i: int, label: int, item: int, before: tuple[int, ...] | None = None) -> bool:
        n = self.ends.get((label, item), 0)
        return n > 0 and log(n) + self._grow(i - 1, self.psi, before) >= log(self.theta) - 1e-12

    def step_ok(self, i: int, item: int, label: int, before: tuple[int, ...] | None = None) -> bool:
        n = self.starts.get((item, label), 0)
        return n > 0 and log(n) + self._grow(i - 1, 1.0, before) >= log(self.theta) - 1e-12

    def reach_tail_ok(self, label: int, item: int, hops: int) -> bool:
        """Sound for up to ``hops`` equal labels: the bounds of all lengths add up. No limit on hops: any edge will do."""
        n = self.ends.get((label, item), 0)
        if not n or not hops:
            return n > 0
        d = max(1, self.by_label.get(label, 0) if self.by_label is not None else self.degree)
        step, logs = self.psi * log(d), []
        for j in range(hops):
            logs.append(j * step)
            if log(n) + logs[-1] >= log(self.theta):
                return True
        top = max(logs)
        return log(n) + top + log(sum(2.718281828459045 ** (x - top) for x in logs)) >= log(self.theta) - 1e-12

    @property
    def tails(self) -> set[int]:
        return {item for _, item in self.ends}


def target_tables(g: PropertyGraph, theta: float, psi: float | None = None, bound: str = "global", kinds: Kinds | None = None, max_len: int | None = None, hops: int = 0) -> Targets:
    """The bounds' counts. With ``max_len``, only those that can pass for patterns of that length, or ``hops`` equal labels, leave the cluster."""
    k = kinds or kinds_of(g)
    psi = 1.0 if psi is None else psi
    k.prepare()
    far, ends, starts = max(1, k.far), k.item_ends, k.item_starts
    if max_len is not None:
        if hops:
            ends = ends.where(F.col("n") >= theta / far ** (psi * (max(max_len, hops) - 1)) / hops - 1e-9)
        starts = starts.where(F.col("n") >= theta / far ** (max_len - 1) - 1e-9)
    jobs = [ends.collect, starts.collect, lambda: k.far_by_label if bound == "per_label" else None]
    at_ends, at_starts, by_label = together(*jobs)
    return Targets(theta, far, {(r.label, r.item): r.n for r in at_ends}, {(r.item, r.label): r.n for r in at_starts}, psi, by_label)


def target_labels(t: Targets, max_len: int, hops: int) -> list[int]:
    """Labels with an end and a start that can be part of a frequent pattern of length one or more."""
    starts = {label for item, label in t.starts if t.step_ok(max_len, item, label)}
    return sorted({label for label, item in t.ends if label in starts and (t.tail_ok(max_len, label, item) or t.reach_tail_ok(label, item, hops))})


def target_items(t: Targets, max_len: int, hops: int) -> list[tuple[int, int]]:
    """(label, item): ends that an edge of a target label can have in a frequent pattern."""
    labels = set(target_labels(t, max_len, hops))
    return sorted((label, item) for label, item in t.ends if label in labels and (t.tail_ok(max_len, label, item) or t.reach_tail_ok(label, item, hops)))


def reduce_graph(g: PropertyGraph, t: Targets, max_len: int, hops: int) -> PropertyGraph:
    """Without edges whose label can't be part of a frequent pattern of length one or more; items and vertices stay."""
    if not max_len:
        return g
    used = target_labels(t, max_len, hops)
    if len(used) == len(g.labels):
        return g
    return PropertyGraph(g.vertices, g.attrs, g.edges.where(F.col("label").isin(used)) if used else g.edges.limit(0), g.items, g.labels, g._n)


def useful(k: Kinds, own: DataFrame, t: Targets) -> DataFrame:
    """Rows of own(v, sid, w) with a target item and an outgoing edge with a target label; no other vertex starts a pattern of length one or more."""
    labels = sorted({label for (item, label) in t.starts if t.step_ok(1, item, label)})
    items = sorted({item for (item, label) in t.starts if t.step_ok(1, item, label)})
    if not labels:
        return own.limit(0)
    kinds = k.small(k.attrs.where(F.col("item").isin(items)).select("sid").distinct())
    return own.join(kinds, "sid", "left_semi").join(k.outs.where(F.col("label").isin(labels)).select("v"), "v", "left_semi")


def damping_loss(supports: list[tuple[Pattern, int]], exact: Targets, psi: float) -> list[tuple[Pattern, int, float, bool]]:
    """(pattern, support, share c of support in its last end's edges, lost): a frequent pattern is lost when theta > support * d^(psi (i-1)) / c."""
    out = []
    for p, n in supports:
        if p.reach or not p.hops:
            continue
        label, tail = p.hops[-1]
        edges = min(exact.ends.get((label, x), 0) for x in tail)
        c = n / edges if edges else float("inf")
        bound = edges * max(1, exact.degree) ** (psi * (len(p.hops) - 1))
        out.append((p, n, c, bound < exact.theta - 1e-9))
    return out
