"""Vertices merged by their items: most questions about a vertex are questions about its kind."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property, reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copath.plans.meter import together
from copath.plans.store import cut
from copath.sources.graphs import PropertyGraph

#: The item that every vertex has where patterns may ask for none.
ANY = -1
#: Tables of kinds are broadcast up to this many kinds.
BROADCAST_KINDS = 50_000
#: The ends of edges are broadcast with their kinds up to this many vertices.
BROADCAST_ENDS = 250_000


@dataclass
class Kinds:
    """attrs(sid, item) of each distinct item set; own(v, sid) of each vertex; plain(src, label, dst): the graph's edges."""

    attrs: DataFrame
    own: DataFrame
    plain: DataFrame
    n: int
    #: Whether several runs share these counts.
    shared: bool = False

    @cached_property
    def ins(self) -> DataFrame:
        """(label, v, n): edges into each vertex."""
        return cut(self.plain.groupBy("label", F.col("dst").alias("v")).agg(F.count("*").alias("n")))

    @cached_property
    def outs(self) -> DataFrame:
        """(label, v): vertices with an edge of the label."""
        return cut(self.plain.select("label", F.col("src").alias("v")).distinct())

    @cached_property
    def ends(self) -> DataFrame:
        """(label, sid, n): edges by the kind of their end."""
        return cut(self.ins.join(self.own, "v").groupBy("label", "sid").agg(F.sum("n").alias("n")))

    @cached_property
    def starts(self) -> DataFrame:
        """(label, sid, n): vertices with an edge of the label by their kind."""
        return cut(self.outs.join(self.own, "v").groupBy("label", "sid").agg(F.count("*").alias("n")))

    @cached_property
    def weights(self) -> DataFrame:
        """(sid, n): vertices of each kind."""
        return cut(self.own.groupBy("sid").agg(F.count("*").alias("n")))

    @cached_property
    def item_ends(self) -> DataFrame:
        """(label, item, n): edges by the items of their end. Edges by kind are few rows for each kind."""
        n = self.ends.join(self.attrs, "sid").groupBy("label", "item").agg(F.sum("n").alias("n"))
        return cut(n) if self.shared else n

    @cached_property
    def item_starts(self) -> DataFrame:
        """(item, label, n): vertices with an edge of the label by their items."""
        n = self.starts.join(self.attrs, "sid").groupBy("item", "label").agg(F.sum("n").alias("n"))
        return cut(n) if self.shared else n

    @cached_property
    def far(self) -> int:
        """Largest in-degree."""
        return self.ins.groupBy("v").agg(F.sum("n").alias("n")).agg(F.max("n")).first()[0] or 0

    @cached_property
    def far_by_label(self) -> dict[int, int]:
        """Largest in-degree under each label."""
        return {r.label: r.n for r in self.ins.groupBy("label").agg(F.max("n").alias("n")).collect()}

    @cached_property
    def followers(self) -> set[tuple[int, int]]:
        """Pairs of labels the second of which leaves a vertex that the first leads to."""
        return self.follow(self.ins, self.outs)

    def follow(self, ins: DataFrame, outs: DataFrame) -> set[tuple[int, int]]:
        pairs = ins.select("v", F.col("label").alias("a")).join(outs.select("v", F.col("label").alias("b")), "v").groupBy("a", "b").count()
        return {(r.a, r.b) for r in pairs.collect()}

    @cached_property
    def met(self) -> DataFrame:
        """Edges of all labels with the kind of the end."""
        return self.meet(sorted(self.far_by_label))

    def prepare(self) -> Kinds:
        """With all counts of the graph made."""
        together(lambda: self.ins, lambda: self.outs, lambda: self.weights)
        together(lambda: self.ends, lambda: self.starts)
        return self

    def share(self) -> Kinds:
        """With all that runs of any threshold ask of the graph made once."""
        self.shared = True
        self.prepare()
        together(lambda: self.item_ends, lambda: self.item_starts, lambda: self.far, lambda: self.followers, lambda: self.met)
        return self

    def edges(self, labels: list[int]) -> DataFrame:
        """(src, label, dst, sid): edges of some labels with the kind of the end (null: no items)."""
        return self.met.where(F.col("label").isin(labels)) if self.shared else self.meet(labels)

    def meet(self, labels: list[int]) -> DataFrame:
        """The same, written. Edges whose labels have few ends stay in their order."""
        few, room = [], BROADCAST_ENDS
        for n, label in sorted((r["count"], r.label) for r in self.ins.where(F.col("label").isin(labels)).groupBy("label").count().collect()):
            if n > room:
                break
            few.append(label)
            room -= n
        parts = []
        for own, hint in ((few, F.broadcast), ([x for x in labels if x not in few], lambda df: df)):
            if own or not parts and not labels:
                of = F.col("label").isin(own)
                kind = self.own.join(self.ins.where(of).select("v").distinct(), "v", "left_semi").withColumnRenamed("v", "dst")
                parts.append(self.plain.where(of).join(hint(kind), "dst", "left").select("src", "label", "dst", "sid"))
        return cut(reduce(DataFrame.union, parts))

    def small(self, df: DataFrame) -> DataFrame:
        """A table with a few rows for each kind, broadcast if there are few kinds."""
        return F.broadcast(df) if self.n <= BROADCAST_KINDS else df

    def holding(self, sets: list[tuple[int, tuple[int, ...]]], name: str) -> DataFrame:
        """(name, sid): kinds that have all items of a set; sets: (number, items), the empty one is ANY."""
        from copath.operators.growth import small_table

        rows = [(k, x, max(1, len(s))) for k, s in sets for x in (s or (ANY,))]
        held = self.attrs.join(small_table(self.attrs, rows, f"{name} int, item int, k int"), "item")
        if any(len(s) > 1 for _, s in sets):
            held = held.groupBy(name, "sid").agg(F.count("*").alias("have"), F.first("k").alias("k")).where("have = k")
        return held.select(name, "sid")


def indexed(g: PropertyGraph) -> PropertyGraph:
    """The graph with its kinds, their counts and the edges between them, for several runs."""
    g.kinds = kinds_of(g).share()
    return g


def kinds_of(g: PropertyGraph, allow_empty: bool = False) -> Kinds:
    """Vertices without items have no kind, unless patterns may ask for no item."""
    if g.kinds is not None and not allow_empty:
        return g.kinds
    per = g.attr_sets()
    if allow_empty:
        per = g.vertices.join(per, "v", "left").select("v", F.concat(F.array(F.lit(ANY)), F.coalesce("items", F.array().cast("array<int>"))).alias("items"))
    per = cut(per)
    kinds = cut(per.select("items").distinct().withColumn("sid", F.monotonically_increasing_id()))
    n = kinds.count()
    own = cut(per.join(F.broadcast(kinds) if n <= BROADCAST_KINDS else kinds, "items").select("v", "sid"))
    return Kinds(kinds.select("sid", F.explode("items").alias("item")), own, g.edges, n)
