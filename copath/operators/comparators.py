"""What the miner is compared with: exhaustive search, correlated subgraph pairs, and classic item sets."""

from __future__ import annotations

from collections import defaultdict

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copath.functions.patterns import Pattern, escape, subsets
from copath.sources.graphs import PropertyGraph, name_table


def brute_force(vertices, attrs, edges, max_len: int, max_reach: int, theta: float, min_len: int = 1, max_items: int | None = None, allow_empty: bool = False):
    """Every frequent pattern and every rule pair of a tiny graph, by enumeration without pruning. allow_empty: sets of no items count too.

    attrs: (v, item) and edges: (src, label, dst) with numbers. Gives {pattern: sources} and {(p, q): n} for p < q.
    """
    items, out = defaultdict(set), defaultdict(set)
    for v, i in attrs:
        items[v].add(i)
    for s, label, d in edges:
        out[s].add((label, d))
    sets = {v: [()] * allow_empty + list(subsets(tuple(sorted(items[v])), max_items)) for v in vertices}
    found: dict[Pattern, set] = defaultdict(set)
    for v in vertices:
        states = {(Pattern(h), v) for h in sets[v]}
        for p, _ in states:
            found[p].add(v)
        for _ in range(max_len):
            states = {(Pattern(p.head, (*p.hops, (label, s))), d) for p, u in states for label, d in out[u] for s in sets[d]}
            for p, _ in states:
                found[p].add(v)
        for label in {x for x, _ in out[v]}:
            seen, front, k = set(), {v}, 0
            while front and (not max_reach or k < max_reach):
                k += 1
                front = {d for u in front for x, d in out[u] if x == label} - seen
                seen |= front
            for d in seen:
                for h in sets[v]:
                    for s in sets[d]:
                        found[Pattern(h, ((label, s),), True)].add(v)
    frequent = {p: s for p, s in found.items() if len(s) >= theta}
    own = sorted((p for p in frequent if len(p.hops) >= min_len), key=repr)
    pairs = {}
    for i, p in enumerate(own):
        for q in own[i + 1 :]:
            n = len(frequent[p] & frequent[q])
            if n >= theta and not p.dominates(q) and not q.dominates(p):
                pairs[p, q] = n
    return frequent, pairs


def correlated_pairs(g: PropertyGraph, theta: int, k: int, h: int = 0, max_edges: int = 2) -> DataFrame:
    """Top k pairs of frequent path-shaped subgraphs of one or two edges by the number of places where both occur.

    An analogue of a search for correlated subgraph pairs, on graphs with one item for each vertex. The frequency of a subgraph
    is the least number of distinct vertices at any of its positions; with h = 0 a place is a shared vertex, else
    a vertex with both within h edges, directions ignored. Ties by text.
    """
    spark = g.attrs.sparkSession
    item = name_table(spark, "item", [escape(s) for s in g.items]).withColumnRenamed("name", "iname")
    label = name_table(spark, "label", [escape(s) for s in g.labels]).withColumnRenamed("name", "lname")
    a = g.attrs.join(item, "item").select("v", "iname")
    e = g.edges.join(label, "label").select("src", "lname", "dst")
    one = e.join(a.select(F.col("v").alias("src"), F.col("iname").alias("a")), "src").join(a.select(F.col("v").alias("dst"), F.col("iname").alias("b")), "dst")
    one = one.select("src", "dst", "a", F.concat(F.lit("{"), "a", F.lit("}|"), "lname", F.lit("|{"), "b", F.lit("}")).alias("text"), F.concat(F.lit("|"), "lname", F.lit("|{"), "b", F.lit("}")).alias("more"))
    # Position images, distinct before the second edge joins: a pattern's places are vertices, not walks.
    single = one.select("text", F.lit(0).alias("pos"), F.col("src").alias("v")).union(one.select("text", F.lit(1).alias("pos"), F.col("dst").alias("v"))).distinct()
    left = one.select(F.col("text").alias("t1"), F.col("src").alias("x"), F.col("dst").alias("y"))
    right = one.select(F.col("more").alias("t2"), F.col("src").alias("y"), F.col("dst").alias("z"))
    starts = left.join(right.select("t2", "y").distinct(), "y").select(F.concat("t1", "t2").alias("text"), F.lit(0).alias("pos"), F.col("x").alias("v"))
    middles = left.select("t1", "y").distinct().join(right.select("t2", "y").distinct(), "y").select(F.concat("t1", "t2").alias("text"), F.lit(1).alias("pos"), F.col("y").alias("v"))
    ends = left.select("t1", "y").distinct().join(right, "y").select(F.concat("t1", "t2").alias("text"), F.lit(2).alias("pos"), F.col("z").alias("v"))
    images = (single.union(starts).union(middles).union(ends) if max_edges > 1 else single).distinct()
    freq = images.groupBy("text", "pos").agg(F.count("*").alias("n")).groupBy("text").agg(F.min("n").alias("frequency")).where(F.col("frequency") >= theta)
    at = images.join(freq.select("text"), "text", "left_semi").select("text", "v").distinct()
    near = at
    for _ in range(h):
        both = g.edges.select(F.col("src").alias("v"), F.col("dst").alias("w")).union(g.edges.select(F.col("dst").alias("v"), F.col("src").alias("w")))
        near = near.union(near.join(both, "v").select("text", F.col("w").alias("v"))).distinct()
    pairs = near.select("v", F.col("text").alias("x")).join(near.select("v", F.col("text").alias("y")), "v").where("x < y").groupBy("x", "y").agg(F.count("*").alias("correlation"))
    return pairs.orderBy(F.desc("correlation"), "x", "y").limit(k)


def itemsets_mllib(g: PropertyGraph, theta: int, n: int) -> DataFrame:
    """Frequent item sets by MLlib's FP-growth: items (sorted array), support."""
    from pyspark.ml.fpm import FPGrowth

    model = FPGrowth(itemsCol="items", minSupport=max(0.0, (theta - 0.5) / n), minConfidence=1.0).fit(g.attr_sets())
    return model.freqItemsets.select(F.sort_array("items").alias("items"), F.col("freq").alias("support"))
