"""The plain method that the pruned one is compared with: only infrequent prefixes are left out.

Every frequent prefix is followed by every label and every set of items that occurs at an end, without bounds
and whether or not a part of the pattern is frequent; reach patterns start from all pairs of vertices that a breadth-first search over
each label joins; rules come from all pairs of patterns. Sources are single vertices.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copath.config import MinerConfig
from copath.functions.patterns import Pattern
from copath.operators.growth import Catalogue, checked, frequent_keys, small_table, union
from copath.operators.kinds import ANY
from copath.plans.store import cut


@dataclass
class Work:
    """attrs(v, item), edges(src, label, dst), weights(v, w) of the sources."""

    attrs: DataFrame
    edges: DataFrame
    weights: DataFrame


def head_matches(work: Work, c: Catalogue) -> DataFrame:
    """(pid, v, w): the frequent item sets of each source."""
    rows = [(c.ids[p], x, max(1, len(p.head))) for p in c.of(0) for x in p.head or (ANY,)]
    held = work.attrs.join(small_table(work.attrs, rows, "pid int, item int, k int"), "item").groupBy("pid", "v").agg(F.count("*").alias("have"), F.first("k").alias("k")).where("have = k")
    return cut(held.join(work.weights, "v").select("pid", "v", "w"))


def item_sets(attrs: DataFrame, most: int | None) -> tuple[DataFrame, int]:
    """(v, items): every set of a vertex's items, up to a size; and how many different ones there are."""
    level = attrs.select("v", F.array("item").alias("items"))
    frames, size = [level], 1
    attrs = attrs.where(F.col("item") != ANY)
    while most is None or size < most:
        level = cut(level.join(attrs, "v").where(F.col("item") > F.element_at("items", -1)).where(F.element_at("items", 1) != ANY).select("v", F.concat("items", F.array("item")).alias("items")))
        if level.isEmpty():
            break
        frames.append(level)
        size += 1
    out = cut(union(frames))
    return out, out.select("items").distinct().count()


def _set(items) -> tuple[int, ...]:
    return tuple(x for x in items if x != ANY)


def grow_fixed(work: Work, c: Catalogue, sets: DataFrame, n_sets: int, n_labels: int, heads: DataFrame, scale: float, cfg: MinerConfig) -> DataFrame | None:
    """(pid, v, w) of all frequent fixed patterns of length 1 to max_len."""
    states = heads.select("pid", F.col("v").alias("src"), F.col("v").alias("tail"), "w")
    ends = sets.withColumnRenamed("v", "dst")
    matches = []
    for i in range(1, cfg.max_len + 1):
        if c.late():
            break
        began, prefixes = time.monotonic(), len(c.of(i - 1))
        hop = states.join(work.edges.withColumnRenamed("src", "tail"), "tail").select("pid", "label", "src", "w", "dst").distinct()
        found = cut(hop.join(ends, "dst").select("pid", "label", "items", "src", "w", F.col("dst").alias("tail")))
        keys = [(pid, label, _set(items), n) for pid, label, items, n in frequent_keys(c, found, ["pid", "label", "items"], scale, True)]
        c.log(f"fixed_{i}", 1, prefixes * n_labels * n_sets, len(keys), began)
        if not keys:
            break
        states = cut(_numbered(c, found, keys, lambda p, label, s: Pattern(p.head, (*p.hops, (label, s)))).select("new", "src", "tail", "w").withColumnRenamed("new", "pid"))
        matches.append(states.select("pid", F.col("src").alias("v"), "w").distinct())
    return cut(union(matches)) if matches else None


def _numbered(c: Catalogue, found: DataFrame, keys: list[tuple], make) -> DataFrame:
    """Rows of frequent keys with their pattern's number, ``new``."""
    number = {s: k for k, s in enumerate(sorted({s for _, _, s, _ in keys}))}
    rows = [(pid, label, number[s], c.add(make(c.names[pid], label, s), n)) for pid, label, s, n in keys]
    spark = found.sparkSession
    names = spark.createDataFrame([(list(s) or [ANY], k) for s, k in number.items()], "items array<int>, sid int")
    return found.join(checked(names, len(number)), "items").join(small_table(found, rows, "pid int, label int, sid int, new int"), ["pid", "label", "sid"])


def grow_reach(work: Work, c: Catalogue, sets: DataFrame, n_sets: int, n_labels: int, heads: DataFrame, scale: float, cfg: MinerConfig) -> DataFrame | None:
    """(pid, v, w) of all frequent reach patterns, from the pairs of vertices that equal labels join."""
    began, hops = time.monotonic(), cfg.hops
    steps = work.edges.select(F.col("src").alias("dst"), "label", F.col("dst").alias("next"))
    start = heads.select(F.col("v").alias("src")).distinct()
    front = cut(work.edges.join(start, "src", "left_semi").select("src", "label", "dst"))
    seen, k = front, 1
    while not hops or k < hops:
        k += 1
        front = front.join(steps, ["dst", "label"]).select("src", "label", F.col("next").alias("dst")).distinct()
        front = cut(front.join(seen, ["src", "label", "dst"], "left_anti"))
        if c.late() or front.isEmpty():
            break
        seen = seen.union(front)
    ends = seen.join(sets.withColumnRenamed("v", "dst"), "dst").select(F.col("src").alias("v"), "label", "items").distinct()
    found = cut(heads.join(ends, "v").select("pid", "label", "items", F.col("v").alias("src"), "w"))
    keys = [(pid, label, _set(items), n) for pid, label, items, n in frequent_keys(c, found, ["pid", "label", "items"], scale)]
    c.log("reach", 1, len(c.of(0)) * n_labels * n_sets, len(keys), began)
    if not keys:
        return None
    return cut(_numbered(c, found, keys, lambda p, label, s: Pattern(p.head, ((label, s),), True)).select(F.col("new").alias("pid"), F.col("src").alias("v"), "w"))
