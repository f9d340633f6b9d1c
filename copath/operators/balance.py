"""Placing source vertices on threads by estimated cost."""

from __future__ import annotations

import heapq
from math import ceil

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from copath.operators.bounds import Targets
from copath.sources.graphs import PropertyGraph


def vertex_cost(g: PropertyGraph, t: Targets) -> DataFrame:
    """(v, cost): outgoing edges with target labels times target items on the vertex; every vertex has a row. An item is a target if it can start or end a frequent hop."""
    labels = sorted({label for item, label in t.starts if t.step_ok(1, item, label)})
    tails = sorted({item for label, item in t.ends if t.tail_ok(1, label, item)} | {item for item, label in t.starts if t.step_ok(1, item, label)})
    out = g.edges.where(F.col("label").isin(labels)).groupBy(F.col("src").alias("v")).agg(F.count("*").alias("d")) if labels else g.vertices.limit(0).withColumn("d", F.lit(0).cast("long"))
    own = g.attrs.where(F.col("item").isin(tails)).groupBy("v").agg(F.count("*").alias("a")) if tails else g.vertices.limit(0).withColumn("a", F.lit(0).cast("long"))
    return g.vertices.join(out, "v", "left").join(own, "v", "left").select("v", (F.coalesce("d", F.lit(0)) * F.coalesce("a", F.lit(0))).alias("cost"))


def greedy_by_vertex(costs: list[int], n: int) -> list[tuple[int, int]]:
    """(index, part): the costliest vertex left goes to the least loaded part that isn't full (cap: vertices over parts, rounded up)."""
    cap = ceil(len(costs) / n) if costs else 0
    heap = [(0, p) for p in range(n)]
    held, out = [0] * n, []
    for i in sorted(range(len(costs)), key=lambda i: (-costs[i], i)):
        load, p = heapq.heappop(heap)
        out.append((i, p))
        held[p] += 1
        if held[p] < cap:
            heapq.heappush(heap, (load + costs[i], p))
    return out


def greedy_by_cost(histogram: list[tuple[int, int]], n: int) -> list[tuple[int, int, int, int]]:
    """(cost, from, to, part): the same greedy on (cost, count), as vertices of one cost are alike. Runs of ranks, from 1."""
    total = sum(k for _, k in histogram)
    cap = ceil(total / n) if total else 0
    load, room, out = [0] * n, [cap] * n, []
    for cost, count in sorted(histogram, reverse=True):
        give = [0] * n
        left = count
        if cost > 0:
            # Largest level up to which every part can be filled without running out of vertices.
            lo, hi = min(load), max(load) + cost * count
            taken = lambda level: [min(r, max(0, -(-(level - x) // cost))) for x, r in zip(load, room)]  # noqa: E731, B023
            while lo < hi:
                mid = (lo + hi + 1) // 2
                if sum(taken(mid)) <= count:
                    lo = mid
                else:
                    hi = mid - 1
            give = taken(lo)
            left -= sum(give)
        heap = [(load[p] + cost * give[p], p) for p in range(n) if give[p] < room[p]]
        heapq.heapify(heap)
        while left:
            x, p = heapq.heappop(heap)
            k = min(left, room[p] - give[p]) if cost == 0 else 1
            give[p] += k
            left -= k
            if give[p] < room[p]:
                heapq.heappush(heap, (x + cost * k, p))
        at = 1
        for p in range(n):
            if give[p]:
                out.append((cost, at, at + give[p] - 1, p))
                at += give[p]
                load[p] += cost * give[p]
                room[p] -= give[p]
    return out


def ranked(costs: DataFrame) -> DataFrame:
    """(v, cost, r): rank among vertices of one cost, counted through 256 slices so that no cost is one task."""
    s = costs.withColumn("slice", F.pmod(F.xxhash64("v"), F.lit(256)))
    sizes = s.groupBy("cost", "slice").agg(F.count("*").alias("k"))
    before = F.coalesce(F.sum("k").over(Window.partitionBy("cost").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    start = sizes.select("cost", "slice", before.alias("start"))
    return s.join(start, ["cost", "slice"]).select("v", "cost", (F.col("start") + F.row_number().over(Window.partitionBy("cost", "slice").orderBy("v"))).alias("r"))


def balance_greedy(costs: DataFrame, n: int) -> DataFrame:
    """(v, cost, part). Only the histogram of costs comes to the driver."""
    runs = greedy_by_cost([(r.cost, r.k) for r in costs.groupBy("cost").agg(F.count("*").alias("k")).collect()], n)
    table = F.broadcast(costs.sparkSession.createDataFrame(runs, "cost long, lo long, hi long, part int")) if runs else None
    if table is None:
        return costs.withColumn("part", F.lit(0))
    return ranked(costs).join(table, "cost").where("r >= lo AND r <= hi").select("v", "cost", "part")


def balance_hash(costs: DataFrame, n: int) -> DataFrame:
    return costs.withColumn("part", F.pmod(F.xxhash64("v"), F.lit(n)).cast("int"))


def balance_snake(costs: DataFrame, n: int) -> DataFrame:
    """Vertices in falling order of cost, dealt forwards and backwards in turn."""
    above = {r.cost: r.k for r in costs.groupBy("cost").agg(F.count("*").alias("k")).collect()}
    rows, at = [], 0
    for c in sorted(above, reverse=True):
        rows.append((c, at))
        at += above[c]
    if not rows:
        return costs.withColumn("part", F.lit(0))
    start = F.broadcast(costs.sparkSession.createDataFrame(rows, "cost long, base long"))
    m = F.pmod(F.col("base") + F.col("r") - 1, F.lit(2 * n))
    return ranked(costs).join(start, "cost").select("v", "cost", F.when(m < n, m).otherwise(2 * n - 1 - m).cast("int").alias("part"))


PLANS = {"greedy": balance_greedy, "hash": balance_hash, "snake": balance_snake}


def place(df: DataFrame, plan: DataFrame, n: int, key: str = "v") -> DataFrame:
    """Rows moved to the partition of their vertex's part."""
    return df.join(plan.select(F.col("v").alias(key), "part"), key).repartitionById(n, F.col("part"))


def balance_report(plan: DataFrame) -> DataFrame:
    """n_parts, max_load, mean_load, imbalance, max_vertices of a plan."""
    per = plan.groupBy("part").agg(F.sum("cost").alias("load"), F.count("*").alias("k"))
    return per.agg(F.count("*").alias("n_parts"), F.max("load").alias("max_load"), F.round(F.avg("load"), 6).alias("mean_load"), F.round(F.max("load") / F.avg("load"), 6).alias("imbalance"), F.max("k").alias("max_vertices"))
