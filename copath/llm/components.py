"""Connected components of links, without gathering links or components anywhere.

Each round joins every node's larger neighbours to its smallest one, then its smaller
neighbours to the smallest of them. Both steps keep components and turn them into
stars around their smallest node within a logarithmic number of rounds.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copath.llm.store import drop_table, write_table


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, root) for each linked node but the roots themselves; root is the smallest node of the component.

    Rounds end when one changes nothing. Self links, repeated links, both directions and nulls (dropped) are allowed; no links give no rows.
    """
    spark = links.sparkSession
    x, y = F.col(a), F.col(b)
    start = links.where(x != y).select(F.greatest(x, y).alias("u"), F.least(x, y).alias("v")).distinct()
    edges, path = write_table(start)
    state = None
    while True:
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == state or not now[0]:
            break
        state = now
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        below = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(below, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v")
        after, new = write_table(small.union(below.select("u", F.col("m").alias("v"))).distinct())
        drop_table(spark, path)
        edges, path = after, new
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))


def local_roots(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Smallest index reachable from each of n nodes by the links (a[i], b[i])."""
    root = np.arange(n)
    while len(a):
        ra, rb = root[a], root[b]
        live = ra != rb
        if not live.any():
            break
        a, b = a[live], b[live]
        low, high = np.minimum(ra[live], rb[live]), np.maximum(ra[live], rb[live])
        np.minimum.at(root, high, low)
        while True:
            nxt = root[root]
            if (nxt == root).all():
                break
            root = nxt
    return root
