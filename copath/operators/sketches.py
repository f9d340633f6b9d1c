"""Supports of rules without joining matches: exact ones from bitmaps, approximate ones from theta sketches."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copath.plans.store import cut


def either_support(matches: DataFrame, pairs: DataFrame) -> DataFrame:
    """x, y, n: how many vertices of matches(pid, v) start x or y, for pairs(x, y); one bitmap a pattern and bucket. Ids must not be negative."""
    maps = cut(matches.groupBy("pid", F.expr("bitmap_bucket_number(v)").alias("b")).agg(F.expr("bitmap_construct_agg(bitmap_bit_position(v))").alias("m")))
    sides = pairs.select("x", "y", F.explode(F.array("x", "y")).alias("pid"))
    both = sides.join(maps, "pid").groupBy("x", "y", "b").agg(F.expr("bitmap_count(bitmap_or_agg(m))").alias("n"))
    return both.groupBy("x", "y").agg(F.sum("n").alias("n"))


def sketched_support(matches: DataFrame, pairs: DataFrame, lg_entries: int = 12) -> DataFrame:
    """x, y, estimate: about how many vertices start x and y. A sketch keeps 2^lg_entries hashes a pattern, whatever its support."""
    of = cut(matches.groupBy("pid").agg(F.expr(f"theta_sketch_agg(v, {lg_entries})").alias("s")))
    side = lambda name: of.select(F.col("pid").alias(name), F.col("s").alias(f"s{name}"))
    return pairs.select("x", "y").join(side("x"), "x").join(side("y"), "y").select("x", "y", F.expr("theta_sketch_estimate(theta_intersection(sx, sy))").alias("estimate"))
