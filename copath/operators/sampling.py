"""Stratified sampling of source vertices; estimates and intervals of supports. The graph itself stays whole."""

from __future__ import annotations

from math import sqrt

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from copath.operators.kinds import Kinds
from copath.sources.graphs import PropertyGraph


def strata(g: PropertyGraph, common: list[int], kinds: Kinds | None = None) -> DataFrame:
    """(v, items): the frequent items of each vertex that has one; equal arrays are a stratum. Kinds of vertices, if known, have theirs once."""
    kinds = kinds or g.kinds
    attrs = g.attrs if kinds is None else kinds.attrs.withColumnRenamed("sid", "v")
    kept = attrs.where(F.col("item").isin(common)) if len(common) <= 10_000 else attrs.join(F.broadcast(attrs.sparkSession.createDataFrame([(i,) for i in common], "item int")), "item", "left_semi")
    per = kept.groupBy("v").agg(F.sort_array(F.collect_set("item")).alias("items"))
    return per if kinds is None else kinds.own.join(kinds.small(per.withColumnRenamed("v", "sid")), "sid").select("v", "items")


def draw(v: Column, seed: int) -> Column:
    """A number that orders vertices at random, the same in every engine that has MD5."""
    return F.md5(F.concat(v.cast("string"), F.lit(f"/{seed}")))


def sample_sources(g: PropertyGraph, common: list[int], rho: float, seed: int = 42, mode: str = "quota", kinds: Kinds | None = None) -> DataFrame:
    """(v): of every stratum a share rho. quota: exactly ceil(rho * n), by one window over each stratum, dealt in slices so that
    no stratum is one task; threshold: each vertex by its own hash, without a shuffle by stratum."""
    s = strata(g, common, kinds)
    if mode == "threshold":
        return s.where(F.conv(F.substring(draw(F.col("v"), seed), 1, 8), 16, 10).cast("double") < rho * float(1 << 32)).select("v")
    # The first hex digits cut a stratum into 256 ordered slices; a slice's quota follows from the sizes of those before it.
    s = s.withColumn("d", draw(F.col("v"), seed)).withColumn("slice", F.substring("d", 1, 2))
    sizes = s.groupBy("items", "slice").agg(F.count("*").alias("k"))
    before = F.coalesce(F.sum("k").over(Window.partitionBy("items").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    total = F.sum("k").over(Window.partitionBy("items"))
    quota = sizes.select("items", "slice", (F.ceil(total * rho - 1e-9) - before).alias("left"), "k").where("left > 0")
    ranked = s.join(quota, ["items", "slice"]).withColumn("r", F.row_number().over(Window.partitionBy("items", "slice").orderBy("d", "v")))
    return ranked.where("r <= left").select("v")


def estimate_support(n_sampled: Column, rho: float) -> Column:
    return n_sampled / F.lit(rho)


def stratum_weights(g: PropertyGraph, common: list[int], sampled: DataFrame, kinds: Kinds | None = None) -> DataFrame:
    """(v, weight): size of the vertex's stratum over the number sampled from it; summed over matches it corrects rounded quotas."""
    s = strata(g, common, kinds).join(sampled.withColumn("hit", F.lit(1)), "v", "left")
    w = s.groupBy("items").agg((F.count("*") / F.count("hit")).alias("weight"), F.count("hit").alias("m")).where("m > 0")
    return s.where("hit = 1").join(w, "items").select("v", "weight")


def support_interval(n_match: Column, m: Column, population: Column, z: float = 1.959963984540054, finite: bool = False) -> tuple[Column, Column, Column]:
    """Estimate and bounds of a support from n_match of m sampled vertices; variance with squared deviations over m - 1."""
    x = n_match / m
    s2 = F.when(m > 1, m * x * (1 - x) / (m - 1)).otherwise(F.lit(0.0))
    if finite:
        s2 = s2 * (1 - m / population)
    half = F.sqrt(s2 / m) * z
    return population * x, population * (x - half), population * (x + half)


def interval(n_match: int, m: int, population: int, z: float = 1.959963984540054) -> tuple[float, float]:
    x = n_match / m
    half = z * sqrt(m * x * (1 - x) / (m - 1) / m) if m > 1 else 0.0
    return population * (x - half), population * (x + half)
