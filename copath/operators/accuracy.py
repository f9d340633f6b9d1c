"""Accuracy of approximate runs, and counts that describe a run's output."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from copath.plans.miner import MiningResult


def accuracy(exact: DataFrame, approx: DataFrame) -> DataFrame:
    """n_exact, n_approx, n_both, recall, precision of rules by their texts (x, y); an empty side counts as fully right."""
    a, b = exact.select("x", "y", F.lit(1).alias("e")), approx.select("x", "y", F.lit(1).alias("a"))
    n = a.join(b, ["x", "y"], "full_outer").agg(F.count("e").alias("n_exact"), F.count("a").alias("n_approx"), F.count_if(F.col("e").isNotNull() & F.col("a").isNotNull()).alias("n_both"))
    share = lambda whole: F.when(F.col(whole) == 0, 1.0).otherwise(F.round(F.col("n_both") / F.col(whole), 6))
    return n.withColumns({"recall": share("n_exact"), "precision": share("n_approx")})


def differences(exact: DataFrame, approx: DataFrame) -> DataFrame:
    """side, x, y: rules that only the exact run has (missed), only the approximate one (added), or both (kept), by their texts."""
    a, b = exact.select("x", "y"), approx.select("x", "y")
    named = lambda side, df: df.select(F.lit(side).alias("side"), "x", "y")
    return named("missed", a.exceptAll(b)).unionByName(named("added", b.exceptAll(a))).unionByName(named("kept", a.intersectAll(b)))


def count_outputs(r: MiningResult) -> DataFrame:
    """kind, len, n of frequent patterns, and the number of unordered rules as kind ``rule``."""
    own = r.patterns().groupBy("kind", "len").agg(F.count("*").alias("n"))
    return own.union(r.pairs.agg(F.count("*").alias("n")).select(F.lit("rule").alias("kind"), F.lit(0).alias("len"), "n"))


def rule_side_types(rules: DataFrame) -> DataFrame:
    """side, n: of unordered rules, how many sides are of length 1, 2, ... or reach; twice the rules in all."""
    kind = F.when(F.col("kind_x") == "reach", F.lit("reach")).otherwise(F.concat(F.lit("length_"), F.col("len_x").cast("string")))
    return rules.groupBy(kind.alias("side")).agg(F.count("*").alias("n"))


def rules_cube(rules: DataFrame) -> DataFrame:
    """Rules by kind of either side, with all subtotals."""
    return rules.cube("kind_x", "kind_y").agg(F.count("*").alias("n"), F.round(F.avg("confidence"), 6).alias("mean_confidence"))


def speedup(baseline_s: float, method_s: float) -> float:
    return baseline_s / method_s if method_s else float("inf")
