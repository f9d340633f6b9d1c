"""The SQL surface: views of a run, and functions on patterns."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from copath.functions.patterns import STRUCT
from copath.plans.miner import MiningResult
from copath.sources.graphs import name_table

_PATTERN = STRUCT.upper().replace("KIND", "kind").replace("HEAD", "head").replace("HOPS", "hops").replace("LABEL", "label").replace("ITEMS", "items")


@F.udtf(returnType="subset array<int>")
class Subsets:
    """Non-empty subsets of a sorted item array, up to a size."""

    def eval(self, items: list, most: int):
        from itertools import combinations

        own = sorted(set(items or []))
        for k in range(1, min(len(own), most) + 1):
            for s in combinations(own, k):
                yield (list(s),)


@F.pandas_udf(DoubleType())
def gini(loads: pd.Series) -> float:
    """Unevenness of loads, from 0 (all equal) towards 1; nulls don't count, no load at all is even."""
    x = loads.dropna().astype("float64").sort_values().to_numpy()
    total = x.sum()
    if not len(x) or not total:
        return 0.0
    ranks = pd.RangeIndex(1, len(x) + 1).to_numpy()
    return float((2 * (ranks * x).sum() / (len(x) * total)) - (len(x) + 1) / len(x))


def _escaped(name: str) -> str:
    """SQL for a name with its special characters escaped; backslashes count twice in SQL text, and twice again in a pattern."""
    return rf"regexp_replace({name}, '([\\\\,|{{}}*])', '\\\\$1')"


def register(spark: SparkSession, r: MiningResult | None = None) -> None:
    """Functions covers, is_unit, dominates, pattern_text, gini and subsets; with a run, the views g_vertices, g_attrs, g_edges, g_items, g_labels, patterns, matches, rules."""
    sql = lambda name, takes, gives, body: spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({takes}) RETURNS {gives} RETURN {body}")
    sql("covers", "items ARRAY<INT>, wanted ARRAY<INT>", "BOOLEAN", "size(array_except(wanted, items)) = 0")
    sql("is_unit", f"p {_PATTERN}", "BOOLEAN", "size(p.head) = 1 AND forall(p.hops, h -> size(h.items) = 1)")
    steps = "zip_with(slice(p.hops, 1, greatest(size(q.hops), 1)), q.hops, (a, b) -> b IS NULL OR (a.label = b.label AND size(array_except(b.items, a.items)) = 0))"
    sql("dominates", f"p {_PATTERN}, q {_PATTERN}", "BOOLEAN", f"(p.kind = q.kind OR size(q.hops) = 0) AND size(q.hops) <= size(p.hops) AND size(array_except(q.head, p.head)) = 0 AND (size(q.hops) = 0 OR forall({steps}, x -> coalesce(x, false)))")
    shown = lambda s: f"concat('{{', array_join(transform({s}, i -> {_escaped('element_at(items, i + 1)')}), ','), '}}')"
    hop = f"array(concat({_escaped('element_at(labels, h.label + 1)')}, if(p.kind = 'reach', '*', '')), {shown('h.items')})"
    sql("pattern_text", f"p {_PATTERN}, items ARRAY<STRING>, labels ARRAY<STRING>", "STRING", f"concat_ws('|', {shown('p.head')}, flatten(transform(p.hops, h -> {hop})))")
    spark.udtf.register("subsets", Subsets)
    spark.udf.register("gini", gini)
    if r is not None:
        g = r.graph
        views = {"g_vertices": g.vertices, "g_attrs": g.attrs, "g_edges": g.edges, "g_items": name_table(spark, "item", g.items), "g_labels": name_table(spark, "label", g.labels), "patterns": r.patterns(), "matches": r.matches, "rules": r.rules()}
        for name, df in views.items():
            df.createOrReplaceTempView(name)
