"""Readers of edge lists and triples, and sinks for what a run gives."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from copath.functions.measures import BASIC
from copath.functions.patterns import STRUCT
from copath.operators import growth
from copath.plans.miner import MiningResult

EDGE = "src long, label string, dst long"


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edges(spark: SparkSession, path: str, kind: str = "csv", **options) -> DataFrame:
    """src, label, dst from csv, json, orc or parquet files."""
    reader = spark.read.options(**options)
    if kind in ("csv", "json"):
        reader = reader.schema(EDGE)
    return reader.format(kind).load(path).select("src", "label", "dst")


def read_triples(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """vertices, attrs, edges of N-Triples-like lines. Objects in angle brackets are vertices, quoted ones are items ``predicate:value``.

    A vertex id is a 62-bit hash of its name; lines that aren't triples are skipped.
    """
    line = r'^\s*<([^>]+)>\s+<([^>]+)>\s+(?:<([^>]+)>|"((?:[^"\\]|\\.)*)"\S*)\s*\.\s*$'
    t = spark.read.text(path).where(F.col("value").rlike(line))
    part = lambda i: F.regexp_extract("value", line, i)
    key = lambda c: F.xxhash64(c).bitwiseAND(F.lit((1 << 62) - 1))
    t = t.select(part(1).alias("s"), part(2).alias("p"), part(3).alias("o"), part(4).alias("text"))
    short = F.element_at(F.split("p", "[/#]"), -1)
    links, facts = t.where("o != ''"), t.where("o = ''")
    edges = links.select(key("s").alias("src"), short.alias("label"), key("o").alias("dst"))
    attrs = facts.select(key("s").alias("v"), F.concat(short, F.lit(":"), "text").alias("item"))
    vertices = t.select(key("s").alias("v")).union(links.select(key("o").alias("v"))).distinct()
    return vertices, attrs, edges


def write_result(r: MiningResult, path: str, kind: str = "parquet") -> None:
    """patterns (by kind and length), matches and rules. Nested columns go as JSON text where the format has none."""
    patterns = r.patterns()
    if kind == "csv":
        patterns = patterns.withColumn("pattern", F.to_json("pattern"))
    patterns.write.mode("overwrite").partitionBy("kind", "len").format(kind).save(f"{path}/patterns")
    r.matches.write.mode("overwrite").format(kind).save(f"{path}/matches")
    r.rules().write.mode("overwrite").format(kind).save(f"{path}/rules")


#: A rule as JSON: both sides' patterns and a map of measures.
RULE_JSON = f"struct<x: {STRUCT}, y: {STRUCT}, measures: map<string, double>>"


def rules_as_json(r: MiningResult) -> DataFrame:
    """rule: one JSON text for each rule, with the patterns' structure (names by number) and its measures."""
    rules, named = r.rules(), r.patterns().select("text", "pattern")
    side = lambda s: growth.checked(named.select(F.col("text").alias(s), F.col("pattern").alias(f"p{s}")), len(r.catalogue.support))
    measures = F.create_map(*[c for m in BASIC for c in (F.lit(m), F.col(m))])
    return rules.join(side("x"), "x").join(side("y"), "y").select(F.to_json(F.struct(F.col("px").alias("x"), F.col("py").alias("y"), measures.alias("measures"))).alias("rule"))


def read_rules_json(spark: SparkSession, path: str) -> DataFrame:
    """x, y, measures of rules that ``rules_as_json`` wrote as text."""
    return spark.read.text(path).select(F.from_json("value", RULE_JSON).alias("r")).select("r.*")


def save_matches_table(r: MiningResult, name: str, buckets: int = 64) -> None:
    """Matches as a table bucketed by vertex, so that later joins on the vertex need no shuffle."""
    r.matches.write.mode("overwrite").bucketBy(buckets, "v").sortBy("v").saveAsTable(name)
