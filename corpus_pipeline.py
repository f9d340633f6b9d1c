"""A corpus pipeline of five stages, each on all that its predecessor kept.

toxicity: documents that score 0.3 or more go. line_dedup: lines that are within one word edit of an
earlier line go. simhash_near_dedup: of documents whose five-word shingles are similar by 0.8 or more, the one with
the smallest id stays. benchmark_decontamination: benchmark words go, and documents that consist of them by half.
sentencepiece: piece ids, their number and the text that they decode to are added.
Where a stage changes a text, n_chars follows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from copath.llm import decontaminate, lines, pieces, simhash, toxicity
from copath.llm.store import read_table, write_table


def _counted(docs: DataFrame) -> DataFrame:
    return docs.withColumn("n_chars", F.length("text").cast("long"))


def reject_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    learn = f"NOT ({toxicity.HELD_OUT.format('id')})"
    model = toxicity.train(docs, read_table(spark, sf_dir, "labels"), learn=learn)
    return toxicity.reject(docs, model)


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _counted(lines.clean(docs))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return simhash.keep_first(docs)


def remove_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _counted(decontaminate.clean(docs, read_table(spark, sf_dir, "benchmark")))


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    encoded = pieces.encode(docs, decoded_col="decoded", model=pieces.fit(docs))
    return encoded.withColumn("n_pieces", F.size("piece_ids").cast("long"))


STAGES = [
    ("toxicity", reject_toxic),
    ("line_dedup", dedup_lines),
    ("simhash_near_dedup", drop_near_duplicates),
    ("benchmark_decontamination", remove_benchmark),
    ("sentencepiece", encode_pieces),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each stage's rows are written to the shared folder and read again."""
    docs = read_table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs, _ = write_table(docs)
    return docs


ORACLE_SQL = None
QUERIES = {"pipeline": run}
ORACLES = {"pipeline": ORACLE_SQL}
