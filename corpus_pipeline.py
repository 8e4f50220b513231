"""A corpus pipeline over `documents`: quality rules, line dedup, near-dedup, substring dedup, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame that is written as Parquet and read
again as the next stage's docs. All but the last return the columns of `documents`; n_chars follows
the text that a stage leaves.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from foldstar.llm import lines, packing, quality, similar, substrings
from foldstar.llm.shared import filtered, released, settled, table


def _sized(before: DataFrame, after: DataFrame) -> DataFrame:
    """`after` with the columns of `before`, n_chars counted anew where there is one."""
    if "n_chars" in before.columns:
        kind = before.schema["n_chars"].dataType
        after = after.withColumn("n_chars", F.length("text").cast(kind))
    return after.select(*[F.col(f"`{c}`") for c in before.columns])


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules reject go."""
    return quality.keep_good(docs)


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later copies of repeated line runs are deleted; documents left without a line go."""
    return _sized(docs, lines.deduped(docs))


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group linked by a similarity of 0.8 or more on five-word shingles stays."""
    return similar.keep_first(docs)


def substring_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages that a document with a smaller id has are cut; documents left without a word go."""
    cut = _sized(docs, substrings.cleaned(docs))
    return filtered(cut, F.col("text").rlike(r"[^ \t-\r]"))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of at most 1024 tokens placed in sequences."""
    return packing.packed_text(docs)


STAGES = [
    ("quality rules", quality_stage),
    ("line dedup", line_stage),
    ("near-dedup", near_duplicate_stage),
    ("substring dedup", substring_stage),
    ("packing", packing_stage),
]


#: SQL has no XXH64, no tokenizer and no automata: the tests hold every stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES[:-1]):
        before, docs = docs, settled(lambda: stage(spark, docs, sf_dir), f"stage-{i}")  # noqa: B023
        released(before)
    return STAGES[-1][1](spark, docs, sf_dir)
