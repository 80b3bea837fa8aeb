"""From raw documents to packed token sequences, stage by stage."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from gradvb.llm.common import table
from gradvb.llm.decontaminate import drop_contaminated
from gradvb.llm.packing import pack
from gradvb.llm.simhash import drop_near_duplicates
from gradvb.llm.suffix_dedup import strip_repeats
from gradvb.llm.toxicity import drop_toxic, train_toxicity


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity model rejects go.

    Null and empty texts are scored as texts without words; equal texts go or stay together; an empty table gives no rows, a
    table without labels loses none.
    """
    return drop_toxic(docs, train_toxicity(docs, table(spark, sf_dir, "labels")))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (five-word shingles, similarity 0.8) stays, that of the smallest id.

    Null and empty texts are equal texts, and ids that are null come last; of rows equal in id and text one stays, whichever its other
    columns are. An empty table gives no rows.
    """
    return drop_near_duplicates(docs)


def repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Strings of 200 bytes that stand in several places are cut out, in all of them.

    Characters that a cut divides go with it; rows of which only white space is left go; null, empty and
    short texts stay. An empty table gives no rows.
    """
    return strip_repeats(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold ten consecutive words of a benchmark item, or a shorter item, go.

    Null and wordless texts stay, wordless items meet nothing, equal rows go or stay together. An empty table gives no rows.
    """
    return drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """What is left, packed into sequences of 2048 tokens; null and empty texts are an end id, equal rows are packed each, an empty table gives no rows."""
    return pack(docs)


STAGES = [
    ("toxicity", toxicity),
    ("simhash_near_dedup", near_duplicates),
    ("suffix_array_dedup", repeats),
    ("decontamination", decontamination),
    ("packing", packing),
]

#: SQL has no subword model, no XXH64 and no tokenizer; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
    return docs
