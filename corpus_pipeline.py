"""The training-data pipeline: quality rules, line dedup, near-dedup, mixing, packing.

Each stage takes (spark, docs, sf_dir) and works on all that the stage before
kept; all but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from arcfield.deploy import save
from arcfield.llm import curriculum, line_dedup, packing, quality_rules, simhash
from arcfield.llm.queries import table, tokenizer_path


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules and the learned decision list keep.

    Null and empty texts have no words and go; rows of a repeated or null id
    are judged each by its text; without labels the base decides alone.
    """
    return quality_rules.judge(docs, table(spark, sf_dir, "labels")).where("kept").select(*docs.columns)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the lines that an earlier one holds; ``n_chars`` follows the text.

    A null text stays null; rows without an id keep their lines and claim none;
    rows that share an id count as one document.
    """
    out = line_dedup.dedup_lines(docs)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast("long"))
    return out.select(*docs.columns)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, that of the smallest id, of each group of SimHash links.

    Rows that share that id, and rows without an id, stay; null and empty texts
    are copies of each other.
    """
    return simhash.keep_one(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as their source's target takes them, in curriculum order.

    A null source is a source; a null or empty text has no words and is taken as
    often as its place in the stream says; rows that share id and source take
    places of their own.
    """
    return curriculum.mix(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of token windows in the mixture's proportions.

    Targets are the token shares of the sources as the mix returned them.  A null
    text is one end token; repeated rows and copies are packed each.
    """
    return packing.digest(docs, tokenizer_path())


STAGES = [("quality rules", quality), ("line dedup", lines), ("simhash near-dedup", near_copies), ("curriculum mix", mix), ("mixture packing", pack)]

#: Fingerprint links and learned rules are beyond SQL; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what one stage returns is stored before the next reads it."""
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = save(docs, f"stage-{k}")
    return docs
