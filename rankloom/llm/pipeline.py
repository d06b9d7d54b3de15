"""From raw documents to training shards, in five stages; corpus_pipeline.py at the top of the repository offers them.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; its result is
written as Parquet and read again as the docs of the next one. All but the last
return the columns of documents.

Edge cases: null and empty texts, null and repeated doc_ids, very long texts, extra
columns and empty tables pass every stage as its operator's module says: empty texts
have a score, are no copies of each other, hold no item, have no tokens and size 1.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from rankloom.llm.common import load, written
from rankloom.llm.decontaminate import decontaminate_stage
from rankloom.llm.jaccard import dedupe_stage
from rankloom.llm.mixing import mix_stage
from rankloom.llm.quality import quality_stage
from rankloom.llm.sharding import shard_documents


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the byte-level classifier does not reject; without labels of both classes, all share one score."""
    return quality_stage(docs, load(spark, sf_dir, "labels"))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies (five-word shingles, similarity of 0.8 or more): that of the smallest doc_id, a null one last."""
    return dedupe_stage(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item; an empty benchmark takes none out."""
    return decontaminate_stage(docs, load(spark, sf_dir, "benchmark"))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the target mix serves them; a null source or language is the node "unknown"."""
    return mix_stage(docs)


def sharding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Shard and slot of every row; repeated rows have slots of their own."""
    return shard_documents(docs)


STAGES = [
    ("quality", quality),
    ("near_duplicates", near_duplicates),
    ("decontamination", decontamination),
    ("mixing", mixing),
    ("sharding", sharding),
]

#: The classifier and label propagation have no SQL form; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The shards of documents."""
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
