"""A corpus from raw documents: rules, near-duplicate removal, decontamination, mixing, shards.

Results by case, in every stage: an empty table gives no rows; columns beyond those used, whatever
their names, pass through all stages but the last as they are.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from geopages.llm._common import Scratch, table
from geopages.llm.decontaminate import drop_contaminated
from geopages.llm.mixing import mixed
from geopages.llm.ngram_join import keep_one_of_each_group
from geopages.llm.quality_rules import keep_good
from geopages.llm.sharding import shard


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules keep. A null or empty text goes; rows that share a doc_id are judged each by its own text; equal rows stay or go together."""
    return keep_good(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest doc_id of each group of similar texts (five-word shingles, Jaccard similarity 0.8); a null doc_id comes after all others, equal rows are one, texts without words are all kept."""
    return keep_one_of_each_group(docs, shingle=5, percent=80)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which no window of a benchmark text occurs. A null or wordless text is kept; rows that share a doc_id are judged each by its own text."""
    return drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents in the order of the schedule. A null source, or one without a target, belongs to the rest; equal rows stand one after another."""
    return mixed(docs)


def sharding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each document went: (doc_id, shard_id, shard_rows, shard_level, position); positions follow the order of the mixture, equal rows have one each."""
    return shard(docs, position=True)


STAGES = [("quality", quality), ("near_duplicates", near_duplicates), ("decontamination", decontamination), ("mixing", mixing), ("sharding", sharding)]

#: Groups of similar documents are the closure of a relation over all pairs, and shards follow file sizes: no SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in turn over ``documents``, each one's rows written and read again for the next."""
    docs = table(spark, sf_dir, "documents")
    scratch = Scratch(spark, "pipeline")
    for i, (name, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        docs = out if i == len(STAGES) - 1 else scratch.put(out, name)
    return docs
