"""A training corpus from raw documents: five stages, each written as Parquet and read again by the next.

Toxic documents go; repeated line chunks go (and documents that little or nothing is left of); one document of
each near-duplicate group stays; documents contaminated by the benchmark go; the rest is packed into sequences.

Line dedup comes before the near duplicates, so what it leaves of a near copy is the lines that differ.  A
document that loses four fifths of its bytes or more to earlier ones is such a copy, and goes as a whole.

Defined cases: null and empty texts score the bias alone, have no lines, no words and no windows, stay, and are
packed as their end id; rows with a null id stay; rows that share an id are judged together by the near-duplicate
stage and one by one elsewhere; extra columns pass through all stages but the last, whatever their names; tables
without rows give none.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from peakcover.llm import common, decontaminate, line_dedup, minhash, packing, toxicity


#: A document stays if one in so many of its bytes is left.
LEAST_LEFT = 5


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.drop_toxic(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without repeated lines; one goes if no line but blank ones is left, or less than a fifth of its bytes."""
    sized = docs.withColumn("__whole", F.octet_length("text"))
    out = line_dedup.dedup_lines(sized, counts=("__lines", "__removed")).where(f"__removed = 0 OR (trim(replace(text, '\\n', ' ')) <> '' AND octet_length(text) * {LEAST_LEFT} >= __whole)")
    fresh = {"n_chars": F.when(F.col("__removed") > 0, F.length("text")).otherwise(F.col("n_chars"))} if "n_chars" in docs.columns else {}
    return out.withColumns(fresh).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return minhash.drop_near_duplicates(docs, percent=80)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs)


STAGES = [("toxicity", drop_toxic), ("line_dedup", drop_repeated_lines), ("minhash", drop_near_duplicates), ("decontaminate", drop_contaminated), ("packing", pack)]

#: A trained score and greedy packing have no SQL form; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = common.staged(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
