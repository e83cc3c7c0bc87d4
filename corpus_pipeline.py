"""Training-corpus pipeline: toxicity, near duplicates, decontamination, mixing, token output.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of documents.
SQL cannot express the stages (trained models, XXH64, a tokenizer), so ORACLE_SQL is None and the tests compare them
with brute-force versions.

Defined results in every stage: null texts count as empty; an empty table gives an empty one; extra columns pass through,
whatever their names; texts are worked on whole, however long; rows without an id, and different texts under one id, are
judged by themselves.  Repeated rows are scored, judged and mixed alike, and reduced to one by the near-duplicate stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from paircuration.llm import decontaminate, mixing, near_copies, token_output, toxicity
from paircuration.llm.common import scratch, settle


def stage_toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the tagger does not reject (score below 0.7); a score of exactly 0.7 is rejected.

    Without labels of both classes every score is the labelled share of toxic rows.
    """
    return toxicity.remove_toxic(docs, toxicity.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def stage_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of near copies (five-word Jaccard of 0.8 or more), the one with the smallest id.

    Candidates come from the SimHash operator's balls, MinHash bands and an exact prefix join, and all are verified.  Ties in id
    go to the smaller digest of the text; texts without words are copies of each other; rows without an id stay if nothing
    they are copies of has one.
    """
    return near_copies.keep_first(docs)


def stage_decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of which less than a twentieth of the words lies in passages of benchmark items; word-less ones stay."""
    return decontaminate.remove_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def stage_mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document at least once, repeated up to three times to bring the languages to the target shares.

    Without labelled rows there is one domain and every document's rate is the same.
    """
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    labelled = docs.select("doc_id", "lang").join(labels.select("doc_id"), "doc_id", "left_semi")
    mixture = mixing.fit(docs, labelled, mixing.TARGET, growth=1.25, floor=1.0, cap=3.0)
    return mixing.mix(docs, mixture)


def stage_token_output(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids in seekable files, in ascending id order, null ids first; returns what the files hold."""
    files = token_output.write_shards(docs, scratch(spark, "corpus-shards"), token_output.public_tokenizer(), 2)
    return token_output.read_shards(spark, files)


STAGES = [
    ("toxicity", stage_toxicity),
    ("near_duplicates", stage_near_duplicates),
    ("decontamination", stage_decontamination),
    ("mixing", stage_mixing),
    ("token_output", stage_token_output),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each is written as Parquet in the shared folder and read again by the next."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = settle(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
