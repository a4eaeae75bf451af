"""The corpus pipeline: quality, near duplicates, contamination, secrets, encoding.

Each stage takes (spark, docs, sf_dir) and returns a frame; it is written as Parquet to the shared folder and read again as the
next stage's docs. All but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from attrgraph.llm import fmindex, minhash, pieces, quality, secrets
from attrgraph.llm.queries import PIECE_MODEL
from attrgraph.session import materialise


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier rejects go. Rows whose doc_id is null are scored like the others."""
    return quality.keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def keep_one_of_each(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each near-duplicate component the document with the smallest doc_id stays; of rows equal in doc_id, one does.

    Documents without words are linked with nothing and stay; so do rows whose doc_id is null.
    """
    gone = minhash.near_duplicates(docs).where("doc_id is not null and not kept").select("doc_id").distinct()
    kept = docs.join(gone, "doc_id", "left_anti").select(docs.columns)
    named = kept.where("doc_id is not null").dropDuplicates(["doc_id"])
    return named.unionByName(kept.where("doc_id is null"))


def cut_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Spans of benchmark windows are cut out of the texts; n_chars follows the text where it changed."""
    return _counted(docs, fmindex.remove_contamination(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")))


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are replaced by a mark; n_chars follows the text."""
    return _counted(docs, secrets.redact(docs))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, the digests of ids and decoded text, and the ids; a null text counts as empty, so it has no ids."""
    return pieces.encode_and_decode(docs, PIECE_MODEL, with_ids=True).drop("decoded")


def _counted(docs: DataFrame, changed: DataFrame) -> DataFrame:
    return changed.withColumn("n_chars", F.length("text").cast("long")).select(docs.columns) if "n_chars" in docs.columns else changed


STAGES = [("quality", keep_good), ("near_duplicates", keep_one_of_each), ("decontamination", cut_benchmark), ("secrets", redact_secrets), ("pieces", encode)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)


#: The quality stage is a trained model, which SQL can't express.
ORACLE_SQL = None
