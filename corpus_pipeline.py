"""A corpus pipeline of five stages, each on all documents that the stage before kept.

STAGES lists (name, function); a function takes (spark, docs, sf_dir) and returns a DataFrame, which run() writes as
Parquet to the shared folder and reads again as the next one's docs. All stages but the last return the columns of
documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dyngraph.llm import decontaminate, fuzzy_lines, simhash_tiles, string_kernel, vector_packing
from dyngraph.llm.common import checked, free_name, table, written

LEAST_LANGUAGE_SCORE = 0.35
BROADCAST_ROWS = 500_000


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents whose language is known: not "und", and a score of at least LEAST_LANGUAGE_SCORE.

    A document is looked up by its doc_id; where rows share one, it stays if any of them is accepted. Rows with a
    null doc_id are judged as documents of one id.
    """
    seen = string_kernel.identify(docs, string_kernel.learn(docs))
    key = free_name(docs, "rejected_id")
    accepted = F.coalesce((F.col("lang_pred") != string_kernel.UNKNOWN) & (F.col("score") >= LEAST_LANGUAGE_SCORE), F.lit(False))
    rejected = written(seen.groupBy(F.col("doc_id").alias(key)).agg(F.max(accepted).alias("accepted")).where("not accepted").select(key), "rejected-ids")
    # few are rejected, so that no text has to be sent
    return docs.join(checked(rejected, BROADCAST_ROWS), F.col("doc_id").eqNullSafe(F.col(key)), "left_anti")


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Removes lines that repeat an earlier one; n_chars follows the text. Documents stay, if need be without text."""
    cleaned = fuzzy_lines.clean(docs)
    length = F.length("text").cast(docs.schema["n_chars"].dataType) if "n_chars" in docs.columns else None
    return cleaned if length is None else cleaned.withColumn("n_chars", F.when(F.col("text").isNull(), F.col("n_chars")).otherwise(length))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps of each group of near duplicates (Jaccard similarity 0.8 of their five-word shingles) the document with the smallest doc_id.

    Tiles of SimHashes and MinHash bands find the candidates; the shingles decide.

    Rows that share that doc_id and the text are one document. Rows with a null doc_id stay.
    """
    found = simhash_tiles.similar_documents(docs.where(F.col("doc_id").isNotNull()).select("doc_id", "text"))
    keep = found.where(F.col("doc_id") == F.col("component_id")).select("doc_id").distinct()
    kept = docs.join(keep, "doc_id", "left_semi").dropDuplicates(["doc_id", "text"])
    return kept.unionByName(docs.where(F.col("doc_id").isNull()))


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold a benchmark item."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark")).select(*docs.columns)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs all documents into sequences."""
    return vector_packing.pack_documents(docs)


STAGES = [
    ("language_id", identify_language),
    ("line_dedup", drop_repeated_lines),
    ("simhash_dedup", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("packing", pack_sequences),
]

#: Kernels, fingerprints and token ids have no SQL form; tests compare the line and document stages, not run(), with brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
