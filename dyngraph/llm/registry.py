"""Queries of the corpus operators, and their SQL twins where SQL can express them."""

from __future__ import annotations

from dyngraph.llm import brown_lm, column_bwt, decontaminate, fuzzy_lines, quality_ftrl, shard_ring, simhash_tiles, string_kernel, term_topk, vector_packing
from dyngraph.llm.common import table


def op1_hash_ring(spark, sf_dir):
    return shard_ring.shard_documents(table(spark, sf_dir, "documents"))


def op2_decontamination(spark, sf_dir):
    return decontaminate.contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op3_quality(spark, sf_dir):
    return quality_ftrl.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op4_brown_lm(spark, sf_dir):
    return brown_lm.evaluate(table(spark, sf_dir, "documents"))


def op5_simhash(spark, sf_dir):
    return simhash_tiles.near_duplicates(table(spark, sf_dir, "documents"))


def op6_passages(spark, sf_dir):
    return column_bwt.report(table(spark, sf_dir, "documents"))


def op7_packing(spark, sf_dir):
    return vector_packing.pack_documents(table(spark, sf_dir, "documents"))


def op8_language(spark, sf_dir):
    return string_kernel.predict(table(spark, sf_dir, "documents"))


def op9_topk(spark, sf_dir):
    return term_topk.top_k(table(spark, sf_dir, "embeddings"))


def op10_lines(spark, sf_dir):
    return fuzzy_lines.decisions(table(spark, sf_dir, "documents"))


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries():
    return {f.__name__: f for f in (op1_hash_ring, op2_decontamination, op3_quality, op4_brown_lm, op5_simhash, op6_passages, op7_packing, op8_language, op9_topk, op10_lines, pipeline)}


def oracle_sql():
    return {"op2_decontamination": decontaminate.ORACLE, "op9_topk": term_topk.ORACLE}
