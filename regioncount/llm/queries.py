"""Queries of the training-data operators, and the SQL beside those that SQL can express."""

from __future__ import annotations

from regioncount.llm import oracles
from regioncount.llm.common import Scratch, table
from regioncount.llm.op10_pii import find
from regioncount.llm.op1_sharding import shard_documents
from regioncount.llm.op2_url import judge
from regioncount.llm.op3_toxicity import score_documents
from regioncount.llm.op4_jaccard import components_of
from regioncount.llm.op5_bpe import digests
from regioncount.llm.op6_tokens import build, recount, sample_edits
from regioncount.llm.op7_quality import quality
from regioncount.llm.op8_html import extract
from regioncount.llm.op9_decontamination import contained


def op1_sharding(spark, sf_dir):
    return shard_documents(table(spark, sf_dir, "documents"), 24)


def op2_url(spark, sf_dir):
    return judge(table(spark, sf_dir, "pages"))


def op3_toxicity(spark, sf_dir):
    return score_documents(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op4_jaccard(spark, sf_dir):
    return components_of(table(spark, sf_dir, "documents"), k=3, pct=90)


def op5_bpe(spark, sf_dir):
    return digests(table(spark, sf_dir, "documents"))


def op6_tokens(spark, sf_dir):
    trees = Scratch(spark).save(build(table(spark, sf_dir, "documents")), "trees")
    return recount(trees.withColumn("edits", sample_edits(trees["text"])), keep_trees=False)


def op7_quality(spark, sf_dir):
    return quality(table(spark, sf_dir, "documents"))


def op8_html(spark, sf_dir):
    return extract(table(spark, sf_dir, "pages"))


def op9_decontamination(spark, sf_dir):
    return contained(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op10_pii(spark, sf_dir):
    return find(table(spark, sf_dir, "documents"))


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    return {
        "op1_sharding": op1_sharding,
        "op2_url": op2_url,
        "op3_toxicity": op3_toxicity,
        "op4_jaccard": op4_jaccard,
        "op5_bpe": op5_bpe,
        "op6_tokens": op6_tokens,
        "op7_quality": op7_quality,
        "op8_html": op8_html,
        "op9_decontamination": op9_decontamination,
        "op10_pii": op10_pii,
        "pipeline": pipeline,
    }


def oracle_sql() -> dict[str, str]:
    return dict(oracles.SQL)
