"""Queries with SQL give DuckDB's rows; all queries run on the given tables."""

import pytest

from regioncount.llm import queries as q

ORACLES = q.oracle_sql()


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query(spark, sf_dir, same_rows, name):
    same_rows(q.queries()[name](spark, sf_dir), ORACLES[name])


@pytest.mark.parametrize("name", ["op2_url", "op3_toxicity", "op4_jaccard", "op5_bpe", "op6_tokens", "op8_html", "op10_pii"])
def test_row_for_every_input(spark, sf_dir, name):
    source = "pages" if name in ("op2_url", "op8_html") else "documents"
    assert q.queries()[name](spark, sf_dir).count() == spark.read.parquet(f"{sf_dir}/{source}.parquet").count()
