"""Queries that used to make their data up read a given table in Spark's tasks."""

import pytest

from clipflow.catalog import QUERIES


@pytest.mark.parametrize(("name", "table"), [
    ("a_alphabet", "documents"), ("c_alignments", "embeddings"), ("c_brute", "embeddings"), ("c_forward", "embeddings"), ("c_homophone_toy", "documents"), ("c_infeasible", "embeddings"), ("e_compare", "documents"),
])
def test_query_reads_a_table(spark, small, name, table):
    found = QUERIES[name](spark, small)
    assert any(f.endswith(f"{table}.parquet") for f in found.inputFiles())
    assert found.count() > 0


def test_the_examples_keep_their_answers(spark, small):
    n = {(r.label, r["T"]): r.n for r in QUERIES["c_alignments"](spark, small).distinct().collect()}
    assert n["122", 5] == 7 and n["122", 3] == 0
    fare = [(r.string, r.p, r.is_word) for r in QUERIES["c_homophone_toy"](spark, small).where("a = 'fair' AND b = 'fare'").orderBy("string").collect()]
    assert fare == [("faie", 0.25, False), ("fair", 0.25, True), ("fare", 0.25, True), ("farr", 0.25, False)]
