"""The queries of the training-data operators and the pipeline, on the smallest tables."""

import re
import sys

import duckdb
import pytest

sys.path.insert(0, __file__.rsplit("/tests/", 1)[0])

from groupstream.llm import queries as llm  # noqa: E402


@pytest.mark.parametrize("name", sorted(llm.oracle_sql()))
def test_same_rows_as_sql(spark, small, name):
    con = duckdb.connect()
    for t in ("documents", "embeddings", "conversations"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    df = llm.queries()[name](spark, small)
    cursor = con.execute(llm.oracle_sql()[name])
    columns = [c[0] for c in cursor.description]
    order = [columns.index(c) for c in df.columns]
    assert sorted(repr(tuple(r)) for r in df.collect()) == sorted(repr(tuple(r[i] for i in order)) for r in cursor.fetchall())


def test_one_query_for_each_operator():
    names = list(llm.queries())
    assert [sum(n.startswith(f"op{k}_") for n in names) for k in range(1, 11)] == [1] * 10 and "pipeline" in names


@pytest.mark.parametrize("name", ["op1_substring_dedup", "op4_shard", "op5_suffix_dedup", "op6_ngram_score", "op7_simhash_near_dedup", "op8_quality"])
def test_one_row_for_each_document(spark, small, name):
    rows = llm.queries()[name](spark, small).collect()
    ids = [r[0] for r in spark.read.parquet(f"{small}/documents.parquet").select("doc_id").collect()]
    assert sorted(r.doc_id for r in rows) == sorted(ids)


def test_pipeline(spark, small):
    import corpus_pipeline

    docs = spark.read.parquet(f"{small}/documents.parquet")
    out = corpus_pipeline.run(spark, small)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality", "near_duplicates", "decontamination", "mixing", "sharding"]
    rows = out.collect()
    known = {r.doc_id: r.text for r in docs.collect()}
    assert rows and all(known[r.doc_id] == r.text for r in rows)
    # One of the exact copies is left at most, none of what repeats a benchmark item, and few of what is labelled bad.
    texts = {}
    for r in rows:
        texts.setdefault(r.text, set()).add(r.doc_id)
    assert all(len(ids) == 1 for t, ids in texts.items() if len((t or "").split()) >= 5)
    items = [" ".join(re.findall(r"\w+", r.text.lower())) for r in spark.read.parquet(f"{small}/benchmark.parquet").collect()]
    said = {r.doc_id: " ".join(re.findall(r"\w+", (r.text or "").lower())) for r in rows}
    assert not any(i in t for t in said.values() for i in items if i)
    labels = spark.read.parquet(f"{small}/labels.parquet").collect()
    ids = {r.doc_id for r in rows}
    good, bad = ({r.doc_id for r in labels if r.quality == q} for q in (1, 0))
    assert len(bad & ids) <= 0.25 * len(bad) and good & ids
    assert sorted({(r.shard, r.slot) for r in rows}) == sorted((r.shard, r.slot) for r in rows)
