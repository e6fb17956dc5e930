"""Driver queries of the document operators against DuckDB, and the pipeline against its stages."""

import duckdb
import pytest

import corpus_pipeline
from steepdraw.llm import bpe, near_dedup, quality_rules, registry
from steepdraw.llm.common import table


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_twin(spark, tiny, name):
    con = duckdb.connect()
    for t in ("documents", "benchmark", "pages"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tiny}/{t}.parquet'")
    df = registry.queries()[name](spark, tiny)
    cols = sorted(df.columns)
    got = sorted(tuple(map(str, (r[c] for c in cols))) for r in df.collect())
    out = con.execute(registry.oracle_sql()[name])
    names = [c[0] for c in out.description]
    assert sorted(names) == cols
    assert got == sorted(tuple(str(r[names.index(c)]) for c in cols) for r in out.fetchall())


@pytest.mark.parametrize("name", ["op1_html_extract", "op3_url_filter", "op4_bpe", "op7_langid", "op8_near_dedup", "op10_quality_rules"])
def test_one_row_each(spark, tiny, name):
    source, key = ("pages", "page_id") if name in ("op1_html_extract", "op3_url_filter") else ("documents", "doc_id")
    got = registry.queries()[name](spark, tiny)
    assert sorted(r[0] for r in got.select(key).collect()) == sorted(r[0] for r in table(spark, tiny, source).select(key).collect())


def test_pipeline_equals_its_parts_by_hand(spark, tiny):
    docs = table(spark, tiny, "documents")
    kept = {r.doc_id for r in quality_rules.assess(docs).where("kept").collect()}
    lined = corpus_pipeline.lines(spark, docs.where(docs.doc_id.isin(list(kept))), tiny)
    classes = {r.doc_id: r.class_id for r in near_dedup.classes(lined).collect()}
    left = {r.doc_id: r.text for r in lined.collect() if classes[r.doc_id] == r.doc_id}
    items = [" ".join((r.text or "").lower().split()) for r in table(spark, tiny, "benchmark").collect()]
    clean = {d: t for d, t in left.items() if not any(i in " ".join(t.lower().split()) for i in items)}
    own = bpe.Codec(registry.tokenizer_path())
    got = {r.doc_id: r.n_tokens for r in corpus_pipeline.run(spark, tiny).collect()}
    assert got == {d: len(own.encode(t)) for d, t in clean.items()}
    assert lined.columns == docs.columns
