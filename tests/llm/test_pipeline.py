"""The pipeline's stages, its SQL-expressible queries and the registry."""

import duckdb
import public_tokenizers
import pytest
import tiktoken
from conftest import same_rows

import corpus_pipeline
from vecrag.llm import bpe, registry, simhash
from vecrag.llm.common import table

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "language", "near_duplicates", "mixing", "bpe"]
    docs = table(spark, SF, "documents")
    before = {r["doc_id"]: r["text"] for r in docs.collect()}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns, name
        ids = [r["doc_id"] for r in out.select("doc_id").collect()]
        assert ids and set(ids) <= set(before)
        if name == "near_duplicates":
            texts = [before[i] for i in ids]
            assert len(set(texts)) == len(texts)
        docs = out
    last = corpus_pipeline.STAGES[-1][1](spark, docs, SF)
    assert last.count() == docs.count()


def test_run_encodes_what_is_left(spark):
    enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=bpe.read_ranks(public_tokenizers.path("byte_bpe_50k.tiktoken")), special_tokens={})
    texts = {r["doc_id"]: r["text"] for r in table(spark, SF, "documents").collect()}
    rows = corpus_pipeline.run(spark, SF).collect()
    assert 0 < len(rows) and all(r["ids"] == enc.encode_ordinary(texts[r["doc_id"]]) and r["n_tokens"] == len(r["ids"]) and r["decoded"] == texts[r["doc_id"]] for r in rows)
    assert all(r["source"] for r in rows)


def test_near_duplicates_equal_brute_force(spark):
    docs = table(spark, "/root/testdata/sf0.01", "documents")
    given = sorted((r["doc_id"], set(simhash.shingle_set(r["text"]).tolist())) for r in docs.select("doc_id", "text").collect())
    low = {i: i for i, _ in given}
    for n, (i, a) in enumerate(given):
        for j, b in given[:n]:
            if min(len(a), len(b)) >= 0.8 * max(len(a), len(b)) and len(a & b) >= 0.8 * len(a | b) - 1e-9 and low[i] != low[j]:
                keep, drop = sorted((low[i], low[j]))
                low = {k: keep if v == drop else v for k, v in low.items()}
    kept = {r["doc_id"] for r in dict(corpus_pipeline.STAGES)["near_duplicates"](spark, docs, "").select("doc_id").collect()}
    assert kept == {i for i, c in low.items() if i == c}


@pytest.mark.parametrize("name", sorted(registry.SQL))
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for t in ("documents", "embeddings", "conversations"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df = registry.QUERIES[name](spark, SF)
    found = con.execute(registry.SQL[name])
    assert same_rows(df.collect(), df.columns, found.fetchall(), [c[0] for c in found.description])


def test_registry_names():
    for n in range(1, 11):
        assert sum(k.startswith(f"op{n}_") for k in registry.QUERIES) == 1
    assert "pipeline" in registry.QUERIES
