"""Registered queries on the smallest tables: SQL where it can express them, and the pipeline."""

import duckdb
import pytest

import corpus_pipeline
from hypernear.llm import contamination, packing, registry, toxicity
from hypernear.llm.order_minhash import near_duplicates

TABLES = "documents embeddings pages benchmark labels conversations".split()
COLUMNS = {"documents": ["doc_id", "text", "lang", "source", "n_chars"]}


@pytest.mark.parametrize("name", sorted(registry.QUERIES))
def test_query(spark, sf_dir, name):
    found = registry.QUERIES[name](spark, sf_dir)
    columns = sorted(found.columns)
    rows = sorted((tuple(r[c] for c in columns) for r in found.collect()), key=repr)
    assert rows
    if name in registry.ORACLES:
        con = duckdb.connect()
        for table in TABLES:
            con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{sf_dir}/{table}.parquet'")
        result = con.execute(registry.ORACLES[name])
        names = [c[0] for c in result.description]
        assert sorted(names) == columns
        assert rows == sorted((tuple(r[names.index(c)] for c in columns) for r in result.fetchall()), key=repr)


def test_pipeline_stages(spark, sf_dir, tmp_path):
    """Each stage keeps what it should of its own input, and the last holds all tokens of what it got."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    benchmark = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    seen = []
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, sf_dir)
        out.write.parquet(str(tmp_path / name))
        after = spark.read.parquet(str(tmp_path / name))
        seen.append(name)
        if name != "packing":
            assert after.columns == COLUMNS["documents"]
        if name in ("toxicity", "near_dedup", "decontamination"):
            assert 0 < after.count() <= docs.count() and after.exceptAll(docs).isEmpty()
        if name == "near_dedup":
            classes = near_duplicates(docs)
            assert after.count() == classes.select("class_id").distinct().count()
            assert near_duplicates(after).groupBy("class_id").count().filter("count > 1").isEmpty()
        if name == "decontamination":
            assert contamination.leaks(after, benchmark).isEmpty()
        if name == "mixing":
            assert after.groupBy("doc_id").count().filter("count > 2").isEmpty()
        if name == "packing":
            encode = packing.tokenizer(packing.load_ranks(packing.VOCABULARY))
            assert after.agg({"n_tokens": "sum"}).first()[0] == sum(len(encode(r.text)) for r in docs.collect())
        docs = after
    assert seen == ["toxicity", "near_dedup", "decontamination", "mixing", "packing"]
    assert corpus_pipeline.run(spark, sf_dir).count() > 0
    assert toxicity.held_out() is not None


def test_pipeline_edge_cases(spark, sf_dir, documents, no_documents):
    """Nulls in any column, empty and very long texts, repeated rows and clashing columns through each stage, and empty tables through all."""
    docs = documents
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, sf_dir)
        assert stage(spark, no_documents, sf_dir).count() == 0
        if name != "packing":
            assert out.columns == documents.columns
            if name != "mixing":
                assert out.exceptAll(docs).isEmpty()
            ids = [r.doc_id for r in out.select("doc_id").collect()]
            assert name in ("toxicity", "mixing") or len(ids) >= 8  # clean documents stay, among them those without a text or an id
            assert name != "near_dedup" or (ids.count(1) == 1 and ids.count(2) == 0 and None in ids and 4 in ids)
            docs = spark.createDataFrame(out.collect(), out.schema)
        else:
            assert out.count() >= 1 and all(r.n_tokens <= 2048 for r in out.collect())
