"""The pipeline's stages one after the other, each held against what it should do to its own input."""

import duckdb

import corpus_pipeline
from studymap.llm import queries


def test_pipeline(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    at = {}
    now = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        now = stage(spark, now, small)
        assert now.columns == docs.columns
        now = now.persist()
        at[name] = now
    n = {k: v.count() for k, v in at.items()}
    assert docs.count() >= n["toxicity"] >= n["exact_dedup"] >= n["near_dedup"] > 0
    con = duckdb.connect()
    con.sql(f"CREATE VIEW docs AS SELECT * FROM '{small}/documents.parquet'")
    con.sql(f"CREATE VIEW labels AS SELECT * FROM '{small}/labels.parquet'")
    clean = {r[0] for r in con.sql("SELECT doc_id FROM labels WHERE toxic = 0").fetchall()}
    left = {r["doc_id"] for r in at["toxicity"].select("doc_id").collect()}
    assert len(clean - left) <= 0.03 * len(clean)
    texts = [r["text"] for r in at["exact_dedup"].select("text").collect()]
    assert len(texts) == len(set(texts)) == len({r["text"] for r in at["toxicity"].select("text").collect()})
    out = corpus_pipeline.run(spark, small)
    assert out.count() == n["mix_sources"] and out.where("NOT round_trip").count() == 0


def test_names():
    names = [n.split("_")[0] for n in queries.registry()]
    assert sorted(names) == sorted(f"op{i}" for i in range(1, 11))
