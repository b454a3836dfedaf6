import random

import corpus_pipeline
from seqvault.llm import queries
from seqvault.operators.barrier import barrier

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def test_stages_over_a_table(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, before = docs.columns, docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = barrier(stage(spark, docs, sf), "stage")
        assert docs.columns == columns, name
        if name != "mixing":
            assert 0.5 * before < docs.count() <= before
    last = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
    assert last.count() == docs.count() == corpus_pipeline.run(spark, sf).count()
    assert {"doc_id", "start", "n_tokens", "ids_crc32"} == set(last.columns)


def test_planted_cases(spark, sf):
    rnd = random.Random(6)
    bench = spark.read.parquet(f"{sf}/benchmark.parquet").first()["text"]
    words = [f"plain{i}" for i in range(500)]
    make = lambda n: " ".join(rnd.choices(words, k=n))
    clean = [make(300) for _ in range(5)]
    near = clean[0].split(" ")
    near[100] = "changed"
    rows = [(10_000_000 + i, t, "en", "src0", 0) for i, t in enumerate([*clean, clean[1], " ".join(near), f"{make(40)} {bench} {make(40)}"])]
    rows += [(None, None, None, None, None), (10_000_001, clean[1], "en", "src0", 0)]
    docs = spark.createDataFrame(rows, DOCS)
    kept = barrier(corpus_pipeline.drop_near_duplicates(spark, docs, sf), "kept")
    texts = [r["text"] for r in kept.collect()]
    assert sorted(t for t in texts if t in clean) == sorted(clean) and " ".join(near) not in texts
    left = [r["text"] for r in corpus_pipeline.drop_leaks(spark, kept, sf).collect()]
    assert len(left) == len(texts) - 1 and not any(t and bench in t for t in left)
    assert corpus_pipeline.mix_sources(spark, kept, sf).count() > 0
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs.limit(0), sf).count() == 0


def test_queries_name_every_operator():
    names = list(queries.queries())
    assert [n.split("_")[0] for n in names] == [f"op{i}" for i in range(1, 11)]
    assert set(queries.oracle_sql()) <= set(names)
