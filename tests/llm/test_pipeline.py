"""Each stage against plain code over its own input, and all of them in a row."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from tests.llm.test_operators import DOCS, VOCABULARY, brute_components, brute_removal, messy_rows
from tokenweave.llm import decontaminate, queries, toxicity

SF = "/root/testdata/sf0.001"


def test_whole_run(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = {r.doc_id: r for r in docs.collect()}
    model = queries.toxicity_model(spark, docs, SF)
    kept = [i for i in sorted(rows) if model.scores([rows[i].text])[0] < 0.5]
    kept = [i for (i, _, c) in brute_components([(i, rows[i].text) for i in kept], 5, 80) if i == c]
    texts = brute_removal([(i, rows[i].text) for i in kept])
    texts = {i: t[2] if t[1] else rows[i].text for i, t in texts.items()}
    bench = decontaminate.read_benchmark(spark.read.parquet(f"{SF}/benchmark.parquet"), "item_id", "text", 8, decontaminate.MASKS)
    clean = {}
    for i, t in texts.items():
        words = decontaminate.plain_hashes(t)
        if not any(decontaminate.verify(words, bench.words[k], at, 0.8, 16) for k, at in bench.met(words)):
            clean[i] = t
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(VOCABULARY)
    want = {i: t.encode(x, add_special_tokens=False).ids for i, x in clean.items()}
    got = {r.doc_id: list(r.ids) for r in corpus_pipeline.run(spark, SF).collect()}
    assert got == want and 0 < len(got) < len(rows)


def test_near_copies_by_five_word_shingles(spark):
    """Copies with a word substituted, or text appended, that are under 0.9 over 3 words and over 0.8 over 5."""
    base = [f"w{k}" for k in range(70)]
    rows = [(1, " ".join(base)), (2, " ".join(base[:35] + ["x"] + base[36:])), (3, " ".join(base + [f"y{k}" for k in range(14)])), (4, " ".join(base[:50] + [f"z{k}" for k in range(20)]))]
    docs = spark.createDataFrame([(i, t, "en", "a", len(t)) for i, t in rows], DOCS)
    assert [c for *_, c in brute_components(rows)] == [1, 1, 3, 4]
    assert [c for *_, c in brute_components(rows, 5, 80)] == [1, 1, 1, 4]
    kept = corpus_pipeline.keep_one_of_near_copies(spark, docs, SF)
    assert sorted(r.doc_id for r in kept.collect()) == [1, 4]


@pytest.mark.parametrize("stage", range(5))
def test_stages_on_messy_and_empty_tables(spark, stage):
    name, make = corpus_pipeline.STAGES[stage]
    for rows in (messy_rows(), []):
        docs = spark.createDataFrame(rows, DOCS).withColumn("score", F.lit("x"))
        got = make(spark, docs, SF)
        if stage < 4:
            assert got.columns == docs.columns, name
        n = got.count()
        assert n <= len(rows)
        if rows and stage in (0, 2, 4):
            assert n == len(rows), name
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "ngram_jaccard", "substring_dedup", "decontamination", "bpe"]
    assert isinstance(toxicity.IDENTITY_TERMS, tuple)
