"""The dealt operators as queries over whole tables, and the SQL of those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ball_tree, bpe, decontaminate, language_crf, masked_lm, ngram_jaccard, quality, substring_dedup, token_orc, toxicity
from .common import Scratch, crc32_mod, documents

TOKENIZER = "byte_bpe_50k.json"


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(TOKENIZER)


def op1_token_orc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Token ids of every document, written as ORC and read back: position, length and checksum."""
    scratch = Scratch(spark)
    path = scratch.path("tokens")
    token_orc.write_tokens(documents(spark, sf_dir), path, tokenizer_path())
    return scratch.finish(token_orc.token_digests(spark, path))


def op5_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Own BPE encoding of every document, its decoding, and digests of both."""
    path = tokenizer_path()
    coded = bpe.encode(documents(spark, sf_dir), path)
    return bpe.decode(coded, path, keep_ids=True).select(
        "doc_id", F.size("ids").cast("long").alias("n_tokens"),
        F.sha2(F.array_join("ids", ",").cast("binary"), 256).alias("ids_sha256"), F.sha2(F.col("text").cast("binary"), 256).alias("decoded_sha256"),
    )


def op2_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Components of documents whose sets of 3-word shingles have a Jaccard similarity of 0.9 or more."""
    scratch = Scratch(spark)
    return scratch.finish(ngram_jaccard.jaccard_components(documents(spark, sf_dir), scratch=scratch))


def op3_ball_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The five largest integer inner products of every fiftieth vector with all others."""
    scratch = Scratch(spark)
    return scratch.finish(ball_tree.top_products(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), scratch=scratch))


def op4_language_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Language of every document, learned from those whose id's checksum isn't 2 modulo 4."""
    docs = documents(spark, sf_dir)
    model = language_crf.fit(docs, docs.where(crc32_mod("doc_id", 4) != 2).select("doc_id", F.col("lang").alias("label")))
    return language_crf.predict(docs, model).select("doc_id", (crc32_mod("doc_id", 4) == 2).alias("held_out"), "lang_pred", "score")


def _judged(docs: DataFrame, score, fold) -> DataFrame:
    found = docs.select("doc_id", fold.alias("held_out"), score.alias("score"))
    return found.select("doc_id", "held_out", "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).alias("predicted"))


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality of every document, learned from labels whose id's checksum isn't 1 modulo 3."""
    docs, labels = documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = quality.fit(docs, labels.where(crc32_mod("doc_id", 3) != 1).select("doc_id", F.col("quality").alias("label")))
    return _judged(docs, quality.scored(docs, model), crc32_mod("doc_id", 3) == 1)


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity of every document, learned from labels whose id's checksum isn't 0 modulo 5."""
    docs = documents(spark, sf_dir)
    return _judged(docs, toxicity.scored(docs, toxicity_model(spark, docs, sf_dir)), crc32_mod("doc_id", 5) == 0)


def toxicity_model(spark: SparkSession, docs: DataFrame, sf_dir: str) -> toxicity.ToxicityModel:
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return toxicity.fit(docs, labels.where(crc32_mod("doc_id", 5) != 0).select("doc_id", F.col("toxic").alias("label")))


def op8_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which documents hold which benchmark items, with substituted words allowed."""
    return decontaminate.find_contaminated(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op9_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each document without the words of 20-word windows that begin earlier too."""
    scratch = Scratch(spark)
    kept = substring_dedup.dedup_substrings(documents(spark, sf_dir), scratch=scratch)
    return scratch.finish(kept.select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept").cast("binary"), 256).alias("kept_sha256")))


def op10_masked_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Masked pseudo-likelihood of every document under a network trained on all of them."""
    scratch, docs = Scratch(spark), documents(spark, sf_dir)
    return scratch.finish(masked_lm.score(docs, masked_lm.fit(docs, scratch=scratch), scratch=scratch))


QUERIES = {"op1_token_orc": op1_token_orc, "op2_ngram_jaccard": op2_ngram_jaccard, "op3_ball_tree": op3_ball_tree, "op4_language_crf": op4_language_crf, "op5_bpe": op5_bpe, "op6_quality": op6_quality, "op7_toxicity": op7_toxicity, "op8_decontaminate": op8_decontaminate, "op9_substring_dedup": op9_substring_dedup, "op10_masked_lm": op10_masked_lm}
ORACLES: dict[str, str] = {
    "op2_ngram_jaccard": r"""
        WITH RECURSIVE d AS (
            SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
        s AS (
            SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) BETWEEN 1 AND 2 THEN [array_to_string(w, ' ')] ELSE list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]) END) AS g FROM d),
        n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
        both_have AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM s a JOIN s b USING (g) WHERE a.doc_id < b.doc_id GROUP BY 1, 2),
        linked AS MATERIALIZED (SELECT a, b FROM both_have JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * i >= 90 * (x.n + y.n - i)),
        edges AS MATERIALIZED (SELECT a, b FROM linked UNION SELECT b, a FROM linked),
        reach AS (SELECT doc_id AS a, doc_id AS b FROM d UNION SELECT reach.a, edges.b FROM reach JOIN edges ON edges.a = reach.b)
        SELECT d.doc_id AS doc_id, coalesce(n, 0) AS n_shingles, component_id FROM d LEFT JOIN n USING (doc_id) JOIN (SELECT a AS doc_id, min(b) AS component_id FROM reach GROUP BY a) USING (doc_id)
    """,
    "op9_substring_dedup": r"""
        WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
        windows AS (SELECT doc_id, unnest(list_transform(range(1, len(w) - 18), lambda p: {'p': p, 'k': array_to_string(w[p:p + 19], ' ')})) AS x FROM d),
        again AS (SELECT doc_id, p FROM (SELECT doc_id, x.p AS p, row_number() OVER (PARTITION BY x.k ORDER BY doc_id, x.p) AS r FROM windows) WHERE r > 1),
        gone AS (SELECT DISTINCT doc_id, p + j AS p FROM again, range(20) AS t(j)),
        words AS (SELECT doc_id, unnest(w) AS x, generate_subscripts(w, 1) AS p FROM d),
        kept AS (SELECT doc_id, count(*) AS n, string_agg(x, ' ' ORDER BY p) AS t FROM words ANTI JOIN gone USING (doc_id, p) GROUP BY doc_id)
        SELECT d.doc_id AS doc_id, len(w) AS n_words, len(w) - coalesce(n, 0) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256 FROM d LEFT JOIN kept USING (doc_id)
    """,
    "op3_ball_tree": """
        WITH usable AS (
            SELECT vec_id, len(embedding) AS dim, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS v FROM embeddings
            WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(embedding) > 0
              AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
        scored AS (
            SELECT q.vec_id AS query_id, c.vec_id AS vec_id, list_inner_product(q.v, c.v)::BIGINT AS score
            FROM usable q JOIN usable c ON q.vec_id % 50 = 0 AND q.vec_id <> c.vec_id AND q.dim = c.dim)
        SELECT query_id, rank::INT AS rank, vec_id, score
        FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM scored) WHERE rank <= 5
    """,
}
