"""The ten operators against brute force, on small tables made to be awkward."""

import hashlib
import math
import random
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from tokenweave.llm import ball_tree, bpe, common, decontaminate, graph, language_crf, masked_lm, ngram_jaccard, parts, quality, queries, substring_dedup, token_orc, toxicity

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
VOCABULARY = queries.tokenizer_path()


def tokenizer():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(VOCABULARY)


def prose(rng, n, words=None):
    words = words or [a + b for a in ("th", "er", "on", "an", "re") for b in ("ing", "ed", "at", "is", "o", "en")]
    return " ".join(rng.choice(words) for _ in range(n))


def messy_rows():
    """Nulls in every column, empty, blank and very long texts, repeated rows and ids, copies, ties."""
    rng = random.Random(3)
    base = prose(rng, 120)
    words = base.split()
    near = [" ".join(words[:k] + ["other"] + words[k + 1 :]) for k in (0, 60, 119)]
    rows = [
        (1, base, "en", "a", 1), (2, None, None, None, None), (3, "", "en", "a", 0), (4, " \t\n ", "en", "b", 3), (5, base, "en", "a", 1), (5, base, "en", "a", 1), (6, near[0], "de", "a", 1), (7, near[1], None, "b", 2), (8, near[2], "en", None, 2),
        (9, "one", "en", "a", 3), (10, "one two", "en", "a", 7), (11, "one  two", "en", "a", 8), (12, prose(rng, 30000), "en", "a", 1), (13, "x" * 200000, "fr", "a", 1), (None, base + " tail", "en", "a", 1), (None, None, None, None, None), (15, "<|endoftext|> it's 12 a b  c\r\nd 😀 ñandú ", "es", "a", 1),
        (16, " ".join(words[:40]) + " " + prose(rng, 30), "en", "a", 1), (17, "ONE TWO three four " * 12, "en", "a", 1), (18, "中文 123 !!!", "zh", "a", 1),
    ]
    return rows


@pytest.fixture(scope="module")
def messy(spark):
    df = spark.createDataFrame(messy_rows(), DOCS)
    for name in ("ids", "score", "token", "sig", "n", "doc", "positions", "held_out", "v", "shard"):
        df = df.withColumn(name, F.lit("x"))
    return df.cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


def null_safe(rows):
    return sorted(rows, key=lambda r: tuple((x is None, x) for x in r))


# ---- 1, 5: tokens


def test_token_orc_matches_the_library(spark, messy, tmp_path):
    path = f"file://{tmp_path}/tokens"
    token_orc.write_tokens(messy, path, VOCABULARY, partitions=3)
    t, at, want = tokenizer(), 0, []
    for i, text in sorted([(r[0], r[1] or "") for r in messy_rows()], key=lambda r: (r[0] is not None, r[0] or 0, 0)):
        want.append((i, [*t.encode(text, add_special_tokens=False).ids, 0]))
    got = token_orc.token_digests(spark, path).collect()
    by_sum = Counter((r.doc_id, r.n_tokens, r.ids_crc32) for r in got)
    assert by_sum == Counter((i, len(x), zlib.crc32(np.array(x, "<u4").tobytes())) for i, x in want)
    for r in sorted(got, key=lambda r: r.start):
        assert r.start == at
        at += r.n_tokens
    ids = [r.doc_id for r in sorted(got, key=lambda r: r.start)]
    assert ids == sorted(ids, key=lambda i: (i is not None, i or 0))
    assert {r.doc_id for r in token_orc.read_tokens(spark, path, [9, 12]).collect()} == {9, 12}
    assert "PushedFilters: [In(doc_id" in token_orc.read_tokens(spark, path, [9, 12])._jdf.queryExecution().executedPlan().toString()


def test_token_orc_of_nothing(spark, empty, tmp_path):
    token_orc.write_tokens(empty, f"file://{tmp_path}/t", VOCABULARY)
    assert token_orc.token_digests(spark, f"file://{tmp_path}/t").collect() == []


def test_bpe_matches_the_library(spark, messy):
    t = tokenizer()
    coded = bpe.encode(messy, VOCABULARY)
    got = Counter((r.doc_id, tuple(r.ids), r.text) for r in bpe.decode(coded, VOCABULARY, keep_ids=True).collect())
    want = Counter()
    for i, text, *_ in messy_rows():
        ids = t.encode(text or "", add_special_tokens=False).ids
        want[(i, tuple(ids), t.decode(ids, skip_special_tokens=False))] += 1
    assert got == want


def test_both_coders_on_random_text():
    """Odd white space, marks, contractions and special tokens in all orders, cut into slices of all sizes."""
    rng, t = random.Random(5), tokenizer()
    odd = [*"ab 1'sß \n\t\r\x0b\x1c\x85\u00a0\u3000\u200bé.!<|", "  ", "\n\n", "<|endoftext|>", "'ll", "日本", "word", " the", "...", "$$$", "x.", "é,", "ﬁ.", "𞤀."]
    usual = ["a", "b", "word", "the", ".", ",", "'s", "9", " ", " ", " ", "\n", "\n ", " \n", "  "]
    texts = ["".join(rng.choice(some) for _ in range(rng.randint(0, 14))) for some in (odd, usual) for _ in range(4000)] + [None, ""]
    want = [x.ids for x in t.encode_batch([x or "" for x in texts], add_special_tokens=False)]
    for coder in (bpe.MergeCoder(VOCABULARY), token_orc.LibraryCoder(VOCABULARY)):
        for step in (1, 7, len(texts)):
            n = 300 if step == 1 else len(texts)
            got = [x for a in range(0, n, step) for x in coder.encode(pa.array(texts[a : a + step])[: n - a]).to_pylist()]
            assert got == want[:n]
        assert coder.encode(pa.array(texts), 0).to_pylist() == [[*x, 0] for x in want]
    foreign = [[rng.randrange(50257) for _ in range(5)] for _ in range(500)]
    own = bpe.Decoder(VOCABULARY)
    assert [own.decode(x) for x in foreign] == [t.decode(x, skip_special_tokens=False) for x in foreign]
    assert [(a, n) for a, n in parts.slices(pa.array(["aaaa", None, "b", "cc", "d" * 9, ""]), 4)] == [(0, 2), (2, 2), (4, 1), (5, 1)]


def test_decode_of_null_and_foreign_ids(spark):
    df = spark.createDataFrame([(1, None), (2, []), (3, [64, 999999])], "doc_id long, ids array<int>")
    assert [r.text for r in bpe.decode(df, VOCABULARY).orderBy("doc_id").collect()] == ["", "", "a"]


# ---- 2: Jaccard join


def brute_components(rows, width=3, num=90, den=100):
    sets = []
    for _, text in rows:
        w = (text or "").encode().lower().split()
        sets.append({tuple(w)} if 0 < len(w) < width else {tuple(w[k : k + width]) for k in range(len(w) - width + 1)})
    root = list(range(len(rows)))

    def find(k):
        while root[k] != k:
            k = root[k]
        return k

    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and sets[b] and den * len(sets[a] & sets[b]) >= num * len(sets[a] | sets[b]):
                root[find(a)] = find(b)
    least = {}
    for k, (i, _) in enumerate(rows):
        least.setdefault(find(k), []).append(i)
    smallest = {k: min((i for i in v if i is not None), default=None) for k, v in least.items()}
    return [(i, len(s), smallest[find(k)] if s else i) for k, ((i, _), s) in enumerate(zip(rows, sets))]


def test_jaccard_on_messy_rows(messy):
    got = [tuple(r) for r in ngram_jaccard.jaccard_components(messy).collect()]
    assert null_safe(got) == null_safe(brute_components([r[:2] for r in messy_rows()]))


@pytest.mark.parametrize(("light", "block"), [(64, 256), (3, 4)])
def test_jaccard_families(spark, light, block):
    """Families of near copies just over and under the threshold, chains, and shared passages; heavy paths included."""
    rng, rows = random.Random(9), []
    common_part = prose(rng, 30)
    for family in range(4):
        words = prose(rng, 60 + 25 * family, [f"w{family}{k}" for k in range(60)]).split()
        for _ in range(22):
            w = list(words)
            for _ in range(rng.randint(0, 3)):
                w[rng.randrange(len(w))] = f"e{rng.randrange(10**6)}"
            rows.append((len(rows), " ".join(w) + (" " + common_part if rng.random() < 0.3 else "")))
    rng.shuffle(rows)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = [tuple(r) for r in ngram_jaccard.jaccard_components(df, light=light, block=block).collect()]
    assert sorted(got) == sorted(brute_components(rows))
    assert len({c for *_, c in got}) < len(rows)


@pytest.mark.parametrize(("light", "block"), [(3, 4), (64, 256)])
def test_jaccard_of_many_sets_with_one_prefix(spark, monkeypatch, light, block):
    """Sets that share their rarest shingles, and with them their group, in several components; long texts; narrow columns."""
    monkeypatch.setattr(ngram_jaccard, "COLUMNS", 7)
    rng = random.Random(4)
    rare, usual = [f"r{k}" for k in range(16)], [f"u{k}" for k in range(400)]
    tails = [rng.sample(usual, 100) for _ in range(3)]
    rows = []
    for k in range(60):
        tail = list(tails[k % 3])
        for _ in range(rng.randint(0, 3)):
            tail[rng.randrange(60, 100)] = rng.choice(usual)
        rows.append((k, " ".join(rare + tail)))
    rows += [(1000 + k, " ".join(rng.choice(usual) for _ in range(60))) for k in range(100)]  # makes the usual words usual
    long = prose(rng, 9000, [f"l{k}" for k in range(3000)]).split()
    rows += [(2000, " ".join(long)), (2001, " ".join([*long[:-3], "x", "y"])), (2002, " ".join(long[4000:]))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for width, num in ((1, 80), (3, 80)):
        got = [tuple(r) for r in ngram_jaccard.jaccard_components(df, width=width, num=num, light=light, block=block).collect()]
        assert sorted(got) == sorted(brute_components(rows, width, num))


def test_jaccard_of_nothing(empty):
    assert ngram_jaccard.jaccard_components(empty).collect() == []


def test_components_of_chains_and_stars(spark):
    rng = random.Random(2)
    links = [(k, k + 1) for k in range(1, 60)] + [(100, k) for k in range(101, 140)] + [(7, 7), (101, 100)] + [(rng.randrange(200, 300), rng.randrange(200, 300)) for _ in range(70)]
    got = dict(map(tuple, graph.components(common.Scratch(spark), spark.createDataFrame(links, "a long, b long")).collect()))
    near = {}
    for a, b in links:
        if a != b:
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
    for node in near:
        seen, todo = {node}, [node]
        while todo:
            for x in near[todo.pop()] - seen:
                seen.add(x)
                todo.append(x)
        assert got[node] == min(seen)


# ---- 3: inner products


@pytest.mark.parametrize("shard_rows", [40, 10**6])
def test_top_products(spark, shard_rows):
    rng = np.random.default_rng(1)
    rows = [(int(i), [float(x) for x in rng.normal(0, 0.3, 8)]) for i in range(160)]
    rows += [(i, [0.5] * 8) for i in range(200, 330)] + [(400, None), (401, []), (402, [1.0, None]), (403, [float("nan")] * 8), (404, [float("inf")] * 8), (None, [0.1] * 8), (450, [0.25] * 3), (451, [0.5] * 3), (100, [0.9] * 8)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("v", F.lit(1)).withColumn("id", F.lit(2)).withColumn("score", F.lit(3))
    got = sorted(map(tuple, ball_tree.top_products(df, shard_rows=shard_rows, block_rows=2).collect()))
    good = [(i, [math.floor(256 * x) for x in v]) for i, v in rows if i is not None and v and all(x is not None and math.isfinite(x) for x in v)]
    want = []
    for q in sorted({i for i, _ in good if i % 50 == 0}):
        found = sorted({(-sum(a * b for a, b in zip(v, w)), i, k) for j, v in good if j == q for k, (i, w) in enumerate(good) if i != q and len(v) == len(w)})
        want += [(q, r, i, -s) for r, (s, i, _) in enumerate(found[:5], 1)]
    assert [g for g in got if g[0] != 100] == [w for w in want if w[0] != 100]


def test_top_products_of_nothing(spark):
    assert ball_tree.top_products(spark.createDataFrame([], "vec_id long, embedding array<float>")).collect() == []


# ---- 4, 6, 7: classifiers


LANGUAGES = {"en": ["the", "and", "thing", "with", "that", "ing"], "de": ["der", "und", "schön", "nicht", "ein", "ung"], "es": ["que", "ción", "los", "para", "ñandú", "una"]}


def language_rows(n=60):
    rng = random.Random(8)
    return [(k, prose(rng, rng.randint(8, 40), LANGUAGES[lang]), lang) for k, lang in enumerate(rng.choice(sorted(LANGUAGES)) for _ in range(n))]


def test_language_of_documents_and_words(spark, messy, empty):
    model = language_crf.train(language_rows(), sequences=200)
    rng = random.Random(1)
    held = [(k, prose(rng, 20, LANGUAGES[lang]), lang) for k, lang in enumerate(["en", "de", "es"] * 5)]
    got = {r.doc_id: r for r in language_crf.predict(spark.createDataFrame(held, "doc_id long, text string, lang string"), model).collect()}
    assert all(got[k].lang_pred == lang and 0 <= got[k].score <= 1 for k, _, lang in held)
    mixed = "the thing with that and 123 der und nicht ein schön que los para una ción"
    words = language_crf.label_words(spark.createDataFrame([(1, mixed)], "doc_id long, text string"), model).first().words
    assert [w.lang for w in words] == ["en"] * 5 + [None] + ["de"] * 5 + ["es"] * 5
    odd = {(r.doc_id, r.lang_pred) for r in language_crf.predict(messy, model).collect() if r.lang_pred == "und"}
    assert odd == {(2, "und"), (3, "und"), (4, "und"), (None, "und")}
    assert language_crf.predict(empty, model).collect() == []
    assert language_crf.fit(empty, empty.select("doc_id", F.col("lang").alias("label"))).documents(["text"]) == [("und", 0.0)]


def test_forward_backward_is_exact():
    rng = np.random.default_rng(0)
    n, size = 7, 3
    evidence, transition, start = rng.normal(size=(n, size)), rng.normal(size=(size, size)), rng.normal(size=size)
    begins = np.array([1, 0, 0, 1, 0, 0, 0], bool)
    step, first = np.exp(transition), np.exp(start)
    total = np.zeros((n, size))
    import itertools

    for path in itertools.product(range(size), repeat=n):
        w = 1.0
        for t, k in enumerate(path):
            w *= math.exp(evidence[t, k]) * (first[k] if begins[t] else step[path[t - 1], k])
        for t, k in enumerate(path):
            total[t, k] += w
    assert np.allclose(language_crf.forward_backward(evidence, begins, transition, start), total / total.sum(1, keepdims=True))


def test_quality(spark, messy, empty):
    rng = random.Random(4)
    rows = [(k, prose(rng, 40) if k % 2 else " ".join(w + "%%%" for w in prose(rng, 40).split()), k % 2) for k in range(120)]
    model = quality.train(rows[:80], epochs=6)
    assert all((s >= 0.5) == bool(label) for s, (_, _, label) in zip(model.scores([r[1] for r in rows[80:]]), rows[80:]))
    got = messy.select(quality.scored(messy, model).alias("s")).collect()
    assert len(got) == len(messy_rows()) and all(0 <= r.s <= 1 for r in got)
    assert empty.select(quality.scored(empty, model).alias("s")).collect() == []
    assert 0 <= quality.train([]).scores(["a", None])[1] <= 1


def test_toxicity_counterfactuals(spark, messy, empty):
    """Group names stand in toxic texts only; swapped copies must take their weight away, while insults keep theirs."""
    rng, rows = random.Random(6), []
    for k in range(400):
        text = prose(rng, 30)
        if k % 4 == 0:
            text += f". {rng.choice(['the muslim is', 'you are'])} an {rng.choice(['idiot', 'moron', 'scum'])}"
        rows.append((k, text, int(k % 4 == 0)))
    plain, fair = toxicity.train(rows, counterfactual=0.0), toxicity.train(rows, counterfactual=3.0)
    neutral = "the muslim went home."
    assert fair.scores([neutral])[0] < 0.5 < 0.9 < plain.scores([neutral])[0]
    gap = lambda model: abs(model.scores(["muslim"])[0] - model.scores(["people"])[0])
    assert gap(fair) < 0.02 and gap(plain) > 0.5
    text = prose(rng, 30)
    without, insult, whole = fair.scores([text, text + " idiot", text + ". you are an idiot"])
    assert without < 0.05 and insult > plain.scores([text + " idiot"])[0] and insult > 0.3 and whole > 0.5
    got = messy.select(toxicity.scored(messy, fair).alias("s")).collect()
    assert len(got) == len(messy_rows()) and all(0 <= r.s <= 1 for r in got)
    assert empty.select(toxicity.scored(empty, fair).alias("s")).collect() == []
    assert toxicity.train([]).scores([None, "a"]) == [0.5, 0.5]


def test_counterfactuals_of_texts():
    """One copy for each name in a text, in all its sentences; without a name two names come in, another one each time."""
    rng, names = np.random.default_rng(0), frozenset(["muslim", "woman"])
    made = toxicity.counterfactuals("The muslim ate. A woman, a Muslim; no woman!", names, ("people",), rng)
    tokens = {"the", "muslim", "ate.", "a", "woman,", "muslim;", "no", "woman!"}
    assert made == [(tokens, tokens - {"muslim", "muslim;"} | {"people", "people;"}), (tokens, tokens - {"woman,", "woman!"} | {"people,", "people!"})]
    ((a, b),) = toxicity.counterfactuals("no names", names, ("gay", "old"), rng)
    assert {frozenset(a - {"no", "names"}), frozenset(b - {"no", "names"})} == {frozenset(["gay"]), frozenset(["old"])}


def test_penalty_acts_on_the_given_labels():
    """No labelled text of the small table holds a name; names inserted into copies still change the model."""
    import duckdb

    sf = "/root/testdata/sf0.01"
    rows = duckdb.sql(f"SELECT doc_id, text, toxic FROM '{sf}/documents.parquet' JOIN '{sf}/labels.parquet' USING (doc_id) WHERE text IS NOT NULL AND toxic IS NOT NULL ORDER BY 1, 2").fetchall()
    spread = []
    for strength in (0.0, 1.0):
        model = toxicity.train(rows, counterfactual=strength, l1=0.002)
        x = [p for p in model.scores([*toxicity.IDENTITY_TERMS, *toxicity.NEUTRAL_TERMS])]
        spread.append(np.std(np.log(x) - np.log1p(-np.array(x))))
    assert spread[1] < 0.5 * spread[0]


def test_toxicity_scores_against_plain_code():
    rng = random.Random(3)
    weights = {f: rng.gauss(0, 1) for f in ["wabcde", "pabc", "pabcd", "gbcde", "wxy", "gabcd"]}
    model = toxicity.ToxicityModel(-0.3, weights, cached=2)
    for text in ("abcde", "Abcde! abcd xy xy", "", None, "...", "zabcde  (xy) \n abcdef"):
        words = [w.strip(".!()") for w in (text or "").lower().split()]
        held = {f for w in words if w for f in [f"w{w}", *(f"p{w[:k]}" for k in range(3, min(7, len(w)))), *(f"g{w[k:k+4]}" for k in range(len(w) - 3))]}
        assert model.scores([text])[0] == pytest.approx(1 / (1 + math.exp(0.3 - sum(weights.get(f, 0) for f in held))))


def test_quality_scores_against_plain_code():
    """The mean of the vectors of words, their n-grams and pairs of neighbours, gathered one by one."""
    rng = np.random.default_rng(2)
    model = quality.train([(k, " ".join(rng.choice(["good", "bad", "fine", "%%"], 5)), k % 2) for k in range(20)])
    for text in ("good fine", "bad bad good", "one", "", None):
        tokens, held = (text or "").split(), []
        for t in tokens:
            held.append(model.words[quality.token_hash(t) & ((1 << quality.BITS) - 1)])
            for n in quality.GRAMS:
                for k in range(len(t) + 3 - n):
                    held.append(model.words[common.char_grams([f"<{t}>"[k : k + n]], (n,), quality.BITS, ("", ""))[0][0]])
        for x, y in zip(tokens, tokens[1:]):
            held.append(model.pairs[int(quality.pair_buckets(np.array([quality.token_hash(x), quality.token_hash(y)], np.uint64))[0])])
        hidden = np.mean(np.array(held, float), 0) if held else np.zeros(quality.DIM)
        x = hidden @ model.output + model.bias
        assert model.scores([text])[0] == pytest.approx(math.exp(x[1]) / (math.exp(x[0]) + math.exp(x[1])), rel=1e-4)


@pytest.mark.parametrize("name", ["op4_language_crf", "op6_quality", "op7_toxicity"])
def test_classifier_queries_on_held_out_rows(spark, name):
    """On held-out rows, both labels by themselves, so that a constant answer fails."""
    sf = "/root/testdata/sf0.01"
    got = queries.QUERIES[name](spark, sf).cache()
    assert got.count() == 1000 and got.where("held_out IS NULL").isEmpty()
    held = got.where("held_out")
    if name == "op4_language_crf":
        right = held.join(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang"), "doc_id").groupBy("lang").agg(F.avg(F.expr("int(lang = lang_pred)")).alias("r")).collect()
        assert len(right) == 4 and all(r.r > 0.9 for r in right)
    else:
        label = "quality" if name == "op6_quality" else "toxic"
        both = held.join(spark.read.parquet(f"{sf}/labels.parquet").select("doc_id", label), "doc_id")
        right = {r[label]: r.r for r in both.groupBy(label).agg(F.avg(F.expr(f"int({label} = predicted)")).alias("r")).collect()}
        assert right[0] > 0.95 and right[1] > (0.95 if label == "quality" else 0.6)  # six toxic texts are held out here


# ---- 8: decontamination


def contamination_cases():
    rng = random.Random(12)
    items = [(k, prose(rng, 20 + 5 * k, [f"b{j}" for j in range(90)])) for k in range(6)] + [(6, "alpha beta gamma delta epsilon zeta eta theta iota"), (7, "too short here"), (8, None), (None, "null id " * 10), (3, prose(rng, 25, [f"c{j}" for j in range(90)]))]
    docs, truth = [], {}
    for k, (i, text) in enumerate(items):
        if text is None or i in (None, 7):
            continue
        words = text.split()
        docs.append((10 * k, prose(rng, 50) + " " + text.upper() + ", " + prose(rng, 9)))
        truth[10 * k] = {i}
        if len(words) >= 20:
            for j in range(5, len(words), 9):
                words[j] = "substituted"
            docs.append((10 * k + 1, prose(rng, 50) + " " + " ".join(words) + " " + prose(rng, 9)))
            truth[10 * k + 1] = {i}
            docs.append((10 * k + 2, prose(rng, 20) + " " + " ".join(text.split()[:9]) + " " + prose(rng, 20)))
            truth[10 * k + 2] = set()
    docs += [(900, prose(rng, 300)), (901, None), (902, ""), (903, "too short here"), (None, "null id " * 10), (904, "alpha beta gamma")]
    truth |= {900: set(), 901: set(), 902: set(), 903: set(), None: set(), 904: set()}
    return docs, items, truth


@pytest.mark.parametrize("limit", [10**6, 0])
def test_decontamination(spark, limit):
    docs, items, truth = contamination_cases()
    df, bench = spark.createDataFrame(docs, "doc_id long, text string").withColumn("item_id", F.lit(5)), spark.createDataFrame(items, "item_id long, text string").withColumn("doc_id", F.lit(0))
    got = decontaminate.find_contaminated(df, bench, broadcast_words=limit).collect()
    assert {r.doc_id: set(r["items"]) for r in got} == truth and all(r.contaminated == bool(r["items"]) and all(s.end > s.begin for s in r.spans) for r in got)
    kept = decontaminate.drop_contaminated(df, bench, broadcast_words=limit)
    assert {r.doc_id for r in kept.collect()} == {i for i, x in truth.items() if not x} and kept.columns == df.columns


def test_longest_stretch_is_found():
    """Against all stretches of random agreements, and whole items with a fifth of their words substituted anywhere."""
    rng = np.random.default_rng(5)
    for _ in range(300):
        equal = rng.random(rng.integers(1, 60)) < rng.choice([0.5, 0.8, 0.9])
        both = [(e - b, -b) for b in range(len(equal)) for e in range(b + 1, len(equal) + 1) if 5 * equal[b:e].sum() >= 4 * (e - b)]
        want = max(both, default=(0, 0))
        assert decontaminate.stretch(equal, 0.8) == (-want[1], want[0] - want[1])
    for _ in range(600):
        n = int(rng.integers(12, 60))
        item = decontaminate.plain_hashes(" ".join(f"w{k}" for k in range(n)))
        bench = decontaminate.Benchmark([7], [item], decontaminate.MASKS)
        words = item.copy()
        at = rng.choice(n, int(rng.integers(1, n // 5 + 1)), replace=False)
        words[at] = at
        doc = np.concatenate([np.arange(900, 930, dtype=np.uint64), words, np.arange(950, 970, dtype=np.uint64)])
        found = [decontaminate.verify(doc, item, offset, 0.8, 16) for _, offset in bench.met(doc)]
        assert (30, 30 + n, n - len(at)) in found


def test_masks_miss_no_stretch():
    """The most equal words that a row of places can have without any mask fitting is under 80 % for all lengths."""
    span, masks = max(map(len, decontaminate.MASKS)), [int(m, 2) for m in decontaminate.MASKS]
    best = {0: 0}
    for length in range(1, 121):
        new: dict[int, int] = {}
        for state, equal in best.items():
            for bit in (0, 1):
                places = state << 1 | bit
                if not any(places & m == m for m in masks):
                    kept = places & ((1 << (span - 1)) - 1)
                    new[kept] = max(new.get(kept, 0), equal + bit)
        best = new
        assert length < 12 or 5 * max(best.values()) < 4 * length


def test_decontamination_of_and_by_nothing(spark, empty, messy):
    none = spark.createDataFrame([], "item_id long, text string")
    assert decontaminate.find_contaminated(empty, none).collect() == []
    assert messy.count() == decontaminate.find_contaminated(messy, none).where("NOT contaminated").count()


# ---- 9: substring removal


def brute_removal(rows, width=20):
    """``rows``: id, text. Nulls first, repeats of an id must be repeats of the row."""
    order = sorted({(i is not None, i or 0, t or "") for i, t in rows})
    seen, out = set(), {}
    for known, i, text in order:
        words = text.encode().split()
        gone = [False] * len(words)
        for s in range(len(words) - width + 1):
            w = tuple(words[s : s + width])
            if w in seen:
                gone[s : s + width] = [True] * width
            seen.add(w)
        out[i if known else None] = (len(words), sum(gone), b" ".join(w for w, g in zip(words, gone) if not g).decode())
    return out


@pytest.mark.parametrize("batches", [1, 2, 5])
def test_substring_removal(spark, batches):
    rng = random.Random(21)
    passages = [prose(rng, n, [f"p{j}" for j in range(40)]) for n in (19, 20, 21, 45, 60)]
    rows = []
    for k in range(60):
        parts = [prose(rng, rng.randint(0, 30)) for _ in range(3)]
        parts += [rng.choice(passages) for _ in range(rng.randint(0, 3))]
        rng.shuffle(parts)
        rows.append((rng.choice([k, k * 1000]), " ".join(parts)))
    rows = list(dict(rows).items()) + [(70000, "la " * 90), (70001, "la " * 30), (70002, ""), (70003, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept) for r in substring_dedup.dedup_substrings(df, batches=batches).collect()}
    assert got == brute_removal(rows)


def test_substring_removal_on_messy_rows(messy):
    got = substring_dedup.dedup_substrings(messy, carry=["positions", "lang"]).collect()
    assert len(got) == len(messy_rows()) and all(r.positions == "x" for r in got)
    want = brute_removal([r[:2] for r in messy_rows() if r[0] is not None])
    known = {r.doc_id: r.n_words for r in got if r.doc_id is not None}
    assert known == {i: w[0] for i, w in want.items()}
    nulls = sorted(r.n_removed for r in got if r.doc_id is None)
    assert nulls == [0, 0]  # a null id comes first
    assert {r.doc_id: r.n_removed for r in got}[1] >= 100


def test_index_takes_batches_from_disk_and_compacts(spark, tmp_path):
    """Each day another index object, loaded from its folder; runs grow, are compacted, and further occurrences stay known."""
    rng, path, rows = random.Random(1), f"file://{tmp_path}/index", []
    passages = [prose(rng, 24, [f"p{j}" for j in range(30)]) for _ in range(3)]
    head = " ".join(passages[0].split()[:12])  # fingerprints in many texts, in windows of which none repeats
    runs = []
    for day in range(5):
        scratch = common.Scratch(spark)
        index = substring_dedup.FingerprintIndex.load(spark, scratch, path) if day else substring_dedup.FingerprintIndex(spark, scratch, path, buckets=5, places=4)
        new = [(100 * day + k, rng.choice([head, rng.choice(passages), prose(rng, 9)]) + " " + prose(rng, rng.randint(0, 40)) + " " + rng.choice(passages[day % 3 :])) for k in range(12)]
        rows += new
        marks = {r.doc: (r.begins, r.ends) for r in index.ingest(spark.createDataFrame([(i, 0, t) for i, t in new], "doc long, tie long, text string")).collect()}
        want = brute_removal(rows)
        for i, _ in new:
            assert sum(b - a for a, b in zip(*marks.get(i, ([], [])))) == want[i][1], (day, i)
        index.save()
        runs.append(len(index.live))
        assert sum(len(substring_dedup.unblock(index._table("runs", index.live).toArrow(), "a")[0]) for _ in [0]) > 0
        if day == 1:
            plan = index._matched(spark.createDataFrame([], substring_dedup.BLOCK))._jdf.queryExecution().executedPlan().toString()
            assert plan.count("Exchange") == 1 and "Bucketed: true" in plan  # history stays where it is
        index.close()
    assert runs == [1, 2, 1, 2, 1]


def test_substring_removal_of_nothing(empty):
    assert substring_dedup.dedup_substrings(empty).collect() == []


# ---- 10: language model


def test_masked_lm(spark, messy, empty):
    rng = random.Random(30)
    texts = [(k, "the cat sat on the mat and the dog sat on the rug " * rng.randint(2, 6)) for k in range(80)]
    df = spark.createDataFrame(texts, "doc_id long, text string")
    first, trained = masked_lm.begin(masked_lm.count_words(df)), masked_lm.fit(df, rounds=3)
    usual, odd = "the cat sat on the mat", "mat the on sat cat the"
    probe = spark.createDataFrame([(1, usual), (2, odd)], "doc_id long, text string")
    mean = lambda net: {r.doc_id: r.mean_log_prob for r in masked_lm.score(probe, net).collect()}
    assert mean(trained)[1] > mean(first)[1] and mean(trained)[1] > mean(trained)[2]
    got = masked_lm.score(messy, trained).collect()
    assert Counter(r.doc_id for r in got) == Counter(r[0] for r in messy_rows())
    assert all((r.n_words == 0 and r.log_prob == 0 and r.mean_log_prob is None) or r.log_prob < 0 for r in got)
    assert masked_lm.score(empty, masked_lm.fit(empty)).collect() == []


def test_masked_lm_tells_words_of_a_bucket_apart(spark):
    """Words outside the network's own list: their shares of the bucket follow their counts, and sum to one with the unseen."""
    rare = [f"rare{k}" for k in range(5000)]
    bucket = [w for w, b in zip(rare, masked_lm.bucket_of(common.text_words(pa.array(rare))[0]).tolist()) if b == 9][:4]
    many, once, few, junk = bucket
    top = " ".join(f"top{k}" for k in range(masked_lm.TOP))
    texts = [(k, top) for k in range(12)] + [(20, f"{many} " * 8 + once), (21, f"{few} {few} {few}")]
    df = spark.createDataFrame(texts, "doc_id long, text string").repartition(3)
    net = masked_lm.fit(df)
    got = {r.doc_id: r.log_prob for r in masked_lm.score(spark.createDataFrame(list(enumerate(bucket)), "doc_id long, text string"), net).collect()}
    ids, *_ = net.encode([many])
    of_bucket = net.log_probs(ids, np.array([masked_lm.SPAN]))[0]
    share = [math.exp(got[k] - of_bucket) for k in range(4)]
    assert share == pytest.approx([8.5 / 14, 1.5 / 14, 3.5 / 14, 0.5 / 14], rel=1e-4)
    assert sum(share) == pytest.approx(1, rel=1e-4)


def test_masked_lm_trains_on_every_word(spark):
    """Six words in a circle: a word at any place, and that of a text of one word, is better known than at the start."""
    texts = [(k, "a b c d e f " * 40) for k in range(60)] + [(k, "alone") for k in range(60, 400)]
    df = spark.createDataFrame(texts, "doc_id long, text string").coalesce(1)
    first = masked_lm.begin(masked_lm.count_words(df))
    for trained in (masked_lm.fit(df), masked_lm.fit(df, rounds=1), masked_lm.fit(df, rounds=3)):
        for probe in ("a b c d e f " * 3, "alone"):
            ids, sizes, _ = trained.encode([probe])
            at = masked_lm.SPAN + np.arange(sizes[0])
            assert (trained.log_probs(ids, at) > first.log_probs(ids, at) + 0.3).all()


def test_masked_lm_does_not_depend_on_the_files(spark, monkeypatch):
    """The same rows in one partition, in eight, and in another order: equal networks and scores, with several shards."""
    monkeypatch.setattr(masked_lm, "SHARD_WORDS", 700)
    rng = random.Random(3)
    rows = [(k, prose(rng, rng.randint(0, 60))) for k in range(90)] + [(5, None), (None, "a b c"), (7, "again and again"), (7, "again and again")]
    found = []
    for n in (1, 8):
        rng.shuffle(rows)
        df = spark.createDataFrame(rows, "doc_id long, text string").repartition(n)
        net = masked_lm.fit(df)
        found.append((net.flat(), null_safe((r.doc_id, r.n_words, r.log_prob) for r in masked_lm.score(df, net).collect())))
    assert (found[0][0] == found[1][0]).all()
    assert [r[:2] for r in found[0][1]] == [r[:2] for r in found[1][1]] and [r[2] for r in found[0][1]] == pytest.approx([r[2] for r in found[1][1]], rel=1e-9)


def test_masked_lm_scores_against_plain_code(spark):
    """Sums of log-probabilities from the definition: one word at a time, with loops."""
    rng = random.Random(13)
    rows = [(k, prose(rng, rng.randint(1, 12), [f"v{j}" for j in range(1200)])) for k in range(300)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    net = masked_lm.fit(df)
    counts = Counter(w for _, t in rows for w in t.split())
    code = lambda w: int(net.ids_of(common.text_words(pa.array([w]))[0])[0])
    totals = Counter()
    for w, n in counts.items():
        totals[code(w)] += n + masked_lm.UNSEEN
    w = net.weights
    softmax = lambda x: x - math.log(sum(math.exp(v) for v in x.tolist()))
    got = {r.doc_id: r.log_prob for r in masked_lm.score(df, net).collect()}
    for i, text in rows[:25]:
        words, total = text.split(), 0.0
        for k, word in enumerate(words):
            hidden = w["bias"].astype(float)
            for s, shift in enumerate(masked_lm.SHIFTS):
                near = code(words[k + shift]) if 0 <= k + shift < len(words) else masked_lm.SIZE
                hidden = hidden + w["embed"][s, near]
            hidden, (kind, inner) = np.tanh(hidden), divmod(code(word), masked_lm.SIDE)
            total += softmax(hidden @ w["classes"] + w["class_bias"])[kind] + softmax(hidden @ w["words"][kind] + w["word_bias"][kind])[inner]
            if code(word) >= masked_lm.TOP:
                total += math.log((counts[word] + masked_lm.UNSEEN) / (totals[code(word)] + masked_lm.UNSEEN))
        assert got[i] == pytest.approx(total, rel=1e-4)


def test_masked_lm_probabilities_sum_to_one():
    rng = np.random.default_rng(0)
    weights = {n: rng.normal(0, 0.3, s).astype(np.float32) for n, s in masked_lm.PARTS.items()}
    net = masked_lm.WindowNetwork(np.empty(0, np.uint64), weights)
    ids = np.full(5, masked_lm.SIZE)
    total = 0.0
    for k in range(masked_lm.SIZE):
        ids[2] = k
        total += math.exp(net.log_probs(ids, np.array([2]))[0])
    assert total == pytest.approx(1, abs=1e-4)


# ---- shared pieces


def test_hashing_pieces():
    words = "a b a b a".encode().split()
    h = common.word_hashes(words)
    g = common.gram_hashes(h, 2)
    assert g[0] == g[2] and g[1] == g[3] and g[0] != g[1]
    assert len(common.gram_hashes(h, 6)) == 0
    hashes, ends = common.text_words(pa.array([" ".join(map(str, range(40))), "", None, "one two", " ".join(map(str, range(10, 50)))]))
    at, values = substring_dedup.winnow(hashes, ends, 6, 20)
    for low in (0, 42):
        assert all(np.any((at >= s) & (at <= s + 14)) for s in range(low, low + 21)) and len(at) == len(values)
    assert ends.tolist() == [0, 40, 40, 40, 42, 82] and not np.any((at > 34) & (at < 42))


def test_words_and_their_hashes():
    """Words of all texts at once are those of each text alone; equal words have equal hashes, others others."""
    rng, word_of, hash_of = random.Random(1), {}, {}
    some = ["a", "b", "ab", "\t", " ", "\n", "\x0b", "\x1c", "é", "xyzxyzxy", "日", "A", "Q" * 9, "z" * 300, "\u00a0"]
    for lower in (False, True):
        for n in (0, 1, 5, 400):
            texts = ["".join(rng.choice(some) for _ in range(rng.randint(0, 12))) if rng.random() < 0.9 else None for _ in range(n)]
            hashes, ends = common.text_words(pa.array(["pad x", *texts], pa.string()).slice(1), lower)
            for k, text in enumerate(texts):
                words, found = common.words_of(text, lower), hashes[ends[k] : ends[k + 1]].tolist()
                assert len(words) == len(found)
                assert all(word_of.setdefault(h, w) == w and hash_of.setdefault(w, h) == h for w, h in zip(words, found))


def test_digests_of_queries(spark):
    """The digest columns follow from plain code over a whole table."""
    import duckdb

    sf, t = "/root/testdata/sf0.001", tokenizer()
    docs = duckdb.sql(f"SELECT doc_id, text FROM '{sf}/documents.parquet' ORDER BY doc_id").fetchall()
    at = 0
    got = {r.doc_id: r for r in queries.op1_token_orc(spark, sf).collect()}
    own = {r.doc_id: r for r in queries.op5_bpe(spark, sf).collect()}
    for i, text in docs:
        ids = t.encode(text or "", add_special_tokens=False).ids
        full = [*ids, 0]
        assert (got[i].start, got[i].n_tokens, got[i].ids_crc32) == (at, len(full), zlib.crc32(np.array(full, "<u4").tobytes()))
        assert (own[i].n_tokens, own[i].ids_sha256, own[i].decoded_sha256) == (len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(t.decode(ids, skip_special_tokens=False).encode()).hexdigest())
        at += len(full)
    removed = {r.doc_id: r for r in queries.op9_substring_dedup(spark, sf).collect()}
    want = brute_removal(docs)
    assert all((removed[i].n_words, removed[i].n_removed, removed[i].kept_sha256) == (*w[:2], hashlib.sha256(w[2].encode()).hexdigest()) for i, w in want.items())
    near = sorted(map(tuple, queries.op2_ngram_jaccard(spark, sf).collect()))
    assert near == sorted(brute_components(docs))


def test_toxicity_keeps_features_small(monkeypatch):
    """Training keeps a token's buckets in 4 bytes each, not as Python numbers; the driver holds them for all words."""
    made = []

    class Seen(common.Kept):
        def __init__(self, make, limit):
            super().__init__(make, limit)
            made.append(self)

    monkeypatch.setattr(toxicity, "Kept", Seen)
    rng = random.Random(2)
    rows = [(k, prose(rng, 30) + (" vile" if k % 2 else ""), k % 2) for k in range(40)]
    model = toxicity.train(rows, epochs=2)
    kept = made[0]
    assert len(kept) > 20 and all(len(v) == 4 * len(toxicity.features(t)) for t, v in kept.items())
    assert model.scores(["so vile"])[0] > model.scores(["so"])[0]
