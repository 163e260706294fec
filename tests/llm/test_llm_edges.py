"""Nulls, empty and long texts, ties, repeated rows, empty tables and clashing columns, for every operator and stage."""

import numpy as np
import pytest

import corpus_pipeline
from twigrank.llm import chat_format, decontaminate, language_id, mixing, near_dedup, pii, quality_classifier, quality_rules, token_output, url_filters
from twigrank.llm.common import connected_components
from twigrank.llm.queries import URL_RULES, vocabulary

DOC = "doc_id long, text string, lang string, source string, n_chars long, pair string, band long, row long, kept boolean"
LONG = "wort " * 30_000 + "ende."
ROWS = [(1, None, "en", "a", 0), (2, "", None, None, 0), (3, LONG, "de", "a", 1), (4, "one two three four five six seven.", "en", None, 2), (4, "one two three four five six seven.", "en", None, 2), (None, "no id here at all, none.", "en", "b", 3), (5, "  \n\n ", "en", "b", 4), (6, "a\u00a0b\u2003c  d\r\n\te", "en", "b", 5), (7, "one two three four five six seven.", "fr", "c", 6)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(*r, "x", 1, 2, True) for r in ROWS], DOC)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOC)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(3, 1, 0), (4, 0, None), (4, 1, 0), (None, 1, 1), (99, 1, 1)], "doc_id long, quality int, toxic int")


@pytest.fixture(scope="module")
def benchmark(spark):
    return spark.createDataFrame([(1, "two three, FOUR"), (2, None), (3, ""), (None, "one two"), (1, "absent words")], "item_id long, text string")


def run_all(spark, docs, labels, benchmark):
    model = quality_classifier.fit(docs, labels)
    yield "classify", quality_classifier.classify(docs, model)
    yield "keep_good", quality_classifier.keep_good(docs, model)
    yield "rules", quality_rules.judge_quality(docs, with_text=True)
    yield "language", language_id.identify(docs, language_id.fit(docs))
    yield "near", near_dedup.near_duplicates(docs)
    yield "keep_one", near_dedup.keep_one(docs)
    yield "mix", mixing.mix(docs)
    yield "mixed", mixing.mixed_documents(docs)
    yield "index", decontaminate.decontaminate(docs, benchmark)
    yield "clean", decontaminate.keep_clean(docs, benchmark)
    yield "tokens", token_output.read_tokens(spark, token_output.tokens_in_shared_folder(docs, token_output.TokenFormat(vocabulary(), block_ids=50)))
    yield "pii", pii.replace_pii(docs, "k")


def test_odd_rows(spark, docs, labels, benchmark):
    got = {name: df.collect() for name, df in run_all(spark, docs, labels, benchmark)}
    for name in ("classify", "rules", "language", "near", "mix", "index", "tokens", "pii"):
        assert len(got[name]) == len(ROWS), name
    near = {r["doc_id"]: r for r in got["near"]}
    assert near[7]["component_id"] == 4 and not near[7]["kept"] and near[4]["kept"] and near[1]["n_shingles"] == 0
    assert near[None]["component_id"] is None and near[None]["kept"]
    assert sorted(str(r["doc_id"]) for r in got["keep_one"]) == sorted(["1", "2", "3", "4", "5", "6", "None"])
    hit = {r["doc_id"]: r for r in got["index"]}
    assert hit[4]["items"] == [1] and hit[4]["n_hit"] == 3 and hit[1]["n_words"] == 0
    assert {r["doc_id"] for r in got["clean"]} == {1, 2, 3, 5, 6, None}
    assert [r["lang_pred"] for r in got["language"] if r["doc_id"] in (1, 2, 5)] == ["und"] * 3
    tokens = sorted(got["tokens"], key=lambda r: r["start"])
    assert [r["doc_id"] for r in tokens] == [None, 1, 2, 3, 4, 4, 5, 6, 7]
    assert all(b["start"] == a["start"] + a["n_tokens"] for a, b in zip(tokens, tokens[1:]))
    assert {r["text"] for r in got["pii"]} == {r[1] for r in ROWS}
    assert not [r for r in got["rules"] if r["doc_id"] in (1, 2, 5) and (r["kept"] or not r["base_failed"])]


def test_empty_tables(spark, none, labels, benchmark):
    for name, df in run_all(spark, none, labels.limit(0), benchmark.limit(0)):
        assert df.count() == 0, name


def test_urls(spark):
    rows = [(1, None), (2, "nothing"), (3, "HTTP://WWW.Example.COM/en/x?q#f"), (3, "HTTP://WWW.Example.COM/en/x?q#f"), (4, "http://a.net"), (5, "http://b.NET/fr/#"), (6, "x://example.com/en/")]
    df = spark.createDataFrame([(*r, "clash", "clash") for r in rows], "page_id long, url string, host string, rule string")
    got = [(r["page_id"], r["host"], r["path"], r["rule"], r["verdict"]) for r in url_filters.judge_urls(df, url_filters.rules_frame(spark, URL_RULES)).collect()]
    assert sorted(got, key=str) == sorted([(1, "", "", None, "allow"), (2, "", "", None, "allow"), (3, "www.example.com", "/en/x", "www.example.com/en/", "allow"), (3, "www.example.com", "/en/x", "www.example.com/en/", "allow"), (4, "a.net", "", None, "allow"), (5, "b.net", "/fr/", "net/fr/", "block"), (6, "example.com", "/en/", "example.com/en/", "block")], key=str)
    assert url_filters.judge_urls(df, url_filters.rules_frame(spark, URL_RULES).limit(0)).where("verdict = 'allow'").count() == 7
    assert url_filters.judge_urls(df.limit(0), url_filters.rules_frame(spark, URL_RULES)).count() == 0


def test_chat(spark):
    rows = [(1, 0, "system", "be <kind>"), *[(1, k, ("user", "assistant")[k % 2], f"{'word ' * 200}{k}\\") for k in range(1, 30)], (2, None, None, None), (None, 1, "assistant", "</turn>\n<turn:x>"), (3, 0, "assistant", "w " * 5000), (3, 0, "assistant", "w " * 5000)]
    df = spark.createDataFrame([(*r, 9) for r in rows], "conv_id long, turn long, role string, text string, window long")
    windows = chat_format.format_conversations(df)
    back = {r["conv_id"]: r for r in chat_format.read_back(windows).collect()}
    assert back[1]["n_turns"] == 30 and back[3]["n_turns"] == 2 and back[None]["loss_chars"] == len("</turn>\n<turn:x>") and back[2]["n_turns"] == 1
    mine = [w for w in windows.collect() if w["conv_id"] == 1]
    assert len(mine) > 5 and all(w["text"].startswith("<turn:system>\n") and w["n_tokens"] <= 1024 for w in mine)
    assert any(w["n_repeated"] > 1 for w in mine)
    assert chat_format.read_back(chat_format.format_conversations(df.limit(0))).count() == 0
    from tokenizers import Tokenizer

    library, budget = Tokenizer.from_file(vocabulary()), chat_format.WindowBudget(vocabulary(), tokens=300, history=100)
    by_ids = chat_format.format_conversations(df, budget)
    for w in by_ids.collect():
        turns = chat_format.MARK.finditer(w["text"])
        assert w["n_tokens"] == sum(len(library.encode(m[0], add_special_tokens=False).ids) for m in turns)
        assert w["over_budget"] == (w["n_tokens"] > 300)
    assert {r["conv_id"]: r["turns_sha256"] for r in chat_format.read_back(by_ids).collect()} == {c: r["turns_sha256"] for c, r in back.items()}


def test_targets_are_filled_by_weight():
    assert mixing.targets([100, 100], [1, 3]) == [50.0, 150.0]
    assert mixing.targets([10, 1000], [3, 1]) == [30.0, 980.0]
    assert mixing.targets([0, 5], [1, 1]) == [0.0, 5.0] and mixing.targets([], []) == []
    for n in (1, 2, 3, 10, 1000):
        assert sorted(mixing.permuted(np.arange(n), n, 5).tolist()) == list(range(n))


def test_sketch_agrees_with_similarity():
    rng = np.random.default_rng(1)
    x = rng.integers(0, 1 << 63, 400, dtype=np.int64).astype(np.uint64)
    for size in (1, 7, 60, 400):
        assert len(set(near_dedup.sketch(x[:size], 128).tolist())) == 128
    same = np.mean([(near_dedup.sketch(a := rng.permutation(x)[:300], 128) == near_dedup.sketch(np.r_[a[:240], rng.integers(0, 1 << 63, 60).astype(np.uint64)], 128)).mean() for _ in range(40)])
    assert abs(same - 240 / 360) < 0.04


def test_stages_keep_the_columns(spark, docs):
    base = docs.select("doc_id", "text", "lang", "source", "n_chars")
    for name, stage in corpus_pipeline.STAGES[1:-1]:
        assert stage(spark, base, "/root/testdata/sf0.001").columns == base.columns, name


def test_components_equal_a_search(spark):
    rng = np.random.default_rng(3)
    chain = [(k, k + 1) for k in range(1000, 1040)]
    edges = [tuple(e) for e in rng.integers(0, 90, (60, 2)).tolist()] + chain + [(2000, k) for k in range(2001, 2050)]
    parent = {n: n for e in edges for n in e}

    def root(n):
        return n if parent[n] == n else root(parent[n])

    for x, y in edges:
        low, high = sorted((root(x), root(y)))
        parent[high] = low
    got = connected_components(spark.createDataFrame(edges, "a long, b long")).collect()
    touched = {n for x, y in edges if x != y for n in (x, y)}
    assert sorted((r["node"], r["component"]) for r in got) == sorted((n, root(n)) for n in touched)
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0
