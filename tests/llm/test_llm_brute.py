"""The classifier, the language models and the mix against plain computations, and the pipeline on empty tables."""

import math
from collections import Counter, defaultdict

import numpy as np
import pyarrow.parquet as pq
import pytest

import corpus_pipeline
from tests.conftest import MIDDLE, SMALL
from twigrank.llm import language_id, mixing
from twigrank.llm.language_id import END, ORDER, START, LanguageModel, kneser_ney, letter_runs
from twigrank.llm.quality_classifier import fit_ordinal


def test_ordinal_fit_is_as_good_as_plain_gradient_descent():
    rng, n, d = np.random.default_rng(8), 1500, 12
    x = rng.random((n, d)) < rng.uniform(0.1, 0.6, d)
    score = x @ np.array([2.5, -2.5, 1.5, *[0] * (d - 3)]) + rng.logistic(size=n)
    grades = np.digitize(score, [-0.5, 1.5])
    model = fit_ordinal([np.nonzero(row)[0] for row in x], grades)
    chosen = np.nonzero(model.weights[:d])[0]
    assert {0, 1, 2} <= set(chosen.tolist()) and len(chosen) < 6 and (np.diff(model.thresholds) > 0).all()
    scale = np.sqrt(n / x.sum(axis=0))
    features = (x * scale)[:, chosen]
    sigmoid = lambda v: 1 / (1 + np.exp(-v))

    def loss(w, theta):
        s, edges = features @ w, np.r_[-50, theta, 50]
        return -np.log(sigmoid(edges[grades + 1] - s) - sigmoid(edges[grades] - s)).mean() + 0.0005 * (w**2).sum()

    w, theta = np.zeros(len(chosen)), np.array([-0.5, 0.5])
    for _ in range(4000):
        at = np.r_[w, theta]
        slope = np.array([(loss(*np.split(at + e, [len(w)])) - loss(*np.split(at - e, [len(w)]))) / 2e-5 for e in np.eye(len(at)) * 1e-5])
        w, theta = np.split(at - 0.3 * slope, [len(w)])
        if np.abs(slope).max() < 1e-4:
            break
    assert loss(model.weights[chosen] / scale[chosen], model.thresholds) <= loss(w, theta) + 1e-3
    assert np.allclose(model.weights[chosen], w * scale[chosen], atol=0.1) and np.allclose(model.thresholds, theta, atol=0.1)


def test_kneser_ney_equals_the_plain_recursion():
    words = ["banana", "band", "ananas", "nab", "ban", "b", "sand", "äß"]
    top = Counter(p[i : i + ORDER] for w in words for p in [START * (ORDER - 1) + w + END] for i in range(len(w) + 1))
    alphabet = len({c for g in top for c in g})
    counts = {ORDER: dict(top)}
    for n in range(ORDER - 1, 0, -1):
        counts[n] = Counter(g[1:] for g in counts[n + 1])

    def p(n, context, c):
        if n == 0:
            return 1 / (alphabet + 1)
        own = {g: k for g, k in counts[n].items() if g[:-1] == context}
        if not own:
            return p(n - 1, context[1:], c)
        ones, twos = sum(k == 1 for k in counts[n].values()), sum(k == 2 for k in counts[n].values())
        d = min(0.95, max(0.1, ones / (ones + 2 * twos) if ones else 0.5))
        return (max(own.get(context + c, 0) - d, 0) if context + c in own else 0) / sum(own.values()) + d * len(own) / sum(own.values()) * p(n - 1, context[1:], c)

    test = ["banana", "bandanas", "xyz", "ñ", "sß"]
    got = LanguageModel(["a"], [kneser_ney(dict(top), alphabet)]).word_scores(test)[:, 0]
    for w, logp in zip(test, got):
        padded = START * (ORDER - 1) + w + END
        want = sum(math.log(p(ORDER, padded[i : i + ORDER - 1], padded[i + ORDER - 1])) for i in range(len(w) + 1))
        assert abs(logp - want) < 1e-9, w


def test_only_letters_are_letters(spark):
    assert letter_runs("½ ² ³x 4 Ⅷ ②") == ["x"] and letter_runs("Ünï-cödé 漢字 _a_") == ["ünï", "cödé", "漢字", "a"]
    model = LanguageModel(["en"], [kneser_ney({START * (ORDER - 1) + "a": 1, START * (ORDER - 2) + "a" + END: 1}, 3)], worst=np.array([np.inf]))
    rows = language_id.identify(spark.createDataFrame([(1, "½ ²"), (2, "aa")], "doc_id long, text string"), model).collect()
    assert {r["doc_id"]: r["lang_pred"] for r in rows} == {1: "und", 2: "en"}


@pytest.mark.parametrize("shard_slots, super_shards", [(64, 2), (64, 16), (1000, 16)])
def test_mix_equals_block_by_block(spark, shard_slots, super_shards):
    plan = mixing.MixPlan(block_words=16, shard_slots=shard_slots, super_shards=super_shards)
    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet")
    counts = mixing.word_counts(docs)
    sources = mixing.plan_sources(counts, plan).orderBy("k").collect()
    places = mixing.placed(counts, mixing.plan_sources(counts, plan), plan).collect()
    slots = np.array([r["n_slots"] for r in sources], dtype=np.int64)
    times, passes = defaultdict(Counter), defaultdict(Counter)
    for shard in range(-(-int(slots.sum()) // plan.shard_slots)):
        own, start = mixing.shard_range(plan, slots, shard, shard + 1)
        for k, (n, at) in enumerate(zip(own.tolist(), start.tolist())):
            for slot in range(at, at + n):
                turn, i = divmod(slot, sources[k]["n_blocks"])
                block = int(mixing.permuted(np.array([i]), sources[k]["n_blocks"], plan.seed * 1000 + k * mixing.MOST * 7 + turn)[0])
                times[k][block] += 1
                passes[k, turn][block] += 1
    assert [sum(times[k].values()) for k in range(len(slots))] == slots.tolist()
    assert all(max(c.values()) == 1 for c in passes.values())
    for k, r in enumerate(sources):
        own = sorted((x["start"], x["size"]) for x in places if x["k"] == k)
        reach = 0
        for start, size in own:  # documents fill the source's words without a gap
            assert start == reach
            reach += size
        assert reach == r["source_size"]
    want = sorted((x["doc_id"], sum(times[x["k"]][w // 16] for w in range(x["start"], x["start"] + x["size"]))) for x in places)
    assert sorted((r["doc_id"], r["taken"]) for r in mixing.mix(docs, plan).collect()) == want


def test_pipeline_on_empty_tables(spark, tmp_path):
    for name in ("documents", "labels", "benchmark"):
        pq.write_table(pq.read_table(f"{SMALL}/{name}.parquet").slice(0, 0), tmp_path / f"{name}.parquet")
    out = corpus_pipeline.run(spark, str(tmp_path))
    assert out.columns == ["doc_id", "start", "n_tokens", "ids_crc32"] and out.count() == 0
