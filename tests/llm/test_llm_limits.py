"""Both sides of every limit (small ones give the same results), and the token encoder against the library."""

import random
import re

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from tests.conftest import MIDDLE
from twigrank.llm import decontaminate, mixing, near_dedup
from twigrank.llm import queries as Q
from twigrank.llm.common import join_per_key, maybe_in
from twigrank.llm.token_output import Encoder


def rows(df):
    return sorted(map(repr, df.collect()))


@pytest.mark.parametrize("limits", [{"bucket_rows": 2}, {"cluster_shingles": 300}])
def test_large_buckets_and_clusters(spark, limits):
    docs = spark.read.parquet(f"{MIDDLE}/documents.parquet")
    want = near_dedup.near_duplicates(docs, Q.LINKS)
    config = near_dedup.DedupConfig(words=3, num=85, den=100, **limits)
    assert rows(near_dedup.near_duplicates(docs, config)) == rows(want)


def test_hot_keys_join_like_others(spark):
    left = spark.createDataFrame([(k if k < 50 else 7, k) for k in range(5000)], "key long, x long")
    right = spark.createDataFrame([(k, k * 10, 1 + 4951 * (k == 7)) for k in range(40)], "key long, y long, n long")
    got = join_per_key(left, right, "key", 5000)
    assert rows(got.select("key", "x", "y")) == rows(left.join(right, "key").select("key", "x", "y"))
    assert rows(maybe_in(left, "key", right).join(right.select("key"), "key", "left_semi")) == rows(left.join(right.select("key"), "key", "left_semi"))
    assert maybe_in(left, "key", right.limit(0)).count() == 0


def test_encoder_equals_the_library():
    from tokenizers import Tokenizer

    library, mine, rng = Tokenizer.from_file(Q.vocabulary()), Encoder(Q.vocabulary()), random.Random(11)
    signs = [*"ab cdé'ß ñ漢字я1 23.,!#| \n\n\t\r\v\f\x1c\x85\xa0 　😀", "'s", "'ll", " the", " \n", "  ", " \t ", "<|endoftext|>", "\n ", "́", "²½"]
    for _ in range(100):
        texts: list[str | None] = [None, "", " ", "\n"]
        for _ in range(100):
            text = "".join(rng.choice(signs) for _ in range(rng.choice([1, 2, 5, 20, 100])))
            texts.append(re.sub(r"\s+", lambda m: rng.choice(" \n"), text).strip() if rng.random() < 0.5 else text)
        want = [e.ids for e in library.encode_batch([t or "" for t in texts], add_special_tokens=False)]
        assert [x.tolist() for x in mine.encode(texts)] == want
    ids, n = mine.encode_column(pa.array(["a b", None, "c"]).slice(1))
    assert n.tolist() == [0, 1] and ids.tolist() == library.encode("c").ids


def test_benchmark_in_parts(spark, monkeypatch):
    docs = spark.createDataFrame([(1, "a b c d e"), (1, "a b c d e"), (1, "x y z a b"), (None, "c d e"), (2, None)], "doc_id long, text string")
    bench = spark.createDataFrame([(5, "b c"), (6, "c d"), (7, "z a b"), (8, "q")], "item_id long, text string")
    whole = rows(decontaminate.decontaminate(docs, bench).select("doc_id", "n_words", "n_hit", "items", "contaminated"))
    assert len(whole) == 5 and sum("n_hit=3" in r and "items=[5, 6]" in r for r in whole) == 2
    big = spark.read.parquet(f"{MIDDLE}/documents.parquet"), spark.read.parquet(f"{MIDDLE}/benchmark.parquet")
    given = rows(decontaminate.decontaminate(*big).select("doc_id", "n_words", "n_hit", "items"))
    monkeypatch.setattr(decontaminate, "BENCHMARK_CHARS", 2)
    assert rows(decontaminate.decontaminate(docs, bench).select("doc_id", "n_words", "n_hit", "items", "contaminated")) == whole
    monkeypatch.setattr(decontaminate, "BENCHMARK_CHARS", 2000)
    assert rows(decontaminate.decontaminate(*big).select("doc_id", "n_words", "n_hit", "items")) == given


def test_proximity_equals_brute_force(spark):
    rng, slack = random.Random(4), 2
    docs = [(k, " ".join(rng.choice("abcdefg") for _ in range(rng.randint(0, 14)))) for k in range(80)]
    items = [(k, " ".join(rng.choice("abcdefgh") for _ in range(rng.randint(1, 4)))) for k in range(12)]
    got = decontaminate.decontaminate(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"), slack).collect()
    known = {w for _, t in items for w in t.split()}
    frequency = {w: sum(w in t.split() for _, t in docs) for w in known}
    found = {r["doc_id"]: (r["n_hit"], r["items"]) for r in got}
    for doc, text in docs:
        words, hit, names = text.split(), set(), []
        for item, query in items:
            terms = query.split()
            rarest = min(range(len(terms)), key=lambda k: (frequency[terms[k]], k))
            for at in (p for p, w in enumerate(words) if w == terms[rarest]):
                start = at - rarest
                if all(any(words[p] == t for p in range(max(0, start + k - slack), min(len(words), start + k + slack + 1))) for k, t in enumerate(terms)):
                    hit |= set(range(max(0, start), min(len(words), start + len(terms))))
                    names.append(item)
        assert found[doc] == (len(hit), sorted(set(names))), (doc, text)


def test_draws_go_down_the_tree():
    for slots in ([5, 0, 17], [1000, 3, 50_000], [4 * 10**12, 10**12, 3], [0, 0]):
        slots, plan = np.array(slots, dtype=np.int64), mixing.MixPlan(shard_slots=64, super_shards=4)
        n = -(-int(slots.sum()) // 64)
        shards = range(n) if n < 1000 else [0, 1, 2, n // 2, n - 2, n - 1]
        last = None
        for k in shards:
            own, before = mixing.shard_range(plan, slots, k, k + 1)
            assert own.sum() == min(64, slots.sum() - 64 * k) and (own >= 0).all() and (before + own <= slots).all()
            if last is not None and last[0] == k - 1:
                assert (before == last[1]).all()
            last = k, before + own
        if n:
            assert (last[1] == slots).all()
