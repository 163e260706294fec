"""The pipeline as run() runs it, stage by stage against brute force on what each stage was given."""

import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow.parquet as pq
import pytest

import corpus_pipeline
from tests.conftest import MIDDLE
from twigrank.llm import mixing, quality_classifier
from twigrank.llm import queries as Q

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
NAMES = [name for name, _ in corpus_pipeline.STAGES]


@pytest.fixture(scope="module")
def given(spark):
    """Rows that each stage of one run() was given, by name, and the rows that it returned, as `result`."""
    seen, kept = {}, corpus_pipeline.STAGES

    def watched(name, stage):
        def run(spark, docs, sf_dir):
            assert docs.columns == COLUMNS
            seen[name] = [tuple(r) for r in docs.collect()]
            return stage(spark, docs, sf_dir)

        return name, run

    try:
        corpus_pipeline.STAGES = [watched(*s) for s in kept]
        seen["result"] = corpus_pipeline.run(spark, MIDDLE).collect()
    finally:
        corpus_pipeline.STAGES = kept
    return seen


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def test_classifier_stage_drops_what_it_rejects(spark, given):
    docs = Q.table(spark, MIDDLE, "documents")
    assert Counter(given[NAMES[0]]) == Counter(map(tuple, docs.collect()))
    judged = quality_classifier.classify(docs, quality_classifier.fit(docs, Q.table(spark, MIDDLE, "labels")))
    good = {r["doc_id"] for r in judged.where("p_good >= 0.5").collect()}
    assert Counter(given[NAMES[1]]) == Counter(r for r in given[NAMES[0]] if r[0] in good)
    assert 0 < len(given[NAMES[1]]) < len(given[NAMES[0]])


def test_dedup_stage_keeps_one_of_each_group(given):
    sets = {}
    for r in given[NAMES[1]]:
        w = re.findall(r"[^\x20\x09-\x0D]+", lower(r[1]))
        sets[r[0]] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
    ids, parent = sorted(sets), {i: i for i in sets}

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for k, i in enumerate(ids):
        for j in ids[:k]:
            both = len(sets[i] & sets[j])
            if sets[i] and 100 * both >= 80 * (len(sets[i]) + len(sets[j]) - both):
                a, b = sorted((root(i), root(j)))
                parent[b] = a
    assert sorted(given[NAMES[2]], key=repr) == sorted((r for r in given[NAMES[1]] if root(r[0]) == r[0]), key=repr)
    assert len(given[NAMES[2]]) < len(given[NAMES[1]])


def test_decontamination_stage_drops_documents_with_a_window(given):
    words = lambda text: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(text))
    windows = set()
    for item in pq.read_table(f"{MIDDLE}/benchmark.parquet").to_pylist():
        w = words(item["text"])
        windows |= {tuple(w[k : k + 10]) for k in range(max(1, len(w) - 9))} if w else set()
    lengths = {len(w) for w in windows}

    def hit(text):
        w = words(text)
        return any(tuple(w[k : k + n]) in windows for n in lengths for k in range(len(w) - n + 1))

    assert sorted(given[NAMES[3]], key=repr) == sorted((r for r in given[NAMES[2]] if not hit(r[1])), key=repr)
    assert len(given[NAMES[3]]) < len(given[NAMES[2]])


def test_mixing_stage_takes_words_of_its_documents_by_weight(given):
    split = lambda text: re.findall(r"[^\x20\x09-\x0D]+", text or "")
    before = {r[0]: r for r in given[NAMES[3]]}
    size, taken, by_doc = defaultdict(int), defaultdict(int), defaultdict(int)
    for r in before.values():
        size[r[3]] += len(split(r[1]))
    for doc, text, lang, source, n_chars in given[NAMES[4]]:
        whole, part = split(before[doc][1]), iter(split(before[doc][1]))
        assert (lang, source, n_chars) == (before[doc][2], before[doc][3], len(text))
        assert all(w in part for w in split(text)), "words of a pass stand in the document's order"
        taken[source] += len(split(text))
        by_doc[doc] += len(split(text))
        assert by_doc[doc] <= 3 * len(whole)
    order = sorted((s for s in size if s is not None), key=lambda s: s.encode()) + [None] * (None in size)
    want = dict(zip(order, mixing.targets([size[s] for s in order], [1 + k % 3 for k in range(len(order))])))
    for s in order:
        assert abs(taken[s] - want[s]) <= 0.03 * want[s] + 64


def test_token_stage_writes_the_ids_of_the_library(given):
    from tokenizers import Tokenizer

    tok, want = Tokenizer.from_file(Q.vocabulary()), Counter()
    for r in given[NAMES[4]]:
        ids = np.array([*tok.encode(r[1] or "", add_special_tokens=False).ids, 0], dtype="<u4")
        want[r[0], len(ids), zlib.crc32(ids.tobytes())] += 1
    rows = sorted(given["result"], key=lambda r: r["start"])
    assert Counter((r["doc_id"], r["n_tokens"], r["ids_crc32"]) for r in rows) == want
    assert rows[0]["start"] == 0 and all(b["start"] == a["start"] + a["n_tokens"] and a["doc_id"] <= b["doc_id"] for a, b in zip(rows, rows[1:]))
