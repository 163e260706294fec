"""The operator queries on the given tables: against SQL where there is some, else against brute force."""

import hashlib
import re
import zlib

import numpy as np
import pyarrow.parquet as pq
import pytest

from tests.conftest import MIDDLE, SMALL
from twigrank.llm import queries as Q
from twigrank.llm import sql

DOCS = pq.read_table(f"{SMALL}/documents.parquet").to_pylist()


@pytest.mark.parametrize("name", sorted(sql.ORACLES))
def test_sql_twin(spark, duck, name):
    mine = Q.queries()[name](spark, SMALL).toPandas()
    theirs = duck.sql(sql.ORACLES[name]).df()
    assert sorted(mine.columns) == sorted(theirs.columns)
    cols = sorted(mine.columns)
    rows = lambda df: sorted(map(repr, df[cols].astype(object).where(df[cols].notna(), None).itertuples(index=False, name=None)))
    assert rows(mine) == rows(theirs)


def test_near_duplicates_equal_brute_force(spark):
    def shingles(text):
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
        return {tuple(w[k : k + 3]) for k in range(len(w) - 2)} if len(w) >= 3 else ({tuple(w)} if w else set())

    docs = pq.read_table(f"{MIDDLE}/documents.parquet").to_pylist()
    sets = {d["doc_id"]: shingles(d["text"]) for d in docs}
    ids, parent = sorted(sets), {i: i for i in sets}

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for k, i in enumerate(ids):
        for j in ids[:k]:
            both = len(sets[i] & sets[j])
            if sets[i] and 100 * both >= 85 * (len(sets[i]) + len(sets[j]) - both):
                a, b = sorted((root(i), root(j)))
                parent[b] = a
    got = {r["doc_id"]: r for r in Q.op5_near_dedup(spark, MIDDLE).collect()}
    assert len(got) == len(docs)
    for i in ids:
        assert (got[i]["n_shingles"], got[i]["component_id"], got[i]["kept"]) == (len(sets[i]), root(i), root(i) == i)


def test_token_files_hold_the_ids_of_the_library(spark):
    from tokenizers import Tokenizer

    tok, at = Tokenizer.from_file(Q.vocabulary()), 0
    got = {r["doc_id"]: r for r in Q.op9_token_output(spark, SMALL).collect()}
    for d in sorted(DOCS, key=lambda d: d["doc_id"]):
        ids = np.array([*tok.encode(d["text"] or "", add_special_tokens=False).ids, 0], dtype="<u4")
        r = got[d["doc_id"]]
        assert (r["start"], r["n_tokens"], r["ids_crc32"]) == (at, len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)
    assert len(got) == len(DOCS)


def test_chat_reads_back_what_went_in(spark):
    rows = pq.read_table(f"{SMALL}/conversations.parquet").to_pylist()
    said = "\\### Assistant: </turn> ok"
    rows += [{"conv_id": -7, "turn": k, "role": r, "text": said} for k, r in enumerate(("user", "assistant"))]
    want = {}
    for r in sorted(rows, key=lambda r: (r["conv_id"], r["turn"])):
        n, turns, loss = want.setdefault(r["conv_id"], [0, [], []])
        want[r["conv_id"]][0] += 1
        turns.append(f"{r['role']}\n{r['text'] or ''}\n")
        if r["role"] == "assistant":
            loss.append(r["text"] or "")
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    got = {r["conv_id"]: r for r in Q.op6_chat_format(spark, SMALL).collect()}
    assert set(got) == set(want)
    for conv, (n, turns, loss) in want.items():
        r = got[conv]
        assert (r["n_turns"], r["turns_sha256"], r["loss_chars"], r["loss_sha256"]) == (n, sha("".join(turns)), len("".join(loss)), sha("".join(loss)))
        assert r["formatted_chars"] > len("".join(turns))


def test_languages_held_out_accuracy(spark):
    lang = {d["doc_id"]: d for d in pq.read_table(f"{MIDDLE}/documents.parquet").to_pylist()}
    got = [r for r in Q.op4_language_id(spark, MIDDLE).collect() if r["held_out"]]
    assert got and all((zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) and 0 <= r["score"] <= 1 for r in got)
    right = [r["lang_pred"] == lang[r["doc_id"]]["lang"] for r in got if lang[r["doc_id"]]["lang"]]
    assert sum(right) >= 0.97 * len(right)


def test_classifier_rejects_abuse_and_junk_and_keeps_clean(spark):
    text = {d["doc_id"]: d["text"] for d in pq.read_table("/root/testdata/sf0.1/documents.parquet").to_pylist()}
    rows = Q.op2_quality_classifier(spark, "/root/testdata/sf0.1").collect()
    abuse = re.compile(r"\b(idiot|moron|scum|stupid|pathetic|worthless|loser|trash)\b")
    junk = lambda t: t.count("###") + t.count("$$$") > 0.1 * len(t.split())
    share = lambda xs: sum(xs) / max(1, len(xs))
    bad = [r["kept"] for r in rows if len(set(abuse.findall(text[r["doc_id"]]))) >= 3]
    assert bad and share(bad) < 0.02
    noisy = [r["kept"] for r in rows if junk(text[r["doc_id"]])]
    assert noisy and share(noisy) < 0.1
    clean = [r["kept"] for r in rows if not abuse.search(text[r["doc_id"]]) and not re.search(r"[#$|%&*!]", text[r["doc_id"]]) and len(set(text[r["doc_id"]].split())) > 0.3 * len(text[r["doc_id"]].split())]
    assert share(clean) > 0.98
    assert all(0 <= r["p_good"] <= r["p_not_toxic"] <= 1 for r in rows)


def test_mix_meets_targets(spark):
    rows = Q.op7_mixing(spark, MIDDLE).collect()
    source = {d["doc_id"]: d["source"] for d in pq.read_table(f"{MIDDLE}/documents.parquet").to_pylist()}
    taken, target = {}, {}
    for r in rows:
        s = source[r["doc_id"]]
        taken[s] = taken.get(s, 0) + r["taken"]
        target[s] = r["target"]
        assert 0 <= r["taken"] <= 3 * r["size"]
    assert abs(sum(target.values()) - sum(r["size"] for r in rows)) < 1
    for s in target:
        assert abs(taken[s] - target[s]) <= 0.03 * target[s] + 64
    again = {(r["doc_id"], r["taken"]) for r in Q.op7_mixing(spark, MIDDLE).collect()}
    assert again == {(r["doc_id"], r["taken"]) for r in rows}


def test_pii_is_replaced_alike_and_apart(spark):
    text = {d["doc_id"]: d["text"] for d in pq.read_table(f"{MIDDLE}/documents.parquet").to_pylist()}
    rows = Q.op10_pii(spark, MIDDLE).collect()
    find = re.compile(r"[\w.]+@[\w.]+\.com|\b\d{16}\b|\+1 \(\d{3}\) \d{3}-\d{4}|\b[0-9a-f]{40}\b|\b\d{1,3}(?:\.\d{1,3}){3}\b")
    seen, hit = {}, 0
    for r in rows:
        old, new = find.findall(text[r["doc_id"]]), find.findall(r["text"])
        assert len(old) == len(new)
        for a, b in zip(old, new):
            assert a != b and seen.setdefault(a, b) == b
            assert a not in r["text"]
            hit += 1
        if not r["n_entities"]:
            assert r["text"] == text[r["doc_id"]]
    assert hit > 50 and len(set(seen.values())) == len(seen)
