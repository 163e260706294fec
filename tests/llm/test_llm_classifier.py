"""Words that tell a rare grade."""

import numpy as np
import pyarrow.parquet as pq

from twigrank.llm.quality_classifier import BUCKETS, apart, bucket, features, fit_ordinal

LARGE = "/root/testdata/sf0.1"
N, ABUSE, JUNK = 12_000, range(BUCKETS - 8, BUCKETS), BUCKETS - 9


def rated():
    """Grade 0 in one of 100 texts, each with one of eight abuse words (15 texts a word); 1 where there is junk."""
    rng, rows, grades = np.random.default_rng(5), [], []
    for i in range(N):
        words = (rng.zipf(1.3, 60) % 5000).tolist()
        grade = 0 if i % 100 == 0 else 1 if i % 5 == 1 else 2
        words += [ABUSE[i // 100 % 8]] if grade == 0 else [JUNK] if grade == 1 else []
        rows.append(np.unique(np.asarray(words, dtype=np.int32)))
        grades.append(grade)
    return rows, np.asarray(grades)


def test_one_per_cent_of_toxic_texts_teaches_their_words():
    rows, grades = rated()
    model = fit_ordinal(rows, grades)
    good = model.tails(np.array([model.weights[r].sum() for r in rows]))[:, -1] >= 0.5
    assert not good[grades == 0].any() and not good[grades == 1].any()
    assert good[grades == 2].mean() > 0.99
    assert all(model.weights[w] < 0 for w in ABUSE)


def test_held_out_ratings_of_the_given_documents():
    """Most toxic words of the given labels stand in under 1 % of the rated texts."""
    ratings = {}
    for r in pq.read_table(f"{LARGE}/labels.parquet").to_pylist():
        ratings[r["doc_id"]] = min(0 if r["toxic"] else 1 + r["quality"], ratings.get(r["doc_id"], 2))
    docs = [r for r in pq.read_table(f"{LARGE}/documents.parquet", columns=["doc_id", "text"]).to_pylist() if r["doc_id"] in ratings and r["text"] is not None]
    rows = [np.unique([bucket(x) for part in features(d["text"]) for x in part]) for d in docs]
    grades = np.array([ratings[d["doc_id"]] for d in docs])
    kept = np.array(apart(rows))
    seen, held = kept[kept % 5 > 0], kept[kept % 5 == 0]
    model = fit_ordinal([rows[i] for i in seen], grades[seen])
    good = model.tails(np.array([model.weights[rows[i]].sum() for i in held]))[:, -1] >= 0.5
    assert good[grades[held] == 0].mean() < 0.25
    assert good[grades[held] == 2].mean() > 0.98
