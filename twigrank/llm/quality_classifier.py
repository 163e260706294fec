"""Quality classifier: ordinal cumulative-link regression on graded ratings over hashed text features.

P(grade > k) = sigmoid(w . x - theta_k) with one weight vector for all grades and increasing thresholds theta_k. Weights
get an L1 penalty, so that a text's score depends on the few telling features and not on its length.
"""

from __future__ import annotations

import operator
import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twigrank.llm.common import slices

BUCKETS = 1 << 18
#: Words whose weights a Python worker remembers.
REMEMBER = 400_000
SYMBOLS = "#*$%&|<>!{}=_~^"
LEVELS = (0.02, 0.1, 0.3, 0.6)


def bucket(feature: str) -> int:
    return zlib.crc32(feature.encode()) % BUCKETS


def shape_features(text: str, words: list[str]) -> list[str]:
    """Names of what a text looks like: symbols for each word, capitals, stutter, variety, long words."""
    n = len(words)
    if not n:
        return ["no words"]
    shares = {s: text.count(s) / n for s in SYMBOLS}
    shares["symbols"] = sum(shares.values())
    shares["capitals"] = sum(map(str.isupper, words)) / n
    shares["stutter"] = sum(map(operator.eq, words, words[1:])) / n
    if n >= 20:
        shares["same"] = 1 - len(set(words)) / n
    shares["long"] = sum(len(w) > 40 for w in words) / n
    return [f"\0{name}>{x}" for name, v in shares.items() for x in LEVELS if v > x]


WORD = re.compile(r"[^\W_]+")


def features(text: str) -> tuple[set[str], list[str]]:
    """(distinct lower-case words of letters and digits, shapes) of a whole text."""
    return set(WORD.findall(text.lower())), shape_features(text, text.split())


@dataclass(frozen=True)
class OrdinalModel:
    weights: np.ndarray  # BUCKETS floats, few of them not 0
    thresholds: np.ndarray  # one for each step between neighbouring grades, increasing

    def tails(self, scores: np.ndarray) -> np.ndarray:
        """P(grade >= k) for k = 1.. in columns."""
        return 1 / (1 + np.exp(-np.clip(scores[:, None] - self.thresholds[None, :], -40, 40)))


def fit_ordinal(rows: list[np.ndarray], grades: np.ndarray, n_grades: int = 3, sigmas: float = 4.5, rounds: int = 200, least_texts: int = 5) -> OrdinalModel:
    """Accelerated proximal gradient on the mean cumulative-link likelihood; rows hold the buckets of each text.

    A feature of share p of the texts has the value p ** -0.5, so that the gradient of one that tells nothing scatters by
    about std / sqrt(texts) whatever p is, std being that of a text's own gradient; the L1 penalty is `sigmas` times that.
    It only selects: the features it leaves
    are fitted again under a slight ridge. Features of fewer than `least_texts` texts are left out, however many texts
    there are: words that tell a rare grade are rare themselves. With no rows, or one grade only, all weights are
    0 and the thresholds give the (smoothed) shares of the grades.
    """
    share = np.cumsum(np.bincount(grades, minlength=n_grades) + 0.5)[:-1] / (len(grades) + 0.5 * n_grades)
    theta = np.log(share / (1 - share))
    if not len(rows) or len(set(grades.tolist())) < 2:
        return OrdinalModel(np.zeros(BUCKETS), theta)
    used, column = np.unique(np.concatenate(rows), return_inverse=True)
    owner, n, d = np.repeat(np.arange(len(rows)), [len(r) for r in rows]), len(rows), len(used)
    often = np.bincount(column, minlength=d)
    keep = (often >= least_texts)[column]
    column, owner = column[keep], owner[keep]
    scale = np.sqrt(n / np.maximum(often, 1))
    value = scale[column]
    forward = lambda w: np.bincount(owner, weights=value * w[column], minlength=n)
    backward = lambda g: np.bincount(column, weights=value * g[owner], minlength=d)
    v = np.ones(d) / np.sqrt(d)
    for _ in range(15):  # largest eigenvalue of the features' second moments
        u = backward(forward(v)) / n
        norm = np.linalg.norm(u)
        v = u / max(norm, 1e-12)
    sigmoid = lambda x: 1 / (1 + np.exp(-np.clip(x, -40, 40)))
    spread = np.std(sigmoid(np.r_[theta, np.inf][grades]) + sigmoid(np.r_[-np.inf, theta][grades]) - 1)
    step, penalty = 3.0 / max(norm, 1e-9), sigmas * spread / np.sqrt(n)
    w, chosen = np.zeros(d), np.ones(d, dtype=bool)
    for l1, ridge in ((penalty, 0.0), (0.0, 1e-3)):
        z, t = w.copy(), 1.0
        for _ in range(rounds):
            s = forward(z)
            low, high = np.r_[-np.inf, theta][grades], np.r_[theta, np.inf][grades]
            up, down = sigmoid(high - s), sigmoid(low - s)  # the likelihood of a row's grade is up - down
            new = z + step * (backward((up + down - 1) / n) - ridge * z)
            new = np.where(chosen, np.sign(new) * np.maximum(np.abs(new) - step * l1, 0), 0.0)
            t_new = (1 + np.sqrt(1 + 4 * t * t)) / 2
            z, w, t = new + (t - 1) / t_new * (new - w), new, t_new
            p = np.maximum(up - down, 1e-12)
            for k in range(n_grades - 1):
                theta[k] += 2.0 * np.mean((np.where(grades == k, up * (1 - up), 0) - np.where(grades == k + 1, down * (1 - down), 0)) / p)
            theta = np.maximum.accumulate(theta)
        chosen = w != 0
    weights = np.zeros(BUCKETS)
    weights[used] = w * scale
    return OrdinalModel(weights, theta)


def apart(rows: list[np.ndarray]) -> list[int]:
    """Places of rows of which no earlier kept one is a near copy (shares 4 of 8 least hashes): copies share the errors
    of their raters, and a group of them would teach its own words."""
    kept, seen = [], {}
    for i, row in enumerate(rows):
        x = row.astype(np.uint64)
        signature = [(k, int(((x + np.uint64(1)) * np.uint64(m) % np.uint64(2**31 - 1)).min())) for k, m in enumerate((48271, 69621, 16807, 39373, 630360016, 742938285, 950706376, 1226874159))] if len(x) else [(0, -1)]
        shared: dict[int, int] = {}
        for s in signature:
            for j in seen.get(s, ()):
                shared[j] = shared.get(j, 0) + 1
        if max(shared.values(), default=0) < 4:
            kept.append(i)
            for s in signature:
                seen.setdefault(s, []).append(i)
    return kept


def grade(quality: F.Column, toxic: F.Column) -> F.Column:
    """0 toxic, 1 poor, 2 good."""
    return F.when(toxic == 1, 0).when(quality == 1, 2).otherwise(1)


def fit(docs: DataFrame, labels: DataFrame, max_rated: int = 12_000) -> OrdinalModel:
    """Fit on at most `max_rated` labelled documents, those of smallest hash of their id.

    Rows of labels with a null id, quality or toxic are ignored; of repeated ids the worst rating counts. Labelled ids
    that docs lack, and documents with null text, add nothing.
    """
    rated = (
        labels.dropna(subset=["doc_id", "quality", "toxic"])
        .groupBy("doc_id")
        .agg(F.min(grade(F.col("quality"), F.col("toxic"))).alias("grade"))
        .orderBy(F.xxhash64("doc_id"), "doc_id")
        .limit(max_rated)
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            rows = []
            for text in batch.column(1).to_pylist():
                words, shapes = features(text)
                rows.append(np.unique(np.fromiter(map(bucket, [*words, *shapes]), dtype=np.int32)).tobytes())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(rows, pa.binary())], names=["doc_id", "grade", "buckets"])

    sample = (
        docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
        .dropna()
        .join(F.broadcast(rated), "doc_id")  # at most max_rated rows
        .select("doc_id", "text", "grade")
        .mapInArrow(run, "doc_id long, grade int, buckets binary")
        .toArrow()
    )
    sample = sample.sort_by([("doc_id", "ascending"), ("buckets", "ascending")])
    rows = [np.frombuffer(b, dtype=np.int32) for b in sample.column("buckets").to_pylist()]
    grades = np.asarray(sample.column("grade").to_pylist(), dtype=np.int64)
    kept = apart(rows)
    return fit_ordinal([rows[i] for i in kept], grades[kept])


class Scorer:
    """Scores of texts; remembers the weights of words that it has met."""

    def __init__(self, model: OrdinalModel):
        self.model, self.known = model, {}

    def scores(self, texts: list[str | None]) -> np.ndarray:
        out, known, weights = np.zeros(len(texts)), self.known, self.model.weights
        for i, text in enumerate(texts):
            words, shapes = features(text or "")
            new = words.difference(known)
            if new:
                if len(known) > REMEMBER:
                    known.clear()
                    new = words
                known.update((w, float(weights[bucket(w)])) for w in new)
            # features that share a bucket count once, as in training; shared ones have weight 0 but for a few
            live = {bucket(w) for w in words if known[w]} | {bucket(s) for s in shapes}
            out[i] = weights[list(live)].sum() if live else 0.0
        return out


def classify(df: DataFrame, model: OrdinalModel, min_tail: float = 0.5) -> DataFrame:
    """doc_id, expected grade, P(grade >= 1), P(grade >= 2) and kept (the last is at least min_tail), a row for each of df.

    Null and empty texts have no words; their features are those of a text without words.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(model)
        for batch in slices(batches):
            tails = model.tails(scorer.scores(batch.column(1).to_pylist()))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(tails.sum(axis=1)), pa.array(tails[:, 0]), pa.array(tails[:, -1]), pa.array(tails[:, -1] >= min_tail)],
                names=["doc_id", "expected_grade", "p_not_toxic", "p_good", "kept"],
            )

    rows = df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, expected_grade double, p_not_toxic double, p_good double, kept boolean")


def keep_good(df: DataFrame, model: OrdinalModel, min_tail: float = 0.5) -> DataFrame:
    """The rows of df (all columns) whose text the classifier keeps."""
    at = df.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(model)
        for batch in slices(batches):
            tails = model.tails(scorer.scores(batch.column(at).to_pylist()))
            yield batch.filter(pa.array(tails[:, -1] >= min_tail))

    return df.mapInArrow(run, df.schema)
