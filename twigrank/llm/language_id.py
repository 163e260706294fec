"""Language identification: interpolated Kneser-Ney character models, one for each language, in sorted hash arrays.

A text is scored by its runs of letters, lower-cased and padded, each run on its own. The language of lowest cross-entropy
for each character wins; a temperature fitted on calibration documents turns the cross-entropies into a probability, and a
text is marked rejected when the best language codes it worse than nearly all calibration documents of that language.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from twigrank.llm.common import materialize, slices

ORDER = 4
LETTERS = re.compile(r"[^\W\d_]+")
START, END = "\x02", "\x03"
#: Letter runs whose scores a Python worker remembers.
REMEMBER = 300_000
UNKNOWN = "und"
#: Parts of a language that are ranked apart when its training documents are chosen.
SALTS = 64
#: Chosen ids, over all languages, up to which they are broadcast; beyond it they are shuffled.
BROADCAST_ROWS = 500_000


def fold(doc_id: F.Column) -> F.Column:
    return F.crc32(doc_id.cast("string").cast("binary")) % 5


def letter_runs(text: str | None) -> list[str]:
    """Runs of letters (Unicode's L categories), lower-cased."""
    runs = LETTERS.findall(text.lower()) if text else []
    if all(map(str.isalpha, runs)):
        return runs
    # numbers that are no decimal digits, such as superscripts and fractions, are no letters
    return [w for r in runs for w in "".join(c if c.isalpha() else " " for c in r).split()]


def gram_hashes(codes: np.ndarray, n: int) -> np.ndarray:
    """64-bit hash of the n codes that end at each position >= ORDER - 1 (code points, padded)."""
    h = np.full(len(codes) - ORDER + 1, n, dtype=np.uint64)
    for k in range(n):
        c = codes[ORDER - n + k : len(codes) - n + k + 1 if n - k - 1 else None]
        h = (h ^ c[: len(h)]) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
    return h


def pack(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of all words, each padded by ORDER-1 starts and an end; lengths with the end."""
    text = "".join(START * (ORDER - 1) + w + END for w in words)
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32).astype(np.uint64)
    return codes, np.array([len(w) + 1 for w in words], dtype=np.int64)


@dataclass
class SortedTable:
    """Sorted hashes with a value each."""

    keys: np.ndarray
    values: np.ndarray

    @classmethod
    def of(cls, items: dict[str, float]) -> "SortedTable":
        keys = np.array([string_hash(g) for g in items], dtype=np.uint64)
        order = np.argsort(keys)
        return cls(keys[order], np.fromiter(items.values(), dtype=np.float64, count=len(items))[order])

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not len(self.keys):
            return np.zeros(len(h), dtype=bool), np.zeros(len(h))
        at = np.minimum(np.searchsorted(self.keys, h), len(self.keys) - 1)
        return self.keys[at] == h, self.values[at]


def string_hash(gram: str) -> int:
    codes = np.r_[np.zeros(ORDER - len(gram), dtype=np.uint64), np.array([ord(c) for c in gram], dtype=np.uint64)]
    return int(gram_hashes(codes, len(gram))[0])


@dataclass
class CharModel:
    """Log probabilities of all seen grams with all lower orders mixed in, and log weights left for unseen ones."""

    probs: list[SortedTable] = field(default_factory=list)  # by order, from 1
    rest: list[SortedTable] = field(default_factory=list)  # of the contexts of order n, n = 1..ORDER-1
    floor: float = 0.0

    def logp(self, hashes: list[np.ndarray], contexts: list[np.ndarray]) -> np.ndarray:
        found, out = self.probs[ORDER - 1].find(hashes[ORDER - 1])
        miss = np.nonzero(~found)[0]
        back = np.zeros(len(miss))
        for n in range(ORDER - 1, 0, -1):
            if not len(miss):
                return out
            known, weight = self.rest[n - 1].find(contexts[n - 1][miss])
            back += np.where(known, weight, 0.0)
            found, p = self.probs[n - 1].find(hashes[n - 1][miss])
            out[miss[found]] = p[found] + back[found]
            miss, back = miss[~found], back[~found]
        out[miss] = self.floor + back
        return out


def kneser_ney(top: dict[str, int], alphabet: int) -> CharModel:
    """From counts of grams of the highest order. Lower orders count the distinct characters before a gram; each order has
    one discount, n1 / (n1 + 2 n2), held within 0.1 and 0.95."""
    counts: list[dict[str, int]] = [{} for _ in range(ORDER)]
    counts[ORDER - 1] = top
    for n in range(ORDER - 1, 0, -1):
        counts[n - 1] = Counter(g[1:] for g in counts[n])
    model, lower = CharModel(), {"": 1.0 / (alphabet + 1)}
    for n in range(1, ORDER + 1):
        own, total, kinds = counts[n - 1], defaultdict(int), defaultdict(int)
        for g, c in own.items():
            total[g[:-1]] += c
            kinds[g[:-1]] += 1
        n1, n2 = sum(c == 1 for c in own.values()), sum(c == 2 for c in own.values())
        d = min(0.95, max(0.1, n1 / (n1 + 2 * n2) if n1 else 0.5))
        left = {h: d * kinds[h] / total[h] for h in total}
        now = {g: (c - d) / total[g[:-1]] + left[g[:-1]] * lower[g[1:] if n > 1 else ""] for g, c in own.items()}
        model.probs.append(SortedTable.of({g: float(np.log(p)) for g, p in now.items()}))
        if n > 1:
            model.rest.append(SortedTable.of({h: float(np.log(x)) for h, x in left.items()}))
        else:
            model.floor = float(np.log(left.get("", 1.0) * lower[""]))
        lower = now
    return model


@dataclass
class LanguageModel:
    languages: list[str]
    models: list[CharModel]
    temperature: float = 8.0
    worst: np.ndarray = field(default_factory=lambda: np.zeros(0))  # cross-entropy beyond which a text is rejected

    def word_scores(self, words: list[str]) -> np.ndarray:
        """Log probability of each word (rows) under each language (columns)."""
        codes, sizes = pack(words)
        hashes = [gram_hashes(codes, n) for n in range(1, ORDER + 1)]
        ends = np.cumsum(sizes + ORDER - 1) - 1  # of the codes
        at = np.repeat(ends - (ORDER - 1) - sizes + 1, sizes) + np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        # the context of order n at a position is the gram of order n that ends one before it
        contexts = [np.r_[np.uint64(0), h[:-1]][at] for h in hashes[: ORDER - 1]]
        hashes = [h[at] for h in hashes]
        starts = np.cumsum(sizes) - sizes
        return np.stack([np.add.reduceat(m.logp(hashes, contexts), starts) for m in self.models], axis=1)

    def entropies(self, texts: list[str | None], known: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """(cross-entropy for each character by language, letters) of each text; known remembers scores of words."""
        runs = [letter_runs(t) for t in texts]
        if len(known) > REMEMBER:
            known.clear()
        new = list({w for r in runs for w in r if w not in known})
        for k in range(0, len(new), 20_000):
            part = new[k : k + 20_000]
            known.update(zip(part, self.word_scores(part)))
        n = np.array([sum(map(len, r)) + len(r) for r in runs], dtype=np.float64)
        total = np.zeros((len(texts), len(self.languages)))
        for i, r in enumerate(runs):
            if r:
                total[i] = np.array([known[w] for w in r]).sum(axis=0)
        return -total / np.maximum(n, 1)[:, None], n

    def probabilities(self, entropy: np.ndarray) -> np.ndarray:
        x = -self.temperature * (entropy - entropy.min(axis=1, keepdims=True))
        e = np.exp(np.clip(x, -60, 0))
        return e / e.sum(axis=1, keepdims=True)


GRAMS = "lang string, gram string, n long"


def fit(docs: DataFrame, max_docs: int = 1200, calibration: int = 300, holdout: int = 0) -> LanguageModel:
    """Learn from documents outside the held-out fold, at most `max_docs` of each language, and calibrate on others, at most
    `calibration` of each: of a language's documents in the order of their ids' hashes, the shares are the same whatever
    their number. Rows with null text or lang are ignored. Without any, no language
    is learned and every text is `und`."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"))
    known = rows.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.coalesce(fold(F.col("doc_id")) != holdout, F.lit(False)))
    # the first of each language are among the first of its salted parts, so that no task ranks a whole language
    most, each = max_docs + calibration, (max_docs + calibration) // max(calibration, 1)
    hashed = [F.xxhash64("doc_id"), F.col("doc_id")]
    parts = known.select("doc_id", "lang", F.pmod(F.xxhash64("doc_id", F.lit(1)), F.lit(SALTS)).alias("salt"))
    parts = parts.withColumn("k", F.row_number().over(Window.partitionBy("lang", "salt").orderBy(*hashed))).where(F.col("k") <= most)
    chosen = parts.select("doc_id", "lang", F.row_number().over(Window.partitionBy("lang").orderBy(*hashed)).alias("k")).where(F.col("k") <= most)
    chosen = materialize(chosen.groupBy("doc_id", "lang").agg((F.min("k") % each == 0 if calibration else F.lit(False)).alias("calibrate")))
    chosen = F.broadcast(chosen) if chosen.count() <= BROADCAST_ROWS else chosen

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[str, Counter] = defaultdict(Counter)
        for batch in slices(batches):
            for lang, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                for w, n in Counter(letter_runs(text)).items():
                    padded, own = START * (ORDER - 1) + w + END, seen[lang]
                    for i in range(len(w) + 1):
                        own[padded[i : i + ORDER]] += n
        for lang, own in seen.items():
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(own)), pa.array(list(own), pa.string()), pa.array(list(own.values()), pa.int64())], names=["lang", "gram", "n"])

    sample = rows.join(chosen, ["doc_id", "lang"])
    grams = sample.where("not calibrate").select("lang", "text").mapInArrow(count, GRAMS).groupBy("lang", "gram").agg(F.sum("n").alias("n")).toArrow()
    by_lang: dict[str, dict[str, int]] = defaultdict(dict)
    for lang, gram, n in zip(*(grams.column(c).to_pylist() for c in ("lang", "gram", "n"))):
        by_lang[lang][gram] = n
    languages = sorted(by_lang)
    alphabet = len({c for own in by_lang.values() for g in own for c in g})
    model = LanguageModel(languages, [kneser_ney(by_lang[x], alphabet) for x in languages])
    model.worst = np.full(len(languages), np.inf)
    if languages and calibration:
        calibrate(model, sample.where("calibrate").select("lang", "text"))
    return model


def calibrate(model: LanguageModel, sample: DataFrame) -> None:
    """Temperature of least log loss among powers of two, and the cross-entropy that bounds acceptance."""
    names = model.languages

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, np.ndarray] = {}
        for batch in slices(batches):
            entropy, n = model.entropies(batch.column(1).to_pylist(), known)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n), pa.array(list(entropy), pa.list_(pa.float64()))], names=["lang", "n", "entropy"])

    rows = sample.mapInArrow(score, "lang string, n double, entropy array<double>").where("n > 0").toArrow()
    if not rows.num_rows:
        return
    entropy = np.array(rows.column("entropy").to_pylist())
    truth = np.array([names.index(x) if x in names else -1 for x in rows.column("lang").to_pylist()])
    entropy, truth = entropy[truth >= 0], truth[truth >= 0]
    if not len(truth):
        return
    losses = {}
    for t in 2.0 ** np.arange(0, 8):
        model.temperature = float(t)
        losses[float(t)] = -np.log(np.maximum(model.probabilities(entropy)[np.arange(len(truth)), truth], 1e-12)).mean()
    model.temperature = min(losses, key=losses.get)
    for k in range(len(names)):
        own = entropy[truth == k, k]
        if len(own) >= 20:
            model.worst[k] = np.quantile(own, 0.99) + 0.5 * own.std() + 0.25


def identify(df: DataFrame, model: LanguageModel) -> DataFrame:
    """doc_id, held_out, lang_pred, score, rejected and cross-entropy (bits a character), a row for each of df.

    Null text, text without letters, and any text when nothing was learned: `und`, score 0, rejected, null cross-entropy.
    Ties go to the first language by name. A null id is not held out.
    """
    names = model.languages

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, np.ndarray] = {}
        for batch in slices(batches):
            texts = batch.column(1).to_pylist()
            lang, score, reject, bits = [UNKNOWN] * len(texts), np.zeros(len(texts)), np.ones(len(texts), dtype=bool), [None] * len(texts)
            if names:
                entropy, n = model.entropies(texts, known)
                best, p = entropy.argmin(axis=1), model.probabilities(entropy)
                for i in np.nonzero(n)[0].tolist():
                    k = best[i]
                    lang[i], score[i], bits[i] = names[k], p[i, k], float(entropy[i, k] / np.log(2))
                    reject[i] = entropy[i, k] > model.worst[k] or p[i, k] < 0.5
            held = pc.fill_null(pa.array([None if x is None else zlib.crc32(str(x).encode()) % 5 == 0 for x in batch.column(0).to_pylist()], pa.bool_()), False)
            yield pa.RecordBatch.from_arrays([batch.column(0), held, pa.array(lang), pa.array(score), pa.array(reject), pa.array(bits, pa.float64())], names=["doc_id", "held_out", "lang_pred", "score", "rejected", "bits_per_char"])

    rows = df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double, rejected boolean, bits_per_char double")
