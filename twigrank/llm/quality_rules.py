"""Quality rules: lines are judged first, failing ones removed, then documents that lose too much text are rejected."""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame

from twigrank.llm.common import slices

SYMBOLS = "#*$%&|<>"
SPACES = " \t\n\v\f\r"
WINDOW = 8


@dataclass(frozen=True)
class LineRules:
    """A line fails if it is boilerplate, navigation, symbol noise, shouting, stutter or a fragment without an end mark."""

    boilerplate: str = r"(?i)licensed under|license, version|all rights reserved|privacy policy|terms of (use|service)|cookie policy|enable javascript|subscribe to our|lorem ipsum"
    separators: int = 3  # bars, bullets and guillemets of a navigation line
    symbol_share: float = 0.2  # symbols for each word
    shout_share: float = 0.3  # words that end in !!
    distinct_share: float = 0.25  # distinct words of a line of at least 8
    fragment_words: int = 3  # shorter lines must have an end mark
    end_mark: str = r"""[.!?…。！？:;"'”’»)\]]$"""
    max_lost: float = 0.5  # share of a document's words in removed lines

    def failing(self) -> "LineTest":
        return LineTest(self)


class LineTest:
    def __init__(self, rules: LineRules):
        self.rules, self.boiler, self.end = rules, re.compile(rules.boilerplate), re.compile(rules.end_mark)

    def __call__(self, line: str, words: list[bytes]) -> str:
        """The name of the first rule that the line breaks, or an empty string."""
        r, n = self.rules, len(words)
        if self.boiler.search(line):
            return "boilerplate"
        if line.count("|") + line.count("»") + line.count("•") >= r.separators:
            return "navigation"
        if sum(map(line.count, SYMBOLS)) > r.symbol_share * n:
            return "symbols"
        if "!!" in line and sum(w.endswith(b"!!") for w in words) > r.shout_share * n:
            return "shouting"
        if n >= WINDOW and len(set(words)) < r.distinct_share * n:
            return "stutter"
        if n < r.fragment_words and not self.end.search(line.strip(SPACES)):
            return "fragment"
        return ""


def repeated_words(words: list[list[bytes]], window: int = WINDOW) -> np.ndarray:
    """Of each text, the words inside windows that stand at two or more places of the text. Exact: windows are ranked by
    doubling (2, 4, 8 words) within all texts of the batch, never hashed."""
    sizes = np.array([len(w) for w in words], dtype=np.int64)
    out = np.zeros(len(words), dtype=np.int64)
    if not sizes.sum():
        return out
    doc = np.repeat(np.arange(len(words)), sizes)
    flat = np.empty(len(doc), dtype=object)
    flat[:] = [x for w in words for x in w]
    rank = pd.factorize(flat)[0].astype(np.int64)
    width = 1
    while width < window:  # rank of the 2*width words at i, where they are in one text
        if len(rank) <= width:
            return out
        joined = rank[:-width] * (int(rank.max()) + 1) + rank[width:]
        rank = np.unique(joined, return_inverse=True)[1].astype(np.int64)
        width *= 2
    at = np.nonzero(doc[: len(rank)] == doc[width - 1 : width - 1 + len(rank)])[0]
    if not len(at):
        return out
    key = doc[at] * (int(rank.max()) + 1) + rank[at]
    _, inverse, count = np.unique(key, return_inverse=True, return_counts=True)
    hit = at[count[inverse] > 1]
    mark = np.zeros(len(doc) + 1, dtype=np.int64)
    np.add.at(mark, hit, 1)
    np.add.at(mark, hit + width, -1)
    return np.bincount(doc, weights=np.cumsum(mark[:-1]) > 0, minlength=len(words)).astype(np.int64)


SCHEMA = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, lost_words long, kept boolean, cleaned string"


def judge_quality(df: DataFrame, rules: LineRules = LineRules(), id_col: str = "doc_id", text_col: str = "text", with_text: bool = False) -> DataFrame:
    """One row per row of df: base measures, words in removed lines, verdict and (with_text) the text of the lines that stay.

    Null and empty texts have no words, fail the base test and are not kept; their cleaned text is empty. A null id is
    passed on. Repeated rows are judged each. Other columns of df are not read.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fails = rules.failing()
        for batch in slices(batches):
            ids, texts = batch.column(0), [t or "" for t in batch.column(1).to_pylist()]
            words = [t.encode().split() for t in texts]  # bytes split at ASCII white space only
            again = repeated_words(words)
            cols: list[list] = [[] for _ in range(8)]
            for text, own, n_again in zip(texts, words, again.tolist()):
                n, lost, dup, seen, stay = len(own), 0, 0, set(), []
                for line in text.split("\n"):
                    if here := line.encode().split():
                        dup += line in seen
                        seen.add(line)
                        if fails(line, here):
                            lost += len(here)
                        elif with_text:
                            stay.append(line)
                    elif with_text:
                        stay.append(line)
                bad = n < 20 or 100 * n_again > 30 * n
                row = (n, len(text) - sum(map(text.count, SPACES)), sum(map(text.count, SYMBOLS)), dup, bad, lost, not bad and lost <= rules.max_lost * n, "\n".join(stay) if with_text else None)
                for col, x in zip(cols, row):
                    col.append(x)
            long = [pa.array(c, pa.int64()) for c in cols[:4]]
            yield pa.RecordBatch.from_arrays(
                [ids, *long, pa.array(again), pa.array(cols[4], pa.bool_()), pa.array(cols[5], pa.int64()), pa.array(cols[6], pa.bool_()), pa.array(cols[7], pa.string())],
                names=[x.split()[0] for x in SCHEMA.split(", ")],
            )

    out = df.select(df[id_col].cast("long").alias("doc_id"), df[text_col].cast("string").alias("text")).mapInArrow(run, SCHEMA)
    return out if with_text else out.drop("cleaned")
