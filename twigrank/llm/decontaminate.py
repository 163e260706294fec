"""Benchmark decontamination by a positional inverted index, sharded by document.

`build_index` stores postings (term, position) of each document for the terms of the benchmark, leaving out positions that
cannot take part in a match since their run of benchmark terms is shorter than the shortest window. `search` gathers a
shard's postings into term order and resolves every window at once: offset-adjusted lists are intersected from the rarest
term of the window on, by document frequency over the whole corpus, to exact phrase matches; with a slack, terms may stand
a few words away from their place (proximity matches).
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from twigrank.llm.common import materialize, slices, without

WINDOW = 10
#: Characters of benchmark text in a part: its windows (50 bytes a word at most) go to every executor by broadcast.
BENCHMARK_CHARS = 4_000_000

#: Bytes of a word stay (A-Z in lower case), all others become spaces: fixed by the operator's definition of a word.
TABLE = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))


def words_of(text: str | None) -> list[bytes]:
    return text.encode().translate(TABLE).split() if text else []


@dataclass
class Windows:
    """All windows of all items: rows of term ids (padded with -1), the item of each and its number of words."""

    vocabulary: dict[bytes, int]
    terms: np.ndarray
    item: np.ndarray
    size: np.ndarray
    items: list[int]

    @classmethod
    def of(cls, items: list[tuple[int, str | None]], width: int = WINDOW) -> "Windows":
        vocabulary: dict[bytes, int] = {}
        rows, owner, sizes = [], [], []
        names = sorted({i for i, _ in items if i is not None})
        place = {x: k for k, x in enumerate(names)}
        for item, text in items:
            ids = [vocabulary.setdefault(w, len(vocabulary)) for w in words_of(text)]
            if item is None or not ids:
                continue
            for at in range(max(1, len(ids) - width + 1)):
                own = ids[at : at + width]
                rows.append(own + [-1] * (width - len(own)))
                owner.append(place[item])
                sizes.append(len(own))
        if not rows:
            return cls(vocabulary, np.zeros((0, width), dtype=np.int64), np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64), names)
        table = np.unique(np.c_[np.array(rows, dtype=np.int32), np.array(owner, dtype=np.int32), np.array(sizes, dtype=np.int32)], axis=0)
        return cls(vocabulary, table[:, :width], table[:, width], table[:, width + 1], names)


def collect_items(benchmark: DataFrame) -> Iterator[list[tuple[int, str | None]]]:
    """The benchmark in parts of bounded size, of whole items' rows; no part for an empty benchmark."""
    part, size = [], 0
    for row in benchmark.select(F.col("item_id").cast("long"), F.col("text").cast("string")).orderBy("item_id").toLocalIterator():
        part.append((row[0], row[1]))
        size += len(row[1] or "")
        if size >= BENCHMARK_CHARS:
            yield part
            part, size = [], 0
    if part:
        yield part


def long_runs(known: np.ndarray, least: int) -> np.ndarray:
    """Marks of known positions in unbroken runs with `least` of them or more."""
    at = np.nonzero(known)[0]
    if not len(at):
        return known
    edge = np.r_[0, np.nonzero(np.diff(at) > 1)[0] + 1, len(at)]
    size = np.diff(edge)
    out = np.zeros(len(known), dtype=bool)
    out[at] = np.repeat(size >= least, size)
    return out


def build_index(docs: DataFrame, windows: Windows, slack: int = 0) -> DataFrame:
    """doc_id, tag (two halves of the text's hash), n_words, terms, positions (sorted by term, then position): the postings
    of each document. With slack, terms of a window may share a position, so no run is too short."""
    least = 1 if slack else int(windows.size.min()) if len(windows.size) else 1 << 30
    shared = docs.sparkSession.sparkContext.broadcast(windows.vocabulary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        get = shared.value.get
        for batch in slices(batches):
            n_words, terms, places, low, high = [], [], [], [], []
            for text in batch.column(1).to_pylist():
                digest = xxhash.xxh3_128_digest((text or "").encode())
                low.append(int.from_bytes(digest[:8], "big", signed=True))
                high.append(int.from_bytes(digest[8:], "big", signed=True))
                words = words_of(text)
                n_words.append(len(words))
                ids = np.fromiter((get(w, -1) for w in words), dtype=np.int32, count=len(words))
                at = np.nonzero(long_runs(ids >= 0, least))[0]
                order = np.lexsort((at, ids[at]))
                terms.append(ids[at][order])
                places.append(at[order].astype(np.int32))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(low, pa.int64()), pa.array(high, pa.int64()), pa.array(n_words, pa.int64()), pa.array(terms, pa.list_(pa.int32())), pa.array(places, pa.list_(pa.int32()))],
                names=["doc_id", "tag_low", "tag_high", "n_words", "terms", "positions"],
            )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, tag_low long, tag_high long, n_words long, terms array<int>, positions array<int>")


def document_frequencies(index: DataFrame, n_terms: int) -> np.ndarray:
    """Of each term of the benchmark, the documents whose stored postings have it: as many rows as the benchmark has terms."""
    rows = index.where("size(terms) > 0").select(F.explode(F.array_distinct("terms")).alias("t")).groupBy("t").count().toArrow()
    out = np.zeros(n_terms, dtype=np.int64)
    out[np.asarray(rows.column("t"))] = np.asarray(rows.column("count"))
    return out


def match(terms: np.ndarray, positions: np.ndarray, windows: Windows, order: np.ndarray, slack: int) -> tuple[np.ndarray, np.ndarray]:
    """(window, start) of all matches in postings of one position space. order: offsets of each window, rarest term first."""
    keys = np.sort(terms.astype(np.int64) << np.int64(40) | positions)
    first = np.take_along_axis(windows.terms, order, axis=1)
    lo = np.searchsorted(keys, first[:, 0] << np.int64(40))
    hi = np.searchsorted(keys, (first[:, 0] + 1) << np.int64(40))
    size = hi - lo
    w = np.repeat(np.arange(len(size)), size)
    at = np.repeat(lo - np.cumsum(size) + size, size) + np.arange(size.sum())
    start = (keys[at] & ((1 << 40) - 1)) - order[w, 0]
    for k in range(1, windows.terms.shape[1]):
        if not len(w):
            break
        want = first[w, k]
        aim = (want << np.int64(40)) + start + order[w, k]
        found = np.searchsorted(keys, aim - slack)
        inside = np.minimum(found, len(keys) - 1)
        good = (want < 0) | ((found < len(keys)) & (keys[inside] >= aim - slack) & (keys[inside] <= aim + slack))
        w, start = w[good], start[good]
    return w, start


FOUND = "doc_id long, tag_low long, tag_high long, items array<long>, spans array<struct<item:long,lo:int,hi:int>>"


def search(index: DataFrame, windows: Windows, frequency: np.ndarray, slack: int = 0) -> DataFrame:
    """doc_id, tag, items (with matching windows) and spans of the matches, for each row of the index that has a match.

    A match starts where its rarest term says (the first of them on ties); with slack the other terms may stand up to so
    many words from their place. Its span is that of the window's own length from there, inside the document.
    """
    # offsets of each window by rising frequency of their terms; padding goes last
    rank = np.where(windows.terms >= 0, frequency[np.maximum(windows.terms, 0)] if len(frequency) else 0, 1 << 62)
    shared = index.sparkSession.sparkContext.broadcast((windows, np.argsort(rank, axis=1, kind="stable").astype(np.int32)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        windows, order = shared.value
        for batch in slices(batches, 4096):
            n = batch.num_rows
            words = np.asarray(batch.column("n_words"))
            base = np.r_[0, np.cumsum(words + WINDOW + 2 * slack)]  # documents stand apart in one position space
            lists, places = batch.column("terms"), batch.column("positions")
            doc = np.repeat(np.arange(n), np.asarray(lists.value_lengths()))
            terms, at = np.asarray(lists.flatten()).astype(np.int64), np.asarray(places.flatten()).astype(np.int64) + base[doc]
            if not len(terms) or not len(windows.terms):
                continue
            w, start = match(terms, at, windows, order, slack)
            if not len(w):
                continue
            d = np.searchsorted(base, start + slack, side="right") - 1
            low = np.maximum(start - base[d], 0)
            high = np.minimum(start - base[d] + windows.size[w], words[d])
            spans: dict[int, list] = {}
            for x, i, lo, hi in np.unique(np.c_[d, windows.item[w], low, high], axis=0).tolist():
                own = spans.setdefault(x, [])
                if own and own[-1]["item"] == windows.items[i] and lo <= own[-1]["hi"]:
                    own[-1]["hi"] = max(own[-1]["hi"], hi)
                else:
                    own.append({"item": windows.items[i], "lo": lo, "hi": hi})
            rows = batch.select(["doc_id", "tag_low", "tag_high"]).take(pa.array(list(spans), pa.int64()))
            items = [sorted({x["item"] for x in own}) for own in spans.values()]
            kind = pa.list_(pa.struct([("item", pa.int64()), ("lo", pa.int32()), ("hi", pa.int32())]))
            yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(items, pa.list_(pa.int64())), pa.array(list(spans.values()), kind)], names=["doc_id", "tag_low", "tag_high", "items", "spans"])

    return index.mapInArrow(run, FOUND)


def items_digest(items: list[int]) -> str:
    return hashlib.sha256(",".join(sorted(map(str, items))).encode()).hexdigest()


def covered(spans: str) -> Column:
    """Words inside any of the spans."""
    by_place = F.array_sort(spans, lambda x, y: F.when(x["lo"] != y["lo"], x["lo"] - y["lo"]).otherwise(x["hi"] - y["hi"]))
    return F.aggregate(
        by_place,
        F.struct(F.lit(0).alias("end"), F.lit(0).alias("n")),
        lambda s, x: F.struct(F.greatest(s["end"], x["hi"]).alias("end"), (s["n"] + F.greatest(F.lit(0), x["hi"] - F.greatest(s["end"], x["lo"]))).alias("n")),
        lambda s: s["n"].cast("long"),
    )


def decontaminate(docs: DataFrame, benchmark: DataFrame, slack: int = 0) -> DataFrame:
    """doc_id, n_words, n_hit (words inside matches), items, spans, contaminated, a row for each row of docs.

    Null and empty texts have no words and no hits. Benchmark rows with a null item_id or without words are ignored; rows
    that share an item_id are one item with the windows of each. An empty benchmark finds nothing. Other columns are not
    read. The benchmark is searched part by part, and what the parts find in documents of one id and text is merged; rows
    that are equal in both have equal results. With slack, proximity matches count too.
    """
    found, every = None, None
    for part in [*collect_items(benchmark)] or [[]]:
        windows = Windows.of(part)
        index = materialize(build_index(docs, windows, slack))
        every = every or index.select("doc_id", "tag_low", "tag_high", "n_words")
        if len(windows.terms):
            frequency = document_frequencies(index, len(windows.vocabulary))
            # equal rows find the same
            one = search(index, windows, frequency, slack).dropDuplicates(["doc_id", "tag_low", "tag_high"])
            found = found.unionByName(one) if found else one
    if found is None:
        found = docs.sparkSession.createDataFrame([], FOUND)
    merged = found.groupBy(F.col("doc_id").alias("_d"), F.col("tag_low").alias("_l"), F.col("tag_high").alias("_h")).agg(
        F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"), F.flatten(F.collect_list("spans")).alias("spans")
    )  # as many rows in a group as the benchmark has parts
    same = F.col("doc_id").eqNullSafe(F.col("_d")) & (F.col("tag_low") == F.col("_l")) & (F.col("tag_high") == F.col("_h"))
    nothing = F.array().cast("array<long>"), F.array().cast("array<struct<item:long,lo:int,hi:int>>")
    out = every.join(merged, same, "left")
    out = out.select("doc_id", "n_words", F.coalesce("items", nothing[0]).alias("items"), F.coalesce("spans", nothing[1]).alias("spans"))
    out = out.select("doc_id", "n_words", covered("spans").alias("n_hit"), "items", "spans")
    return out.withColumn("contaminated", F.col("n_hit") > 0)


def keep_clean(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of docs (all columns) without any exact match. Rows that share a doc_id go together if one has a match; a
    row with a null doc_id stays only if no row with a null doc_id has a match."""
    bad = decontaminate(docs, benchmark).where("contaminated").select("doc_id")
    return without(docs, "doc_id", materialize(bad))
