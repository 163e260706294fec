"""Token-ID output in Simple-8b words.

A 64-bit word has a selector in its top four bits and as many ids as fit at the selector's width below. Values beyond 60
bits are escapes: selector 15 holds an index into a list of raw values. Ids go into blocks of whole documents; a block
knows the place of its first id in its part, its number of ids and the ids of each of its documents, so that any block is
decoded on its own, all words at once. Blocks are rows of Parquet files, in ascending order of doc_id over all parts.
"""

from __future__ import annotations

import os
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from itertools import pairwise

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from twigrank.llm.common import by_bytes, shared_dir, slices

#: Ids in a word and their bits for each selector; fixed values of the format. 0 and 1 are runs of zeros, 15 an escape.
COUNTS = np.array([240, 120, 60, 30, 20, 15, 12, 10, 8, 7, 6, 5, 4, 3, 2, 1], dtype=np.int64)
BITS = np.array([0, 0, 1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 15, 20, 30, 60], dtype=np.int64)
ONE, ESCAPE = 14, 15  # selectors of one id: 14 holds two of 30 bits; a lone id of up to 60 bits has selector 15, bit 59 set
RAW_LIMIT = 1 << 59


SMALL = np.array([x.bit_length() for x in range(1 << 12)], dtype=np.int8)


def bit_lengths(values: np.ndarray) -> np.ndarray:
    if int(values.max()) < 1 << 24:
        high = values >> np.uint64(12)
        return np.where(high > 0, SMALL[high.astype(np.int64)] + np.int8(12), SMALL[(values & np.uint64(4095)).astype(np.int64)])
    bits, rest = np.zeros(len(values), dtype=np.int8), values.copy()
    for s in (32, 16, 8, 4, 2, 1):
        high = rest >> np.uint64(s) > 0
        bits += np.where(high, np.int8(s), np.int8(0))
        rest = np.where(high, rest >> np.uint64(s), rest)
    return bits + (rest > 0)


def encode(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(words, escaped values) of an array of unsigned integers of up to 64 bits."""
    values = np.ascontiguousarray(values, dtype=np.uint64)
    n = len(values)
    if not n:
        return np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.uint64)
    bits = bit_lengths(values)
    # the widest selector that fits at each place: running maxima of bits over 1, 2, .. ids, ended where none fits any more
    choice = np.full(n, 15, dtype=np.int8)
    reach = bits.copy()
    by_count = {int(c): k for k, c in enumerate(COUNTS)}
    for m in range(2, 241):
        if len(reach) <= 1:
            break
        reach = np.maximum(reach[:-1], bits[m - 1 :])
        k = by_count.get(m)
        widest = BITS[max(k for c, k in by_count.items() if c >= m)]  # of the selectors still to come
        if k is not None:
            head = choice[: len(reach)]
            np.minimum(head, np.where(reach <= np.int8(BITS[k]), np.int8(k), np.int8(15)), out=head)
        if not (reach <= widest).any():
            break
    steps, choices = COUNTS[choice].tolist(), choice
    starts, at = [], 0
    while at < n:
        starts.append(at)
        at += steps[at]
    starts_at = np.array(starts, dtype=np.int64)
    own = choices[starts_at].astype(np.int64)
    words = own.astype(np.uint64) << np.uint64(60)
    for k in np.unique(own).tolist():
        if k < 2:
            continue
        rows = np.nonzero(own == k)[0]
        block = values[starts_at[rows][:, None] + np.arange(COUNTS[k])]
        if k == 15:
            continue
        shift = (np.arange(COUNTS[k]) * BITS[k]).astype(np.uint64)
        words[rows] |= np.bitwise_or.reduce(block << shift, axis=1)
    lone = np.nonzero(own == 15)[0]
    value = values[starts_at[lone]]
    far = value >= np.uint64(RAW_LIMIT)
    words[lone[~far]] |= value[~far]
    words[lone[far]] |= np.uint64(RAW_LIMIT) | np.arange(far.sum(), dtype=np.uint64)
    return words, value[far]


def decode(words: np.ndarray, escapes: np.ndarray) -> np.ndarray:
    """All values of the words, selector by selector."""
    selector = (words >> np.uint64(60)).astype(np.int64)
    sizes = COUNTS[selector]
    starts = np.cumsum(sizes) - sizes
    out = np.zeros(int(sizes.sum()), dtype=np.uint64)
    for k in np.unique(selector).tolist():
        if k < 2:
            continue
        rows = np.nonzero(selector == k)[0]
        if k == 15:
            own = words[rows] & np.uint64((1 << 60) - 1)
            far = own >= np.uint64(RAW_LIMIT)
            if far.any():
                own[far] = escapes[(own[far] - np.uint64(RAW_LIMIT)).astype(np.int64)]
            out[starts[rows]] = own
            continue
        shift = (np.arange(COUNTS[k]) * BITS[k]).astype(np.uint64)
        part = (words[rows][:, None] >> shift) & np.uint64((1 << int(BITS[k])) - 1)
        out[starts[rows][:, None] + np.arange(COUNTS[k])] = part
    return out


#: White space that the vocabulary's splitter knows besides the ASCII one, and characters that only Python counts as such.
ODD_SPACE = r"[\x1c-\x1f\x{85}\x{a0}\x{1680}\x{2000}-\x{200a}\x{2028}\x{2029}\x{202f}\x{205f}\x{3000}]"
#: Other white space than single spaces and single line ends between words.
UNEVEN = r"^[ \n]|[ \n]$|  | \n|\n |\n\n|[\t\r\x0b\x0c]"
LEARN_BYTES = 1 << 14  # of distinct words that the library gets as one text


class Encoder:
    """Token ids of whole texts by the tokenizers library, which sees each distinct word of a batch once.

    The byte-level splitter never lets a pre-token run from a non-space character into white space, and its look-ahead
    stays within a run of white space; a text cut before each single space or line end therefore has the ids of its
    segments, one after another. Distinct segments go to the library side by side in long texts for the same reason; each id
    stands for a fixed number of bytes, so the ids are told apart by the segments' lengths. Texts with other white space
    go to the library whole. Nothing is remembered between batches.
    """

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # the tasks of an executor share its cores already
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        vocabulary = self.tokenizer.get_vocab(with_added_tokens=False)
        added = self.tokenizer.get_added_tokens_decoder()
        last = max([*vocabulary.values(), *added])
        self.dtype = np.dtype(np.uint16 if last < 1 << 16 else np.uint32)
        self.n_bytes = np.zeros(last + 1, dtype=np.int64)  # of the text that an id stands for; a vocabulary character is a byte
        self.n_bytes[list(vocabulary.values())] = [len(x) for x in vocabulary]
        for k, token in added.items():
            self.n_bytes[k] = len(token.content.encode())

    def library(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, dtype=self.dtype) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def words(self, words: pa.Array) -> tuple[list[np.ndarray], np.ndarray]:
        """(ids in pieces, number of ids of each word) of words as they stand after a space, or after the line end that they
        begin with; an empty word has none."""
        sizes = np.zeros(len(words), dtype=np.int32)
        full = np.asarray(pc.greater(pc.binary_length(words), 0))
        segments = words.filter(pa.array(full))
        before = pc.if_else(pc.starts_with(segments, "\n"), "", " ")
        segments = pc.binary_join_element_wise(before, segments, "")
        if not len(segments):
            return [], sizes
        ends, data = np.frombuffer(segments.buffers()[1], dtype=np.int32)[: len(segments) + 1].astype(np.int64), memoryview(segments.buffers()[2])
        cuts = np.unique(np.r_[np.searchsorted(ends, np.arange(0, ends[-1], LEARN_BYTES)), len(segments)])
        pieces, counts = [], []
        for k in range(0, len(cuts) - 1, 16):
            spans = list(pairwise(cuts[k : k + 17].tolist()))
            found = self.library([bytes(data[ends[lo] : ends[hi]]).decode() for lo, hi in spans])
            for (lo, hi), ids in zip(spans, found):
                reach, wanted = np.cumsum(self.n_bytes[ids]), ends[lo + 1 : hi + 1] - ends[lo]
                last = np.searchsorted(reach, wanted)
                if not len(ids) or reach[-1] != wanted[-1] or (reach[last] != wanted).any():
                    raise ValueError("ids of the vocabulary do not stand for fixed numbers of bytes")
                pieces.append(ids)
                counts.append(np.diff(last, prepend=-1))
        sizes[full] = np.concatenate(counts)
        return pieces, sizes

    def encode_column(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts one after another, number of ids of each); null texts are empty."""
        texts = texts.fill_null("")
        uneven = np.asarray(pc.match_substring_regex(texts, f"{UNEVEN}|{ODD_SPACE}"))
        special = np.nonzero(uneven)[0].tolist()
        if special:
            own = dict(zip(special, self.library([texts[k].as_py() for k in special])))
            texts = pc.if_else(pa.array(uneven), "", texts)
        # words as they stand between single spaces, and a line's first word with its line end
        split = pc.split_pattern(pc.replace_substring(texts, "\n", " \n"), " ")
        offsets = np.asarray(split.offsets) - split.offsets[0].as_py()
        coded = split.flatten().dictionary_encode()
        codes, distinct = np.array(coded.indices), coded.dictionary
        del split, texts, coded
        # a text's first word has no space before it: a code of its own
        heads = np.unique(codes[offsets[:-1]])
        codes[offsets[:-1]] = len(distinct) + np.searchsorted(heads, codes[offsets[:-1]])
        pieces, n_ids = self.words(distinct)
        first = self.library(distinct.take(pa.array(heads)).to_pylist())
        pool = np.concatenate([np.zeros(0, dtype=self.dtype), *pieces, *first])
        n_ids = np.r_[n_ids, np.array([len(x) for x in first], dtype=np.int32)]
        starts, sizes = np.cumsum(n_ids, dtype=np.int32) - n_ids, n_ids[codes]
        reach = np.cumsum(sizes, dtype=np.int32)  # a batch has far fewer ids than 2^31
        place = np.repeat(starts[codes] - (reach - sizes), sizes)
        place += np.arange(len(place), dtype=np.int32)
        ids, reach = pool[place], np.r_[0, reach].astype(np.int64)
        n = np.diff(reach[offsets])
        if special:
            parts = np.split(ids, np.cumsum(n)[:-1])
            for k in special:
                parts[k], n[k] = own[k], len(own[k])
            ids = np.concatenate(parts)
        return ids, n

    def encode(self, texts: list[str | None]) -> list[np.ndarray]:
        """The ids of each text."""
        if not texts:
            return []
        ids, n = self.encode_column(pa.array(texts, pa.string()))
        return np.split(ids, np.cumsum(n)[:-1])


@lru_cache(maxsize=2)
def encoder_of(path: str) -> Encoder:
    """The encoder of this process, for all tasks of a Python worker; its vocabulary is read once."""
    return Encoder(path)


@dataclass(frozen=True)
class TokenFormat:
    vocabulary: str  # path of a tokenizers file; every executor has it
    end_id: int = 0
    block_ids: int = 1 << 16
    parts: int | None = None  # None: one for each shuffle partition


BLOCKS = "part int, block int, first_id long, n_ids long, doc_ids array<long>, doc_sizes array<long>, words binary, escapes binary"


def write_tokens(df: DataFrame, path: str, form: TokenFormat) -> None:
    """Write the ids of all documents (null text: only the end id) in ascending order of doc_id, nulls first, rows that
    share an id by a hash of their text. Other columns of df are not read. An empty table writes files without blocks."""
    spark = df.sparkSession
    parts = form.parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    rows = df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, part, number, first = encoder_of(form.vocabulary), TaskContext.get().partitionId(), 0, 0
        docs: list[int | None] = []
        sizes: list[int] = []
        held_ids: list[np.ndarray] = []
        held = 0

        def block() -> pa.RecordBatch:
            nonlocal number, first, docs, sizes, held_ids, held
            words, far = encode(np.concatenate(held_ids))
            cols = [part, number, first, held, docs, sizes, words.astype("<u8").tobytes(), far.astype("<u8").tobytes()]
            kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.binary(), pa.binary()]
            out = pa.RecordBatch.from_arrays([pa.array([c], k) for c, k in zip(cols, kinds)], names=[x.split()[0] for x in BLOCKS.split(", ")])
            number, first, docs, sizes, held_ids, held = number + 1, first + held, [], [], [], 0
            return out

        for batch in by_bytes(batches, "text"):
            ids, n = encoder.encode_column(batch.column(1))
            ids = np.insert(ids, np.cumsum(n), form.end_id)
            n, at, begin = n + 1, 0, 0
            own, reach = batch.column(0).to_pylist(), np.cumsum(n)
            while at < len(own):  # whole documents up to the block's size
                end = min(len(own), int(np.searchsorted(reach, begin + form.block_ids - held)) + 1)
                docs += own[at:end]
                sizes += n[at:end].tolist()
                held_ids.append(ids[begin : reach[end - 1]])
                held, at, begin = held + int(reach[end - 1]) - begin, end, int(reach[end - 1])
                if held >= form.block_ids:
                    yield block()
        if docs:
            yield block()

    ordered = rows.repartitionByRange(parts, F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), F.xxhash64("text"))
    ordered.mapInArrow(run, BLOCKS).write.option("compression", "uncompressed").parquet(path)


def read_tokens(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start (ids of all documents before it), n_tokens and ids_crc32 of each document, decoded from the files."""
    blocks = spark.read.schema(BLOCKS).parquet(path)
    # a row for each part, and there are no more parts than shuffle partitions
    totals = blocks.groupBy("part").agg(F.sum("n_ids").alias("n"))
    before = F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    offsets = totals.select("part", F.coalesce(before, F.lit(0)).alias("offset"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, 1):
            row = {name: batch.column(name)[0].as_py() for name in batch.schema.names}
            ids = decode(np.frombuffer(row["words"], dtype="<u8"), np.frombuffer(row["escapes"], dtype="<u8")).astype("<u4")
            if len(ids) != row["n_ids"]:
                raise ValueError(f"part {row['part']}, block {row['block']}: {len(ids)} ids, not {row['n_ids']}")
            sizes = np.array(row["doc_sizes"], dtype=np.int64)
            ends = np.cumsum(sizes)
            view = memoryview(ids).cast("B")
            crc = [zlib.crc32(view[4 * (e - n) : 4 * e]) for n, e in zip(sizes.tolist(), ends.tolist())]
            start = row["offset"] + row["first_id"] + ends - sizes
            yield pa.RecordBatch.from_arrays([pa.array(row["doc_ids"], pa.int64()), pa.array(start), pa.array(sizes), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return blocks.join(F.broadcast(offsets), "part").mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def tokens_in_shared_folder(df: DataFrame, form: TokenFormat) -> str:
    """Write to a new folder beside the checkpoints; returns its path."""
    path = f"{shared_dir(df.sparkSession)}/tokens-{uuid.uuid4().hex}"
    write_tokens(df, path, form)
    return path
