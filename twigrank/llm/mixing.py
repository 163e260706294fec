"""Mixing sources to target weights.

Each source's words are packed, document after document, into blocks of fixed length. The output has slots of one block
each, cut into shards; every shard draws its number of slots of each source from the multinomial law of the target weights that
are left. The draws go down a tree: the slots of a range of shards are split between its halves by a multinomial draw, of
which no source gives more than it has left, so that totals come out exact at any size; free draws would leave small
sources far from their target. Any task can walk down to its own shards, since a node's draw has a seed of its own. The
slots of a source are numbered through, and number k is block perm(k mod blocks) of pass k div blocks, where every pass has
a pseudorandom permutation of its own; slots then join blocks by index.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from twigrank.llm.common import materialize, slices

#: Each source's documents are packed in this many sub-sequences side by side, so that no task packs a whole source.
LANES = 256
#: Sources that a plan takes; their sizes and targets are summed up on the driver.
MAX_SOURCES = 100_000
MOST = 3  # times its size that a source is taken at most


@dataclass(frozen=True)
class MixPlan:
    block_words: int = 64
    shard_slots: int = 4096
    super_shards: int = 16  # shards that one step of a task draws
    seed: int = 20240607
    weights: tuple[float, ...] = (1, 2, 3)  # of sources by code point, null last, repeating


def targets(sizes: list[int], weights: list[float], most: float = MOST) -> list[float]:
    """Shares of the total by weight; none above `most` times its size, the excess shared again by weight."""
    out, total, open_ = [0.0] * len(sizes), float(sum(sizes)), [i for i in range(len(sizes)) if sizes[i]]
    while open_:
        share = total / sum(weights[i] for i in open_)
        full = [i for i in open_ if share * weights[i] > most * sizes[i]]
        for i in full or open_:
            out[i] = float(most * sizes[i]) if full else share * weights[i]
        if not full:
            break
        total -= sum(out[i] for i in full)
        open_ = [i for i in open_ if i not in full]
    return out


def permuted(x: np.ndarray, n: int, seed: int, rounds: int = 24) -> np.ndarray:
    """Places of the indexes x under a pseudorandom permutation of range(n): swap-or-not rounds, for any n."""
    x = x.astype(np.uint64)
    rng = np.random.Generator(np.random.Philox(seed))
    keys = rng.integers(0, 1 << 62, size=(rounds, 2), dtype=np.int64).astype(np.uint64)
    for key, salt in keys:
        partner = (key % np.uint64(n) + np.uint64(n) - x) % np.uint64(n)
        h = (np.maximum(x, partner) ^ salt) * np.uint64(0x9E3779B97F4A7C15)
        h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
        x = np.where((h >> np.uint64(63)) > 0, partner, x)
    return x.astype(np.int64)


def word_counts(df: DataFrame, text_col: str = "text", source_col: str = "source", id_col: str = "doc_id") -> DataFrame:
    """doc_id, source, size (words; null: 0) and a hash of the text that orders rows of one id."""
    import xxhash

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            texts = [(t or "").encode() for t in batch.column(2).to_pylist()]
            size = pa.array([len(t.split()) for t in texts], pa.int64())
            tag = pa.array([xxhash.xxh3_64_intdigest(t) >> 1 for t in texts], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), size, tag], names=["doc_id", "source", "size", "tag"])

    rows = df.select(df[id_col].cast("long").alias("doc_id"), df[source_col].cast("string").alias("source"), df[text_col].cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, source string, size long, tag long")


def plan_sources(counts: DataFrame, plan: MixPlan) -> DataFrame:
    """source, weight, source_size and target of each source, on the driver: more than MAX_SOURCES sources raise.

    Sorted by code point, null last, which also is the order of their UTF-8 bytes."""
    rows = counts.groupBy("source").agg(F.sum("size").alias("n")).limit(MAX_SOURCES + 1).collect()
    if len(rows) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources")
    rows = sorted(rows, key=lambda r: (r["source"] is None, (r["source"] or "").encode()))
    sizes = [r["n"] for r in rows]
    weights = [plan.weights[i % len(plan.weights)] for i in range(len(rows))]
    wanted = targets(sizes, weights)
    blocks = [-(-n // plan.block_words) for n in sizes]
    table = [(k, r["source"], float(w), int(n), float(t), int(b), min(MOST * b, round(t / n * b)) if n else 0) for k, (r, w, n, t, b) in enumerate(zip(rows, weights, sizes, wanted, blocks))]
    schema = "k int, source string, weight double, source_size long, target double, n_blocks long, n_slots long"
    return counts.sparkSession.createDataFrame(table, schema)


def draw(rng: np.random.Generator, left: np.ndarray, span: int) -> np.ndarray:
    """Slots of each source in the next `span` slots: multinomial by what is left; what a source lacks is drawn again from
    the others."""
    if int(left.sum()) <= span:
        return left.copy()
    own, wanted = np.zeros_like(left), span
    while wanted:
        rest = left - own
        own = np.minimum(left, own + rng.multinomial(wanted, rest / rest.sum()))
        wanted = span - int(own.sum())
    return own


def shard_range(plan: MixPlan, slots: np.ndarray, lo: int, hi: int) -> tuple[np.ndarray, np.ndarray]:
    """(slots of each source in shards lo to hi - 1, slots of each source before them), where hi - lo is a power of two and
    divides lo: down the tree of halves, whose nodes draw from seeds of their own."""
    own, before, at = slots.copy(), np.zeros_like(slots), 0
    total = -(-int(slots.sum()) // plan.shard_slots)
    size = 1 << max(hi - lo, total - 1, 1).bit_length()
    if hi > size:
        raise ValueError(f"there are {total} shards only")
    while size > hi - lo:
        size //= 2
        rng = np.random.Generator(np.random.Philox(key=[plan.seed, size]).jumped(at // size + 1))
        left = draw(rng, own, size * plan.shard_slots)
        if lo >= at + size:
            own, before, at = own - left, before + left, at + size
        else:
            own = left
    return own, before


def draw_slots(sources: DataFrame, plan: MixPlan) -> DataFrame:
    """(k, block, times): how often each block is taken, from the slots of all shards. Only blocks that are taken."""
    spark = sources.sparkSession
    rows = sources.orderBy("k").collect()
    slots = np.array([r["n_slots"] for r in rows], dtype=np.int64)
    n_blocks = [max(1, r["n_blocks"]) for r in rows]
    n_shards = -(-int(slots.sum()) // plan.shard_slots)
    steps = -(-n_shards // plan.super_shards)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for step in batch.column(0).to_pylist():
                for shard in range(step * plan.super_shards, min((step + 1) * plan.super_shards, n_shards)):
                    own, start = shard_range(plan, slots, shard, shard + 1)
                    for k in np.nonzero(own)[0].tolist():
                        slot = np.arange(start[k], start[k] + own[k])
                        turn, index = slot // n_blocks[k], slot % n_blocks[k]
                        block = np.empty_like(slot)
                        for e in np.unique(turn).tolist():
                            at = turn == e
                            block[at] = permuted(index[at], n_blocks[k], plan.seed * 1000 + k * MOST * 7 + e)
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(slot), k, dtype=np.int32)), pa.array(block)], names=["k", "block"])

    shards = spark.range(0, steps, 1, max(1, min(steps, 4096)))
    return shards.mapInArrow(run, "k int, block long").groupBy("k", "block").agg(F.count("*").cast("int").alias("times"))


def placed(counts: DataFrame, sources: DataFrame, plan: MixPlan) -> DataFrame:
    """counts with k and start, the number of words of the source before each document.

    A source's order is by lane (hash of the id), then id, then text hash; lanes sum up apart and are then offset."""
    lane = counts.join(F.broadcast(sources.select("k", F.col("source").alias("_s"))), F.col("source").eqNullSafe(F.col("_s"))).drop("_s")
    lane = lane.withColumn("lane", F.pmod(F.xxhash64("doc_id", "tag"), F.lit(LANES)).cast("int"))
    totals = lane.groupBy("k", "lane").agg(F.sum("size").alias("words"))  # at most LANES rows for each source
    before = F.sum("words").over(Window.partitionBy("k").orderBy("lane").rowsBetween(Window.unboundedPreceding, -1))
    offsets = totals.select("k", "lane", F.coalesce(before, F.lit(0)).alias("offset"))
    inside = F.sum("size").over(Window.partitionBy("k", "lane").orderBy("doc_id", "tag").rowsBetween(Window.unboundedPreceding, -1))
    return lane.withColumn("inside", F.coalesce(inside, F.lit(0))).join(offsets, ["k", "lane"]).withColumn("start", F.col("offset") + F.col("inside")).drop("inside", "offset", "lane")


def mix(df: DataFrame, plan: MixPlan = MixPlan()) -> DataFrame:
    """One row for each row of df: doc_id, source, size, source_size, target, taken (words the mix takes, repeats counted)
    and pieces, an array of (lo, hi, times) in words of the document, by lo.

    Null texts have size 0; null sources are one source, the last. Repeated rows are documents of their own. An empty
    table, or one without words, gives no slots. No document is taken more than 3 times. Reruns and other numbers of
    partitions agree: nothing depends on where a row is. Other columns of df are not read.
    """
    counts = materialize(word_counts(df))
    sources = materialize(plan_sources(counts, plan))
    docs = materialize(placed(counts, sources, plan).withColumn("row", F.monotonically_increasing_id()))
    size = F.lit(plan.block_words)
    first, last = F.floor(F.col("start") / size), F.floor((F.col("start") + F.col("size") - 1) / size)
    parts = docs.where("size > 0").select("row", "k", "start", "size", F.explode(F.sequence(first, last)).alias("block"))
    low = F.greatest(F.col("block") * size - F.col("start"), F.lit(0))
    high = F.least((F.col("block") + 1) * size - F.col("start"), F.col("size"))
    taken = (
        parts.join(materialize(draw_slots(sources, plan)), ["k", "block"])  # its size is known then
        .select("row", F.struct(low.alias("lo"), high.alias("hi"), "times").alias("piece"))
        .groupBy("row")
        .agg(F.sort_array(F.collect_list("piece")).alias("pieces"))  # as many as the document has blocks
    )
    out = docs.join(taken, "row", "left").join(F.broadcast(sources.select("k", "source_size", "target")), "k")
    words = F.aggregate("pieces", F.lit(0).cast("long"), lambda a, p: a + (p["hi"] - p["lo"]) * p["times"])
    return out.select("doc_id", "source", "size", "source_size", "target", F.coalesce(words, F.lit(0)).alias("taken"), "tag", "pieces")


def mixed_documents(df: DataFrame, plan: MixPlan = MixPlan()) -> DataFrame:
    """The mix as documents with the columns of df (doc_id, text, lang, source, n_chars): for each pass over a document
    one row with the words of the pass, the whole text where all are taken, else its runs joined by a space.

    A document that the mix doesn't take is absent. Null texts and texts without words are absent.
    """
    import re

    word = re.compile(r"[^ \t-\r]+")
    at, chars = df.columns.index("text"), df.columns.index("n_chars") if "n_chars" in df.columns else -1
    schema = df.schema

    def tagged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        for batch in slices(batches):
            tag = pa.array([xxhash.xxh3_64_intdigest((t or "").encode()) >> 1 for t in batch.column(at).to_pylist()], pa.int64())
            yield pa.RecordBatch.from_arrays([*batch.columns, tag], names=[*batch.schema.names, "_tag"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches, 128):
            rows, texts = [], []
            for i, (text, pieces) in enumerate(zip(batch.column(at).to_pylist(), batch.column(batch.num_columns - 1).to_pylist())):
                spans = [m.span() for m in word.finditer(text)]
                for layer in range(1, max(p["times"] for p in pieces) + 1):
                    runs: list[list[int]] = []
                    for p in pieces:
                        if p["times"] >= layer:
                            if runs and runs[-1][1] == p["lo"]:
                                runs[-1][1] = p["hi"]
                            else:
                                runs.append([p["lo"], p["hi"]])
                    rows.append(i)
                    texts.append(text if runs == [[0, len(spans)]] else " ".join(text[spans[lo][0] : spans[hi - 1][1]] for lo, hi in runs))
            own = batch.select(batch.schema.names[:-1]).take(pa.array(rows, pa.int64()))
            cols = list(own.columns)
            cols[at] = pa.array(texts, own.schema.field(at).type)
            if chars >= 0:
                cols[chars] = pa.array([len(t) for t in texts], pa.int64()).cast(own.schema.field(chars).type)
            yield pa.RecordBatch.from_arrays(cols, names=own.schema.names)

    plus = df.mapInArrow(tagged, T.StructType([*schema.fields, T.StructField("_tag", T.LongType())]))
    # equal rows (id, source and text) are told apart by their number, which is all that may differ between them
    same = Window.partitionBy("doc_id", "source", "_tag").orderBy("_tag")
    plus = plus.withColumn("_n", F.row_number().over(same))
    mine = mix(df, plan).where("taken > 0").select(F.col("doc_id").alias("_d"), F.col("source").alias("_s"), F.col("tag").alias("_t"), "pieces")
    mine = mine.withColumn("_m", F.row_number().over(Window.partitionBy("_d", "_s", "_t").orderBy("pieces")))
    on = F.col("doc_id").eqNullSafe(F.col("_d")) & F.col("source").eqNullSafe(F.col("_s")) & (F.col("_tag") == F.col("_t")) & (F.col("_n") == F.col("_m"))
    return plus.join(mine, on).select(*df.columns, "pieces").mapInArrow(run, schema)
