"""Helpers shared by the corpus operators: shared storage, batch slicing and connected components."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder every executor can reach: spark.checkpoint.dir, or one of ours where it is unset and all runs in one process (tests)."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors reach")
        folder = tempfile.mkdtemp(prefix="twigrank-")
        spark.sparkContext.setCheckpointDir(folder)
    return folder


def materialize(df: DataFrame) -> DataFrame:
    """Write df as Parquet in the shared folder and read it back: cuts lineage and survives lost executors."""
    path = f"{shared_dir(df.sparkSession)}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def checkpointed(df: DataFrame) -> DataFrame:
    shared_dir(df.sparkSession)
    return df.checkpoint()


def slices(batches: Iterable[pa.RecordBatch], rows: int = 512) -> Iterator[pa.RecordBatch]:
    """The same rows in small record batches, so that long texts never meet in one Python list."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def by_bytes(batches: Iterable[pa.RecordBatch], text: str, limit: int = 12 << 20, rows: int = 512) -> Iterator[pa.RecordBatch]:
    """The same rows in record batches of about `limit` bytes of column `text`, joined or cut from what comes."""
    held: list[pa.RecordBatch] = []
    size = 0
    for part in slices(batches, rows):
        held.append(part)
        lengths = pa.compute.sum(pa.compute.binary_length(part.column(text))).as_py() or 0
        size += lengths + part.num_rows
        if size >= limit:
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            held, size = [], 0
    if held:
        merged = pa.Table.from_batches(held).combine_chunks().to_batches()
        yield from merged[:1]


def blocks_of_pairs(df: DataFrame, key: str, row: str, parts: str = "n_parts") -> DataFrame:
    """Deal the rows of each group into `parts` blocks and give each pair of blocks (i <= j) a group of its own.

    Adds column `pair` (string, key of the new group). A group with parts = 1 stays as it is; of larger ones every two
    rows meet in at least one pair of blocks, with two blocks in memory at once.
    """
    mine = F.pmod(F.xxhash64(row), F.col(parts))
    other = F.explode(F.sequence(F.lit(0).cast("long"), F.col(parts) - 1))
    wide = df.withColumn("_mine", mine.cast("long")).withColumn("_other", other)
    low, high = F.least("_mine", "_other"), F.greatest("_mine", "_other")
    return wide.withColumn("pair", F.concat_ws("/", F.col(key).cast("string"), low, high)).drop("_mine", "_other")


#: Keys that hold more than one in so many rows are joined by broadcast: there are fewer of them than this.
HOT_KEYS = 2000
#: Bits of `maybe_in`'s filter: at most an eighth of a megabyte of rows of eight bytes.
FILTER_BITS = 1 << 25


def join_per_key(rows: DataFrame, per_key: DataFrame, key: str | list[str], n_rows: int, count: str = "n") -> DataFrame:
    """Inner join of rows with per_key (a row for each key; `count`, the key's number of rows, is dropped). Keys with more
    than one in HOT_KEYS of all n_rows come by broadcast and the rest by shuffle, so that no task gets a hot key."""
    is_hot = F.col(count) > n_rows / HOT_KEYS
    few = F.broadcast(per_key.where(is_hot).drop(count))
    most = per_key.where(~is_hot).drop(count)
    rest = rows.join(few.select(key), key, "left_anti")
    return rows.join(few, key).unionByName(rest.join(most, key))


def mark_in(rows: DataFrame, key: str, wanted: DataFrame, name: str) -> DataFrame:
    """rows with a boolean column: true where the key (long, maybe null) is in wanted (column of the same name), and for a
    few others. A filter of FILTER_BITS bits, broadcast as words of 64."""
    place = F.pmod(F.xxhash64(key), F.lit(FILTER_BITS))
    word, bit = F.shiftright(place, 6), F.expr(f"shiftleft(1L, cast(pmod(xxhash64({key}), {FILTER_BITS}L) & 63 as int))")
    filled = wanted.select(word.alias("_word"), bit.alias("_bit")).groupBy("_word").agg(F.bit_or("_bit").alias("_bits"))
    marked = rows.withColumn("_word", word).join(F.broadcast(filled), "_word", "left")
    return marked.select(*rows.columns, F.coalesce(F.col("_bits").bitwiseAND(bit) != 0, F.lit(False)).alias(name))


def maybe_in(rows: DataFrame, key: str, wanted: DataFrame) -> DataFrame:
    """The rows whose key is in wanted, and a few others, so that rows nobody wants are not shuffled. An exact join must
    follow."""
    return mark_in(rows, key, wanted, "_maybe").where("_maybe").select(rows.columns)


def without(df: DataFrame, id_col: str, bad: DataFrame) -> DataFrame:
    """The rows of df whose id (as long) is not in bad (one long column, null for null ids). Rows that a filter of the bad
    ids tells clear are not shuffled."""
    bad = bad.toDF("_bad_id").distinct()
    marked = mark_in(df.withColumn("_id_here", df[id_col].cast("long")), "_id_here", bad.select(F.col("_bad_id").alias("_id_here")), "_maybe_bad")
    rest = marked.where("_maybe_bad").join(bad, F.col("_id_here").eqNullSafe(F.col("_bad_id")), "left_anti")
    return marked.where("not _maybe_bad").select(df.columns).union(rest.select(df.columns))


def complete_groups(batches: Iterable[pa.RecordBatch], key: str) -> Iterator[pa.Table]:
    """Tables that hold whole groups each, from batches in which equal keys stand together."""
    carry: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        keys = batch.column(key)
        last = keys[batch.num_rows - 1].as_py()
        first_of_last = batch.num_rows - 1
        step = np.asarray(pa.compute.equal(keys, pa.scalar(last, keys.type)))
        first_of_last = int(np.argmax(step))
        if first_of_last == 0 and carry and carry[-1].column(key)[carry[-1].num_rows - 1].as_py() == last:
            carry.append(batch)
            continue
        done = [*carry, batch.slice(0, first_of_last)] if first_of_last else carry
        if sum(x.num_rows for x in done):
            yield pa.Table.from_batches(done).combine_chunks()
        carry = [batch.slice(first_of_last)]
    if carry:
        yield pa.Table.from_batches(carry).combine_chunks()


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", max_rounds: int = 60) -> DataFrame:
    """(node, component): component is the smallest node reachable. Nodes without an edge are absent.

    Alternates star contractions towards larger and towards smaller neighbours until every component is a star around its
    smallest node; every round is two joins and aggregates and one checkpoint, and the number of rounds grows with the
    logarithm of the longest path. Stars with many ends, as large groups of copies give, are joined by broadcast.
    """
    current = checkpointed(
        edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct()
    )
    for _ in range(max_rounds):
        ends = current.select(F.col("u").alias("node"), F.lit(1).alias("up"), F.lit(0).alias("down"))
        ends = ends.union(current.select("v", F.lit(0), F.lit(1))).groupBy("node").agg(F.sum("up").alias("up"), F.sum("down").alias("down"))
        state = ends.agg(F.coalesce(F.sum("up"), F.lit(0)), F.count_if(F.expr("up > 1 or (up = 1 and down > 0)"))).first()
        if not state[1]:
            break
        both = current.union(current.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")).select("u", F.least("u", "m").alias("m"), "n")
        large = checkpointed(join_per_key(both, low, "u", 2 * state[0]).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct())
        least = large.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n"))
        small = join_per_key(large, least, "u", state[0]).select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
        current = checkpointed(small.union(least.select("u", F.col("m").alias("v"))).distinct())
    else:
        raise RuntimeError("connected_components did not settle")
    nodes = current.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return nodes.union(current.select(F.col("v"), F.col("v")).distinct())
