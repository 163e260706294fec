"""Near-duplicate detection by fast similarity sketching, banding and exact verification.

1. Each text becomes its set of hashed word shingles. Rounds of bin placement fill a sketch: in round i every shingle goes
   into one hashed bin with a value that all later rounds exceed, until each bin is filled; after as many rounds as there
   are bins, bin j takes the least hash of a round of its own, so every coordinate fills whatever the set's size. Each
   coordinate agrees between two texts with their Jaccard similarity, and agreement is concentrated.
2. Texts with equal sets collapse into one. Bands of coordinates deal the rest into buckets; in a bucket, texts whose short
   sketches agree in half the places are linked into candidate clusters (a spanning forest, never all pairs). Sketches are
   sent only for buckets with two members or more; a bucket with thousands is a star around its first member.
3. In each candidate cluster the links are confirmed on full sets by an inverted index of the cluster's shingles.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from twigrank.llm.common import blocks_of_pairs, complete_groups, connected_components, join_per_key, mark_in, materialize, maybe_in, slices, without

MIX = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9))


@dataclass(frozen=True)
class DedupConfig:
    """Defaults: five words, similarity of 0.8 or more."""

    words: int = 5
    num: int = 80
    den: int = 100
    bins: int = 128  # a power of two
    rows: int = 5  # coordinates in a band
    bands: int = 25
    short: int = 48  # coordinates, a byte each, that the bucket step compares
    short_agree: float = 0.45
    bucket_rows: int = 2000  # larger buckets are one candidate cluster each, without a look at their sketches
    cluster_shingles: int = 8_000_000  # of a cluster in one task; larger ones go by pairs of blocks

    def least_set(self) -> int:
        """Smaller sets can only be linked to equal ones."""
        return -(-self.num // (self.den - self.num)) if self.num < self.den else 1 << 62


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingle_sets(texts: list[str | None], words: int) -> list[np.ndarray]:
    """Sorted distinct 64-bit hashes of the word shingles of each text; A-Z lower-cased, words split at ASCII white space."""
    split = [t.encode().lower().split() if t else [] for t in texts]
    sizes = [len(w) for w in split]
    if not sum(sizes):
        return [np.zeros(0, dtype=np.uint64) for _ in texts]
    flat = np.empty(sum(sizes), dtype=object)
    flat[:] = [x for w in split for x in w]
    codes, distinct = pd.factorize(flat)
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, distinct), dtype=np.uint64, count=len(distinct))[codes]
    rolled = np.zeros(max(0, len(h) - words + 1), dtype=np.uint64)
    for k in range(words):
        rolled = mix(rolled * MIX[0] + h[k : k + len(rolled)])
    out, at = [], 0
    for n in sizes:
        if n >= words:
            out.append(np.unique(rolled[at : at + n - words + 1]))
        elif n:
            whole = np.array([n], dtype=np.uint64)
            for k in range(at, at + n):
                whole = mix(whole * MIX[1] + h[k : k + 1])
            out.append(whole)
        else:
            out.append(np.zeros(0, dtype=np.uint64))
        at += n
    return out


def sketch(x: np.ndarray, bins: int) -> np.ndarray:
    """`bins` coordinates (uint64) of the set of hashes x, not empty."""
    shift, out, empty = np.uint64(64 - bins.bit_length() + 1), np.zeros(bins, dtype=np.uint64), np.ones(bins, dtype=bool)
    done, at_once = 0, max(1, min(bins, 5 * bins // len(x)))  # several rounds in one sort: most bins fill in t ln t placements
    while done < bins and empty.any():
        rounds = np.arange(done, min(bins, done + at_once), dtype=np.uint64)[:, None]
        h = mix(x[None, :] ^ (rounds + np.uint64(1)) * MIX[1])
        value = (rounds << np.uint64(40)) | ((h << np.uint64(16)) >> np.uint64(24))
        placed = np.sort(((h >> shift) << np.uint64(50) | value).ravel())
        where = (placed >> np.uint64(50)).astype(np.int64)
        first = np.nonzero(np.r_[True, where[1:] != where[:-1]])[0]
        first = first[empty[where[first]]]
        out[where[first]], empty[where[first]] = placed[first] & np.uint64((1 << 50) - 1), False
        done += len(rounds)
    for j in np.nonzero(empty)[0]:  # the rounds that belong to a bin
        out[j] = mix(x ^ np.array([bins + j + 1], dtype=np.uint64) * MIX[1]).min() | np.uint64(1 << 63)
    return mix(out)


def linked(ids: np.ndarray, sets: list[np.ndarray], num: int, den: int) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the graph whose links are the pairs with den * |A & B| >= num * |A | B|, exactly.

    Searches breadth-first; a member meets only those that share a shingle with it, by an inverted index.
    """
    n, sizes = len(ids), np.array([len(s) for s in sets], dtype=np.int64)
    flat, owner = np.concatenate(sets), np.repeat(np.arange(n), sizes)
    _, code, times = np.unique(flat, return_inverse=True, return_counts=True)
    posts, starts = owner[np.argsort(code, kind="stable")], np.cumsum(times) - times
    at = np.r_[0, np.cumsum(sizes)]
    fresh, a, b = np.ones(n, dtype=bool), [], []
    for seed in range(n):
        if not fresh[seed]:
            continue
        fresh[seed], todo = False, [seed]
        while todo and fresh.any():
            p = todo.pop()
            terms = code[at[p] : at[p + 1]]
            size = times[terms]
            reach = np.repeat(starts[terms] - np.cumsum(size) + size, size) + np.arange(size.sum())
            shared = np.bincount(posts[reach], minlength=n)
            new = np.nonzero(fresh & (shared > 0) & (den * shared >= num * (sizes[p] + sizes - shared)))[0]
            fresh[new] = False
            a.append(np.full(len(new), ids[p]))
            b.append(ids[new])
            todo.extend(new.tolist())
    none = np.zeros(0, dtype=np.int64)
    return (np.concatenate(a), np.concatenate(b)) if a else (none, none)


def bucket_links(ids: np.ndarray, short: np.ndarray, agree: int) -> tuple[list[int], list[int]]:
    """A spanning forest of the members of one bucket whose short sketches agree in `agree` places or more."""
    a, b, rest = [], [], np.arange(len(ids))
    todo: list[int] = []
    while len(rest):
        if not todo:
            todo, rest = [int(rest[0])], rest[1:]
        p = todo.pop()
        near = (short[rest] == short[p]).sum(axis=1) >= agree
        new = rest[near]
        a.extend([int(ids[p])] * len(new))
        b.extend(ids[new].tolist())
        todo.extend(new.tolist())
        rest = rest[~near]
    return a, b


def signatures(df: DataFrame, config: DedupConfig) -> DataFrame:
    """doc_id, n_shingles, two halves of the set's digest, band hashes and short sketch (null for small sets)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            size, d1, d2, bands, short = [], [], [], [], []
            for s in shingle_sets(batch.column(1).to_pylist(), config.words):
                size.append(len(s))
                digest = xxhash.xxh3_128_digest(s.tobytes())
                d1.append(int.from_bytes(digest[:8], "big", signed=True))
                d2.append(int.from_bytes(digest[8:], "big", signed=True))
                if len(s) < config.least_set():
                    bands.append(None)
                    short.append(None)
                    continue
                row = sketch(s, config.bins)
                cut = row[: config.rows * config.bands].reshape(config.bands, config.rows)
                key = np.arange(1, config.bands + 1, dtype=np.uint64)
                for k in range(config.rows):
                    key = mix(key * MIX[2] + cut[:, k])
                bands.append(key.view(np.int64))
                short.append((row[: config.short] & np.uint64(255)).astype(np.uint8).tobytes())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(size, pa.int64()), pa.array(d1, pa.int64()), pa.array(d2, pa.int64()), pa.array(bands, pa.list_(pa.int64())), pa.array(short, pa.binary())],
                names=["doc_id", "n_shingles", "d1", "d2", "bands", "short"],
            )

    return df.select("doc_id", "text").mapInArrow(run, "doc_id long, n_shingles long, d1 long, d2 long, bands array<long>, short binary")


def candidate_links(reps: DataFrame, config: DedupConfig) -> DataFrame:
    """(a, b): spanning links of the members of each bucket with near short sketches. reps: a row for each doc_id and set."""
    # rows that share a doc_id have sets, and thus sketches, of their own
    known = reps.where("bands is not null").withColumn("set", F.pmod("d1", F.lit(1 << 31)).cast("int"))
    rows = known.select("doc_id", "set", F.explode("bands").alias("band"))
    shared = materialize(rows.groupBy("band").agg(F.count("*").alias("n"), F.min("doc_id").alias("lead")).where("n > 1"))
    n_rows = shared.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    met = materialize(join_per_key(rows, shared.withColumn("large", F.col("n") > config.bucket_rows), "band", n_rows))
    stars = met.where("large").select(F.col("doc_id").alias("a"), F.col("lead").alias("b"))
    few = met.where("not large").select("band", "doc_id", "set")
    dealt = few.join(known.select("doc_id", "set", "short"), ["doc_id", "set"]).select(F.col("band").alias("pair"), "doc_id", "short")
    agree = int(np.ceil(config.short_agree * config.short))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in complete_groups(batches, "pair"):
            key = np.asarray(table.column("pair"))
            ids = np.asarray(table.column("doc_id"))
            edge = np.r_[0, np.nonzero(key[1:] != key[:-1])[0] + 1, len(key)]
            size = np.diff(edge)
            a: list[int] = []
            b: list[int] = []
            if (size > 1).any():
                many = np.repeat(size > 1, size)
                short = np.zeros((len(key), config.short), dtype=np.uint8)
                picked = table.column("short").filter(pa.array(many)).to_pylist()
                short[many] = np.frombuffer(b"".join(picked), dtype=np.uint8).reshape(-1, config.short)
                two = edge[:-1][size == 2]
                near = two[(short[two] == short[two + 1]).sum(axis=1) >= agree]
                a, b = ids[near].tolist(), ids[near + 1].tolist()
                for k in np.nonzero(size > 2)[0]:
                    x, y = bucket_links(ids[edge[k] : edge[k + 1]], short[edge[k] : edge[k + 1]], agree)
                    a += x
                    b += y
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    near = dealt.repartition("pair").sortWithinPartitions("pair").mapInArrow(run, "a long, b long")
    return near.union(stars).where("a <> b").distinct()


def confirmed_links(docs: DataFrame, clusters: DataFrame, config: DedupConfig) -> DataFrame:
    """(a, b): spanning links confirmed on the full sets of the members of each cluster. clusters: node, component, n_shingles."""
    weight = clusters.groupBy("component").agg(F.sum("n_shingles").alias("w"))
    weight = weight.select("component", F.ceil(F.col("w") / config.cluster_shingles).cast("long").alias("n_parts"))
    members = clusters.select(F.col("node").alias("doc_id"), "component").join(weight, "component")

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            own = shingle_sets(batch.column(3).to_pylist(), config.words)
            packed = pa.array([s.tobytes() for s in own], pa.binary())
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], packed], names=["doc_id", "component", "n_parts", "shingles"])

    texts = maybe_in(docs, "doc_id", members.select("doc_id"))  # few of all texts are shuffled
    full = texts.join(members, "doc_id").select("doc_id", "component", "n_parts", "text")
    full = full.mapInArrow(sets, "doc_id long, component long, n_parts long, shingles binary")
    dealt = blocks_of_pairs(full, "component", "doc_id").select(F.xxhash64("pair").alias("pair"), "doc_id", "shingles")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in complete_groups(slices(batches, 64), "pair"):
            key, ids = np.asarray(table.column("pair")), np.asarray(table.column("doc_id"))
            edge = np.r_[0, np.nonzero(key[1:] != key[:-1])[0] + 1, len(key)]
            for lo, hi in zip(edge[:-1], edge[1:]):
                own = [np.frombuffer(x, dtype=np.uint64) for x in table.column("shingles").slice(lo, hi - lo).to_pylist()]
                a, b = linked(ids[lo:hi], own, config.num, config.den)
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return dealt.repartition("pair").sortWithinPartitions("pair").mapInArrow(run, "a long, b long")


def copy_links(known: DataFrame, rep: DataFrame) -> DataFrame:
    """(a, b): a document and the representative of its set, where they differ. rep: d1, d2, rep, n (rows of the set)."""
    digest = F.xxhash64("d1", "d2").alias("digest")
    copies = rep.where("n > 1").select(digest, F.col("d1").alias("r1"), F.col("d2").alias("r2"), "rep", "n")
    n_rows = copies.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    rows = join_per_key(known.select("doc_id", "d1", "d2", digest), copies, "digest", n_rows)
    return rows.where("d1 = r1 and d2 = r2 and doc_id <> rep").select(F.col("doc_id").alias("a"), F.col("rep").alias("b"))


def near_duplicates(df: DataFrame, config: DedupConfig = DedupConfig()) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable over links), kept (doc_id = component_id), one row for
    each row of df.

    Null and empty texts have no shingles and no links. Rows that share a doc_id are one node; a row with a null doc_id
    is linked with nothing, has a null component and is kept. Texts with fewer words than a shingle are one shingle.
    Other columns of df are not read. The chance that a pair at the threshold shares no band is (1 - s^rows)^bands,
    5e-5 by default (0.8, as in the pipeline) and 5e-7 at op5's 0.85; pairs in one cluster need not share one.
    """
    docs = df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    sig = materialize(signatures(docs, config))
    known = sig.where("doc_id is not null and n_shingles > 0")
    # one representative for each distinct set; small columns only, summed before the shuffle
    rep = materialize(known.groupBy("d1", "d2").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n")))
    reps = known.join(rep.select("d1", "d2", F.col("rep").alias("doc_id")), ["doc_id", "d1", "d2"]).dropDuplicates(["doc_id", "d1", "d2"])
    reps = materialize(reps.select("doc_id", "d1", "n_shingles", "bands", "short"))
    same = copy_links(known, rep)
    found = candidate_links(reps, config)
    clusters = connected_components(found)
    sizes = reps.groupBy("doc_id").agg(F.max("n_shingles").alias("n_shingles")).withColumnRenamed("doc_id", "node")
    clusters = materialize(clusters.join(sizes, "node"))
    links = confirmed_links(docs, clusters, config)
    labels = connected_components(links.union(same.distinct()))
    out = sig.select("doc_id", "n_shingles").join(labels.withColumnRenamed("node", "doc_id"), "doc_id", "left")
    component = F.coalesce("component", "doc_id")
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept"))


def keep_one(df: DataFrame, config: DedupConfig = DedupConfig()) -> DataFrame:
    """The rows of df (all columns) with one document of each group: that of the smallest doc_id. Of rows that share a
    doc_id one stays, that of the least hash of its text; rows with a null doc_id all stay. Only rows that may go are
    shuffled."""
    ids = near_duplicates(df, config).where("doc_id is not null").groupBy("doc_id")
    ids = materialize(ids.agg(F.count("*").alias("n"), F.max("kept").alias("kept")).where("n > 1 or not kept"))
    left = without(df, "doc_id", ids.where("not kept").select("doc_id"))
    again = materialize(ids.where("kept").select(F.col("doc_id").alias("_again")))
    marked = mark_in(left.withColumn("_id", F.col("doc_id").cast("long")), "_id", again.select(F.col("_again").alias("_id")), "_maybe")
    some = marked.where("_maybe").join(again, F.col("_id") == F.col("_again"), "left")
    first = F.row_number().over(Window.partitionBy("_again").orderBy(F.xxhash64("text"), "text"))
    once = some.where("_again is not null").withColumn("_row", first).where("_row = 1")
    rest = some.where("_again is null").select(df.columns).union(once.select(df.columns))
    return marked.where("not _maybe").select(df.columns).union(rest)
