"""Exact Jaccard self-join of word n-gram sets with several global token orders, down to its link components.

A pair above the threshold shares a token among the first few of each side under *every* order of all tokens, so
each order gives a filter of its own, and only pairs that pass them all are verified. Equal sets are one class from the start, and pairs that
a verified chain already joins are never made, so a group of near copies costs about one pair for each member.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import connected_components, forget, saved, slices, tidy
from .hashing import mix, shingle_sets

#: Buckets of the count sketch that orders tokens from rare to frequent: a fixed size, whatever the corpus.
SKETCH_BITS = 23
_CHUNK_BITS = 15
#: Bits of the filter of document ids that a verification needs: a fixed size too; false hits only cost time.
FILTER_BITS = 22
ORDERS = 2
#: Classes of equal sets are broadcast up to so many rows (some 32 bytes each), else joined under so many salts.
BROADCAST_CLASSES = 200_000
SALTS = 32
#: Rows for each leader, and leaders that each row is tried with in a round.
SLOT = 16
TRIALS = 3


def _sketch(docs: DataFrame, words: int) -> dict[int, bytes]:
    """How often the shingles of each bucket are held, over all documents, in packed chunks of buckets (those of zeros are left out);
    frequent shingles make their buckets stand out.

    Every task counts in one array and hands it on in chunks; tasks of the second stage add up chunks as they stream by.
    """
    chunk = 1 << _CHUNK_BITS

    @tidy
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(1 << SKETCH_BITS, np.int32)
        some: list[np.ndarray] = []
        held = 0

        def put() -> None:
            at, n = np.unique(np.concatenate(some), return_counts=True)
            seen[at] += n.astype(np.int32)
            some.clear()

        for batch in batches:
            for s in shingle_sets(batch.column(0), words):
                some.append((s >> np.uint64(64 - SKETCH_BITS)).astype(np.int32))
                held += len(s)
                if held > 1 << 20:
                    put()
                    held = 0
        if some:
            put()
        yield from packed({i: row for i, row in enumerate(seen.reshape(-1, chunk)) if row.any()})

    def packed(sums: dict[int, np.ndarray]) -> Iterator[pa.RecordBatch]:
        kept = list(sums)
        yield pa.RecordBatch.from_arrays([pa.array(kept, pa.int32()), pa.array([zlib.compress(sums[i].astype(np.int64).tobytes(), 1) for i in kept], pa.binary())], ["chunk", "counts"])

    @tidy
    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for i, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                row = np.frombuffer(zlib.decompress(raw), np.int64)
                sums[i] = sums[i] + row if i in sums else row
        yield from packed(sums)

    kind = "chunk int, counts binary"
    rows = docs.select("text").mapInArrow(count, kind).repartition("chunk").mapInArrow(add, kind).collect()  # a bucket's count each, packed
    return {r.chunk: bytes(r.counts) for r in rows}


def _ranks(sketch: dict[int, bytes]) -> np.ndarray:
    """A class from 0 (rare) to 31 for each bucket: half powers of two of how far its load is above chance, in spreads of a random load.

    The driver unpacks one chunk at a time: all counts at once, and what is reckoned from them, would take it some 200 MB.
    """
    chunk = 1 << _CHUNK_BITS
    unpacked = lambda raw: np.frombuffer(zlib.decompress(raw), np.int64)
    mean = max(1.0, sum(int(unpacked(raw).sum()) for raw in sketch.values()) / (1 << SKETCH_BITS))
    spread = np.sqrt(mean)
    of = lambda counts: np.clip(np.floor(2 * np.log2(np.maximum(counts - mean, 1.0) / (3 * spread)) + 1), 0, 31).astype(np.uint8)
    out = np.tile(of(np.zeros(chunk, np.int64)), (1 << SKETCH_BITS) // chunk).reshape(-1, chunk)
    for i, raw in sketch.items():
        out[i] = of(unpacked(raw))
    return out.reshape(-1)


def _profiles(docs: DataFrame, words: int, percent: int, ranks) -> DataFrame:
    """doc_id, n (set size), sign_a and sign_b (of the set), prefix0, prefix1, ...: first tokens under each order."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rank = ranks.value
        for batch in slices(batches, 1024):
            sizes, signs, first = [], ([], []), [[] for _ in range(ORDERS)]
            for s in shingle_sets(batch.column(1), words):
                n = len(s)
                sizes.append(n)
                signs[0].append(mix(s, 21).sum(dtype=np.uint64))
                signs[1].append(np.bitwise_xor.reduce(mix(s, 22)) if n else np.uint64(0))
                keep = n - (percent * n + 99) // 100 + 1 if n else 0
                high = rank[(s >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)].astype(np.uint64) << np.uint64(58)
                for k in range(ORDERS):
                    token = high | (mix(s, 31 + k) >> np.uint64(6))
                    first[k].append(np.sort(np.partition(token, keep - 1)[:keep] if keep < n else token).view(np.int64))
            columns = [batch.column(0), pa.array(sizes, pa.int32()), *(pa.array(np.array(x, np.uint64).view(np.int64)) for x in signs)]
            for lists in first:
                offsets = np.concatenate([[0], np.cumsum([len(x) for x in lists])]).astype(np.int32)
                columns.append(pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(lists) if lists else np.zeros(0, np.int64))))
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n", "sign_a", "sign_b", *(f"prefix{k}" for k in range(ORDERS))])

    prefixes = ", ".join(f"prefix{k} array<bigint>" for k in range(ORDERS))
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, n int, sign_a bigint, sign_b bigint, {prefixes}")


def _fit(n: str, place: str, m: str, at: str, percent: int):
    """Length and positional filter: sizes within the threshold, and enough left of both sets from the first common token on."""
    asked = F.expr(f"({percent}L * ({n} + {m}) + {99 + percent}) div {100 + percent}")
    return (100 * F.least(n, m) >= percent * F.greatest(n, m)) & (F.col(n) - F.col(place) >= asked) & (F.col(m) - F.col(at) >= asked)


def _stars(rows: DataFrame, turn: int, percent: int) -> DataFrame:
    """Pairs (a, b) of bucket members with leaders: in every trial the leader that a member meets in most buckets.

    The first leader of a bucket is its smallest doc_id. Later ones are drawn by hash, one for each ``SLOT`` rows or so, anew
    in every trial, and preferably with an early place, where more pairs pass the positional filter.
    """
    lead = [F.col("doc_id").alias("lead"), F.col("comp").alias("lead_comp"), F.col("n").alias("lead_n"), F.col("place").alias("lead_place")]
    if turn:
        rows = rows.withColumn("trial", F.explode(F.sequence(F.lit(1), F.lit(TRIALS))))
        rows = rows.withColumn("slot", F.pmod(F.xxhash64(F.lit(turn), "trial", "token", "doc_id"), F.col("slots")))
        order = [F.expr("place * 10 > n").alias("late"), F.xxhash64("trial", F.lit(turn), "token", "doc_id").alias("h")]
    else:
        rows, order = rows.withColumns({"trial": F.lit(0), "slot": F.lit(0)}), []
    spot = ["token", "trial", "slot"]
    leaders = rows.groupBy(*spot).agg(F.min(F.struct(*order, *lead)).alias("l"), F.max("comp").alias("top"), F.min("comp").alias("low"))
    leaders = leaders.where("top <> low").select(*spot, "l.lead", "l.lead_comp", "l.lead_n", "l.lead_place")
    met = rows.join(leaders, spot).where((F.col("comp") != F.col("lead_comp")) & _fit("n", "place", "lead_n", "lead_place", percent))
    met = met.groupBy("doc_id", "trial", "lead").agg(F.count(F.lit(1)).alias("times"))
    met = met.groupBy("doc_id", "trial").agg(F.max(F.struct("times", "lead")).alias("best")).select("doc_id", F.col("best.lead").alias("lead"))
    return met.select(F.least("doc_id", "lead").alias("a"), F.greatest("doc_id", "lead").alias("b")).distinct()


def _passing(pairs: DataFrame, profiles: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) that every order lets through.

    Up to the smaller of the two last prefix tokens, both prefixes hold all tokens of their sets; so the overlap is at
    most the number of common prefix tokens plus what the set with the smaller last token has behind its prefix. This has to reach the overlap
    that the threshold asks of the two sizes.
    """
    profiles = profiles.where(_in_pairs(pairs)(_place("doc_id")))
    side = lambda s: profiles.select(F.col("doc_id").alias(s), F.col("n").alias(f"n_{s}"), *(F.col(f"prefix{k}").alias(f"p{k}_{s}") for k in range(ORDERS)))
    out = pairs.join(side("a"), "a").join(side("b"), "b").where(100 * F.least("n_a", "n_b") >= percent * F.greatest("n_a", "n_b"))
    asked = F.expr(f"({percent}L * (n_a + n_b) + {99 + percent}) div {100 + percent}")
    for k in range(ORDERS):
        behind = F.when(F.array_max(f"p{k}_a") <= F.array_max(f"p{k}_b"), F.col("n_a") - F.size(f"p{k}_a")).otherwise(F.col("n_b") - F.size(f"p{k}_b"))
        common = F.size(F.array_intersect(f"p{k}_a", f"p{k}_b"))
        out = out.where((common > 0) & (common + behind >= asked))
    return out.select("a", "b")


def _place(column: str):
    return F.pmod(F.xxhash64(column), F.lit(1 << FILTER_BITS))


def _in_pairs(pairs: DataFrame):
    """A test of places (see ``_place``) for ids that stand in pairs, by a bit array of fixed size: what it lets through too much only costs time."""
    words = (
        pairs.select(F.explode(F.array("a", "b")).alias("id")).select(_place("id").alias("p"))
        .groupBy(F.expr("p div 32").alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, int(p % 32))")).alias("bits")).toArrow()
    )
    out = np.zeros(1 << (FILTER_BITS - 5), np.uint32)
    out[words["w"].to_numpy()] = words["bits"].to_numpy().astype(np.uint32)
    bits = pairs.sparkSession.sparkContext.broadcast(out)

    @F.pandas_udf("boolean")
    def wanted(place: pd.Series) -> pd.Series:
        p = place.to_numpy()
        return pd.Series((bits.value[p >> 5] >> (p & 31).astype(np.uint32)) & 1 == 1)

    return wanted


def verify_pairs(pairs: DataFrame, docs: DataFrame, words: int, percent: int) -> DataFrame:
    """The pairs (a, b) of doc_ids whose sets reach the threshold, by exact intersection of the whole sets."""
    texts = docs.select("doc_id", "text").where(_in_pairs(pairs)(_place("doc_id")))
    left = pairs.join(texts.select(F.col("doc_id").alias("a"), F.col("text").alias("left_text")), "a")
    both = left.join(texts.select(F.col("doc_id").alias("b"), F.col("text").alias("right_text")), "b").select("a", "b", "left_text", "right_text")
    kind = docs.schema["doc_id"].dataType.simpleString()

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(shingle_sets(batch.column(2), words), shingle_sets(batch.column(3), words)):
                same = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(len(x) > 0 and 100 * same >= percent * (len(x) + len(y) - same))
            yield pa.RecordBatch.from_arrays(batch.columns[:2], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return both.mapInArrow(run, f"a {kind}, b {kind}")


def jaccard_components(docs: DataFrame, words: int = 5, percent: int = 80, star_rounds: int = 3) -> DataFrame:
    """One row per distinct non-null doc_id: doc_id, n_shingles (set size), component_id (smallest doc_id reachable by links).

    Two documents link when the Jaccard index of their sets of ``words``-word shingles is at least ``percent`` per cent; a text with
    fewer words is one shingle, one without words links with nothing. Words are cut at ASCII white space, A-Z lower-cased.
    Rows with null doc_id are left out, and of rows with equal doc_id the one whose text is greatest is used. Empty tables give no rows.

    1. A sketch of how frequent all shingles are ranks them (rare first), fixed in size. 2. Each document gets its set's signature and
    its prefix under every order. 3. Equal signatures (128 bits and the set's size) collapse to the smallest doc_id; shingles are compared by 64-bit hashes throughout. 4. In rounds, each member of a first-order bucket is
    tried with a leader or a few of it; verified links make components. 5. What is still apart after the rounds is joined pair by pair within
    buckets and across components only, so the result is exact.
    """
    spark: SparkSession = docs.sparkSession
    base = docs.where("doc_id is not null").select("doc_id", "text")
    ranks = spark.sparkContext.broadcast(_ranks(_sketch(base, words)))
    every = saved(_profiles(base, words, percent, ranks), "profiles")
    if every.groupBy("doc_id").count().where("count > 1").limit(1).count():
        base = saved(base.groupBy("doc_id").agg(F.max("text").alias("text")), "texts")
        forget(spark, every)
        every = saved(_profiles(base, words, percent, ranks), "profiles")
    signs = ["sign_a", "sign_b", "n"]
    classes = every.where("n > 0").groupBy(*signs).agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("c")).where("c > 1").drop("c")
    named = _with_class(every, saved(classes, "classes"), signs).withColumn("rep", F.coalesce("rep", "doc_id"))
    member = saved(named.select("doc_id", "n", "rep"), "members")
    reps = saved(named.where("doc_id = rep and n > 1").select(*every.columns), "representatives")
    forget(spark, every)
    rows = reps.select("doc_id", "n", F.posexplode("prefix0").alias("place", "token"))
    shared = rows.groupBy("token").agg(F.count(F.lit(1)).alias("c")).where("c > 1").select("token")
    buckets = saved(rows.join(shared, "token"), "buckets")
    links: list[DataFrame] = []
    comp: DataFrame | None = None
    left = buckets.select("doc_id", "n", "place", "token", F.col("doc_id").alias("comp"), F.lit(1).alias("slots"))
    for turn in range(star_rounds):
        stars = saved(_stars(left, turn, percent), "stars")
        tried = saved(_passing(stars, reps, percent), "candidates")
        links.append(saved(verify_pairs(tried, base, words, percent), "verified"))
        forget(spark, stars, tried, left)
        comp = _components(links)
        left = buckets.join(comp, "doc_id", "left").select("doc_id", "n", "place", "token", F.coalesce("comp", "doc_id").alias("comp"))
        apart = left.groupBy("token").agg(F.min("comp").alias("low"), F.max("comp").alias("top"), F.count(F.lit(1)).alias("c")).where("low <> top")
        left = saved(left.join(apart.select("token", F.expr(f"(c - 1) div {SLOT} + 1").alias("slots")), "token"), "apart")
        if turn and not links[-1].limit(1).count():
            break
    one = left.select("token", F.col("doc_id").alias("a"), F.col("comp").alias("comp_a"), F.col("n").alias("n_a"), F.col("place").alias("place_a"))
    two = left.select("token", F.col("doc_id").alias("b"), F.col("comp").alias("comp_b"), F.col("n").alias("n_b"), F.col("place").alias("place_b"))
    rest = one.join(two, "token").where((F.col("a") < F.col("b")) & (F.col("comp_a") != F.col("comp_b")) & _fit("n_a", "place_a", "n_b", "place_b", percent)).select("a", "b").distinct()
    tried = saved(_passing(saved(rest, "rest"), reps, percent), "candidates")
    links.append(saved(verify_pairs(tried, base, words, percent), "verified"))
    comp = _components(links)
    forget(spark, buckets, reps, left, tried, *links)
    return member.join(comp.withColumnRenamed("doc_id", "rep"), "rep", "left").select("doc_id", F.col("n").cast("long").alias("n_shingles"), F.coalesce("comp", "rep").alias("component_id"))


def _with_class(every: DataFrame, classes: DataFrame, signs: list[str]) -> DataFrame:
    """The profiles with the representative of their class, if it has several members. The classes are broadcast up to a size; beyond it
    they are joined under salts, so that the members of a large class are dealt over several tasks."""
    if classes.count() <= BROADCAST_CLASSES:
        return every.join(F.broadcast(classes), signs, "left")
    dealt = classes.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return every.withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(SALTS)).cast("int")).join(dealt, [*signs, "salt"], "left").drop("salt")


def _components(links: list[DataFrame]) -> DataFrame:
    edges = links[0]
    for more in links[1:]:
        edges = edges.unionByName(more)
    return saved(connected_components(edges).select(F.col("node").alias("doc_id"), F.col("component").alias("comp")), "components")
