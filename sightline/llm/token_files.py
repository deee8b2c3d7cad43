"""Token ids in Parquet list columns: sorted shards with controlled row groups, pages and encodings."""

from __future__ import annotations

import os
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .bpe import Pieces, newer_of
from .common import shared_dir, slices, tidy

#: More than the distinct pieces of some tens of megabytes of text: with fewer, generations push out pieces that the next documents need again.
_CACHE_ROWS = 400_000
_CACHE_PIECE = 64
_STEP = 1000
#: The letter that stands for the byte of a space in vocabularies.
_SPACE = "\u0120"
#: Shards grow to about so much input before there are more of them.
SHARD_BYTES = 256 << 20
_READY: dict[str, "LibraryEncoder"] = {}


class LibraryEncoder:
    """Ids as the ``tokenizers`` library gives them, with the ids of recent pieces kept.

    The library's own pre-tokenizer pattern cuts a text into pieces that merge alone; each piece that two generations of
    recent ones lack goes through the library, all of a step at once. Texts that hold an added token go through it whole.
    """

    def __init__(self, path: str, newer: dict[str, str]):
        from tokenizers import Tokenizer

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a worker has one core
        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        self.added = [t.content for t in self.library.get_added_tokens_decoder().values()]
        vocab = self.library.get_vocab(with_added_tokens=False)
        self.spaced = np.zeros(self.library.get_vocab_size() + 1, bool)
        self.spaced[[i for s, i in vocab.items() if s[0] == _SPACE]] = True
        self.pieces = Pieces(newer)
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}

    def encode(self, texts: list[str]) -> list[bytes]:
        cut = [None if any(a in t for a in self.added) else self.pieces.cut(t) for t in texts]
        if len(self.young) > _CACHE_ROWS:
            self.old, self.young = self.young, {}
        young, old = self.young, self.old
        need = set().union(*(c for c in cut if c)).difference(young)
        young.update((p, old[p]) for p in need.intersection(old))
        names = [p for p in need if p not in young]
        plain: list[str] = []
        rest: list[str] = []
        for p in names:
            (plain if p[0] == " " and p[1:].isalpha() else rest).append(p)
        for some, (ids, ends) in ((plain, self._in_a_row(plain)), (rest, self._each(rest))):
            raw, ends = ids.tobytes(), (4 * ends).tolist()
            young.update((p, raw[a:b]) for p, a, b in zip(some, ends, ends[1:]))
        out = [
            np.array(self.library.encode(t, add_special_tokens=False).ids, np.uint32).tobytes() if found is None else b"".join(map(young.__getitem__, found))
            for t, found in zip(texts, cut)
        ]
        for p in names:
            if len(p) > _CACHE_PIECE:
                del young[p]
        return out


    def _each(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the pieces, and where those of each begin and end."""
        made = self.library.encode(pieces, is_pretokenized=True, add_special_tokens=False)
        return np.array(made.ids, np.uint32), np.searchsorted(np.array(made.word_ids, np.int64), np.arange(len(pieces) + 1))

    def _in_a_row(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """As ``_each``, for pieces of a space and letters: the library cuts their row at the spaces, so a piece begins with each token that begins
        with a space, and neither offsets nor words have to be made."""
        ids = np.array(self.library.encode_batch_fast(["".join(pieces)], add_special_tokens=False)[0].ids, np.uint32)
        starts = np.flatnonzero(self.spaced[ids])
        return (ids, np.append(starts, len(ids))) if len(starts) == len(pieces) else self._each(pieces)


def library(path: str, newer: dict[str, str]) -> LibraryEncoder:
    if path not in _READY:
        _READY[path] = LibraryEncoder(path, newer)
    return _READY[path]


def _size(docs: DataFrame) -> int:
    """Bytes of the input as the planner knows them, 0 where it doesn't."""
    known = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return known if known < 1 << 60 else 0


def write_token_files(docs: DataFrame, tokenizer_path: str, target: str, end_id: int = 0, shards: int | None = None, row_group_bytes: int = 16 << 20, page_bytes: int = 256 << 10) -> None:
    """Encode ``docs`` (doc_id, text) and write Parquet shards in ascending doc_id order below ``target``.

    Columns: doc_id, shard, inside (ids before the document in its shard), n_tokens, ids_crc32 (of the little-endian ids), tokens (list of
    int). ``end_id`` ends every document. Row groups and pages have the given sizes, ids are dictionary encoded, or delta coded where a
    dictionary doesn't pay (format version 2), and the writer leaves column and offset indexes, so that a reader of metadata or of a range of
    documents skips the token pages. Documents are dealt by ranges of doc_id, null ids first, equal ids by a hash of the text. Null texts are
    empty. Spark's commit protocol makes lost tasks harmless. An empty table gives an empty data set.
    """
    spark = docs.sparkSession
    count = shards or max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-_size(docs) // SHARD_BYTES))

    newer = newer_of(tokenizer_path)

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = library(tokenizer_path, newer)
        end = np.uint32(end_id).tobytes()
        shard, before = TaskContext.get().partitionId(), 0
        for part in slices(batches, _STEP):
            ids = [i + end for i in own.encode([t or "" for t in part.column(1).to_pylist()])]
            sizes = np.array([len(i) // 4 for i in ids], np.int64)
            ends = np.cumsum(sizes)
            flat = pa.array(np.frombuffer(b"".join(ids), "<i4"), pa.int32())
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]).astype(np.int32)), flat)
            yield pa.RecordBatch.from_arrays(
                [part.column(0), pa.array(np.full(len(ids), shard, np.int32)), pa.array(before + ends - sizes), pa.array(sizes), pa.array([zlib.crc32(i) for i in ids], pa.int64()), lists],
                ["doc_id", "shard", "inside", "n_tokens", "ids_crc32", "tokens"],
            )
            before += int(ends[-1])

    kind = docs.schema["doc_id"].dataType.simpleString()
    order = F.col("doc_id").asc_nulls_first()
    dealt = docs.select("doc_id", "text").repartitionByRange(count, order).sortWithinPartitions(order, F.xxhash64("text"))
    (
        dealt.mapInArrow(run, f"doc_id {kind}, shard int, inside bigint, n_tokens bigint, ids_crc32 bigint, tokens array<int>")
        .write.option("parquet.block.size", row_group_bytes).option("parquet.page.size", page_bytes)
        .option("parquet.writer.version", "PARQUET_2_0").option("parquet.enable.dictionary", "true")
        .option("compression", "zstd").parquet(target)
    )


def read_token_files(spark: SparkSession, target: str, tokens: bool = True) -> DataFrame:
    """The shards as rows (doc_id, start, n_tokens, ids_crc32, and tokens): start counts the ids of all documents before.

    Starts come from metadata columns alone: the totals of the shards before, one row per shard, and the place inside the shard.
    """
    rows = spark.read.parquet(target)
    totals = rows.groupBy("shard").agg(F.max(F.col("inside") + F.col("n_tokens")).alias("total"))
    earlier = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    before = totals.select("shard", F.coalesce(F.sum("total").over(earlier), F.lit(0)).alias("before"))
    return rows.join(F.broadcast(before), "shard").select(  # one row per shard
        "doc_id", (F.col("before") + F.col("inside")).alias("start"), "n_tokens", "ids_crc32", *(["tokens"] if tokens else [])
    )


def verified(rows: DataFrame) -> DataFrame:
    """Recomputes n_tokens and ids_crc32 from the token lists that the files hold."""

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(2)
            flat, offsets = lists.values.to_numpy(zero_copy_only=False).astype("<u4", copy=False), lists.offsets.to_numpy()
            crcs = [zlib.crc32(flat[a:b].tobytes()) for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist())]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(np.diff(offsets).astype(np.int64)), pa.array(crcs, pa.int64())],
                ["doc_id", "start", "n_tokens", "ids_crc32"],
            )

    kind = rows.schema["doc_id"].dataType.simpleString()
    return rows.select("doc_id", "start", "tokens").mapInArrow(run, f"doc_id {kind}, start bigint, n_tokens bigint, ids_crc32 bigint")


def new_target(spark: SparkSession) -> str:
    return f"{shared_dir(spark)}/token-files-{uuid.uuid4().hex}"
