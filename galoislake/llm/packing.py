"""Best-fit packing of documents into sequences of bounded length, by residuals and a merge tree.

Each task encodes its documents, cuts the longer ones, and packs the pieces best-fit, longest first.
Bins that are nearly full are done. The others become items: round after round, fewer tasks pack them
best-fit into fuller bins, until one task holds all that is left or a round merges no bins.
Only (bin, filled) pairs travel between rounds; pieces are joined with their bin's moves at the end.

Defined results: a null text is an empty one, which is the closing id alone; repeated rows are packed
each; a null id stays null; an empty table gives no rows. Other columns are not read.
"""

from __future__ import annotations

import os
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from galoislake.llm.common import forget, settle, table, tidied
from galoislake.llm.vocab import vocabulary_path, word_encoder

CAPACITY = 2048
SLACK = 4  # a bin with at most so many free places is done
AT_ONCE = 50_000  # pieces that a task packs together
WORDS = 100_000  # words that a worker remembers, twice; more memory for less time
BINS_AT_ONCE = 8_000  # underfull bins that a task of a later round packs together
_BIN = 1 << 32


def best_fit(sizes: list[int], capacity: int = CAPACITY) -> tuple[list[int], list[int], list[int]]:
    """(bin of each item, its place there, how full each bin is): longest first, each item into the
    open bin that it leaves the least room in. Open bins are found through a bit set of residuals."""
    bins, places = [0] * len(sizes), [0] * len(sizes)
    filled: list[int] = []
    rooms: list[list[int]] = [[] for _ in range(capacity + 1)]
    some = 0
    for i in sorted(range(len(sizes)), key=lambda i: (-sizes[i], i)):
        size = sizes[i]
        fits = some >> size
        if fits:
            room = size + (fits & -fits).bit_length() - 1
            b = rooms[room].pop()
            if not rooms[room]:
                some &= ~(1 << room)
        else:
            b = len(filled)
            filled.append(0)
        bins[i], places[i] = b, filled[b]
        filled[b] += size
        room = capacity - filled[b]
        if room:
            rooms[room].append(b)
            some |= 1 << room
    return bins, places, filled


def pieces_of(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, at_once: int = AT_ONCE, remembered: int = WORDS, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Pieces, each with the bin that its own task packed it into."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        encode = word_encoder(vocabulary, remembered).ids
        first = TaskContext.get().partitionId() * _BIN
        rows: list[tuple] = []
        kind = pa.null()
        for b in batches:
            kind = b.column(0).type
            for key, body in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                ids = encode(body.as_py() or "") + b"\0\0\0\0"
                for k, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    rows.append((key, k, at // 4, len(part) // 4, zlib.crc32(part)))
                if len(rows) >= at_once:
                    out, first = _packed(rows, first, capacity, kind)
                    yield out
                    rows = []
        if rows:
            yield _packed(rows, first, capacity, kind)[0]

    kind = docs.schema[doc_id].dataType.simpleString()
    return docs.select(doc_id, text).mapInArrow(tidied(run), f"doc_id {kind}, piece int, start long, length long, ids_crc32 long, bin long, place long, filled int")


def _packed(rows: list[tuple], first: int, capacity: int, kind: pa.DataType) -> tuple[pa.RecordBatch, int]:
    bins, places, filled = best_fit([r[3] for r in rows], capacity)
    keys, piece, start, length, crc = zip(*rows, strict=True)
    columns = [pa.array(keys, kind), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64()), pa.array([first + b for b in bins], pa.int64()), pa.array(places, pa.int64()), pa.array([filled[b] for b in bins], pa.int32())]
    return pa.RecordBatch.from_arrays(columns, names=["doc_id", "piece", "start", "length", "ids_crc32", "bin", "place", "filled"]), first + len(filled)


def _repack(capacity: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, sizes = [], []
        for b in batches:
            ids += b.column("bin").to_pylist()
            sizes += b.column("filled").to_pylist()
        if ids:
            bins, places, filled = best_fit(sizes, capacity)
            into: dict[int, int] = {}
            for i, b in zip(ids, bins, strict=True):
                into.setdefault(b, i)  # a merged bin keeps the id of one of its parts
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([into[b] for b in bins], pa.int64()), pa.array(places, pa.int64()), pa.array([filled[b] for b in bins], pa.int32())], names=["bin", "into", "shift", "filled"])

    return run


def pack(docs: DataFrame, vocabulary: str | None = None, capacity: int = CAPACITY, slack: int = SLACK, bins_at_once: int = BINS_AT_ONCE, remembered: int = WORDS, **names: str) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id and offset of every piece."""
    pieces = settle(pieces_of(docs, vocabulary or vocabulary_path("word_bpe_49k.json"), capacity, remembered=remembered, **names), "pieces")
    moves = merge_underfull(pieces.where(F.col("filled") < capacity - slack).groupBy("bin").agg(F.max("filled").alias("filled")), capacity, slack, bins_at_once)
    out = pieces.join(moves.withColumnRenamed("bin", "from"), F.col("bin") == F.col("from"), "left")
    return out.select("doc_id", "piece", "start", "length", "ids_crc32", F.coalesce("into", "bin").alias("sequence_id"), (F.col("place") + F.coalesce("shift", F.lit(0))).alias("offset"))


def merge_underfull(bins: DataFrame, capacity: int, slack: int, bins_at_once: int) -> DataFrame:
    """(bin, into, shift) for every bin that starts underfull, over all rounds of the tree."""
    moves, left = None, settle(bins, "underfull")
    while True:
        count = left.count()
        tasks = max(1, -(-count // bins_at_once))
        step = settle(left.repartition(tasks).mapInArrow(_repack(capacity), "bin long, into long, shift long, filled int"), "round")
        forget(left)
        if moves is None:
            moves = step
        else:
            then = step.select(F.col("bin").alias("into"), F.col("into").alias("further"), F.col("shift").alias("more"), F.col("filled").alias("now"))
            joined = moves.join(then, "into", "left")
            old, moves = moves, settle(joined.select("bin", F.coalesce("further", "into").alias("into"), (F.col("shift") + F.coalesce("more", F.lit(0))).alias("shift"), F.coalesce("now", "filled").alias("filled")), "moves")
            forget(old)
        if tasks == 1:
            return moves
        merged = step.groupBy("into").agg(F.max("filled").alias("filled"))
        left = settle(merged.where(F.col("filled") < capacity - slack).select(F.col("into").alias("bin"), "filled"), "underfull")
        if left.count() == count:  # a round that merges nothing: what is left does not fit together
            return moves


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"), remembered=400_000)
