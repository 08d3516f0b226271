"""Byte-level BPE as folds of higher-order functions over byte arrays, with a literal rank map.

Texts are cut by the vocabulary's pattern. A fold starts from the bytes of a word, as an array of ids,
and merges the leftmost pair of least rank until no pair has a rank; a word that has a rank itself is that
id. The words are counted, and the most frequent ones (at most `TABLE`, whatever the corpus) are folded
once and sent to the tasks in a compact form, sorted by hash; an entry is taken only if its ids spell the
word. Tasks fold each other word of a partition where it stands first. A fold takes time with the square
of a word, so runs of more than `LONG` bytes without a cut take the same merges from a heap of pairs
instead. Decoding looks up the bytes of each id and concatenates them.

The rank map takes a pair of ids to the id of their bytes together, which is its rank. It is literal
arrays without collisions: the pair's 64-bit hash finds a displacement in one, and with it the place of
the pair's own hash and rank in two others.

Defined results: a null text is an empty one and has no ids; repeated rows are encoded each; an empty
table gives no rows. Columns other than the named ones are not read.
"""

from __future__ import annotations

import functools
import hashlib
import heapq
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.classic.column import Column as _JvmColumn

from galoislake.llm.common import settle, table, tidied
from galoislake.llm.vocab import cutter, ranks, split_pattern, vocabulary_path

TABLE = 1_500_000  # about 30 bytes each
REMEMBERED = 300_000  # words that a task has at hand, but for those of its last text
LONG = 128
_SLOT_BITS, _BUCKET_BITS = 18, 15
_AT_BITS = 12  # of a pair's place in a word that is folded; more than LONG needs


def pattern() -> str:
    """The vocabulary's pattern; white space is Unicode's in it."""
    return "(?U)" + split_pattern()


def _pairs(path: str) -> list[tuple[int, int, int]]:
    """Every (left id, right id, id of both together)."""
    by_bytes = ranks(path)
    return [(by_bytes[t[:k]], by_bytes[t[k:]], r) for t, r in by_bytes.items() for k in range(1, len(t)) if t[:k] in by_bytes and t[k:] in by_bytes]


def _parted(hashes: np.ndarray) -> tuple[int, np.ndarray, np.ndarray]:
    """(skip, bucket, rest): the first bits of each hash, and those after `skip` bits, which tell apart
    the hashes of one bucket."""
    bits = hashes.view(np.uint64)
    bucket = (bits >> np.uint64(64 - _BUCKET_BITS)).astype(np.int64)
    for skip in range(_BUCKET_BITS, 65 - _SLOT_BITS):
        rest = ((bits << np.uint64(skip)) >> np.uint64(64 - _SLOT_BITS)).astype(np.int64)
        if len(np.unique(bucket << _SLOT_BITS | rest)) == len(hashes):
            return skip, bucket, rest
    raise ValueError("the hashes of two pairs agree in too many bits")


def _placed(hashes: np.ndarray, values: np.ndarray) -> tuple[int, np.ndarray, np.ndarray, np.ndarray]:
    """(skip, displacement of each bucket, hash in each place, value in each place): a perfect hash."""
    skip, bucket, rest = _parted(hashes)
    by = np.argsort(bucket, kind="stable")
    cut = np.searchsorted(bucket[by], np.arange((1 << _BUCKET_BITS) + 1))
    size = 1 << _SLOT_BITS
    taken, moves, placed, held = np.zeros(size, dtype=bool), np.zeros(1 << _BUCKET_BITS, dtype=np.int64), np.zeros(size, dtype=np.int64), np.zeros(size, dtype=np.int64)
    for b in np.argsort(cut[:-1] - cut[1:], kind="stable"):
        own = by[cut[b] : cut[b + 1]]
        if not len(own):
            break
        for d in range(size):
            at = rest[own] ^ d
            if not taken[at].any():
                break
        else:
            raise ValueError("the rank map is too full")
        taken[at], moves[b], placed[at], held[at] = True, d, hashes[own], values[own]
    return skip, moves, placed, held


def _literal(spark: SparkSession, values: np.ndarray) -> Column:
    """A literal array of int32 or int64 in Spark's binary layout: plans neither spell it out nor box it."""
    catalyst = spark._jvm.org.apache.spark.sql.catalyst.expressions
    flat = values.tobytes()
    raw = bytearray(len(values).to_bytes(8, "little") + bytes((len(values) + 63) // 64 * 8) + flat + bytes(-len(flat) % 8))
    data = catalyst.UnsafeArrayData()
    data.pointTo(raw, spark._jvm.org.apache.spark.unsafe.Platform.BYTE_ARRAY_OFFSET, len(raw))
    kind = spark._jvm.org.apache.spark.sql.types.DataType.fromDDL("array<int>" if values.itemsize == 4 else "array<bigint>")
    return _JvmColumn(spark._jvm.org.apache.spark.sql.classic.ExpressionUtils.column(catalyst.Literal(data, kind)))


class Coder:
    """The fold of one vocabulary file, as a column.

    A pair is known by the 64-bit hash of its two ids. A rank and the pair's place in the word are one
    number, so the least one tells both; array_position would end each search by an exception. The
    expressions of the fold keep clear of arithmetic, which is slow where expressions are interpreted."""

    def __init__(self, spark: SparkSession, path: str):
        pairs = np.array(_pairs(path), dtype=np.int64)
        if pairs[:, 2].max() >= 1 << 31 - _AT_BITS:
            raise ValueError("ranks are too high to stand beside a place")
        rows = pa.table({"l": pairs[:, 0].astype(np.int32), "r": pairs[:, 1].astype(np.int32), "v": pairs[:, 2]})
        hashed = spark.createDataFrame(rows).select(F.xxhash64("l", "r").alias("h"), "v").toArrow()  # as many rows as the vocabulary has pairs
        self._skip, moves, placed, held = _placed(hashed.column(0).to_numpy().copy(), hashed.column(1).to_numpy())
        self._moves, self._placed, self._held = (_literal(spark, x) for x in (moves, placed, (held << _AT_BITS).astype(np.int32)))

    def _best(self, ids: Column) -> Column:
        """The least rank of a neighbouring pair with the pair's place in its low bits; null for none."""

        def found(hashes: Column) -> Column:
            places = F.transform(hashes, lambda h: F.get(self._moves, F.shiftrightunsigned(h, 64 - _BUCKET_BITS)).bitwiseXOR(F.shiftrightunsigned(F.shiftleft(h, self._skip), 64 - _SLOT_BITS)))
            return F.transform(places, lambda at, i: F.when(F.get(self._placed, at) == F.get(hashes, i), F.get(self._held, at).bitwiseOR(i)))

        return F.array_min(_named(F.transform(F.slice(ids, F.lit(2), F.size(ids)), lambda right, i: F.xxhash64(F.get(ids, i), right)), found))

    def fold(self, ids: Column) -> Column:
        """The ids of a word from the ids of its bytes, at most 2^_AT_BITS."""

        def state(p: Column) -> Column:
            return F.struct(p.alias("p"), self._best(p).alias("b"))

        def merged(s: Column) -> Column:
            p, b = s["p"], s["b"]
            put = lambda k: F.transform(p, lambda x, i: F.when(i == k, F.shiftrightunsigned(b, _AT_BITS)).otherwise(x))
            joined = _named(b.bitwiseAND(F.lit((1 << _AT_BITS) - 1)), lambda k: _named(k + 1, lambda gone: F.filter(put(k), lambda x, i: i != gone)))
            return F.when(b.isNotNull(), _named(joined, state)).otherwise(s)

        folded = F.aggregate(F.slice(ids, F.lit(2), F.size(ids)), state(ids), lambda s, _: merged(s))["p"]
        return F.when(F.size(ids) > 1, folded).otherwise(ids)


def _named(value: Column, use: Callable[[Column], Column]) -> Column:
    """use(value), with the value computed once: it becomes the variable of a one-element transform."""
    return F.element_at(F.transform(F.array(value), use), 1)


def merge_long(word: bytes, by_bytes: dict[bytes, int]) -> list[int]:
    """The same merges, leftmost pair of least rank first, from a heap of pairs."""
    ends, before = list(range(1, len(word) + 1)), list(range(-1, len(word) - 1))  # of the piece that begins at each byte
    waiting = [(r, i, i + 2) for i in range(len(word) - 1) if (r := by_bytes.get(word[i : i + 2])) is not None]
    heapq.heapify(waiting)
    live = [True] * len(word)

    def offer(i: int) -> None:
        if i >= 0 and ends[i] < len(word) and (r := by_bytes.get(word[i : ends[ends[i]]])) is not None:
            heapq.heappush(waiting, (r, i, ends[ends[i]]))

    while waiting:
        _, i, end = heapq.heappop(waiting)
        if not live[i] or ends[i] == len(word) or ends[ends[i]] != end or end == ends[i]:
            continue
        live[ends[i]], ends[i] = False, end
        if end < len(word):
            before[end] = i
        offer(before[i])
        offer(i)
    return [by_bytes[word[i : ends[i]]] for i in range(len(word)) if live[i]]


@functools.cache
def _byte_ids(path: str) -> np.ndarray:
    by_bytes = ranks(path)
    return np.array([by_bytes[bytes([b])] for b in range(256)], dtype=np.int32)


def _spelled(words: list[bytes], path: str) -> pa.ListArray:
    """The ids of the bytes of each word."""
    ends = np.cumsum([0, *map(len, words)])
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(_byte_ids(path)[np.frombuffer(b"".join(words), np.uint8)]))


def words_of(text: Column) -> Column:
    return F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(pattern()), F.lit(0))


def frequent_words(docs: DataFrame, most: int, *, text: str = "text") -> DataFrame:
    """At most `most` words: all those that occur at least so often that no more than that do."""
    words = docs.select(F.explode(words_of(F.col(text))).alias("word")).where(F.octet_length("word") <= LONG)
    counts = settle(words.groupBy("word").agg(F.count("*").alias("n")), "words")
    least, total = None, 0
    for r in counts.groupBy(F.least("n", F.lit(100_000)).alias("n")).agg(F.count("*").alias("words")).orderBy(F.desc("n")).toLocalIterator():  # at most 100,000 rows
        total += r.words
        if total > most:
            break
        least = r.n
    return counts.where(F.col("n") >= least).select("word") if least else counts.select("word").limit(0)


@dataclass(frozen=True)
class _Table:
    """The ids of many words, found by the words' hashes."""

    hashes: np.ndarray
    ends: np.ndarray
    flat: bytes  # little-endian int32

    def find(self, words: list[bytes], path: str) -> list[bytes | None]:
        if not len(self.hashes):
            return [None] * len(words)
        asked = np.array([xxhash.xxh64_intdigest(w, 42) for w in words], np.uint64).view(np.int64)
        at = np.minimum(np.searchsorted(self.hashes, asked), len(self.hashes) - 1)
        low, high, tokens = np.where(at > 0, self.ends[at - 1], 0).tolist(), self.ends[at].tolist(), _tokens(path)
        out: list[bytes | None] = []
        for w, same, a, b in zip(words, (self.hashes[at] == asked).tolist(), low, high, strict=True):
            ids = self.flat[4 * a : 4 * b] if same else None
            out.append(ids if ids is not None and b"".join([tokens[i] for i in memoryview(ids).cast("i")]) == w else None)
        return out


def _folded_table(words: DataFrame, coder: Coder, path: str) -> _Table:
    """The ids of at most `TABLE` words. Words that have ranks themselves are looked up in the vocabulary."""

    def spell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        whole = ranks(path)
        for b in batches:
            some = [w for w in (x.encode() for x in b.column(0).to_pylist()) if w not in whole]
            yield pa.RecordBatch.from_arrays([pa.array([xxhash.xxh64_intdigest(w, 42) for w in some], pa.uint64()).view(pa.int64()), _spelled(some, path)], names=["hash", "start"])

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lists = b.column(1)
            ends = np.asarray(lists.offsets).astype(np.int64)
            flat = lists.values.to_numpy(zero_copy_only=False).astype("<i4")[ends[0] : ends[-1]]
            yield pa.RecordBatch.from_arrays([pa.array([b.column(0).to_numpy().tobytes()]), pa.array([np.diff(ends).astype("<i4").tobytes()]), pa.array([flat.tobytes()])], names=["hashes", "sizes", "flat"])

    ids = words.mapInArrow(tidied(spell), "hash long, start array<int>").select("hash", coder.fold(F.col("start")).alias("ids"))
    got = ids.mapInArrow(tidied(pack), "hashes binary, sizes binary, flat binary").toArrow().to_pydict()  # at most `TABLE` words
    hashes, sizes, flat = (np.frombuffer(b"".join(got[k]), t) for k, t in (("hashes", "<i8"), ("sizes", "<i4"), ("flat", "<i4")))
    order, ends = hashes.argsort(kind="stable"), np.cumsum(sizes.astype(np.int64))
    own = sizes[order].astype(np.int64)
    sorted_ends = np.cumsum(own)
    at = np.repeat((ends - sizes)[order] - sorted_ends + own, own) + np.arange(len(flat))
    return _Table(hashes[order], sorted_ends.astype(np.int32), flat[at].tobytes())


def encode(docs: DataFrame, vocabulary: str | None = None, most: int = TABLE, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id and ids (binary, little-endian int32) of every row."""
    path = vocabulary or vocabulary_path("byte_bpe_50k.tiktoken")
    coded, kind = _coded(docs, path, most, doc_id, text)

    def fill(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        others: list[bytes] = []
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(list(_filled(b, others)), pa.binary())], names=["doc_id", "ids"])

    return coded.mapInArrow(tidied(fill), f"doc_id {kind}, ids binary")


def _coded(docs: DataFrame, path: str, most: int, doc_id: str, text: str) -> tuple[DataFrame, str]:
    """doc_id, coded, folded and fresh: ids with -1, -2, ... for words that are not in the table, the ids of
    those of them that the partition had not had before, and whether their numbers begin anew."""
    cut_by, spark = split_pattern(), docs.sparkSession
    coder = Coder(spark, path)
    known = spark.sparkContext.broadcast(_folded_table(frequent_words(docs, most, text=text), coder, path))  # at most `most` words

    def look_up(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cut, whole, table = cutter(cut_by), ranks(path), known.value
        seen: dict[str, bytes] = {}
        given = 0
        for b in batches:
            coded, new, cuts, fresh = [], [], [0], []
            for t in b.column(1):
                words = cut(t.as_py() or "")
                fresh.append(len(seen) > REMEMBERED)
                if fresh[-1]:
                    seen, given = {}, 0
                parts = list(map(seen.get, words))
                if None in parts:
                    missing = list({w for w, p in zip(words, parts, strict=True) if p is None})
                    raw = [w.encode() for w in missing]
                    for w, r, own in zip(missing, raw, table.find(raw, path), strict=True):
                        if own is None and r in whole:
                            own = whole[r].to_bytes(4, "little")
                        elif own is None and len(r) > LONG:
                            own = np.array(merge_long(r, whole), "<i4").tobytes()
                        elif own is None:
                            given += 1
                            own = (-given).to_bytes(4, "little", signed=True)
                            new.append(r)
                        seen[w] = own
                    parts = list(map(seen.__getitem__, words))
                coded.append(b"".join(parts))
                cuts.append(len(new))
            lists = pa.ListArray.from_arrays(pa.array(cuts, pa.int32()), _spelled(new, path))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(coded, pa.binary()), lists, pa.array(fresh)], names=["doc_id", "coded", "new", "fresh"])

    kind = docs.schema[doc_id].dataType.simpleString()
    found = docs.select(doc_id, text).mapInArrow(tidied(look_up), f"doc_id {kind}, coded binary, new array<array<int>>, fresh boolean")
    return found.select("doc_id", "coded", F.transform("new", coder.fold).alias("folded"), "fresh"), kind


def _filled(b: pa.RecordBatch, others: list[bytes]) -> Iterator[bytes]:
    """The coded ids of each row with the other words' ids in their places. others: those words' ids so
    far in the partition; the batch's are added."""
    lists = b.column("folded")
    inner = lists.values
    flat, starts = inner.values.to_numpy().astype("<i4").tobytes(), (4 * np.asarray(inner.offsets)).tolist()
    first = np.asarray(lists.offsets).tolist()
    for i, (coded, fresh) in enumerate(zip(b.column("coded").to_pylist(), b.column("fresh").to_pylist(), strict=True)):
        if fresh:
            others.clear()
        others += [flat[starts[k] : starts[k + 1]] for k in range(first[i], first[i + 1])]
        ids = np.frombuffer(coded, "<i4")
        at = np.flatnonzero(ids < 0)
        if not len(at):
            yield coded
            continue
        parts, before = [], 0
        for k, w in zip((4 * at).tolist(), (-1 - ids[at]).tolist(), strict=True):
            parts += (coded[before:k], others[w])
            before = k + 4
        yield b"".join([*parts, coded[before:]])


@functools.cache
def _tokens(path: str) -> list[bytes]:
    by_bytes = ranks(path)
    tokens = [b""] * (max(by_bytes.values()) + 1)
    for token, rank in by_bytes.items():
        tokens[rank] = token
    return tokens


@functools.cache
def _token_table(path: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All tokens' bytes in a row, where each begins, and how long each is."""
    tokens = _tokens(path)
    sizes = np.array([len(t) for t in tokens], dtype=np.int64)
    return np.frombuffer(b"".join(tokens), np.uint8), np.cumsum(sizes) - sizes, sizes


def decode(ids: bytes, path: str) -> bytes:
    """The bytes of the ids, piece after piece."""
    flat, starts, sizes = _token_table(path)
    at = np.frombuffer(ids, "<i4")
    own = sizes[at]
    ends = np.cumsum(own)
    return flat[np.repeat(starts[at] - ends + own, own) + np.arange(ends[-1] if len(ends) else 0)].tobytes()


@functools.cache
def _decimals(count: int) -> np.ndarray:
    """Each number's decimal digits and a blank, filled up with zero bytes."""
    width = len(str(count)) + 1
    return np.frombuffer(b"".join(f"{i} ".encode().ljust(width, b"\0") for i in range(count)), np.uint8).reshape(count, width)


def decimal_ids(ids: bytes, path: str) -> bytes:
    """The ids as decimal numbers joined by one blank."""
    digits = _decimals(len(_token_table(path)[2]))[np.frombuffer(ids, "<i4")].ravel()
    return digits[digits != 0].tobytes()[:-1]


def digests(docs: DataFrame, vocabulary: str | None = None, most: int = TABLE, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_tokens, and the SHA-256 of the decimal ids and of the decoded bytes."""
    path = vocabulary or vocabulary_path("byte_bpe_50k.tiktoken")
    coded, kind = _coded(docs, path, most, doc_id, text)

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sha = lambda b: hashlib.sha256(b).hexdigest()
        others: list[bytes] = []
        for b in batches:
            ids = list(_filled(b, others))
            columns = [b.column(0), pa.array([len(c) // 4 for c in ids], pa.int64()), pa.array([sha(decimal_ids(c, path)) for c in ids], pa.string()), pa.array([sha(decode(c, path)) for c in ids], pa.string())]
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return coded.mapInArrow(tidied(digest), f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op7_byte_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digests(table(spark, sf_dir, "documents"))
