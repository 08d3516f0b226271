"""N-gram Jaccard join by grouped prefixes, exact, with connected components as its result.

A document is its set of five-word shingles, as 64-bit hashes. In one global order of shingles (rare
ones first, the heavy ones last) two sets with Jaccard similarity t or more share at least `c` shingles
among the first few of each, the prefixes. Documents with equal sets are one; sets with equal prefix and
size are one group, and only groups enter the inverted lists of prefix shingles.

Lists may be long where thousands of documents are near copies, so pairs within a list are never
written out. Rounds first compare each group with one leader it shares most with, verify the members'
sets and contract what is linked; rounds go on while they find links. What then shares prefix shingles
across different components is compared in full, so no link between components is lost. Lists led by
one component make a bundle, and groups that stand in enough of its lists are members: their sets meet
one another. Any other group meets each component with which it shares at least `c` shingles. Meetings
are held inside of tasks, block by block of whole sets, and only links leave a task.

Nothing but the heavy shingles (at most HEAVY, only an order) and a bit map of fixed size is sent to
tasks. Defined results: null and empty texts, and texts of white space, have no shingles and link with
nothing; a text of fewer than five words is one shingle; rows with a null id link with nothing;
repeated rows get the same component; an empty table gives no rows. Other columns are not read.
"""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from galoislake.llm.common import forget, release, settle, shared_dir, table, tidied
from galoislake.llm.graph import components

WORDS, PERCENT = 5, 80
HEAVY = 200_000  # shingles that end the order; which ones they are changes the cost, never the result
CHUNK, LOCAL = 1 << 21, 5  # shingles that a task counts together; a count that makes one a candidate
ROUNDS = 4
SETS, SHINGLES = 512, 500_000  # bounds of one side of a block
_BITS = 1 << 26
_U = np.uint64


def _powers(n: int, base: int) -> np.ndarray:
    out = np.full(n, base, dtype=_U)
    if n:
        out[0] = 1
    return np.multiply.accumulate(out)


_BASE = 0x9E3779B97F4A7C15  # odd, so that it has an inverse
_INVERSE = pow(_BASE, -1, 1 << 64)
_LETTERS = np.random.default_rng(1_618).integers(1, 1 << 63, 256, dtype=np.int64).astype(_U)
_TABLES: dict[str, np.ndarray] = {"up": _powers(1 << 12, _BASE), "down": _powers(1 << 12, _INVERSE)}


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def shingle_set(text: str | None, words: int = WORDS) -> np.ndarray:
    """The sorted distinct hashes of the text's shingles."""
    # bytes.lower() and bytes.split() know A-Z and the six ASCII blanks only.
    parts = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not parts:
        return np.zeros(0, dtype=_U)
    flat = np.frombuffer(b" ".join(parts), dtype=np.uint8)
    if len(flat) > len(_TABLES["up"]):
        size = 1 << (len(flat) - 1).bit_length()
        _TABLES.update(up=_powers(size, _BASE), down=_powers(size, _INVERSE))
    sums = np.zeros(len(flat) + 1, dtype=_U)
    np.cumsum(_LETTERS[flat] * _TABLES["up"][: len(flat)], out=sums[1:])
    ends = np.cumsum(np.fromiter(map(len, parts), dtype=np.int64, count=len(parts)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    k = min(words, len(parts))
    first, last = starts[: len(parts) - k + 1], ends[k - 1 :]
    return np.unique(_mixed((sums[last] - sums[first]) * _TABLES["down"][first] + (last - first).astype(_U)))


def least_common(n: int, percent: int = PERCENT) -> int:
    """Shingles that a prefix of a set of n is long enough to hold of any linked pair."""
    return 1 + -(-n * percent // 100) // 20


def prefix_length(n: int, percent: int = PERCENT) -> int:
    return min(n, n - -(-n * percent // 100) + least_common(n, percent))


def _needed(n: str, percent: int) -> Column:
    """least_common() of the smallest set that a set of size n may link with."""
    return F.expr(f"1 + (({percent} * (({percent} * {n} + 99) div 100) + 99) div 100) div 20")


def _signed(b: bytes) -> int:
    return int.from_bytes(b, "little", signed=True)


def heavy_shingles(docs: DataFrame, text: str, words: int, most: int = HEAVY) -> np.ndarray:
    """The most frequent shingles of all documents, the most frequent one last."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for b in batches:
            for t in b.column(0):
                held.append(shingle_set(t.as_py(), words))
                size += len(held[-1])
                if size >= CHUNK:
                    yield counted(held)
                    held, size = [], 0
        if held:
            yield counted(held)

    def counted(held: list[np.ndarray]) -> pa.RecordBatch:
        token, n = np.unique(np.concatenate(held), return_counts=True)
        return pa.RecordBatch.from_pydict({"token": pa.array(token[n >= LOCAL].view(np.int64)), "n": pa.array(n[n >= LOCAL])})

    rows = docs.select(text).mapInArrow(tidied(run), "token long, n long").groupBy("token").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "token").limit(most)
    return rows.select("token").toArrow().column(0).to_numpy()[::-1].astype(np.int64).view(_U)


def _sets(docs: DataFrame, heavy: np.ndarray, doc_id: str, text: str, words: int, percent: int) -> DataFrame:
    """Per document: size n, digest (a, b) of its set, group g of its prefix, and the prefix."""
    at = heavy.argsort()
    known = heavy[at]

    def ordered(s: np.ndarray) -> np.ndarray:
        if not len(known):
            return s
        i = np.minimum(np.searchsorted(known, s), len(known) - 1)
        is_heavy = known[i] == s
        late = s[is_heavy]
        return np.concatenate([s[~is_heavy], late[at[i[is_heavy]].argsort(kind="stable")]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for low in range(0, batch.num_rows, 1000):
                part = batch.slice(low, 1000)
                n, a, b, g, prefix = [], [], [], [], []
                for t in part.column(1):
                    s = shingle_set(t.as_py(), words)
                    d = hashlib.blake2b(s.tobytes(), digest_size=16).digest()
                    p = ordered(s)[: prefix_length(len(s), percent)]
                    n.append(len(s))
                    a.append(_signed(d[:8]))
                    b.append(_signed(d[8:]))
                    g.append(_signed(hashlib.blake2b(p.tobytes() + len(s).to_bytes(8, "little"), digest_size=8).digest()))
                    prefix.append(p.view(np.int64))
                cuts = np.concatenate([[0], np.cumsum([len(p) for p in prefix])])
                lists = pa.ListArray.from_arrays(pa.array(cuts, pa.int32()), pa.array(np.concatenate(prefix)))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(n, pa.int64()), pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(g, pa.int64()), lists], names=["id", "n", "a", "b", "g", "prefix"])

    return docs.select(F.col(doc_id).cast("long"), text).mapInArrow(tidied(run), "id long, n long, a long, b long, g long, prefix array<long>")


def _whole_sets(docs: DataFrame, pool: DataFrame, doc_id: str, text: str, words: int) -> DataFrame:
    """(id, a, b, s): the whole sets of the pool, read anew. A bit map of fixed size spares most of the rest."""
    bit = lambda c: F.pmod(F.xxhash64(c), F.lit(_BITS)) + 1  # noqa: E731  bitmap buckets count from 1
    marks = np.zeros(_BITS // 8, dtype=np.uint8)
    position = F.bitmap_bit_position(F.col("bit"))
    for r in pool.select(bit(F.col("id")).alias("bit")).groupBy(F.bitmap_bucket_number(F.col("bit")).alias("k")).agg(F.bitmap_construct_agg(position).alias("m")).collect():  # _BITS / 32768 rows
        own = np.frombuffer(r.m, dtype=np.uint8)
        marks[(r.k - 1) * 4096 : r.k * 4096] = np.frombuffer(r.m, dtype=np.uint8)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            bits = batch.column(2).to_numpy(zero_copy_only=False) - 1
            rows = np.flatnonzero(marks[bits // 8] >> (bits % 8).astype(np.uint8) & 1)
            for low in range(0, len(rows), 500):
                part = batch.take(pa.array(rows[low : low + 500]))
                s = [shingle_set(t.as_py(), words).tobytes() for t in part.column(1)]
                d = [hashlib.blake2b(x, digest_size=16).digest() for x in s]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([_signed(x[:8]) for x in d], pa.int64()), pa.array([_signed(x[8:]) for x in d], pa.int64()), pa.array(s, pa.binary())], names=["id", "a", "b", "s"])

    ids = F.col(doc_id).cast("long")
    read = docs.where(F.col(doc_id).isNotNull()).select(ids.alias("id"), F.col(text), bit(ids).alias("bit"))
    found = read.mapInArrow(tidied(run), "id long, a long, b long, s binary")
    # Dealt once, by id: the digests are compared as a filter, so that they are no keys of the join.
    own = pool.select(F.col("id").alias("pool_id"), F.col("a").alias("pool_a"), F.col("b").alias("pool_b"))
    same = (F.col("id") == F.col("pool_id")) & (F.col("a").bitwiseXOR(F.col("pool_a")) == 0) & (F.col("b").bitwiseXOR(F.col("pool_b")) == 0)
    buckets = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return found.repartition(buckets, "id").join(own, same, "left_semi").dropDuplicates(["id"])


def _dealt(df: DataFrame, by: str, again: bool = True) -> DataFrame:
    """df as a table dealt by a column, so that later joins by it leave its rows where they are."""
    spark = df.sparkSession
    name = f"galoislake_{by}_{uuid.uuid4().hex}"
    buckets = int(spark.conf.get("spark.sql.shuffle.partitions"))
    (df.repartition(buckets, by) if again else df).write.bucketBy(buckets, by).option("path", f"{shared_dir(spark)}/{name}").saveAsTable(name)
    return spark.table(name)


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Those (x, y) whose whole sets are similar enough."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for i, (s, t) in enumerate(zip(batch.column("s").to_pylist(), batch.column("t").to_pylist(), strict=True)):
                s, t = np.frombuffer(s, dtype=_U), np.frombuffer(t, dtype=_U)
                at = np.minimum(np.searchsorted(t, s), len(t) - 1)
                both = int((t[at] == s).sum())
                if 100 * both >= percent * (len(s) + len(t) - both):
                    keep.append(i)
            yield batch.select(["x", "y"]).take(pa.array(keep, pa.int64()))

    one = sets.select(F.col("id").alias("x"), "s")
    two = sets.select(F.col("id").alias("y"), F.col("s").alias("t"))
    return pairs.distinct().join(one, "x").join(two, "y").select("x", "y", "s", "t").mapInArrow(tidied(run), "x long, y long")


def near_duplicates(docs: DataFrame, percent: int = PERCENT, words: int = WORDS, rounds: int = ROUNDS, heavy: int = HEAVY, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_shingles and component_id of every row."""
    rows = settle(_sets(docs, heavy_shingles(docs, text, words, heavy), doc_id, text, words, percent), "sets")
    some = rows.where("n > 0 AND id IS NOT NULL")
    sets = settle(some.groupBy("a", "b").agg(F.min("id").alias("id"), F.first("n").alias("n"), F.first("g").alias("g")), "distinct")
    by_token = Window.partitionBy("token")
    lists = some.select("g", F.explode("prefix").alias("token")).withColumns({"least": F.min("g").over(by_token), "most": F.max("g").over(by_token)})
    shared = settle(lists.where("least != most").select("token", "g").distinct(), "lists")

    counts = shared.groupBy("g").agg(F.count("*").alias("c"))
    grouped = sets.join(counts, "g", "left").withColumn("enough", F.coalesce(F.col("c") >= _needed("n", percent), F.lit(False)))
    several = sets.groupBy("g").agg(F.count("*").alias("sets"), F.min("id").alias("lead")).where("sets > 1")
    pool = settle(grouped.join(several, "g", "left").where("enough OR sets > 1").select("id", "a", "b", "n", "g", "enough", "lead"), "pool")
    whole = _dealt(_whole_sets(docs, pool, doc_id, text, words), "id", again=False)
    active = _dealt(shared.join(pool.where("enough").select("g").distinct(), "g", "left_semi"), "g")
    forget(shared)

    links = settle(_verified(pool.where("id != lead").select(F.col("id").alias("x"), F.col("lead").alias("y")), whole, percent), "links")
    parts = settle(components(links, "x", "y"), "parts")
    for _ in range(rounds):
        pairs = settle(_leaders(pool, active, parts, percent).distinct(), "pairs")
        new = settle(_verified(pairs, whole, percent), "new")
        tried, linked = pairs.count(), new.count()
        forget(pairs)
        if not linked:
            break
        old, links = links, settle(links.unionByName(new), "links")
        forget(old)
        forget(new)
        old, parts = parts, settle(components(links, "x", "y"), "parts")
        forget(old)
        if linked * 2 < tried:  # what is left is mostly not linked, and compared in full below
            break
    own = settle(_labelled(pool, parts), "labelled")
    tagged = _dealt(_bundled(own, active, percent), "token")
    meetings = _across(own, tagged, percent).unionByName(_bundles(own, tagged))
    rest = settle(_met(settle(meetings, "meetings"), whole, percent), "rest")
    if not rest.isEmpty():
        parts = components(links.unionByName(rest), "x", "y")
    of_set = sets.join(parts, sets["id"] == parts["node"], "left").select("a", "b", F.coalesce("component", "id").alias("component"))
    out = rows.join(of_set, ["a", "b"], "left")
    own = F.when((F.col("n") > 0) & F.col("id").isNotNull(), F.col("component")).otherwise(F.col("id"))
    return out.select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), own.alias("component_id"))


def _labelled(pool: DataFrame, parts: DataFrame) -> DataFrame:
    return pool.join(parts, pool["id"] == parts["node"], "left").select("id", "n", "g", F.coalesce("component", "id").alias("part"))


def _leaders(pool: DataFrame, active: DataFrame, parts: DataFrame, percent: int) -> DataFrame:
    """(x, y): for each part of a group, its sets against one set of the other part that leads most of
    the lists the group is in."""
    own = settle(_labelled(pool, parts), "labelled")
    groups = own.groupBy("g", "part").agg(F.min("id").alias("first"), F.max("n").alias("n"))
    run = active.join(groups, "g")
    lead = run.groupBy("token").agg(F.min(F.struct("part", "g", "first")).alias("lead"), F.max("part").alias("last")).where("lead.part != last").select("token", F.col("lead.part").alias("to_part"), F.col("lead.first").alias("y"))
    found = run.join(lead, "token").where("part != to_part").groupBy("g", "part", "y").agg(F.count("*").alias("c"), F.first("n").alias("n")).where(F.col("c") >= _needed("n", percent))
    best = found.groupBy("g", "part").agg(F.max(F.struct("c", "y"))["y"].alias("y"))
    return own.join(best, ["g", "part"]).select(F.col("id").alias("x"), "y")


def _bundled(own: DataFrame, active: DataFrame, percent: int) -> DataFrame:
    """The lists that hold several parts, each with the least of them as its lead. The lists of one lead
    are its bundle; a group that stands in enough of them is a member."""
    sizes = own.groupBy("part").agg(F.count("*").alias("size"))
    run = active.join(own.groupBy("g", "part").agg(F.max("n").alias("n")).join(sizes, "part"), "g")
    lead = run.groupBy("token").agg(F.min("part").alias("lead"), F.max("part").alias("last")).where("lead != last").select("token", "lead")
    own_lists = F.count("*").over(Window.partitionBy("lead", "g", "part"))
    return run.join(lead, "token").withColumn("member", own_lists >= _needed("n", percent)).select("lead", "token", "g", "part", "n", "size", "member")


def _bundles(own: DataFrame, tagged: DataFrame) -> DataFrame:
    """Meetings of the members of each bundle with one another."""
    members = tagged.where("member").select("lead", "g", "part").distinct()
    several = members.groupBy("lead").agg(F.min("part").alias("p"), F.max("part").alias("q")).where("p != q").select("lead")
    sets = members.join(several, "lead", "left_semi").join(own, ["g", "part"])
    return _same_key(_both_sides(sets.select(F.struct(F.lit("bundle"), "lead").alias("key"), "id", "part", "n")))


def _both_sides(members: DataFrame) -> DataFrame:
    return members.withColumn("asks", F.explode(F.array(F.lit(True), F.lit(False))))


def _across(own: DataFrame, run: DataFrame, percent: int) -> DataFrame:
    """Meetings of groups with other parts that may hold a linked set. Members of one bundle meet there."""
    held = run.groupBy("token", "part", "member").agg(F.first("size").alias("size"), F.min("n").alias("low"), F.max("n").alias("high"))
    other = held.select("token", F.col("part").alias("to_part"), F.col("size").alias("to_size"), "low", "high", F.col("member").alias("to_member"))
    may = (F.struct("size", "part") < F.struct("to_size", "to_part")) & (100 * F.col("high") >= percent * F.col("n")) & (percent * F.col("low") <= 100 * F.col("n"))
    pairs = run.where("NOT member").join(other, "token").where(may).unionByName(run.where("member").join(other.where("NOT to_member"), "token").where(may))
    found = pairs.groupBy("g", "part", "to_part").agg(F.count("*").alias("c"), F.first("n").alias("n")).where(F.col("c") >= _needed("n", percent)).select("g", "part", "to_part")
    asks = own.join(found, ["g", "part"]).select(F.struct(F.lit("part"), "to_part").alias("key"), "id", "part", "n", F.lit(True).alias("asks"))
    asked = own.join(found.select(F.col("to_part").alias("part")).distinct(), "part").select(F.struct(F.lit("part"), F.col("part").alias("to_part")).alias("key"), "id", "part", "n", F.lit(False).alias("asks"))
    # Sets of one group share their whole prefix, whether or not other groups do.
    mixed = own.groupBy("g").agg(F.min("part").alias("p"), F.max("part").alias("q")).where("p != q").select("g")
    within = _both_sides(own.join(mixed, "g", "left_semi").select(F.struct(F.lit("group"), "g").alias("key"), "id", "part", "n"))
    return _same_key(asks).unionByName(_same_key(asked)).unionByName(_same_key(within))


def _same_key(meetings: DataFrame) -> DataFrame:
    """The key as two plain columns."""
    kind, number = meetings.schema["key"].dataType.names
    return meetings.select(F.col(f"key.{kind}").alias("kind"), F.col(f"key.{number}").alias("number"), "id", "part", "n", "asks")


def _met(meetings: DataFrame, whole: DataFrame, percent: int) -> DataFrame:
    """Links (x, y) between different parts: the sets of a meeting that ask, against the others, in blocks
    of bounded size inside of tasks; only links leave a task."""
    key = ["kind", "number"]
    blocks = lambda side: F.ceil(F.greatest(F.count_if(side) / SETS, F.sum(F.when(side, F.col("n")).otherwise(0)) / SHINGLES, F.lit(1.0)))
    placed = meetings.join(meetings.groupBy(*key).agg(blocks(F.col("asks")).alias("rows"), blocks(~F.col("asks")).alias("columns")), key)
    at = F.pmod(F.xxhash64("id"), F.when(F.col("asks"), F.col("rows")).otherwise(F.col("columns")))
    each = placed.withColumn("at", at).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.when(F.col("asks"), F.col("columns")).otherwise(F.col("rows")) - 1)))
    sent = each.select(*key, "id", "part", "asks", F.when(F.col("asks"), F.col("at")).otherwise(F.col("other")).alias("i"), F.when(F.col("asks"), F.col("other")).otherwise(F.col("at")).alias("j"))

    def compare(t: pa.Table) -> pa.Table:
        ids, part, asks = (t.column(c).to_numpy() for c in ("id", "part", "asks"))
        sets = [np.frombuffer(x, dtype=_U) for x in t.column("s").to_pylist()]
        sizes = np.array([len(x) for x in sets], dtype=np.int64)
        a, b = np.flatnonzero(asks), np.flatnonzero(~asks)
        _, code, often = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
        keep = often[code] > 1  # shingles of one set alone are in no intersection
        code, row = (np.cumsum(often > 1) - 1)[code[keep]], np.repeat(np.arange(len(sets)), sizes)[keep]
        both = np.zeros((len(a), len(b)), dtype=np.float32)
        for low in range(0, int(code.max(initial=-1)) + 1, 4096):
            inside = (code >= low) & (code < low + 4096)
            x = np.zeros((len(sets), 4096), dtype=np.float32)
            x[row[inside], code[inside] - low] = 1
            both += x[a] @ x[b].T
        linked = 100 * both >= percent * (sizes[a][:, None] + sizes[b][None] - both)
        linked &= part[a][:, None] != part[b][None]
        x, y = np.nonzero(linked)
        if len(sets) > 200:
            release()
        return pa.table({"x": pa.array(ids[a[x]], pa.int64()), "y": pa.array(ids[b[y]], pa.int64())})

    return sent.join(whole.select("id", "s"), "id").groupBy(*key, "i", "j").applyInArrow(compare, "x long, y long")


def keep_one(docs: DataFrame, **options: object) -> DataFrame:
    """The rows of docs whose document has the least id of its component."""
    gone = near_duplicates(docs, **options).where("doc_id != component_id").select(F.col("doc_id").alias("_nd_gone")).distinct()
    return docs.join(gone, F.col("doc_id").cast("long") == F.col("_nd_gone"), "left_anti")


def op9_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))
