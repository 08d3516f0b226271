"""Embedding near-dedup: an exact range join in the metric of the unit sphere.

Vectors of one label within cosine `threshold` are within r = sqrt(2 - 2 threshold) of each other.
Exactly equal vectors are first collapsed into one with a count. Pivots split the vectors of a label
into cells, each vector at home with its nearest pivot; it visits the cell of another pivot only if it
is so near the border between the two (a consequence of the triangle inequality) that a partner may
live there. Cells then join on their own: every row of a cell against the cell's home rows, in blocks
of bounded size, so that a cell with a third of all rows is many tasks. A block returns link counts and
a spanning forest of its links, never all pairs.

Defined results: rows whose label is null, or whose vector is null, empty, zero or has a null, NaN or
infinite component, link with nothing; vectors of other lengths than their label's pivots link only to
vectors of their own length; ids are keys, rows repeating one are answered once each, with the links of
the distinct vectors. A null id is answered with no links. An empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from galoislake.llm.common import settle, table
from galoislake.llm.graph import components

THRESHOLD = 0.93
ROWS_A_PIVOT = 4000
MOST_PIVOTS = 4096
HOME_BLOCK, VISIT_BLOCK = 1000, 4000


def usable(vector: Column) -> Column:
    """Not null, not empty, every component finite, not all zero."""
    finite = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return F.coalesce(vector.isNotNull() & (F.size(vector) > 0) & finite & F.exists(vector, lambda x: x != 0), F.lit(False))


def matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), -1)


def unit(x: np.ndarray) -> np.ndarray:
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def dedup(vectors: DataFrame, threshold: float = THRESHOLD, rows_a_pivot: int = ROWS_A_PIVOT, home_block: int = HOME_BLOCK, visit_block: int = VISIT_BLOCK, *, vec_id: str = "vec_id", vector: str = "embedding", label: str = "label") -> DataFrame:
    """vec_id, n_links, component_id and kept of every row."""
    fit = vectors.where(F.col(vec_id).isNotNull() & F.col(label).isNotNull() & usable(F.col(vector))).select(F.col(vec_id).cast("long").alias("id"), F.col(vector).cast("array<double>").alias("x"), F.concat_ws(":", F.col(label).cast("string"), F.size(vector).cast("string")).alias("label"))
    fit = fit.withColumns({"h": F.xxhash64("label", "x"), "g": F.xxhash64(F.lit(1), "label", "x")}).dropDuplicates(["id", "h", "g"])
    same = settle(fit.groupBy("h", "g").agg(F.min_by("x", "id").alias("x"), F.first("label").alias("label"), F.min("id").alias("rep"), F.count("*").alias("copies")), "distinct")
    members = fit.select("id", "h", "g").join(same.select("h", "g", "rep", "copies"), ["h", "g"])
    cells = settle(_cells(same, threshold, rows_a_pivot), "cells")
    found = settle(_joined(cells, threshold, home_block, visit_block), "links")
    links = found.where("n > 0").groupBy("rep").agg(F.sum("n").alias("n"))
    parts = components(found.where("root is not null"), "rep", "root")
    full = members.join(links, "rep", "left").join(parts, members["rep"] == parts["node"], "left")
    own = full.groupBy("id").agg(F.sum(F.coalesce("n", F.lit(0)) + F.col("copies") - 1).alias("n"), F.min(F.coalesce("component", "rep")).alias("component"))
    out = vectors.select(F.col(vec_id)).join(own, F.col(vec_id) == F.col("id"), "left")
    component = F.coalesce("component", F.col(vec_id).cast("long"))
    return out.select(F.col(vec_id).alias("vec_id"), F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(component == F.col(vec_id), F.lit(True)).alias("kept"))


def _cells(same: DataFrame, threshold: float, rows_a_pivot: int) -> DataFrame:
    """(label, cell, home, rep, copies, x): each distinct vector in its home cell and those it visits."""
    total = same.count()
    most = min(MOST_PIVOTS, -(-total // rows_a_pivot))
    pivots: dict[str, np.ndarray] = {}
    for r in same.orderBy("h", "g").limit(most).select("label", "x").collect():  # at most MOST_PIVOTS rows
        pivots.setdefault(r.label, []).append(r.x)
    pivots = {k: unit(np.array(v)) for k, v in pivots.items()}
    r = np.sqrt(2 - 2 * threshold) + 1e-9

    def run(batches):
        for b in batches:
            labels, take, cells, homes = b.column("label").to_pylist(), [], [], []
            by: dict[str, list[int]] = {}
            for i, k in enumerate(labels):
                by.setdefault(k, []).append(i)
            for k, rows in by.items():
                if k not in pivots or len(pivots[k]) == 1:
                    take += rows
                    cells += [0] * len(rows)
                    homes += [True] * len(rows)
                    continue
                x, p = unit(matrix(b.column("x").take(pa.array(rows)))), pivots[k]
                square = np.maximum(2 - 2 * (x @ p.T), 0)
                home = square.argmin(axis=1)
                apart = np.sqrt(np.maximum(2 - 2 * (p @ p.T), 1e-12))
                border = (square - square[np.arange(len(x)), home][:, None]) / (2 * apart[home])
                border[np.arange(len(x)), home] = 0
                i, j = np.nonzero(border <= r)
                take += np.array(rows)[i].tolist()
                cells += j.tolist()
                homes += (home[i] == j).tolist()
            if take:
                own = b.take(pa.array(take))
                yield pa.RecordBatch.from_arrays([own.column("label"), pa.array(cells, pa.int32()), pa.array(homes), own.column("rep"), own.column("copies"), own.column("x")], names=["label", "cell", "home", "rep", "copies", "x"])

    return same.select("label", "rep", "copies", "x").mapInArrow(run, "label string, cell int, home boolean, rep long, copies long, x array<double>")


def _joined(cells: DataFrame, threshold: float, home_block: int, visit_block: int) -> DataFrame:
    """(rep, n, root): links found for rep in one block pair, and the least vector it is tied to there."""
    sizes = cells.groupBy("label", "cell").agg(F.ceil(F.count_if("home") / home_block).alias("hs"), F.ceil(F.count("*") / visit_block).alias("vs")).where("hs > 0")
    rows = cells.join(sizes, ["label", "cell"]).withColumn("salt", F.xxhash64("rep"))
    shared = ["label", "cell", "rep", "copies", "x"]
    homes = rows.where("home").select(*shared, F.lit(True).alias("home"), F.pmod("salt", "hs").alias("hb"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("vs") - 1)).alias("vb"))
    visits = rows.select(*shared, F.lit(False).alias("home"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("hs") - 1)).alias("hb"), F.pmod("salt", "vs").alias("vb"))

    def block(t: pa.Table) -> pa.Table:
        home = t.column("home").to_numpy()
        reps, copies, x = t.column("rep").to_numpy(), t.column("copies").to_numpy(), matrix(t.column("x"))
        norms = np.linalg.norm(x, axis=1)
        u = x / norms[:, None]
        h, v = np.flatnonzero(home), np.flatnonzero(~home)
        out_rep, out_n, out_root = [], [], []
        if len(h) and len(v):
            cos = u[v] @ u[h].T
            linked = cos >= threshold
            for i, j in zip(*np.nonzero(np.abs(cos - threshold) < 1e-9), strict=True):
                linked[i, j] = float(np.dot(x[v[i]], x[h[j]])) / float(norms[v[i]] * norms[h[j]]) >= threshold
            linked &= reps[v][:, None] != reps[h][None]
            i = np.flatnonzero(linked.any(axis=1))
            j = np.flatnonzero(linked.any(axis=0))
            if len(i):
                tie = linked[np.ix_(i, j)]
                a, b = reps[v[i]], reps[h[j]]
                low, top = np.minimum(a, np.where(tie, b[None], np.iinfo(np.int64).max).min(axis=1)), b.copy()
                while True:
                    top2 = np.minimum(top, np.where(tie, low[:, None], np.iinfo(np.int64).max).min(axis=0))
                    low2 = np.minimum(low, np.where(tie, top2[None], np.iinfo(np.int64).max).min(axis=1))
                    if (low2 == low).all() and (top2 == top).all():
                        break
                    low, top = low2, top2
                out_rep = np.concatenate([a, b])
                out_n = np.concatenate([(tie * copies[h[j]][None]).sum(axis=1), np.zeros(len(b), dtype=np.int64)])
                out_root = np.concatenate([low, top])
        return pa.table({"rep": pa.array(out_rep, pa.int64()), "n": pa.array(out_n, pa.int64()), "root": pa.array(out_root, pa.int64())})

    return homes.unionByName(visits).groupBy("label", "cell", "hb", "vb").applyInArrow(block, "rep long, n long, root long")


def op4_vector_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup(table(spark, sf_dir, "embeddings"))


SQL = """
WITH RECURSIVE fit AS (
  SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS x FROM embeddings
  WHERE label IS NOT NULL AND embedding IS NOT NULL AND len(embedding) > 0
    AND len(list_filter(embedding, lambda c: c IS NULL OR NOT isfinite(c))) = 0 AND len(list_filter(embedding, lambda c: c <> 0)) > 0
), links AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM fit a JOIN fit b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.x) = len(b.x)
  WHERE list_cosine_similarity(a.x, b.x) >= 0.93
), reach(a, b) AS (
  SELECT vec_id, vec_id FROM embeddings UNION SELECT r.a, l.b FROM reach r JOIN links l ON l.a = r.b
), least AS (SELECT a AS vec_id, min(b) AS component_id FROM reach GROUP BY a),
counted AS (SELECT a AS vec_id, count(*) AS n FROM links GROUP BY a)
SELECT e.vec_id, CAST(coalesce(c.n, 0) AS BIGINT) AS n_links, l.component_id, l.component_id = e.vec_id AS kept
FROM embeddings e JOIN least l ON l.vec_id = e.vec_id LEFT JOIN counted c ON c.vec_id = e.vec_id
"""
