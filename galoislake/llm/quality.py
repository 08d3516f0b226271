"""Quality classifier: regularised quadratic discriminant analysis over document statistics.

A text becomes a short vector of transformed statistics (shares of character classes, word and line
shapes, repetition). Each class is a Gaussian whose covariance is shrunk twice: towards the pooled
covariance, and towards its own mean variance. A score is the logistic of the difference of the two
log densities, each a Mahalanobis form solved through a Cholesky factor that is computed once, on
the driver, from sums (two rows of moments, whatever the corpus size).

Defined results: a null or empty text has the statistics of an empty text and is scored like any
other; repeated rows are scored each; a document labelled both ways counts in both classes; labels
that are null or neither 0 nor 1 are left out. With no usable class contrast (no labels, or one
class only) every score is the smoothed share of label 1. Columns other than the named ones are
neither read nor returned.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from galoislake.llm.common import held_out, release, table

SLICE = 64
_LOWER, _UPPER, _DIGIT, _SPACE, _LINE, _STOP, _BANG, _BAR, _SYMBOL, _OTHER = range(10)
_CLASSES = 10


def _char_classes() -> np.ndarray:
    out = np.full(0x110000, _OTHER, dtype=np.uint8)
    for code in range(0x3000):
        c = chr(code)
        if c == "\n":
            out[code] = _LINE
        elif c.isspace():
            out[code] = _SPACE
        elif c.isdigit():
            out[code] = _DIGIT
        elif c.isupper():
            out[code] = _UPPER
        elif c.isalpha():
            out[code] = _LOWER
        elif c in ".,;:?'\"-()":
            out[code] = _STOP
        elif c == "!":
            out[code] = _BANG
        elif c in "|<>{}[]=_\\/":
            out[code] = _BAR
        else:
            out[code] = _SYMBOL
    return out


_TABLE: list[np.ndarray] = []


def statistics(texts: list[str | None]) -> np.ndarray:
    """One row of transformed statistics for each text."""
    if not _TABLE:
        _TABLE.append(_char_classes())
    return np.concatenate([_slice_statistics([t or "" for t in texts[i : i + SLICE]]) for i in range(0, len(texts), SLICE)]) if texts else np.zeros((0, len(NAMES)))


NAMES = (
    "log_chars", "log_words", "word_mean", "word_spread", "upper", "digit", "space", "stops", "bangs", "bars",
    "symbols", "others", "caps_words", "distinct_words", "distinct_lines", "line_mean", "same_word_pairs", "doubled_marks",
)


def _slice_statistics(texts: list[str]) -> np.ndarray:
    n = len(texts)
    lengths = np.array([len(t) for t in texts], dtype=np.int64)
    kinds = _TABLE[0][np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), dtype=np.uint32)]
    owner = np.repeat(np.arange(n), lengths)
    counts = np.bincount(owner * _CLASSES + kinds, minlength=n * _CLASSES).reshape(n, _CLASSES).astype(float)
    first = np.zeros(len(kinds) + 1, dtype=bool)
    first[np.concatenate([[0], np.cumsum(lengths)])] = True
    blank = (kinds == _SPACE) | (kinds == _LINE)
    starts = ~blank & (first[:-1] | np.concatenate([[True], blank[:-1]]))
    at = np.flatnonzero(starts)
    letters = np.cumsum(np.concatenate([[0], ~blank]))
    ends = np.concatenate([at[1:], [len(kinds)]])
    word_len = (letters[ends] - letters[at]).astype(float) if len(at) else np.zeros(0)
    word_of = owner[at]
    words = np.bincount(word_of, minlength=n).astype(float)
    total = np.bincount(word_of, weights=word_len, minlength=n)
    square = np.bincount(word_of, weights=word_len**2, minlength=n)
    caps = np.bincount(word_of, weights=(kinds[at] == _UPPER).astype(float), minlength=n)
    marked = (kinds == _BANG) | (kinds == _SYMBOL)
    doubled = marked & np.concatenate([[False], marked[:-1]]) & ~first[:-1]
    doubles = np.bincount(owner[doubled], minlength=n).astype(float)
    rows = []
    for t in texts:
        w = t.split()
        lines = t.split("\n")
        rows.append((len(set(w)), len(lines), len(set(lines)), sum(map(str.__eq__, w, w[1:]))))
    distinct, lines, distinct_lines, pairs = np.array(rows, dtype=float).reshape(n, 4).T
    chars, some = np.maximum(lengths, 1).astype(float), np.maximum(words, 1)
    mean = total / some
    share = lambda x, of: np.sqrt(x / of)
    columns = [
        np.log1p(lengths), np.log1p(words), np.log1p(mean), np.sqrt(np.maximum(square / some - mean**2, 0)),
        share(counts[:, _UPPER], chars), share(counts[:, _DIGIT], chars), share(counts[:, _SPACE], chars), share(counts[:, _STOP], chars),
        share(counts[:, _BANG], chars), share(counts[:, _BAR], chars), share(counts[:, _SYMBOL], chars), share(counts[:, _OTHER], chars),
        share(caps, some), distinct / np.maximum(np.sqrt(some), 1), share(distinct_lines, lines), np.log1p(lengths / lines), share(pairs, some), share(doubles, chars),
    ]
    return np.stack(columns, axis=1)


@dataclass(frozen=True)
class Discriminant:
    """Two Gaussians on standardised statistics, kept as means, Cholesky factors and log constants."""

    centre: np.ndarray
    scale: np.ndarray
    means: np.ndarray
    factors: np.ndarray
    constants: np.ndarray
    flat: float | None = None

    def scores(self, x: np.ndarray) -> np.ndarray:
        if self.flat is not None:
            return np.full(len(x), self.flat)
        z = (x - self.centre) / self.scale
        logs = []
        for k in (0, 1):
            y = np.linalg.solve(self.factors[k], (z - self.means[k]).T)
            logs.append(self.constants[k] - 0.5 * (y * y).sum(axis=0))
        return 1 / (1 + np.exp(np.clip(logs[0] - logs[1], -700, 700)))


def discriminant(moments: dict[int, tuple[float, np.ndarray, np.ndarray]], to_pooled: float, to_round: float) -> Discriminant:
    """Fit from {class: (rows, sum, sum of outer products)}."""
    d = len(NAMES)
    n = {k: moments[k][0] if k in moments else 0.0 for k in (0, 1)}
    if min(n.values()) < 2:
        none = np.zeros(0)
        return Discriminant(none, none, none, none, none, flat=(n[1] + 1) / (n[0] + n[1] + 2))
    rows = n[0] + n[1]
    centre = (moments[0][1] + moments[1][1]) / rows
    scale = np.sqrt(np.maximum(np.diag(moments[0][2] + moments[1][2]) / rows - centre**2, 1e-8))
    means, covs = [], []
    for k in (0, 1):
        mu = moments[k][1] / n[k]
        covs.append((moments[k][2] / n[k] - np.outer(mu, mu)) / np.outer(scale, scale))
        means.append((mu - centre) / scale)
    pooled = (n[0] * covs[0] + n[1] * covs[1]) / rows
    factors, constants = [], []
    for k in (0, 1):
        s = (1 - to_pooled) * covs[k] + to_pooled * pooled
        s = (1 - to_round) * s + to_round * (np.trace(s) / d) * np.eye(d)
        factor = np.linalg.cholesky(s + 1e-9 * np.eye(d))
        factors.append(factor)
        constants.append(np.log(n[k] / rows) - np.log(np.diag(factor)).sum())
    return Discriminant(centre, scale, np.array(means), np.array(factors), np.array(constants))


def _partition_moments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    d, sums = len(NAMES), {}
    for b in batches:
        x = b.column("x").flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, d)
        y = b.column("y").to_numpy(zero_copy_only=False)
        for k in (0, 1):
            if len(own := x[y == k]):
                add = np.concatenate([[len(own)], own.sum(axis=0), (own.T @ own).ravel()])
                sums[k] = sums.get(k, 0) + add
    if sums:
        yield pa.RecordBatch.from_pydict({"y": pa.array(list(sums), pa.int32()), "m": pa.array([list(v) for v in sums.values()], pa.list_(pa.float64()))})


def fit(docs: DataFrame, labels: DataFrame, to_pooled: float = 0.15, to_round: float = 0.02, *, doc_id: str = "doc_id", text: str = "text", label: str = "quality") -> Discriminant:
    """Learn from every labelled document outside the held-out fold.

    Statistics are computed beside the text, so the join with the labels moves vectors, not texts.
    Only sums come to the driver: two rows for each class."""

    @F.pandas_udf("array<double>")
    def vectors(texts: pd.Series) -> pd.Series:
        out = pd.Series(list(statistics(texts.tolist())))
        release()
        return out

    known = labels.select(F.col(doc_id).alias("id"), F.col(label).cast("int").alias("y")).where("y in (0, 1)").where(~held_out(F.col("id")))
    # The text's vector is computed ahead of the join; the fold is cut on both sides.
    own = docs.where(~held_out(F.col(doc_id))).select(F.col(doc_id).alias("id"), vectors(F.col(text)).alias("x"))
    parts = own.join(known, "id").select("y", "x").mapInArrow(_partition_moments, "y int, m array<double>")
    sums = parts.select("y", F.posexplode("m")).groupBy("y", "pos").agg(F.sum("col").alias("v")).collect()  # 2 x (1 + d + d*d) rows
    d = len(NAMES)
    flat = {k: np.zeros(1 + d + d * d) for k in {r.y for r in sums}}
    for r in sums:
        flat[r.y][r.pos] = r.v
    return discriminant({k: (v[0], v[1 : d + 1], v[d + 1 :].reshape(d, d)) for k, v in flat.items()}, to_pooled, to_round)


def score_column(model: Discriminant, text: str | Column = "text") -> Column:
    """Score of a text by a fitted model, from 0 to 1."""

    @F.pandas_udf("double")
    def score(texts: pd.Series) -> pd.Series:
        out = pd.Series(model.scores(statistics(texts.tolist())), dtype="float64")
        release()
        return out

    return score(F.col(text) if isinstance(text, str) else text)


def judge(docs: DataFrame, labels: DataFrame, threshold: float = 0.7) -> DataFrame:
    """doc_id, held_out, score and predicted (score >= threshold) of every row of docs."""
    model = fit(docs, labels)
    scored = docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), score_column(model).alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def keep_good(docs: DataFrame, labels: DataFrame, threshold: float = 0.7) -> DataFrame:
    """The rows of docs, whole, whose score reaches the threshold."""
    return docs.where(score_column(fit(docs, labels)) >= threshold)


def op1_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
