"""Token counts of sections by offsets: each document is encoded once, as a whole.

The byte lengths of the ids give every token its span; sections are spans as well, and a sorted
interval join gives each token to a section. Encoding sections apart would count other tokens, as
merges and leading blanks cross the boundaries.

A token that crosses boundaries goes by an explicit rule: "first", to the section with its first
byte; "last", to that with its last byte; "most", to that with most of its bytes, the first of equals.

Sections are the fields, in order, joined by a line break where there are several, each cut after its
line breaks unless `lines` is false. Defined results: a null or empty field is one empty section with
no tokens of its own (its joining line break counts to it); repeated rows count each; an empty table
gives no rows. Columns other than the named ones are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from galoislake.llm.common import table
from galoislake.llm.vocab import byte_encoder, split_pattern, vocabulary_path

RULES = ("first", "last", "most")


def sections_of(parts: list[str], lines: bool) -> tuple[str, list[tuple[int, int, int]]]:
    """The whole text, and (field, start, end) of its sections in code points."""
    whole, out, at = "\n".join(parts), [], 0
    for k, part in enumerate(parts):
        own = part + "\n" if k + 1 < len(parts) else part
        cut = _after_breaks(own) if lines else [own]
        for piece in cut or [""]:
            out.append((k, at, at + len(piece)))
            at += len(piece)
    return whole, out


def _after_breaks(text: str) -> list[str]:
    pieces = text.split("\n")
    return [p + "\n" for p in pieces[:-1]] + ([pieces[-1]] if pieces[-1] else [])


def allot(text: str, spans: list[tuple[int, int, int]], sizes: np.ndarray, rule: str) -> tuple[np.ndarray, np.ndarray]:
    """Tokens of each section, and how many of them cross a boundary. sizes: bytes of each token."""
    if text.isascii():
        starts = np.array([s for _, s, _ in spans], dtype=np.int64)
        total = len(text)
    else:
        lengths = [len(text[s:e].encode("utf-8", "surrogatepass")) for _, s, e in spans]
        starts = np.concatenate([[0], np.cumsum(lengths)[:-1]])
        total = int(sum(lengths))
    ends = np.concatenate([starts[1:], [total]])
    stop = np.cumsum(sizes)
    begin = stop - sizes
    first = np.searchsorted(starts, begin, side="right") - 1
    last = np.searchsorted(starts, stop - 1, side="right") - 1
    crossing = first != last
    at = last if rule == "last" else first.copy()
    if rule == "most":
        for i in np.flatnonzero(crossing):
            inside = np.minimum(ends[first[i] : last[i] + 1], stop[i]) - np.maximum(starts[first[i] : last[i] + 1], begin[i])
            at[i] = first[i] + int(inside.argmax())
    return np.bincount(at, minlength=len(spans)), np.bincount(at[crossing], minlength=len(spans))


def count_tokens(docs: DataFrame, fields: tuple[str, ...] = ("text",), rule: str = "first", lines: bool = True, vocabulary: str | None = None, *, doc_id: str = "doc_id") -> DataFrame:
    """Per section: doc_id, field, section (from 0 in its document), start, end (code points of the
    whole), n_tokens, n_crossing."""
    if rule not in RULES:
        raise ValueError(f"rule is none of {RULES}")
    path, pattern = vocabulary or vocabulary_path("byte_bpe_50k.tiktoken"), split_pattern()
    names = pa.array(fields)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, bytes_of = byte_encoder(path, pattern)
        for b in batches:
            for low in range(0, b.num_rows, 500):
                some = b.slice(low, 500)
                rows, kinds, order, starts, ends, counts, crossings = [], [], [], [], [], [], []
                for i, parts in enumerate(zip(*(some.column(k + 1).to_pylist() for k in range(len(fields))), strict=True)):
                    text, spans = sections_of([p or "" for p in parts], lines)
                    n, c = allot(text, spans, bytes_of[encoder.encode_to_numpy(text)], rule)
                    rows += [i] * len(spans)
                    order += range(len(spans))
                    kinds += [s[0] for s in spans]
                    starts += [s[1] for s in spans]
                    ends += [s[2] for s in spans]
                    counts.append(n)
                    crossings.append(c)
                if rows:
                    columns = [some.column(0).take(pa.array(rows)), names.take(pa.array(kinds)), pa.array(order, pa.int32()), pa.array(starts, pa.int64()), pa.array(ends, pa.int64()), pa.array(np.concatenate(counts)), pa.array(np.concatenate(crossings))]
                    yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "field", "section", "start", "end", "n_tokens", "n_crossing"])

    kind = docs.schema[doc_id].dataType.simpleString()
    return docs.select(doc_id, *fields).mapInArrow(run, f"doc_id {kind}, field string, section int, start long, end long, n_tokens long, n_crossing long")


def op10_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(table(spark, sf_dir, "documents"))
