"""Indicator features of texts as hashed ids, computed once per distinct word of a batch.

Features: words (letters and digits only), pairs of neighbouring words, beginnings of longer words (4 and 5 characters), word ends (their last
characters that are neither), and pairs of neighbouring word ends.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .words import pieces, split, texts_of

SPACE = 1 << 20
PIECE_BYTES = 2 << 20  # text handled at once in a worker
FIRST = 3  # ids below stand for added inputs


def indicators(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Distinct feature ids of all texts in a row, sorted inside each, and the bounds of the texts."""
    w = split(texts, ascii_only=True, lower_ascii=True)
    plain = ["".join(filter(str.isalnum, s)) for s in w.distinct]
    code = lambda parts: np.fromiter((xxhash.xxh3_64_intdigest(x) for x in parts), np.uint64, len(plain))[w.index]
    n = np.diff(w.bounds)
    row = np.repeat(np.arange(len(n)), n)
    same = row[1:] == row[:-1] if len(row) else np.zeros(0, bool)
    word = code(plain)
    tail = code("\x00" + "".join(c for c in s if not c.isalnum())[-3:] for s in w.distinct)
    first = row[:-1][same] if len(row) else row
    pairs = [(x[:-1] * np.uint64(0x9E3779B97F4A7C15) + x[1:])[same] if len(row) else x for x in (word, tail)]
    size = np.fromiter(map(len, plain), np.int64, len(plain))[w.index]
    starts = [(k, code(f"\x01{s[:k]}" for s in plain)[size > k]) for k in (4, 5)]
    real = size > 0
    ids = np.concatenate([word[real], tail, *pairs, *(c for _, c in starts)])
    rows = np.concatenate([row[real], row, first, first, *(row[size > k] for k, _ in starts)])
    key = np.unique(rows * SPACE + (FIRST + (ids >> np.uint64(20)) % np.uint64(SPACE - FIRST)).astype(np.int64))
    return key % SPACE, np.searchsorted(key, np.arange(len(n) + 1) * SPACE)


def sample(docs: DataFrame, labels: DataFrame, targets: list[str], most: int, id_col: str = "doc_id", text_col: str = "text") -> tuple[list[np.ndarray], np.ndarray]:
    """Features and labels of at most ``most`` labelled rows, the smallest by a hash of the id; texts stay on the executors."""
    complete = labels.where(" and ".join(f"{t} is not null" for t in ["doc_id", *targets]))
    chosen = complete.select(F.col("doc_id").alias("__id"), *targets).orderBy(F.xxhash64("doc_id"), *targets).limit(most)
    rows = docs.select(F.col(id_col).alias("__id"), F.col(text_col).alias("text")).join(F.broadcast(chosen), "__id").select("text", F.array(*[F.col(t).cast("int") for t in targets]).alias("y"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text", PIECE_BYTES):
            ids, bounds = indicators(texts_of(b, "text"))
            yield pa.RecordBatch.from_arrays([pa.ListArray.from_arrays(pa.array(bounds, pa.int32()), pa.array(ids, pa.int32())), b.column("y")], names=["ids", "y"])

    found = rows.mapInArrow(run, "ids array<int>, y array<int>").toArrow().combine_chunks()
    if not found.num_rows:
        return [], np.zeros((0, len(targets)), np.int64)
    ids, y = (found.column(c).combine_chunks() for c in ("ids", "y"))
    values, ends = ids.values.to_numpy(), ids.offsets.to_numpy()
    return [values[a:b] for a, b in zip(ends[:-1], ends[1:], strict=True)], y.values.to_numpy().astype(np.int64).reshape(-1, len(targets))


def with_columns(docs: DataFrame, text_col: str, names: list[str], kind: T.DataType, run: Callable[[pa.Array], list[pa.Array]]) -> DataFrame:
    """``docs`` with computed columns appended; the rows pass once, unshuffled, other columns untouched. ``names`` must be new (see ``fresh``)."""
    schema = T.StructType([*docs.schema.fields, *[T.StructField(n, kind) for n in names]])
    at = docs.columns.index(text_col)

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, text_col, PIECE_BYTES):
            more = run(texts_of(b, text_col))
            yield pa.RecordBatch.from_arrays([*b.columns, *more], names=[*b.schema.names, *names])

    assert docs.columns[at] == text_col
    return docs.mapInArrow(each, schema)


def total(weights: np.ndarray, ids: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Sum of the weights of each text's features."""
    s = np.concatenate([[0.0], np.cumsum(weights[ids])])
    return s[bounds[1:]] - s[bounds[:-1]]


def flat(rows: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    bounds = np.concatenate([[0], np.cumsum([len(r) for r in rows])]).astype(np.int64)
    return (np.concatenate(rows) if rows else np.zeros(0, np.int32)), bounds


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))
