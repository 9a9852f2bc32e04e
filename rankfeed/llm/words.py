"""Columnar splitting of text batches into words: the work in Python is done once for each distinct word of a batch."""

from __future__ import annotations

import ctypes
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

BATCH_BYTES = 12 << 20  # text handled at once


@dataclass
class Words:
    """Words of a batch of texts: ``distinct[index[k]]`` is the k-th word; text t has words ``bounds[t]:bounds[t + 1]``."""

    index: np.ndarray
    distinct: list[str]
    bounds: np.ndarray


def split(texts: pa.Array, ascii_only: bool, lower_ascii: bool = False) -> Words:
    """Split at white space (of ASCII only, or of Unicode); without empty words."""
    if lower_ascii:
        texts = pc.ascii_lower(texts)
    lists = (pc.ascii_split_whitespace if ascii_only else pc.utf8_split_whitespace)(texts)
    bounds = lists.offsets.to_numpy().astype(np.int64)
    coded = lists.values.slice(0, int(bounds[-1])).dictionary_encode()
    index, distinct = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64), coded.dictionary.to_numpy(zero_copy_only=False).tolist()
    if "" in distinct:
        real = index != distinct.index("")
        bounds = np.concatenate([[0], np.cumsum(real)])[bounds]
        index = index[real]
    return Words(index, distinct, bounds)


def give_back() -> None:
    """Return freed memory to the system: a worker that waits for its next task then holds little more than what it imported."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def filled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The batches that have rows; memory is given back before the first one (what an earlier task of the worker left) and after the last one."""
    give_back()
    try:
        for batch in batches:
            if batch.num_rows:
                yield batch
    finally:
        give_back()


def pieces(batches: Iterator[pa.RecordBatch], text: str, most: int = BATCH_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut batches so that each holds about ``most`` bytes of text, or one row."""
    for batch in filled(batches):
        ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False).astype(np.int64) + 16)
        at = 0
        while at < batch.num_rows:
            upto = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + most, "right")))
            yield batch.slice(at, upto - at)
            at = upto


def texts_of(batch: pa.RecordBatch, text: str) -> pa.Array:
    """The text column, null as empty, starting at offset zero."""
    column = pc.fill_null(batch.column(text), "")
    return pa.concat_arrays([column]) if column.offset == 0 else pa.concat_arrays([column, column.slice(0, 0)])


def gather(values: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Concatenation of ``values[s:s + n]`` over pairs of starts and lengths."""
    before = np.cumsum(lengths) - lengths
    return values[np.repeat(starts - before, lengths) + np.arange(int(lengths.sum()))]
