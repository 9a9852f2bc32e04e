"""Benchmark decontamination: block-max pruned BM25 retrieval over test items, then question and answer overlap.

Test items are cut into segments of at most ``REACH`` words and indexed: per term its postings (segment, weight) and, per block of segments, the
largest weight. Weights are BM25 contributions divided by the segment's score against itself, so one threshold fits all. Each passage
(``2 * REACH`` words, stepping by ``REACH``) is a query. The pivot test runs for all passages of a batch at once: first the sum of
term maxima, then per block the sum of block maxima; only (passage, block) pairs that can reach the threshold are scored exactly. A document
counts as contaminated if it holds enough word 5-grams of both the question and the answer of a retrieved item. A question, answer or whole item
of fewer than five words must be there in full, as one run of words: a one-word answer anywhere in the document is enough, besides its question.

An item's question ends at its first question mark; an item without one is divided in the middle, and one of fewer than ten words is not divided.

Items are dealt to indexes of about ``ITEMS`` and documents pass once for each, so what travels to the tasks is bounded. Document frequencies and the mean
length are counted once over the segments of all items, so which items are retrieved does not depend on how they are dealt.
Defined cases: null or empty texts and items match nothing; repeated items are listed each; an empty table gives an empty result.
"""

from __future__ import annotations

import math
import re
from collections import Counter, defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .features import with_columns
from .runtime import fresh, written
from .words import split

REACH = 48
BLOCK = 8
ITEMS = 1024
GRAM = 5
SOME = 64  # passages whose block bounds are taken at once
SLACK = 1e-4  # bounds are 32-bit sums
_word = re.compile(r"\w+").findall


def plain(word: str) -> str:
    return "".join(_word(word.lower()))


def grams(words: list) -> set[tuple]:
    return {tuple(words[k : k + GRAM]) for k in range(max(1, len(words) - GRAM + 1))} if words else set()


def words_of(text: str) -> list[str]:
    return [p for p in map(plain, text.split()) if p]


def segments_of(words: list[str]) -> list[list[str]]:
    """An item in pieces of nearly equal length, of at most ``REACH`` words."""
    count = -(-len(words) // REACH)
    size = -(-len(words) // max(1, count))
    return [words[k * size : (k + 1) * size] for k in range(count)]


@dataclass(frozen=True)
class Statistics:
    """Of all segments: their number, mean length, and in how many each word is (of the words that an index needs)."""

    segments: int
    mean: float
    frequency: dict[str, int]


class Index:
    def __init__(self, items: list[tuple[int, str]], known: Statistics | None = None, k1: float = 1.2, b: float = 0.75):
        self.ids, self.sides, segments = [], [], []
        for item, text in items:
            words = words_of(text)
            if not words:
                continue
            head = [p for p in map(plain, text[: text.find("?") + 1].split()) if p]
            cut = len(head) if 0 < len(head) < len(words) else (len(words) + 1) // 2
            sides = [grams(words)] if len(words) < 2 * GRAM else [grams(words[:cut]), grams(words[cut:])]
            segments += [(len(self.ids), ws) for ws in segments_of(words)]
            self.ids.append(item)
            self.sides.append(sides)
        self.owner = np.array([s[0] for s in segments], np.int64)
        df = Counter(w for _, ws in segments for w in set(ws))
        if known is None:
            known = Statistics(len(segments), sum(len(ws) for _, ws in segments) / max(1, len(segments)), df)
        self.terms = {w: k + 1 for k, w in enumerate(df)}
        self.sides = [[{tuple(self.terms[w] for w in g) for g in side} for side in sides] for sides in self.sides]
        self.widths = [[len(next(iter(side))) for side in sides] for sides in self.sides]  # GRAM, or all words of a shorter side
        self.blocks = -(-len(segments) // BLOCK)
        self.block_max = np.zeros((len(df) + 1, max(1, self.blocks)), np.float32)
        postings: dict[int, list[tuple[int, float]]] = defaultdict(list)
        for s, (_, ws) in enumerate(segments):
            tf = Counter(ws)
            score = {w: math.log(1 + (known.segments - known.frequency[w] + 0.5) / (known.frequency[w] + 0.5)) * n * (k1 + 1) / (n + k1 * (1 - b + b * len(ws) / known.mean)) for w, n in tf.items()}
            own = sum(score[w] * n for w, n in tf.items())
            for w, x in score.items():
                t = self.terms[w]
                postings[t].append((s, x / own))
                self.block_max[t, s // BLOCK] = max(self.block_max[t, s // BLOCK], x / own)
        flat = [p for t in range(len(df) + 1) for p in postings.get(t, ())]
        self.segment = np.array([s for s, _ in flat], np.int64)
        self.weight = np.array([x for _, x in flat], np.float64)
        # begin[t, b]: first posting of term t in block b or later
        sizes = np.zeros((len(df) + 1, max(1, self.blocks)), np.int64)
        np.add.at(sizes, ([t for t in range(len(df) + 1) for _ in postings.get(t, ())], self.segment // BLOCK), 1)
        self.begin = np.concatenate([[0], np.cumsum(sizes)])[:-1].reshape(sizes.shape).astype(np.int32)
        self.sizes = sizes.astype(np.int8)
        self.term_max = self.block_max.max(1)

    def search(self, term: np.ndarray, threshold: float) -> set[int]:
        """Items with a segment that reaches the threshold in some passage of a text."""
        if not len(term) or not self.blocks:
            return set()
        starts = np.arange(0, len(term), REACH)
        half = np.add.reduceat(self.term_max[term], starts)
        bound = half + np.append(half[1:], 0)
        found: set[int] = set()
        for first in range(0, len(starts), SOME):
            mine = np.arange(first, min(first + SOME, len(starts)))
            if not (bound[mine] >= threshold - SLACK).any():
                continue
            words = term[first * REACH : (first + SOME + 1) * REACH]
            part = np.add.reduceat(self.block_max[words], np.arange(0, len(words), REACH))
            part = part[: len(mine)] + np.concatenate([part[1:], np.zeros((1, part.shape[1]), part.dtype)])[: len(mine)]
            reach = part >= threshold - SLACK
            if reach.any():
                # both halves of a passage are scored, once for the two passages that share one
                wanted = np.zeros((len(mine) + 1, reach.shape[1]), bool)
                wanted[:-1] |= reach
                wanted[1:] |= reach
                known = np.flatnonzero(words)
                word, block = np.nonzero(wanted[known // REACH] & (self.sizes[words[known]] > 0))
                word = known[word]
                begin, lengths = self.begin[words[word], block], self.sizes[words[word], block].astype(np.int64)
                at = np.repeat(begin - np.cumsum(lengths) + lengths, lengths)
                at += np.arange(len(at))
                cell = np.repeat(word // REACH, lengths) * len(self.owner) + self.segment[at]
                score = np.bincount(cell, self.weight[at], (len(mine) + 1) * len(self.owner)).reshape(len(mine) + 1, -1)
                found.update(self.owner[(score[:-1] + score[1:] >= threshold).any(0)].tolist())
        return found

    def known_grams(self, term: np.ndarray, width: int) -> set[tuple[int, ...]]:
        """Grams of a text that have terms of the index only; no other gram can be in an item."""
        if len(term) < width:
            return set()
        whole = np.convolve(term > 0, np.ones(width, int), "valid") == width
        return set(map(tuple, np.lib.stride_tricks.sliding_window_view(term, width)[whole].tolist()))

    def hits(self, texts: pa.Array, threshold: float, overlap: float) -> list[list[int]]:
        w = split(texts, ascii_only=False)
        words = [plain(s) for s in w.distinct]
        code = np.fromiter((self.terms.get(s, 0) for s in words), np.int64, len(words))
        real = np.fromiter((bool(s) for s in words), bool, len(words))
        out = []
        for a, b in zip(w.bounds[:-1], w.bounds[1:], strict=True):
            index = w.index[a:b]
            index = index[real[index]]
            near = self.search(code[index], threshold)
            if near:
                own = {n: self.known_grams(code[index], n) for n in {n for k in near for n in self.widths[k]}}
                near = {k for k in near if all(len(side & own[n]) >= overlap * len(side) for side, n in zip(self.sides[k], self.widths[k], strict=True))}
            out.append(sorted(self.ids[k] for k in near))
        return out


def statistics(items: DataFrame, parts: int, dealt: Column) -> tuple[int, float, DataFrame]:
    """Number and mean length of all segments, and ``part, word, n``: frequencies over all segments of the words that each part has."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            part, words, length = [], [], []
            for p, text in zip(b.column("part").to_pylist(), b.column("text").to_pylist(), strict=True):
                for ws in segments_of(words_of(text)):
                    part.append(p)
                    words.append(sorted(set(ws)))
                    length.append(len(ws))
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), pa.array(words, pa.list_(pa.string())), pa.array(length, pa.int64())], names=["part", "words", "length"])

    cut = written(items.select(dealt.cast("int").alias("part"), "text").mapInArrow(run, "part int, words array<string>, length long"), "segments")
    whole = cut.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.avg("length"), F.lit(0.0)).alias("mean")).first()
    each = cut.select("part", F.explode("words").alias("word"))
    return whole["n"], whole["mean"], written(each.distinct().join(each.groupBy("word").agg(F.count(F.lit(1)).alias("n")), "word"), "frequencies")


def matched(docs: DataFrame, benchmark: DataFrame, threshold: float = 0.5, overlap: float = 0.6, text_col: str = "text", name: str = "item_ids", most: int = ITEMS) -> DataFrame:
    """``docs`` with the sorted list of the test items that each row contains, under the new column ``name``."""
    spark = docs.sparkSession
    items = benchmark.where("item_id is not null and text is not null")
    parts = max(1, -(-items.count() // most))
    dealt = F.pmod(F.xxhash64("item_id", "text"), F.lit(parts))
    segments, mean, frequencies = statistics(items, parts, dealt)
    names, out = [], docs
    for k in range(parts):
        mine = [(r.item_id, r.text) for r in items.where(dealt == k).select("item_id", "text").collect()]
        known = Statistics(segments, mean, {r.word: r.n for r in frequencies.where(F.col("part") == k).collect()})
        shared = spark.sparkContext.broadcast((mine, known))
        names += fresh(out, "found_items")
        made: dict = {}

        def run(texts: pa.Array, shared=shared, made=made) -> list[pa.Array]:
            if "index" not in made:
                made["index"] = Index(*shared.value)
            return [pa.array(made["index"].hits(texts, threshold, overlap), pa.list_(pa.int64()))]

        out = with_columns(out, text_col, [names[-1]], T.ArrayType(T.LongType()), run)
    return out.withColumn(name, F.array_sort(F.flatten(F.array(*names)))).drop(*names)


def report(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    return matched(docs.select("doc_id", "text"), benchmark).select("doc_id", (F.size("item_ids") > 0).alias("contaminated"), F.size("item_ids").cast("long").alias("n_items"), "item_ids")


def clean(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows without a test item, columns as given."""
    (name,) = fresh(docs, "item_ids")
    return matched(docs, benchmark, name=name).where(F.size(name) == 0).drop(name)
