"""Token counts of a unigram tokenizer without building tokens: Aho-Corasick matches and a count-only Viterbi pass.

Texts are white-space words with a leading space mark, as the pre-tokenizer makes them; no piece crosses words, so equal words have equal
counts and each worker keeps a cache. At each end position, matches arrive longest first and only a strictly better score replaces
the best one: the tokenizer's tie rule. A character without a piece of its own costs the lowest score less ten; runs of them are one token.

Defined cases: null and empty texts have no tokens. Other columns are carried along.
"""

from __future__ import annotations

import functools

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .features import with_columns
from .words import split

MARK = "▁"
MOST = 500_000


def vocabulary(path: str) -> list[tuple[str, float]]:
    """Pieces and scores of a public model file, unknown first."""
    import sentencepiece

    m = sentencepiece.SentencePieceProcessor(model_file=path)
    real = [k for k in range(m.get_piece_size()) if not (m.is_control(k) or m.is_unknown(k) or m.is_byte(k) or m.is_unused(k))]
    return [("<unk>", 0.0)] + [(m.id_to_piece(k), m.get_score(k)) for k in real]


class Counter:
    def __init__(self, pieces: list[tuple[str, float]]):
        self.matches = ahocorasick.Automaton()
        for k, (piece, score) in enumerate(pieces):
            if k:
                self.matches.add_word(piece, (len(piece), score))
        self.matches.make_automaton()
        self.unknown = min(s for _, s in pieces) - 10.0
        self.cache: dict[str, int] = {}

    def count(self, word: str) -> int:
        found = self.cache.get(word)
        if found is None:
            found = self.fresh(word)
            if len(self.cache) >= MOST:
                self.cache.clear()
            if len(word) <= 64:
                self.cache[word] = found
        return found

    def fresh(self, word: str) -> int:
        n = len(word)
        ends: list[list[tuple[int, float]]] = [[] for _ in range(n)]
        for end, hit in self.matches.iter(word):
            ends[end].append(hit)
        best, pieces, open_run = [0.0] * (n + 1), [0] * (n + 1), [False] * (n + 1)
        for end in range(n):
            top, count, run, single = None, 0, False, False
            for length, score in ends[end]:
                start = end + 1 - length
                single |= length == 1
                total = best[start] + score
                if top is None or total > top:
                    top, count, run = total, pieces[start] + 1, False
            if not single:
                total = best[end] + self.unknown
                if top is None or total > top:
                    top, count, run = total, pieces[end] + (not open_run[end]), True
            best[end + 1], pieces[end + 1], open_run[end + 1] = top, count, run
        return pieces[n]


@functools.lru_cache(maxsize=2)
def counter(path: str) -> Counter:
    return Counter(vocabulary(path))


def counted(docs: DataFrame, path: str, text_col: str = "text", name: str = "n_tokens") -> DataFrame:
    def run(texts: pa.Array) -> list[pa.Array]:
        own, w = counter(path), split(texts, ascii_only=False)
        sizes = np.fromiter((own.count(MARK + s) for s in w.distinct), np.int64, len(w.distinct))
        s = np.concatenate([[0], np.cumsum(sizes[w.index])]).astype(np.int64)
        return [pa.array(s[w.bounds[1:]] - s[w.bounds[:-1]])]

    return with_columns(docs, text_col, [name], T.LongType(), run)
