"""Exact ids of the public word-end BPE tokenizer, with a cache of white-space chunks in each worker.

The tokenizer normalises (NFC, lower case), splits by a pattern that never joins characters across white space, and
merges bytes inside each split piece. So a text is the concatenation of its chunks, and equal chunks have equal ids.

A chunk that is not cached is merged by a rank-table BPE engine: a piece is its UTF-8 bytes and one end byte (0xFF,
which UTF-8 never uses), the end byte joins the last byte first, and the published merges follow in their order.
Texts that could differ from this rule are encoded whole by the tokenizer itself: those with the four separators that
only Python counts as white space, and those that may hold an added token.
"""

from __future__ import annotations

import functools
import json
import unicodedata

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .words import gather, split

WHOLE = r"[\x1c-\x1f]|<\|"
MOST = 300_000  # chunks in each of two generations of the cache
LONGEST = 64  # characters of a chunk that is worth caching
END = b"\xff"


def byte_alphabet() -> dict[str, int]:
    """The printable stand-ins of byte-level vocabularies: printable Latin-1 stands for itself, the rest from 256 on."""
    plain = [b for b in range(256) if chr(b).isprintable() and chr(b) != " "]
    other = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(other)}


class ChunkEncoder:
    def __init__(self, path: str):
        import regex
        import tiktoken
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        model = json.loads(self.tokenizer.to_str())["model"]
        letters, suffix = byte_alphabet(), model["end_of_word_suffix"]

        def raw(token: str) -> bytes:
            ends = token.endswith(suffix)
            return bytes(letters[c] for c in (token.removesuffix(suffix) if ends else token)) + END * ends

        ranks: dict[bytes, int] = {}
        for b in range(256):
            ranks[bytes([b])] = len(ranks)
        for b in range(255):
            ranks[bytes([b]) + END] = len(ranks)
        for pair in model["merges"]:
            ranks.setdefault(raw("".join(pair if isinstance(pair, list) else pair.split(" "))), len(ranks))
        self.ids = np.zeros(len(ranks), "<u4")
        for token, k in model["vocab"].items():
            if (r := ranks.get(raw(token))) is not None:
                self.ids[r] = k
        self.merge = tiktoken.Encoding("chunks", pat_str=".+", mergeable_ranks=ranks, special_tokens={})._core_bpe.encode_single_piece
        self.pieces = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|\p{L}+|\p{N}|[^\s\p{L}\p{N}]+").findall
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}

    def whole(self, texts: list[str]) -> list[bytes]:
        return [np.asarray(e.ids, "<u4").tobytes() for e in self.tokenizer.encode_batch(texts, add_special_tokens=False)]

    def chunk(self, raw: str) -> bytes:
        """Ids of one chunk, packed as little-endian uint32."""
        found = self.young.get(raw)
        if found is not None:
            return found
        found = self.old.get(raw)
        if found is None:
            # by character, without the final-sigma rule of words
            c = (raw if raw.isascii() else unicodedata.normalize("NFC", raw).replace("Σ", "σ")).lower()
            parts = [c] if c.isalpha() else self.pieces(c)
            found = self.ids[[r for p in parts for r in self.merge(p.encode() + END)]].tobytes() if parts else b""
        if len(raw) <= LONGEST:
            if len(self.young) >= MOST:
                self.old, self.young = self.young, {}
            self.young[raw] = found
        return found

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in a row, and the bounds of each text in them."""
        odd = np.flatnonzero(pc.match_substring_regex(texts, WHOLE).to_numpy(zero_copy_only=False))
        if len(odd):
            keep = pa.array(~np.isin(np.arange(len(texts)), odd))
            w = split(pc.if_else(keep, texts, ""), ascii_only=False)
        else:
            w = split(texts, ascii_only=False)
        packed = [self.chunk(c) if c else b"" for c in w.distinct]
        sizes = np.fromiter(map(len, packed), np.int64, len(packed)) >> 2
        lengths = sizes[w.index]
        ids = gather(np.frombuffer(b"".join(packed), "<u4"), (np.cumsum(sizes) - sizes)[w.index], lengths)
        bounds = np.concatenate([[0], np.cumsum(lengths)])[w.bounds]
        if len(odd):
            rows = np.split(ids, bounds[1:-1])
            for k, found in zip(odd, self.whole([texts[int(k)].as_py() for k in odd]), strict=True):
                rows[k] = np.frombuffer(found, "<u4")
            ids, bounds = np.concatenate(rows), np.concatenate([[0], np.cumsum([len(r) for r in rows])])
        return ids, bounds


@functools.lru_cache(maxsize=2)
def encoder(path: str) -> ChunkEncoder:
    return ChunkEncoder(path)
