"""Removal of repeated byte strings by a sparse enhanced suffix array that Spark sorts, and its common-prefix interval tree.

A byte goes when a string of ``LENGTH`` bytes that covers it also starts anywhere else, in the same text too.

1. *Anchors.* Every window of ``LENGTH`` bytes selects, by its content alone, the leftmost smallest of its 32-byte grams. Equal windows
   select the same gram at the same place, so suffixes that start at selected grams (about one position in 85) stand for all.
2. *Suffix array.* A window that covers an anchor holds ``SIDE`` more bytes on its left or on its right, so anchors for which both of these longer
   strings occur once go (bit tables of bounded size find nearly all of them before anything is shuffled). The others get their text around, are
   dealt by gram and sorted by the text to the right, by Spark and with spilling: each partition is a part of the suffix array whose groups share
   at least the gram.
3. *Interval tree.* A stack scan of common-prefix lengths visits each interval once. Inside it, the order of left contexts shows which
   occurrences also agree to the left, and where their left extensions part: maximal repeats with all their occurrences.
4. *Frequent grams.* A gram with more than ``most`` occurrences never meets in one task: occurrences with equal text around on both sides are found by
   counting and need one of them only; the windows of the rest are counted, with map-side sums.

Copies of a whole text are one representative throughout. Only texts with such an anchor are moved.

Defined cases: null texts are empty, texts below ``LENGTH`` bytes lose nothing, null ids and repeated rows stay rows of their own (a repeated
row is a copy), an empty table gives an empty result, and other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .near_dedup import mix
from .runtime import Bits, attach, discard, written
from .words import pieces, texts_of

LENGTH = 200
NULL_ID = -(1 << 63)
GRAM = 32
LEFT = LENGTH - GRAM
SIDE = LEFT // 2
STEP = 1 << 17
LOW = np.uint64((1 << 20) - 1)
EMPTY_SHA = hashlib.sha256(b"").hexdigest()
_rng = np.random.default_rng(23)
_of_byte = _rng.integers(0, 1 << 63, 256, dtype=np.int64).astype(np.uint64)
_factor = _rng.integers(0, 1 << 62, 5, dtype=np.int64).astype(np.uint64) * np.uint64(2) + np.uint64(1)


def grams(data: np.ndarray) -> np.ndarray:
    """A 64-bit hash of the ``GRAM`` bytes from each position on."""
    h, width = _of_byte[data], 1
    for f in _factor:
        h = h[:-width] * f + h[width:]
        h ^= h >> np.uint64(29)
        width *= 2
    return mix(h)


def sliding_least(v: np.ndarray, width: int) -> np.ndarray:
    span = 1
    while span * 2 <= width:
        v, span = np.minimum(v[:-span], v[span:]), span * 2
    return np.minimum(v[: len(v) - (width - span)], v[width - span :]) if span < width else v


def anchors(data: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Selected positions of concatenated texts, ascending, their gram hashes, and codes of the ``SIDE`` bytes before and behind (0 where a text has not so many)."""
    n = len(data)
    whole = np.ones(n, bool)  # a window that starts here ends in the same text
    for start, end in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
        whole[max(start, end - LENGTH + 1) : end] = False
    places, hashes, lefts, rights = [np.empty(0, np.int64)], [np.empty(0, np.uint64)], [np.empty(0, np.int32)], [np.empty(0, np.int32)]
    for s in range(0, max(n - LENGTH + 1, 0), STEP):
        before = min(s, SIDE)
        g = grams(data[s - before : s + STEP + LENGTH - 1 + SIDE])
        windows = min(n, s + STEP + LENGTH - 1) - s - GRAM + 1
        least = sliding_least((g[before : before + windows] & ~LOW) | np.arange(windows, dtype=np.uint64), LEFT + 1)
        at = np.unique((least & LOW).astype(np.int64)[whole[s : s + len(least)]])
        places.append(at + s)
        hashes.append(g[at + before])
        for out, shifts in ((lefts, (-SIDE, -52, -20)), (rights, (32, 64, SIDE))):
            code = np.zeros(len(at), np.uint64)
            for k, f in zip(shifts, _factor, strict=False):
                code = code * f + g[np.clip(at + before + k, 0, len(g) - 1)]
            out.append((mix(code) >> np.uint64(32)).astype(np.uint32).view(np.int32) | np.int32(1))
    where, first = np.unique(np.concatenate(places), return_index=True)
    found, left, right = (np.concatenate(x)[first] for x in (hashes, lefts, rights))
    text = np.searchsorted(bounds, where, "right") - 1
    left[where - bounds[text] < SIDE] = 0
    right[bounds[text + 1] - where < SIDE + GRAM] = 0
    return where, found, left, right


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Maximal runs of a union of half-open spans."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def scan(docs: DataFrame) -> DataFrame:
    """``id, key, sha, n, hashes, places, lefts, rights, own`` of each row of ``id, text``; own: spans that repeat inside the text, flat.

    Of equal surroundings inside one text only the first anchor goes on, so a periodic text has few.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text", 4 << 20):
            texts = texts_of(b, "text")
            bounds = np.frombuffer(texts.buffers()[1], np.int32)[: len(texts) + 1].astype(np.int64)
            raw = texts.buffers()[2]
            data = np.frombuffer(raw, np.uint8)[: bounds[-1]] if raw is not None else np.empty(0, np.uint8)
            where, found, left, right = anchors(data, bounds)
            cut = np.searchsorted(where, bounds)
            rows: list[list] = [[], [], [], [], [], [], [], []]
            for k in range(len(texts)):
                start, end = int(bounds[k]), int(bounds[k + 1])
                body = data[start:end].tobytes()
                mine = slice(cut[k], cut[k + 1])
                p, h, lo, hi = where[mine] - start, found[mine].view(np.int64), left[mine], right[mine]
                spans: list[tuple[int, int]] = []
                if len(np.unique(h)) < len(h):
                    seen: dict[tuple, int] = {}
                    use = []
                    for j, x in enumerate(p.tolist()):
                        around = (x if x < LEFT else LEFT, body[max(0, x - LEFT) : x + LENGTH])
                        if around in seen:
                            spans += [(x - LEFT, x + LENGTH), (seen[around] - LEFT, seen[around] + LENGTH)]
                        else:
                            seen[around] = x
                            use.append(j)
                    p, h, lo, hi, spans = p[use], h[use], lo[use], hi[use], merged(spans)
                digest = hashlib.sha256(body)
                for column, value in zip(rows, (digest.digest()[:16], digest.hexdigest(), end - start, h, p.astype(np.int32), lo, hi, [y for s in spans for y in s]), strict=True):
                    column.append(value)
            kinds = [pa.binary(), pa.string(), pa.int64(), pa.list_(pa.int64()), *[pa.list_(pa.int32())] * 4]
            yield pa.RecordBatch.from_arrays([b.column("id"), *(pa.array(x, t) for x, t in zip(rows, kinds, strict=True))], names=["id", "key", "sha", "n", "hashes", "places", "lefts", "rights", "own"])

    return docs.mapInArrow(run, "id long, key binary, sha string, n long, hashes array<long>, places array<int>, lefts array<int>, rights array<int>, own array<int>")


def once(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """``id, key, text`` of the rows that ``wanted`` (a written table) names by ``id, key`` and of few others, repeated rows once."""
    named = wanted.select(F.xxhash64("id", "key").alias("tag")).distinct()
    found = Bits.of(named, "tag", named.count(), "named").sift(docs.withColumn("tag", F.xxhash64("id", "key")), "tag")
    return found.groupBy("id", "key").agg(F.first("text").alias("text"))


def surroundings(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """``hash, id, key, place, before, after, hot`` of the ``wanted`` anchors; before is reversed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text", 2 << 20):
            out: list[list] = [[], [], [], [], [], [], []]
            for id_, key, text, marks in zip(*(b.column(c).to_pylist() for c in ("id", "key", "text", "marks")), strict=True):
                body = text.encode()
                for m in marks:
                    x = m["place"]
                    for column, value in zip(out, (m["hash"], id_, key, x, body[max(0, x - LEFT) : x][::-1], body[x : x + LENGTH], m["hot"]), strict=True):
                        column.append(value)
                if len(out[0]) > 20000:
                    yield batch(out)
                    out = [[], [], [], [], [], [], []]
            yield batch(out)

    def batch(out: list[list]) -> pa.RecordBatch:
        kinds = [pa.int64(), pa.int64(), pa.binary(), pa.int32(), pa.binary(), pa.binary(), pa.bool_()]
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(out, kinds, strict=True)], names=["hash", "id", "key", "place", "before", "after", "hot"])

    marks = wanted.groupBy("id", "key").agg(F.collect_list(F.struct("hash", "place", "hot")).alias("marks"))
    return once(docs, wanted).join(marks, ["id", "key"]).mapInArrow(run, "hash long, id long, key binary, place int, before binary, after binary, hot boolean")


def common(strings: list[bytes], width: int) -> np.ndarray:
    """Common-prefix length of each string and the next one, up to ``width``."""
    size = np.fromiter(map(len, strings), np.int64, len(strings))
    table = np.frombuffer(b"".join(s.ljust(width, b"\0") for s in strings), np.uint8).reshape(-1, width)
    differ = np.concatenate([table[:-1] != table[1:], np.ones((max(len(strings) - 1, 0), 1), bool)], axis=1)
    return np.minimum(differ.argmax(1), np.minimum(size[:-1], size[1:]))


def intervals(prefix: list[int]) -> Iterator[tuple[int, int, int]]:
    """Common-prefix intervals ``first, last, length`` of an array whose neighbours k, k + 1 share ``prefix[k]``; children first."""
    stack: list[tuple[int, int]] = []
    for k, length in enumerate([*prefix, 0]):
        first = k
        while stack and stack[-1][1] > length:
            first, own = stack.pop()
            yield first, k, own
        if length and (not stack or stack[-1][1] < length):
            stack.append((first, length))


def maximal_groups(after: list[bytes], before: list[bytes], least: int = LENGTH) -> Iterator[tuple[np.ndarray, np.ndarray, int, int]]:
    """Repeats of an array sorted by ``after``: ``members, best, left, right``.

    Members share ``right`` bytes onwards and ``left`` bytes backwards, at least ``least`` together. Left is where their left extensions first
    differ or end; best is how far back each member agrees with some other one.
    """
    n = len(after)
    prefix = common(after, max(map(len, after)) or 1).tolist()
    order = sorted(range(n), key=before.__getitem__)
    shared = common([before[k] for k in order], max(map(len, before)) or 1)
    rank = np.empty(n, np.int64)
    rank[order] = np.arange(n)
    order_of = np.asarray(order)
    for first, last, right in intervals(prefix):
        r = np.sort(rank[first : last + 1])
        near = shared if len(r) == n else np.minimum.reduceat(shared[: r[-1]], r[:-1])
        together = near + right >= least
        if not together.any():
            continue
        edge = np.diff(np.concatenate([[False], together, [False]]).astype(np.int8))
        for lo, hi in zip(np.flatnonzero(edge == 1), np.flatnonzero(edge == -1), strict=True):
            run = near[lo:hi]
            yield order_of[r[lo : hi + 1]], np.maximum(np.concatenate([[0], run]), np.concatenate([run, [0]])), int(run.min()), right


def covered(placed: DataFrame) -> DataFrame:
    """``id, key, low, high``: repeated spans around the anchors of ``placed``, whole grams of it in each partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest: list[pa.RecordBatch] = []
        for b in batches:
            if not b.num_rows:
                continue
            rest.append(b)
            whole = pa.Table.from_batches(rest).combine_chunks()
            h = whole.column("hash").to_numpy()
            end = int(np.searchsorted(h, h[-1], "left"))
            if end:
                yield from spans(whole.slice(0, end))
                rest = whole.slice(end).combine_chunks().to_batches()
        if rest:
            yield from spans(pa.Table.from_batches(rest))

    def spans(t: pa.Table) -> Iterator[pa.RecordBatch]:
        h = t.column("hash").to_numpy()
        after, before = t.column("after").to_pylist(), t.column("before").to_pylist()
        left, right = np.zeros(len(h), np.int64), np.zeros(len(h), np.int64)
        start = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]]))
        stop = np.append(start[1:], len(h))
        two = start[stop - start == 2]
        if len(two):  # a group of two is one interval
            ends = np.ravel(np.column_stack([two, two + 1]))
            b = common([after[k] for k in ends], LENGTH)[::2]
            a = common([before[k] for k in ends], LEFT)[::2]
            good = a + b >= LENGTH
            for k in (0, 1):
                left[two[good] + k], right[two[good] + k] = a[good], b[good]
        for lo, hi in zip(start.tolist(), stop.tolist(), strict=True):
            if hi - lo > 2:
                for members, best, _, b in maximal_groups(after[lo:hi], before[lo:hi]):
                    at = lo + members
                    left[at] = np.maximum(left[at], best)
                    right[at] = np.maximum(right[at], b)
        hit = right > 0
        place = t.column("place").to_numpy()[hit]
        kept = t.select(["id", "key"]).filter(pa.array(hit)).combine_chunks()
        yield pa.RecordBatch.from_arrays([*(pa.concat_arrays(kept.column(c).chunks or [pa.array([], kept.column(c).type)]) for c in ("id", "key")), pa.array(place - left[hit], pa.int32()), pa.array(place + right[hit], pa.int32())], names=["id", "key", "low", "high"])

    return placed.repartition("hash").sortWithinPartitions("hash", "after").select("hash", "id", "key", "place", "before", "after").mapInArrow(run, "id long, key binary, low int, high int")


def counted(hot: DataFrame) -> DataFrame:
    """``id, key, low, high`` around anchors of frequent grams: each window that holds one is counted, by gram and place of the gram in it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for at in range(0, whole.num_rows, 200):
                b = whole.slice(at, 200)
                digests, owner, back = [], [], []
                for k, (gram, before, after) in enumerate(zip(*(b.column(c).to_pylist() for c in ("hash", "before", "after")), strict=True)):
                    text, x = before[::-1] + after, len(before)
                    for t in range(max(0, LENGTH - len(after)), x + 1):
                        digests.append(xxhash.xxh3_128_digest(text[x - t : x - t + LENGTH], (gram + t) % (1 << 64)))
                        owner.append(k)
                        back.append(t)
                mine = b.select(["id", "key", "place"]).take(pa.array(owner, pa.int32()))
                yield pa.RecordBatch.from_arrays([pa.array(digests, pa.binary()), *mine.columns, pa.array(back, pa.int32())], names=["window", "id", "key", "place", "back"])

    windows = hot.mapInArrow(run, "window binary, id long, key binary, place int, back int")
    often = written(windows.groupBy("window").agg(F.count(F.lit(1)).alias("group_size")).where("group_size > 1"), "windows")
    hits = attach(windows, often, "window", hot.count() * (LEFT + 1), how="inner")
    span = hits.groupBy("id", "key", "place").agg(F.max("back").alias("most"), F.min("back").alias("least"))
    return span.selectExpr("id", "key", "place - most as low", f"place + {LENGTH} - least as high")


def twins(hot: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Spans of anchors whose whole surroundings occur again, and one anchor for each distinct surroundings, of a written table."""
    same = hot.withColumn("same", F.md5(F.concat("before", F.encode(F.concat(F.lit("|"), F.length("before"), F.lit("|")), "utf-8"), "after")))
    least = F.min(F.struct("id", "key", "place")).alias("first")
    several = written(same.groupBy("same").agg(least, F.count(F.lit(1)).alias("group_size")).where("group_size > 1"), "twins")
    found = attach(same, several, "same", hot.count())
    whole = found.where(f"group_size > 1 and length(before) + length(after) >= {LENGTH}")
    spans = whole.selectExpr("id", "key", "cast(place - length(before) as int) as low", "cast(place + length(after) as int) as high")
    alone = found.where("group_size is null or (first.id = id and first.key = key and first.place = place)").select(*hot.columns)
    return spans, alone


def without(docs: DataFrame, spans: DataFrame) -> DataFrame:
    """``id, key, n_removed, n_spans, kept_sha256, kept_bytes`` of the texts that lose something."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text", 4 << 20):
            out: list[list] = [[], [], [], []]
            for text, lows, highs in zip(*(b.column(c).to_pylist() for c in ("text", "lows", "highs")), strict=True):
                body, runs = text.encode(), merged(list(zip(lows, highs, strict=True)))
                ends = [0, *(y for s in runs for y in s), len(body)]
                kept = b"".join(body[x:y] for x, y in zip(ends[::2], ends[1::2], strict=True))
                for column, value in zip(out, (len(body) - len(kept), len(runs), hashlib.sha256(kept).hexdigest(), kept), strict=True):
                    column.append(value)
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.binary()]
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("key"), *(pa.array(x, t) for x, t in zip(out, kinds, strict=True))], names=["id", "key", "n_removed", "n_spans", "kept_sha256", "kept_bytes"])

    each = spans.groupBy("id", "key").agg(F.collect_list("low").alias("lows"), F.collect_list("high").alias("highs"))
    return once(docs, spans).join(each, ["id", "key"]).mapInArrow(run, "id long, key binary, n_removed long, n_spans long, kept_sha256 string, kept_bytes binary")


def removed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", most: int = 100_000) -> DataFrame:
    """One row per input row: ``doc_id, n_bytes, n_removed, n_spans, kept_sha256``."""
    base = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_ID)).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    texts = base.withColumn("key", F.substring(F.unhex(F.sha2("text", 256)), 1, 16))
    scanned = written(scan(base), "scanned")
    total = scanned.count()
    copies = scanned.groupBy("key").agg(F.min("id").alias("first_id"), F.count(F.lit(1)).alias("group_size"))
    repeated = written(copies.where("group_size > 1"), "copies")
    # a copied text keeps only its first row's anchors; equal rows count once
    copied = Bits.of(repeated.select(F.xxhash64("key").alias("tag")), "tag", total, "copied")
    known = copied.mark(scanned.where("n >= %d" % LENGTH).select("id", "key", "hashes", "places", "lefts", "rights", F.xxhash64("key").alias("tag")), "tag", "maybe").drop("tag")
    single = known.where("not maybe").drop("maybe")
    first = attach(known.where("maybe").drop("maybe"), repeated, "key", total).where("group_size is null or id = first_id").drop("first_id", "group_size").dropDuplicates(["key", "id"])
    zipped = F.explode(F.arrays_zip("hashes", "places", "lefts", "rights")).alias("m")
    marks = single.unionByName(first).select("id", "key", zipped).select("id", "key", F.col("m.hashes").alias("hash"), F.col("m.places").alias("place"), F.col("m.lefts").alias("left"), F.col("m.rights").alias("right"))
    groups = written(marks.groupBy("hash").agg(F.count(F.lit(1)).alias("group_size")).where("group_size > 1").select("hash"), "grams")
    maybe = written(Bits.of(groups, "hash", groups.count(), "gram_bits").sift(marks, "hash"), "anchors")
    sides = [F.when(F.col(c) != 0, F.xxhash64("hash", c, F.lit(k))) for k, c in enumerate(("left", "right"))]
    longer = maybe.select(F.explode(F.array(*sides)).alias("side")).where("side is not null")
    longer = written(longer.groupBy("side").agg(F.count(F.lit(1)).alias("group_size")).where("group_size > 1").select("side"), "sides")
    bits = Bits.of(longer, "side", longer.count(), "side_bits")
    found = bits.mark(bits.mark(maybe.withColumns({"before": sides[0], "behind": sides[1]}), "before", "in_left"), "behind", "in_right").where("in_left or in_right").select("id", "key", "hash", "place")
    frequent = written(found.groupBy("hash").agg(F.count(F.lit(1)).alias("group_size")).where(F.col("group_size") > most).select("hash"), "frequent")
    wanted = written(Bits.of(frequent, "hash", frequent.count(), "frequent_bits").mark(found, "hash", "hot"), "wanted")
    discard(docs.sparkSession, maybe)
    placed = surroundings(texts, wanted)
    if frequent.isEmpty():
        spans = covered(placed)
    else:
        placed = written(placed, "surroundings")
        equal, alone = twins(placed.where("hot"))
        spans = covered(placed.where("not hot")).unionByName(equal).unionByName(counted(written(alone, "alone")))
    own = scanned.where("size(own) > 0").select("id", "key", F.explode(F.sequence(F.lit(0), F.size("own") - 2, F.lit(2))).alias("k"), "own").selectExpr("id", "key", "own[k] as low", "own[k + 1] as high")
    spans = written(written(spans.unionByName(own), "all_spans").join(repeated, "key", "left_anti"), "spans")
    lost = written(without(texts, spans).drop("kept_bytes"), "lost")
    discard(docs.sparkSession, placed, spans)
    sized = attach(scanned.select("id", "key", "sha", "n"), repeated.select("key", "group_size"), "key", total)
    out = sized.join(lost, ["id", "key"], "left")
    gone = (F.col("group_size") > 1) & (F.col("n") >= LENGTH)
    return out.select(
        F.nullif(F.col("id"), F.lit(NULL_ID)).alias("doc_id"),
        F.col("n").alias("n_bytes"),
        F.when(gone, F.col("n")).otherwise(F.coalesce(F.col("n_removed"), F.lit(0))).alias("n_removed"),
        F.when(gone, F.lit(1)).otherwise(F.coalesce(F.col("n_spans"), F.lit(0))).cast("long").alias("n_spans"),
        F.when(gone, F.lit(EMPTY_SHA)).otherwise(F.coalesce(F.col("kept_sha256"), F.col("sha"))).alias("kept_sha256"),
    )
