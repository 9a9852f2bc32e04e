"""Pattern packing of token sequences by non-negative least squares.

Documents become token ids (a public tokenizer, then id 0); only documents above ``capacity`` are cut. Everything after
the token pass works on the histogram of piece lengths, whose size is ``capacity`` whatever the input:

1. *Patterns*: multisets of at most ``parts`` length bins that fill a sequence, enumerated once. Bins are ``grain`` tokens wide
   and round up, so a pattern always fits; lengths below ``small`` stay out and fill gaps later.
2. *Fit*: an active-set non-negative least squares gives repeat counts whose bins add up to the histogram; counts are rounded
   and bounded by what is there. Real lengths are drawn from the bins.
3. *Residuals*: what rounding leaves, and all small pieces, go longest first into the tightest remaining gap (of pattern sequences,
   too) or open a sequence. Whole runs of equal pieces and equal gaps move at once.

The plan says, for each length, which run of ranks takes which place in which run of sequences. Pieces get their rank within a
length from a window over salted (length, salt) groups, so a length that a third of all rows share spreads over many tasks.

Defined cases: a null or empty text is one token (the end id). Repeated rows and repeated ids are pieces of their own. An empty
table packs to an empty table. Other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .chunk_tokens import encoder
from .runtime import written
from .words import pieces as cut
from .words import texts_of

PIECE_BYTES = 2 << 20  # text tokenized at once in a worker
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def tokenized(docs: DataFrame, tokenizer: str, capacity: int, end_id: int, id_col: str, text_col: str) -> DataFrame:
    """One row per piece, without the ids themselves."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = encoder(tokenizer)
        for batch in cut(batches, "text", PIECE_BYTES):
            ids, bounds = own.encode(texts_of(batch, "text"))
            n = len(bounds) - 1
            sizes = np.diff(bounds) + 1
            out = np.full(len(ids) + n, end_id, "<u4")
            out[np.arange(len(ids)) + np.repeat(np.arange(n), sizes - 1)] = ids
            first = np.cumsum(sizes) - sizes
            many = -(-sizes // capacity)
            row = np.repeat(np.arange(n), many)
            k = np.arange(len(row)) - np.repeat(np.cumsum(many) - many, many)
            start = k * capacity
            length = np.minimum(capacity, sizes[row] - start)
            at = first[row] + start
            view = memoryview(out).cast("B")
            crc = [zlib.crc32(view[4 * a : 4 * b]) for a, b in zip(at.tolist(), (at + length).tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id").take(pa.array(row)), pa.array(k, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())],
                names=["doc_id", "piece", "start", "length", "ids_crc32"],
            )

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, PIECES)


def patterns(bins: int, least: int, parts: int) -> list[tuple[int, ...]]:
    """Multisets of at most ``parts`` bins, each ``least`` or more, that add up to ``bins``; descending inside."""
    found: list[tuple[int, ...]] = []

    def grow(head: tuple[int, ...], room: int) -> None:
        top = min(room, head[-1] if head else bins)
        if room >= least and room <= top:
            found.append((*head, room))
        if len(head) + 1 < parts:
            for b in range(top, least - 1, -1):
                if room - b >= least and b * (parts - len(head)) >= room:
                    grow((*head, b), room - b)

    grow((), bins)
    return found


def nnls(columns: np.ndarray, target: np.ndarray, rounds: int = 4) -> np.ndarray:
    """Least squares with x >= 0; ``columns`` holds the row numbers of each column's ones, padded with the number of rows.

    Active set method: the best few columns by gradient enter together, the free set is solved, negative ones leave.
    """
    rows, n = len(target), len(columns)
    x, free, weight = np.zeros(n), np.zeros(0, np.int64), 1 / np.sqrt(target + 1.0)
    goal = target * weight
    padded = np.append(weight, 0.0)

    def dense(which: np.ndarray) -> np.ndarray:
        a = np.zeros((rows + 1, len(which)))
        for p in range(columns.shape[1]):
            np.add.at(a, (columns[which, p], np.arange(len(which))), 1.0)
        return a[:rows] * weight[:, None]

    def total(which: np.ndarray, amount: np.ndarray) -> np.ndarray:
        s = np.zeros(rows + 1)
        for p in range(columns.shape[1]):
            np.add.at(s, columns[which, p], amount)
        return s[:rows] * weight

    for _ in range(rounds * 40):
        rest = goal - total(free, x[free])
        gain = (np.append(rest, 0.0) * padded)[columns].sum(1)
        gain[free] = -np.inf
        enter = np.argpartition(gain, -min(32, n))[-min(32, n) :]
        enter = enter[gain[enter] > 1e-6 * max(1.0, float(np.abs(goal).max()))]
        if not len(enter) or len(free) >= rows:
            break
        free = np.union1d(free, enter)
        for _ in range(50):
            a = dense(free)
            y = np.linalg.solve(a.T @ a + 1e-9 * np.eye(len(free)), a.T @ goal)
            if (y > 0).all():
                x[free] = y
                break
            low = y <= 0
            gap = x[free] - y
            step = float(np.min(np.where(low & (gap > 0), x[free] / np.where(gap > 0, gap, 1), 1.0)))
            x[free] = np.maximum(0, x[free] + step * (y - x[free]))
            leave = low & (x[free] <= 1e-12)
            if not leave.any():
                leave = low
            x[free[leave]] = 0
            free = free[~leave]
            if not len(free):
                break
    return x


@dataclass
class Plan:
    """Runs of ranks: pieces of ``length`` with rank in [first, first + count) take ``offset`` in sequences from ``sequence`` on."""

    length: np.ndarray
    first: np.ndarray
    offset: np.ndarray
    sequence: np.ndarray
    sequences: int
    by_pattern: int


def plan(histogram: dict[int, int], capacity: int, parts: int = 3, grain: int = 4, small: int = 128) -> Plan:
    """Places for all pieces shorter than ``capacity``."""
    left = np.zeros(capacity + 1, np.int64)
    for length, count in histogram.items():
        if 0 < length < capacity:
            left[length] = count
    grain = max(grain, -(-capacity // 512))
    bins = capacity // grain
    least = max(1, min(small, capacity // 4) // grain)
    groups: list[list] = []  # [count, lengths]
    by_bin = np.zeros(bins + 1, np.int64)
    np.add.at(by_bin, -(-np.arange(capacity + 1) // grain), left)
    by_bin[:least] = 0
    used = [p for p in patterns(bins, least, parts) if all(by_bin[b] for b in p)]
    if used:
        columns = np.full((len(used), parts), bins + 1)
        for k, p in enumerate(used):
            columns[k, : len(p)] = p
        fitted = nnls(columns, by_bin.astype(float))
        for k in np.argsort(-fitted, kind="stable"):
            want = int(round(float(fitted[k])))
            if want <= 0:
                break
            p = used[k]
            need = {b: p.count(b) for b in p}
            want = min(want, *(int(by_bin[b] // m) for b, m in need.items()))
            while want > 0:  # runs of equal real lengths, the longest of each bin first
                lengths, taken = [], defaultdict(int)
                for b in p:
                    at = min(b * grain, capacity)
                    while left[at] - taken.get(at, 0) <= 0:
                        at -= 1
                    taken[at] += 1
                    lengths.append(at)
                run = min(want, *(int(left[a] // m) for a, m in taken.items()))
                for a, m in taken.items():
                    left[a] -= m * run
                for b, m in need.items():
                    by_bin[b] -= m * run
                groups.append([run, tuple(lengths)])
                want -= run
    by_pattern = sum(g[0] for g in groups)
    gaps: list[list] = [[] for _ in range(capacity + 1)]  # by room: groups
    for g in groups:
        gaps[capacity - sum(g[1])].append(g)
    done: list[list] = []
    for length in range(capacity - 1, 0, -1):
        count = int(left[length])
        room = length
        while count > 0:
            while room <= capacity and not gaps[room]:
                room += 1
            if room > capacity:
                each = capacity // length
                full, rest = divmod(count, each)
                for n, k in ((full, each), (1 if rest else 0, rest)):
                    if n:
                        gaps[capacity - k * length].append([n, (length,) * k])
                break
            g = gaps[room].pop()
            run = min(count, g[0])
            if run < g[0]:
                gaps[room].append([g[0] - run, g[1]])
            gaps[room - length].append([run, (*g[1], length)])
            count -= run
    for of_room in gaps:
        done += of_room
    runs, next_rank, base = [], defaultdict(int), 0
    for count, lengths in done:
        at = 0
        for length in lengths:
            runs.append((length, next_rank[length], at, base))
            next_rank[length] += count
            at += length
        base += count
    runs.sort()
    table = np.array(runs, np.int64).reshape(-1, 4)
    return Plan(table[:, 0], table[:, 1], table[:, 2], table[:, 3], base, by_pattern)


def best_plan(histogram: dict[int, int], capacity: int, parts: int = 3) -> Plan:
    """The plan with the fewest sequences among a few pattern sets: long patterns, fewer small bins, pairs."""
    settings = [(parts, capacity // 16), (parts, capacity // 8), (min(parts, 2), capacity // 5)]
    return min((plan(histogram, capacity, k, small=max(1, least)) for k, least in settings), key=lambda p: p.sequences)


def ranked(rows: DataFrame, counts: DataFrame, total: int) -> DataFrame:
    """``rows`` with a rank among the rows of their length, by way of salted groups of a bounded share of all rows."""
    target = max(500, total // 100_000)
    salted = rows.join(F.broadcast(counts.select("length", F.ceil(F.col("n") / target).cast("int").alias("salts"))), "length").withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece", "uid"), F.col("salts")))
    sizes = salted.groupBy("length", "salt").agg(F.count(F.lit(1)).alias("m"))
    ahead = sizes.withColumn("ahead", F.sum("m").over(Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1))).select("length", "salt", F.coalesce("ahead", F.lit(0)).alias("ahead"))
    within = F.row_number().over(Window.partitionBy("length", "salt").orderBy("doc_id", "piece", "uid"))
    return salted.withColumn("within", within).join(F.broadcast(ahead), ["length", "salt"]).withColumn("rank", F.col("ahead") + F.col("within") - 1)


def pack(docs: DataFrame, tokenizer: str, capacity: int = 2048, end_id: int = 0, parts: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: ``doc_id, piece, start, length, ids_crc32, sequence_id, offset``."""
    spark = docs.sparkSession
    rows = written(tokenized(docs, tokenizer, capacity, end_id, id_col, text_col), "pieces").withColumn("uid", F.monotonically_increasing_id())
    counts = written(rows.groupBy("length").agg(F.count(F.lit(1)).alias("n")), "lengths")  # at most ``capacity`` rows
    histogram = {r["length"]: r["n"] for r in counts.collect()}
    fit = best_plan(histogram, capacity, parts)
    table = spark.sparkContext.broadcast((fit.length * (1 << 44) + fit.first, fit.first, fit.offset, fit.sequence))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, first, offset, sequence = table.value
        for b in batches:
            rank = b.column("rank").to_numpy(zero_copy_only=False)
            k = np.searchsorted(keys, b.column("length").to_numpy(zero_copy_only=False) * (1 << 44) + rank, "right") - 1
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in names), pa.array(sequence[k] + rank - first[k]), pa.array(offset[k])], names=[*names, "sequence_id", "offset"])

    names = ["doc_id", "piece", "start", "length", "ids_crc32"]
    short = ranked(rows.where(F.col("length") < capacity), counts.where(F.col("length") < capacity), sum(histogram.values()))
    placed = short.select(*names, "rank").mapInArrow(place, f"{PIECES}, sequence_id long, offset long")
    full = rows.where(F.col("length") == capacity).select(*names, (F.col("uid") + F.lit(fit.sequences)).alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    return placed.unionByName(full)
