"""Near-duplicate classes by HyperMinHash registers, banding, corrected similarity estimates and exact verification.

1. *Registers.* A document's set of five-word shingles is hashed once. The low bits of a hash name a bucket; of the rest, the bucket
   keeps its minimum as a leading-zero count (6 bits) and a mantissa (10 bits): two bytes. Empty buckets borrow from a
   filled one by a fixed random walk, so short documents band like long ones.
2. *Classes of equal sets* collapse first, by a digest of the whole set: a group of copies is one representative from then on.
3. *Bands* of four registers give buckets of candidates. First round: each member against the hub of its bucket, the member that shares most
   with others (the unedited text of a group, mostly), never all pairs. Components follow.
4. *Estimate, then verify.* Register matches minus the expected accidental ones estimate the similarity; pairs six standard errors below the
   threshold go. The error is that of the registers that a small set fills itself. All others are confirmed on the full hashed sets.
5. *Second round*, exact: buckets whose members are in different components are open. The members of all open buckets go through a prefix join:
   sets in one global order, rare shingles first, can reach the threshold only if they share a shingle in their first few, at places that leave
   enough behind. So pairs that share a frequent passage only never meet, however many there are, and no bucket is capped.

A pair at the threshold misses all 32 bands with probability below 1e-5; pairs in one component need no link of their own.
Shuffles carry ids, bands and registers; shingle sets move only for documents that share a bucket.

Defined cases: null or empty texts (white space only, too) have an empty set, link with nothing and are kept. Fewer than five words make
one shingle. Every row stands for itself: null ids and repeated ids link nothing. A class is named by its smallest id (null if it has none),
so classes that share a repeated id, or have none, share a name; ``kept`` marks exactly one row of each. An empty table gives an empty result.
Other columns are ignored by ``classes`` and carried untouched by ``drop_near_duplicates``, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import Bits, attach, bits_for, discard, settle, survivors, text_of, written
from .words import filled, pieces, split, texts_of

WIDTH = 5
BUCKETS = 128
PIECE_BYTES = 3 << 20  # text hashed at once in a worker
ROWS = 4
MANTISSA = 10
_walk = np.random.default_rng(7).integers(0, BUCKETS, (4 * BUCKETS, BUCKETS))
_odd = np.random.default_rng(11).integers(1, 1 << 62, ROWS + WIDTH, dtype=np.int64).astype(np.uint64) * np.uint64(2) + np.uint64(1)


def mix(x: np.ndarray) -> np.ndarray:
    """A fixed bijection of 64-bit words that spreads all bits."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingles(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes of all texts in a row, sorted inside each text, and the bounds of the texts."""
    w = split(texts, ascii_only=True, lower_ascii=True)
    of_word = np.fromiter((xxhash.xxh3_64_intdigest(s) for s in w.distinct), np.uint64, len(w.distinct))[w.index]
    n = np.diff(w.bounds)
    found = np.zeros(len(of_word), np.uint64)
    at = np.arange(len(of_word)) - np.repeat(w.bounds[:-1], n)
    upto = np.repeat(n, n)
    for k in range(WIDTH):
        there = at + k < upto
        word = np.zeros(len(of_word), np.uint64)
        word[there] = of_word[k + np.flatnonzero(there)] | np.uint64(1)
        found = mix(found + word * _odd[k])
    use = at < np.maximum(upto - WIDTH + 1, 1)
    row = np.repeat(np.arange(len(n)), n)[use]
    found = found[use]
    order = np.lexsort((found, row))
    row, found = row[order], found[order]
    if len(found):
        first = np.concatenate([[True], (row[1:] != row[:-1]) | (found[1:] != found[:-1])])
        row, found = row[first], found[first]
    return found, np.searchsorted(row, np.arange(len(n) + 1))


def registers(found: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Compressed registers, one row of ``BUCKETS`` 16-bit words per text; zeros for an empty set."""
    n = len(bounds) - 1
    out = np.zeros((n, BUCKETS), np.uint16)
    if not len(found):
        return out
    cell = np.repeat(np.arange(n), np.diff(bounds)) * BUCKETS + (found % np.uint64(BUCKETS)).astype(np.int64)
    order = np.argsort(cell, kind="stable")
    cell, value = cell[order], (mix(found) >> np.uint64(7))[order]
    start = np.flatnonzero(np.concatenate([[True], cell[1:] != cell[:-1]]))
    least = np.minimum.reduceat(value, start)
    size = np.frexp(least.astype(np.float64))[1].astype(np.uint64)  # bits in use, of 57
    shift = np.where(size > MANTISSA + 1, size - np.minimum(size, MANTISSA + 1), 0).astype(np.uint64)
    code = ((np.uint64(57) - np.minimum(size, 57)) << np.uint64(MANTISSA)) | ((least >> shift) & np.uint64((1 << MANTISSA) - 1))
    filled = np.zeros(n * BUCKETS, bool)
    filled[cell[start]] = True
    out.reshape(-1)[cell[start]] = code.astype(np.uint16)
    filled = filled.reshape(n, BUCKETS)
    own = filled.any(1)
    todo = ~filled & own[:, None]
    for step in _walk:
        if not todo.any():
            break
        r, c = np.nonzero(todo)
        hit = filled[r, step[c]]
        out[r[hit], c[hit]] = out[r[hit], step[c[hit]]]
        todo[r[hit], c[hit]] = False
    for r in np.flatnonzero(todo.any(1)):
        out[r, todo[r]] = out[r, np.flatnonzero(filled[r])[0]]
    return out


def bands(codes: np.ndarray) -> np.ndarray:
    """64-bit band keys, ``BUCKETS / ROWS`` a row."""
    g = codes.reshape(len(codes), -1, ROWS).astype(np.uint64)
    key = np.broadcast_to(np.arange(g.shape[1], dtype=np.uint64) + np.uint64(1), g.shape[:2])
    for k in range(ROWS):
        key = mix(key + g[:, :, k] * _odd[WIDTH + k])
    return key.view(np.int64)


def signed(docs: DataFrame) -> DataFrame:
    """``id, tag, stamp, n, digest, codes, bands`` of each row of ``id, text, tag, stamp``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text", PIECE_BYTES):
            found, bounds = shingles(texts_of(b, "text"))
            codes = registers(found, bounds)
            keys = bands(codes)
            raw = [found[x:y].tobytes() for x, y in zip(bounds[:-1], bounds[1:], strict=True)]
            offsets = pa.array(np.arange(len(keys) + 1) * keys.shape[1], pa.int32())
            yield pa.RecordBatch.from_arrays(
                [b.column("id"), b.column("tag"), b.column("stamp"), pa.array(np.diff(bounds), pa.int64()), pa.array([xxhash.xxh3_128_digest(r) for r in raw], pa.binary()), pa.array([c.tobytes() for c in codes], pa.binary()), pa.ListArray.from_arrays(offsets, pa.array(keys.reshape(-1)))],
                names=["id", "tag", "stamp", "n", "digest", "codes", "bands"],
            )

    return docs.mapInArrow(run, "id long, tag long, stamp binary, n long, digest binary, codes binary, bands array<long>")


def sets_of(docs: DataFrame) -> DataFrame:
    """``id, items``: the hashed set of each row of ``id, text``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in pieces(batches, "text", PIECE_BYTES):
            found, bounds = shingles(texts_of(b, "text"))
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.ListArray.from_arrays(pa.array(bounds, pa.int32()), pa.array(found.view(np.int64)))], names=["id", "items"])

    return docs.mapInArrow(run, "id long, items array<long>")


def standard_error(n: np.ndarray, t: float) -> np.ndarray:
    """Of the share of equal registers, at similarity ``t``: borrowed registers count with those that they come from."""
    filled = BUCKETS * -np.expm1(-np.maximum(n, 1.0) / BUCKETS)
    borrowed = (BUCKETS - filled) / filled
    independent = BUCKETS**2 / (filled * ((1 + borrowed) ** 2 + borrowed))
    return np.sqrt(t * (1 - t) / independent)


def estimated(pairs: DataFrame, known: DataFrame, percent: int) -> DataFrame:
    """Pairs ``a, b`` whose corrected estimate is not far below the threshold; ``known`` has ``id, n, codes``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in filled(batches):
            x, y = (np.frombuffer(b"".join(b.column(c).to_pylist()), np.uint16).reshape(-1, BUCKETS) for c in ("codes", "codes_b"))
            n, m = (b.column(c).to_numpy(zero_copy_only=False).astype(float) for c in ("n", "n_b"))
            ratio = np.maximum(n, m) / np.minimum(n, m)
            accidental = 0.1699194871 * BUCKETS / (1 << MANTISSA) * 4 * ratio / (1 + ratio) ** 2
            guess = ((x == y).sum(1) - accidental) / (BUCKETS - accidental)
            t = percent / 100
            keep = (100 * np.minimum(n, m) >= percent * np.maximum(n, m)) & (guess >= t - 6 * standard_error(np.minimum(n, m), t))
            yield b.filter(pa.array(keep)).select(["a", "b"])

    left = known.select(F.col("id").alias("a"), "codes", "n")
    right = known.select(F.col("id").alias("b"), F.col("codes").alias("codes_b"), F.col("n").alias("n_b"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", "codes", "codes_b", "n", "n_b").mapInArrow(run, "a long, b long")


def tagged(docs: DataFrame) -> DataFrame:
    """``id, text`` with a digest of the text, ``stamp``, and a hash of both, ``tag``."""
    return docs.withColumn("stamp", F.unhex(F.md5("text"))).withColumn("tag", F.xxhash64("id", "stamp"))


def verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs ``a, b`` confirmed on full sets; a hub ``b`` with many partners is salted, so its partners spread over tasks."""
    hubs = pairs.groupBy("b").agg(F.count(F.lit(1)).alias("partners")).withColumn("salts", F.ceil(F.col("partners") / 200).cast("int"))
    salted = pairs.join(sets.select(F.col("id").alias("a"), "items"), "a").withColumn("salt_seed", F.xxhash64("a"))
    of_hub = hubs.join(sets.select(F.col("id").alias("b"), F.col("items").alias("items_b")), "b")
    few, many = of_hub.where("salts = 1"), of_hub.where("salts > 1")
    wide = written(many.select("b", "salts"), "hubs")
    spread = salted.join(wide, "b", "left").withColumn("salt", F.coalesce(F.pmod("salt_seed", "salts"), F.lit(0)).cast("int"))
    every = few.select("b", F.lit(0).alias("salt"), "items_b").unionByName(many.select("b", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"), "items_b"))
    both = F.size(F.array_intersect("items", "items_b"))
    return spread.join(every, ["b", "salt"]).where(both * 100 >= percent * (F.size("items") + F.size("items_b") - both)).select("a", "b")


LEVELS = 8


def prefixes(sets: DataFrame, tables: Broadcast, percent: int) -> DataFrame:
    """``token, id, root, n, place`` of the first shingles of each set of ``id, root, n, items``, in the order of (frequency class, hash).

    The order needs only to be the same for all sets; the frequency class of a shingle is the number of bit tables that have it. Places from which
    too little is left to reach the threshold with any partner are not listed, nor shingles that no other set has.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in filled(batches):
            lists = b.column("items")
            bounds = lists.offsets.to_numpy().astype(np.int64)
            token = lists.values.to_numpy(zero_copy_only=False)[bounds[0] : bounds[-1]]
            bounds = bounds - bounds[0]
            n = np.diff(bounds)
            row = np.repeat(np.arange(len(n)), n)
            level = np.zeros(len(token), np.int64)
            for bits, size in tables.value:
                slot = np.mod(token, size)
                level += (bits[slot >> 3] >> (slot & 7).astype(np.uint8)) & 1
            order = np.lexsort((token, level, row))
            token, level = token[order], level[order]
            place = np.arange(len(token)) - bounds[row]
            use = (level > 0) & ((n[row] - place) * 100 >= percent * n[row])
            mine = pa.array(row[use])
            yield pa.RecordBatch.from_arrays(
                [pa.array(token[use]), b.column("id").take(mine), b.column("root").take(mine), pa.array(n[row[use]], pa.int64()), pa.array(place[use], pa.int64())],
                names=["token", "id", "root", "n", "place"],
            )

    return sets.select("id", "root", "items").mapInArrow(run, "token long, id long, root long, n long, place long")


def frequency_bits(often: DataFrame) -> list[tuple[np.ndarray, int]]:
    """Bit tables of the tokens in at least 2, 8, 32, ... sets, on the driver; each as large as its own tokens need, and bounded."""
    top = F.least(F.floor(F.log2(F.col("sets") / 2) / 2).cast("int"), F.lit(LEVELS - 1))
    tokens = {r.top: r.n for r in often.groupBy(top.alias("top")).agg(F.count(F.lit(1)).alias("n")).collect()}
    sizes = [bits_for(sum(n for t, n in tokens.items() if t >= level)) for level in range(1 + max(tokens, default=-1))]
    if not sizes:
        return []
    level = F.explode(F.sequence(F.lit(0), top)).alias("level")
    slots = often.select("token", level).select("level", F.pmod("token", F.element_at(F.array(*map(F.lit, sizes)), F.col("level") + 1)).alias("slot"))
    parts = slots.groupBy("level", F.expr("slot div 32768").alias("part")).agg(F.expr("bitmap_construct_agg(slot % 32768)").alias("bits")).collect()
    out = [np.zeros(size // 8, np.uint8) for size in sizes]
    for r in parts:
        out[r.level][r.part * 4096 : (r.part + 1) * 4096] = np.frombuffer(r.bits, np.uint8)
    return list(zip(out, sizes, strict=True))


def prefix_pairs(sets: DataFrame, percent: int) -> DataFrame:
    """Pairs ``a, b`` of ``id, root, n, items`` with different roots that may reach the threshold: every pair that does is among them."""
    often = written(sets.select(F.explode("items").alias("token")).groupBy("token").agg(F.count(F.lit(1)).alias("sets")).where("sets > 1"), "often")
    tables = sets.sparkSession.sparkContext.broadcast(frequency_bits(often))
    listed = written(prefixes(sets, tables, percent), "prefixes")
    tables.destroy()
    # a frequent token's longer side is dealt over tasks, its shorter side repeated for each
    wide = written(listed.groupBy("token").agg(F.ceil(F.count(F.lit(1)) / 1000).cast("int").alias("salts")).where("salts > 1"), "wide")
    listed = listed.join(wide, "token", "left").withColumn("salts", F.coalesce("salts", F.lit(1)))
    x = listed.select("token", F.pmod(F.xxhash64("id"), "salts").cast("int").alias("salt"), F.col("id").alias("a"), F.col("root").alias("ra"), F.col("n").alias("na"), F.col("place").alias("pa"))
    short = listed.where(F.expr(f"(n - place) * {100 + percent} >= {2 * percent} * n"))
    y = short.select("token", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"), F.col("id").alias("b"), F.col("root").alias("rb"), F.col("n").alias("nb"), F.col("place").alias("pb"))
    fits = f"ra <> rb and (nb < na or (nb = na and b < a)) and nb * 100 >= {percent} * na and least(na - pa, nb - pb) * {100 + percent} >= {percent} * (na + nb)"
    return x.join(y, ["token", "salt"]).where(fits).select("a", "b").distinct()


def components(edges: DataFrame) -> DataFrame:
    """``id, root`` of every vertex of ``a, b``: smallest reachable id, by minimum labels with pointer jumping over written tables."""
    both = written(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct(), "edges")
    total = both.count()
    label = written(both.groupBy(F.col("a").alias("id")).agg(F.least(F.min("b"), F.col("id")).alias("root"), F.count(F.lit(1)).alias("group_size")), "labels")
    while total:
        near = attach(both.withColumnRenamed("b", "id"), label, "id", total, how="inner").groupBy(F.col("a").alias("id")).agg(F.min("root").alias("near"))
        low = written(label.join(near, "id").select("id", F.least("root", "near").alias("next"), "root", "group_size"), "lower")
        if low.where("next < root").isEmpty():
            break
        sizes = low.groupBy("next").agg(F.count(F.lit(1)).alias("members"))
        ahead = sizes.join(low.select(F.col("id").alias("next"), F.col("next").alias("beyond")), "next", "left")
        jumped = attach(low.select("id", "next", "group_size"), ahead, "next", total, size="members")
        label = written(jumped.select("id", F.least("next", F.coalesce("beyond", "next")).alias("root"), "group_size"), "labels")
    return label.select("id", "root")


def representatives(rows: DataFrame, groups: DataFrame) -> DataFrame:
    """The row of each group of equal sets that stands for it; only rows of groups of several are looked up."""
    several = groups.where("group_size > 1")
    copied = Bits.of(several.select(F.xxhash64("digest").alias("key")), "key", groups.count(), "copied")
    known = copied.mark(rows.where("n > 0").withColumn("key", F.xxhash64("digest")), "key", "maybe").drop("key")
    chosen = known.where("maybe").join(groups.select("row"), "row", "left_semi")
    return known.where("not maybe").unionByName(chosen).drop("maybe", "id").withColumnRenamed("row", "id")


def judged(docs: DataFrame, id_col: str, text_col: str, percent: int) -> DataFrame:
    """``id, tag, stamp, n, component, kept`` of each row."""
    base = tagged(docs.select(F.col(id_col).cast("long").alias("id"), text_of(text_col).alias("text")))
    rows = written(signed(base).withColumn("row", F.monotonically_increasing_id()), "registers")
    total = rows.count()
    first_row = F.min(F.struct(F.col("id").isNull().alias("none"), "id", "row")).alias("first")
    found = rows.where("n > 0").groupBy("digest").agg(first_row, F.count(F.lit(1)).alias("group_size"))
    groups = written(found.select("digest", "group_size", "first.none", F.col("first.id").alias("least_id"), "first.row"), "digests")
    full = representatives(rows, groups)
    spread = full.select("id", F.explode("bands").alias("band"))
    shared = written(spread.groupBy("band").agg(F.count(F.lit(1)).alias("group_size")).where("group_size > 1"), "buckets")
    likely = Bits.of(shared, "band", shared.count(), "bucket_bits").sift(spread, "band")
    member = written(attach(likely, shared, "band", total * BUCKETS // ROWS, how="inner"), "members")
    central = written(member.groupBy("id").agg(F.sum("group_size").alias("score")), "central")
    near = Bits.of(central, "id", total, "member_bits").sift(full.select("id", "n", "codes", "tag", "stamp"), "id")
    known = written(near.join(central, "id"), "contenders")
    needed = Bits.of(known, "tag", total, "wanted").sift(base.select("tag", "stamp", "text"), "tag")
    texts = needed.groupBy("tag", "stamp").agg(F.first("text").alias("text")).join(known.select("id", "tag", "stamp"), ["tag", "stamp"])
    sets = written(sets_of(texts), "sets")
    settle(docs.sparkSession)
    placed = written(member.drop("group_size").join(central, "id"), "placed")
    hubs = placed.groupBy("band").agg(F.max(F.struct("score", "id")).alias("best"), F.count(F.lit(1)).alias("group_size")).select("band", "group_size", F.col("best.id").alias("hub"))
    hubs = written(hubs, "hubs")
    star = attach(placed.select("band", "id"), hubs, "band", total, how="inner").where("id <> hub").select(F.col("id").alias("a"), F.col("hub").alias("b")).distinct()
    links = written(verified(written(estimated(star, known, percent), "pairs"), sets, percent), "links")
    root = written(components(links), "roots")
    settle(docs.sparkSession)
    named = written(placed.select("band", "id").join(root, "id", "left").select("band", "id", F.coalesce("root", "id").alias("root")), "named")
    split_up = named.groupBy("band").agg(F.min("root").alias("low"), F.max("root").alias("high"), F.count(F.lit(1)).alias("group_size")).where("low < high").select("band", "group_size")
    open_rows = attach(named, split_up, "band", total, how="inner").select("id", "root").distinct()
    met = written(prefix_pairs(written(sets.join(open_rows, "id"), "open_sets"), percent), "open_pairs")
    if not met.isEmpty():
        links = links.unionByName(written(verified(met, sets, percent), "links"))
        root = written(components(links), "roots")
    discard(docs.sparkSession, member, placed, named, sets, known)
    settle(docs.sparkSession)
    rooted = groups.join(root.withColumnRenamed("id", "row"), "row", "left").withColumn("root", F.coalesce("root", "row"))
    class_of = rooted.groupBy("root").agg(F.min(F.struct("none", "least_id", "row")).alias("best"), F.count(F.lit(1)).alias("members"))
    named_groups = attach(rooted.select("digest", "group_size", "root"), class_of, "root", total, size="members", how="inner").select("digest", "group_size", F.col("best.least_id").alias("component"), F.col("best.row").alias("chosen"))
    out = attach(rows.where("n > 0").select("id", "tag", "stamp", "n", "digest", "row"), named_groups, "digest", total, how="inner")
    out = out.select("id", "tag", "stamp", "n", "component", (F.col("row") == F.col("chosen")).alias("kept"))
    empty = rows.where("n = 0").select("id", "tag", "stamp", "n", F.col("id").alias("component"), F.lit(True).alias("kept"))
    return out.unionByName(empty)


def classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = 75) -> DataFrame:
    """One row per input row: ``doc_id, n_shingles, component_id, kept``."""
    return judged(docs, id_col, text_col, percent).select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.col("component").alias("component_id"), "kept")


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = 75) -> DataFrame:
    """The rows of ``docs`` that stay, columns as given: one row with the smallest id of each class, and all rows with an empty set."""
    marked = written(judged(docs, id_col, text_col, percent), "judged")
    id_, stamp = F.col(id_col).cast("long"), F.md5(text_of(text_col))
    verdict = marked.groupBy(F.col("tag").alias("key"), F.concat_ws(":", F.col("id").cast("string"), F.lower(F.hex("stamp"))).alias("proof")).agg(F.count_if("kept").alias("stay"), F.count(F.lit(1)).alias("total"))
    return survivors(docs, F.xxhash64(id_, F.unhex(stamp)), F.concat_ws(":", id_.cast("string"), stamp), written(verdict, "verdict"), marked.count())
