"""Shared ground of the operators: scratch tables, sizes, and column hygiene.

Scratch tables live under the folder that the session names in ``spark.checkpoint.dir``. Writing one and reading it
again cuts the lineage, survives a lost executor, and lets two branches of a plan share one expensive pass.
"""

from __future__ import annotations

import atexit
import contextlib
import gc
import shutil
import tempfile
import uuid
from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SETTING = "spark.checkpoint.dir"
BATCH_SETTING = "spark.sql.execution.arrow.maxRecordsPerBatch"
BATCH_ROWS = 2000
_own: list[str] = []


def scratch_root(spark: SparkSession) -> str:
    """The shared folder of the session; a temporary one only where the session names none and runs in one process (tests)."""
    root = spark.conf.get(SETTING, None) or spark.sparkContext.getConf().get(SETTING, None)
    if root:
        return root.rstrip("/")
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise ValueError(f"set {SETTING} to a folder that driver and executors share")
    if not _own:
        _own.append(tempfile.mkdtemp(prefix="rankfeed-"))
        atexit.register(shutil.rmtree, _own[0], ignore_errors=True)
    return _own[0]


def scratch_path(spark: SparkSession, label: str) -> str:
    return f"{scratch_root(spark)}/{label}-{uuid.uuid4().hex}"


@contextlib.contextmanager
def small_batches(spark: SparkSession) -> Iterator[None]:
    """Plans that run meanwhile hand rows to Python workers in batches of ``BATCH_ROWS``, which both sides hold at once; the session's setting comes back."""
    before = spark.conf.get(BATCH_SETTING)
    if 0 < int(before) <= BATCH_ROWS:
        yield
        return
    spark.conf.set(BATCH_SETTING, BATCH_ROWS)
    try:
        yield
    finally:
        spark.conf.set(BATCH_SETTING, before)


def written(df: DataFrame, label: str, codec: str = "zstd") -> DataFrame:
    """``df`` as a scratch table: written once, read from then on."""
    spark = df.sparkSession
    path = scratch_path(spark, label)
    with small_batches(spark):
        df.write.option("compression", codec).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch = path  # type: ignore[attr-defined]
    return out


def discard(spark: SparkSession, *tables: DataFrame | str) -> None:
    """Delete scratch tables that no later plan reads."""
    for t in tables:
        path = t if isinstance(t, str) else getattr(t, "_scratch", None)
        if path:
            where = spark._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def settle(spark: SparkSession) -> None:
    """Between phases of a long query: the driver's garbage goes, with it the broadcast tables and shuffle files of plans that are done, and its heap shrinks."""
    gc.collect()
    spark._jvm.System.gc()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return ship(spark).read.parquet(f"{sf_dir}/{name}.parquet")


def text_of(column: str) -> Column:
    """A text column with null read as empty."""
    return F.coalesce(F.col(column), F.lit(""))


def attach(rows: DataFrame, groups: DataFrame, key: str | list[str], total: int, size: str = "group_size", how: str = "left", share: int = 1000) -> DataFrame:
    """``rows`` joined to one row per group; groups above ``total / share`` rows, fewer than ``share`` of them, go by broadcast.

    So no shuffled key of ``rows`` holds more than a thousandth of all rows.
    """
    most = max(1000, total // share)
    (mark,) = fresh(rows, "in_hot_group")
    hot = groups.where(F.col(size) > most).withColumn(mark, F.lit(True))
    marked = rows.join(F.broadcast(hot), key, "left")
    big = marked.where(F.col(mark)).drop(mark)
    rest = marked.where(F.col(mark).isNull()).select(*[F.col(f"`{c}`") for c in rows.columns]).join(groups.where(F.col(size) <= most), key, how)
    return big.select(*[F.col(f"`{c}`") for c in rest.columns]).unionByName(rest)


def fresh(df: DataFrame, *names: str) -> list[str]:
    """Column names like ``names`` that ``df`` does not have, in any case."""
    taken = {c.lower() for c in df.columns}
    out = []
    for n in names:
        while n.lower() in taken:
            n += "_"
        taken.add(n.lower())
        out.append(n)
    return out


MOST_BITS = 1 << 27
PIECE = 1 << 10  # bits of one broadcast row


def bits_for(rows: int) -> int:
    """Bits of a table for so many keys: a power of two, 32 a key as long as that is below the limit."""
    size = 1 << 15
    while size < min(32 * rows, MOST_BITS):
        size *= 2
    return size


@dataclass(frozen=True)
class Bits:
    """One bit for each hashed key: a key that was put in is always found, another one seldom. At most ``MOST_BITS`` (16 MB), whatever the input."""

    pieces: DataFrame
    size: int

    @classmethod
    def of(cls, keys: DataFrame, key: str, rows: int, label: str) -> Bits:
        """The long column ``key`` of about ``rows`` rows: one aggregation, no key is shuffled."""
        size = bits_for(rows)
        slot = keys.where(F.col(key).isNotNull()).select(F.pmod(F.col(key), F.lit(size)).alias("slot"))
        whole = slot.groupBy(F.expr("slot div 32768").alias("part")).agg(F.expr("bitmap_construct_agg(slot % 32768)").alias("bits"))
        each = whole.select("part", F.explode(F.sequence(F.lit(0), F.lit(32768 // PIECE - 1))).alias("k"), "bits")
        cut = each.select((F.col("part") * (32768 // PIECE) + F.col("k")).alias("part"), F.expr(f"substring(bits, k * {PIECE // 8} + 1, {PIECE // 8})").alias("bits"))
        return cls(written(cut, label), size)

    def mark(self, df: DataFrame, key: str, name: str) -> DataFrame:
        """``df`` with a boolean column: false for a key that was not put in (and null), true for every one that was and few others."""
        part, bits = fresh(df, "bit_part", "bit_values")
        slot = F.pmod(F.col(key), F.lit(self.size))
        with_part = df.withColumn(part, F.floor(slot / PIECE))
        joined = with_part.join(F.broadcast(self.pieces.withColumnsRenamed({"part": part, "bits": bits})), part, "left")
        place = f"pmod(`{key}`, {self.size}L) % {PIECE}"
        hit = F.expr(f"(shiftright(cast(conv(hex(substring(`{bits}`, cast(({place}) div 8 as int) + 1, 1)), 16, 10) as int), cast(({place}) % 8 as int)) & 1) = 1")
        return joined.select(*[F.col(f"`{c}`") for c in df.columns], F.coalesce(hit, F.lit(False)).alias(name))

    def sift(self, df: DataFrame, key: str) -> DataFrame:
        """The rows whose key may have been put in; they pass unshuffled."""
        (name,) = fresh(df, "bit_found")
        return self.mark(df, key, name).where(F.col(name)).select(*[F.col(f"`{c}`") for c in df.columns])


def survivors(docs: DataFrame, key: Column, proof: Column, verdict: DataFrame, rows: int) -> DataFrame:
    """The rows of ``docs`` that stay, columns as given. ``verdict``: ``key, proof, stay, total`` of each pair of key (long) and proof.

    Of the ``total`` rows with a key and proof all, none, or one of equal ones stay. Bits of the keys that stay and of those that lose a row decide
    most rows in one pass over the texts, unshuffled; only rows that are in both (and the filter's few errors) meet their verdict in a join.
    """
    k, p, keeps, loses = fresh(docs, "row_key", "row_proof", "row_keeps", "row_loses")
    own = [F.col(f"`{c}`") for c in docs.columns]
    kept = Bits.of(verdict.where("stay > 0"), "key", rows, "kept_bits")
    lost = Bits.of(verdict.where("stay < total"), "key", rows, "lost_bits")
    known = lost.mark(kept.sift(docs.withColumns({k: key, p: proof}), k), k, loses)
    sure = known.where(~F.col(loses)).select(*own)
    (stay, total) = fresh(known, "row_stay", "row_total")
    told = verdict.where("stay > 0").withColumnsRenamed({"key": k, "proof": p, "stay": stay, "total": total})
    open_rows = attach(known.where(F.col(loses)), told, [k, p], rows, size=total, how="inner")
    all_stay = open_rows.where(F.col(stay) == F.col(total)).select(*own)
    one = open_rows.where(F.col(stay) < F.col(total)).groupBy(k, p).agg(F.first(F.struct(*own)).alias(keeps)).select(f"{keeps}.*")
    return sure.unionByName(all_stay).unionByName(one)


def ship(spark: SparkSession) -> SparkSession:
    """Make the package importable in Python workers that do not have it on their path; once for each session."""
    import pathlib
    import zipfile

    context = spark.sparkContext
    if getattr(context, "_rankfeed_shipped", False):
        return spark
    package = pathlib.Path(__file__).resolve().parents[1]
    archive = pathlib.Path(tempfile.mkdtemp(prefix="rankfeed-code-")) / "rankfeed.zip"
    with zipfile.ZipFile(archive, "w") as z:
        for source in sorted(package.rglob("*.py")):
            z.write(source, source.relative_to(package.parent))
    context.addPyFile(str(archive))
    context._rankfeed_shipped = True
    return spark
