"""Exact duplicate removal with a heavy-hitter split; DataFrame functions only.

Texts are equal when identical after lower-casing A-Z. A digest table (row id, SHA-256) is written once, so later
shuffles move digests and ids, never texts.

1. A mergeable frequent-items sketch of the Misra-Gries family (``approx_top_k_*``) runs over the digests, merged in a
   two-level tree, and names at most ``winners`` candidates.
2. Their exact counts and largest ids come from one aggregation over a broadcast semi join; the verified rows number
   at most ``winners``, whatever the input, so they are broadcast and resolve the hot digests map-side, unshuffled.
3. All other digests take the ordinary road: one exchange by digest and a window in it. A group there is smaller than
   the sketch's error bound, so no task meets a hot key.

Defined cases: a null text equals an empty one. The row with the largest id stays; a null id ranks below all others.
Rows repeated in full, or with equal id and text, leave exactly one row. An empty table gives an empty result. Other
columns are ignored by ``assign`` and carried untouched by ``drop_duplicates``, whatever their names.
"""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .runtime import survivors, text_of, written

FAN_IN = 64


def fold_ascii(text: Column) -> Column:
    """Lower-case A-Z and nothing else; texts of one byte a character take the fast path."""
    plain = F.octet_length(text) == F.char_length(text)
    return F.when(plain, F.lower(text)).otherwise(F.translate(text, string.ascii_uppercase, string.ascii_lowercase))


def digest(text: Column) -> Column:
    return F.sha2(fold_ascii(text), 256)


def frequent(digests: DataFrame, winners: int, tracked: int) -> DataFrame:
    """Candidates of the sketch: at most ``winners`` rows (``digest``)."""
    partial = digests.groupBy(F.pmod(F.col("uid"), F.lit(FAN_IN)).alias("part")).agg(F.expr(f"approx_top_k_accumulate(digest, {tracked})").alias("sketch"))
    merged = partial.groupBy(F.lit(1)).agg(F.expr(f"approx_top_k_combine(sketch, {tracked})").alias("sketch"))
    return merged.select(F.explode(F.expr(f"approx_top_k_estimate(sketch, {winners})")).alias("hit")).where("hit.count > 1").select(F.col("hit.item").alias("digest"))


def assign(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", winners: int = 1000, tracked: int = 65536) -> DataFrame:
    """One row per input row: ``doc_id, keep_id, group_size, kept, text_sha256``."""
    rows = written(docs.select(F.col(id_col).alias("doc_id"), digest(text_of(text_col)).alias("digest"), F.monotonically_increasing_id().alias("uid")), "digests")
    best, size = F.max(F.struct("doc_id", "uid")), F.count(F.lit(1))
    top = written(rows.join(F.broadcast(frequent(rows, winners, tracked)), "digest", "left_semi").groupBy("digest").agg(best.alias("best"), size.alias("group_size")), "winners")
    known = rows.join(F.broadcast(top), "digest", "left")
    of_digest = Window.partitionBy("digest")
    rest = known.where("group_size is null").select("doc_id", "digest", "uid").withColumns({"best": best.over(of_digest), "group_size": size.over(of_digest)})
    hot = known.where("group_size is not null").select(*rest.columns)
    return hot.unionByName(rest).select(
        "doc_id", F.col("best.doc_id").alias("keep_id"), "group_size", (F.col("best.uid") == F.col("uid")).alias("kept"), F.col("digest").alias("text_sha256")
    )


def drop_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of ``docs`` that stay, columns as given; decided on ids and digests, then one pass over the texts.

    Of rows with equal id and equal text any one stays.
    """
    kept = written(assign(docs, id_col, text_col, **options).select("doc_id", F.col("text_sha256").alias("digest"), "kept"), "kept")
    key, proof = (lambda id_, d: (F.xxhash64(id_, d), F.concat_ws(":", id_.cast("string"), d)))(F.col("doc_id"), F.col("digest"))
    verdict = kept.select(key.alias("key"), proof.alias("proof"), "kept").groupBy("key", "proof").agg(F.count_if("kept").alias("stay"), F.count(F.lit(1)).alias("total"))
    own = digest(text_of(text_col))
    return survivors(docs, F.xxhash64(F.col(id_col), own), F.concat_ws(":", F.col(id_col).cast("string"), own), written(verdict, "verdict"), kept.count())


ORACLE = f"""
with t as (select doc_id, sha256(translate(coalesce(text, ''), '{string.ascii_uppercase}', '{string.ascii_lowercase}')) as h from documents),
g as (select h, max(doc_id) as keep_id, cast(count(*) as bigint) as group_size from t group by h)
select doc_id, keep_id, group_size, doc_id = keep_id as kept, h as text_sha256 from t join g using (h)
"""
