"""Tables that an iteration writes once and reads from then on: that cuts the lineage and survives a lost executor."""

from __future__ import annotations

import atexit
import json
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

SETTING = "spark.checkpoint.dir"
_own: list[str] = []


def shared_root(spark: SparkSession) -> str:
    """The folder that the session names; a temporary one only where it names none and runs in one process (tests)."""
    named = spark.conf.get(SETTING, None) or spark.sparkContext.getConf().get(SETTING, None)
    if named:
        return named.rstrip("/")
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise ValueError(f"set {SETTING} to a folder that driver and executors share")
    if not _own:
        _own.append(tempfile.mkdtemp(prefix="rankfeed-"))
        atexit.register(shutil.rmtree, _own[0], ignore_errors=True)
    return _own[0]


def kept(df: DataFrame, label: str = "state", by: str | None = None) -> DataFrame:
    """``df`` computed once, in the shared folder; ``by``: a column whose values become folders, so that a filter on it reads only its own."""
    spark = df.sparkSession
    path = f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"
    writer = df.write if by is None else df.write.partitionBy(by)
    writer.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch = path  # type: ignore[attr-defined]
    return out.select(*df.columns) if by else out


def delete(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def discard(df: DataFrame) -> None:
    """Delete a kept table that no later plan reads."""
    path = getattr(df, "_scratch", None)
    if path:
        delete(df.sparkSession, path)


def save(tables: dict[str, DataFrame], path: str, step: int, **settings) -> None:
    """Tables of a state under a new folder of ``path``, then the manifest that names it: a reader never meets half a state."""
    spark = next(iter(tables.values())).sparkSession
    folder = f"{path}/state-{step}-{uuid.uuid4().hex}"
    for name, t in tables.items():
        t.write.parquet(f"{folder}/{name}")
    manifest = json.dumps({"folder": folder, "step": step, "tables": {n: t.schema.json() for n, t in tables.items()}, "settings": settings})
    spark.createDataFrame([(manifest,)], "manifest string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")


def load(spark: SparkSession, path: str) -> tuple[dict[str, DataFrame], int, dict]:
    """What ``save`` wrote last: tables, step, settings."""
    from pyspark.sql.types import StructType

    m = json.loads(spark.read.text(f"{path}/manifest").first()[0])
    tables = {n: spark.read.schema(StructType.fromJson(json.loads(s))).parquet(f"{m['folder']}/{n}") for n, s in m["tables"].items()}
    return tables, m["step"], m["settings"]
