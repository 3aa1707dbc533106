"""Intermediate tables in the folder that driver and executors share, and their removal."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_MADE: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir. Where it is unset, a temporary one, but only if driver and executors are one process; else an error."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        found = tempfile.mkdtemp(prefix="contrastmine-")
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def fresh_path(spark: SparkSession, label: str) -> str:
    """A new path in the shared folder; clear_scratch() removes what was written there."""
    _MADE.append(f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}")
    return _MADE[-1]


def scratch_mark() -> int:
    """A point in the list of intermediate paths, for clear_scratch()."""
    return len(_MADE)


def clear_scratch(spark: SparkSession, since: int = 0, keep: tuple[str, ...] = ()) -> int:
    """Delete the intermediate tables made after a mark, but for those to keep; tables that are still to be read must be kept."""
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    gone = [p for p in _MADE[since:] if p not in keep]
    for p in gone:
        path = jvm.org.apache.hadoop.fs.Path(p)
        path.getFileSystem(conf).delete(path, True)
    _MADE[since:] = [p for p in _MADE[since:] if p in keep]
    return len(gone)


def stored(df: DataFrame, label: str, files: int | None = None) -> DataFrame:
    """Write a table to the shared folder as compressed Parquet and read it back: its lineage ends, and its size is known to the planner.

    files: deal a result that is known to be small over so many files first."""
    path = fresh_path(df.sparkSession, label)
    (df if files is None else df.repartition(files)).write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def settled(df: DataFrame, label: str, most: int = 50_000) -> DataFrame:
    """A result computed once: on the driver while it has at most `most` rows, beyond that as a table in the shared folder."""
    kept = df.persist()
    rows = kept.limit(most + 1).collect()
    out = df.sparkSession.createDataFrame(rows, df.schema) if len(rows) <= most else stored(kept, label)
    kept.unpersist()
    return out
