"""Sources and sinks: tables, transaction files, libsvm, pattern, item and block stores, and a data source for transaction files."""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_any(spark: SparkSession, form: str, path: str, schema=None, **options) -> DataFrame:
    reader = spark.read.format(form).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def write_any(df: DataFrame, form: str, path: str, mode: str = "errorifexists", **options) -> None:
    df.write.format(form).mode(mode).options(**options).save(path)


def read_transactions(spark: SparkSession, path: str, sep: str = " ") -> DataFrame:
    """One row of item ids a line -> items array<int>, sorted and distinct; empty lines are empty rows."""
    ids = F.filter(F.split(F.trim("value"), sep), lambda x: x != "")
    return spark.read.text(path).select(F.array_sort(F.array_distinct(F.transform(ids, lambda x: x.cast("int")))).alias("items"))


def write_transactions(df: DataFrame, path: str, sep: str = " ") -> None:
    df.select(F.array_join(F.transform("items", lambda i: i.cast("string")), sep).alias("value")).write.text(path)


def read_libsvm(spark: SparkSession, path: str) -> DataFrame:
    """Sparse matrix text (label index:value ...) -> label int, items array<int> of the indices with a value."""
    parts = F.split(F.trim("value"), r"\s+")
    pairs = F.filter(F.transform(F.slice(parts, 2, F.greatest(F.size(parts) - 1, F.lit(0))), lambda x: F.split(x, ":")), lambda x: F.get(x, F.lit(1)).cast("double") != 0)
    return spark.read.text(path).where(F.trim("value") != "").select(F.get(parts, F.lit(0)).cast("double").cast("int").alias("label"), F.array_sort(F.transform(pairs, lambda x: F.get(x, F.lit(0)).cast("int"))).alias("items"))


def write_patterns(patterns: DataFrame, path: str, run_id: str) -> None:
    patterns.withColumn("run_id", F.lit(run_id)).write.mode("append").partitionBy("run_id").parquet(path)


def read_patterns(spark: SparkSession, path: str, run_id: str | None = None) -> DataFrame:
    found = spark.read.parquet(path)
    return found if run_id is None else found.where(F.col("run_id") == run_id)


def catalogue_hash(names) -> str:
    """Names the alphabet, so that patterns are applied to no other."""
    return hashlib.sha256("\n".join(names).encode()).hexdigest()[:16]


def write_items(spark: SparkSession, names, path: str) -> str:
    tag = catalogue_hash(names)
    spark.createDataFrame([(k, n, tag) for k, n in enumerate(names)], "item_id int, label string, catalogue string").write.mode("overwrite").parquet(path)
    return tag


def read_items(spark: SparkSession, path: str) -> tuple[tuple[str, ...], str]:
    rows = sorted(spark.read.parquet(path).collect())  # one row per item
    return tuple(r.label for r in rows), rows[0].catalogue if rows else catalogue_hash(())


def write_blocks(blocks: DataFrame, path: str) -> None:
    blocks.write.mode("overwrite").option("parquet.block.size", str(64 << 20)).parquet(path)


def read_blocks(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


class ByteRange(InputPartition):
    def __init__(self, path: str, begin: int, end: int):
        self.path, self.begin, self.end = path, begin, end


class TransactionReader(DataSourceReader):
    """Reads lines by byte ranges: a range owns the lines that begin in it."""

    def __init__(self, options):
        self.path, self.size = options["path"], int(options.get("rangebytes", str(32 << 20)))

    def _open(self):
        from pyarrow import fs

        return fs.FileSystem.from_uri(self.path) if "://" in self.path or self.path.startswith("file:") else (fs.LocalFileSystem(), self.path)

    def partitions(self):
        store, path = self._open()
        size = store.get_file_info(path).size
        return [ByteRange(self.path, a, min(size, a + self.size)) for a in range(0, size, self.size)]

    def read(self, partition):
        store, path = self._open()
        with store.open_input_file(path) as f:
            at = partition.begin
            tail = b""
            if at:
                f.seek(at - 1)
                skipped = f.read(1)
                while skipped and b"\n" not in skipped:  # the line before owns these bytes
                    skipped = f.read(4096)
                    at += len(skipped)
                    if b"\n" in skipped:
                        k = skipped.index(b"\n") + 1
                        at -= len(skipped) - k
                f.seek(at)
            while at < partition.end:
                chunk = f.read(1 << 16)
                if not chunk:
                    if tail:
                        yield (sorted({int(x) for x in tail.split()}),)
                    return
                lines = (tail + chunk).split(b"\n")
                tail = lines.pop()
                for line in lines:
                    yield (sorted({int(x) for x in line.split()}),)
                    at += len(line) + 1
                    if at >= partition.end:
                        return


class TransactionDataSource(DataSource):
    """spark.dataSource.register(TransactionDataSource); spark.read.format("transactions").option("rangebytes", n).load(path)"""

    @classmethod
    def name(cls):
        return "transactions"

    def schema(self):
        return "items array<int>"

    def reader(self, schema):
        return TransactionReader(self.options)
