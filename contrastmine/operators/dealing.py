"""Stratified folds, and inner folds of their training parts, of a stored table of any size; the same as folds() and tune() deal.

Rows stay in their files: only eight bytes of hash for each row and dealing are shuffled, and small numbers come back to
the file that asked. Numeric features are replaced by their places among the column's distinct values on the way."""

from __future__ import annotations

from typing import Any

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.parquet as pq
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.scratch import fresh_path, stored

SLICE = "of int, part int, file int, body binary"
TOLD = "of int, part int, file int, n long, body binary"
ROWS_A_FILE = 1_000_000
ROWS_A_RANGE = 400_000
P1, P2, P3, P5 = 0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5


def chained(h: np.ndarray, f: int) -> np.ndarray:
    """Spark's xxhash64(key, f), f an int, from xxhash64(key)."""
    u = np.uint64
    h = h.view(u) + u((P5 + 4) % (1 << 64))
    h ^= u((f % (1 << 32)) * P1 % (1 << 64))
    h = ((h << u(23)) | (h >> u(41))) * u(P2) + u(P3)
    h ^= h >> u(33)
    h *= u(P2)
    h ^= h >> u(29)
    h *= u(P3)
    h ^= h >> u(32)
    return h.view(np.int64)


def opened(path: str):
    """(file system, path) as pyarrow reads them."""
    return fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)


def read_file(path: str, name: str, columns: list[str]) -> pa.Table:
    store, folder = opened(path)
    return pq.read_table(f"{folder}/{name}", filesystem=store, columns=columns, partitioning=None)


def places(h: np.ndarray, y: np.ndarray, ranges: int) -> tuple[np.ndarray, np.ndarray]:
    """(order, sizes): rows by class and range of the hash, and the number of rows of each."""
    part = (y.astype(np.int64) * ranges + (((h >> 54) + 512) * ranges >> 10)).astype(np.uint16)
    return np.argsort(part, kind="stable"), np.bincount(part, minlength=2 * ranges)


def slices(h, y, ranges: int, of: int, file: int) -> pd.DataFrame:
    order, sizes = places(h, y, ranges)
    h, ends = h[order], np.cumsum(sizes)
    return pd.DataFrame([(of, int(p), file, h[ends[p] - sizes[p] : ends[p]].tobytes()) for p in np.flatnonzero(sizes)], columns=["of", "part", "file", "body"])


def answers(frame: pd.DataFrame, of: int, h, y, ranges: int, before: dict, k: int) -> np.ndarray:
    """The rank of each row within its class, modulo k, from the ranks within ranges; before: the number of rows in the ranges before, modulo k."""
    order, sizes = places(h, y, ranges)
    own = frame[frame["of"] == of].sort_values("part")
    got = np.concatenate([np.zeros(0, np.uint8), *(np.frombuffer(b, np.uint8) for b in own["body"])])
    out = np.empty(len(h), np.uint8)
    out[order] = (got + np.repeat([before.get((of, p), 0) for p in range(2 * ranges)], sizes)) % k
    return out


def ranked(frame: pd.DataFrame, k: int) -> pd.DataFrame:
    """The ranks of hashes among those of all files, modulo k."""
    bodies = [np.frombuffer(b, np.int64) for b in frame["body"]]
    h = np.concatenate(bodies)
    rank = np.empty(len(h), np.uint8)
    rank[np.argsort(h, kind="stable")] = np.arange(len(h)) % k
    told = np.split(rank, np.cumsum([len(b) for b in bodies])[:-1])
    return frame.assign(n=[len(b) for b in bodies], body=[t.tobytes() for t in told])[["of", "part", "file", "n", "body"]]


def ranges_before(told: DataFrame, ranges: int, k: int) -> dict:
    """For each dealing, class and range the number of rows in the ranges before, modulo k."""
    sizes = {(r.of, r.part): r.n for r in told.groupBy("of", "part").agg(F.sum("n").alias("n")).collect()}  # at most 2,048 rows a dealing
    out = {}
    for of in {o for o, _ in sizes}:
        for y in (0, 1):
            sum_ = 0
            for p in range(y * ranges, (y + 1) * ranges):
                out[of, p] = sum_ % k
                sum_ += sizes.get((of, p), 0)
    return out


def distinct_values(path: str, k: int) -> np.ndarray:
    """The ascending distinct values of a column; one NaN, the last, for all missing ones."""
    store, folder = opened(path)
    return np.unique(pq.read_table(folder, filesystem=store, columns=["value"], filters=[("k", "=", k)], partitioning=None)["value"].to_numpy().astype(float))


def list_values(table: DataFrame, n_features: int) -> str:
    """Where the distinct values of all columns are written: (k, value)."""
    path = fresh_path(table.sparkSession, "values")
    cells = F.explode(F.array(*(F.struct(F.lit(k).alias("k"), F.col(f"_f{k}").cast("double").alias("value")) for k in range(n_features))))
    table.select(cells.alias("x")).select("x.*").distinct().write.option("compression", "zstd").parquet(path)
    return path


def in_files(codes: DataFrame, values: str) -> tuple[DataFrame, str, list[str]]:
    """Writes the codes to files of a bounded number of rows, which are read one at a time."""
    spark, path = codes.sparkSession, fresh_path(codes.sparkSession, "codes")
    codes.write.option("compression", "zstd").option("maxRecordsPerFile", ROWS_A_FILE).parquet(path)
    table = spark.read.schema(codes.schema).parquet(path)
    return table, values, sorted(f.rpartition("/")[2] for f in table.inputFiles())


def coded_schema(n_features: int, folds: int, inner_folds: int) -> str:
    return ", ".join(["y byte", "fold byte", *(f"_in{f} byte" for f in range(folds if inner_folds else 0)), *(f"_f{k} int" for k in range(n_features))])


def coded(dealt: DataFrame, n_features: int, folds: int, inner_folds: int) -> tuple[DataFrame, str, list[str]]:
    """What deal() gives, for a table that has its folds."""
    values = list_values(dealt, n_features)
    schema = coded_schema(n_features, folds, inner_folds)
    kept = dealt.select(*(F.coalesce(c, F.lit(-1)).cast("byte").alias(c) for c in ("y", "fold", *(f"_in{f}" for f in range(folds if inner_folds else 0)))), *(F.col(f"_f{k}").cast("double").alias(f"_f{k}") for k in range(n_features)))

    def work(batches):
        known = [distinct_values(values, k) for k in range(n_features)]
        for b in batches:
            places = [np.searchsorted(v, b.column(f"_f{k}").to_numpy(zero_copy_only=False).astype(float)).astype(np.int32) for k, v in enumerate(known)]
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in range(b.num_columns - n_features)), *map(pa.array, places)], b.schema.names)

    return in_files(kept.mapInArrow(work, schema), values)


def deal(slim: DataFrame, n_features: int, folds: int, inner_folds: int) -> tuple[DataFrame, str, list[str]]:
    """(codes, values, files) of (key, y, _f0, _f1, ...): a table with y, fold, the inner folds _in0, _in1, ... (-1 in the test part; none for inner_folds=0) and each feature's place among its distinct values; where those are stored; the names of the table's files."""
    spark: SparkSession = slim.sparkSession
    path = fresh_path(spark, "features")
    features = [f"_f{k}" for k in range(n_features)]
    slim.select(F.xxhash64("key").alias("h"), F.col("y").cast("byte").alias("y"), *features).write.option("compression", "zstd").option("maxRecordsPerFile", ROWS_A_FILE).parquet(path)
    table = spark.read.parquet(path)
    values = list_values(table, n_features)
    files = sorted(f.rpartition("/")[2] for f in table.inputFiles())
    ranges = min(1024, max(1, table.count() // ROWS_A_RANGE))
    by_file = lambda df: df.repartition(max(1, len(files)), "file").groupBy("file")  # a few numbers ask for a file of rows: a task each
    keys = lambda name: (lambda t: (t["h"].to_numpy(), t["y"].to_numpy()))(read_file(path, name, ["h", "y"]))

    def first(frames):
        for frame in frames:
            for i in frame["id"]:
                h, y = keys(files[i])
                yield slices(chained(h, 0), y, ranges, -1, int(i))

    outer = stored(spark.range(0, len(files), 1, max(1, len(files))).mapInPandas(first, SLICE).groupBy("of", "part").applyInPandas(lambda frame: ranked(frame, folds), TOLD), "folds")
    before = ranges_before(outer, ranges, folds)

    def second(key: tuple[Any, ...], frame: pd.DataFrame) -> pd.DataFrame:
        i = int(key[0])
        h, y = keys(files[i])
        fold = answers(frame, -1, chained(h, 0), y, ranges, before, folds)
        return pd.concat([slices(chained(h[fold != f], f), y[fold != f], ranges, f, i) for f in range(folds)])

    told, within = outer, {}
    if inner_folds:
        inner = stored(by_file(outer).applyInPandas(second, SLICE).groupBy("of", "part").applyInPandas(lambda frame: ranked(frame, inner_folds), TOLD), "folds")
        told, within = outer.unionByName(inner), ranges_before(inner, ranges, inner_folds)

    def last(key: tuple[pa.Scalar, ...], held: pa.Table) -> pa.Table:
        i, frame = key[0].as_py(), held.to_pandas()
        h, y = keys(files[i])
        fold = answers(frame, -1, chained(h, 0), y, ranges, before, folds)
        out = {"y": y.astype(np.int8), "fold": fold.astype(np.int8)}
        for f in range(folds if inner_folds else 0):
            out[f"_in{f}"] = np.full(len(y), -1, np.int8)
            out[f"_in{f}"][fold != f] = answers(frame, f, chained(h[fold != f], f), y[fold != f], ranges, within, inner_folds)
        for k, c in enumerate(features):
            out[c] = np.searchsorted(distinct_values(values, k), read_file(path, files[i], [c])[c].to_numpy()).astype(np.int32)
        return pa.table(out)

    return in_files(by_file(told).applyInArrow(last, coded_schema(n_features, folds, inner_folds)), values)
