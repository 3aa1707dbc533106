"""Table access, the shared folder and helpers that every operator of this subpackage uses."""

from __future__ import annotations

import sys
import types

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.scratch import clear_scratch, fresh_path, scratch_mark, shared_dir, stored

__all__ = ["clear_scratch", "fresh_path", "scratch_mark", "shared_dir", "stored"]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def clean_text(column: str | Column = "text") -> Column:
    return F.coalesce(F.col(column) if isinstance(column, str) else column, F.lit(""))


def held_out(doc_id: str | Column = "doc_id") -> Column:
    """crc32 of the id as text, modulo 4, is 2; a null id is never held out."""
    c = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return F.coalesce(F.crc32(c.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def drawn_share(share: float, *columns: str) -> Column:
    """True for about this share of rows, by a hash of the columns: the same rows in every run."""
    return F.pmod(F.xxhash64(*columns, F.lit("drawn")), F.lit(1 << 30)) < int(share * (1 << 30))


def worker_batches(spark: SparkSession, rows: int = 2000) -> None:
    """Let texts go to Python workers in batches of at most so many rows, which bounds the buffers beside the heap.

    A setting of the session, so a choice for applications: the driver's queries and the pipeline make it, operators do not."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= rows:
        spark.conf.set(key, rows)


def spare(columns, *names: str) -> list[str]:
    """The names, lengthened until none is a column already, whatever its case."""
    taken = {c.lower() for c in columns}
    out = []
    for n in names:
        while n.lower() in taken:
            n += "_"
        taken.add(n.lower())
        out.append(n)
    return out


def files_for(rows: int, per_file: int = 100_000, most_rows: int = 5_000_000) -> int | None:
    """Files for a table of so many short rows: few for a small one, and its own partitions (None) for a large one."""
    return None if rows > most_rows else max(1, -(-rows // per_file))


def join_by_size(left: DataFrame, right: DataFrame, key: str, rows: str, total: int, most: int = 10_000) -> DataFrame:
    """Inner join with a table of one row a key, that knows in column `rows` how many rows of `left` have the key; `total` is their sum.

    Keys with more than total / most rows are less than `most`, so theirs are joined by broadcast and no task gathers
    them; all others meet in a shuffle. Both sides should be stored, as each is read twice."""
    bound = max(1000, total // most)
    hot, cold = right.where(F.col(rows) > bound), right.where(F.coalesce(F.col(rows), F.lit(0)) <= bound)
    if not hot.limit(1).count():
        return left.join(cold, key)
    return left.join(F.broadcast(hot), key).unionByName(left.join(F.broadcast(hot.select(key)), key, "left_anti").join(cold, key))


def worker_state(name: str) -> dict:
    """A dictionary that lives as long as the Python worker, across its tasks; asking for one drops those of other names."""
    holder = sys.modules.setdefault("_contrastmine_worker_state", types.ModuleType("_contrastmine_worker_state"))
    kept = holder.__dict__.setdefault("kept", {})
    if name not in kept:
        kept.clear()
        kept[name] = {}
    return kept[name]


def tidy(work, rows: int = 2000):
    """The same map over batches, which come in slices of at most so many rows, and which hands free memory back to the machine when its task ends."""

    def slices(frames):
        for f in frames:
            n = len(f) if hasattr(f, "iloc") else f.num_rows
            for a in range(0, n, rows):
                yield f.iloc[a : a + rows] if hasattr(f, "iloc") else f.slice(a, rows)

    def run(frames):
        yield from work(slices(frames))
        import ctypes

        import pyarrow as pa

        pa.default_memory_pool().release_unused()
        trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
        if trim:
            trim(0)

    return run


def file_system(path: str):
    """File system and path inside it for a URI or a plain path."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)


def to_frame(rows: list[tuple], schema: str):
    """A pandas frame for rows of a DDL schema; whole numbers keep their nulls and all their digits."""
    import pandas as pd

    names = [c.split() for c in schema.split(", ")]
    columns = list(zip(*rows, strict=True)) if rows else [()] * len(names)
    typed = lambda c, kind: pd.array(list(c), "Int64") if kind in ("long", "int") else pd.Series(list(c), dtype=object if kind in ("string", "binary") or "<" in kind else None)
    return pd.DataFrame({n: typed(c, kind) for (n, kind), c in zip(names, columns, strict=True)})


def whole(series) -> list:
    """Whole numbers or None, from a pandas column of them."""
    return [int(x) if x is not None and x == x else None for x in series.astype(object).where(series.notna(), None)]
