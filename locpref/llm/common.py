"""Helpers that the operators share: table access, scratch tables, Arrow batches."""

from __future__ import annotations

import contextlib
import ctypes
import os
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space as the contracts define it: space and \x09-\x0D.
ASCII_SPACE = r"[\x20\x09-\x0D]+"

#: Rows, and bytes of strings, that an Arrow function works on at a time, whatever Spark's batch size is.
SLICE_ROWS, SLICE_BYTES = 512, 4_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def checkpoint_root(spark: SparkSession) -> str:
    """The shared folder the cluster names; a folder of our own only where it is unset and all runs on one machine."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        root = f"file://{tempfile.gettempdir()}/checkpoints"
        os.makedirs(root[7:], exist_ok=True)
    return root


class Scratch:
    """Tables written to the shared checkpoint folder to cut lineage between rounds.

    A table stays readable if an executor is lost. ``drop`` removes what no later
    plan reads, ``last`` all but the table it writes; tables behind a returned DataFrame
    stay until the folder is cleaned.
    """

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.root = f"{checkpoint_root(spark)}/{name}-{uuid.uuid4().hex[:12]}"
        self.made: dict[str, str] = {}

    def keep(self, df: DataFrame, name: str) -> DataFrame:
        path = f"{self.root}/{name}"
        df.write.mode("overwrite").parquet(path)
        self.made[name] = path
        return self.spark.read.schema(df.schema).parquet(path)

    def last(self, df: DataFrame, name: str) -> DataFrame:
        out = self.keep(df, name)
        self.drop(*(n for n in list(self.made) if n != name))
        return out

    def drop(self, *names: str) -> None:
        jvm = self.spark._jvm
        for name in names:
            path = jvm.org.apache.hadoop.fs.Path(self.made.pop(name))
            path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


#: Keys that count as hot are at most so many, as each has that part of all rows, and LEAST_HOT rows at least.
MOST_HOT, LEAST_HOT = 10_000, 2_000


def hot_floor(rows: int) -> int:
    """A key with more of the ``rows`` than this is hot; there can't be more than MOST_HOT of them."""
    return max(LEAST_HOT, rows // MOST_HOT)


def met(rows: DataFrame, found: DataFrame, keys: list[str], hot: Column) -> DataFrame:
    """``rows`` joined with ``found`` on ``keys``, unique in it; ``hot`` marks MOST_HOT of its rows at most.

    Rows of hot keys stay where they are: a broadcast meets them. The others are joined.
    """
    if found.where(hot).isEmpty():
        return rows.join(found, keys)
    few = F.broadcast(found.where(hot))  # MOST_HOT rows at most, each of a bounded size
    rest = rows.join(F.broadcast(found.where(hot).select(keys)), keys, "left_anti").join(found.where(~hot), keys)
    return rows.join(few, keys).unionByName(rest)


def slices(batch: pa.RecordBatch, rows: int = SLICE_ROWS) -> Iterator[pa.RecordBatch]:
    """Cuts of ``rows`` rows and SLICE_BYTES bytes at most, or one row."""
    size = np.zeros(batch.num_rows, np.int64)
    for c in batch.columns:
        if pa.types.is_string(c.type) or pa.types.is_binary(c.type):
            size += pc.fill_null(pc.binary_length(c), 0).to_numpy(zero_copy_only=False)
        elif pa.types.is_list(c.type):
            size += 64 * pc.fill_null(pc.list_value_length(c), 0).to_numpy(zero_copy_only=False)
    total, at = np.cumsum(size), 0
    while at < batch.num_rows:
        before = int(total[at - 1]) if at else 0
        cut = min(at + rows, max(at + 1, int(np.searchsorted(total, before + SLICE_BYTES, "right"))))
        yield batch.slice(at, cut - at)
        at = cut


def release() -> None:
    """Give freed memory back: workers live on, and what a task leaves would add up."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def lists_of(column: pa.ListArray, *fields: str) -> tuple[np.ndarray, ...]:
    """Offsets and flat fields of lists of structs, without a Python object for each."""
    return column.offsets.to_numpy(), *(column.values.field(f).to_numpy(zero_copy_only=False) for f in fields)


def arrow_rows(
    each: Callable[[dict[str, list]], dict[str, list]], schema: pa.Schema, slice_rows: int = SLICE_ROWS, raw: bool = False
) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Make a ``mapInArrow`` function from one that maps column lists to column lists.

    Batches are cut into small slices, so memory doesn't follow Spark's batch size. With
    ``raw`` the function gets the slice itself.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, slice_rows):
                out = each(part if raw else part.to_pydict())
                yield pa.RecordBatch.from_arrays(
                    [v if isinstance(v, pa.Array) else pa.array(v, f.type) for f, v in zip(schema, (out[f.name] for f in schema), strict=True)],
                    schema=schema,
                )
        release()

    return run


def crc_mod(col: str, n: int):
    """crc32 of the id as text, modulo n; null ids give null."""
    return F.crc32(F.col(col).cast("string").cast("binary")) % n
