"""Packing by power-of-two decomposition.

A document of n tokens is cut by the binary digits of n: as many pieces of the
longest length as fit, then one piece for each lower power of two in the rest, the
longest first. Equal lengths form a bucket; each piece is a sequence of its own, so
no sequence crosses documents and none needs padding. ``write_buckets`` lays the pieces
out by bucket, and ``read_bucket`` reads one length without touching the others.

Defined cases: a null text counts as empty and still gets its end token; repeated
rows are packed each on its own; other columns are ignored. ``sequence_id`` is the
number of the input partition in the upper bits and a running number in the lower
ones, the same when a task is run again.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import release, slices
from .vocab import byte_vocabulary

PIECES = "doc_id long, start long, length long, tokens binary, doc_tokens long, sequence_id long, offset long"


def binary_lengths(n: int, longest: int) -> list[int]:
    """Powers of two that sum to n, none above ``longest`` (itself a power of two)."""
    rest = n % longest
    return [longest] * (n // longest) + [1 << b for b in range(rest.bit_length() - 1, -1, -1) if rest >> b & 1]


def pack(docs: DataFrame, json_path: str, ranks_path: str, pattern: str, longest: int = 1024, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece; ``tokens`` holds its ids as little-endian uint32; the bucket is ``length``."""
    if longest < 1 or longest & (longest - 1):
        raise ValueError("longest must be a power of two")
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    schema = pa.schema([(c, pa.binary() if c == "tokens" else pa.int64()) for c in ("doc_id", "start", "length", "tokens", "doc_tokens", "sequence_id", "offset")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = byte_vocabulary(json_path, ranks_path, pattern)
        sequence = TaskContext.get().partitionId() << 40
        for batch in batches:
            for cut in map(pa.RecordBatch.to_pydict, slices(batch)):
                ids_of, starts, lengths, tokens, totals = [], [], [], [], []
                for doc, text in zip(cut["doc_id"], cut["text"], strict=True):
                    raw = np.append(v.ids(text), end_id).astype("<u4").tobytes()
                    n, begin = len(raw) // 4, 0
                    for length in binary_lengths(n, longest):
                        ids_of.append(doc)
                        starts.append(begin)
                        lengths.append(length)
                        totals.append(n)
                        tokens.append(raw[4 * begin : 4 * (begin + length)])
                        begin += length
                k = len(starts)
                yield pa.RecordBatch.from_arrays([pa.array(x, f.type) for f, x in zip(schema, (ids_of, starts, lengths, tokens, totals, np.arange(sequence, sequence + k), np.zeros(k, np.int64)), strict=True)], schema=schema)
                sequence += k
        release()

    return src.mapInArrow(run, PIECES)


def write_buckets(pieces: DataFrame, path: str) -> None:
    """The pieces by length, a folder for each bucket; a task adds its own file to every bucket, so no length is dealt to one task."""
    pieces.withColumn("bucket", F.col("length")).write.mode("overwrite").partitionBy("bucket").parquet(path)


def read_bucket(spark: SparkSession, path: str, length: int) -> DataFrame:
    """Pieces of one length: batches of them stack without padding."""
    return spark.read.parquet(path).where(F.col("bucket") == length).drop("bucket")


def bucket_sizes(pieces: DataFrame) -> DataFrame:
    """``length, sequences, tokens`` of every bucket."""
    return pieces.groupBy("length").agg(F.count("*").alias("sequences"), F.sum("length").alias("tokens"))
