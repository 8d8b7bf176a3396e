"""Helpers shared by the training-data operators."""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from comotion.components import cut  # noqa: F401

_libc = ctypes.CDLL(None)
#: Word separators of every contract in this package: space and the controls 9 to 13.
WORD_GAP = r"[\x20\x09-\x0D]+"
#: Python work is cut into slices of about this many text bytes, so that memory does not follow the batch size.
SLICE_BYTES = 4 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def doc_text(docs: DataFrame) -> DataFrame:
    """Only the two columns an operator reads; other columns, whatever their names, never reach it."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def small_table(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    """A few rows of the driver's as a table; by Arrow, so that no Python worker starts for them."""
    kinds = {"long": pa.int64(), "bigint": pa.int64(), "int": pa.int32(), "string": pa.string()}
    fields = [f.split() for f in schema.split(", ")]
    return spark.createDataFrame(pa.table([pa.array(c, kinds[k]) for c, (_, k) in zip(zip(*rows) if rows else [[]] * len(fields), fields)], names=[n for n, _ in fields]))


def hash_sample(rows: DataFrame, by: str, per: int, most: int) -> DataFrame:
    """(doc_id, ``by``): at most ``per`` rows of each value, of the least hashes of doc_id, for the ``most`` most frequent values (ties by value).

    Rows above a hash that about twice as many rows stay under are dropped where they lie, so that no value gathers in one task.
    """
    h = F.xxhash64("doc_id")
    counts = rows.groupBy(by).agg(F.count("*").alias("n")).orderBy(F.desc("n"), by).limit(most).collect()
    tops = [(r[by], -(1 << 63) + min((1 << 64) - 1, (1 << 64) * (2 * per + 64) // r.n)) for r in counts]
    kind = rows.schema[by].dataType.simpleString()
    bound = F.broadcast(small_table(rows.sparkSession, tops, f"_value {kind}, _top long"))  # ``most`` rows
    near = rows.join(bound, (F.col(by) == F.col("_value")) & (h <= F.col("_top"))).select("doc_id", by, h.alias("_h"))
    first = Window.partitionBy(by).orderBy("_h", "doc_id")
    return near.withColumn("_r", F.row_number().over(first)).filter(F.col("_r") <= per).select("doc_id", by)


def slices(batches: Iterator[pa.RecordBatch], limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Re-cuts Arrow batches so that each holds about ``limit`` bytes of text (one document at least)."""
    for batch in batches:
        if not batch.num_rows:
            continue
        text = batch.column(batch.schema.get_field_index("text"))
        sizes = pc.fill_null(pc.binary_length(text), 0).to_numpy(zero_copy_only=False)
        ends = np.cumsum(sizes)
        lo = 0
        while lo < batch.num_rows:
            base = ends[lo - 1] if lo else 0
            hi = max(lo + 1, int(np.searchsorted(ends, base + limit, side="right")))
            yield batch.slice(lo, hi - lo)
            lo = hi
    hand_back()


def hand_back() -> None:
    """Gives freed memory back to the system at a task's end: workers outlive their tasks."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(_libc, "malloc_trim", None):
        trim(0)


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All texts of a string column as one byte array and the n+1 offsets into it (null: empty)."""
    column = pc.fill_null(column, "").cast(pa.large_string())
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    data = np.frombuffer(data, dtype=np.uint8) if data is not None else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def record(schema: pa.Schema, *columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(columns, schema)], schema=schema)


def squeezed(text: Column) -> Column:
    """Text as compressed UTF-8 bytes, for shuffles that carry whole texts. Null stays null."""

    def run(columns: Iterator[pa.Array]) -> Iterator[pa.Array]:
        pack = zstandard.ZstdCompressor(level=1).compress
        for column in columns:
            data = column.cast(pa.binary()) if not pa.types.is_binary(column.type) else column
            yield pa.array((None if not v.is_valid else pack(v.as_buffer()) for v in data), pa.binary())
        hand_back()

    return F.arrow_udf(run, "binary")(text)


def unsqueezed(value: pa.Scalar) -> bytes | None:
    return zstandard.ZstdDecompressor().decompress(value.as_buffer()) if value.is_valid else None
