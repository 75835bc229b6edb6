"""Shared pieces of the training-data operators.

Rules kept by every operator of this subpackage:

* only the needed columns are selected first, so extra columns of any name in
  the input cannot clash with working columns;
* a null text is read as the empty text, a null id stays null and sorts first;
* what has to outlive a stage is written as Parquet into the folder that the
  cluster names in ``spark.checkpoint.dir`` (shared by driver and executors), so
  a lost executor never takes the only copy with it;
* what reaches the driver is bounded by the number of partitions or by a
  constant that the docstring states.
"""

from __future__ import annotations

import ctypes
import gc
import sys

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..storage import new_path


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def free_name(taken: list[str], name: str) -> str:
    """A column name that none of ``taken`` has (in any case): name, or name with underscores before it."""
    held = {c.lower() for c in taken}
    while name.lower() in held:
        name = "_" + name
    return name


def staged(df: DataFrame, name: str) -> DataFrame:
    """Writes df once to the shared folder and reads it back: lineage ends here.

    Shuffle files of finished plans are let go, as nothing can need them any more.
    """
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    gc.collect()
    spark._jvm.System.gc()
    return spark.read.schema(df.schema).parquet(path)


def tidy() -> None:
    """Gives memory that a task no longer uses back to the system: workers live on and wait for other tasks."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def clear_encoders() -> None:
    """Lets go of tokenizer caches that an earlier task of this worker left, for tasks that need none."""
    held = sys.modules.get(f"{__package__}.word_ids")
    if held is not None and held._ENCODERS:
        held._ENCODERS.clear()
        tidy()


def tidied(f):
    """An Arrow map function that tidies up at the end of its task, and begins without caches it has no use for."""

    def run(batches):
        if "encoder" not in f.__code__.co_names:
            clear_encoders()
        try:
            yield from f(batches)
        finally:
            tidy()

    return run


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def dealt_rank(df: DataFrame, keys: list[str], order: list[str], name: str, buckets: int) -> DataFrame:
    """Adds ``name``: a gapless rank from 0 within keys, with no task that holds a whole key.

    Rows of a key are dealt into hash buckets of their order columns; ranks count
    within (key, bucket) and a running sum over bucket sizes shifts them.
    """
    dealt = df.withColumn("_bucket", F.pmod(F.xxhash64(*order), F.lit(buckets)).cast("int"))
    sizes = dealt.groupBy(*keys, "_bucket").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.partitionBy(*keys).orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    shifts = sizes.select(*[F.col(k).alias(f"_k{i}") for i, k in enumerate(keys)], F.col("_bucket").alias("_b"), F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_shift"))
    inside = Window.partitionBy(*keys, "_bucket").orderBy(*order)
    ranked = dealt.withColumn("_inside", F.row_number().over(inside) - 1)
    on = [F.col(k).eqNullSafe(F.col(f"_k{i}")) for i, k in enumerate(keys)] + [F.col("_bucket") == F.col("_b")]
    joined = ranked.join(shifts, on)
    return joined.select(*df.columns, (F.col("_inside") + F.col("_shift")).cast("long").alias(name))


def blocks_of(batch: pa.RecordBatch, column: str = "text", limit: int = 1 << 20):
    """Cuts an Arrow batch into pieces of about ``limit`` bytes of text.

    Yields (first row, row count, bytes as uint8, offsets as int64 from 0). Null
    texts are empty. One text longer than the limit is a piece of its own.
    """
    text = batch.column(batch.schema.get_field_index(column))
    if text.null_count:
        text = text.fill_null("")
    if len(text) == 0:
        return
    large = pa.types.is_large_string(text.type)
    offsets = np.frombuffer(text.buffers()[1], np.int64 if large else np.int32)[text.offset : text.offset + len(text) + 1].astype(np.int64)
    data = np.frombuffer(text.buffers()[2], np.uint8) if text.buffers()[2] is not None else np.zeros(0, np.uint8)
    first = 0
    while first < len(text):
        last = max(first + 1, int(np.searchsorted(offsets, offsets[first] + limit, "right")) - 1)
        last = min(last, len(text))
        yield first, last - first, data[offsets[first] : offsets[last]], offsets[first : last + 1] - offsets[first]
        first = last


#: Powers of the odd multiplier and of its inverse modulo 2**64 make every slice's polynomial hash two look-ups.
_MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)
_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))


def _powers(base: np.uint64, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    if n:
        out[0] = 1
        np.multiply.accumulate(out, out=out)
    return out


_POWER_CACHE: dict[str, np.ndarray] = {}


def _cached_powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if "up" not in _POWER_CACHE or len(_POWER_CACHE["up"]) < n:
        if n > 2 << 20:  # one huge text: not kept
            return _powers(_MULTIPLIER, n), _powers(_INVERSE, n)
        m = max(n, 1 << 20)
        _POWER_CACHE["up"], _POWER_CACHE["down"] = _powers(_MULTIPLIER, m), _powers(_INVERSE, m)
    return _POWER_CACHE["up"][:n], _POWER_CACHE["down"][:n]


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on uint64 (murmur-style), in place on a copy."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xFF51AFD7ED558CCD)
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xC4CEB9FE1A85EC53)
    x ^= x >> np.uint64(33)
    return x


def _word_lut() -> np.ndarray:
    """Byte to its value inside a word after lower-casing A-Z, 0 for bytes between words."""
    lut = np.zeros(256, np.uint8)
    lut[0x30:0x3A] = np.arange(0x30, 0x3A)
    lut[0x61:0x7B] = np.arange(0x61, 0x7B)
    lut[0x41:0x5B] = np.arange(0x61, 0x7B)
    lut[0x80:] = np.arange(0x80, 0x100)
    return lut


WORD_LUT = _word_lut()


def words_of(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Words (maximal runs of digits, letters a-z in either case and bytes over 0x7F) of a block.

    Returns starts, ends, 64-bit hashes of the lower-cased words, and the words'
    bounds by document (length documents + 1). Words never cross documents.
    """
    lower = WORD_LUT[data]
    inside = np.zeros(len(data) + 2, bool)
    inside[1:-1] = lower != 0
    starts = np.flatnonzero(inside[1:-1] & ~inside[:-2])
    # a document's first byte starts a word even where the previous document ended in one
    edges = offsets[1:-1]
    edges = edges[(edges > 0) & (edges < len(data))]
    glued = np.unique(edges[(lower[edges] != 0) & (lower[edges - 1] != 0)]) if len(edges) else edges
    ends = np.flatnonzero(inside[1:-1] & ~inside[2:]) + 1
    if len(glued):
        starts, ends = np.sort(np.concatenate([starts, glued])), np.sort(np.concatenate([ends, glued]))
    up, down = _cached_powers(len(data) + 1)
    total = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((lower.astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=total[1:])
    hashes = mix64((total[ends] - total[starts]) * down[starts])
    return starts, ends, hashes, np.searchsorted(starts, offsets)


def to_batch(columns: dict, schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(columns[f.name], f.type) for f in schema], schema=schema)
