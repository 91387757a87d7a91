"""Shared helpers: words, hashes, scratch tables and Arrow plumbing.

Words are what the contracts call words: maximal runs of bytes other than space and
0x09-0x0D, after lower-casing A-Z only. ``bytes.lower`` and ``bytes.split`` do exactly that.
"""

from __future__ import annotations

import atexit
import re
import uuid
import zlib
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from attrition.functions.scratch import tidy

#: Bits of the fixed-size row filters that are sent to executors (2 MiB whatever the input).
FILTER_BITS = 1 << 24


def words_of(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").lower().split() if text else []


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), dtype=np.uint64, count=len(words))


def mix64(x: np.ndarray) -> np.ndarray:
    """The splitmix finaliser: every input bit reaches every output bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def crc_bucket(column, modulus: int):
    """crc32 of a column's text, modulo; null ids are in no bucket."""
    return F.crc32(F.col(column).cast("string")) % modulus


def scratch_root(spark: SparkSession) -> str:
    """The shared folder that the cluster names; one of our own only on a local master that names none (tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    return named or "file:///tmp/checkpoints/attrition"


def spare(df: DataFrame, *names: str) -> list[str]:
    """The names given, each prefixed until no column of df is called so (in any case of letters)."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name = f"_{name}"
        taken.add(name.lower())
        out.append(name)
    return out


_scratch: list[tuple[SparkSession, str]] = []


def _sweep() -> None:
    for spark, path in _scratch:
        try:
            hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)
        except Exception:  # noqa: BLE001  the session has ended; the folder is the cluster's to clean
            pass


atexit.register(_sweep)


def saved(df: DataFrame, name: str = "table") -> DataFrame:
    """df written to the shared scratch folder and read back: lineage ends here, lost executors cost nothing. The folder goes
    when the driver ends; what was shuffled to write it goes at once."""
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/{name}-{uuid.uuid4().hex}"
    _scratch.append((spark, path))
    with tidy(spark):
        df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def slice_bits(df: DataFrame, least: int = 64) -> int:
    """Upper bits of a hash that name its slice, the unit that is dealt out: at least as many slices as shuffle partitions."""
    wanted = max(least, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    return min(16, (wanted - 1).bit_length())


def row_filter(keys: DataFrame, column: str) -> bytes:
    """A bitmap of crc32(key as text) modulo FILTER_BITS: at most 512 words of 4 KiB, so bounded on the driver. Null keys are in no spot.

    It only spares work: rows that pass are still joined exactly."""
    spot = F.crc32(F.col(column).cast("string")) % FILTER_BITS + 1  # positions of bitmaps start at 1
    rows = (
        keys.where(F.col(column).isNotNull()).select(spot.alias("spot"))
        .groupBy(F.bitmap_bucket_number("spot").alias("bucket"))
        .agg(F.bitmap_construct_agg(F.bitmap_bit_position("spot")).alias("bits"))
        .collect()
    )
    out = bytearray(FILTER_BITS // 8)
    for bucket, bits in rows:
        out[(bucket - 1) * 4096 : bucket * 4096] = bits
    return bytes(out)


def in_filter(bits: np.ndarray, keys: Iterable[bytes]) -> np.ndarray:
    """Which keys may be in the filter. bits: np.unpackbits(..., bitorder="little") of row_filter."""
    spots = np.fromiter((zlib.crc32(k) for k in keys), dtype=np.int64)
    return bits[spots % FILTER_BITS].astype(bool)


def unpacked(raw: bytes) -> np.ndarray:
    return np.unpackbits(np.frombuffer(raw, dtype=np.uint8), bitorder="little")


def arrow_schema(ddl: str) -> tuple[T.StructType, pa.Schema]:
    from pyspark.sql.pandas.types import to_arrow_schema

    schema = T.StructType.fromDDL(ddl)
    return schema, to_arrow_schema(schema)


def pieces(batches: Iterable[pa.RecordBatch], rows: int = 1000) -> Iterator[pa.RecordBatch]:
    """Batches cut into slices of so many rows (no copies), so that what a task holds of texts and words stays small."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def map_batches(df: DataFrame, ddl: str, work: Callable[[], Callable]) -> DataFrame:
    """mapInArrow with a per-task factory: work() returns a function of (columns as lists) -> dict of columns or None."""
    schema, arrow = arrow_schema(ddl)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = work()
        for batch in pieces(batches):
            out = step(*(column.to_pylist() for column in batch.columns))
            if out is not None:
                yield pa.RecordBatch.from_arrays([pa.array(out[f.name], type=f.type) for f in arrow], schema=arrow)
        last = getattr(step, "rest", None)
        if last is not None and (out := last()) is not None:
            yield pa.RecordBatch.from_arrays([pa.array(out[f.name], type=f.type) for f in arrow], schema=arrow)

    return df.mapInArrow(run, schema)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")
