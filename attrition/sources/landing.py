"""Landing: spooled files, sliced imports, parsing of semi-structured text, the storage trial and the chosen layout."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.scratch import new_path


def spool(spark: SparkSession, src_dir: str, dst_dir: str, fmt: str, schema: str, files_per_trigger: int = 100) -> None:
    """Lands the files of a spool directory in the format they came in, each file once; returns when all are landed."""
    reader = spark.readStream.format(fmt).option("maxFilesPerTrigger", files_per_trigger)
    if fmt == "csv":
        reader = reader.option("header", True)
    stream = reader.schema(schema).load(src_dir)
    writer = stream.writeStream.format(fmt).option("checkpointLocation", f"{dst_dir}/_progress").trigger(availableNow=True)
    if fmt == "csv":
        writer = writer.option("header", True)
    writer.start(f"{dst_dir}/data").awaitTermination()


def range_slices(lo: int, hi: int, key: str, slices: int = 4) -> list[str]:
    """Predicates of even ranges of a key, as a parallel import uses; ends are open, null keys go with the first."""
    step = (hi - lo + 1) / slices
    cuts = [lo + round(step * i + 0.499999) for i in range(1, slices)]
    bounds = [None, *cuts, None]
    out = []
    for a, b in zip(bounds, bounds[1:]):
        parts = [f"{key} >= {a}"] * (a is not None) + [f"{key} < {b}"] * (b is not None)
        text = " AND ".join(parts) or "TRUE"
        out.append(f"{text} OR {key} IS NULL" if a is None else text)
    return out


def bulk_import(spark: SparkSession, url: str, table: str, key: str, lo: int, hi: int, dst: str, slices: int = 4, **properties) -> None:
    """Reads a relational table in parallel slices of an indexed key and stores it as CSV."""
    df = spark.read.jdbc(url, table, predicates=range_slices(lo, hi, key, slices), properties=properties)
    df.write.mode("overwrite").option("header", True).csv(dst)


def slice_counts(df: DataFrame, key: str, slices: int = 4) -> DataFrame:
    """(slice, rows, low, high): how a sliced import would deal the rows out."""
    ends = df.agg(F.min(key).alias("lo"), F.max(key).alias("hi"))  # one row
    number = F.least(F.lit(slices - 1), F.floor((F.col(key) - F.col("lo")) * slices / (F.col("hi") - F.col("lo") + 1))).cast("int")
    return df.crossJoin(F.broadcast(ends)).groupBy(number.alias("slice")).agg(F.count("*").alias("rows"), F.min(key).alias("low"), F.max(key).alias("high"))


def parse(df: DataFrame, column: str, schema: str, kind: str = "json", mode: str = "PERMISSIVE") -> DataFrame:
    """Adds parsed: the struct of a JSON, XML or CSV text. In PERMISSIVE mode bad text gives nulls, FAILFAST raises."""
    fn = {"json": F.from_json, "xml": F.from_xml, "csv": F.from_csv}[kind]
    return df.withColumn("parsed", fn(F.col(column), schema, {"mode": mode}))


def bytes_of(spark: SparkSession, path: str) -> int:
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(hadoop).getLength()


CODECS = {"csv": ("none", "gzip"), "json": ("none", "gzip"), "parquet": ("none", "snappy", "zstd"), "orc": ("none", "snappy", "zstd"), "avro": ("uncompressed", "snappy", "deflate")}


def storage_trial(df: DataFrame, column: str, group: str, formats: dict[str, tuple[str, ...]] = CODECS) -> DataFrame:
    """(fmt, codec, status, bytes, write_s, scan_s, agg_s) of writing df and reading one column and one sum of it back."""
    spark, rows = df.sparkSession, []
    for fmt, codecs in formats.items():
        for codec in codecs:
            path = new_path(spark, f"trial-{fmt}")
            began = time.time()
            try:
                df.write.format(fmt).option("compression", codec).option("header", True).save(path)
            except Exception as e:  # noqa: BLE001  a format whose module this Spark lacks is reported, not hidden
                if "DATA_SOURCE" not in str(e) and "Failed to find" not in str(e) and "data source" not in str(e):
                    raise
                rows.append((fmt, codec, "unavailable", None, None, None, None))
                continue
            wrote = time.time() - began
            reader = spark.read.format(fmt).schema(df.schema)
            back = (reader.option("header", True) if fmt == "csv" else reader).load(path)
            began = time.time()
            back.select(column).write.format("noop").mode("overwrite").save()
            scanned = time.time() - began
            began = time.time()
            back.groupBy(group).agg(F.sum(column)).write.format("noop").mode("overwrite").save()
            rows.append((fmt, codec, "measured", bytes_of(spark, path), wrote, scanned, time.time() - began))
    return spark.createDataFrame(rows, "fmt STRING, codec STRING, status STRING, bytes BIGINT, write_s DOUBLE, scan_s DOUBLE, agg_s DOUBLE")


def store(df: DataFrame, path: str, partition_by: str | None = None, sort_by: str | None = None) -> None:
    """The chosen layout: Parquet with Snappy, a folder for each period, rows of a subscriber together."""
    if partition_by and sort_by:
        df = df.repartition(partition_by, sort_by).sortWithinPartitions(partition_by, sort_by)
    elif sort_by:
        df = df.sortWithinPartitions(sort_by)
    writer = df.write.mode("overwrite").option("compression", "snappy")
    (writer.partitionBy(partition_by) if partition_by else writer).parquet(path)


def bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    """A table whose joins and sums by key need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).option("compression", "snappy").saveAsTable(table)
