"""Packed stores on disk: Parquet clustered by a bucket of seq_id. Requests name sequences or positions; only the rows that hold them are read."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trieaccess import kernels as K
from trieaccess.functions import substr_of
from trieaccess.operators.codec import STORE, join_segments


def write(store: DataFrame, path: str, buckets: int = 16) -> None:
    """One shuffle by bucket, sorted within: min/max of seq_id then prune row groups."""
    rows = store.withColumn("bucket", F.pmod(F.xxhash64("seq_id"), F.lit(buckets)).cast("int"))
    rows.repartition("bucket").sortWithinPartitions("bucket", "seq_id", "seg_no").write.mode("overwrite").partitionBy("bucket").option("compression", "zstd").parquet(path)


def read(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(f"{STORE}, bucket int").parquet(path)


def read_sequences(spark: SparkSession, path: str, ids: list[int], buckets: int = 16) -> DataFrame:
    """A few sequences: partition pruning by bucket, then row groups by seq_id."""
    wanted = spark.range(1).select(F.array(*[F.pmod(F.xxhash64(F.lit(i).cast("long")), F.lit(buckets)).cast("int") for i in ids]).alias("b")).first().b
    return read(spark, path).where(F.col("bucket").isin(sorted(set(wanted))) & F.col("seq_id").isin(ids))


def read_ranges(spark: SparkSession, path: str, first: int, size: int, capacity: int = K.MAX_SYMBOLS) -> DataFrame:
    """seq_id, piece: `size` symbols from position `first` on of every sequence, clipped at its end, from the segments that hold them and without expanding any; sequences that end before have no row."""
    low, high = (first - 1) // capacity, (first + size - 2) // capacity
    rows = read(spark, path).where(F.col("seg_no").between(low, high)).select("seq_id", "seg_no", "blob")
    base = F.col("seg_no").cast("long") * capacity
    start, end = F.greatest(F.lit(first) - base, F.lit(1)), F.least(F.lit(first + size - 1) - base, F.lit(capacity))
    pieces = rows.select("seq_id", "seg_no", substr_of("blob", start.cast("long"), (end - start + 1).cast("long")).alias("text")).where("text IS NOT NULL")
    return join_segments(pieces).withColumnRenamed("text", "piece")
