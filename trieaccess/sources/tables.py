from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def load(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """A given table, only the columns asked for."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def dealt(scan: DataFrame, key: str) -> DataFrame:
    """A plain scan with fewer splits than there are cores is dealt over them by `key`; one with more stays where it is read, without a shuffle."""
    cores = scan.sparkSession.sparkContext.defaultParallelism
    return scan if scan.rdd.getNumPartitions() >= cores else scan.repartition(2 * cores, key)


def read_any(spark: SparkSession, fmt: str, path: str, schema: str) -> DataFrame:
    """csv, json, text, orc or parquet with a fixed schema."""
    reader = spark.read.format(fmt).schema(schema)
    return (reader.option("header", True) if fmt == "csv" else reader).load(path)


def write_any(df: DataFrame, fmt: str, path: str) -> None:
    writer = df.write.mode("overwrite").format(fmt)
    (writer.option("header", True) if fmt == "csv" else writer).save(path)
