"""What the operators of this subpackage share: shared scratch space, words, splits.

Words are maximal runs of characters other than space and \\t..\\r (``[^\\x20\\x09-\\x0D]+``).
On bytes that is exactly ``bytes.split()``, and ``bytes.lower()`` lower-cases A-Z only.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from trieaccess.session import scratch_path

WORD = r"[^\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


class Scratch:
    """Written tables in the shared folder: they cut lineage and survive lost executors."""

    def __init__(self, spark: SparkSession, tag: str):
        self.spark, self.root = spark, scratch_path(spark, tag)

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def save(self, df: DataFrame, name: str) -> DataFrame:
        df.write.option("compression", "zstd").parquet(self.path(name))
        return self.spark.read.schema(df.schema).parquet(self.path(name))

    def drop(self, *names: str) -> None:
        jvm = self.spark._jvm
        for name in names:
            path = jvm.org.apache.hadoop.fs.Path(self.path(name))
            path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)


def crc_mod(id_col: str, n: int) -> Column:
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % n


def lower_ascii(c: Column) -> Column:
    return F.translate(c, UPPER, LOWER)


def text_bytes(c: str = "text") -> Column:
    """Whole text as UTF-8 bytes; null counts as empty."""
    return F.coalesce(F.col(c).cast("binary"), F.lit(b""))


def boxed(df: DataFrame) -> Column:
    """All columns of `df` as one struct: whatever they are called, they cannot meet a name of an operator."""
    return F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("row")


def unboxed(df: DataFrame, rows: DataFrame, **made: Column) -> DataFrame:
    """The columns that `boxed(df)` holds in `rows`, then those made; a made one replaces one of its name. In two steps: no made column sees a user's name."""
    rows = rows.select("row", F.struct(*[c.alias(name) for name, c in made.items()]).alias("made"))
    return rows.select(*[F.col("row").getField(c).alias(c) for c in df.columns if c.lower() not in made], *[F.col("made").getField(c).alias(c) for c in made])


def in_slices(sizes: list[int], most: int) -> Iterator[tuple[int, int]]:
    """Consecutive ranges whose sizes sum to about `most`; one item is never cut."""
    start = total = 0
    for i, n in enumerate(sizes):
        if total and total + n > most:
            yield start, i
            start, total = i, 0
        total += n
    if start < len(sizes):
        yield start, len(sizes)
