"""The three corpora of the experiments, each one string of a stated length: (seq_id 0, text).

A string is a parameter's length and no more, so it is put together in one task; only the rows that reach into it get there.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

LOG_LINE, BUCKET = 40, 1024


def log_line() -> Column:
    return F.concat(F.date_format("ts", "yyyy-MM-dd'T'HH:mm:ss"), F.lit(" user="), F.col("user_id").cast("string"), F.lit(" "), "event_type", F.lit(" value="),
                    F.col("value").cast("decimal(18,2)").cast("string"), F.lit(" "), "props")


def first_symbols(rows: DataFrame, order: str, text: str, n: int, glue: str) -> DataFrame:
    """`rows` few enough for a task, in the order of `order`, joined and cut at n symbols."""
    parts = F.array_sort(F.collect_list(F.struct(F.col(order).alias("o"), F.col(text).alias("t"))))
    whole = F.array_join(F.transform(parts, lambda p: p["t"]), glue)
    return rows.groupBy().agg(whole.alias("text")).select(F.lit(0).cast("long").alias("seq_id"), F.substring(F.coalesce("text", F.lit("")), F.lit(1), F.lit(n)).alias("text"))


def log(events: DataFrame, n: int = 1_200_000) -> DataFrame:
    """The first n symbols of the event log; a line has more than LOG_LINE symbols."""
    rows = events.orderBy("event_id").limit(n // LOG_LINE + 1)
    return first_symbols(rows.select("event_id", log_line().alias("line")), "event_id", "line", n, "\n")


def dna(docs: DataFrame, n: int = 1_700_000) -> DataFrame:
    """The first n symbols of the documents in the order of doc_id, code point mod 4 as A, C, G, T. The documents are found by sums over buckets of ids."""
    size = F.length("text").cast("long")
    sums = docs.where("text IS NOT NULL").groupBy(F.floor(F.col("doc_id") / BUCKET).alias("bucket")).agg(F.sum(size).alias("size"))
    run = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)  # a row a bucket
    near = sums.withColumn("before", F.coalesce(F.sum("size").over(run), F.lit(0))).where(F.col("before") < n).select("bucket", "before")
    inside = Window.partitionBy("bucket").orderBy("doc_id").rowsBetween(Window.unboundedPreceding, -1)
    rows = docs.where("text IS NOT NULL").withColumn("bucket", F.floor(F.col("doc_id") / BUCKET)).join(near, "bucket")
    rows = rows.withColumn("at", F.col("before") + F.coalesce(F.sum(size).over(inside), F.lit(0))).where(F.col("at") < n)
    letters = F.transform(F.filter(F.split("text", ""), lambda c: c != ""), lambda c: F.substring(F.lit("ACGT"), F.ascii(c) % 4 + 1, F.lit(1)))
    return first_symbols(rows.select("doc_id", F.array_join(letters, "").alias("line")), "doc_id", "line", n, "")


def vocabulary(docs: DataFrame, n: int = 1_300_000) -> DataFrame:
    """The first n symbols of the sorted distinct lower-cased words, one a line."""
    words = docs.select(F.explode(F.split(F.lower("text"), r"\s+")).alias("w")).where("w <> ''").distinct()
    return first_symbols(words.orderBy("w").limit(n // 2 + 1), "w", "w", n, "\n")
