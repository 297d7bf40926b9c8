"""Where passages occur in sequences, without comparing every passage with every sequence."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WORDS, SALTS = 3, 16


def runs(words: Column, first: Column, last: Column) -> Column:
    """Hashes of WORDS words from each of the places first..last on."""
    return F.transform(F.sequence(first, last), lambda i: F.xxhash64(F.array_join(F.slice(words, i, WORDS), " ")))


def occurrences(seqs: DataFrame, items: DataFrame) -> DataFrame:
    """(seq_id, text) and (item_id, passage) -> seq_id, item_id, l1, k: the first place of each passage in each sequence that holds it. Nulls and empty passages occur nowhere.

    Wherever a passage of WORDS + 2 words or more occurs, the sequence has the passage's second to fourth words as whole words. So passages are filed under these and meet the
    distinct runs of words of the sequences by an equi-join, passages repeated under salts; `instr` decides. Shorter passages are compared with all.
    """
    asked = items.where(F.length("passage") > 0).withColumn("words", F.split("passage", r"\s+"))
    long_ = asked.where(F.size("words") >= WORDS + 2).select("item_id", "passage", F.element_at(runs(F.col("words"), F.lit(2), F.lit(2)), 1).alias("h"))
    words = seqs.where("text IS NOT NULL").select("seq_id", F.split("text", r"\s+").alias("words")).where(F.size("words") >= WORDS)
    shown = words.select("seq_id", F.explode(F.array_distinct(runs(F.col("words"), F.lit(1), F.size("words") - WORDS + 1))).alias("h"))
    shown = shown.withColumn("salt", F.pmod(F.xxhash64("seq_id"), F.lit(SALTS)).cast("int"))
    salted = long_.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    maybe = shown.join(salted, ["h", "salt"]).select("seq_id", "item_id", "passage").distinct().join(seqs, "seq_id")
    short = seqs.join(asked.where(F.size("words") < WORDS + 2).select("item_id", "passage"), F.expr("contains(text, passage)"))
    both = maybe.select("seq_id", "item_id", "passage", "text").unionByName(short.select("seq_id", "item_id", "passage", "text"))
    return both.select("seq_id", "item_id", F.instr(F.col("text"), F.col("passage")).cast("long").alias("l1"), F.length("passage").alias("k")).where("l1 > 0")
