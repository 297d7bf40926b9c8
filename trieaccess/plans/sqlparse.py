"""The parse as relations: one plan of built-in functions for Spark, and recursive SQL as an independent check."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def parse_native(seqs: DataFrame) -> DataFrame:
    """seq_id, phrase_no, parent_no, symbol, depth, start_pos by a fold over the symbols; quadratic in the phrases of a text, so for short texts."""
    zero = F.struct(F.array().cast("array<string>").alias("phrases"), F.lit("").alias("open"))

    def step(acc, c):
        longer = F.concat(acc["open"], c)
        known = F.array_contains(acc["phrases"], longer)
        return F.struct(F.when(known, acc["phrases"]).otherwise(F.array_append(acc["phrases"], longer)).alias("phrases"), F.when(known, longer).otherwise("").alias("open"))

    # the accumulator keeps its type: both branches are arrays of strings and a string
    folded = seqs.where(F.length("text") > 0).select("seq_id", F.aggregate(F.filter(F.split("text", ""), lambda c: c != ""), zero, step).alias("r"))
    done = folded.select("seq_id", F.when(F.col("r.open") == "", F.col("r.phrases")).otherwise(F.array_append("r.phrases", F.col("r.open"))).alias("phrases"))
    rows = done.select("seq_id", "phrases", F.posexplode("phrases").alias("i", "phrase"))
    depth = F.length("phrase")
    parent = F.when(depth == 1, F.lit(0)).otherwise(F.array_position("phrases", F.left(F.col("phrase"), depth - 1)).cast("int"))
    before = F.aggregate(F.slice("phrases", F.lit(1), F.col("i")), F.lit(0).cast("long"), lambda a, p: a + F.length(p))
    return rows.select("seq_id", (F.col("i") + 1).alias("phrase_no"), parent.alias("parent_no"), F.ascii(F.right(F.col("phrase"), F.lit(1))).alias("symbol"), depth.alias("depth"), (before + 1).alias("start_pos"))


def parse_sql(source: str, tag: str = "") -> str:
    """CTEs (names end in `tag`) ending in c(seq_id, phrase_no, parent_no, symbol, depth, start_pos, phrase, phrases) over `source` giving (seq_id, x)."""
    return f"""WITH RECURSIVE src{tag} AS ({source}),
walk{tag} AS (
  SELECT seq_id, x AS rest, CAST([] AS VARCHAR[]) AS phrases, 0 AS phrase_no, 0 AS parent_no, '' AS phrase, CAST(1 AS BIGINT) AS next_pos FROM src{tag} WHERE length(x) > 0
  UNION ALL
  SELECT seq_id, substr(rest, length(new) + 1), list_append(phrases, new), phrase_no + 1,
    CASE WHEN length(new) = 1 THEN 0 ELSE list_position(phrases, left(new, length(new) - 1)) END, new, next_pos + length(new)
  FROM (SELECT *, left(rest, coalesce(list_max(list_transform(list_filter(phrases, lambda p: starts_with(rest, p)), lambda p: length(p))), 0) + 1) AS new
        FROM walk{tag} WHERE length(rest) > 0)),
c{tag} AS (SELECT seq_id, phrase_no, parent_no, unicode(right(phrase, 1)) AS symbol, length(phrase) AS depth, next_pos - length(phrase) AS start_pos, phrase, phrases
  FROM walk{tag} WHERE phrase_no > 0)
"""


def coin_sql(seed: int, alpha: float) -> str:
    """A lateral chain of columns over c that ends in `special`: the 32-bit coin of each phrase."""

    def mix(x: str, tag: str) -> str:
        return f"""xor({x}, {x} >> 16) AS {tag}1, ({tag}1 * 2246822507::UBIGINT) % 4294967296::UBIGINT AS {tag}2, xor({tag}2, {tag}2 >> 13) AS {tag}3,
          ({tag}3 * 3266489909::UBIGINT) % 4294967296::UBIGINT AS {tag}4, xor({tag}4, {tag}4 >> 16) AS {tag}5"""

    return f"""coin AS (SELECT *, (({seed} * 2654435761 + seq_id) % 4294967296)::UBIGINT AS k0, {mix('k0', 'k')},
  xor((phrase_no::UBIGINT * 2654435761::UBIGINT) % 4294967296::UBIGINT, k5) AS h0, {mix('h0', 'h')}, h5 < {int(alpha * 2**32)}::UBIGINT AS special FROM c)"""
