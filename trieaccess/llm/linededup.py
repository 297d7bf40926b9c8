"""Line dedup by content-defined chunks of lines (DataFrame functions only).

Two boundary rules file chunks. The sparse one ends a chunk after a line where a rolling hash of the last three line hashes is divisible by
`modulus`, so an inserted or removed line moves only the boundaries near it. The dense one ends a chunk after every line that is not blank, and
begins it at the one before: these chunks of two worded lines overlap, and a repeated passage of two lines or more is covered by them whatever surrounds it.
A chunk of two lines or more, not only white space, whose bytes occur elsewhere in the corpus is removed everywhere but at its first place
(smallest doc_id, then line). A 64-bit hash only preselects; equality is decided by grouping on the text itself.
Each different line of a removed chunk stays at its own first place at least.

Chunks travel as hash and place; texts move twice, to cut the bodies of chunks whose hash repeats and to meet what is lost. What repeats grows with the corpus, so
these joins are merge joins at every size.

Nulls: a null text has no lines and stays null; an empty text is one empty line. Rows with the same doc_id and
text are one document with the same result. Null doc_ids come last as first places. Ties: places are different for different rows, else the rows are alike.
Very long texts are whole; work grows with their lines. Empty table: empty result. Extra columns are kept; those named like an output are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, boxed, unboxed

LAG1, LAG2, SALTS = 31, 961, 16


def line_hashes(lines: Column) -> Column:
    return F.transform(lines, lambda x: F.conv(F.substring(F.md5(x.cast("binary")), 1, 7), 16, 10).cast("long"))


def chunk_bounds(h: Column, modulus: int) -> Column:
    """0-based numbers of the lines that end a chunk; the last line always does."""
    n = F.size(h)

    def at(i: Column) -> Column:
        return F.when(i >= 0, F.get(h, i)).otherwise(F.lit(0))

    return F.filter(F.sequence(F.lit(0), n - 1), lambda i: (i == n - 1) | ((at(i) + LAG1 * at(i - 1) + LAG2 * at(i - 2)) % modulus == 0))


WORDED = r"[^\x20\x09-\x0D]"


def body(lines: Column, a: Column, b: Column) -> Column:
    return F.array_join(F.slice(lines, a + 1, b - a + 1), "\n")


def chunks(docs: DataFrame, modulus: int = 4, min_lines: int = 2) -> DataFrame:
    """doc_id, tkey (hash of the text), a, b (first and last line), key (hash of the body): one row a chunk of either rule."""
    cut = (
        docs.where(F.col("text").isNotNull())
        .select("doc_id", F.xxhash64("text").alias("tkey"), F.split("text", "\n", -1).alias("lines"))
        .withColumn("h", line_hashes(F.col("lines")))  # a column of its own: the bounds read it many times
        .withColumn("ends", chunk_bounds(F.col("h"), modulus))
        .withColumn("worded", F.filter(F.sequence(F.lit(0), F.size("lines") - 1), lambda i: F.get("lines", i).rlike(WORDED)))
    )
    span = lambda a, b: F.struct(a.alias("a"), b.alias("b"))
    sparse = F.transform(F.sequence(F.lit(0), F.size("ends") - 1), lambda k: span(F.when(k == 0, 0).otherwise(F.get("ends", k - 1) + 1), F.get("ends", k)))
    dense = F.when(F.size("worded") > 1, F.transform(F.sequence(F.lit(1), F.size("worded") - 1), lambda k: span(F.get("worded", k - 1), F.get("worded", k)))).otherwise(
        F.array().cast("array<struct<a: int, b: int>>"))
    spans = F.array_union(F.filter(sparse, lambda s: (s["b"] - s["a"] + 1 >= min_lines) & F.exists("worded", lambda i: i.between(s["a"], s["b"]))), dense)
    return cut.select("doc_id", "tkey", F.inline(F.transform(spans, lambda s: F.struct(s["a"].alias("a"), s["b"].alias("b"), F.xxhash64(body(F.col("lines"), s["a"], s["b"])).alias("key")))))


def repeated_chunks(docs: DataFrame, scratch: Scratch, modulus: int = 4, min_lines: int = 2) -> DataFrame:
    """doc_id, tkey, a, b of every occurrence to remove."""
    many = scratch.save(chunks(docs, modulus, min_lines), "chunks")
    keys = many.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    # a chunk may occur in a third of all documents: its occurrences are dealt over SALTS tasks, its key is sent to each
    keys = keys.select("key", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    salted = many.withColumn("salt", F.pmod(F.xxhash64("doc_id", "tkey", "a"), F.lit(SALTS)).cast("int"))
    twice = salted.join(keys.hint("merge"), ["key", "salt"], "left_semi").groupBy("doc_id", "tkey").agg(F.collect_set(F.struct("a", "b")).alias("spans"))  # of one document
    twice = twice.select(F.col("doc_id").alias("doc"), F.col("tkey").alias("own"), "spans", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    texts = docs.where(F.col("text").isNotNull()).select("doc_id", "text", F.xxhash64("text").alias("tkey"), F.pmod(F.monotonically_increasing_id(), F.lit(SALTS)).cast("int").alias("s"))
    whole = texts.join(twice.hint("merge"), F.col("doc_id").eqNullSafe(F.col("doc")) & (F.col("tkey") == F.col("own")) & (F.col("s") == F.col("salt")))
    pieces = F.transform("spans", lambda x: F.struct(x["a"].alias("a"), x["b"].alias("b"), body(F.split("text", "\n", -1), x["a"], x["b"]).alias("body")))
    bodies = scratch.save(whole.select("doc_id", "tkey", F.inline(pieces)).withColumn("key", F.xxhash64("body")), "twice")
    place = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "tkey", "a")
    first = scratch.save(bodies.groupBy("key", "body").agg(F.min(place).alias("first")), "first")  # written: the join below can then split a hot key
    hit = bodies.join(first.hint("merge"), ["key", "body"])
    return hit.where((F.col("a") != F.col("first.a")) | ~F.col("doc_id").eqNullSafe(F.col("first.doc_id")) | (F.col("tkey") != F.col("first.tkey"))).select("doc_id", "tkey", "a", "b").distinct()


def dedup_lines(docs: DataFrame, modulus: int = 4, min_lines: int = 2, scratch: Scratch | None = None) -> DataFrame:
    """`docs` with n_lines, n_chunks (of the sparse rule), removed_chunks (of both), removed_lines and `kept`, the text without the removed lines."""
    scratch = scratch or Scratch(docs.sparkSession, "lines")
    gone = repeated_chunks(docs.select("doc_id", "text"), scratch, modulus, min_lines).groupBy("doc_id", "tkey").agg(F.collect_set(F.struct("a", "b")).alias("spans"))
    lost = F.array_distinct(F.flatten(F.transform("spans", lambda x: F.sequence(x["a"], x["b"]))))
    gone = scratch.save(gone.select(F.col("doc_id").alias("doc"), F.col("tkey").alias("own"), F.size("spans").alias("removed_chunks"), lost.alias("lost")), "gone")
    rows = docs.select(boxed(docs), "doc_id", F.xxhash64("text").alias("tkey")).join(gone.hint("merge"), F.col("doc_id").eqNullSafe(F.col("doc")) & (F.col("tkey") == F.col("own")), "left")
    rows = rows.withColumn("text", F.col("row")["text"]).withColumn("lines", F.split("text", "\n", -1)).withColumn("h", line_hashes(F.col("lines")))
    left = F.array_except(F.sequence(F.lit(0), F.size("lines") - 1), F.col("lost"))
    none = F.col("text").isNull()
    return unboxed(
        docs, rows, n_lines=F.when(none, 0).otherwise(F.size("lines")), n_chunks=F.when(none, 0).otherwise(F.size(chunk_bounds(F.col("h"), modulus))),
        removed_chunks=F.coalesce("removed_chunks", F.lit(0)), removed_lines=F.when(F.col("lost").isNull(), 0).otherwise(F.size("lost")),
        kept=F.when(F.col("lost").isNull(), F.col("text")).otherwise(F.array_join(F.transform(left, lambda i: F.get("lines", i)), "\n")))


SQL = r"""
WITH d AS (SELECT DISTINCT doc_id, text FROM documents),
l AS (SELECT doc_id, text, unnest(string_split(text, chr(10))) AS line, unnest(range(len(string_split(text, chr(10))))) AS i FROM d WHERE text IS NOT NULL),
h AS (SELECT *, CAST('0x' || substr(md5(line), 1, 7) AS BIGINT) AS v, regexp_matches(line, '[^\x20\x09-\x0D]') AS worded FROM l),
b AS (SELECT *, ((v + 31 * coalesce(lag(v, 1) OVER w, 0) + 961 * coalesce(lag(v, 2) OVER w, 0)) % 4 = 0) AS ends,
        lead(i) OVER w IS NULL AS last FROM h WINDOW w AS (PARTITION BY doc_id, text ORDER BY i)),
c AS (SELECT *, coalesce(sum(CASE WHEN ends OR last THEN 1 ELSE 0 END) OVER
        (PARTITION BY doc_id, text ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS chunk FROM b),
k AS (SELECT doc_id, text, chunk, min(i) AS a, max(i) AS b, bool_or(worded) AS worded FROM c GROUP BY ALL),
p AS (SELECT doc_id, text, lag(i) OVER (PARTITION BY doc_id, text ORDER BY i) AS a, i AS b FROM h WHERE worded),
u AS (SELECT doc_id, text, a, b FROM k WHERE b > a AND worded UNION SELECT doc_id, text, a, b FROM p WHERE a IS NOT NULL),
r AS (SELECT *, row_number() OVER (PARTITION BY array_to_string(list_slice(string_split(text, chr(10)), a + 1, b + 1), chr(10)) ORDER BY doc_id, a) > 1 AS gone FROM u),
g AS (SELECT doc_id, text, a, b FROM r WHERE gone),
x AS (SELECT DISTINCT doc_id, text, unnest(range(a, b + 1)) AS i FROM g),
y AS (SELECT l.doc_id, l.text, CAST(count(*) AS INTEGER) AS n_lines, CAST(count(x.i) AS INTEGER) AS removed_lines,
        md5(coalesce(string_agg(line, chr(10) ORDER BY l.i) FILTER (x.i IS NULL), '')) AS kept_md5
      FROM l LEFT JOIN x ON l.doc_id = x.doc_id AND l.text = x.text AND l.i = x.i GROUP BY l.doc_id, l.text),
n AS (SELECT doc_id, text, CAST(count(*) AS INTEGER) AS n_chunks FROM k GROUP BY ALL),
m AS (SELECT doc_id, text, CAST(count(*) AS INTEGER) AS removed_chunks FROM g GROUP BY ALL)
SELECT s.doc_id, coalesce(y.n_lines, 0) AS n_lines, coalesce(n.n_chunks, 0) AS n_chunks, coalesce(m.removed_chunks, 0) AS removed_chunks,
    coalesce(y.removed_lines, 0) AS removed_lines, y.kept_md5 FROM documents s LEFT JOIN y ON s.doc_id = y.doc_id AND s.text = y.text
    LEFT JOIN n ON s.doc_id = n.doc_id AND s.text = n.text LEFT JOIN m ON s.doc_id = m.doc_id AND s.text = m.text
"""
