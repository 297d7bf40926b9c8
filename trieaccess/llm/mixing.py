"""Mixing sources to target weights by capped water-filling (DataFrame functions only).

Every source gets its share of a word budget by weight; a source cannot be repeated more than `max_epochs`
times, and what it cannot take goes to the others by weight until no target is above its cap. The fixed point
is found without iterating: in order of cap/weight the capped sources form a prefix, so running sums suffice.

Sampling: each row is taken floor(target/size of source) times, and the remaining fraction is the
prefix of the source's rows in the order of a seeded md5 that comes nearest to the wanted words. The end of the prefix is
found in three steps (sums of `BINS` hash bins, sums of `BINS` parts of the one bin that holds it, running sums inside that part);
then every row only compares its key with the end of its source, so neither rows nor texts are sorted or shuffled.

Nulls: null text has size 0; null source is a source of its own, ranked last; null doc_id hashes as empty.
Sources of size 0 get target 0. Ties and repeated rows: rows with equal key and size at the end of a prefix are numbered
and cut in any order, with the same multiset of results. An empty table gives an empty result. Extra columns are left
out unless named in `keep`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from .common import WORD, Scratch

BINS, SPAN = 4096, 1 << 48
MAX_SENT, SALTS = 100_000, 16


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def water_fill(sources: DataFrame, max_epochs: int, weights: tuple[int, ...]) -> DataFrame:
    """(src, source_size) -> + weight, target. One row a source: bounded by the number of weights a user can set."""
    order = W.Window.orderBy(F.col("src").asc_nulls_last())
    ranked = sources.select("src", "source_size", (F.row_number().over(order) - 1).alias("k")).withColumn(
        "weight", F.element_at(F.array(*[F.lit(w).cast("long") for w in weights]), (F.col("k") % len(weights) + 1).cast("int")))
    capped = ranked.withColumn("cap", F.col("source_size") * max_epochs)
    by_ratio = W.Window.orderBy((F.col("cap") / F.col("weight")).asc(), F.col("k"))
    before = by_ratio.rowsBetween(W.Window.unboundedPreceding, -1)
    everything = W.Window.partitionBy(F.lit(1))
    steps = (
        capped.withColumn("cap_before", F.coalesce(F.sum("cap").over(before), F.lit(0)))
        .withColumn("weight_before", F.coalesce(F.sum("weight").over(before), F.lit(0)))
        .withColumn("budget", F.sum("source_size").over(everything))
        .withColumn("weights", F.sum("weight").over(everything))
        .withColumn("full", F.col("cap").cast("decimal(38,0)") * (F.col("weights") - F.col("weight_before"))
                    <= F.col("weight").cast("decimal(38,0)") * (F.col("budget") - F.col("cap_before")))
    )
    rest = (
        steps.withColumn("left_words", F.col("budget") - F.sum(F.when(F.col("full"), F.col("cap")).otherwise(0)).over(everything))
        .withColumn("left_weight", F.sum(F.when(F.col("full"), 0).otherwise(F.col("weight"))).over(everything))
    )
    level = (F.col("weight") * F.col("left_words")).cast("double") / F.col("left_weight").cast("double")
    return rest.select("src", "source_size", "weight", F.when(F.col("full"), F.col("cap").cast("double")).otherwise(level).alias("target"))


def sample_key(id_col: str, seed: int) -> Column:
    """48 seeded bits of a row, the same in every run and in SQL."""
    text = F.concat(F.lit(f"{seed}:"), F.coalesce(F.col(id_col).cast("string"), F.lit("")))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 12), 16, 10).cast("long")


def by_source(rows: DataFrame, per_source: DataFrame, n_sources: int) -> DataFrame:
    """`rows` (src, u, ...) with the columns of `per_source`, which has one row a source.

    Up to `MAX_SENT` sources are sent to all tasks, so rows don't move. Beyond, the sources' rows are repeated under `SALTS` salts
    and merged, so that a source with a third of all rows is spread over tasks.
    """
    other = per_source.withColumnRenamed("src", "_src")
    same = F.col("src").eqNullSafe(F.col("_src"))
    if n_sources <= MAX_SENT:
        return rows.join(F.broadcast(other), same).drop("_src")
    other = other.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return rows.join(other.hint("merge"), same & (F.pmod(F.col("u"), F.lit(SALTS)) == F.col("_salt"))).drop("_src", "_salt")


def first_over(sums: DataFrame, part: str) -> DataFrame:
    """(src, part, words, wanted, start) -> src, at, start: of each source the first part that ends behind the wanted words."""
    run = W.Window.partitionBy("src").orderBy(part).rowsBetween(W.Window.unboundedPreceding, -1)
    placed = sums.withColumn("begin", F.col("start") + F.coalesce(F.sum("words").over(run), F.lit(0)))
    over = placed.where(F.col("begin") + F.col("words") > F.col("wanted"))
    return over.groupBy("src").agg(F.min(F.struct(F.col(part).alias("at"), "begin")).alias("hit")).select("src", "hit.at", F.col("hit.begin").alias("start"))


def cuts(sized: DataFrame, targets: DataFrame, bins: DataFrame, n_sources: int, scratch: Scratch) -> DataFrame:
    """Of each source where its fraction ends: cut_u, cut_size, and cut_take of the rows that are at just that place; what is before is taken.

    Two levels of `BINS` parts each narrow it down to 2^-24 of a source; only the rows in there are put in order.
    """
    step, fine = SPAN // BINS, SPAN // BINS // BINS
    wanted = by_source(bins.withColumn("u", F.col("bin")), targets.select("src", "wanted"), n_sources)
    one = first_over(wanted.select("src", "bin", F.col("bin_size").alias("words"), "wanted", F.lit(0).cast("long").alias("start")), "bin")
    one = scratch.save(by_source(one.withColumn("u", F.lit(0)), targets.select("src", "wanted"), n_sources).drop("u"), "cut1")
    near = by_source(sized.select("src", "u", "size"), one, n_sources).where(F.floor(F.col("u") / step) == F.col("at"))
    parts = near.groupBy("src", F.floor(F.col("u") / fine).alias("part"), "wanted", "start").agg(F.sum("size").alias("words"))
    two = first_over(parts, "part")
    two = scratch.save(by_source(two.withColumn("u", F.lit(0)), targets.select("src", "wanted"), n_sources).drop("u"), "cut2")
    inside = by_source(sized.select("src", "u", "size"), two, n_sources).where(F.floor(F.col("u") / fine) == F.col("at"))
    places = inside.groupBy("src", "u", "size", "at", "start", "wanted").agg(F.count(F.lit(1)).alias("rows"))
    run = W.Window.partitionBy("src").orderBy("u", "size").rowsBetween(W.Window.unboundedPreceding, -1)
    begin = F.col("start") + F.coalesce(F.sum(F.col("size") * F.col("rows")).over(run), F.lit(0))
    fit = F.floor((F.col("wanted") - F.col("begin")) / F.col("size") - 0.5) + 1  # rows whose middle is not behind the wanted words
    take = F.when(F.col("begin") + F.col("size") / 2 > F.col("wanted"), 0).when((F.col("rows") == 1) | (F.col("size") == 0), F.col("rows")).otherwise(F.least("rows", fit))
    open_ = places.withColumn("begin", begin).withColumn("take", take.cast("long")).where("take < rows")
    found = open_.groupBy("src").agg(F.min(F.struct("u", "size", "take")).alias("hit")).select("src", "hit.*")
    ends = two.select("src", ((F.col("at") + 1) * fine).alias("end"))
    last = ends.join(found.withColumnRenamed("src", "_src"), F.col("src").eqNullSafe(F.col("_src")), "left").select(
        "src", F.coalesce("u", "end").alias("cut_u"), F.coalesce("size", F.lit(0)).cast("long").alias("cut_size"), F.coalesce("take", F.lit(0)).cast("long").alias("cut_take"))
    # a source that no part ends behind is taken whole
    return scratch.save(targets.join(last.withColumnRenamed("src", "_src"), F.col("src").eqNullSafe(F.col("_src")), "left").drop("_src").fillna(
        {"cut_u": SPAN, "cut_size": 0, "cut_take": 0}), "cuts")


def first_rows(rows: DataFrame) -> DataFrame:
    """Written rows (src, cut_take, id, ...) -> + extra: 1 for `cut_take` rows of each source. They are numbered within the task that wrote them, and
    these numbers are moved on by the counts of the tasks before, so that equal rows of one source are never in one task."""
    task = F.shiftright("id", 33)
    counts = rows.groupBy("src", task.alias("task")).agg(F.count(F.lit(1)).alias("n"))
    before = F.coalesce(F.sum("n").over(W.Window.partitionBy("src").orderBy("task").rowsBetween(W.Window.unboundedPreceding, -1)), F.lit(0))
    counts = counts.select(F.col("src").alias("_src"), F.col("task").alias("_task"), before.alias("before"))
    own = rows.withColumn("task", task).withColumn("no", F.row_number().over(W.Window.partitionBy("src", "task").orderBy("id")))
    own = own.join(counts, F.col("src").eqNullSafe(F.col("_src")) & (F.col("task") == F.col("_task")))
    return own.withColumn("extra", (F.col("no") + F.col("before") <= F.col("cut_take")).cast("long")).drop("task", "no", "before", "id", "_src", "_task")


def mix(docs: DataFrame, max_epochs: int = 3, weights: tuple[int, ...] = (1, 2, 3), seed: int = 42,
        keep: tuple[str, ...] = (), scratch: Scratch | None = None) -> DataFrame:
    """One row per input row: doc_id, source, size, source_size, target, epochs (times taken), taken (words); with `keep`, those columns in a struct `_kept`."""
    scratch = scratch or Scratch(docs.sparkSession, "mix")
    own = ["doc_id", F.col("source").alias("src"), word_count(F.col("text")).alias("size"), sample_key("doc_id", seed).alias("u")]
    sized = scratch.save(docs.select(*own), "sized")  # sizes and keys only: texts are never written or moved
    bins = scratch.save(sized.groupBy("src", F.floor(F.col("u") / (SPAN // BINS)).alias("bin")).agg(F.sum("size").alias("bin_size")), "bins")
    targets = water_fill(bins.groupBy("src").agg(F.sum("bin_size").alias("source_size")), max_epochs, weights)
    targets = scratch.save(
        targets.withColumn("whole", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long"))
        .withColumn("wanted", F.col("target") - F.col("whole") * F.col("source_size")), "targets")
    n_sources = targets.count()
    ends = cuts(sized, targets, bins, n_sources, scratch)
    rows = docs.select(*own, F.struct(*keep).alias("_kept")) if keep else sized
    rows = by_source(rows, ends, n_sources)
    at_cut = (F.col("u") == F.col("cut_u")) & (F.col("size") == F.col("cut_size"))
    before = (F.col("u") < F.col("cut_u")) | ((F.col("u") == F.col("cut_u")) & (F.col("size") < F.col("cut_size")))
    if ends.where("cut_take > 0").isEmpty():
        out = rows.withColumn("extra", before.cast("long"))
    else:  # rows with one key and one size, some of them taken: only these are numbered
        numbered = first_rows(scratch.save(rows.where(at_cut).withColumn("id", F.monotonically_increasing_id()), "at_cut"))
        out = rows.where(~at_cut).withColumn("extra", before.cast("long")).unionByName(numbered)
    return out.select(
        "doc_id", F.col("src").alias("source"), "size", "source_size", "target", (F.col("whole") + F.col("extra")).alias("epochs"),
        (F.col("size") * (F.col("whole") + F.col("extra"))).alias("taken"), *(["_kept"] if keep else []))


SQL = r"""
WITH d AS (SELECT doc_id, source AS src,
    CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size,
    CAST('0x' || substr(md5('42:' || coalesce(CAST(doc_id AS VARCHAR), '')), 1, 12) AS BIGINT) AS u FROM documents),
s AS (SELECT src, CAST(sum(size) AS BIGINT) AS source_size, row_number() OVER (ORDER BY src NULLS LAST) - 1 AS k FROM d GROUP BY src),
w AS (SELECT *, k % 3 + 1 AS weight, 3 * source_size AS cap FROM s),
r AS (SELECT *, coalesce(sum(cap) OVER o, 0) AS cap_before, coalesce(sum(weight) OVER o, 0) AS weight_before,
        sum(source_size) OVER () AS budget, sum(weight) OVER () AS weights FROM w
      WINDOW o AS (ORDER BY cap / CAST(weight AS DOUBLE), k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
f AS (SELECT *, cap * (weights - weight_before) <= weight * (budget - cap_before) AS full_ FROM r),
g AS (SELECT *, budget - sum(CASE WHEN full_ THEN cap ELSE 0 END) OVER () AS left_words,
        sum(CASE WHEN full_ THEN 0 ELSE weight END) OVER () AS left_weight FROM f),
t AS (SELECT src, source_size, CASE WHEN full_ THEN CAST(cap AS DOUBLE)
        ELSE CAST(weight * left_words AS DOUBLE) / CAST(left_weight AS DOUBLE) END AS target FROM g),
q AS (SELECT *, CASE WHEN source_size > 0 THEN CAST(floor(target / source_size) AS BIGINT) ELSE 0 END AS whole FROM t),
x AS (SELECT d.doc_id, d.size, q.source_size, q.target, q.whole, q.target - q.whole * q.source_size AS wanted,
        coalesce(sum(d.size) OVER (PARTITION BY d.src ORDER BY u, d.size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS start
      FROM d JOIN q ON d.src IS NOT DISTINCT FROM q.src)
SELECT doc_id, size, CAST(source_size AS BIGINT) AS source_size, target,
    CAST(size * (whole + CASE WHEN start + size / 2.0 <= wanted THEN 1 ELSE 0 END) AS BIGINT) AS taken FROM x
"""
