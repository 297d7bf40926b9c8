"""String families that the unmodified parse cannot answer locally, and the extremes of its trie."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from trieaccess import kernels as K


def members(spark: SparkSession, k: int) -> DataFrame:
    """level i in 1..k-1, j in 1..2^i, and the j-th string of that length."""
    rows = spark.range(2, 1 << k).select(F.floor(F.log2("id") + 1e-12).cast("int").alias("i"), "id")
    j = F.col("id") - F.pow(F.lit(2), F.col("i")).cast("long")
    return rows.select("i", (j + 1).alias("j"), F.substring(F.bin("id"), 2, 64).alias("s"))


def joined(rows: DataFrame, *by: str) -> DataFrame:
    """The members in order as one text per `by`."""
    parts = F.array_sort(F.collect_list(F.struct("i", "j", "s")))
    return rows.groupBy(*by).agg(F.array_join(F.transform(parts, lambda p: p["s"]), "").alias("text"))


def perturb(ell: Column, k: int, mode: str) -> Column:
    """The ell-th member of length k-1 that begins with 01 becomes one of length k that begins with 00."""
    q = 1 << (k - 1) >> 2
    new = F.lit("0" * k) if mode == "formal" else F.concat(F.lit("00"), F.substring("s", 3, k), F.lit("0"))
    return F.when((ell > 0) & (F.col("i") == k - 1) & (F.col("j") == q + ell), new).otherwise(F.col("s"))


def family(spark: SparkSession, k: int, mode: str = "formal", lead: str = "") -> DataFrame:
    """seq_id 0 the complete order, 1..q its perturbations: (seq_id, text)."""
    q = 1 << (k - 1) >> 2
    rows = members(spark, k).join(F.broadcast(spark.range(q + 1).select(F.col("id").alias("seq_id"))))  # q + 1 copies are the family itself
    return joined(rows.select("seq_id", "i", "j", F.concat(F.lit(lead), perturb(F.col("seq_id"), k, mode)).alias("s")), "seq_id")


def distribution(spark: SparkSession, k: int, mode: str = "formal") -> DataFrame:
    """seq_id, text, weight: half on the complete order, the rest evenly on its perturbations."""
    q = 1 << (k - 1) >> 2
    return family(spark, k, mode).withColumn("weight", F.when(F.col("seq_id") == 0, 0.5).otherwise(1 / (2 * q)))


def extended(spark: SparkSession, k: int, t: int) -> DataFrame:
    """The general family: members led by 0 (the empty one too), then runs of ones up to t."""
    runs = F.array_join(F.transform(F.sequence(F.lit(1), F.lit(t)), lambda i: F.repeat(F.lit("1"), i)), "")
    return family(spark, k, "formal", "0").select("seq_id", F.concat(F.lit("0"), "text", runs).alias("text"))


def line_string(spark: SparkSession, j: int) -> DataFrame:
    """0, 01, 011, ...: the trie is a line."""
    text = F.array_join(F.transform(F.sequence(F.lit(0), F.lit(j - 1)), lambda i: F.concat(F.lit("0"), F.repeat(F.lit("1"), i))), "")
    return spark.range(1).select(F.col("id").alias("seq_id"), text.alias("text"))


PLACE = 1 << 27


def drawn(docs: DataFrame, members: int) -> DataFrame:
    """Texts draw strings over their own two letters: (a, b, member, seq_id, docs), a row a string that is drawn, with the number of texts that draw it.

    Letters are a text's first symbol and the first other one, 0 and 1 if there are fewer (null: both). The member is told by the md5 of the text (null: empty). seq_id holds
    all three, so it takes `members` up to 64."""
    text = F.coalesce("text", F.lit(""))
    a = F.substring(text, 1, 1)
    b = F.substring(F.expr("ltrim(substring(coalesce(text, ''), 1, 1), coalesce(text, ''))"), 1, 1)
    both = b != ""
    draw = F.pmod(F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(members))
    rows = docs.select(F.when(both, a).otherwise("0").alias("a"), F.when(both, b).otherwise("1").alias("b"), draw.alias("member"))
    rows = rows.groupBy("a", "b", "member").agg(F.count(F.lit(1)).alias("docs"))
    return rows.withColumn("seq_id", F.ascii("a").cast("long") * PLACE + F.ascii("b") * 64 + F.col("member"))


def lettered(rows: DataFrame, texts: DataFrame) -> DataFrame:
    """Strings of 0 and 1 (seq_id the member) written in the letters of each row of `drawn` that draws them."""
    own = texts.select(F.col("seq_id").alias("member"), "text")
    return rows.join(own, "member").withColumn("text", F.expr("translate(text, '01', concat(a, b))"))


def codeword_diff(phrases: DataFrame, own: str = "0L", member: str = "seq_id") -> DataFrame:
    """seq_id, phrase_no of members above 0 where the codeword differs from that of member 0 of the same family `own`."""
    own, member = F.expr(own), F.expr(member)
    base = phrases.where(member == 0).select(own.alias("own"), "phrase_no", F.struct("parent_no", "symbol").alias("w0"))
    other = phrases.where(member > 0).select("seq_id", own.alias("own"), "phrase_no", F.struct("parent_no", "symbol").alias("w"))
    return other.join(base.hint("merge"), ["own", "phrase_no"], "left").where(~F.col("w").eqNullSafe(F.col("w0"))).select("seq_id", "phrase_no")


def drawn_diff(phrases: DataFrame) -> DataFrame:
    """The same for strings of `drawn`: families are pairs of letters."""
    return codeword_diff(phrases, "shiftright(seq_id, 6)", "seq_id % 64")


def with_plain(rows: DataFrame) -> DataFrame:
    """Rows of `drawn`, and the complete order in each pair of letters."""
    first = rows.select("a", "b", F.lit(0).cast("long").alias("member"), (F.col("seq_id") - F.col("member")).alias("seq_id"))
    return rows.select("a", "b", "member", "seq_id").unionByName(first).distinct()


def whole_families(rows: DataFrame, k: int) -> DataFrame:
    """Every member in each pair of letters: (seq_id of the pair, member, text)."""
    q = 1 << (k - 1) >> 2
    every = rows.select("a", "b", (F.col("seq_id") - F.col("member")).alias("seq_id")).distinct().withColumn("member", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(q).cast("long"))))
    return lettered(every, family(rows.sparkSession, k)).select("seq_id", "member", "text")


def witness_positions(texts: DataFrame, own: str = "0L", member: str = "seq_id") -> DataFrame:
    """own, pos: positions whose symbol in the complete order differs from that in every perturbation of the family `own`."""
    texts = texts.select(F.expr(own).alias("own"), F.expr(member).alias("member"), "text")
    chars = texts.select("own", "member", F.posexplode(F.split("text", "")).alias("p", "c")).where("c <> ''")
    base = chars.where("member = 0").select("own", "p", F.col("c").alias("c0"))
    q = texts.where("member > 0").groupBy("own").agg(F.count(F.lit(1)).alias("q"))
    hit = chars.where("member > 0").join(base.hint("merge"), ["own", "p"]).where("c <> c0").groupBy("own", "p").agg(F.count(F.lit(1)).alias("n"))
    return hit.join(q, "own").where("n = q").select("own", (F.col("p") + 1).alias("pos"))


def probe_success(spark: SparkSession, k: int, budgets: tuple[int, ...], trials: int = 4000, seed: int = 3) -> DataFrame:
    """budget, success: a string is drawn from the distribution, `budget` codewords of its list are read at random places, and the symbol at a position that every
    perturbation changes is told: as in the complete order unless a codeword read differs from it. Beside it the closed form of uniform probes."""
    import random

    q = 1 << (k - 1) >> 2
    plain = [format(j, f"0{i}b") for i in range(1, k) for j in range(1 << i)]
    place = (1 << (k - 1)) - 2 + q  # members before the first that may change
    texts = ["".join(plain), *("".join([*plain[: place + e], "0" * k, *plain[place + e + 1 :]]) for e in range(q))]
    lists = [K.pack_base(K.base_parse(K.to_symbols(t))).tolist() for t in texts]  # (q + 1) lists of 2^k codewords: the family itself
    m, length = len(lists[0]), min(map(len, texts))
    asked = next(i for i in range(length) if all(t[i] != texts[0][i] for t in texts[1:]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for trial in b.column(0).to_pylist():
                for budget in budgets:
                    rng = random.Random(f"{seed}:{trial}:{budget}")
                    drawn = 0 if rng.random() < 0.5 else rng.randint(1, q)
                    differs = any(lists[drawn][i] != lists[0][i] for i in rng.sample(range(m), budget))
                    told = texts[1][asked] if differs else texts[0][asked]
                    rows.append((budget, float(told == texts[drawn][asked])))
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.float64())], names=["budget", "ok"])

    got = spark.range(0, trials, 1, spark.sparkContext.defaultParallelism).mapInArrow(run, "budget long, ok double")
    return got.groupBy("budget").agg(F.avg("ok").alias("success")).select(
        "budget", F.lit(m).alias("m"), F.lit(q).alias("q"), "success", (F.lit(0.5) + F.col("budget") / (2 * m)).alias("expected"))
