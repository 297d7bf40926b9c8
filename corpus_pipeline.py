"""A corpus pipeline of five operators; each stage works on what its predecessor kept.

All stages take nulls in any column: a null text is empty (not toxic, near to other empty texts, without passages, of size 0, one end token), a null source is a
source of its own, rows with a null id are rows like others. Repeated rows are near copies of each other: one stays. Ties go to the smaller id, then
to the smaller hash of the row. Texts are read whole, however long. An empty table gives an empty table. Extra columns go through
untouched, whatever their names, up to the last stage, which returns doc_id, start, n_tokens and ids_crc32.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trieaccess.llm import decontamination, mixing, simhash, tokens, toxicity
from trieaccess.llm.common import Scratch, boxed, table, text_bytes


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents scored 0.3 or more by a machine fitted on `labels` go; without labels of both kinds all have one score."""
    fm = toxicity.fit(docs, table(spark, sf_dir, "labels").select("doc_id", "toxic"))
    return docs.where(toxicity.score_column(fm) < 0.3)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near copies (five-word shingles, `simhash.CORPUS`) stays: that with the smallest id, null ids last; of rows with one id, that with the smallest hash.

    The rows to keep grow with the corpus, so texts and keys meet by a shuffle at every size.
    """
    scratch, rule = Scratch(spark, "stage-simhash"), simhash.CORPUS
    # a hash of the whole row, nulls told apart: rows alike in it are equal, so any of them may stay
    columns = [F.col(f"`{c}`") for c in docs.columns]
    key = F.xxhash64(*columns, *[c.isNull() for c in columns])
    marked = scratch.save(docs.select("doc_id", key.alias("key"), simhash.fingerprint(text_bytes(), rule).alias("mark")).select("doc_id", "key", "mark.*"), "rows")
    root = scratch.save(simhash.roots(marked, scratch, rule=rule).select("fp", "root"), "roots")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "key"))
    keep = scratch.save(simhash.by_fp(marked.select("doc_id", "key", "fp"), root).groupBy("root").agg(first.alias("first")).select(F.col("first.key").alias("kept")), "keep")
    rows = docs.select(boxed(docs), key.alias("key")).join(keep.hint("merge"), F.col("key") == F.col("kept")).dropDuplicates(["key"])
    return rows.select("row.*")


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a passage of `benchmark` go; an empty benchmark leaves all."""
    return decontamination.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as many times as the mix takes it."""
    others = tuple(c for c in docs.columns if c not in ("doc_id", "source"))
    mixed = mixing.mix(docs, keep=others).where("epochs > 0")
    copies = mixed.select("doc_id", "source", "_kept", F.explode(F.sequence(F.lit(1), F.col("epochs"))))
    return copies.select(*[F.col(c) if c in ("doc_id", "source") else F.col("_kept").getField(c).alias(c) for c in docs.columns])


def write_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of all rows in a store, in the order of the ids, null ids first; what the store holds is read back."""
    return tokens.tokenize_and_read(docs, tokens.public_vocabulary())


STAGES = [
    ("toxicity", drop_toxic),
    ("simhash near-dedup", drop_near_copies),
    ("benchmark decontamination", drop_leaks),
    ("source mixing", mix_sources),
    ("token output", write_tokens),
]

#: Hashing with XXH64, a trained model and a tokenizer are beyond SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = scratch.save(stage(spark, docs, sf_dir), f"stage{k}")
        if k:
            scratch.drop(f"stage{k - 1}")
    return docs
