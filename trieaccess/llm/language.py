"""Language identification by nearest centroid.

A text becomes the vector of its byte trigrams (A-Z lower-cased, other ASCII but letters as one blank each, runs kept),
hashed to `DIMS` slots, weighted (1 + log tf) * idf and normalised. Each language has up to `CLUSTERS` centroids from spherical
k-means on a sample of at most about `per_lang` labelled texts of it (a documented bound), each language in a task of its own.
The idf is that of the sample. Languages are scored in groups of `GROUP`, so that any number of them can be told apart.
The prediction is the language of the centroid with the largest cosine, which is the score. A text further from its
centroid than all but `reject` of that centroid's own texts is marked `rejected`.

Nulls: a null text, or one without a letter, is `und` with score 0. Rows with null lang or id don't teach. Ties
between centroids go to the smaller language code. Without any labelled text all are `und`. Repeated
rows are scored each. Empty table: empty result. Extra columns are kept; those
named like an output are replaced.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import Scratch, boxed, crc_mod, in_slices, text_bytes, unboxed

DIMS, CLUSTERS, GROUP = 4096, 3, 256
_TABLE = bytes(b + 32 if 65 <= b <= 90 else b if 97 <= b <= 122 or b > 127 else 32 for b in range(256))
SLICE, ROWS = 1 << 20, 64  # texts are counted at most 64 at a time: a row of counts is dense


def slices(texts: list[bytes]) -> Iterator[tuple[int, int]]:
    return in_slices([max(len(t), SLICE // ROWS) for t in texts], SLICE)


def trigram_counts(texts: list[bytes]) -> np.ndarray:
    """One row of hashed trigram counts a text."""
    padded = [b" " + t.translate(_TABLE) + b" " for t in texts]
    sizes = np.array([len(p) for p in padded])
    a = np.frombuffer(b"".join(padded), np.uint8).astype(np.uint32)
    code = (a[:-2] << 16) | (a[1:-1] << 8) | a[2:]
    slot = ((code * np.uint32(2654435761)) >> np.uint32(20)).astype(np.int64) % DIMS
    owner = np.repeat(np.arange(len(texts)), sizes)[: len(slot)]
    ends = np.cumsum(sizes)
    inside = np.ones(len(slot), bool)  # no trigram across two texts
    for e in ends[:-1]:
        inside[max(0, e - 2) : e] = False
    return np.bincount(owner[inside] * DIMS + slot[inside], minlength=len(texts) * DIMS).reshape(len(texts), DIMS)


def vectors(counts: np.ndarray, idf: np.ndarray) -> np.ndarray:
    x = np.where(counts > 0, 1 + np.log(np.maximum(counts, 1)), 0).astype(np.float32) * idf
    return x / np.maximum(1e-12, np.linalg.norm(x, axis=1, keepdims=True))


def spherical_kmeans(x: np.ndarray, k: int, rounds: int = 8) -> np.ndarray:
    """Unit centroids; the first is the text nearest to the mean, each next one the text furthest from those before."""
    mean = x.mean(0)
    seeds = [int(np.argmax(x @ mean))]
    while len(seeds) < min(k, len(x)):
        seeds.append(int(np.argmin((x @ x[seeds].T).max(1))))
    c = x[seeds]
    for _ in range(rounds):
        own = (x @ c.T).argmax(1)
        c = np.stack([x[own == j].mean(0) if (own == j).any() else c[j] for j in range(len(c))])
        c /= np.maximum(1e-12, np.linalg.norm(c, axis=1, keepdims=True))
    return c


class Centroids:
    def __init__(self, idf: np.ndarray, langs: list[str], c: np.ndarray, floor: np.ndarray):
        self.idf, self.langs, self.c, self.floor = idf, langs, c, floor

    def nearest(self, texts: list[bytes]) -> tuple[list[str], np.ndarray, np.ndarray]:
        cos = vectors(trigram_counts(texts), self.idf) @ self.c.T
        best = cos.argmax(1)
        score = cos[np.arange(len(texts)), best]
        return [self.langs[i] for i in best], np.clip(score, 0, 1).astype(float), score < self.floor[best]


def _frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """In how many texts each slot occurs: one row a task."""
    n, df = 0, np.zeros(DIMS, np.int64)
    for b in batches:
        texts = b.column(0).to_pylist()
        for i, j in slices(texts):
            df += (trigram_counts(texts[i:j]) > 0).sum(0)
            n += j - i
    yield pa.RecordBatch.from_pydict({"n": pa.array([n], pa.int64()), "df": pa.array([df.tolist()], pa.list_(pa.int64()))})


def _train(idf: np.ndarray, reject: float):
    """The texts of one language -> its centroids and the cosine below which a text is rejected."""

    def run(key: tuple[pa.Scalar, ...], rows: pa.Table) -> pa.Table:
        texts = sorted(rows.column("t").to_pylist())
        x = np.concatenate([vectors(trigram_counts(texts[i:j]), idf) for i, j in slices(texts)])
        c = spherical_kmeans(x, CLUSTERS)
        cos = x @ c.T
        near = cos.argmax(1)
        floor = [float(np.quantile(cos[near == j, j], reject)) if (near == j).any() else 0.0 for j in range(len(c))]
        return pa.table({"lang": pa.array([key[0].as_py()] * len(c), pa.string()), "centroid": pa.array(c.astype(float).tolist(), pa.list_(pa.float64())), "floor": pa.array(floor, pa.float64())})

    return run


def fit(docs: DataFrame, per_lang: int = 800, reject: float = 0.005, scratch: Scratch | None = None) -> list[Centroids]:
    """Groups of languages in the order of their codes; none without labelled texts."""
    scratch = scratch or Scratch(docs.sparkSession, "lang")
    teach = docs.where(F.col("lang").isNotNull() & F.col("text").rlike(r"\p{L}") & (crc_mod("doc_id", 4) != 2)).select("doc_id", "lang", text_bytes().alias("t"))
    seen = scratch.save(teach.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).withColumnRenamed("lang", "l"), "counts")  # usable texts only: the rate is over what can teach
    u = F.pmod(F.xxhash64("doc_id", F.lit(11)), F.lit(1 << 20))
    sample = teach.join(seen, F.col("lang") == F.col("l")).where(u * F.col("n") < F.lit(per_lang * (1 << 20))).select("t", "lang")
    sample = scratch.save(sample, "sample")
    df = sample.select("t").mapInArrow(_frequencies, "n long, df array<long>").select("n", F.posexplode("df").alias("slot", "df"))
    df = df.groupBy("slot").agg(F.sum("n").alias("n"), F.sum("df").alias("df")).orderBy("slot").collect()  # DIMS rows
    if not df or not df[0].n:
        return []
    idf = np.log((1 + df[0].n) / (1 + np.array([r.df for r in df]))).astype(np.float32) + 1
    rows = sample.groupBy("lang").applyInArrow(_train(idf, reject), "lang string, centroid array<double>, floor double").orderBy("lang").collect()  # CLUSTERS a language
    langs = sorted({r.lang for r in rows})
    groups = [set(langs[a : a + GROUP]) for a in range(0, len(langs), GROUP)]
    return [Centroids(idf, [r.lang for r in rows if r.lang in g], np.array([r.centroid for r in rows if r.lang in g], np.float32), np.array([r.floor for r in rows if r.lang in g])) for g in groups]


JUDGED = T.StructType([T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType()), T.StructField("rejected", T.BooleanType())])


def judge_column(model: Centroids, text: Column) -> Column:
    """Struct of the nearest language, its cosine and whether it is too far; null for a null text."""

    @F.arrow_udf(JUDGED)
    def judge(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for batch in texts:
            raw = batch.to_pylist()
            names, scores, far = [], [], []
            for i, j in slices([t or b"" for t in raw]):
                n, s, r = model.nearest([t or b"" for t in raw[i:j]])
                names += n
                scores += s.tolist()
                far += r.tolist()
            none = pa.array([t is None for t in raw])
            yield pa.StructArray.from_arrays([pa.array(names, pa.string()), pa.array(scores, pa.float64()), pa.array(far, pa.bool_())], names=["lang_pred", "score", "rejected"], mask=none)

    return judge(text)


def judged(model: list[Centroids]) -> Column:
    worded = F.when(F.col("text").rlike(r"\p{L}"), F.col("text").cast("binary"))
    none = F.struct(F.lit("und").alias("lang_pred"), F.lit(0.0).alias("score"), F.lit(True).alias("rejected"))
    found = [judge_column(m, worded) for m in model]
    best = functools.reduce(lambda a, b: F.when(b["score"] > a["score"], b).otherwise(a), found) if found else none
    return F.coalesce(best, none)


def predict(docs: DataFrame, model: list[Centroids]) -> DataFrame:
    """`docs` with lang_pred, score, rejected."""
    rows = docs.select(boxed(docs), judged(model).alias("j"))
    return unboxed(docs, rows, **{c: F.col("j")[c] for c in ("lang_pred", "score", "rejected")})


def identify(docs: DataFrame, per_lang: int = 800) -> DataFrame:
    """`docs` with held_out, lang_pred, score, rejected."""
    rows = docs.select(boxed(docs), F.coalesce(crc_mod("doc_id", 4) == 2, F.lit(False)).alias("held_out"), judged(fit(docs, per_lang)).alias("j"))
    return unboxed(docs, rows, held_out=F.col("held_out"), **{c: F.col("j")[c] for c in ("lang_pred", "score", "rejected")})
