"""Size, ratio and read-cost measures."""

from __future__ import annotations

import math
import time
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from trieaccess import kernels as K

from . import codec


PARAMS = "array<struct<alpha: double, grid: int, m2: long, m3: long, words: long>>"


def sweep(segs: DataFrame, params: list[tuple[float, int | None]], seed: int = 7) -> DataFrame:
    """seq_id, seg_no, n, w, alpha, grid (0: none), m1, m2, m3, dense_words, sparse_words: every segment is parsed once for all (alpha, grid)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("alpha", pa.float64()), ("grid", pa.int32()), ("m2", pa.int64()), ("m3", pa.int64()), ("words", pa.int64())]))
        for b in batches:
            rows = []
            for seq, no, text in zip(*(c.to_pylist() for c in b.columns)):
                p, per = K.base_parse(K.to_symbols(text)), []
                for alpha, grid in params:
                    s = K.sparse_layout(p, K.coins(seed, seq, p.m, alpha), grid, K.block_size(max(1, p.n)))
                    per.append({"alpha": alpha, "grid": grid or 0, "m2": int(s.special.sum()), "m3": len(s.position_phrase), "words": s.n_words})
                rows.append((seq, no, p.n, p.m, per))
            columns = list(zip(*rows)) or [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), kind))], names=["seq_id", "seg_no", "n", "w", "per"])

    rows = segs.select("seq_id", "seg_no", "text").mapInArrow(run, f"seq_id long, seg_no int, n long, w long, per {PARAMS}")
    rows = rows.select("seq_id", "seg_no", "n", "w", F.inline("per"))
    return rows.select("seq_id", "seg_no", "n", "w", "alpha", "grid", (F.col("w") - F.col("m2")).alias("m1"), "m2", "m3", (3 * F.col("w")).alias("dense_words"), F.col("words").alias("sparse_words"))


def word_counts(segs: DataFrame, alpha: float, grid: int | None, seed: int = 7) -> DataFrame:
    """seq_id, seg_no, n, w, m1, m2, m3, dense_words, sparse_words: dense is 3 w, sparse m1 + 5 m2 + 2 m3."""
    return sweep(segs, [(alpha, grid)], seed).drop("alpha", "grid")


def competitive_ratio(words: DataFrame, variant: str, by: tuple[str, ...] = ()) -> DataFrame:
    """Worst, mean and corpus-wide ratio of a variant to the base words."""
    r = F.col(variant) / F.col("w")
    return words.where("w > 0").groupBy(*by).agg(F.max(r).alias("worst"), F.avg(r).alias("mean"), (F.sum(variant) / F.sum("w")).alias("corpus"), F.sum("w").alias("w"), F.sum(variant).alias("words"))


def word_bits(n: Column, model: str = "n", m: Column | None = None, sigma: Column | None = None) -> Column:
    """Bits a word: ceil(log2 n) + 1; with model 'm' words of ceil(log2 m) + 1; with 'alphabet' ceil(log2 n) + ceil(log2 sigma)."""
    width = F.ceil(F.log2(F.greatest(m if model == "m" else n, F.lit(2))))
    return width + (F.ceil(F.log2(F.greatest(sigma, F.lit(2)))) if model == "alphabet" else 1)


def size_bits(words: DataFrame) -> DataFrame:
    """Of `word_counts`: bits of the three schemes with words of log n, and words in units of log m, where a position takes two:
    dense 4 a codeword, sparse 2 more a special (a depth and a start need no more than the square of m) and 1 more a position codeword."""
    n_bits, m_bits = word_bits(F.col("n")), word_bits(F.col("n"), "m", F.col("w"))
    dense_m, sparse_m = 4 * F.col("w"), F.col("sparse_words") + F.col("m2") + F.col("m3")
    return words.where("w > 0").select(
        "seq_id", "seg_no", "w", (F.col("w") * n_bits).alias("base_bits"), (F.col("dense_words") * n_bits).alias("dense_bits"), (F.col("sparse_words") * n_bits).alias("sparse_bits"),
        dense_m.alias("dense_words_m"), sparse_m.alias("sparse_words_m"), (dense_m * m_bits).alias("dense_bits_m"), (sparse_m * m_bits).alias("sparse_bits_m"))


def special_tail(segs: DataFrame, eps: float, seeds: int, c: int = 40) -> DataFrame:
    """Share of (sequence, seed) runs with more than eps / 20 of the codewords special."""

    def per(seq: int, p: K.Parse) -> dict[str, int]:
        over = sum(int(K.coins(s, seq, p.m, eps / c).sum() > eps / 20 * p.m) for s in range(seeds))
        return {"over": over, "m": p.m}

    v = codec.counts(segs, per)
    return v.agg((F.sum(F.col("values")["over"]) / (F.count(F.lit(1)) * seeds)).alias("share_over"), F.sum(F.col("values")["m"]).alias("codewords"), F.count(F.lit(1)).alias("sequences"))


def eps_sweep(segs: DataFrame, eps: tuple[float, ...], c: int = 40, seed: int = 7) -> DataFrame:
    """Corpus-wide ratio of the sparse scheme with special share eps / c and a position every c / eps words."""
    params = [K.sparse_params(e, c) for e in eps]
    words = sweep(segs, params, seed).where("w > 0").groupBy("alpha", "grid").agg(
        F.max(F.col("sparse_words") / F.col("w")).alias("worst"), (F.sum("sparse_words") / F.sum("w")).alias("corpus"), F.sum("w").alias("w"), F.sum("sparse_words").alias("words"))
    return words.select((F.col("alpha") * c).alias("eps"), "corpus", "worst", (1 + F.col("alpha") * c).alias("bound"), "w", "words")


def alpha_sizes(segs: DataFrame, alphas: tuple[float, ...], seed: int = 7, grid: int | None = None) -> DataFrame:
    """Codewords and words for each share of special codewords."""
    t = sweep(segs, [(a, grid) for a in alphas], seed).groupBy("alpha").agg(F.sum("n").alias("n"), F.sum("w").alias("w"), F.sum("m2").alias("m2"), F.sum("m3").alias("m3"), F.sum("sparse_words").alias("words"))
    return t.select("alpha", "n", "w", "m2", "m3", "words", (F.col("words") / F.col("w")).alias("word_ratio"))


def byte_sizes(segs: DataFrame, alphas: tuple[float, ...], grid: int | None = None, seed: int = 7) -> DataFrame:
    """alpha, n, bytes: the length of the byte stores that are written, summed over the segments. A store for each alpha is what is measured."""
    out = None
    for a in alphas:
        part = codec.compress_bytes(segs, a, grid, seed).agg(F.sum("seg_len").alias("n"), F.sum(F.octet_length("blob")).alias("bytes")).select(F.lit(a).alias("alpha"), "n", "bytes")
        out = part if out is None else out.unionByName(part)
    return out


def access_times(segs: DataFrame, requests: int = 2000, seed: int = 1) -> DataFrame:
    """seq_id, seg_no, n, and in ms, in one thread: access (mean over random positions) and expansion of the sparse store, and what the base store needs to find a position."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for seq, no, text in zip(*(c.to_pylist() for c in b.columns)):
                symbols, rng = K.to_symbols(text), np.random.default_rng(seed)
                if not len(symbols):
                    continue
                blob, plain = K.pack(symbols, "sparse", alpha=1 / 16, grid=64), K.pack(symbols, "base")
                store = K.open_store(blob, requests)[0]
                asks = rng.integers(1, len(symbols) + 1, requests).tolist()
                began = time.perf_counter()
                for a in asks:
                    store.symbol(a)
                access = (time.perf_counter() - began) / requests
                began = time.perf_counter()
                K.expand(plain)
                expand = time.perf_counter() - began
                yield pa.RecordBatch.from_pydict({"seq_id": pa.array([seq], pa.int64()), "seg_no": pa.array([no], pa.int32()), "n": pa.array([len(symbols)], pa.int64()),
                                                  "access_ms": pa.array([access * 1000]), "expand_ms": pa.array([expand * 1000])})

    return segs.select("seq_id", "seg_no", "text").mapInArrow(run, "seq_id long, seg_no int, n long, access_ms double, expand_ms double")


def access_bounds(segs: DataFrame, eps: tuple[float, ...], lengths: tuple[int, ...], requests: int = 400, seeds: int = 3, c: int = 40) -> DataFrame:
    """n, eps, mean and largest reads of random accesses to the sparse store of the first n symbols of each segment over several coins, the same over
    log2 n + 1 / eps^2, and the share above log2 n / eps^2 times the constant c, which should vanish; and the mean with a memo shared by a store's requests."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for seq, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                whole, rows = K.to_symbols(text), []
                for n in lengths:
                    if n > len(whole):
                        continue
                    for e in eps:
                        alpha, grid = K.sparse_params(e, c)
                        reads, memo = [], []
                        for seed in range(seeds):
                            blob = K.pack(whole[:n], "sparse", alpha=alpha, grid=grid, seed=seed, seq_id=seq)
                            asks = np.random.default_rng(seed).integers(1, n + 1, requests).tolist()
                            one, two = K.open_store(blob, requests)[0], K.open_store(blob, requests, memo=True)[0]
                            reads += [one.symbol(a)[1].total for a in asks]
                            memo += [two.symbol(a)[1].total for a in asks]
                        log = math.log2(n)
                        rows.append((seq, n, e, float(np.mean(reads)), max(reads), float(np.mean(reads)) / (log + 1 / e**2), float(np.mean(np.array(reads) > c * log / e**2)), float(np.mean(memo))))
                names = ["seq_id", "n", "eps", "mean_reads", "max_reads", "mean_over_bound", "share_over_tail", "mean_reads_memo"]
                kinds = [pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.int64(), pa.float64(), pa.float64(), pa.float64()]
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(list(zip(*rows)) or [[]] * 8, kinds)], names=names)

    return segs.select("seq_id", "text").mapInArrow(run, "seq_id long, n long, eps double, mean_reads double, max_reads long, mean_over_bound double, share_over_tail double, mean_reads_memo double")


def reads_report(answers: DataFrame) -> DataFrame:
    """Mean and largest number of codewords read in each phase of an access."""
    hops = ("reads_locate", "hops_align", "hops_jump", "hops_parent")
    return answers.where("status = 'ok'").agg(F.count(F.lit(1)).alias("requests"), *[F.avg(h).alias(f"mean_{h}") for h in hops], *[F.max(h).alias(f"max_{h}") for h in hops])


def segment_penalty(seqs: DataFrame, capacity: int) -> DataFrame:
    """Codewords of segments of `capacity` symbols over those of whole sequences."""
    m = lambda segs: codec.counts(segs, lambda _, p: {"m": p.m}).agg(F.sum(F.col("values")["m"]).alias("m"))
    cut, whole = m(codec.cut(seqs, capacity)).select(F.col("m").alias("m_cut")), m(codec.cut(seqs)).select(F.col("m").alias("m_whole"))
    return cut.join(whole).select("m_cut", "m_whole", (F.col("m_cut") / F.col("m_whole")).alias("penalty"))  # two single rows


def order0_bits(seqs: DataFrame) -> DataFrame:
    """Context only: the order-0 entropy of the symbols, in bits."""
    freq = seqs.select(F.explode(F.split("text", "")).alias("c")).where("c <> ''").groupBy("c").agg(F.count(F.lit(1)).alias("k"))
    return freq.agg(F.sum("k").alias("n"), (F.sum(F.col("k") * F.log2("k"))).alias("klogk")).select("n", (F.col("n") * F.log2("n") - F.col("klogk")).alias("bits"))


def deflate_bytes(seqs: DataFrame, level: int = 6) -> DataFrame:
    """seq_id, n_bytes, deflated: the size under a sliding-window coder, which the method is not compared with; for orientation only."""

    @F.arrow_udf("long")
    def deflated(texts: pa.Array) -> pa.Array:
        return pa.array([len(zlib.compress(t.encode(), level)) for t in texts.to_pylist()], pa.int64())

    text = F.col("text")
    return seqs.where(text.isNotNull()).select("seq_id", F.octet_length(text).cast("long").alias("n_bytes"), deflated(text).alias("deflated"))
