from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from trieaccess import kernels as K

SIZE = T.StructType([T.StructField(n, T.LongType()) for n in ("m", "m1", "m2", "m3", "words", "bits")])


def pack_text(text: Column, scheme: str = "dense", alphabet: str = "codepoint", alpha: float = 1 / 40, grid: int | None = 40, seed: int = 7) -> Column:
    """A text as a store in one cell; null stays null."""

    @F.arrow_udf(T.BinaryType())
    def tx_pack(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for b in batches:
            yield pa.array([None if t is None else K.pack(K.to_symbols(t, alphabet), scheme, alphabet, alpha, grid, seed) for t in b.to_pylist()], pa.binary())

    return tx_pack(text)


@F.arrow_udf(T.StringType())
def expand_blob(blobs: pa.Array) -> pa.Array:
    return pa.array([None if b is None else K.expand(b) for b in blobs.to_pylist()], pa.string())


@F.arrow_udf(T.StringType())
def substr_of(blobs: pa.Array, first: pa.Array, size: pa.Array) -> pa.Array:
    """`size` symbols from position `first` on, clipped at the end; null for a start outside the text."""
    out = []
    for blob, a, n in zip(blobs.to_pylist(), first.to_pylist(), size.to_pylist()):
        if blob is None or a is None or n is None:
            out.append(None)
            continue
        store, alphabet = K.open_store(blob)
        b = min(store.n, a + n - 1)
        out.append(K.from_symbols(store.substring(a, b)[0], alphabet) if 1 <= a <= b else None)
    return pa.array(out, pa.string())


def sizes(texts: pa.Array, alpha: float, grid: int | None, seed: int) -> pa.Array:
    rows = []
    for t in texts.to_pylist():
        if t is None:
            rows.append(None)
            continue
        p = K.base_parse(K.to_symbols(t))
        s = K.sparse_layout(p, K.coins(seed, 0, p.m, alpha), grid, K.block_size(max(1, p.n)))
        m2, m3 = int(s.special.sum()), len(s.position_phrase)
        rows.append({"m": p.m, "m1": p.m - m2, "m2": m2, "m3": m3, "words": s.n_words, "bits": s.n_words * (K.block_size(max(1, p.n)) + 1)})
    return pa.array(rows, pa.struct([(f.name, pa.int64()) for f in SIZE]))


def size_of(text: Column, alpha: float = 1 / 40, grid: int | None = 40, seed: int = 7) -> Column:
    """Codewords and words of the sparse scheme, and bits at ceil(log2 n) + 1 a word."""

    @F.arrow_udf(SIZE)
    def tx_size(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for b in batches:
            yield sizes(b, alpha, grid, seed)

    return tx_size(text)


class Codewords:
    def eval(self, text: str):
        if text is None:
            return
        p = K.base_parse(K.to_symbols(text))
        for i in range(1, p.m + 1):
            yield i, int(p.parent[i]), int(p.symbol[i]), int(p.depth[i]), int(p.start[i])


class DenseWords:
    def eval(self, text: str):
        if text is None:
            return
        p = K.base_parse(K.to_symbols(text))
        jump = K.tree_jumps(p.parent, p.depth, K.block_size(max(1, p.n)))
        for i in range(1, p.m + 1):
            yield i, int(p.start[i]), int(p.parent[i]), int(jump[i]) if jump[i] >= 0 else None, int(p.symbol[i])


class SparseWords:
    def eval(self, text: str, alpha: float = 1 / 40, grid: int = 40, seed: int = 7):
        if text is None:
            return
        p = K.base_parse(K.to_symbols(text))
        s = K.sparse_layout(p, K.coins(seed, 0, p.m, float(alpha)), grid, K.block_size(max(1, p.n)))
        for i in range(1, p.m + 1):
            yield i, int(p.parent[i]), int(p.symbol[i]), bool(s.special[i]), int(s.offset[i])


def dense_udtf():
    return F.udtf(DenseWords, returnType="phrase_no int, start_pos long, parent_no int, jump_no int, symbol int")


def sparse_udtf():
    return F.udtf(SparseWords, returnType="phrase_no int, parent_no int, symbol int, special boolean, word_off long")


def codewords_udtf():
    return F.udtf(Codewords, returnType="phrase_no int, parent_no int, symbol int, depth int, start_pos long")


def register(spark: SparkSession) -> None:
    """SQL names: tx_pack, tx_expand, tx_substr, tx_char_at, tx_size; the table functions tx_codewords, tx_dense, tx_sparse."""

    @F.arrow_udf(T.BinaryType())
    def tx_pack(texts: pa.Array) -> pa.Array:
        return pa.array([None if t is None else K.pack(K.to_symbols(t), "dense") for t in texts.to_pylist()], pa.binary())

    @F.arrow_udf(T.StringType())
    def tx_char_at(blobs: pa.Array, at: pa.Array) -> pa.Array:
        out = []
        for blob, pos in zip(blobs.to_pylist(), at.to_pylist()):
            store, alphabet = K.open_store(blob) if blob is not None else (None, "")
            out.append(K.from_symbols(np.array([store.symbol(pos)[0]]), alphabet) if store and pos and 1 <= pos <= store.n else None)
        return pa.array(out, pa.string())

    @F.arrow_udf(SIZE)
    def tx_size(texts: pa.Array) -> pa.Array:
        return sizes(texts, 1 / 40, 40, 7)

    for name, f in (("tx_size", tx_size), ("tx_pack", tx_pack), ("tx_expand", expand_blob), ("tx_substr", substr_of), ("tx_char_at", tx_char_at)):
        spark.udf.register(name, f)
    for name, f in (("tx_codewords", codewords_udtf()), ("tx_dense", dense_udtf()), ("tx_sparse", sparse_udtf())):
        spark.udtf.register(name, f)
