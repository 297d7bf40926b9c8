"""Benchmark decontamination by the q-gram lemma.

Texts are compared after lower-casing A-Z and joining their words by single blanks. A passage of m bytes within k edits of
a region of a document shares at least m - q + 1 - k q of its q-grams with it, and all these lie on diagonals that span at most k + 1.
So shared q-grams are counted in diagonal bands of width 2 (k + 1) that overlap by half; a band below the bound is
discarded, the others are verified by a banded alignment with free ends. k is `edits` of the length, lowered where
the bound would fall under one gram. Passages shorter than q must occur exactly, on word boundaries.

The benchmark is taken in blocks of about `BLOCK_BYTES` of text, each sent to all tasks; one scan of the documents meets all of them. Shared
q-grams are expanded `EXPAND` at a time, so that a gram that repeats in passage and document costs time, not memory.

Nulls: null and empty texts or passages never match; a null item_id is kept as the id of its passage. Repeated passages count under each
id; repeated documents are judged each. Ties: the first band with the fewest edits. Empty tables: no rows. Extra columns are kept.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import in_slices, text_bytes

Q, BLOCK_BYTES, SLICE, BLOOM_BITS, EXPAND = 12, 1 << 20, 2 << 20, 22, 1 << 20
_K1, _K2, _K3 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9)
HITS = "array<struct<item_id: bigint, edits: int, shared: int, start_word: int>>"


def normal(text: bytes) -> bytes:
    return b" ".join(text.lower().split())


def gram_hashes(buf: bytes) -> np.ndarray:
    """A 64-bit hash of the 12 bytes at each position."""
    n = len(buf) - Q + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    h = np.ndarray((n,), "<u8", buf, strides=(1,)) * _K1
    h += np.ndarray((n,), "<u4", buf, 8, strides=(1,)).astype(np.uint64) * _K2
    h ^= h >> np.uint64(29)
    h *= _K3
    return h


def banded_edits(item: np.ndarray, doc: np.ndarray, low: int, high: int) -> tuple[int, int]:
    """(fewest edits, end in doc) of item against any region of doc whose alignment stays on diagonals low..high."""
    width = high - low + 1
    steps = np.arange(width)
    padded = np.full(len(item) + width, -1, np.int16)
    a, b = max(0, low), min(len(doc), low + len(padded))
    if b > a:
        padded[a - low : b - low] = doc[a:b]
    row = np.zeros(width, np.int64)
    for i, c in enumerate(item):
        best = row + (padded[i : i + width] != c)
        best[:-1] = np.minimum(best[:-1], row[1:] + 1)
        row = np.minimum.accumulate(best - steps) + steps
    d = int(row.argmin())
    return int(row[d]), min(len(doc), len(item) + low + d)


class Passages:
    """One block of the benchmark, indexed by its q-grams."""

    def __init__(self, items: list[tuple[int, bytes]], edits: float):
        items = [(i, normal(t)) for i, t in items]
        self.short = [(i, t) for i, t in items if 0 < len(t) < Q]
        items = [(i, t) for i, t in items if len(t) >= Q]
        self.ids, self.texts = [i for i, _ in items], [t for _, t in items]
        m = np.array([len(t) for t in self.texts], np.int64)
        self.k = np.minimum((edits * m).astype(np.int64), (m - Q) // Q)
        self.least = m - Q + 1 - self.k * Q
        grams = [gram_hashes(t) for t in self.texts]
        flat = np.concatenate(grams) if grams else np.zeros(0, np.uint64)
        order = np.argsort(flat, kind="stable")
        self.gram = flat[order]
        self.item = np.repeat(np.arange(len(items)), [len(g) for g in grams])[order]
        self.at = np.concatenate([np.arange(len(g)) for g in grams])[order] if grams else np.zeros(0, np.int64)
        self.bloom = np.zeros(1 << BLOOM_BITS, bool)
        self.bloom[flat >> np.uint64(64 - BLOOM_BITS)] = True

    def _bands(self, pos: np.ndarray, owner: np.ndarray, lo: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Hits (position in its document, document, first index entry, entries) -> (document * passages + passage, band, shared grams), `EXPAND` at a time."""
        total: tuple[np.ndarray, ...] = ()
        ends = np.cumsum(n)
        for a in range(0, int(ends[-1]), EXPAND):
            b = min(a + EXPAND, int(ends[-1]))
            i, j = np.searchsorted(ends, a, "right"), np.searchsorted(ends, b, "left") + 1
            first = np.maximum(ends[i:j] - n[i:j], a)  # the part of each hit that lies in a..b
            some = np.minimum(ends[i:j], b) - first
            g = np.repeat(lo[i:j] + first - (ends[i:j] - n[i:j]) - np.concatenate([[0], np.cumsum(some)[:-1]]), some) + np.arange(b - a)
            item = self.item[g]
            diag = np.repeat(pos[i:j], some) - self.at[g]
            pair = np.repeat(owner[i:j], some) * len(self.ids) + item
            band = np.floor_divide(diag, self.k[item] + 1)
            key, count = np.unique(np.r_[pair, pair] << 32 | (np.r_[band, band - 1] + (1 << 31)), return_counts=True)
            if total:
                merged, at = np.unique(np.r_[total[0], key], return_inverse=True)
                key, count = merged, np.bincount(at, np.r_[total[1], count]).astype(np.int64)
            total = key, count
        key, count = total
        return key >> 32, (key & 0xFFFFFFFF) - (1 << 31), count

    def find(self, texts: list[bytes]) -> list[list[dict]]:
        docs = [normal(t) for t in texts]
        out: list[list[dict]] = [[] for _ in docs]
        for item, t in self.short:
            for d, doc in enumerate(docs):
                at = (b" " + doc + b" ").find(b" " + t + b" ")
                if at >= 0:
                    out[d].append({"item_id": item, "edits": 0, "shared": 0, "start_word": doc[:at].count(b" ")})
        if not len(self.gram):
            return out
        buf = b"\0".join(docs)
        size = np.array([len(d) for d in docs], np.int64)
        start = np.concatenate([[0], np.cumsum(size + 1)[:-1]])
        h = gram_hashes(buf)
        pos = np.flatnonzero(self.bloom[h >> np.uint64(64 - BLOOM_BITS)])
        lo, hi = np.searchsorted(self.gram, h[pos], "left"), np.searchsorted(self.gram, h[pos], "right")
        pos, lo, n = pos[hi > lo], lo[hi > lo], (hi - lo)[hi > lo]
        owner = np.searchsorted(start, pos, "right") - 1
        within = pos + Q <= start[owner] + size[owner]
        pos, lo, n, owner = pos[within], lo[within], n[within], owner[within]
        if not len(pos):
            return out
        pair, band, count = self._bands(pos - start[owner], owner, lo, n)
        good = count >= self.least[pair % len(self.ids)]
        best: dict[int, dict] = {}
        for p, j, shared in zip(pair[good].tolist(), band[good].tolist(), count[good].tolist()):
            d, i = divmod(p, len(self.ids))
            if p in best and best[p]["edits"] == 0:
                continue
            k, t, doc = int(self.k[i]), self.texts[i], docs[d]
            low, high = j * (k + 1) - k, (j + 2) * (k + 1) - 1 + k
            at = doc.find(t, max(0, low), max(0, high) + len(t))
            edits, end = (0, at + len(t)) if at >= 0 else banded_edits(np.frombuffer(t, np.uint8), np.frombuffer(doc, np.uint8), low, high)
            if edits <= k and (p not in best or edits < best[p]["edits"]):
                best[p] = {"item_id": self.ids[i], "edits": edits, "shared": shared, "start_word": doc[: max(0, end - len(t))].count(b" ")}
        for p, hit in best.items():
            out[p // len(self.ids)].append(hit)
        return out


def blocks(benchmark: DataFrame, edits: float = 0.05) -> Iterator[Passages]:
    """The benchmark's passages in blocks of bounded size."""
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), text_bytes().alias("t")).where(F.length("t") > 0)
    total = items.agg(F.sum(F.length("t"))).first()[0] or 0
    n = max(1, -(-total // BLOCK_BYTES))
    for b in range(n):
        own = items.where(F.pmod(F.xxhash64("item_id", "t"), F.lit(n)) == b).collect()  # about BLOCK_BYTES
        yield Passages(sorted((tuple(r) for r in own), key=lambda r: (r[0] is None, r)), edits)


def hits_column(block: Passages) -> Column:
    @F.arrow_udf(HITS)
    def leaks(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        kind = pa.list_(pa.struct([("item_id", pa.int64()), ("edits", pa.int32()), ("shared", pa.int32()), ("start_word", pa.int32())]))
        for batch in batches:
            raw, found = batch.to_pylist(), []
            for i, j in in_slices([len(t) for t in raw], SLICE):
                found += block.find(raw[i:j])
            yield pa.array(found, kind)

    return leaks(text_bytes())


def all_hits(benchmark: DataFrame, edits: float) -> Column:
    """The hits of all blocks of the benchmark: one scan of the documents meets them all."""
    return F.concat(*[hits_column(b) for b in blocks(benchmark, edits)])


def find_leaks(docs: DataFrame, benchmark: DataFrame, edits: float = 0.05) -> DataFrame:
    """doc_id, item_id, edits, shared, start_word: one row for each passage found in a document."""
    return docs.select("doc_id", all_hits(benchmark, edits).alias("hits")).where(F.size("hits") > 0).select("doc_id", F.inline("hits"))


def decontaminate(docs: DataFrame, benchmark: DataFrame, edits: float = 0.05) -> DataFrame:
    """`docs` without the documents that hold a passage."""
    return docs.where(F.size(all_hits(benchmark, edits)) == 0)
