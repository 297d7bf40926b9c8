"""SimHash near-dedup with pigeonhole blocks.

Fingerprint: the bitwise majority of the XXH64 values (seed 42) of a text's word shingles. How many words a shingle has, how many bits may differ
and into how many blocks a fingerprint is split is a `Rule`. Two fingerprints that differ in at most `radius` bits agree on at least
blocks - radius blocks, so each distinct fingerprint is filed under every choice of that many blocks (4 bits, 7 blocks: 35
triples) and only fingerprints filed together are compared. Inside a bucket no pairs are listed: a flood fill from its smallest
fingerprint removes what it reaches, so a dense bucket of m members costs few scans and gives at most m - 1 links.

With a `total`, fingerprints filed together are linked if they differ in at most `total` of 128 bits, whatever the first 64 differ by; the
others are a second, independent fingerprint (the smallest among texts with one first fingerprint). That finds most pairs beyond the
radius too, and keeps strangers apart in a large corpus.

A bucket of more than `WIDE` distinct fingerprints is not kept in one task: its members stream out and are filed anew under
the choices of half of the halves of the other blocks (again a pigeonhole, so no link within the radius is lost; pairs beyond it, which a
`total` allows, are found there only if they share such halves). Components come from alternating large-star / small-star steps; a
node with very many links is salted.

Nulls: null and empty texts, and those of white space only, have fingerprint zero and are linked like any other. Ties and repeated
rows share a component; a null doc_id never names a component unless no other id does. Very long texts are whole, hashed in slices. Empty
table: empty result. Extra columns are left out: join by doc_id.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import Scratch, text_bytes

SEED, WIDE, SALTS = 42, 4096, 16


@dataclass(frozen=True)
class Rule:
    """What counts as near: shingles of `shingle` words, at most `radius` of 64 bits; or, with a `total`, blocks - radius equal blocks and at most that many of 128 bits."""

    shingle: int = 4
    radius: int = 4
    blocks: int = 7
    total: int | None = None

    @cached_property
    def spans(self) -> tuple[tuple[int, int], ...]:
        """(first bit, bits) of each block."""
        at = [64 * i // self.blocks for i in range(self.blocks + 1)]
        return tuple((x, y - x) for x, y in zip(at, at[1:]))

    @cached_property
    def keys(self) -> tuple[tuple[int, ...], ...]:
        """The choices of blocks that two near fingerprints may agree on."""
        return tuple(combinations(range(self.blocks), self.blocks - self.radius))

    def halves(self, i: int) -> list[tuple[int, int]]:
        """Half blocks of those that choice i leaves out: 2 * radius of them, of which near fingerprints agree on `radius`."""
        rest = [self.spans[x] for x in range(self.blocks) if x not in self.keys[i]]
        return [h for at, n in rest for h in ((at, n // 2), (at + n // 2, n - n // 2))]


EXACT = Rule()  # what the fingerprint query states
CORPUS = Rule(shingle=5, radius=6, blocks=10, total=19)  # for a corpus stage: five words; sets of similarity 0.8 have a cosine of 8/9, an angle of 27 degrees, 19 of 128 bits
BATCH_SHINGLES = 1 << 17


def shingle_hashes(text: bytes, shingle: int = EXACT.shingle) -> np.ndarray:
    from xxhash import xxh64_intdigest

    words = text.lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    joined = b" ".join(words)
    if len(words) <= shingle:
        return np.array([xxh64_intdigest(joined, SEED)], np.uint64)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = [0, *(ends[: len(words) - shingle] + 1).tolist()]
    return np.array([xxh64_intdigest(joined[a:b], SEED) for a, b in zip(starts, ends[shingle - 1 :].tolist())], np.uint64)


def simhash(h: np.ndarray) -> int:
    if not len(h):
        return 0
    ones = np.zeros(64, np.int64)
    for a in range(0, len(h), BATCH_SHINGLES):
        part = h[a : a + BATCH_SHINGLES]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.uint32)
    return int(np.packbits(2 * ones > len(h), bitorder="little").view(np.uint64)[0])


def second_hash(h: np.ndarray) -> np.ndarray:
    """Other 64 bits of the same shingles: a finaliser of the multiply-shift kind."""
    x = (h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    return (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)


MARK = T.StructType([T.StructField("fp", T.LongType()), T.StructField("more", T.LongType())])


def fingerprint(text: Column, rule: Rule = EXACT) -> Column:
    """(fp, more): 64 bits, and the second 64 or 0."""

    @F.arrow_udf(MARK)
    def marks(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for batch in texts:
            fp, more = [], []
            for t in batch:
                h = shingle_hashes(t.as_py(), rule.shingle)
                fp.append(simhash(h))
                more.append(0 if rule.total is None else simhash(second_hash(h)))
            yield pa.StructArray.from_arrays([pa.array(np.array(x, np.uint64).view(np.int64)) for x in (fp, more)], names=["fp", "more"])

    return marks(text)


def spanning_links(a: np.ndarray, more: np.ndarray, rule: Rule) -> tuple[np.ndarray, np.ndarray]:
    """Links (smallest of its group, member) that connect the distinct fingerprints `a` exactly as all near pairs would."""
    order = np.argsort(a, kind="stable")
    left, mark, low, high = a[order], more[order], [], []
    while len(left) > 1:
        root, todo, left, mark = left[0], [(left[0], mark[0])], left[1:], mark[1:]
        while todo and len(left):
            x, m = todo.pop()
            close = near(left, mark, x, m, rule)
            if close.any():
                found = left[close]
                low.append(np.full(len(found), root))
                high.append(found)
                todo.extend(zip(found, mark[close]))
                left, mark = left[~close], mark[~close]
    empty = np.zeros(0, a.dtype)
    return (np.concatenate(low), np.concatenate(high)) if low else (empty, empty)


def near(a, more_a, b, more_b, rule: Rule) -> np.ndarray:
    """Of fingerprints (unsigned) filed together."""
    first = np.bitwise_count(a ^ b)
    return first <= rule.radius if rule.total is None else first + np.bitwise_count(more_a ^ more_b) <= rule.total


def _bits(fp: np.ndarray, spans) -> np.ndarray:
    out = np.zeros(len(fp), np.uint64)
    for at, n in spans:
        out = (out << np.uint64(n)) | ((fp >> np.uint64(at)) & np.uint64((1 << n) - 1))
    return out


FILED = "key long, key2 long, fp long, more long"


def _file(rule: Rule):
    """(fp, more) -> (key, key2, fp, more) for each choice of blocks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = b.column(0).to_numpy().view(np.uint64)
            for i, t in enumerate(rule.keys):
                key = _bits(fp, [rule.spans[x] for x in t]) | np.uint64(i << 32)
                yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(np.zeros(len(fp), np.int64)), b.column(0), b.column(1)], names=["key", "key2", "fp", "more"])

    return run


def _file_again(rule: Rule):
    """(key, fp, more) of wide buckets -> (key, key2, fp, more) for each choice of half of the half blocks that the key leaves out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            key, fp, more = b.column(0).to_numpy(), b.column(1).to_numpy().view(np.uint64), b.column(2).to_numpy()
            for i in np.unique(key >> 32):
                own = (key >> 32) == i
                for j, some in enumerate(combinations(rule.halves(i), rule.radius)):
                    key2 = _bits(fp[own], some) | np.uint64((j + 1) << 40)
                    yield pa.RecordBatch.from_arrays([pa.array(key[own]), pa.array(key2.view(np.int64)), pa.array(fp[own].view(np.int64)), pa.array(more[own])], names=["key", "key2", "fp", "more"])

    return run


def _bucket_links(wide: int, rule: Rule):
    """Sorted (key, key2, fp, more) -> (key, a, b, more): links where key is null, members of wide buckets where b is null."""

    def out(key, a, b, more):
        n = len(a)
        return pa.RecordBatch.from_arrays([
            pa.array(np.full(n, key)) if key is not None else pa.nulls(n, pa.int64()), pa.array(a.view(np.int64)),
            pa.array(b.view(np.int64)) if b is not None else pa.nulls(n, pa.int64()), pa.array(more.view(np.int64)) if more is not None else pa.nulls(n, pa.int64())], names=["key", "a", "b", "more"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []  # the open bucket, empty while a wide one streams out
        open_key, size, streaming = None, 0, False

        def joined():
            return np.concatenate([h[0] for h in held]), np.concatenate([h[1] for h in held])

        def close():
            if not streaming and size > 1:
                a, b = spanning_links(*joined(), rule)
                if len(a):
                    yield out(None, a, b, None)

        for batch in batches:
            key, key2 = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            fp, more = batch.column(2).to_numpy().view(np.uint64), batch.column(3).to_numpy().view(np.uint64)
            if not len(key):
                continue
            cut = np.flatnonzero((key[1:] != key[:-1]) | (key2[1:] != key2[:-1])) + 1
            starts, ends = np.r_[0, cut], np.r_[cut, len(key)]
            inner = (ends - starts == 2) & (starts > 0) & (ends < len(key))  # whole buckets of two, the common case
            x, y = starts[inner], starts[inner] + 1
            close_two = near(fp[x], more[x], fp[y], more[y], rule)
            if close_two.any():
                yield out(None, np.minimum(fp[x], fp[y])[close_two], np.maximum(fp[x], fp[y])[close_two], None)
            skip = inner | ((ends - starts == 1) & (starts > 0) & (ends < len(key)))
            for s, e in zip(starts[~skip], ends[~skip]):
                k = (key[s], key2[s])
                if k != open_key:
                    yield from close()
                    held, open_key, size, streaming = [], k, 0, False
                held.append((fp[s:e], more[s:e]))
                size += e - s
                if streaming or (key2[s] == 0 and size > wide):
                    streaming = True
                    a, m = joined()
                    yield out(key[s], a, None, m)
                    held = []
        yield from close()

    return run


def links(fps: DataFrame, scratch: Scratch, wide: int = WIDE, rule: Rule = EXACT) -> DataFrame:
    """Distinct fingerprints (fp, more) -> (a, b), a < b: links whose components are those of all near pairs."""

    def bucketed(filed: DataFrame) -> DataFrame:
        return filed.repartition("key", "key2").sortWithinPartitions("key", "key2", "fp").mapInArrow(_bucket_links(wide, rule), "key long, a long, b long, more long")

    first = scratch.save(bucketed(fps.select("fp", "more").mapInArrow(_file(rule), FILED)), "links")
    again = bucketed(first.where("key IS NOT NULL").select("key", "a", "more").mapInArrow(_file_again(rule), FILED))
    return first.where("key IS NULL").select("a", "b").unionByName(again.where("key IS NULL").select("a", "b")).distinct()


def salted(many: DataFrame, on: str, few: DataFrame) -> DataFrame:
    """`many` (u, v) joined with one row a node `few` (k, m), rows of a node dealt over SALTS tasks."""
    few = few.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    many = many.withColumn("s", F.pmod(F.xxhash64("u", "v"), F.lit(SALTS)).cast("int"))
    return many.join(few, (F.col(on) == F.col("k")) & (F.col("s") == F.col("salt"))).drop("s", "salt", "k")


def components(edges: DataFrame, scratch: Scratch, rounds: int = 60) -> DataFrame:
    """(a, b) -> (node, root), root the smallest node of its component; nodes without edges are absent, roots too.

    The rounds needed grow with the logarithm of the longest chain; if `rounds` were not enough, it raises rather than give a partial result.
    """

    def mark(df):
        r = df.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        return r.n, r.h

    e = scratch.save(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), "edges0")
    before = mark(e)
    for i in range(1, rounds):
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("k"), F.least("u", "m").alias("m"))
        large = salted(both.where("v > u"), "u", low).select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        down = large.groupBy("u").agg(F.min("v").alias("m"))
        small = salted(large, "u", down.withColumnRenamed("u", "k"))
        small = small.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(small.select("u", F.col("m").alias("v"))).where("u <> v").distinct()
        e = scratch.save(small, f"edges{i}")
        scratch.drop(f"edges{i - 1}")
        now = mark(e)
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components not settled after {rounds} rounds")
    return e.select(F.col("u").alias("node"), F.col("v").alias("root"))


def roots(marked: DataFrame, scratch: Scratch, wide: int = WIDE, rule: Rule = EXACT) -> DataFrame:
    """Rows with doc_id, fp and more -> fp, first (its smallest doc_id), root (smallest fingerprint of its component, never null)."""
    fps = scratch.save(marked.groupBy("fp").agg(F.min("doc_id").alias("first"), F.min("more").alias("more")), "fps")
    root = components(links(fps, scratch, wide, rule), scratch)
    return fps.join(root, F.col("fp") == F.col("node"), "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))


def by_fp(marked: DataFrame, group: DataFrame) -> DataFrame:
    """Rows with a fingerprint (fp) joined with one row a fingerprint: copies of one text may be a third of all rows and are dealt over SALTS tasks."""
    group = group.withColumnRenamed("fp", "own").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    rows = marked.withColumn("s", F.pmod(F.monotonically_increasing_id(), F.lit(SALTS)).cast("int"))  # any salt will do
    return rows.join(group, (F.col("fp") == F.col("own")) & (F.col("s") == F.col("salt"))).drop("own", "s", "salt")


def near_duplicates(docs: DataFrame, scratch: Scratch | None = None, wide: int = WIDE, rule: Rule = EXACT) -> DataFrame:
    """doc_id, fp (long), fingerprint (hex) and component_id (smallest doc_id reachable): one row per input row."""
    scratch = scratch or Scratch(docs.sparkSession, "simhash")
    marked = scratch.save(docs.select("doc_id", fingerprint(text_bytes(), rule).alias("mark")).select("doc_id", "mark.*"), "marked")
    placed = roots(marked, scratch, wide, rule)
    name = placed.groupBy("root").agg(F.min("first").alias("component_id"))
    group = scratch.save(placed.select("fp", "root").join(name, "root").select("fp", "component_id"), "groups")
    return by_fp(marked.select("doc_id", "fp"), group).select("doc_id", "fp", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
