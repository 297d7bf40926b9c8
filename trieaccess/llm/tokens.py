"""Token ids in a directly addressable store.

Every id is cut into 8-bit chunks. Level k holds the k-th chunk of the ids that reach it, a bitmap per level says
which of them continue, and a rank directory (set bits before each block of 512) turns "continues" into the index
on the next level. Any token is read by at most as many steps as its id has chunks; no block is decoded.

A store is a Parquet table in the shared folder, one row a segment of whole documents (about `SEGMENT` tokens),
written in ascending doc_id order: shard = range partition, seg = number within it. It is not compressed, so that no page is inflated for one
token; pages are of about a segment.

The tokenizer drops white space between pre-tokens and never joins across it, so ids(text) is the concatenation of
the ids of its white-space words; a bounded cache of words saves most calls. Null text: empty. Every document ends
with `end_id`. Null doc_ids come first. Rows with equal doc_id follow each other in the order of the text's hash. An
empty table gives a store without segments. Extra columns are ignored.
"""

from __future__ import annotations

import functools
import json
import re
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import window as W

from .common import Scratch, in_slices, text_bytes

SEGMENT = 1 << 16
CACHE, RUNS = 200_000, 250_000
BATCH_BYTES = 4 << 20
RANK_BLOCK = 512
STORE = ("shard int, seg int, n_docs int, n_tokens long, doc_ids array<long>, doc_ends array<long>, "
         "levels array<binary>, bitmaps array<binary>, ranks array<binary>")
_BITS = np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1).sum(1).astype(np.uint32)


def public_vocabulary(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


#: fixed values: the steps that `WordTokenizer` does itself, as vocabulary files describe them
NORMALIZER = {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": "\\s+"}, "content": " "}, {"type": "Lowercase"}]}
PRE_TOKENIZER = {"type": "Sequence", "pretokenizers": [
    {"type": "Split", "pattern": {"Regex": "'s|'t|'re|'ve|'m|'ll|'d|[\\p{L}]+|[\\p{N}]|[^\\s\\p{L}\\p{N}]+"}, "behavior": "Removed", "invert": True},
    {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False}]}


def plain_pipeline(path: str) -> bool:
    """Whether the vocabulary's own normalizer and pre-tokenizer are those that are done here; its added tokens must hold "<|"."""
    with open(path, encoding="utf-8") as f:
        own = json.load(f)
    return own["normalizer"] == NORMALIZER and own["pre_tokenizer"] == PRE_TOKENIZER and all("<|" in t["content"] for t in own["added_tokens"])


class WordTokenizer(dict):
    """bytes of a text -> little-endian uint32 ids. The dictionary itself is a bounded cache: word -> ids, filled on a miss.

    Words of printable Latin-1 only are lower-cased and cut here, as normalizer and pre-tokenizer would (NFC leaves them
    as they are), and only unseen pre-tokens go to the library's model. Any other word goes through the whole library.
    """

    #: letter runs, single numerals, other runs and the contractions of the vocabulary's pre-tokenizer, within Latin-1
    LETTER, NUMERAL = "A-Za-z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-\xff", "0-9\xb2\xb3\xb9\xbc-\xbe"

    def __init__(self, path: str, end_id: int):
        from tokenizers import Tokenizer

        super().__init__()
        self.inner, self.end = Tokenizer.from_file(path), np.uint32(end_id).tobytes()
        self.runs: dict[str, bytes] = {}
        self.cut = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{self.LETTER}]+|[{self.NUMERAL}]|[^{self.LETTER}{self.NUMERAL}]+").findall
        self.plain = re.compile("[!-~\xa1-\xff]+").fullmatch
        self.plain_pipeline = plain_pipeline(path)
        self.model_ids = self.inner.model.tokenize
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]  # the byte-level alphabet: printable bytes stand for themselves, the others follow 255 in order
        hidden = [b for b in range(256) if b not in shown]
        self.alphabet = {b: chr(b) for b in shown} | {b: chr(256 + i) for i, b in enumerate(hidden)}

    def __missing__(self, w: bytes) -> bytes:
        word = w.decode("utf-8", "replace")
        if self.plain_pipeline and self.plain(word) and "<|" not in word:
            runs, out = self.runs, b""
            for run in self.cut(word.lower()):
                ids = runs.get(run)
                if ids is None:
                    shown = run if run.isascii() else run.encode().decode("latin-1").translate(self.alphabet)
                    ids = runs[run] = array("I", [t.id for t in self.model_ids(shown)]).tobytes()
                out += ids
        else:
            out = array("I", self.inner.encode(word, add_special_tokens=False).ids).tobytes()
        self[w] = out
        return out

    def __call__(self, texts: list[bytes]) -> list[bytes]:
        if len(self) > CACHE:
            self.clear()
        if len(self.runs) > RUNS:
            self.runs.clear()
        ids = self.__getitem__
        return [b"".join(map(ids, t.split())) + self.end for t in texts]


@functools.cache
def word_tokenizer(path: str, end_id: int) -> WordTokenizer:
    """One a Python worker: the caches stay warm from task to task."""
    return WordTokenizer(path, end_id)


def dac_encode(ids: np.ndarray) -> tuple[list[bytes], list[bytes], list[bytes]]:
    """Levels, bitmaps and rank directories of one segment."""
    levels, bitmaps, ranks = [], [], []
    rest = ids.astype(np.uint32)
    while True:
        more = rest > 255
        levels.append((rest & 255).astype(np.uint8).tobytes())
        bits = np.packbits(more, bitorder="little")
        bitmaps.append(bits.tobytes())
        per_block = np.add.reduceat(_BITS[bits], np.arange(0, len(bits), RANK_BLOCK // 8)) if len(bits) else np.zeros(0, np.uint32)
        ranks.append(np.concatenate([[0], np.cumsum(per_block)[:-1]]).astype("<u4").tobytes() if len(bits) else b"")
        if not more.any():
            return levels, bitmaps, ranks
        rest = rest[more] >> np.uint32(8)


def dac_get(levels: list[bytes], bitmaps: list[bytes], ranks: list[bytes], i: int) -> int:
    """The i-th id of a segment, by one byte, one bit and one rank a level."""
    value = shift = 0
    for level, bits, rank in zip(levels, bitmaps, ranks):
        value |= level[i] << shift
        if not bits[i >> 3] >> (i & 7) & 1:
            break
        block = i // RANK_BLOCK
        base = block * RANK_BLOCK // 8
        inside = sum(x.bit_count() for x in bits[base : i >> 3]) + (bits[i >> 3] & ((1 << (i & 7)) - 1)).bit_count()
        i = int.from_bytes(rank[4 * block : 4 * block + 4], "little") + inside
        shift += 8
    return value


def dac_decode(levels: list[bytes], bitmaps: list[bytes]) -> np.ndarray:
    """All ids of a segment."""
    out = np.frombuffer(levels[0], np.uint8).astype(np.uint32)
    at = np.arange(len(out))
    for k in range(1, len(levels)):
        at = at[np.unpackbits(np.frombuffer(bitmaps[k - 1], np.uint8), count=len(at), bitorder="little").astype(bool)]
        out[at] |= np.frombuffer(levels[k], np.uint8).astype(np.uint32) << np.uint32(8 * k)
    return out


def _segments(path: str, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        many = {"doc_ids": pa.list_(pa.int64()), "doc_ends": pa.list_(pa.int64())}
        few = {"shard": pa.int32(), "seg": pa.int32(), "n_docs": pa.int32(), "n_tokens": pa.int64()}
        schema = pa.schema([*few.items(), *many.items(), *((k, pa.list_(pa.binary())) for k in ("levels", "bitmaps", "ranks"))])
        shard, seg, encode = TaskContext.get().partitionId(), 0, word_tokenizer(path, end_id)
        ids, parts, total = [], [], 0

        def flush():
            nonlocal ids, parts, total, seg
            sizes = np.array([len(p) // 4 for p in parts], np.int64)
            levels, bitmaps, ranks = dac_encode(np.frombuffer(b"".join(parts), "<u4"))
            row = [shard, seg, len(ids), int(sizes.sum()), ids, np.cumsum(sizes).tolist(), levels, bitmaps, ranks]
            ids, parts, total, seg = [], [], 0, seg + 1
            return pa.RecordBatch.from_arrays([pa.array([v], f.type) for v, f in zip(row, schema)], schema=schema)

        for batch in batches:
            docs, texts = batch.column(0), batch.column(1)
            for a, b in in_slices(pc.binary_length(texts).to_pylist(), BATCH_BYTES):
                for doc, part in zip(docs.slice(a, b - a).to_pylist(), encode(texts.slice(a, b - a).to_pylist())):
                    ids.append(doc)
                    parts.append(part)
                    total += len(part) // 4
                    if total >= SEGMENT:
                        yield flush()
        if ids:
            yield flush()

    return run


def write_tokens(docs: DataFrame, store: str, tokenizer: str, end_id: int = 2) -> None:
    """Tokenize whole texts and write them as a store, in ascending doc_id order."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_bytes().alias("text"), F.xxhash64("text").alias("h"))
    dealt = rows.repartitionByRange("doc_id", "h").sortWithinPartitions("doc_id", "h").select("doc_id", "text")
    dealt.mapInArrow(_segments(tokenizer, end_id), STORE).write.option("compression", "none").option("parquet.page.size", 1 << 17).option("parquet.enable.dictionary", "false").parquet(store)


def read_store(spark: SparkSession, store: str) -> DataFrame:
    return spark.read.schema(STORE).parquet(store)


def directory(spark: SparkSession, store: str) -> DataFrame:
    """shard, seg, n_tokens, seg_start: global offsets. Two levels: a running sum over shards (as many rows as write tasks), then one inside each shard."""
    segs = read_store(spark, store).select("shard", "seg", "n_tokens")
    shards = segs.groupBy("shard").agg(F.sum("n_tokens").alias("t"))
    before = W.Window.orderBy("shard").rowsBetween(W.Window.unboundedPreceding, -1)
    shards = shards.select("shard", F.coalesce(F.sum("t").over(before), F.lit(0)).alias("shard_start"))
    inside = W.Window.partitionBy("shard").orderBy("seg").rowsBetween(W.Window.unboundedPreceding, -1)
    return segs.withColumn("in_shard", F.coalesce(F.sum("n_tokens").over(inside), F.lit(0))).join(shards, "shard").select(
        "shard", "seg", "n_tokens", (F.col("shard_start") + F.col("in_shard")).alias("seg_start"))


def _digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for r in range(batch.num_rows):
            shard, seg, docs, ends, levels, bitmaps = (batch.column(c)[r].as_py() for c in ("shard", "seg", "doc_ids", "doc_ends", "levels", "bitmaps"))
            raw = memoryview(dac_decode(levels, bitmaps).astype("<u4").tobytes())
            starts = [0, *ends[:-1]]
            yield pa.RecordBatch.from_pydict({
                "doc_id": pa.array(docs, pa.int64()), "shard": pa.array([shard] * len(docs), pa.int32()), "seg": pa.array([seg] * len(docs), pa.int32()),
                "in_seg": pa.array(starts, pa.int64()), "n_tokens": pa.array([e - s for s, e in zip(starts, ends)], pa.int64()),
                "ids_crc32": pa.array([zlib.crc32(raw[4 * s : 4 * e]) for s, e in zip(starts, ends)], pa.int64())})


def token_digests(spark: SparkSession, store: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every stored document, read back from the store."""
    rows = read_store(spark, store).select("shard", "seg", "doc_ids", "doc_ends", "levels", "bitmaps").mapInArrow(
        _digests, "doc_id long, shard int, seg int, in_seg long, n_tokens long, ids_crc32 long")
    starts = directory(spark, store).select("shard", "seg", "seg_start")
    return rows.join(starts, ["shard", "seg"]).select("doc_id", (F.col("seg_start") + F.col("in_seg")).alias("start"), "n_tokens", "ids_crc32")


def _ids(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for r in range(batch.num_rows):
            docs, ends, levels, bitmaps = (batch.column(c)[r].as_py() for c in ("doc_ids", "doc_ends", "levels", "bitmaps"))
            ids = dac_decode(levels, bitmaps)
            for doc, s, e in zip(docs, [0, *ends[:-1]], ends):
                yield pa.RecordBatch.from_arrays([pa.array([doc], pa.int64()), pa.array([ids[s:e].tolist()], pa.list_(pa.int64()))], names=["doc_id", "ids"])


def read_ids(spark: SparkSession, store: str) -> DataFrame:
    """doc_id, ids: the stored sequences."""
    return read_store(spark, store).select("doc_ids", "doc_ends", "levels", "bitmaps").mapInArrow(_ids, "doc_id long, ids array<long>")


@F.arrow_udf(T.LongType())
def _one(levels: pa.Array, bitmaps: pa.Array, ranks: pa.Array, at: pa.Array) -> pa.Array:
    return pa.array([dac_get(l.as_py(), b.as_py(), r.as_py(), i.as_py()) for l, b, r, i in zip(levels, bitmaps, ranks, at)], pa.int64())


def tokens_at(spark: SparkSession, store: str, positions: DataFrame) -> DataFrame:
    """(pos) -> pos, id: the ids at global positions, which may be many. No block is decoded; a position outside the store has no row.

    Segments are found by steps of the directory's mean size: each is filed under the steps it touches, so that a position meets few.
    """
    where = directory(spark, store)
    step = where.agg(F.greatest(F.avg("n_tokens"), F.lit(1.0)).cast("long")).first()[0] or 1
    filed = where.select("shard", "seg", "seg_start", "n_tokens", F.explode(F.sequence(F.floor(F.col("seg_start") / step), F.floor((F.col("seg_start") + F.col("n_tokens") - 1) / step))).alias("step"))
    found = positions.select("pos", F.floor(F.col("pos") / step).alias("step")).join(filed, "step").where((F.col("pos") >= F.col("seg_start")) & (F.col("pos") < F.col("seg_start") + F.col("n_tokens")))
    found = found.select("pos", "shard", "seg", (F.col("pos") - F.col("seg_start")).cast("long").alias("at"))
    return found.join(read_store(spark, store).select("shard", "seg", "levels", "bitmaps", "ranks"), ["shard", "seg"]).select("pos", _one("levels", "bitmaps", "ranks", "at").alias("id"))


def tokenize_and_read(docs: DataFrame, tokenizer: str, end_id: int = 2) -> DataFrame:
    scratch = Scratch(docs.sparkSession, "tokens")
    write_tokens(docs, scratch.path("store"), tokenizer, end_id)
    return token_digests(docs.sparkSession, scratch.path("store"))
