"""Compressing sequences: relations of codewords, packed stores, and back.

The unit of work is a segment, a slice of at most `capacity` symbols with a trie of its own, so parsing is a narrow map: no
shuffle, one segment in memory. Whoever reads few files deals their rows first (`sources.dealt`). Null texts give no rows; an empty text is one segment without codewords.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from trieaccess import kernels as K

STORE = "seq_id long, seg_no int, seg_start long, seg_len int, seq_len long, m int, n_words long, blob binary"
BATCH = 1 << 14  # codewords that leave together; a segment is not cut
BYTES, ROWS = 1 << 20, 1024  # bytes of blobs (symbols of texts) or rows that leave together
PHRASE = "seq_id long, seg_no int, phrase_no int, parent_no int, symbol int, depth int, start_pos long, jump_no int, special boolean, near_no int, special_depth int, chain_no int, word_off long"


def sequences(df: DataFrame, id_col: str, text_col: str = "text") -> DataFrame:
    return df.select(F.col(id_col).cast("long").alias("seq_id"), F.col(text_col).alias("text"))


def cut(seqs: DataFrame, capacity: int = K.MAX_SYMBOLS) -> DataFrame:
    """seq_id, seg_no, seg_start (1-based), seq_len, text; a text within the capacity stays one row."""
    n = F.length("text")
    pieces = F.greatest(F.ceil(n / capacity).cast("int"), F.lit(1))
    rows = seqs.where(F.col("text").isNotNull()).select("seq_id", "text", n.cast("long").alias("seq_len"), F.explode(F.sequence(F.lit(0), pieces - 1)).alias("seg_no"))
    start = F.col("seg_no").cast("long") * capacity + 1
    body = F.when(F.col("seq_len") <= capacity, F.col("text")).otherwise(F.substring("text", start, F.lit(capacity)))
    return rows.select("seq_id", "seg_no", start.alias("seg_start"), "seq_len", body.alias("text"))


def _arrow(names_types: list[tuple[str, pa.DataType]]):
    schema = pa.schema(names_types)
    return lambda columns: pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, schema)], schema=schema)


def compress(segs: DataFrame, scheme: str = "dense", alphabet: str = "codepoint", alpha: float = 1 / 40, grid: int | None = 40, seed: int = 7, capacity: int | None = None, tag: bool = True, every: int = 6, height_rule: bool = True) -> DataFrame:
    """Segments -> packed stores, one row a segment. `every` and `height_rule` are of the spaced scheme."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = _arrow([("seq_id", pa.int64()), ("seg_no", pa.int32()), ("seg_start", pa.int64()), ("seg_len", pa.int32()), ("seq_len", pa.int64()), ("m", pa.int32()), ("n_words", pa.int64()), ("blob", pa.binary())])
        held, size = [], 0
        for b in batches:
            for seq, no, start, total, text in zip(*(c.to_pylist() for c in b.columns)):
                symbols = K.to_symbols(text, alphabet)
                blob = K.pack(symbols, scheme, alphabet, alpha, grid, seed, seq, capacity, tag, every, height_rule)
                words = np.frombuffer(blob, "<i8", offset=K._HEAD.size)
                held.append((seq, no, start, len(symbols), total, len(K.base_words(scheme, words)), len(words), blob))
                size += len(blob)
                if size >= BYTES or len(held) >= ROWS:
                    yield out(zip(*held))
                    held, size = [], 0
        if held:
            yield out(zip(*held))

    return segs.select("seq_id", "seg_no", "seg_start", "seq_len", "text").mapInArrow(run, STORE)


def codewords(segs: DataFrame, alphabet: str = "codepoint", alpha: float = 1 / 40, grid: int | None = 40, seed: int = 7, capacity: int | None = None) -> DataFrame:
    """One row a codeword with the fields of all schemes: base (parent, symbol), dense (start, jump), sparse (special chain, word offset)."""
    names = [(n, t) for n, t in (("seq_id", pa.int64()), ("seg_no", pa.int32()), ("phrase_no", pa.int32()), ("parent_no", pa.int32()), ("symbol", pa.int32()), ("depth", pa.int32()),
                                 ("start_pos", pa.int64()), ("jump_no", pa.int32()), ("special", pa.bool_()), ("near_no", pa.int32()), ("special_depth", pa.int32()), ("chain_no", pa.int32()), ("word_off", pa.int64()))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out, held, size = _arrow(names), [], 0
        for b in batches:
            for seq, no, text in zip(*(c.to_pylist() for c in b.columns)):
                p = K.base_parse(K.to_symbols(text, alphabet))
                if not p.m:
                    continue
                B = K.block_size(max(capacity or p.n, p.n))
                s = K.sparse_layout(p, K.coins(seed, seq, p.m, alpha), grid, B)
                jump, chain = K.tree_jumps(p.parent, p.depth, B)[1:], s.jump[1:]
                held.append((np.full(p.m, seq), np.full(p.m, no), np.arange(1, p.m + 1), p.parent[1:], p.symbol[1:], p.depth[1:], p.start[1:], jump, s.special[1:], s.near[1:], s.special_depth[1:], chain, s.offset[1:]))
                size += p.m
                if size >= BATCH:
                    yield together(out, held)
                    held, size = [], 0
        if held:
            yield together(out, held)

    def together(out, held: list[tuple]) -> pa.RecordBatch:
        whole = [np.concatenate(c) for c in zip(*held)]
        return out([pa.array(c, pa.int32(), mask=c < 0) if name in ("jump_no", "chain_no") else c for (name, _), c in zip(names, whole)])

    return segs.select("seq_id", "seg_no", "text").mapInArrow(run, PHRASE)


def counts(segs: DataFrame, per: Callable[[int, K.Parse], dict[str, int]], alphabet: str = "codepoint") -> DataFrame:
    """seq_id, seg_no, and a map of integer measures of each segment's parse."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = _arrow([("seq_id", pa.int64()), ("seg_no", pa.int32()), ("values", pa.map_(pa.string(), pa.int64()))])
        for b in batches:
            for seq, no, text in zip(*(c.to_pylist() for c in b.columns)):
                yield out([[seq], [no], [list(per(seq, K.base_parse(K.to_symbols(text, alphabet))).items())]])

    return segs.select("seq_id", "seg_no", "text").mapInArrow(run, "seq_id long, seg_no int, values map<string,long>")


def compress_bytes(segs: DataFrame, alpha: float = 0.0, grid: int | None = None, seed: int = 7) -> DataFrame:
    """Segments -> byte stores: seq_id, seg_no, seg_len, blob."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = _arrow([("seq_id", pa.int64()), ("seg_no", pa.int32()), ("seg_len", pa.int32()), ("blob", pa.binary())])
        for b in batches:
            for seq, no, text in zip(*(c.to_pylist() for c in b.columns)):
                symbols = K.to_symbols(text)
                yield out([[seq], [no], [len(symbols)], [K.pack_bytes(symbols, alpha, grid, seed, seq)]])

    return segs.select("seq_id", "seg_no", "text").mapInArrow(run, "seq_id long, seg_no int, seg_len int, blob binary")


def expand_segments(store: DataFrame) -> DataFrame:
    """seq_id, seg_no, text: full sequential decompression, a row a segment."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out, held, size = _arrow([("seq_id", pa.int64()), ("seg_no", pa.int32()), ("text", pa.string())]), [], 0
        for b in batches:
            for seq, no, blob in zip(*(c.to_pylist() for c in b.columns)):
                held.append((seq, no, K.expand(blob)))
                size += len(held[-1][2])
                if size >= BYTES or len(held) >= ROWS:
                    yield out(zip(*held))
                    held, size = [], 0
        if held:
            yield out(zip(*held))

    return store.select("seq_id", "seg_no", "blob").mapInArrow(run, "seq_id long, seg_no int, text string")


def join_segments(parts: DataFrame) -> DataFrame:
    """seq_id, text of whole sequences, which must fit into a cell (2 GB): for those who need them in one piece."""
    joined = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("seg_no", "text"))), lambda s: s["text"]), "")
    return parts.groupBy("seq_id").agg(joined.alias("text"))


def expand(store: DataFrame) -> DataFrame:
    """seq_id, text: full decompression, segments joined; `expand_segments` where sequences are long."""
    return join_segments(expand_segments(store))


def compress_groups(df: DataFrame, key: str, order: str, text: str = "text", rows_per_part: int = 64, scheme: str = "dense", alphabet: str = "codepoint") -> DataFrame:
    """Rows of a key joined in the order of the integer `order` -> key, part, sub, seg_no, n, m, blob.

    A part holds the rows of one range of `rows_per_part` orders, so a key with any number of rows is spread over tasks; a part longer than
    the capacity becomes several segments. Null texts are left out, a null key is a key of its own. Rows with a null order, and rows that share one order, are
    dealt over parts by a hash of their text, so that a part is bounded whatever the orders are: `sub` numbers these.
    """

    def run(rows: pa.Table) -> pa.Table:
        rows = rows.sort_by([("_order", "ascending"), ("_text", "ascending")])
        symbols = K.to_symbols("".join(rows.column("_text").to_pylist()), alphabet)
        pieces = [symbols[i : i + K.MAX_SYMBOLS] for i in range(0, max(1, len(symbols)), K.MAX_SYMBOLS)]
        blobs = [K.pack(x, scheme, alphabet) for x in pieces]
        m = [len(K.base_words(scheme, np.frombuffer(b, "<i8", offset=K._HEAD.size))) for b in blobs]
        same = lambda c: pa.chunked_array([rows.column(c).combine_chunks().take(pa.array([0] * len(blobs)))])
        return pa.table({key: same("_key"), "part": same("_part"), "sub": same("_sub"), "seg_no": pa.array(range(len(blobs)), pa.int32()), "n": pa.array([len(x) for x in pieces], pa.int64()),
                         "m": pa.array(m, pa.int64()), "blob": pa.array(blobs, pa.binary())})

    part, own = F.floor(F.col(order) / rows_per_part).cast("long"), F.col(order).cast("long")
    rows = df.where(F.col(text).isNotNull()).select(F.col(key).alias("_key"), part.alias("_part"), own.alias("_order"), F.col(text).alias("_text"))
    many = rows.groupBy("_key", "_part").agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") > rows_per_part).select(
        F.col("_key").alias("_k"), F.col("_part").alias("_p"), F.ceil(F.col("_n") / rows_per_part).alias("_parts"))
    rows = rows.join(many, F.col("_key").eqNullSafe(F.col("_k")) & F.col("_part").eqNullSafe(F.col("_p")), "left")
    rows = rows.select("_key", "_part", F.coalesce(F.pmod(F.xxhash64("_text"), F.col("_parts")), F.lit(0).cast("long")).alias("_sub"), "_order", "_text")
    kind = df.schema[key].dataType.simpleString()
    return rows.groupBy("_key", "_part", "_sub").applyInArrow(run, f"`{key}` {kind}, part long, sub long, seg_no int, n long, m long, blob binary")


SURROGATES, N_SURROGATES = 0xD800, 0x800
SINGLE = 0x110000 - N_SURROGATES - 16  # ids below stand for themselves; the 16 code points from there on tell how many digits follow


def _spelled(i: int) -> list[int]:
    """An id as numbers below SINGLE + 16: itself, or a lead (8 more for a negative id) and its digits in base SINGLE."""
    if 0 <= i < SINGLE:
        return [i]
    digits, rest = [], abs(i)
    while rest:
        rest, digit = divmod(rest, SINGLE)
        digits.append(digit)
    return [SINGLE + len(digits) + 8 * (i < 0), *reversed(digits)]


def _read_ids(numbers: Iterator[int]) -> Iterator[int]:
    for lead in numbers:
        if lead < SINGLE:
            yield lead
            continue
        value = 0
        for _ in range((lead - SINGLE) % 8):
            value = value * SINGLE + next(numbers)
        yield -value if lead >= SINGLE + 8 else value


@F.arrow_udf(T.StringType())
def tokens_as_text(ids: pa.Array) -> pa.Array:
    """Sequences of token ids (64 bits) as text, so that every scheme and access path applies. Ids of 0 to 1,112,047 are one code point, others a few: positions are those of tokens only in sequences without such."""
    return pa.array([None if x is None else "".join(chr(n + N_SURROGATES * (n >= SURROGATES)) for i in x for n in _spelled(i)) for x in ids.to_pylist()], pa.string())


@F.arrow_udf(T.ArrayType(T.LongType()))
def text_as_tokens(texts: pa.Array) -> pa.Array:
    return pa.array([None if t is None else list(_read_ids(ord(c) - N_SURROGATES * (ord(c) >= SURROGATES) for c in t)) for t in texts.to_pylist()], pa.list_(pa.int64()))


def truncate(phrases: DataFrame, upto: int) -> DataFrame:
    """The first codewords of each segment: still decodable, for nothing refers forward."""
    return phrases.where(F.col("phrase_no") <= upto)


def phrase_strings(phrases: DataFrame, segs: DataFrame) -> DataFrame:
    """+ phrase: each codeword's text. Codewords are more than the planner takes them for, so none are broadcast."""
    body = segs.select("seq_id", "seg_no", "text").hint("merge")
    return phrases.join(body, ["seq_id", "seg_no"]).withColumn("phrase", F.substring("text", F.col("start_pos"), F.col("depth"))).drop("text")


def trie_edges(phrases: DataFrame) -> DataFrame:
    return phrases.select("seq_id", "seg_no", F.col("phrase_no").alias("src"), F.col("parent_no").alias("dst"))
