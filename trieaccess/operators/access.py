"""Reading symbols and substrings of compressed sequences.

Requests are (req_id, seq_id, l1, l2), 1-based and inclusive. With fixed-capacity segments the segment of a position is
arithmetic, so routing is an equi-join on (seq_id, seg_no); requests of one segment travel as one array. With `salts` those of a hot segment are split into up to
that many arrays, and the segment is sent to each of them; other segments are sent once. Relational ways to locate and climb work within segments too: positions, phrase numbers and
starts are those of a segment; their joins are merge joins by hint, since the planner takes codewords, of which a text has many, for smaller than the texts and would
broadcast them. Requests outside the sequence, or for none, have a null value and status 'invalid'.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from trieaccess import kernels as K

ANSWER = T.ArrayType(T.StructType([T.StructField("req_id", T.LongType()), T.StructField("piece", T.StringType()), T.StructField("reads_locate", T.LongType()),
                                   T.StructField("hops_align", T.LongType()), T.StructField("hops_jump", T.LongType()), T.StructField("hops_parent", T.LongType())]))
_HOPS = ("reads_locate", "hops_align", "hops_jump", "hops_parent")


@F.arrow_udf(ANSWER)
def read_pieces(blobs: pa.Array, wanted: pa.Array) -> pa.Array:
    """For each segment, the pieces of its requests and the codewords each one touched."""
    out = []
    for blob, asks in zip(blobs, wanted):
        asks = asks.as_py()
        store, alphabet = K.open_store(blob.as_py(), len(asks))
        rows = []
        for q in asks:
            if q["a"] == q["b"]:
                symbol, r = store.symbol(q["a"])
                symbols = [symbol]
            else:
                symbols, r = store.substring(q["a"], q["b"])
            rows.append({"req_id": q["req_id"], "piece": K.from_symbols(symbols, alphabet), "reads_locate": r.locate, "hops_align": r.align, "hops_jump": r.jump, "hops_parent": r.parent})
        out.append(rows)
    kind = pa.list_(pa.struct([("req_id", pa.int64()), ("piece", pa.string()), *((h, pa.int64()) for h in _HOPS)]))
    return pa.array(out, kind)


def route(requests: DataFrame, heads: DataFrame, capacity: int) -> DataFrame:
    """req_id, seq_id, seg_no, a, b: valid requests cut at segment borders, positions within the segment. `heads` has seq_id, seg_no, seq_len: a store, or segments not compressed yet."""
    ok = requests.join(heads.where("seg_no = 0").select("seq_id", "seq_len"), "seq_id").where("l1 >= 1 AND l1 <= l2 AND l2 <= seq_len")
    first, last = F.floor((F.col("l1") - 1) / capacity).cast("int"), F.floor((F.col("l2") - 1) / capacity).cast("int")
    cut = ok.withColumn("seg_no", F.explode(F.sequence(first, last)))
    base = F.col("seg_no").cast("long") * capacity
    return cut.select("req_id", "seq_id", "seg_no", F.greatest(F.col("l1") - base, F.lit(1)).alias("a"), F.least(F.col("l2") - base, F.lit(capacity)).alias("b"))


HOT, FILES = 64, 1 << 18  # requests that one group of a segment takes before it is split; hash values that segments are filed under


def spread(routed: DataFrame, store: DataFrame, salts: int) -> tuple[DataFrame, DataFrame]:
    """`routed` and `store` with a salt: a segment with more than HOT requests gets a salt for each HOT of them, `salts` at most, and every other segment the salt 0.

    How often a segment is split is told by its hash value, at most FILES rows; a cold segment filed with a hot one is split with it."""
    file = F.pmod(F.xxhash64("seq_id", "seg_no"), F.lit(FILES)).cast("int").alias("file")
    hot = routed.groupBy("seq_id", "seg_no").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > HOT)
    ways = F.broadcast(hot.groupBy(file).agg(F.least(F.lit(salts), F.ceil(F.max("n") / HOT)).cast("int").alias("ways")))
    told = lambda rows: rows.withColumn("file", file).join(ways, "file", "left").withColumn("ways", F.coalesce("ways", F.lit(1))).drop("file")
    asked = told(routed).withColumn("salt", F.pmod(F.xxhash64("req_id"), F.col("ways")).cast("int")).drop("ways")
    return asked, told(store).withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("ways") - 1))).drop("ways")


def access(store: DataFrame, requests: DataFrame, capacity: int = K.MAX_SYMBOLS, salts: int = 1, heads: DataFrame | None = None) -> DataFrame:
    """req_id, value, status, and the codewords read in each phase. A store that is still a plan rather than files is read once if `heads` is given."""
    asked, held, by = route(requests, store if heads is None else heads, capacity), store.select("seq_id", "seg_no", "blob"), ["seq_id", "seg_no"]
    if salts > 1:
        (asked, held), by = spread(asked, held, salts), [*by, "salt"]
    asked = asked.groupBy(*by).agg(F.collect_list(F.struct("req_id", "a", "b")).alias("asks"))
    read = asked.join(held, by).select("seg_no", read_pieces("blob", "asks").alias("got")).select("seg_no", F.inline("got"))
    whole = read.groupBy("req_id").agg(
        F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("seg_no", "piece"))), lambda s: s["piece"]), "").alias("value"), *[F.sum(h).alias(h) for h in _HOPS])
    return requests.select("req_id").join(whole, "req_id", "left").select("req_id", "value", F.when(F.col("value").isNull(), "invalid").otherwise("ok").alias("status"), *_HOPS)


def access_by_full_expand(store: DataFrame, requests: DataFrame, capacity: int = K.MAX_SYMBOLS, heads: DataFrame | None = None) -> DataFrame:
    """The baseline: decompress everything, then index. Segments stay rows: no sequence is put together."""
    from .codec import expand_segments

    asked = route(requests, store if heads is None else heads, capacity)
    got = asked.join(expand_segments(store), ["seq_id", "seg_no"]).select("req_id", "seg_no", F.substring("text", F.col("a"), F.col("b") - F.col("a") + 1).alias("piece"))
    whole = got.groupBy("req_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("seg_no", "piece"))), lambda s: s["piece"]), "").alias("value"))
    return requests.select("req_id").join(whole, "req_id", "left")


SEGMENT = ["seq_id", "seg_no"]
LOCATED = ("req_id", *SEGMENT, "at", "phrase_no", "start_pos", "depth")


def positions(requests: DataFrame, capacity: int) -> DataFrame:
    """req_id, seq_id, seg_no, at: single positions within their segments."""
    seg = F.floor((F.col("l1") - 1) / capacity).cast("int")
    return requests.select("req_id", "seq_id", seg.alias("seg_no"), (F.col("l1") - seg.cast("long") * capacity).alias("at"))


def locate_asof(phrases: DataFrame, requests: DataFrame, capacity: int = K.MAX_SYMBOLS) -> DataFrame:
    """As-of: the last phrase start at or before the position, by one sort per segment."""
    from pyspark.sql import Window

    marks = phrases.select(*SEGMENT, F.col("start_pos").alias("at"), F.lit(0).alias("tag"), F.lit(None).cast("long").alias("req_id"), F.struct("phrase_no", F.col("start_pos").alias("pos"), "depth").alias("hit"))
    asks = positions(requests, capacity).select(*SEGMENT, "at", F.lit(1).alias("tag"), "req_id", F.lit(None).cast(marks.schema["hit"].dataType).alias("hit"))
    w = Window.partitionBy(*SEGMENT).orderBy("at", "tag").rowsBetween(Window.unboundedPreceding, 0)
    found = marks.unionByName(asks).withColumn("last", F.last("hit", ignorenulls=True).over(w)).where("tag = 1 AND at < last.pos + last.depth")
    return found.select("req_id", *SEGMENT, "at", F.col("last.phrase_no").alias("phrase_no"), F.col("last.pos").alias("start_pos"), F.col("last.depth").alias("depth"))


def rank_directory(phrases: DataFrame, block: int = K.RankSelect.BLOCK) -> DataFrame:
    """seq_id, seg_no, block, inside: one row for each block of positions, with the phrases that touch it in order."""
    first, last = F.floor((F.col("start_pos") - 1) / block), F.floor((F.col("start_pos") + F.col("depth") - 2) / block)
    touched = phrases.select(*SEGMENT, F.explode(F.sequence(first, last)).alias("block"), "start_pos", "phrase_no", "depth")
    return touched.groupBy(*SEGMENT, "block").agg(F.array_sort(F.collect_list(F.struct("start_pos", "phrase_no", "depth"))).alias("inside"))  # at most `block` phrases


def locate_rank(phrases: DataFrame, requests: DataFrame, capacity: int = K.MAX_SYMBOLS, block: int = K.RankSelect.BLOCK) -> DataFrame:
    """Preprocessed: an equi-join with the directory of blocks, then the last start in the block that is not behind the position."""
    asks = positions(requests, capacity).withColumn("block", F.floor((F.col("at") - 1) / block))
    met = asks.join(rank_directory(phrases, block).hint("merge"), [*SEGMENT, "block"])
    hit = F.element_at(F.filter("inside", lambda x: x["start_pos"] <= F.col("at")), -1)
    found = met.where(F.exists("inside", lambda x: (x["start_pos"] <= F.col("at")) & (F.col("at") < x["start_pos"] + x["depth"])))
    return found.select("req_id", *SEGMENT, "at", hit.alias("hit")).select("req_id", *SEGMENT, "at", "hit.phrase_no", "hit.start_pos", "hit.depth")


def locate_scan(phrases: DataFrame, requests: DataFrame, capacity: int = K.MAX_SYMBOLS) -> DataFrame:
    """As unmodified codewords force: running sums of the depths, then a range condition within the segment."""
    from pyspark.sql import Window

    w = Window.partitionBy(*SEGMENT).orderBy("phrase_no").rowsBetween(Window.unboundedPreceding, 0)
    ends = phrases.select(*SEGMENT, "phrase_no", "depth", F.sum("depth").over(w).alias("end"))
    hit = positions(requests, capacity).join(ends.hint("merge"), SEGMENT).where("at <= end AND at > end - depth")
    return hit.select("req_id", *SEGMENT, "at", "phrase_no", (F.col("end") - F.col("depth") + 1).alias("start_pos"), "depth")


def climb_by_prefix(located: DataFrame, strings: DataFrame) -> DataFrame:
    """Level ancestors by one equi-join: the ancestor of depth g is the phrase of its segment that equals the first g symbols."""
    first = strings.groupBy(*SEGMENT, "phrase").agg(F.min("phrase_no").alias("hit_no"), F.max("symbol").alias("symbol"))
    own = strings.select(*SEGMENT, "phrase_no", F.col("phrase").alias("own"))
    want = located.join(own.hint("merge"), [*SEGMENT, "phrase_no"]).withColumn("phrase", F.substring("own", F.lit(1), F.col("at") - F.col("start_pos") + 1))
    return want.join(first.hint("merge"), [*SEGMENT, "phrase"]).select("req_id", F.col("hit_no").alias("phrase_no"), F.char("symbol").alias("value"))


def climb_parents(phrases: DataFrame, located: DataFrame) -> DataFrame:
    """Parents only: the parents and symbols of a segment in the order of its phrases, in which a request goes up one parent a level."""
    rows = F.array_sort(F.collect_list(F.struct("phrase_no", "parent_no", "symbol")))
    held = phrases.groupBy(*SEGMENT).agg(rows.alias("rows")).select(*SEGMENT, F.col("rows.parent_no").alias("up"), F.col("rows.symbol").alias("symbols"))
    lift = F.col("depth") - (F.col("at") - F.col("start_pos") + 1)
    levels = F.when(lift > 0, F.sequence(F.lit(1).cast("long"), lift.cast("long"))).otherwise(F.array().cast("array<long>"))
    no = F.aggregate(levels, F.col("phrase_no"), lambda no, _: F.element_at("up", no))
    found = located.join(held.hint("merge"), SEGMENT).select("req_id", no.alias("phrase_no"), "symbols")
    return found.select("req_id", "phrase_no", F.char(F.element_at("symbols", F.col("phrase_no"))).alias("value"))


def access_preprocessed(segs: DataFrame, requests: DataFrame, capacity: int = K.MAX_SYMBOLS) -> DataFrame:
    """req_id, value of single positions by rank/select and level-ancestor tables, built for the segments that are asked for; all requests of a segment step together."""

    def run(keys: tuple, held: pa.Table, asks: pa.Table) -> pa.Table:
        ids, values = asks.column("req_id").to_numpy(), np.zeros(0, np.int64)
        if held.num_rows and len(ids):
            p, pos = K.base_parse(K.to_symbols(held.column("text")[0].as_py())), asks.column("at").to_numpy()
            ids, pos = ids[(pos >= 1) & (pos <= p.n)], pos[(pos >= 1) & (pos <= p.n)]
            if len(pos):
                t = K.RankSelect(p.start[1:], p.n).locate(pos)
                values = p.symbol[K.LevelAncestor(p.parent, int(p.depth.max())).climb(t, p.depth[t] - (pos - p.start[t] + 1))]
        return pa.table({"req_id": pa.array(ids[: len(values)], pa.int64()), "value": pa.array(list(map(chr, values)), pa.string())})

    asks = positions(requests, capacity)
    asked = asks.groupBy(*SEGMENT)
    return segs.select(*SEGMENT, "text").join(asks.select(*SEGMENT).distinct(), SEGMENT, "left_semi").groupBy(*SEGMENT).cogroup(asked).applyInArrow(run, "req_id long, value string")


def access_codewords(phrases: DataFrame, requests: DataFrame, capacity: int = K.MAX_SYMBOLS) -> DataFrame:
    """req_id, value (null where it is not there yet) of single positions, read from dense codewords that are rows (start_pos, jump_no, ...) by the dense scheme's own
    binary search and guarded climb; the segments asked for are read, one in memory at a time."""

    def run(keys: tuple, held: pa.Table, asks: pa.Table) -> pa.Table:
        got = []
        if held.num_rows and asks.num_rows:
            held = held.sort_by("phrase_no")
            parent, symbol, start, jump, depth = (held.column(c).fill_null(-1).to_numpy().astype(np.int64) for c in ("parent_no", "symbol", "start_pos", "jump_no", "depth"))
            n = int(start[-1] + depth[-1] - 1)
            store = K.dense_store(parent, symbol, start, jump, n, K.block_size(capacity))
            got = [(i, chr(store.symbol(at)[0])) for i, at in zip(asks.column("req_id").to_pylist(), asks.column("at").to_pylist()) if 1 <= at <= n]
        return pa.table({"req_id": pa.array([g[0] for g in got], pa.int64()), "value": pa.array([g[1] for g in got], pa.string())})

    asks = positions(requests, capacity)
    held = phrases.select(*SEGMENT, "phrase_no", "parent_no", "symbol", "start_pos", "jump_no", "depth").join(asks.select(*SEGMENT).distinct(), SEGMENT, "left_semi")
    found = held.groupBy(*SEGMENT).cogroup(asks.groupBy(*SEGMENT)).applyInArrow(run, "req_id long, value string")
    return requests.select("req_id").join(found, "req_id", "left")


def symbol_requests(df: DataFrame, id_col: str, text_col: str = "text", per: int = 10) -> DataFrame:
    """Deterministic single positions: l = 1 + (id * 7919 + j * 104729) mod length."""
    n = F.length(text_col)
    rows = df.where(n > 0).select(F.col(id_col).cast("long").alias("seq_id"), n.alias("n"), F.explode(F.sequence(F.lit(0), F.lit(per - 1))).alias("j"))
    pos = F.pmod(F.col("seq_id") * 7919 + F.col("j").cast("long") * 104729, F.col("n")) + 1
    return rows.select((F.col("seq_id") * per + F.col("j")).alias("req_id"), "seq_id", pos.alias("l1"), pos.alias("l2"))


def range_requests(df: DataFrame, id_col: str, text_col: str = "text", per: int = 10, most: int = 200) -> DataFrame:
    """The same positions with lengths 1 + (id * 31 + j * 17) mod `most`, clipped at the end."""
    base = symbol_requests(df, id_col, text_col, per)
    n = df.select(F.col(id_col).cast("long").alias("seq_id"), F.length(text_col).cast("long").alias("n"))
    j = F.col("req_id") % per
    return base.join(n, "seq_id").select("req_id", "seq_id", "l1", F.least(F.col("l1") + F.pmod(F.col("seq_id") * 31 + j * 17, F.lit(most)), F.col("n")).alias("l2"))
