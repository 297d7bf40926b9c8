"""Queries of the compression schemes, their access paths, comparators and measures; each over whole tables and whole texts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trieaccess import kernels as K
from trieaccess.operators import access as A
from trieaccess.operators import codec, cost, hard, spanner
from trieaccess.sources import corpora
from trieaccess.session import scratch_path
from trieaccess.sources.tables import dealt, load

from . import sqlparse

QUERIES: dict = {}
SQL: dict[str, str] = {}
ALPHA, GRID, SEED = 1 / 16, 64, 7

TURNS = "SELECT conv_id * 100 + turn AS seq_id, text AS x FROM conversations"
PARSE = sqlparse.parse_sql(TURNS)


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return add


def docs(spark: SparkSession, d: str) -> DataFrame:
    return codec.sequences(dealt(load(spark, d, "documents", "doc_id", "text"), "doc_id"), "doc_id")


def turns(spark: SparkSession, d: str) -> DataFrame:
    t = dealt(load(spark, d, "conversations", "conv_id", "turn", "text"), "conv_id")
    return t.select((F.col("conv_id") * 100 + F.col("turn")).alias("seq_id"), "text")


def turn_words(spark: SparkSession, d: str, capacity: int = K.MAX_SYMBOLS) -> DataFrame:
    whole = capacity == K.MAX_SYMBOLS
    return codec.codewords(codec.cut(turns(spark, d), capacity), alpha=ALPHA, grid=GRID, seed=SEED, capacity=None if whole else capacity)


def _digest(texts: DataFrame) -> DataFrame:
    return texts.select("seq_id", F.length("text").cast("long").alias("n"), F.md5(F.col("text").cast("binary")).alias("text_md5"))


DIGEST = "SELECT doc_id AS seq_id, length(text) AS n, md5(text) AS text_md5 FROM documents WHERE text IS NOT NULL"


def _roundtrip(name: str, **how) -> None:
    def f(spark: SparkSession, d: str) -> DataFrame:
        return _digest(codec.expand(codec.compress(codec.cut(docs(spark, d), how.get("capacity", K.MAX_SYMBOLS)), **how)))

    f.__name__ = name
    query(DIGEST)(f)


_roundtrip("base_roundtrip", scheme="base")
_roundtrip("base_roundtrip_bytes", scheme="base", alphabet="byte")
_roundtrip("base_roundtrip_bits", scheme="base", alphabet="bit")
_roundtrip("dense_roundtrip", scheme="dense")
_roundtrip("dense_roundtrip_segments", scheme="dense", capacity=4096)
_roundtrip("sparse_roundtrip", scheme="sparse", alpha=ALPHA, grid=GRID)
_roundtrip("sparse_roundtrip_specials_only", scheme="sparse", alpha=ALPHA, grid=None)
_roundtrip("sparse_roundtrip_positions_only", scheme="sparse", alpha=0.0, grid=GRID)

SYMBOLS_SQL = "SELECT doc_id * 10 + j AS req_id, substr(text, CAST(1 + (doc_id * 7919 + j * 104729) % length(text) AS BIGINT), 1) AS value FROM documents, range(10) r(j) WHERE length(text) > 0"
RANGES_SQL = """SELECT doc_id * 10 + j AS req_id, substr(text, l1, least(1 + (doc_id * 31 + j * 17) % 200, length(text) - l1 + 1)) AS value
FROM (SELECT *, CAST(1 + (doc_id * 7919 + j * 104729) % length(text) AS BIGINT) AS l1 FROM documents, range(10) r(j) WHERE length(text) > 0)"""


def _access(name: str, ranges: bool, sql: str, capacity: int = K.MAX_SYMBOLS, salts: int = 1, **how) -> None:
    def f(spark: SparkSession, d: str) -> DataFrame:
        seqs = docs(spark, d)
        segs = codec.cut(seqs, capacity)
        store = codec.compress(segs, capacity=None if capacity == K.MAX_SYMBOLS else capacity, **how)
        asks = (A.range_requests if ranges else A.symbol_requests)(seqs, "seq_id")
        return A.access(store, asks, capacity, salts, heads=segs).select("req_id", "value")

    f.__name__ = name
    query(sql)(f)


_access("dense_access_symbol", False, SYMBOLS_SQL, scheme="dense")
_access("dense_access_range", True, RANGES_SQL, scheme="dense")
_access("sparse_access_symbol", False, SYMBOLS_SQL, scheme="sparse", alpha=ALPHA, grid=GRID)
_access("sparse_access_range", True, RANGES_SQL, scheme="sparse", alpha=ALPHA, grid=GRID)
_access("base_scan_access", False, SYMBOLS_SQL, scheme="base")
_access("segment_access", True, RANGES_SQL, capacity=4096, scheme="dense")
_access("segment_access_sparse", True, RANGES_SQL, capacity=4096, scheme="sparse", alpha=ALPHA, grid=GRID)


@query(SYMBOLS_SQL)
def full_expand_access(spark, d):
    seqs = docs(spark, d)
    segs = codec.cut(seqs)
    return A.access_by_full_expand(codec.compress(segs, "base"), A.symbol_requests(seqs, "seq_id"), heads=segs)


_access("hot_segment_access", True, RANGES_SQL, salts=8, scheme="dense")
_access("spaced_access", False, SYMBOLS_SQL, scheme="spaced", every=4, height_rule=False, grid=GRID)
_access("spaced_height_access", False, SYMBOLS_SQL, scheme="spaced", every=4, height_rule=True, grid=GRID)
_access("sparse_greedy_access", False, SYMBOLS_SQL, scheme="sparse", alpha=ALPHA, grid=GRID, tag=False)


def _planned(name: str, few: int, ranges: bool, sql: str) -> None:
    def f(spark, d):
        """The planner picks point reads, co-located reads or full expansion from the sizes of store and requests."""
        from .planner import planned_access

        seqs = docs(spark, d)
        segs = codec.cut(seqs)
        return planned_access(codec.compress(segs, "dense"), (A.range_requests if ranges else A.symbol_requests)(seqs, "seq_id"), K.MAX_SYMBOLS, heads=segs, few=few)

    f.__name__ = name
    query(sql)(f)


_planned("planned_access", 1000, True, RANGES_SQL)
_planned("planned_point_access", 1_000_000, False, SYMBOLS_SQL)


def _long(size: int) -> str:
    return f"SELECT doc_id AS req_id, substr(text, least(17, length(text)), {size}) AS value FROM documents WHERE length(text) > 0"


def _long_ranges(size: int) -> None:
    def f(spark, d):
        seqs = docs(spark, d)
        n, first = F.length("text").cast("long"), F.least(F.lit(17), F.length("text")).cast("long")
        asks = seqs.where(n > 0).select(F.col("seq_id").alias("req_id"), "seq_id", first.alias("l1"), F.least(n, first + size - 1).alias("l2"))
        segs = codec.cut(seqs)
        return A.access(codec.compress(segs, "sparse", alpha=ALPHA, grid=GRID), asks, heads=segs).select("req_id", "value")

    f.__name__ = f"range_access_{size}"
    query(_long(size))(f)


for _size in (1_000, 10_000):
    _long_ranges(_size)


@query("""SELECT req_id, CASE WHEN l1 >= 1 AND l2 <= length(text) THEN substr(text, l1, l2 - l1 + 1) END AS value, CASE WHEN l1 >= 1 AND l2 <= length(text) THEN 'ok' ELSE 'invalid' END AS status
FROM (SELECT doc_id * 3 + k AS req_id, text, CAST(CASE k WHEN 0 THEN 0 WHEN 1 THEN length(text) ELSE 1 END AS BIGINT) AS l1, CAST(CASE k WHEN 0 THEN 3 WHEN 1 THEN length(text) + 1 ELSE length(text) END AS BIGINT) AS l2 FROM documents, range(3) r(k) WHERE length(text) > 0)""")
def invalid_requests(spark, d):
    seqs = docs(spark, d).where(F.length("text") > 0)
    n = F.length("text").cast("long")
    k = seqs.select("seq_id", n.alias("n"), F.explode(F.array(*[F.lit(i) for i in range(3)])).alias("k"))
    asks = k.select((F.col("seq_id") * 3 + F.col("k")).alias("req_id"), "seq_id", F.when(F.col("k") == 0, 0).when(F.col("k") == 1, F.col("n")).otherwise(1).cast("long").alias("l1"),
                    F.when(F.col("k") == 0, 3).when(F.col("k") == 1, F.col("n") + 1).otherwise(F.col("n")).cast("long").alias("l2"))
    segs = codec.cut(seqs)
    return A.access(codec.compress(segs, "dense"), asks, heads=segs).select("req_id", "value", "status")


@query("SELECT doc_id * 10000 + item_id AS req_id, b.text AS value FROM documents d JOIN benchmark b ON contains(d.text, b.text)")
def passage_offsets(spark, d):
    """Benchmark passages found by offset and read back from the store. The passages are looked for by their first symbols, filed by window."""
    from .passages import occurrences

    seqs, items = docs(spark, d), load(spark, d, "benchmark", "item_id", F.col("text").alias("passage"))
    found = occurrences(seqs, items)
    asks = found.select((F.col("seq_id") * 10000 + F.col("item_id")).alias("req_id"), "seq_id", "l1", (F.col("l1") + F.col("k") - 1).alias("l2"))
    segs = codec.cut(seqs)
    return A.access(codec.compress(segs, "dense"), asks, heads=segs).select("req_id", "value")


# relations of codewords, checked against a recursive parse in SQL
@query(PARSE + "SELECT seq_id, phrase_no, parent_no, symbol, depth, start_pos FROM c")
def base_codewords(spark, d):
    return turn_words(spark, d).select("seq_id", "phrase_no", "parent_no", "symbol", "depth", "start_pos")


@query(PARSE + "SELECT seq_id, phrase_no, parent_no, symbol, depth, start_pos FROM c")
def base_codewords_native(spark, d):
    return sqlparse.parse_native(turns(spark, d))


@query(PARSE + "SELECT seq_id, phrase_no, parent_no, symbol, depth, start_pos FROM c")
def base_codewords_udtf(spark, d):
    from trieaccess.functions import register

    register(spark)
    turns(spark, d).createOrReplaceTempView("_turns")
    return spark.sql("SELECT t.seq_id, c.* FROM _turns t, LATERAL tx_codewords(t.text) c")


@query(PARSE + "SELECT seq_id, count(*) AS w, max(depth) AS deepest, CAST(sum(depth) AS BIGINT) AS n FROM c GROUP BY seq_id")
def base_counts(spark, d):
    return turn_words(spark, d).groupBy("seq_id").agg(F.count(F.lit(1)).alias("w"), F.max("depth").alias("deepest"), F.sum("depth").alias("n"))


@query(PARSE + "SELECT depth, count(*) AS phrases FROM c GROUP BY depth")
def base_depth_hist(spark, d):
    return turn_words(spark, d).groupBy("depth").agg(F.count(F.lit(1)).alias("phrases"))


@query(PARSE + "SELECT seq_id, phrase_no AS src, parent_no AS dst FROM c")
def trie_edges(spark, d):
    return codec.trie_edges(turn_words(spark, d)).drop("seg_no")


@query(PARSE + "SELECT seq_id, parent_no, count(*) AS children FROM c GROUP BY seq_id, parent_no ORDER BY children DESC, seq_id, parent_no LIMIT 20")
def trie_fanout_topk(spark, d):
    return turn_words(spark, d).groupBy("seq_id", "parent_no").agg(F.count(F.lit(1)).alias("children")).orderBy(F.desc("children"), "seq_id", "parent_no").limit(20)


@query(PARSE + "SELECT seq_id, phrase_no, parent_no FROM c WHERE phrase_no <= 20")
def base_truncate(spark, d):
    """Stopping after 20 codewords: what is out decodes a prefix."""
    return codec.truncate(turn_words(spark, d), 20).select("seq_id", "phrase_no", "parent_no")


@query(PARSE + "SELECT seq_id, phrase_no, phrase FROM c")
def phrase_strings(spark, d):
    segs = codec.cut(turns(spark, d))
    return codec.phrase_strings(codec.codewords(segs), segs).select("seq_id", "phrase_no", "phrase")


JUMPS = PARSE + """, b AS (SELECT seq_id, CAST(greatest(ceil(log2(length(x))), 1) AS BIGINT) AS B FROM src WHERE length(x) > 0),
j AS (SELECT c.*, B, B * CAST(pow(2, depth % B) AS BIGINT) AS reach FROM c JOIN b USING (seq_id)),
k AS (SELECT *, CASE WHEN reach > depth THEN NULL WHEN reach = depth THEN 0 ELSE list_position(phrases, left(phrase, CAST(depth - reach AS BIGINT))) END AS jump_no FROM j)
"""


@query(JUMPS + "SELECT seq_id, phrase_no, start_pos, parent_no, jump_no, symbol FROM k")
def dense_words(spark, d):
    return turn_words(spark, d).select("seq_id", "phrase_no", "start_pos", "parent_no", "jump_no", "symbol")


@query("SELECT CAST(i AS INTEGER) AS src, CAST(i - 15 * CAST(pow(2, i % 15) AS BIGINT) AS INTEGER) AS dst FROM range(1, 201) r(i) WHERE i >= 15 * CAST(pow(2, i % 15) AS BIGINT)")
def tree_jumps(spark, d):
    """Far edges of a line-shaped trie of 20,100 symbols (B = 15): phrase i has depth i."""
    return codec.codewords(codec.cut(hard.line_string(spark, 200))).where("jump_no IS NOT NULL").select(F.col("phrase_no").alias("src"), F.col("jump_no").alias("dst"))


@query(PARSE + "SELECT seq_id, count(*) AS w, 3 * count(*) AS dense_words, 3.0 AS ratio FROM c GROUP BY seq_id")
def dense_ratio(spark, d):
    w = cost.word_counts(codec.cut(turns(spark, d)), ALPHA, GRID).where("w > 0")
    return w.select("seq_id", "w", "dense_words", (F.col("dense_words") / F.col("w")).cast("decimal(2,1)").alias("ratio"))


COINS = PARSE + ", " + sqlparse.coin_sql(SEED, ALPHA)


@query(COINS + " SELECT seq_id, phrase_no, special FROM coin")
def sparse_coins(spark, d):
    return turn_words(spark, d).select("seq_id", "phrase_no", "special")


@query(COINS + """, near AS (SELECT a.seq_id, a.phrase_no, max(b.depth) AS near_depth, count(b.phrase_no) AS above FROM coin a LEFT JOIN coin b
  ON a.seq_id = b.seq_id AND b.special AND b.depth < a.depth AND starts_with(a.phrase, b.phrase) AND list_position(a.phrases, b.phrase) = b.phrase_no GROUP BY ALL)
SELECT coin.seq_id, phrase_no, coalesce(near_depth, 0) AS near_depth, above + CASE WHEN special THEN 1 ELSE 0 END AS special_depth FROM coin JOIN near USING (seq_id, phrase_no)""")
def sparse_chain(spark, d):
    """Nearest special ancestor (as its depth) and special depth of every codeword."""
    c = turn_words(spark, d)
    up = c.select("seq_id", F.col("phrase_no").alias("near_no"), F.col("depth").alias("near_depth"))
    return c.join(up, ["seq_id", "near_no"], "left").select("seq_id", "phrase_no", F.coalesce("near_depth", F.lit(0)).alias("near_depth"), "special_depth")


@query(COINS + " SELECT seq_id, count(*) AS w, count(*) FILTER (NOT special) AS m1, count(*) FILTER (special) AS m2, count(*) + 4 * count(*) FILTER (special) AS sparse_words FROM coin GROUP BY seq_id")
def sparse_word_identity(spark, d):
    """Without position codewords the sparse scheme has m1 + 5 m2 = w + 4 m2 words."""
    return cost.word_counts(codec.cut(turns(spark, d)), ALPHA, None, SEED).where("w > 0").select("seq_id", "w", "m1", "m2", "sparse_words")


def _coin_total(alpha: float) -> str:
    return "SELECT CAST(%r AS DOUBLE) AS alpha, CAST(count(*) AS BIGINT) AS w, CAST(count(*) FILTER (h5 < %d::UBIGINT) AS BIGINT) AS m2 FROM coin" % (alpha, int(alpha * 2**32))


@query(COINS + " " + " UNION ALL ".join(_coin_total(a) for a in (0.0, 1 / 16, 1 / 8, 1 / 4)))
def sparse_alpha_sweep(spark, d):
    return cost.alpha_sizes(codec.cut(turns(spark, d)), (0.0, 1 / 16, 1 / 8, 1 / 4), SEED).select("alpha", "w", "m2")


@query()
def sparse_eps_sweep(spark, d):
    return cost.eps_sweep(codec.cut(docs(spark, d)), (0.25, 0.5, 1.0, 2.0))


@query()
def sparse_special_tail(spark, d):
    return cost.special_tail(codec.cut(docs(spark, d)), 1.0, 20)


# word offsets: a running sum of widths, and a position codeword at the first codeword that starts on a grid mark or after it
LAYOUT = COINS + f""", z AS (SELECT seq_id, phrase_no, special, start_pos, 0 AS word_off, CAST(NULL AS BIGINT) AS position_off, CASE WHEN special THEN 5 ELSE 1 END AS total, {GRID} AS mark FROM coin WHERE phrase_no = 1
UNION ALL SELECT c.seq_id, c.phrase_no, c.special, c.start_pos, CASE WHEN total >= mark THEN total + 2 ELSE total END, CASE WHEN total >= mark THEN total END,
  CASE WHEN total >= mark THEN total + 2 ELSE total END + CASE WHEN c.special THEN 5 ELSE 1 END, CASE WHEN total >= mark THEN (total + 2) // {GRID} * {GRID} + {GRID} ELSE mark END
  FROM z JOIN coin c ON c.seq_id = z.seq_id AND c.phrase_no = z.phrase_no + 1)"""


@query(LAYOUT + " SELECT seq_id, phrase_no, CAST(word_off AS BIGINT) AS word_off, special, start_pos FROM z")
def sparse_words(spark, d):
    return turn_words(spark, d).select("seq_id", "phrase_no", "word_off", "special", "start_pos")


@query("WITH c AS (SELECT 0 AS seq_id, i AS phrase_no FROM range(1, 201) r(i)), " + sqlparse.coin_sql(SEED, 0.5) + """, s AS (SELECT phrase_no, row_number() OVER (ORDER BY phrase_no) AS nth FROM coin WHERE special)
SELECT CAST(a.phrase_no AS INTEGER) AS phrase_no, CAST(b.phrase_no AS INTEGER) AS chain_no FROM s a JOIN s b ON b.nth = a.nth - 15 * CAST(pow(2, a.nth % 15) AS BIGINT)""")
def sparse_chain_jumps(spark, d):
    """Far edges among the special codewords of a line-shaped trie (B = 15): all specials above one are its chain."""
    c = codec.codewords(codec.cut(hard.line_string(spark, 200)), alpha=0.5, grid=None, seed=SEED)
    return c.where("chain_no IS NOT NULL").select("phrase_no", "chain_no")


GRIDDED = LAYOUT + " SELECT {0} FROM (SELECT seq_id, count(*) AS w, count(*) FILTER (special) AS m2, count(position_off) AS m3, CAST(max(total) AS BIGINT) AS words FROM z GROUP BY seq_id)"


@query(GRIDDED.format("seq_id, w, w - m2 AS m1, m2, m3, words AS sparse_words, words = w - m2 + 5 * m2 + 2 * m3 AS holds"))
def sparse_word_counts(spark, d):
    """m1 + 5 m2 + 2 m3 with position codewords."""
    w = cost.word_counts(codec.cut(turns(spark, d)), ALPHA, GRID, SEED).where("w > 0")
    return w.select("seq_id", "w", "m1", "m2", "m3", "sparse_words", (F.col("sparse_words") == F.col("m1") + 5 * F.col("m2") + 2 * F.col("m3")).alias("holds"))


@query(GRIDDED.format("max(words / w) AS worst, avg(words / w) AS mean, sum(words) / sum(w) AS corpus, CAST(sum(w) AS BIGINT) AS w, CAST(sum(words) AS BIGINT) AS words"))
def sparse_ratio(spark, d):
    return cost.competitive_ratio(cost.word_counts(codec.cut(turns(spark, d)), ALPHA, GRID, SEED), "sparse_words")


@query(GRIDDED.replace("seq_id, count(*) AS w", "z.seq_id, count(*) AS w").replace("FROM z GROUP BY seq_id", ", max(length(x)) AS n FROM z JOIN src ON z.seq_id = src.seq_id GROUP BY z.seq_id").format(
    "seq_id, w * (CAST(ceil(log2(greatest(n, 2))) AS BIGINT) + 1) AS base_bits, words * (CAST(ceil(log2(greatest(n, 2))) AS BIGINT) + 1) AS sparse_bits, 4 * w AS dense_words_m, words + m2 + m3 AS sparse_words_m, "
    "4 * w * (CAST(ceil(log2(greatest(w, 2))) AS BIGINT) + 1) AS dense_bits_m"))
def size_in_bits(spark, d):
    """Words of log n and of log m bits."""
    return cost.size_bits(cost.word_counts(codec.cut(turns(spark, d)), ALPHA, GRID, SEED)).select("seq_id", "base_bits", "sparse_bits", "dense_words_m", "sparse_words_m", "dense_bits_m")


_EPS_TURNS = (1.0, 2.0)


@query(COINS + " " + " UNION ALL ".join("SELECT CAST(%r AS DOUBLE) AS eps, CAST(count(*) AS BIGINT) AS w, CAST(count(*) FILTER (h5 < %d::UBIGINT) AS BIGINT) AS m2 FROM coin" % (e, int(e / 40 * 2**32)) for e in _EPS_TURNS))
def sparse_eps_turns(spark, d):
    t = cost.sweep(codec.cut(turns(spark, d)), [K.sparse_params(e) for e in _EPS_TURNS], SEED).groupBy("alpha").agg(F.sum("w").alias("w"), F.sum("m2").alias("m2"))
    return t.select((F.col("alpha") * 40).alias("eps"), "w", "m2")


@query()
def ablate_alpha_grid(spark, d):
    words = cost.sweep(codec.cut(docs(spark, d)), [(1 / 4, 64), (1 / 8, 64), (1 / 16, 64), (1 / 40, 40), (0.0, 40), (1 / 16, None)]).where("w > 0")
    return words.groupBy("alpha", "grid").agg((F.sum("sparse_words") / F.sum("w")).alias("corpus"), F.max(F.col("sparse_words") / F.col("w")).alias("worst"))


@query(PARSE + "SELECT seq_id, count(*) FILTER (depth % 4 = 0) AS marked, count(*) AS w FROM c GROUP BY seq_id")
def spaced_marks(spark, d):
    """The deterministic strawman: every depth divisible by k is marked."""
    v = codec.counts(codec.cut(turns(spark, d)), lambda _, p: {"marked": int(K.spaced_marks(p, 4, False).sum()), "w": p.m})
    return v.select("seq_id", F.col("values")["marked"].alias("marked"), F.col("values")["w"].alias("w")).where("w > 0")


@query(PARSE + """, h AS (SELECT a.seq_id, a.phrase_no, a.depth, max(b.depth) - a.depth AS height FROM c a JOIN c b ON a.seq_id = b.seq_id AND starts_with(b.phrase, a.phrase) GROUP BY a.seq_id, a.phrase_no, a.depth)
SELECT seq_id, count(*) FILTER (depth % 4 = 0 AND height >= 4) AS marked, count(*) AS w FROM h GROUP BY seq_id""")
def spaced_height_marks(spark, d):
    """Marks only nodes of height k or more; heights are known only at the end."""
    v = codec.counts(codec.cut(turns(spark, d)), lambda _, p: {"marked": int(K.spaced_marks(p, 4, True).sum()), "w": p.m})
    return v.select("seq_id", F.col("values")["marked"].alias("marked"), F.col("values")["w"].alias("w")).where("w > 0")


@query(" UNION ALL ".join(f"SELECT {k} AS k, CAST({sum(1 << i for i in range(1, 13) if i % k == 0)} AS BIGINT) AS plain, CAST({sum(1 << i for i in range(1, 13) if i % k == 0 and 12 - i >= k)} AS BIGINT) AS height, CAST({(1 << 13) - 2} AS BIGINT) AS w" for k in (4, 6, 12)))
def spaced_full_tree(spark, d):
    """On a complete binary trie the strawman marks about half of the nodes, the height rule at most 1/k."""
    t = hard.joined(hard.members(spark, 13).withColumn("seq_id", F.lit(0).cast("long")), "seq_id")
    out = None
    for k in (4, 6, 12):
        v = codec.counts(codec.cut(t), lambda _, p, k=k: {"plain": int(K.spaced_marks(p, k, False).sum()), "height": int(K.spaced_marks(p, k, True).sum()), "w": p.m})
        part = v.select(F.lit(k).alias("k"), *[F.col("values")[x].alias(x) for x in ("plain", "height", "w")])
        out = part if out is None else out.unionByName(part)
    return out


# locating and climbing on relations
TURN_REQ = "SELECT conv_id * 100 + turn AS seq_id, text, (conv_id * 100 + turn) * 10 + j AS req_id, CAST(1 + ((conv_id * 100 + turn) * 7919 + j * 104729) % length(text) AS BIGINT) AS l1 FROM conversations, range(10) r(j) WHERE length(text) > 0"
TURN_SYMBOLS = f"SELECT req_id, substr(text, l1, 1) AS value FROM ({TURN_REQ})"
LOCATED = PARSE + f", r AS ({TURN_REQ}) SELECT r.req_id, c.phrase_no, c.start_pos, CAST(c.depth AS INTEGER) AS depth FROM r JOIN c ON r.seq_id = c.seq_id AND r.l1 >= c.start_pos AND r.l1 < c.start_pos + c.depth"


CUT = 64
TURN_SEGMENTS = f"SELECT (conv_id * 100 + turn) * 10000 + k AS seq_id, substr(text, {CUT} * k + 1, {CUT}) AS x FROM conversations, range(0, 9999) g(k) WHERE {CUT} * k < length(text)"
LOCATED_CUT = sqlparse.parse_sql(TURN_SEGMENTS) + f""", r AS (SELECT *, (l1 - 1) // {CUT} AS seg FROM ({TURN_REQ}))
SELECT r.req_id, CAST(seg AS INTEGER) AS seg_no, c.phrase_no, c.start_pos, CAST(c.depth AS INTEGER) AS depth FROM r JOIN c ON r.seq_id * 10000 + seg = c.seq_id AND r.l1 - {CUT} * seg >= c.start_pos AND r.l1 - {CUT} * seg < c.start_pos + c.depth"""


def _located(name, how):
    def f(spark, d):
        return how(turn_words(spark, d), A.symbol_requests(turns(spark, d), "seq_id")).select("req_id", "phrase_no", "start_pos", "depth")

    def segments(spark, d):
        return how(turn_words(spark, d, CUT), A.symbol_requests(turns(spark, d), "seq_id"), CUT).select("req_id", "seg_no", "phrase_no", "start_pos", "depth")

    f.__name__, segments.__name__ = name, f"{name}_segments"
    query(LOCATED)(f)
    query(LOCATED_CUT)(segments)


_located("asof_locate", A.locate_asof)
_located("rankselect_locate", A.locate_rank)
_located("scan_locate", A.locate_scan)


def _climbed(name, capacity, how):
    def f(spark, d):
        t = turns(spark, d)
        segs = codec.cut(t, capacity)
        return how(codec.codewords(segs), segs, A.symbol_requests(t, "seq_id"), capacity).select("req_id", "value")

    f.__name__ = name if capacity == K.MAX_SYMBOLS else f"{name}_segments"
    query(TURN_SYMBOLS)(f)


for _capacity in (K.MAX_SYMBOLS, CUT):
    _climbed("levelancestor_access", _capacity, lambda c, segs, asks, cap: A.climb_by_prefix(A.locate_asof(c, asks, cap), codec.phrase_strings(c, segs)))
    _climbed("parents_only_access", _capacity, lambda c, segs, asks, cap: A.climb_parents(c, A.locate_rank(c, asks, cap)))
    _climbed("preprocessed_access", _capacity, lambda c, segs, asks, cap: A.access_preprocessed(segs, asks, cap))


@query(TURN_SYMBOLS)
def cell_access(spark, d):
    """The store as one cell, read by a function."""
    from trieaccess.functions import pack_text, substr_of

    t = turns(spark, d)
    cells = t.select("seq_id", pack_text(F.col("text")).alias("blob"))
    return A.symbol_requests(t, "seq_id").join(cells, "seq_id").select("req_id", substr_of(F.col("blob"), F.col("l1"), F.lit(1).cast("long")).alias("value"))


# jump graphs
@query("SELECT 'path' AS graph, CAST(0 AS BIGINT) AS too_far UNION ALL SELECT 'tree', CAST(0 AS BIGINT)")
def spanner_check(spark, d):
    """Pairs that the path or a trie reaches and the jump graph does not reach in 4 B steps: none."""
    path = spanner.not_spanned(spanner.path_edges(spark, 9), spanner.path_jumps(spark, 9), 4 * K.block_size(9)).count()
    words = codec.codewords(codec.cut(hard.line_string(spark, 8)), capacity=4)
    edges = words.select(F.col("phrase_no").cast("long").alias("src"), F.col("parent_no").cast("long").alias("dst"))
    far = words.where("jump_no IS NOT NULL").select(F.col("phrase_no").cast("long").alias("src"), F.col("jump_no").cast("long").alias("dst"))
    tree = spanner.not_spanned(edges, far, 4 * K.block_size(36)).count()
    return spark.createDataFrame([("path", path), ("tree", tree)], "graph string, too_far long")


@query("SELECT true AS within_bound, 2 AS tries")
def tree_stretch(spark, d):
    """Hops in the tries at both extremes, a line and a complete binary tree, against 4 B."""
    both = hard.line_string(spark, 300).unionByName(hard.joined(hard.members(spark, 11).withColumn("seq_id", F.lit(1).cast("long")), "seq_id"))
    return spanner.tree_stretch(codec.cut(both), 1 << 16).agg((F.max(F.col("max_hops") - F.col("bound")) <= 0).alias("within_bound"), F.count(F.lit(1)).cast("int").alias("tries"))


@query()
def stretch_report(spark, d):
    """Largest and mean hops against 4 B, on tries of documents and on the line."""
    both = docs(spark, d).unionByName(hard.line_string(spark, 300).select((-F.col("seq_id") - 1).alias("seq_id"), "text"))
    t = spanner.tree_stretch(codec.cut(both), K.MAX_SYMBOLS)
    return t.groupBy((F.col("seq_id") < 0).alias("line")).agg(F.max("max_hops").alias("max_hops"), (F.sum(F.col("mean_hops") * F.col("pairs")) / F.sum("pairs")).alias("mean_hops"), F.max("bound").alias("bound"))


@query()
def access_bounds(spark, d):
    """Reads of the sparse scheme over lengths and eps."""
    return cost.access_bounds(codec.cut(corpora.dna(load(spark, d, "documents", "doc_id", "text"), 1 << 16)), (0.5, 1.0, 2.0), (1 << 12, 1 << 14, 1 << 16))


@query("SELECT i AS src, greatest(i - CAST(pow(2, i % 9) AS BIGINT) * 9, 0) AS dst FROM range(1, 500) r(i)")
def path_jumps(spark, d):
    return spanner.path_jumps(spark, 500)


@query("""WITH RECURSIVE w AS (SELECT t AS v, t, r, 0 AS hops, false AS aligned FROM range(1, 120) a(t), range(0, 120) b(r) WHERE r < t
UNION ALL SELECT CASE WHEN (aligned OR v % 7 = 6) AND greatest(v - CAST(pow(2, v % 7) AS BIGINT) * 7, 0) >= r THEN greatest(v - CAST(pow(2, v % 7) AS BIGINT) * 7, 0) ELSE v - 1 END, t, r, hops + 1, aligned OR v % 7 = 6 FROM w WHERE v > r)
SELECT t, r, CAST(hops AS BIGINT) AS hops FROM w WHERE v = r""")
def path_route_hops(spark, d):
    return spanner.route_hops(spark, 120).select("t", "r", (F.col("align") + F.col("far") + F.col("single")).alias("hops"))


@query("SELECT true AS within_bound")
def path_stretch(spark, d):
    """At most 4 B hops for every pair of a path."""
    n = 400
    return spanner.route_hops(spark, n).agg((F.max(F.col("align") + F.col("far") + F.col("single")) <= 4 * K.block_size(n)).alias("within_bound"))


@query()
def dense_reads(spark, d):
    seqs = docs(spark, d)
    segs = codec.cut(seqs)
    return cost.reads_report(A.access(codec.compress(segs, "dense"), A.symbol_requests(seqs, "seq_id"), heads=segs))


@query()
def sparse_reads(spark, d):
    seqs = docs(spark, d)
    segs = codec.cut(seqs)
    return cost.reads_report(A.access(codec.compress(segs, "sparse", alpha=ALPHA, grid=GRID), A.symbol_requests(seqs, "seq_id"), heads=segs))


@query()
def range_overhead(spark, d):
    """Codewords read beyond the length of the substring, which one access bounds."""
    seqs = docs(spark, d)
    asks = A.range_requests(seqs, "seq_id")
    segs = codec.cut(seqs)
    got = A.access(codec.compress(segs, "dense"), asks, heads=segs).join(asks, "req_id")
    extra = F.col("reads_locate") + F.col("hops_align") + F.col("hops_jump") + F.col("hops_parent") - (F.col("l2") - F.col("l1") + 1)
    return got.agg(F.avg(extra).alias("mean_extra"), F.max(extra).alias("max_extra"))


# hard strings
def _family_sql(k: int) -> str:
    q = 1 << (k - 1) >> 2
    levels = f"SELECT CAST(i AS INTEGER) AS i, j, lpad(bin(j - 1), CAST(i AS INTEGER), '0') AS s FROM range(1, {k}) a(i), range(1, {1 << k}) b(j) WHERE j <= CAST(pow(2, i) AS BIGINT)"
    return f"m AS ({levels}), f AS (SELECT e AS seq_id, string_agg(CASE WHEN e > 0 AND i = {k - 1} AND j = {q} + e THEN '{'0' * k}' ELSE s END, '' ORDER BY i, j) AS text FROM m, range(0, {q + 1}) r(e) GROUP BY e)"


def _drawn_sql(members: int) -> str:
    return f"""t AS (SELECT coalesce(text, '') AS t FROM documents), l AS (SELECT t, t[1] AS a, ltrim(t, t[1])[1] AS b FROM t),
d AS (SELECT CASE WHEN b <> '' THEN a ELSE '0' END AS a, CASE WHEN b <> '' THEN b ELSE '1' END AS b, CAST(('0x' || md5(t)[1:8])::UBIGINT % {members} AS BIGINT) AS member FROM l),
drawn AS (SELECT a, b, member, count(*) AS docs, unicode(a)::BIGINT * {hard.PLACE} + unicode(b) * 64 + member AS seq_id FROM d GROUP BY a, b, member)"""


def _drawn(spark: SparkSession, d: str, members: int) -> DataFrame:
    return hard.drawn(load(spark, d, "documents", "text"), members)


def _hard(k: int, tag: str) -> None:
    """Family, distribution, differing codewords, witness positions and the general family for one k."""
    q, family = 1 << (k - 1) >> 2, _family_sql(k)

    def add(name: str, sql: str, f) -> None:
        f.__name__ = f"{name}{tag}"
        query(sql)(f)

    drawn = _drawn_sql(q + 1)
    add("hard_strings", f"WITH {family}, {drawn} SELECT drawn.seq_id, translate(text, '01', a || b) AS text, docs FROM drawn JOIN f ON f.seq_id = member",
        lambda spark, d: hard.lettered(_drawn(spark, d, q + 1), hard.family(spark, k)).select("seq_id", "text", "docs"))
    add("hard_distribution", f"WITH {family}, {drawn} SELECT drawn.seq_id, translate(text, '01', a || b) AS text, docs, CASE WHEN member = 0 THEN 0.5 ELSE 1 / (2.0 * {q}) END::DOUBLE AS weight FROM drawn JOIN f ON f.seq_id = member",
        lambda spark, d: hard.lettered(_drawn(spark, d, q + 1), hard.family(spark, k)).join(hard.distribution(spark, k).select(F.col("seq_id").alias("member"), "weight"), "member").select("seq_id", "text", "docs", "weight"))
    # exactly one codeword differs, at another place for each perturbation
    add("hard_diff", f"WITH {drawn} SELECT seq_id, CAST({(1 << k - 1) - 2 + q} + member AS INTEGER) AS phrase_no FROM drawn WHERE member > 0",
        lambda spark, d: hard.drawn_diff(codec.codewords(codec.cut(hard.lettered(hard.with_plain(_drawn(spark, d, q + 1)), hard.family(spark, k)).select("seq_id", "text")))))
    add("hard_witness", f"""WITH {family}, {drawn}, u AS (SELECT seq_id, unnest(range(1, CAST(length(text) AS BIGINT) + 1)) AS pos, text FROM f), x AS (SELECT seq_id, pos, text[pos] AS c FROM u), y AS (SELECT a.pos FROM x a JOIN x b ON a.seq_id = 0 AND b.seq_id > 0 AND a.pos = b.pos AND a.c <> b.c GROUP BY a.pos HAVING count(*) = {q})
SELECT DISTINCT drawn.seq_id - member AS seq_id, CAST(pos AS INTEGER) AS pos FROM drawn, y""",
        lambda spark, d: hard.witness_positions(hard.whole_families(_drawn(spark, d, q + 1), k), "seq_id", "member").select(F.col("own").alias("seq_id"), "pos"))
    add("hard_extended", f"WITH {drawn} SELECT seq_id, CAST({(1 << k) - 1 + 40} AS BIGINT) AS w FROM drawn",
        lambda spark, d: codec.codewords(codec.cut(hard.lettered(_drawn(spark, d, q + 1), hard.extended(spark, k, 40)).select("seq_id", "text"))).groupBy("seq_id").agg(F.count(F.lit(1)).alias("w")))


_hard(6, "")
_hard(8, "_8")


@query(f"WITH {_drawn_sql(1)} SELECT seq_id, docs, 200 AS w, 20100 AS n FROM drawn")
def line_string_counts(spark, d):
    """The line in the letters of each text: a row a pair of letters, with the number of its texts."""
    rows = _drawn(spark, d, 1)
    c = codec.codewords(codec.cut(hard.lettered(rows, hard.line_string(spark, 200)).select("seq_id", "text")))
    return c.groupBy("seq_id").agg(F.count(F.lit(1)).cast("int").alias("w"), F.sum("depth").cast("int").alias("n")).join(rows.select("seq_id", "docs"), "seq_id")


@query()
def probe_success(spark, d):
    return hard.probe_success(spark, 8, (16, 64, 128, 254))


# experiments: each corpus is one string
LOG_SQL = """SELECT 0 AS seq_id, substr(string_agg(strftime(ts, '%Y-%m-%dT%H:%M:%S') || ' user=' || user_id || ' ' || event_type || ' value=' || CAST(CAST(value AS DECIMAL(18,2)) AS VARCHAR) || ' ' || props, chr(10) ORDER BY event_id), 1, {n}) AS x FROM events"""
DNA_SQL = "SELECT 0 AS seq_id, substr(string_agg(array_to_string(list_transform(string_split(text, ''), lambda c: substr('ACGT', unicode(c) % 4 + 1, 1)), ''), '' ORDER BY doc_id), 1, {n}) AS x FROM documents WHERE length(text) > 0{few}"
VOCAB_SQL = "SELECT 0 AS seq_id, substr(string_agg(w, chr(10) ORDER BY w), 1, {n}) AS x FROM (SELECT DISTINCT unnest(regexp_split_to_array(lower(text), '\\s+')) AS w FROM documents) WHERE w <> ''"
_ALPHAS = (0.0, 1 / 16, 1 / 8, 1 / 4)
CORPORA = {  # name: (builder, SQL, symbols)
    "log": (lambda spark, d, n: corpora.log(load(spark, d, "events"), n), LOG_SQL, 1_200_000),
    "dna": (lambda spark, d, n: corpora.dna(load(spark, d, "documents", "doc_id", "text"), n), DNA_SQL, 1_700_000),
    "vocab": (lambda spark, d, n: corpora.vocabulary(load(spark, d, "documents", "text"), n), VOCAB_SQL, 1_300_000),
}
SHORT = 2500


def _corpus(name: str) -> None:
    build, sql, n = CORPORA[name]

    def roundtrip(spark, d):
        return _digest(codec.expand(codec.compress(codec.cut(build(spark, d, n)), "sparse", alpha=ALPHA, grid=GRID)))

    def sizes(spark, d):
        """Codewords, words and KB (1024 bytes) of the byte stores that are written, for each share of special codewords."""
        segs = codec.cut(build(spark, d, n))
        t = cost.alpha_sizes(segs, _ALPHAS).join(cost.byte_sizes(segs, _ALPHAS).select("alpha", "bytes"), "alpha")
        return t.select("alpha", "n", "w", "m2", "words", "word_ratio", "bytes", (F.col("bytes") / 1024).alias("kb"))

    def short(spark, d):
        segs = codec.cut(build(spark, d, SHORT))
        return cost.alpha_sizes(segs, _ALPHAS).join(cost.byte_sizes(segs, _ALPHAS).select("alpha", "bytes"), "alpha").select("alpha", "w", "m2", "words", "bytes")

    def times(spark, d):
        """Mean ms of a random access and ms of the full decompression."""
        return cost.access_times(codec.cut(build(spark, d, n)))

    small = sql.format(n=SHORT, few=f" AND doc_id < {SHORT}")
    per = " UNION ALL ".join("SELECT CAST(%r AS DOUBLE) AS alpha, %d::UBIGINT AS bar" % (a, int(a * 2**32)) for a in _ALPHAS)
    per_sql = sqlparse.parse_sql(small) + ", " + sqlparse.coin_sql(SEED, 0.0) + f""", bars AS ({per}), sigma AS (SELECT count(DISTINCT symbol) AS s FROM c)
SELECT alpha, count(*) AS w, count(*) FILTER (h5 < bar) AS m2, count(*) + 4 * count(*) FILTER (h5 < bar) AS words, 5 * count(*) + 16 * count(*) FILTER (h5 < bar) + {K._BYTES.size} + 4 * max(s) AS bytes FROM coin, bars, sigma GROUP BY alpha"""
    for f, tag, oracle in ((roundtrip, "roundtrip", f"SELECT seq_id, length(x) AS n, md5(x) AS text_md5 FROM ({sql.format(n=n, few='')})"), (sizes, "sizes", None), (short, "sizes_short", per_sql), (times, "times", None)):
        f.__name__ = f"{name}_{tag}"
        query(oracle)(f)


for _name in CORPORA:
    _corpus(_name)


@query()
def segment_penalty(spark, d):
    return cost.segment_penalty(docs(spark, d), 4096)


@query("SELECT CAST(sum(k) AS BIGINT) AS n, CAST(round(sum(k) * log2(sum(k)) - sum(k * log2(k))) AS BIGINT) AS bits FROM (SELECT c, count(*) AS k FROM (SELECT unnest(regexp_extract_all(text, '(?s).')) AS c FROM documents) GROUP BY c)")
def order0_bits(spark, d):
    return cost.order0_bits(docs(spark, d)).select("n", F.round("bits").cast("long").alias("bits"))


@query(PARSE + ", p AS (SELECT count(*) AS m_whole FROM c), " + sqlparse.parse_sql(TURN_SEGMENTS, "2").removeprefix("WITH RECURSIVE ") + ", q AS (SELECT count(*) AS m_cut FROM c2) SELECT m_cut, m_whole, CAST(m_cut AS DOUBLE) / m_whole AS penalty FROM p, q")
def segment_penalty_turns(spark, d):
    return cost.segment_penalty(turns(spark, d), CUT)


STRATA = LAYOUT + ", t AS (SELECT seq_id, count(*) AS w, CAST(max(total) AS BIGINT) AS words FROM z GROUP BY seq_id), s AS (SELECT t.*, role, turn % 2 AS odd FROM t JOIN conversations ON seq_id = conv_id * 100 + turn)"


def _turn_strata(spark, d):
    meta = load(spark, d, "conversations", (F.col("conv_id") * 100 + F.col("turn")).alias("seq_id"), "role", (F.col("turn") % 2).alias("odd"))
    return cost.word_counts(codec.cut(turns(spark, d)), ALPHA, GRID, SEED).where("w > 0").join(meta, "seq_id")


@query(STRATA + " SELECT role, odd, CAST(sum(w) AS BIGINT) AS w, CAST(sum(words) AS BIGINT) AS words, sum(words) / sum(w) AS ratio FROM s GROUP BY ROLLUP (role, odd)")
def ratio_by_role_rollup(spark, d):
    return _turn_strata(spark, d).rollup("role", "odd").agg(F.sum("w").alias("w"), F.sum("sparse_words").alias("words"), (F.sum("sparse_words") / F.sum("w")).alias("ratio"))


@query(STRATA + " SELECT role, odd, CAST(sum(w) AS BIGINT) AS w, sum(words) / sum(w) AS ratio FROM s GROUP BY CUBE (role, odd)")
def ratio_by_role_cube(spark, d):
    return _turn_strata(spark, d).cube("role", "odd").agg(F.sum("w").alias("w"), (F.sum("sparse_words") / F.sum("w")).alias("ratio"))


@query()
def ratio_by_lang_rollup(spark, d):
    meta = load(spark, d, "documents", F.col("doc_id").alias("seq_id"), "lang", "source")
    w = cost.word_counts(codec.cut(docs(spark, d)), ALPHA, GRID).join(meta, "seq_id").where("w > 0")
    return w.rollup("lang", "source").agg(F.sum("w").alias("w"), F.sum("sparse_words").alias("words"), (F.sum("sparse_words") / F.sum("w")).alias("ratio"))


@query()
def ratio_by_label_cube(spark, d):
    lab = load(spark, d, "labels", F.col("doc_id").alias("seq_id"), "quality", "toxic")
    w = cost.word_counts(codec.cut(docs(spark, d)), ALPHA, GRID).join(lab, "seq_id").where("w > 0")
    return w.cube("quality", "toxic").agg(F.sum("w").alias("w"), (F.sum("sparse_words") / F.sum("w")).alias("ratio"))


CONV = "SELECT conv_id AS seq_id, string_agg(role || ': ' || text || chr(10), '' ORDER BY turn) AS x FROM conversations GROUP BY conv_id"


@query(sqlparse.parse_sql(CONV) + "SELECT seq_id, phrase_no, parent_no, symbol, depth, start_pos FROM c")
def conversation_append(spark, d):
    """Turns appended in order, one sequence a conversation."""
    t = load(spark, d, "conversations").select(F.col("conv_id").alias("seq_id"), "turn", F.concat("role", F.lit(": "), "text", F.lit("\n")).alias("line"))
    parts = F.array_sort(F.collect_list(F.struct("turn", "line")))
    whole = t.groupBy("seq_id").agg(F.array_join(F.transform(parts, lambda p: p["line"]), "").alias("text"))
    return codec.codewords(codec.cut(whole)).select("seq_id", "phrase_no", "parent_no", "symbol", "depth", "start_pos")


def _growing(spark, d, scheme: str, capacity: int, close: bool = True):
    """Turns in three micro-batches, a null text at the end of each conversation."""
    from trieaccess.streaming import compress_stream, replay

    t = load(spark, d, "conversations").select("conv_id", "turn", F.concat("role", F.lit(": "), "text", F.lit("\n")).alias("line"), F.least(F.floor(F.col("turn") / 2), F.lit(2)).cast("int").alias("no"))
    if close:
        t = t.unionByName(t.groupBy("conv_id").agg((F.max("turn") + 1).alias("turn")).select("conv_id", "turn", F.lit(None).cast("string").alias("line"), F.lit(2).alias("no")))
    return replay(spark, t, lambda s: compress_stream(s, "conv_id", "turn", "line", scheme, capacity, ALPHA, GRID, SEED), scratch_path(spark, "q"), 3, "no")


GROWN = 1 << 12
CONV_CUT = f"SELECT seq_id * 10000 + k AS seq_id, substr(x, {GROWN} * k + 1, {GROWN}) AS x FROM ({CONV}), range(0, 9999) g(k) WHERE {GROWN} * k < length(x)"
GROWN_SQL = sqlparse.parse_sql(CONV_CUT)


@query(GROWN_SQL + "SELECT seq_id // 10000 AS seq_id, CAST(seq_id % 10000 AS INTEGER) AS seg_no, phrase_no, parent_no, symbol, depth, start_pos FROM c")
def stream_codewords(spark, d):
    """The same by a stream whose state is the open segment, in segments."""
    return _growing(spark, d, "base", GROWN)


@query(GROWN_SQL + f""", j AS (SELECT *, 12 * CAST(pow(2, depth % 12) AS BIGINT) AS reach FROM c)
SELECT seq_id // 10000 AS seq_id, CAST(seq_id % 10000 AS INTEGER) AS seg_no, phrase_no, start_pos, parent_no, symbol,
  CASE WHEN reach > depth THEN NULL WHEN reach = depth THEN 0 ELSE list_position(phrases, left(phrase, CAST(depth - reach AS BIGINT))) END AS jump_no FROM j""")
def stream_dense(spark, d):
    """Far ancestors are known as soon as a phrase closes: B = 12 comes from the capacity."""
    return _growing(spark, d, "dense", GROWN).select("seq_id", "seg_no", "phrase_no", "start_pos", "parent_no", "symbol", "jump_no")


def _coin_of_key() -> str:
    return sqlparse.coin_sql(SEED, ALPHA).replace("+ seq_id)", "+ seq_id // 10000)")


@query(GROWN_SQL + ", " + _coin_of_key() + LAYOUT[len(COINS):] + " SELECT seq_id // 10000 AS seq_id, CAST(seq_id % 10000 AS INTEGER) AS seg_no, phrase_no, special, CAST(word_off AS BIGINT) AS word_off, CAST(position_off AS BIGINT) AS position_off FROM z")
def stream_sparse(spark, d):
    """Coins, word offsets and position codewords leave with their phrase."""
    return _growing(spark, d, "sparse", GROWN).select("seq_id", "seg_no", "phrase_no", "special", "word_off", "position_off")


@query(f"SELECT seq_id * 10 + j AS req_id, substr(x, l1, 1) AS value FROM (SELECT *, CAST(1 + (seq_id * 7919 + j * 104729) % length(x) AS BIGINT) AS l1 FROM ({CONV}), range(10) r(j))")
def serve_growing(spark, d):
    """Positions read from the committed dense codewords of all segments by search and guarded climb."""
    from trieaccess.streaming import serve

    t = load(spark, d, "conversations").select("conv_id", (F.length("role") + F.length("text") + 3).alias("n")).groupBy("conv_id").agg(F.sum("n").alias("n"))
    j = F.explode(F.sequence(F.lit(0), F.lit(9)))
    rows = t.select(F.col("conv_id").alias("seq_id"), "n", j.alias("j"))
    asks = rows.select((F.col("seq_id") * 10 + F.col("j")).alias("req_id"), "seq_id", (F.pmod(F.col("seq_id") * 7919 + F.col("j").cast("long") * 104729, F.col("n")) + 1).alias("l1"))
    return serve(asks, _growing(spark, d, "dense", 64), 64)


@query("SELECT count(*) AS late FROM conversations WHERE turn < 2 AND conv_id IN (SELECT conv_id FROM conversations WHERE turn >= 2)")
def stream_late(spark, d):
    """Turns that come a micro-batch after later ones of their conversation cannot be inserted: they are counted."""
    from trieaccess.streaming import compress_stream, replay

    t = load(spark, d, "conversations", "conv_id", "turn", "text").withColumn("no", F.when(F.col("turn") >= 2, 0).otherwise(1))
    out = replay(spark, t, lambda s: compress_stream(s, "conv_id", "turn", "text"), scratch_path(spark, "q"), 2, "no")
    return out.agg(F.count_if(F.col("phrase_no") == -1).alias("late"))


@query(JUMPS + "SELECT seq_id, phrase_no, start_pos, parent_no, jump_no, symbol FROM k")
def dense_words_udtf(spark, d):
    from trieaccess.functions import register

    register(spark)
    turns(spark, d).createOrReplaceTempView("_turns")
    return spark.sql("SELECT t.seq_id, c.phrase_no, c.start_pos, c.parent_no, c.jump_no, c.symbol FROM _turns t, LATERAL tx_dense(t.text) c")


@query(PARSE + "SELECT seq_id, phrase_no, parent_no, symbol FROM c")
def sparse_words_udtf(spark, d):
    """The sparse scheme's codewords are those of the base parse, whatever the coin says."""
    from trieaccess.functions import register

    register(spark)
    turns(spark, d).createOrReplaceTempView("_turns")
    return spark.sql("SELECT t.seq_id, c.phrase_no, c.parent_no, c.symbol FROM _turns t, LATERAL tx_sparse(t.text, 0.0625D, 64, 7) c")


@query(PARSE + "SELECT seq_id, count(*) AS m FROM c GROUP BY seq_id")
def text_sizes_sql(spark, d):
    from trieaccess.functions import register

    register(spark)
    turns(spark, d).createOrReplaceTempView("_turns")
    return spark.sql("SELECT seq_id, s.m FROM (SELECT seq_id, tx_size(text) AS s FROM _turns) WHERE s.m > 0")


@query("SELECT conv_id, length(t) AS n, md5(t) AS text_md5 FROM (SELECT conv_id, string_agg(text, '' ORDER BY turn) AS t FROM conversations GROUP BY conv_id) WHERE t IS NOT NULL")
def concat_compress(spark, d):
    """Many rows compressed into one store a key, and read back."""
    from trieaccess.functions import expand_blob

    packed = codec.compress_groups(load(spark, d, "conversations", "conv_id", "turn", "text"), "conv_id", "turn")
    parts = F.array_sort(F.collect_list(F.struct("part", "sub", "seg_no", expand_blob("blob").alias("text"))))
    whole = packed.groupBy("conv_id").agg(F.array_join(F.transform(parts, lambda p: p["text"]), "").alias("text"))
    return whole.select("conv_id", F.length("text").cast("long").alias("n"), F.md5(F.col("text").cast("binary")).alias("text_md5"))


@query()
def copies_gain(spark, d):
    """Codewords of a source's documents parsed one by one, and joined 64 neighbouring ids at a time: copies meet in one trie."""
    t = load(spark, d, "documents", "doc_id", "source", "text")
    alone = cost.word_counts(codec.cut(docs(spark, d)), ALPHA, GRID).groupBy("seq_id").agg(F.sum("w").alias("w"))
    alone = t.select(F.col("doc_id").alias("seq_id"), "source").join(alone, "seq_id").groupBy("source").agg(F.sum("w").alias("alone"))
    joined = codec.compress_groups(t, "source", "doc_id", scheme="base").groupBy("source").agg(F.sum("m").alias("joined"))
    return alone.withColumnRenamed("source", "_s").join(joined, F.col("_s").eqNullSafe(F.col("source"))).select("source", "alone", "joined", (F.col("joined") / F.col("alone")).alias("ratio"))


@query("SELECT l_orderkey AS seq_id, count(*) AS n, md5(string_agg(CAST(l_partkey AS VARCHAR), ' ' ORDER BY l_linenumber, l_partkey)) AS ids_md5 FROM lineitem GROUP BY l_orderkey")
def token_roundtrip(spark, d):
    """Sequences over an alphabet of ids: the parts of an order."""
    lines = load(spark, d, "lineitem", "l_orderkey", "l_linenumber", "l_partkey")
    ids = F.transform(F.array_sort(F.collect_list(F.struct("l_linenumber", "l_partkey"))), lambda x: x["l_partkey"])  # an order has a few lines
    seqs = lines.groupBy(F.col("l_orderkey").alias("seq_id")).agg(ids.alias("ids")).select("seq_id", codec.tokens_as_text("ids").alias("text"))
    back = codec.expand(codec.compress(codec.cut(seqs), "dense")).select("seq_id", codec.text_as_tokens("text").alias("ids"))
    return back.select("seq_id", F.size("ids").cast("long").alias("n"), F.md5(F.array_join(F.col("ids").cast("array<string>"), " ").cast("binary")).alias("ids_md5"))


@query()
def deflate_sizes(spark, d):
    """For orientation, not a comparison of the method: bytes of a sliding-window coder beside the text's, by language."""
    meta = load(spark, d, "documents", F.col("doc_id").alias("seq_id"), "lang")
    return cost.deflate_bytes(docs(spark, d)).join(meta, "seq_id").groupBy("lang").agg(F.sum("n_bytes").alias("n_bytes"), F.sum("deflated").alias("deflated"))
