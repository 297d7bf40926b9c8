"""Every query of the library with an oracle, at the smallest size, and edge cases of the operators."""

import os

import duckdb
import pytest
from pyspark.sql import functions as F

from trieaccess import kernels as K
from trieaccess.operators import access as A
from trieaccess.operators import codec, hard
from trieaccess.plans import core_queries, planner, relational_queries
from trieaccess.sources import dealt

D = "/root/testdata/sf0.001"
QUERIES, SQL = core_queries.QUERIES | relational_queries.QUERIES, core_queries.SQL | relational_queries.SQL


def plain(v):
    return round(v, 9) if isinstance(v, float) else tuple(map(plain, v)) if isinstance(v, (list, tuple)) else v


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for f in os.listdir(D):
        con.execute(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM read_parquet('{D}/{f}')")
    return con


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query(spark, duck, name):
    df = QUERIES[name](spark, D)
    rows = [tuple(r) for r in df.collect()]
    if name not in SQL:
        assert rows
        return
    got = duck.execute(SQL[name])
    names = [c[0] for c in got.description]
    assert sorted(names) == sorted(df.columns)
    at = [names.index(c) for c in df.columns]
    want = [tuple(plain(r[i]) for i in at) for r in got.fetchall()]
    assert sorted(map(plain, rows), key=repr) == sorted(want, key=repr)


def test_null_empty_and_borders(spark):
    seqs = spark.createDataFrame([(1, None), (2, ""), (3, "x"), (4, "ab" * 50)], "seq_id long, text string")
    store = codec.compress(codec.cut(seqs, 16), "dense", capacity=16)
    assert {r.seq_id: r.text for r in codec.expand(store).collect()} == {2: "", 3: "x", 4: "ab" * 50}
    asks = spark.createDataFrame([(1, 1, 1, 1), (2, 2, 1, 1), (3, 3, 1, 1), (4, 4, 15, 18), (5, 4, 1, 100), (6, 4, 100, 101), (7, 4, 3, 2), (8, 99, 1, 1)], "req_id long, seq_id long, l1 long, l2 long")
    got = {r.req_id: (r.value, r.status) for r in A.access(store, asks, 16, salts=3).collect()}
    assert got[3] == ("x", "ok") and got[4] == ("abab", "ok") and got[5] == ("ab" * 50, "ok")
    assert all(got[i] == (None, "invalid") for i in (1, 2, 6, 7, 8))


@pytest.mark.parametrize("parts", [1, 4, 37])
def test_same_store_in_any_partitioning(spark, parts):
    seqs = codec.sequences(spark.read.parquet(f"{D}/documents.parquet"), "doc_id").repartition(parts)
    blobs = {r.seq_id: r.blob for r in codec.compress(codec.cut(seqs), "sparse", alpha=0.1, grid=16).collect()}
    assert all(blobs[r.seq_id] == K.pack(K.to_symbols(r.text), "sparse", alpha=0.1, grid=16, seq_id=r.seq_id) for r in seqs.collect())


@pytest.mark.parametrize("k,mode", [(4, "formal"), (6, "formal"), (6, "prose")])
def test_hard_strings(spark, k, mode):
    c = codec.codewords(codec.cut(hard.family(spark, k, mode)))
    q = 1 << (k - 1) >> 2
    diffs = hard.codeword_diff(c).collect()
    assert {r.m for r in c.groupBy("seq_id").count().withColumnRenamed("count", "m").collect()} == {(1 << k) - 2}
    assert len(diffs) == q == len({r.phrase_no for r in diffs})
    if mode == "formal":
        assert hard.witness_positions(hard.family(spark, k)).count() == {4: 7, 6: 41}[k]


def test_planner():
    assert planner.choose(10, 100, 10**6).strategy == "point"
    assert planner.choose(10**6, 10**6, 10**9).strategy == "kernel"
    assert planner.choose(10**6, 10**9, 10**9).strategy == "expand"


def test_a_hot_segment_is_split(spark):
    """One sequence, many requests: with salts its requests meet it in several groups, with the same answers."""
    seqs = spark.createDataFrame([(1, "abcde" * 200), (2, "x")], "seq_id long, text string")
    asks = spark.range(3000).select(F.col("id").alias("req_id"), F.lit(1).cast("long").alias("seq_id"), (F.col("id") % 1000 + 1).alias("l1"), F.least(F.col("id") % 1000 + 8, F.lit(1000)).alias("l2"))
    store = codec.compress(codec.cut(seqs, 128), "dense", capacity=128)
    got = {salts: sorted((r.req_id, r.value) for r in A.access(store, asks, 128, salts).collect()) for salts in (1, 7)}
    assert got[1] == got[7] and all(v == ("abcde" * 200)[i % 1000 : min(i % 1000 + 8, 1000)] for i, v in got[7])


def test_only_hot_segments_are_sent_more_than_once(spark):
    seqs = spark.range(300).select(F.col("id").alias("seq_id"), F.lit("abcde" * 20).alias("text"))
    asks = spark.range(3300).select(F.col("id").alias("req_id"), F.when(F.col("id") < 3000, F.floor(F.col("id") / 10)).otherwise(7).alias("seq_id"), (F.col("id") % 100 + 1).alias("l1"), (F.col("id") % 100 + 1).alias("l2"))
    store = codec.compress(codec.cut(seqs), "dense")
    asked, held = A.spread(A.route(asks, store, K.MAX_SYMBOLS), store.select("seq_id", "seg_no", "blob"), 8)
    sent = {r.seq_id: r["count"] for r in held.groupBy("seq_id").count().collect()}
    assert sent.pop(7) == 5 and len(sent) == 299 and sum(sent.values()) < 310  # 310 requests of one segment; no other has more than ten
    assert {r.salt for r in asked.where("seq_id = 7").collect()} == set(range(5))
    assert {r.req_id: r.value for r in A.access(store, asks, salts=8).collect()} == {i: "abcde"[i % 100 % 5] for i in range(3300)}


@pytest.mark.parametrize("name", [n + s for n in ("levelancestor_access", "scan_locate", "rankselect_locate", "parents_only_access") for s in ("", "_segments")])
def test_codewords_are_not_broadcast(spark, name):
    plan = QUERIES[name](spark, D)._jdf.queryExecution().executedPlan().toString()
    assert "Broadcast" not in plan and "SortMergeJoin" in plan


def test_climbing_by_parents(spark):
    text = "".join("0" + "1" * i for i in range(40)) + "0"
    segs = codec.cut(spark.createDataFrame([(1, text), (2, "aaaa")], "seq_id long, text string"), 500)
    asks = spark.createDataFrame([(i, 1, i + 1) for i in range(len(text))] + [(5000, 2, 4), (5001, 2, 5), (5002, 3, 1)], "req_id long, seq_id long, l1 long")
    c = codec.codewords(segs)
    got = {r.req_id: r.value for r in A.climb_parents(c, A.locate_rank(c, asks, 500)).collect()}
    assert got == dict(enumerate(text)) | {5000: "a"}


@pytest.mark.parametrize("few,ranges", [(0, False), (10**6, False), (0, True)])
def test_every_plan_gives_the_same(spark, few, ranges):
    seqs = codec.sequences(spark.read.parquet(f"{D}/documents.parquet"), "doc_id")
    asks = (A.range_requests if ranges else A.symbol_requests)(seqs, "seq_id")
    segs = codec.cut(seqs, 1000)
    got = {r.req_id: r.value for r in planner.planned_access(codec.compress(segs, "dense", capacity=1000), asks, 1000, segs, few).collect()}
    texts = {r.seq_id: r.text for r in seqs.collect()}
    assert got == {r.req_id: texts[r.seq_id][r.l1 - 1 : r.l2] for r in asks.collect()}
    assert planner.explain_access(segs, asks, few).strategy == ("expand" if ranges and planner.explain_access(segs, asks, few).strategy == "expand" else "point" if few else "kernel")


def test_dealing_a_scan(spark):
    scan = spark.read.parquet(f"{D}/documents.parquet")
    assert scan.rdd.getNumPartitions() < 4 and dealt(scan, "doc_id").rdd.getNumPartitions() == 8
    many = scan.repartition(9)
    assert dealt(many, "doc_id") is many


def test_late_rows_sealing_and_serving(spark, tmp_path):
    from trieaccess.streaming import compress_stream, replay, serve

    rows = [(1, 0, "abab", 0), (1, 1, "ababa", 1), (1, 0, "late", 2), (1, 2, "ba", 2), (1, 3, "bbab", 2), (2, 5, "xyxyx", 0), (2, 6, None, 1), (2, 7, "xy", 2), (None, 0, "q", 0)]
    df = spark.createDataFrame(rows, "k long, at int, text string, no int")
    out = replay(spark, df, lambda s: compress_stream(s, "k", "at", "text", "dense", 64), str(tmp_path), 3, "no")
    got = [r for r in out.collect()]
    assert [r.seq_id for r in got if r.phrase_no == -1] == [1]  # the late row, and nothing of it
    want = K.base_parse(K.to_symbols("abababababa" + "bbab"))
    one = sorted((r.phrase_no, r.parent_no) for r in got if r.seq_id == 1 and r.phrase_no > 0)
    assert one == [(i, int(want.parent[i])) for i in range(1, len(one) + 1)] and len(one) >= want.m - 1
    assert sum(r.depth for r in got if r.seq_id == 2 and r.seg_no == 0) == 5 and {r.seg_no for r in got if r.seq_id == 2} == {0, 1}
    assert [r.symbol for r in got if r.seq_id is None] == [ord("q")]
    asks = spark.createDataFrame([(1, 1, 6), (2, 1, 12), (3, 1, 14), (4, 9, 1)], "req_id long, seq_id long, l1 long")
    assert {r.req_id: r.value for r in serve(asks, out, 64).collect()} == {1: "b", 2: "b", 3: None, 4: None}  # position 14 is in the open phrase


def test_an_idle_segment_is_sealed():
    from trieaccess.streaming.online import Segment

    seg = Segment(3, 16, 0.1, 8, 7)
    first = seg.take(1, "ababa")
    seg = Segment.load(seg.dump())
    last = seg.seal()
    assert sum(r[5] for r in first + last) == 5 and seg.no == 1 and seg.seal() == []
    assert Segment.load(seg.dump()).take(2, "ab" * 10)[0][1] == 1


def test_joined_documents_against_the_kernel(spark):
    rows = spark.read.parquet(f"{D}/documents.parquet").select("doc_id", "source", "text").collect()
    got = {r.source: (r.alone, r.joined) for r in core_queries.QUERIES["copies_gain"](spark, D).collect()}
    for source in {r.source for r in rows}:
        own = sorted((r.doc_id, r.text) for r in rows if r.source == source and r.text is not None)
        parts = {i // 64: "".join(t for j, t in own if j // 64 == i // 64) for i, _ in own}  # no part holds more than 64 rows here
        count = lambda t: K.base_parse(K.to_symbols(t)).m
        assert got[source] == (sum(count(t) for _, t in own), sum(map(count, parts.values())))


def test_groups_and_tokens_at_the_edges(spark):
    from trieaccess.functions import expand_blob

    rows = spark.createDataFrame([("a", 0, "xy"), ("a", 70, "z"), (None, 1, "n"), ("b", 2, None), ("c", 3, ""), ("a", 0, "ab"), ("d", None, "q")], "k string, at int, text string")
    got = {(r.k, r.part): r.text for r in codec.compress_groups(rows, "k", "at").select("k", "part", expand_blob("blob").alias("text")).collect()}
    assert got == {("a", 0): "abxy", ("a", 1): "z", (None, 0): "n", ("c", 0): "", ("d", None): "q"}
    hot = spark.range(500).select(F.lit("k").alias("k"), F.lit(None).cast("int").alias("at"), F.col("id").cast("string").alias("text"))
    parts = codec.compress_groups(hot, "k", "at").select("n", expand_blob("blob").alias("text")).collect()
    assert len(parts) > 4 and max(r.n for r in parts) < 500 and sum(r.n for r in parts) == sum(len(str(i)) for i in range(500))
    assert codec.compress_groups(rows.where("false"), "k", "at").count() == 0
    ids = [[], [0, 5, 0xD7FF, 0xD800, 1_112_063 - 0x800], None]
    df = spark.createDataFrame([(x,) for x in ids], "ids array<int>")
    assert [r.ids for r in df.select(codec.text_as_tokens(codec.tokens_as_text("ids")).alias("ids")).collect()] == ids


def test_ids_beyond_code_points(spark):
    ids = [[0, 1_112_047, 1_112_048, 1_112_063, 1_112_064, 1_200_000, 2**31 - 1, 2**31, 2**63 - 1, -1, -(2**63), 7], [], [1_112_048**2, 1_112_048**2 - 1, 3]]
    df = spark.createDataFrame([(i, x) for i, x in enumerate(ids)], "seq_id long, ids array<long>")
    store = codec.compress(codec.cut(df.select("seq_id", codec.tokens_as_text("ids").alias("text"))), "dense")
    assert {r.seq_id: r.ids for r in codec.expand(store).select("seq_id", codec.text_as_tokens("text").alias("ids")).collect()} == dict(enumerate(ids))


@pytest.mark.parametrize("name", [f"hard_{n}{t}" for n in ("strings", "distribution", "diff", "witness", "extended") for t in ("", "_8")] + ["line_string_counts"])
def test_hard_strings_read_a_table(spark, name):
    assert any("documents" in f for f in QUERIES[name](spark, D).inputFiles())


def test_entry_works_without_llm():
    import __spark_entry__ as e

    assert "dense_access_symbol" in e.queries() and set(e.oracle_sql()) <= set(e.queries())
