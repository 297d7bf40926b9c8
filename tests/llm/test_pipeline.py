"""The pipeline against brute force, and its stages on clashing columns."""

import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline as P
from trieaccess.llm import decontamination, mixing, simhash, tokens, toxicity

D = "/root/testdata/sf0.001"


def close_groups(fps, rule=simhash.EXACT, more=None, within=False):
    """Component of each fingerprint by comparing all pairs; `within`: those in the radius only, which are found in wide buckets too."""
    fps = np.unique(np.array(fps, np.uint64))
    more = np.array([more[int(f)] if more else 0 for f in fps], np.int64).view(np.uint64)
    root = np.arange(len(fps))
    for i, f in enumerate(fps):
        ok = np.bitwise_count(fps ^ f) <= rule.radius
        if rule.total is not None:
            equal = sum(((fps ^ f) >> np.uint64(at)) & np.uint64((1 << n) - 1) == 0 for at, n in rule.spans)
            ok = ok if within else equal >= rule.blocks - rule.radius
            ok &= np.bitwise_count(fps ^ f).astype(int) + np.bitwise_count(more ^ more[i]) <= rule.total
        for j in np.flatnonzero(ok):
            a, b = root[i], root[j]
            root[root == max(a, b)] = min(a, b)
    return {int(f): int(r) for f, r in zip(fps, root)}


def test_stages(spark):
    docs = spark.read.parquet(f"{D}/documents.parquet").withColumn("size", F.lit(1)).withColumn("predicted", F.lit(0)).withColumn("epochs", F.lit(9))
    cols = docs.columns
    clean = P.drop_toxic(spark, docs, D)
    assert clean.columns == cols
    fm = toxicity.fit(docs, spark.read.parquet(f"{D}/labels.parquet"))
    seen = {r.doc_id: r.text for r in docs.collect()}
    ids = {r.doc_id for r in clean.collect()}
    for i, text in seen.items():
        place = {int(k): n for n, k in enumerate(fm.kept)}
        at = sorted(place[s] for s in toxicity.text_slots(text.encode(), {}) if s in place)
        pairs = sum(float(fm.v[a] @ fm.v[b]) for n, a in enumerate(at) for b in at[n + 1 :])
        margin = fm.bias + sum(fm.w[a] for a in at) + pairs
        assert (1 / (1 + np.exp(-margin)) < 0.3) == (i in ids)
    single = P.drop_near_copies(spark, clean, D)
    h = {i: simhash.shingle_hashes(seen[i].encode(), 5) for i in ids}
    fp, more = {i: simhash.simhash(x) for i, x in h.items()}, {}
    for i, x in h.items():
        second = int(np.uint64(simhash.simhash(simhash.second_hash(x))).view(np.int64))
        more[fp[i]] = min(more.get(fp[i], second), second)
    group = close_groups(list(fp.values()), simhash.CORPUS, more)
    best = {}
    for i in sorted(ids):
        best.setdefault(group[fp[i]], i)
    left = {r.doc_id for r in single.collect()}
    assert single.columns == cols and left == set(best.values())
    items = [r.text for r in spark.read.parquet(f"{D}/benchmark.parquet").collect()]
    kept = P.drop_leaks(spark, single, D)
    got = {r.doc_id for r in kept.collect()}
    exact = {i for i in left if any(decontamination.normal(t.encode()) in decontamination.normal(seen[i].encode()) for t in items)}
    assert kept.columns == cols and not got & exact and left - got == exact
    mixed = P.mix_sources(spark, kept, D)
    times = {r.doc_id: r.epochs for r in mixing.mix(kept).collect()}
    n = {r.doc_id: r["count"] for r in mixed.groupBy("doc_id").count().collect()}
    assert mixed.columns == cols and n == {i: e for i, e in times.items() if e}
    out = P.write_tokens(spark, mixed, D).orderBy("start").collect()
    assert len(out) == sum(n.values()) and [r.doc_id for r in out] == sorted(r.doc_id for r in out)


def test_run(spark):
    rows = P.run(spark, D).collect()
    assert rows and {len(P.STAGES)} == {5} and P.ORACLE_SQL is None


def test_repeated_ids(spark):
    rows = [(1, "a b c d e f", "en", "s", 1), (1, "a b c d e f", "en", "s", 1), (None, "q w e r t", "en", "s", 1), (None, None, None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted(P.drop_near_copies(spark, docs, D).collect(), key=str) and P.drop_near_copies(spark, docs.where("false"), D).count() == 0
    assert P.drop_near_copies(spark, docs, D).where("doc_id = 1").count() == 1


def test_one_row_a_group_whatever_its_id(spark):
    """Different texts stay though their ids are null or equal; copies go though theirs are."""
    far = [" ".join(f"{w}{i}" for i in range(30)) for w in "abcde"]
    rows = [(None, far[0]), (None, far[1]), (None, far[1]), (3, far[2]), (3, far[3]), (4, far[4]), (None, far[4]), (5, far[4]), (4, far[4])]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted(((r.doc_id, r.text) for r in P.drop_near_copies(spark, docs, D).collect()), key=str)
    assert got == sorted([(None, far[0]), (None, far[1]), (3, far[2]), (3, far[3]), (4, far[4])], key=str)


def test_store(spark):
    from tokenizers import Tokenizer

    docs = spark.read.parquet(f"{D}/documents.parquet")
    from trieaccess.llm.common import Scratch

    store = Scratch(spark, "t").path("store")
    tokens.write_tokens(docs, store, tokens.public_vocabulary())
    tk = Tokenizer.from_file(tokens.public_vocabulary())
    flat = []
    for r in docs.orderBy("doc_id").collect():
        flat += [*tk.encode(r.text, add_special_tokens=False).ids, 2]
    assert {r.doc_id: r.ids for r in tokens.read_ids(spark, store).collect()}[0] == [*tk.encode(docs.where("doc_id = 0").first().text, add_special_tokens=False).ids, 2]
    at = [0, 1, 777, len(flat) // 2, len(flat) - 1, len(flat)]
    got = tokens.tokens_at(spark, store, spark.createDataFrame([(p,) for p in at], "pos long"))
    assert {r.pos: r.id for r in got.collect()} == {p: flat[p] for p in at[:-1]}


def test_token_query_by_the_library(spark):
    """start, n_tokens and ids_crc32 of every document against the tokenizer itself."""
    from tokenizers import Tokenizer

    docs = spark.read.parquet(f"{D}/documents.parquet")
    tk, start = Tokenizer.from_file(tokens.public_vocabulary()), 0
    got = {r.doc_id: r for r in tokens.tokenize_and_read(docs, tokens.public_vocabulary()).collect()}
    for r in docs.orderBy("doc_id").collect():
        ids = [*tk.encode(r.text or "", add_special_tokens=False).ids, 2]
        assert (got[r.doc_id].start, got[r.doc_id].n_tokens, got[r.doc_id].ids_crc32) == (start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)


def test_another_vocabulary_under_the_same_name(tmp_path):
    """The steps done here are chosen by the vocabulary's fields, not by its name."""
    import shutil

    from tokenizers import Tokenizer

    path = str(tmp_path / "word_bpe_49k.json")
    shutil.copy(tokens.public_vocabulary("byte_bpe_50k.json"), path)
    assert tokens.plain_pipeline(tokens.public_vocabulary()) and not tokens.plain_pipeline(path)
    got = np.frombuffer(tokens.WordTokenizer(path, 2)([b"Word"])[0], "<u4").tolist()
    assert got == [*Tokenizer.from_file(path).encode("Word", add_special_tokens=False).ids, 2]


EDGE = [(1, "a b c d e f", "en", "s", 11), (1, "a b c d e f", "en", "s", 11), (None, "q w e r t", "en", None, 9), (2, None, None, "s", None), (3, "", "en", "s", 0), (4, "x " * 50_000, None, "t", 100_000)]


@pytest.mark.parametrize("name,stage", P.STAGES)
def test_stage_edges(spark, name, stage):
    """Nulls, repeats, long texts, clashing names, empty tables: each stage keeps its contract."""
    names = ["key", "row", "mark", "fp", "root", "kept", "_kept", "_row", "_keep", "src", "u", "size", "epochs", "extra", "hits", "id", "task", "salt", "s", "own"]
    docs = spark.createDataFrame(EDGE, "doc_id long, text string, lang string, source string, n_chars long").select("*", *[F.lit(i).alias(c) for i, c in enumerate(names)])
    out, none = stage(spark, docs, D), stage(spark, docs.where("false"), D)
    assert none.count() == 0
    rows = out.collect()
    if stage is P.write_tokens:
        assert len(rows) == len(EDGE) and set(out.columns) >= {"doc_id", "start", "n_tokens", "ids_crc32"}
        return
    assert out.columns == docs.columns and none.columns == docs.columns
    assert all(r[c] == i for r in rows for i, c in enumerate(names))
    texts = {(r.doc_id, r.text) for r in rows}
    if stage is P.drop_near_copies:
        assert len(rows) == 4 and texts == {(1, EDGE[0][1]), (None, EDGE[2][1]), (2, None), (4, EDGE[5][1])}
    elif stage is not P.mix_sources:
        assert len(rows) == len(EDGE)


@pytest.mark.parametrize("wide,rule", [(2, simhash.EXACT), (5, simhash.EXACT), (4096, simhash.EXACT), (4096, simhash.Rule(5, 3, 6, 9)), (3, simhash.Rule(5, 3, 6, 9)), (4096, simhash.CORPUS)], ids=str)
def test_links(spark, wide, rule):
    """Dense balls, chains and hot buckets: the links connect exactly what all close pairs would; in wide buckets with a total, at least those in the radius."""
    from trieaccess.llm.common import Scratch

    rng = np.random.default_rng(wide)
    base = rng.integers(0, 2**63, 6, dtype=np.uint64)
    fps = [int(b) ^ (1 << int(i)) ^ (1 << int(j)) for b in base for i, j in rng.integers(0, 64, (60, 2))] + [int(x) for x in rng.integers(0, 2**63, 200, dtype=np.uint64)] + [0, 1, 2**63]
    fps = sorted(set(fps))
    more = {f: int(rng.integers(0, 1 << 12)) - (1 << 62) if rule.total is not None else 0 for f in fps}
    df = spark.createDataFrame([(int(np.uint64(f).view(np.int64)), more[f]) for f in fps], "fp long, more long")
    edges = [(int(np.int64(r.a).view(np.uint64)), int(np.int64(r.b).view(np.uint64))) for r in simhash.links(df, Scratch(spark, "t"), wide, rule).collect()]
    root = {f: f for f in fps}

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        root[max(top(a), top(b))] = min(top(a), top(b))
    want, mine = close_groups(fps, rule, more), {}
    for f in fps:
        assert mine.setdefault(top(f), want[f]) == want[f]
    if rule.total is None or wide > len(fps):
        assert len({top(f) for f in fps}) == len(set(want.values()))
    least, mine = close_groups(fps, rule, more, within=True), {}
    assert all(mine.setdefault(least[f], top(f)) == top(f) for f in fps)


def test_components(spark):
    from trieaccess.llm.common import Scratch

    chain = [(i, i + 1) for i in range(40)] + [(100, 101), (101, 100), (7, 7)]
    got = {r.node: r.root for r in simhash.components(spark.createDataFrame(chain, "a long, b long"), Scratch(spark, "t")).collect()}
    assert got == {i: 0 for i in range(1, 41)} | {101: 100}
