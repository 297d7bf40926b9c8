"""The operators' methods against brute force, held-out accuracy and exact identities."""

import hashlib
import math
import os
import zlib
from collections import Counter

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from trieaccess.llm import audio, decontamination, language, mixing, pitmanyor, queries, tokens, urls

D = "/root/testdata/sf0.01"


def duck():
    con = duckdb.connect()
    for f in os.listdir(D):
        con.execute(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM read_parquet('{D}/{f}')")
    return con


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_oracle(spark, name):
    df = queries.queries()[name](spark, D)
    got = duck().execute(queries.oracle_sql()[name])
    at = [[c[0] for c in got.description].index(c) for c in df.columns]
    tidy = lambda r: tuple(round(v, 6) if isinstance(v, float) else v for v in r)
    assert sorted(map(tidy, map(tuple, df.collect())), key=repr) == sorted((tidy(r[i] for i in at) for r in got.fetchall()), key=repr)


@pytest.mark.parametrize("most_sent", [100_000, 0])
def test_mix_cuts_ties_and_merges_as_brute_force(spark, monkeypatch, most_sent):
    monkeypatch.setattr(mixing, "MAX_SENT", most_sent)
    rows = [(None, "a b c", "x")] * 10 + [(7, "a b", "y")] * 9 + [(i, "w " * (i % 5), None) for i in range(40)] + [(i, "", "z") for i in range(3)]
    out = mixing.mix(spark.createDataFrame(rows, "doc_id long, text string, source string"), keep=("text",)).collect()
    assert len(out) == len(rows) and all(r.size == len(r["_kept"].text.split()) and r.taken == r.size * r.epochs for r in out)
    per = {r.source: (r.source_size, r.target) for r in out}
    keyed = sorted((int(hashlib.md5(f"42:{'' if i is None else i}".encode()).hexdigest()[:12], 16), len(t.split()), str(s), s) for i, t, s in rows)
    want, start = Counter(), Counter()
    for _, size, _, s in keyed:
        total, target = per[s]
        whole = int(target // total) if total else 0
        want[s, size, size * (whole + (start[s] + size / 2 <= target - whole * total))] += 1
        start[s] += size
    assert Counter((r.source, r.size, r.taken) for r in out) == want
    assert {s: t[0] for s, t in per.items()} == dict(start)


def test_mix_hits_its_targets(spark):
    rows = queries.op2_mix(spark, D).collect()
    taken, target, largest = Counter(), {}, Counter()
    docs = {r.doc_id: r.source for r in spark.read.parquet(f"{D}/documents.parquet").collect()}
    for r in rows:
        s = docs[r.doc_id]
        taken[s] += r.taken
        target[s] = r.target
        largest[s] = max(largest[s], r.size)
        assert r.taken <= 3 * r.size
    assert all(abs(taken[s] - target[s]) <= largest[s] for s in target)
    assert math.isclose(sum(target.values()), sum({docs[r.doc_id]: r.source_size for r in rows}.values()))


def test_held_out_accuracy(spark):
    docs = {r.doc_id: r for r in spark.read.parquet(f"{D}/documents.parquet").collect()}
    lang = [r for r in queries.op6_language(spark, D).collect() if r.held_out]
    assert np.mean([r.lang_pred == docs[r.doc_id].lang for r in lang]) > 0.95
    more = D.replace("sf0.01", "sf0.1")  # some 3,000 labels to learn from
    toxic = {r.doc_id: r.toxic for r in spark.read.parquet(f"{more}/labels.parquet").collect()}
    tox = [r for r in queries.op7_toxicity(spark, more).collect() if r.held_out and r.doc_id in toxic]
    assert np.mean([r.predicted == toxic[r.doc_id] for r in tox]) > 0.97


def test_language_model(spark):
    rows = queries.op8_pitman_yor(spark, D).collect()
    words = {r.doc_id: r.text.encode().lower().split() for r in spark.read.parquet(f"{D}/documents.parquet").collect()}
    count = Counter()
    for i, w in words.items():
        if zlib.crc32(str(i).encode()) % 10:
            count.update([*w, b""])
    n, v = sum(count.values()), len(count)
    for r in rows:
        t = [*words[r.doc_id], b""]
        assert r.train_tokens == n and r.n_tokens == len(t) and r.n_known == sum(count[w] > 0 for w in t)
        assert math.isclose(r.base_score, sum(math.log10((count[w] + 0.1) / (n + 0.1 * (v + 1))) for w in t), rel_tol=1e-9)
    held = [r for r in rows if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)


def test_predictive_probabilities_sum_to_one():
    """One partition: the probabilities of all words and the unknown one sum to 1 in the parent and in each context."""
    rng = np.random.default_rng(1)
    dish_ctx, party = np.unique(rng.zipf(1.5, (4000, 2)).clip(1, 50), axis=0, return_counts=True)
    (dishes, dish), (contexts, ctx) = (np.unique(dish_ctx[:, i], return_inverse=True) for i in (0, 1))
    size = np.bincount(ctx, party)
    for tables, top_party, top_tables in pitmanyor.sample_seats(party, dish, ctx, len(dishes), size, len(dishes), 1.0, 1, rng):
        assert (tables <= party).all() and (tables >= 1).all() and (top_tables >= 1).all() and (top_tables <= top_party).all()
        assert (top_party == np.bincount(dish, tables)).all()
        top = pitmanyor.parent_probability(top_party, top_tables, top_party.sum(), top_tables.sum(), len(dishes))
        unknown = pitmanyor.parent_probability(0, 0, top_party.sum(), top_tables.sum(), len(dishes))
        assert math.isclose(top.sum() + unknown, 1, rel_tol=1e-9)
        for u in range(len(contexts)):
            own, of = np.zeros(len(dishes)), np.zeros(len(dishes))
            own[dish[ctx == u]], of[dish[ctx == u]] = party[ctx == u], tables[ctx == u]
            p = pitmanyor.context_probability(own, of, size[u], of.sum(), top)
            assert math.isclose(p.sum() + pitmanyor.context_probability(0, 0, size[u], of.sum(), unknown), 1, rel_tol=1e-9)


def test_seats_follow_the_restaurant_rule():
    """The mean number of tables of a party against the rule's expectation, by seating one customer after another many times."""
    rng = np.random.default_rng(2)
    party, new, d = np.array([1, 2, 7, 40, 300]), np.array([0.5, 3.0, 20.0, 1.0, 8.0]), 0.6
    got = np.mean([pitmanyor.seat(party, new, d, rng) for _ in range(1500)], axis=0)
    for c, a, mean in zip(party, new, got):
        share = np.zeros(c + 2)  # share[t]: probability of t tables
        share[1] = 1
        for n in range(1, c):
            t = np.arange(c + 2)
            open_ = np.where(t <= n, a / np.maximum(1e-9, n - d * t + a), 0)
            share = share * (1 - open_) + np.r_[0, (share * open_)[:-1]]
        assert mean == pytest.approx((share * np.arange(c + 2)).sum(), rel=0.05)


def test_scores_by_brute_force(spark):
    """One chunk and one word partition after another: the score of each text from the sampled seats of all words, counted here anew."""
    rng = np.random.default_rng(3)
    rows = [(i, " ".join(f"w{x}" for x in rng.zipf(1.6, 60).clip(1, 40))) for i in range(1, 120)]
    got = {r.doc_id: r for r in pitmanyor.score_texts(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    pairs, size = Counter(), Counter()
    for i, text in rows:
        if zlib.crc32(str(i).encode()) % 10:
            words = [*text.split(), ""]
            pairs.update(zip(words, ["", *words[:-1]]))
            size.update(words)
    # the expectation of the score: seats sampled in one piece, many times
    (dishes, dish), (contexts, ctx) = (np.unique([k[i] for k in pairs], return_inverse=True) for i in (0, 1))
    party, n = np.array(list(pairs.values())), {k: j for j, k in enumerate(pairs)}
    prob = []
    for seed in range(12):
        for tables, tp, tt in pitmanyor.sample_seats(party, dish, ctx, len(dishes), np.array([size[u] for u in contexts]), len(dishes), 1.0, 1, np.random.default_rng(seed)):
            top = pitmanyor.parent_probability(tp, tt, tp.sum(), tt.sum(), len(dishes))
            own = np.bincount(ctx, tables)
            prob.append((top, tables, own, pitmanyor.parent_probability(0, 0, tp.sum(), tt.sum(), len(dishes))))
    place, cplace = {w: j for j, w in enumerate(dishes)}, {w: j for j, w in enumerate(contexts)}
    for i, text in rows[:20]:
        words, want = [*text.split(), ""], 0.0
        for w, u in zip(words, ["", *words[:-1]]):
            p = []
            for top, tables, own, unknown in prob:
                j = n.get((w, u))
                p.append(pitmanyor.context_probability(party[j] if j is not None else 0, tables[j] if j is not None else 0, size[u], own[cplace[u]] if u in cplace else 0, top[place[w]] if w in place else unknown))
            want += math.log10(np.mean(p))
        assert got[i].score == pytest.approx(want, rel=0.02)


def test_a_rare_word_is_a_context(spark):
    """`rare` is under 1/1024 of the training tokens and always followed by `next`: what follows it is scored with it."""
    fill = " ".join(f"w{i % 97}" for i in range(400))
    train = [i for i in range(1, 400) if zlib.crc32(str(i).encode()) % 10][:200]
    held = [i for i in range(1, 400) if not zlib.crc32(str(i).encode()) % 10][:2]
    rows = [(i, fill + (" rare next" if k < 40 else " w1 w2")) for k, i in enumerate(train)] + [(held[0], "rare next"), (held[1], "next rare")]
    got = {r.doc_id: r for r in pitmanyor.score_texts(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert 40 < got[held[0]].train_tokens / 1024 and got[held[0]].base_score == pytest.approx(got[held[1]].base_score)
    assert got[held[0]].score > got[held[1]].score + 0.5  # the gap is sampled: about 0.95, where a model without that context has none


def test_small_and_deep_sections_are_judged_by_their_own_labels(spark):
    rows = [(f"http://h.com/s{chr(97 + k)}/x1", 0) for k in range(25) for _ in range(60)]  # clean sections
    rows += [("http://h.com/bad/x1", 1)] * 40 + [("http://h.com/bad/x2", None)]  # under 5 % of the host's pages
    rows += [("http://only.com/bad/x1", 1)] * 30 + [("http://only.com/bad/x2", None)] + [(f"http://only.com/{chr(97 + k)}/x1", None) for k in range(20) for _ in range(60)]
    deep = "http://deep.com/a/b/c/d/e"
    rows += [(f"{deep}/good/x1", 0)] * 60 + [(f"{deep}/bad/x1", 1)] * 20 + [(f"{deep}/bad/x2", None), (f"{deep}/good/x2", None)]
    df = spark.createDataFrame(rows, "url string, mark int")
    got = {r.url: r.verdict for r in urls.judge_urls(df, (), F.col("mark")).collect()}
    assert {u for u, v in got.items() if v == "block"} == {f"{u}/{x}" for u in ("http://h.com/bad", "http://only.com/bad", f"{deep}/bad") for x in ("x1", "x2")}


def test_texts_without_letters_take_no_share_of_the_teachers(spark):
    empty = spark.range(100_000, 150_000).select(F.col("id").alias("doc_id"), F.lit(None).cast("string").alias("text"), F.lit("aa").alias("lang"))
    texts = spark.range(200).select(F.col("id").alias("doc_id"), F.when(F.col("id") < 100, "saluton amiko").otherwise("good morning friend").alias("text"), F.when(F.col("id") < 100, "aa").otherwise("bb").alias("lang"))
    assert {l for m in language.fit(empty.unionByName(texts), per_lang=20) for l in m.langs} == {"aa", "bb"}


def test_groups_of_languages_and_their_vectors(spark, monkeypatch):
    """The prediction in groups equals that in one group, and the cosine that of dictionaries of trigrams."""
    docs = spark.read.parquet(f"{D.replace('sf0.01', 'sf0.001')}/documents.parquet").select("doc_id", "text", "lang")
    whole = {r.doc_id: (r.lang_pred, round(r.score, 5)) for r in language.identify(docs).collect()}
    monkeypatch.setattr(language, "GROUP", 1)
    assert {r.doc_id: (r.lang_pred, round(r.score, 5)) for r in language.identify(docs).collect()} == whole
    model = language.fit(docs)[0]
    for text in (b"Hello, World 42", b"a", "äöü".encode()):
        raw = b" " + bytes(b + 32 if 65 <= b <= 90 else b if 97 <= b <= 122 or b > 127 else 32 for b in text) + b" "
        tf = Counter(((raw[i] << 16 | raw[i + 1] << 8 | raw[i + 2]) * 2654435761 % 2**32 >> 20) % language.DIMS for i in range(len(raw) - 2))
        v = {k: (1 + math.log(n)) * float(model.idf[k]) for k, n in tf.items()}
        norm = math.sqrt(sum(x * x for x in v.values()))
        best = max(sum(x / norm * float(c[k]) for k, x in v.items()) for c in model.c)
        assert model.nearest([text])[1][0] == pytest.approx(best, abs=1e-4)


def test_memory_of_short_texts_and_repeated_grams():
    """Ten thousand short texts, and a passage and a document that repeat one gram, stay within 300 MB."""
    import tracemalloc

    model = language.Centroids(np.ones(language.DIMS, np.float32), ["aa"], np.ones((1, language.DIMS), np.float32), np.zeros(1))
    texts = [b"short one"] * 10_000
    tracemalloc.start()
    assert sum(len(model.nearest(texts[i:j])[0]) for i, j in language.slices(texts)) == len(texts)
    assert tracemalloc.get_traced_memory()[1] < 100 << 20
    tracemalloc.reset_peak()
    block = decontamination.Passages([(1, b"ha " * 130 + b"x"), (2, b"ha " * 130)], 0.05)
    found = block.find([b"ha " * 100_000])[0]
    assert {h["item_id"] for h in found} >= {2} and tracemalloc.get_traced_memory()[1] < 300 << 20
    tracemalloc.stop()


def test_rules_beyond_those_compiled(spark, monkeypatch):
    df = spark.createDataFrame([(u,) for u in ("http://a.example.com/en/7x", "http://b.com/en/1", "http://x.net/de/8", "http://example.net/de/8", "http://com/en/", "https://q.org/es", None, "http://x.com./en/")], "url string")
    want = [(r.rule, r.verdict) for r in urls.judge_urls(df).collect()]
    monkeypatch.setattr(urls, "COMPILED", 0)
    assert sorted([(r.rule, r.verdict) for r in urls.judge_urls(df).collect()], key=str) == sorted(want, key=str) and ("example.com/en/7", "allow") in want


def edit_distance(a, b):
    row = np.zeros(len(b) + 1, int)
    for c in a:
        new = np.minimum(row[1:] + 1, row[:-1] + (np.frombuffer(b, np.uint8) != c))
        full = [row[0] + 1]
        for x in new:
            full.append(min(x, full[-1] + 1))
        row = np.array(full)
    return row.min()


def test_edited_passages():
    rng = np.random.default_rng(4)
    words = ["".join(rng.choice(list("abcdefgh"), rng.integers(2, 8))) for _ in range(400)]
    text = lambda n: " ".join(rng.choice(words, n))
    items = [(i, text(40).encode()) for i in range(20)]
    block = decontamination.Passages(items, 0.05)
    for i, t in items:
        k = int(block.k[i])
        for edits in (0, 1, k, 3 * k + 20):
            s = bytearray(t)
            for _ in range(edits):
                at = rng.integers(0, len(s))
                s[at : at + rng.integers(0, 2)] = b"#" * int(rng.integers(0, 2))
            doc = text(100).encode() + b" " + bytes(s) + b" " + text(100).encode()
            near = edit_distance(t, decontamination.normal(doc))
            found = {h["item_id"]: h["edits"] for h in block.find([doc])[0]}
            assert (i in found) == (near <= k) and (i not in found or found[i] == near)


def brute_votes(a, b):
    """(offset, votes) with the most equal frames of a and b, the smallest of several."""
    n = Counter(j - i for i, x in enumerate(a) for j, y in enumerate(b) if x == y)
    return min(n.items(), key=lambda kv: (-kv[1], kv[0])) if n else (0, 0)


def test_audio_offsets(spark):
    rng = np.random.default_rng(3)
    whole = audio.melody(((rng.random(64) - 0.5) / 2).tolist())
    late = (whole[audio.HOP * 20 :] * 0.6 + rng.normal(0, 100, len(whole) - audio.HOP * 20)).astype(np.int16)
    other = audio.melody(((rng.random(64) - 0.5) / 2).tolist())
    rows = [(50, whole.tobytes()), (51, late.tobytes()), (52, other.tobytes())]
    pairs = audio.pairs_of(audio.align_media(spark.createDataFrame(rows, "id long, pcm binary"), "id", "pcm")).collect()
    assert {(r.query_id, r.rec_id, r.offset) for r in pairs} == {(50, 50, 0), (50, 51, -20)}


def test_audio_search_by_brute_force(spark):
    vectors = spark.read.parquet(f"{D.replace('sf0.01', 'sf0.001')}/embeddings.parquet").select("vec_id", "embedding").limit(150).collect()
    vectors = [(r.vec_id, r.embedding) for r in vectors] + [(1000, vectors[0].embedding), (1050, [0.1] * 64), (1051, [0.1] * 60 + [0.2] * 4)]
    out = audio.align_media(spark.createDataFrame(vectors, "vec_id long, embedding array<float>"), "vec_id", "embedding", audio.melody)
    got = {(r.query_id, r.rec_id): (r.offset, r.votes, r.frames, round(r.bit_errors, 9)) for r in audio.pairs_of(out).collect()}
    prints = {i: audio.packed_fingerprint(audio.chroma(audio.melody(v))) for i, v in vectors}
    want = {}
    for q in [i for i, _ in vectors if i % 50 == 0]:
        for i, b in prints.items():
            offset, n = brute_votes(prints[q].tolist(), b.tolist())
            frames, errors = audio.align(prints[q], b, offset)
            if n >= 6 and frames >= 24 and errors <= 0.2:
                want[q, i] = (offset, n, frames, round(errors, 9))
    assert got == want and len(want) > 4


def test_box_filters_by_brute_force():
    frames = np.random.default_rng(5).random((30, 12))
    got = audio.packed_fingerprint(frames)
    t, value = 4, 0
    for kind, y, tall, wide in audio.filters():
        win = frames[t : t + wide, y : y + tall]
        half, third, mid = wide // 2, wide // 3, tall // 2
        a = [win[:, mid:].sum(), win[half:].sum(), win[:half, :mid].sum() + win[half:, mid:].sum(), win[third : wide - third].sum(), win[:, tall // 3 : tall - tall // 3].sum()][kind]
        value = value << 2 | int(audio._GRAY[np.searchsorted((-0.15, 0.0, 0.15), np.log((1 + a) / (1 + win.sum() - a)))])
    assert got[t] == value


def test_direct_access():
    ids = np.random.default_rng(6).zipf(1.3, 5000).clip(0, 2**31).astype(np.uint32)
    levels, bitmaps, ranks = tokens.dac_encode(ids)
    assert (tokens.dac_decode(levels, bitmaps) == ids).all() and all(tokens.dac_get(levels, bitmaps, ranks, i) == ids[i] for i in range(0, 5000, 7))
