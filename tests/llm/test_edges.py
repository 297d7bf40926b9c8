"""Nulls in any column, empty tables, repeated rows, ties, very long texts, extra columns with clashing names."""

import hashlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from trieaccess.llm import audio, decontamination, language, linededup, mixing, pitmanyor, simhash, tokens, toxicity, urls

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
LONG = "lorem ipsum dolor sit amet " * 8000
ROWS = [
    (1, "the cat sat on the mat", "en", "a", 22), (2, None, "en", "a", None), (3, "", None, None, 0), (4, "   \n\t ", "de", "b", 6), (None, "no id here", "en", None, 10), (5, "der hund und die katze", "de", "b", 22),
    (6, "the cat sat on the mat", "en", "a", 22), (6, "the cat sat on the mat", "en", "a", 22), (7, LONG, "en", "c", len(LONG)), (8, "\x00 nul \x85 \xa0 ÅÄÖ 日本 😀", None, "c", 9), (9, "12345 67", "en", "é", 8), (10, "you idiot", "en", "a", 9),
]
CLASH = ["held_out", "score", "predicted", "rejected", "lang_pred", "size", "epochs", "taken", "target", "fp", "fingerprint", "component_id", "host", "path", "rule", "verdict", "template", "purity", "shaped",
         "kept", "n_lines", "n_chunks", "hits", "src", "bin", "u", "whole", "wanted", "key", "h", "first", "root", "_copy", "seg", "n", "l", "b", "t", "Text_", "labelled", "blocked", "cut", "weight",
         "_h", "_s", "_j", "_keep", "_lines", "_ends", "_gone", "_doc", "_tkey", "_key", "_row", "_root", "_label", "row", "doc", "own", "lost", "lines", "given", "by_rule", "label", "a", "s", "x", "_kept"]


def docs(spark, rows=ROWS, clash=False):
    df = spark.createDataFrame(rows, DOCS)
    return df.select("*", *[F.lit("x").alias(c) for c in CLASH]) if clash else df


def labels(spark, rows=((1, 1, 0), (10, 0, 1), (5, None, None), (None, 1, 1), (99, 1, 1), (10, 0, 0))):
    return spark.createDataFrame(list(rows), "doc_id long, quality int, toxic int")


def bench(spark, rows=((1, "sat on the mat"), (2, None), (3, ""), (None, "hund und die katze"), (4, "cat"))):
    return spark.createDataFrame(list(rows), "item_id long, text string")


def pages(spark, rows=((1, "http://a.com/x/1"), (2, None), (3, "no scheme"), (4, "http://Example.COM/en/7?q"), (4, "http://Example.COM/en/7?q"), (5, "x://"), (None, "https://b.org/es/2#f"))):
    return spark.createDataFrame(list(rows), "page_id long, url string, html string") if rows and len(rows[0]) == 3 else spark.createDataFrame(list(rows), "page_id long, url string")


OPS = {
    "tokens": lambda s, d: tokens.tokenize_and_read(d, tokens.public_vocabulary()),
    "mixing": lambda s, d: mixing.mix(d),
    "simhash": lambda s, d: simhash.near_duplicates(d),
    "language": lambda s, d: language.identify(d),
    "toxicity": lambda s, d: toxicity.score_toxicity(d, labels(s)),
    "pitmanyor": lambda s, d: pitmanyor.score_texts(d),
    "linededup": lambda s, d: linededup.dedup_lines(d),
}


@pytest.mark.parametrize("name", sorted(OPS))
@pytest.mark.parametrize("clash", [False, True])
def test_one_row_a_document(spark, name, clash):
    d = docs(spark, clash=clash)
    out = OPS[name](spark, d)
    assert len(out.columns) == len(set(out.columns))
    rows = out.collect()
    assert sorted((r.doc_id is None, r.doc_id or 0) for r in rows) == sorted((r[0] is None, r[0] or 0) for r in ROWS)


@pytest.mark.parametrize("name", sorted(OPS))
def test_empty_table(spark, name):
    assert OPS[name](spark, docs(spark, [])).count() == 0


def test_decontamination(spark):
    got = {(r.doc_id, r.item_id) for r in decontamination.find_leaks(docs(spark, clash=True), bench(spark)).collect()}
    assert got == {(i, j) for i in (1, 6) for j in (1, 4)} | {(5, None)}
    assert decontamination.find_leaks(docs(spark, []), bench(spark)).count() == 0
    assert decontamination.find_leaks(docs(spark), bench(spark, ())).count() == 0
    assert decontamination.decontaminate(docs(spark, clash=True), bench(spark)).count() == len(ROWS) - 4


def test_urls(spark):
    d = pages(spark).select("*", *[F.lit("x").alias(c) for c in CLASH])
    out = urls.judge_urls(d)
    assert len(out.columns) == len(set(out.columns))
    got = sorted((r.page_id or 0, r.host, r.path, r.rule, r.verdict) for r in out.collect())
    assert got == [(0, "b.org", "/es/2", "org/es/", "block"), (1, "a.com", "/x/1", None, "allow"), (2, "", "", None, "allow"), (3, "", "", None, "allow"), (4, "example.com", "/en/7", "example.com/en/7", "allow"), (4, "example.com", "/en/7", "example.com/en/7", "allow"), (5, "", "", None, "allow")]
    assert urls.judge_urls(pages(spark).where("false")).count() == 0


def test_audio(spark):
    rows = [(i, [float(np.sin(i * 13.7 + k)) / 4 for k in range(64)]) for i in (0, 1, 2, 50, 50)] + [(3, None), (None, [0.1] * 64), (4, [None] * 64), (5, [])]
    d = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("print", F.lit(1)).withColumn("key", F.lit(1))
    out = audio.align_media(d, "vec_id", "embedding", audio.melody)
    got = out.collect()
    assert len(got) == len(rows) and {r.class_id for r in got if r.rec_id in (3, 5)} == {None}
    pairs = audio.pairs_of(out).collect()
    errors = {(r.query_id, r.rec_id): r.bit_errors for r in pairs}
    assert errors[(0, 0)] == 0 and errors[(50, 50)] == 0
    for r in got:
        if r.is_query and r.rec_id == 0:
            assert r.n_links == sum(p.query_id == 0 for p in pairs)
        if r.rec_id == 50:
            assert r.members == 2 and r.n_links == sum(p.query_id == 50 for p in pairs) / 2
    assert audio.align_media(d.where("false"), "vec_id", "embedding", audio.melody).count() == 0


def test_silence_and_steady_tones(spark):
    """Two minutes of silence match nothing; two minutes of one tone match each other at a bounded cost."""
    quiet, tone = np.zeros(120 * audio.RATE, np.int16), (8000 * np.sin(np.arange(120 * audio.RATE) * 0.7)).astype(np.int16)
    rows = [(50 * i, quiet.tobytes()) for i in range(20)] + [(50 * i + 5000, tone[i * 4096 :].tobytes()) for i in range(8)]
    got = {r.rec_id: r for r in audio.align_media(spark.createDataFrame(rows, "id long, pcm binary"), "id", "pcm").collect()}
    assert all(got[50 * i].n_links == 0 and got[50 * i].class_id is None for i in range(20)) and all(got[50 * i + 5000].n_links == 8 for i in range(8))


def test_values(spark):
    tok = {r.doc_id: r for r in OPS["tokens"](spark, docs(spark)).collect()}
    assert tok[2].n_tokens == tok[3].n_tokens == tok[4].n_tokens == 1 and tok[None].start == 0
    sim = {r.doc_id: r for r in OPS["simhash"](spark, docs(spark)).collect()}
    assert sim[2].fingerprint == sim[3].fingerprint == "0" * 16 and {sim[i].component_id for i in (2, 3, 4)} == {2} and sim[6].component_id == 1
    lang = {r.doc_id: r for r in OPS["language"](spark, docs(spark)).collect()}
    assert all(lang[i].lang_pred == "und" and lang[i].score == 0 for i in (2, 3, 4, 9))
    lm = {r.doc_id: r for r in OPS["pitmanyor"](spark, docs(spark)).collect()}
    assert lm[2].n_tokens == 1 and lm[2].score <= 0 and lm[7].n_tokens == 40001
    line = {r.doc_id: r for r in linededup.dedup_lines(docs(spark)).collect()}
    assert line[2].kept is None and line[3].kept == "" and line[7].kept == LONG
    assert hashlib.md5(line[8].kept.encode()).hexdigest() == hashlib.md5(ROWS[9][1].encode()).hexdigest()
