"""Toxicity: a factorization machine over hashed terms.

Terms are the distinct lower-cased words of a text without outer punctuation, and the 5-byte prefixes of longer words,
hashed to 2^18 slots. The `SLOTS` slots with the largest chi-square against the label stay; the machine
scores b + sum w + sum over pairs <v_i, v_j>, so that terms harmless by themselves can count together.

The machine is fitted in one task on a sample of at most about `max_rows` labelled rows (picked by a hash of the id);
scoring reads every whole text. Labels come only from rows whose crc32(id) mod 4 is not 2.

Nulls: null and empty texts have no terms and get the score of the bias; rows with a null label or id don't teach.
A document with several labels is toxic if one says so. Without labelled rows of both kinds the score is the
smoothed share of toxic rows. Repeated rows are scored each. Empty table: empty result. Extra columns are kept.
"""

from __future__ import annotations

import pickle
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, crc_mod, text_bytes

HASH_BITS, SLOTS, FACTORS, CACHE = 18, 4096, 8, 400_000
EDGE = b".,;:!?\"'()[]{}<>*&%$#@~|-_/\\+="


def word_slots(word: bytes) -> tuple[int, ...]:
    core = word.strip(EDGE) or word
    mask = (1 << HASH_BITS) - 1
    whole = zlib.crc32(core) & mask
    return (whole, zlib.crc32(b"^" + core[:5]) & mask) if len(core) > 5 else (whole,)


def text_slots(text: bytes, seen: dict[bytes, tuple[int, ...]]) -> set[int]:
    out: set[int] = set()
    for w in set(text.lower().split()):
        s = seen.get(w)
        if s is None:
            if len(seen) > CACHE:
                seen.clear()
            s = seen[w] = word_slots(w)
        out.update(s)
    return out


class FactorizationMachine:
    """Parameters over the kept slots; `slot` maps a hash to its row."""

    def __init__(self, kept: np.ndarray, seed: int = 7):
        self.kept = kept
        self.bias, self.w = 0.0, np.zeros(len(kept))
        self.v = np.random.default_rng(seed).normal(0, 0.05, (len(kept), FACTORS))

    def margin(self, row: np.ndarray, at: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
        """(margins of n texts, their factor sums) for pairs (text number, parameter row)."""
        s1 = np.zeros((n, FACTORS))
        np.add.at(s1, row, self.v[at])
        own = np.bincount(row, (self.v[at] ** 2).sum(1), n)
        return self.bias + np.bincount(row, self.w[at], n) + ((s1**2).sum(1) - own) / 2, s1

    def fit(self, rows: list[np.ndarray], y: np.ndarray, epochs: int = 12, rate: float = 0.1, l2: float = 1e-4, batch: int = 64, seed: int = 7) -> None:
        """AdaGrad on the log loss."""
        rng, gb = np.random.default_rng(seed), 1e-8
        gw, gv = np.full(len(self.w), 1e-8), np.full(self.v.shape, 1e-8)
        share = np.clip(y.mean(), 1e-3, 1 - 1e-3)
        self.bias = float(np.log(share / (1 - share)))
        for _ in range(epochs):
            order = rng.permutation(len(rows))
            for a in range(0, len(order), batch):
                pick = order[a : a + batch]
                at = np.concatenate([rows[i] for i in pick])
                row = np.repeat(np.arange(len(pick)), [len(rows[i]) for i in pick])
                m, s1 = self.margin(row, at, len(pick))
                err = 1 / (1 + np.exp(-np.clip(m, -30, 30))) - y[pick]
                used, where = np.unique(at, return_inverse=True)
                dw = np.bincount(where, err[row], len(used)) + l2 * self.w[used]
                dv = np.zeros((len(used), FACTORS))
                np.add.at(dv, where, err[row, None] * (s1[row] - self.v[at]))
                dv += l2 * self.v[used]
                gw[used] += dw**2
                gv[used] += dv**2
                gb += err.sum() ** 2
                self.w[used] -= rate * dw / np.sqrt(gw[used])
                self.v[used] -= rate * 0.3 * dv / np.sqrt(gv[used])
                self.bias -= rate * err.sum() / np.sqrt(gb)


def choose_slots(rows: list[set[int]], y: np.ndarray, most: int = SLOTS, least: int = 3) -> np.ndarray:
    """The slots most dependent on the label, by chi-square with Yates' correction."""
    df = np.zeros((2, 1 << HASH_BITS))
    for s, label in zip(rows, y):
        df[int(label), list(s)] += 1
    pos, neg = df[1], df[0]
    p, n = y.sum(), len(y) - y.sum()
    total = pos + neg
    gap = np.maximum(0, np.abs(pos * (n - neg) - neg * (p - pos)) - len(y) / 2)
    chi = np.where(total >= least, len(y) * gap**2 / np.maximum(1, total * (len(y) - total) * p * n), 0)
    best = np.argsort(-chi, kind="stable")[:most]
    return np.sort(best[chi[best] > 3.84])


def _train(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    seen: dict[bytes, tuple[int, ...]] = {}
    rows, y = [], []
    for b in batches:
        for text, label in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
            rows.append(text_slots(text, seen))
            y.append(float(label > 0))
    y = np.array(y)
    if 0 < y.sum() < len(y):
        kept = choose_slots(rows, y)
        fm = FactorizationMachine(kept)
        place = {int(k): i for i, k in enumerate(kept)}
        fm.fit([np.array(sorted(place[s] for s in r if s in place), np.int64) for r in rows], y)
    else:
        fm = FactorizationMachine(np.zeros(0, np.int64))
        share = (y.sum() + 0.5) / (len(y) + 1)
        fm.bias = float(np.log(share / (1 - share)))
    yield pa.RecordBatch.from_pydict({"model": pa.array([pickle.dumps(fm)], pa.binary())})


def fit(docs: DataFrame, labels: DataFrame, max_rows: int = 12_000, label_col: str = "toxic") -> FactorizationMachine:
    """docs(doc_id, text), labels(doc_id, label_col); fits in one task on about `max_rows` rows at most."""
    teach = labels.where(F.col("doc_id").isNotNull() & F.col(label_col).isNotNull() & (crc_mod("doc_id", 4) != 2)).groupBy("doc_id").agg(F.max(label_col).alias("_y"))
    share = min(1.0, max_rows / max(1, teach.count()))
    picked = teach.where(F.pmod(F.xxhash64(F.col("doc_id"), F.lit(7)), F.lit(1 << 20)) < int(share * (1 << 20)))
    sample = docs.select(F.col("doc_id"), text_bytes().alias("_t")).join(F.broadcast(picked), "doc_id").select("_t", "_y")  # about max_rows rows; the scan stays parallel, only they move
    first = sample.repartition(1).mapInArrow(_train, "model binary").first()
    return pickle.loads(first.model) if first else FactorizationMachine(np.zeros(0, np.int64))


def scorer(fm: FactorizationMachine):
    def score(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        place = {int(k): i for i, k in enumerate(fm.kept)}
        seen: dict[bytes, tuple[int, ...]] = {}
        for texts in batches:
            row, at = [], []
            for i, t in enumerate(texts):
                found: set[int] = set()
                for w in set(t.as_py().lower().split()):
                    s = seen.get(w)
                    if s is None:
                        if len(seen) > CACHE:
                            seen.clear()
                        s = seen[w] = tuple(place[x] for x in word_slots(w) if x in place)
                    if s:
                        found.update(s)
                row += [i] * len(found)
                at += found
            m, _ = fm.margin(np.array(row, np.int64), np.array(at, np.int64), len(texts))
            yield pa.array(1 / (1 + np.exp(-np.clip(m, -30, 30))))

    return score


def score_column(fm: FactorizationMachine) -> Column:
    @F.arrow_udf("double")
    def toxic_score(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        yield from scorer(fm)(batches)

    return toxic_score(text_bytes())


def score_toxicity(docs: DataFrame, labels: DataFrame, threshold: float = 0.3, max_rows: int = 12_000) -> DataFrame:
    """`docs` with held_out, score, predicted."""
    fm = fit(docs, labels, max_rows)
    out = docs.withColumn("held_out", F.coalesce(crc_mod("doc_id", 4) == 2, F.lit(False))).withColumn("score", score_column(fm))
    return out.withColumn("predicted", (F.col("score") >= threshold).cast("int"))
