"""Media columns: chroma audio fingerprints.

A recording (mono PCM) becomes pitch-class frames: power spectra of 1024 samples every 256, folded onto 12 classes, smoothed over
five frames and normalised. 16 box filters over up to 16 frames, read from an integral image, each give a log
ratio that is quantised to two Gray-coded bits; the 32 bits are one packed integer a frame. To align two recordings,
equal integers vote for a time offset; the offset with the most votes is kept if the bit error rate over the
overlap is small enough.

The queries are a stated set: they go in blocks of `QUERY_BLOCK` prints, each an inverted index of its integers that is sent to all tasks, and every recording
looks up its own integers there. A run of equal integers is one entry, and a pair of runs adds a trapezoid to the histogram of offsets, which four second
differences describe: long steady tones cost as much as short ones. Frames without any energy in their window (silence) cast no votes, but count
as frames. Pairs of runs are expanded `EXPAND` at a time. Recordings with equal prints form a class and are compared once.

The media of the given tables: each `embeddings` row is rendered as a melody of 64 notes (`melody`).

Nulls: null or too short media, and media that are silent throughout, have no voting frames: they match nothing and have a null class. Rows with null
id are fingerprinted. Ties between offsets: the smaller one. Repeated rows are of one class. Empty table: empty result. Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch

RATE, FRAME, HOP, SPAN, SLICE = 4096, 1024, 256, 16, 64
NOTE, LOWEST = 512, 220.0
SALTS, QUERY_BLOCK, EXPAND = 8, 1024, 1 << 20
_SMOOTH = np.array([0.25, 0.75, 1.0, 0.75, 0.25])
_GRAY = np.array([0, 1, 3, 2], np.uint32)


def _fold(rate: int) -> np.ndarray:
    """(bins, 12): which pitch class each spectral bin between 60 Hz and 2 kHz feeds."""
    f = np.fft.rfftfreq(FRAME, 1 / rate)
    out = np.zeros((len(f), 12))
    ok = (f >= 60) & (f <= min(2000, rate / 2))
    out[np.flatnonzero(ok), np.round(12 * np.log2(f[ok] / 440)).astype(int) % 12] = 1
    return out


def chroma(pcm: np.ndarray, rate: int = RATE, fold: np.ndarray | None = None) -> np.ndarray:
    """(frames, 12) normalised pitch-class energies."""
    n = (len(pcm) - FRAME) // HOP + 1
    if n < len(_SMOOTH):
        return np.zeros((0, 12))
    x = np.lib.stride_tricks.sliding_window_view(pcm.astype(np.float32), FRAME)[::HOP][:n] * np.hanning(FRAME).astype(np.float32)
    power = np.abs(np.fft.rfft(x)) ** 2 @ (_fold(rate) if fold is None else fold)
    k = n - len(_SMOOTH) + 1
    power = sum(w * power[i : i + k] for i, w in enumerate(_SMOOTH))
    norm = np.linalg.norm(power, axis=1, keepdims=True)
    return np.where(norm > 1e-3, power / np.maximum(norm, 1e-12), 0)


def filters() -> list[tuple[int, int, int, int]]:
    """(kind, first class, classes, frames) of the 16 filters, by rule: kinds alternate, boxes wander over classes and grow in time."""
    out = []
    for i in range(16):
        tall = 3 + (i * 5) % 9
        out.append((i % 5, (i * 7) % (13 - tall), tall, 4 + (i * 3) % 13))
    return out


def packed_fingerprint(frames: np.ndarray, cuts: tuple[float, float, float] = (-0.15, 0.0, 0.15)) -> np.ndarray:
    """One uint32 for each frame that has SPAN frames from it on."""
    n = len(frames) - SPAN + 1
    if n <= 0:
        return np.zeros(0, np.uint32)
    image = np.zeros((len(frames) + 1, 13))
    image[1:, 1:] = frames.cumsum(0).cumsum(1)
    t = np.arange(n)

    def box(t0: int, t1: int, y0: int, y1: int) -> np.ndarray:
        return image[t + t1, y1] - image[t + t0, y1] - image[t + t1, y0] + image[t + t0, y0]

    out = np.zeros(n, np.uint32)
    for kind, y, tall, wide in filters():
        mid, half, third = y + tall // 2, wide // 2, wide // 3
        whole = box(0, wide, y, y + tall)
        if kind == 0:  # upper against lower classes
            a = box(0, wide, mid, y + tall)
        elif kind == 1:  # later against earlier frames
            a = box(half, wide, y, y + tall)
        elif kind == 2:  # one diagonal of quarters against the other
            a = box(0, half, y, mid) + box(half, wide, mid, y + tall)
        elif kind == 3:  # the middle third in time against the rest
            a = box(third, wide - third, y, y + tall)
        else:  # the middle classes against the rest
            a = box(0, wide, y + tall // 3, y + tall - tall // 3)
        level = np.searchsorted(cuts, np.log((1 + a) / (1 + whole - a)))
        out = (out << np.uint32(2)) | _GRAY[level]
    return out


def runs(prints: np.ndarray, voiced: np.ndarray) -> list[dict]:
    """Runs of equal integers among the frames that may vote: value, first frame, frames."""
    edge = np.flatnonzero(np.r_[True, (prints[1:] != prints[:-1]) | (voiced[1:] != voiced[:-1])]) if len(prints) else np.zeros(0, np.int64)
    size = np.diff(np.r_[edge, len(prints)])
    return [{"value": int(v), "at": int(a), "n": int(n)} for v, a, n, ok in zip(prints[edge], edge, size, voiced[edge]) if ok]


def pcm16(value: bytes) -> np.ndarray:
    return np.frombuffer(value[: len(value) // 2 * 2], "<i2")


def melody(vector: list[float | None]) -> np.ndarray:
    """64 numbers as notes of 1/8 s: the value picks the pitch class."""
    v = np.nan_to_num(np.array([0.0 if x is None else x for x in vector], float))
    steps = np.arange(NOTE) / RATE
    waves = np.array([np.sin(2 * np.pi * LOWEST * 2 ** (c / 12) * steps) for c in range(12)]) * 12000
    return waves[np.clip(np.floor((v + 0.3) * 20), 0, 11).astype(int)].ravel().astype(np.int16)


RUNS = "array<struct<value: bigint, at: int, n: int>>"


def fingerprints(media: DataFrame, id_col: str, col: str, decode: Callable[..., np.ndarray] = pcm16, rate: int = RATE) -> DataFrame:
    """rec_id, print (binary, little-endian uint32 a frame), runs (of equal integers that may vote)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fold = _fold(rate)
        kind = pa.list_(pa.struct([("value", pa.int64()), ("at", pa.int32()), ("n", pa.int32())]))
        for batch in batches:
            for a in range(0, batch.num_rows, SLICE):  # decoded sound is large: few rows at a time
                part, prints, found = batch.slice(a, SLICE), [], []
                for v in part.column(1).to_pylist():
                    frames = np.zeros((0, 12)) if v is None else chroma(decode(v), rate, fold)
                    p = packed_fingerprint(frames)
                    sounding = np.r_[0, np.cumsum(frames.any(axis=1))]
                    prints.append(p.astype("<u4").tobytes())
                    found.append(runs(p, sounding[SPAN : SPAN + len(p)] > sounding[: len(p)]))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(prints, pa.binary()), pa.array(found, kind)], names=["rec_id", "print", "runs"])

    return media.select(F.col(id_col).cast("long").alias("rec_id"), F.col(col)).mapInArrow(run, f"rec_id long, print binary, runs {RUNS}")


def align(a: np.ndarray, b: np.ndarray, offset: int) -> tuple[int, float]:
    """(frames of overlap, bit error rate) of a[i] against b[i + offset]."""
    lo, hi = max(0, -offset), min(len(a), len(b) - offset)
    if hi <= lo:
        return 0, 1.0
    return hi - lo, float(np.bitwise_count(a[lo:hi] ^ b[lo + offset : hi + offset]).sum()) / (32 * (hi - lo))


class QueryBlock:
    """An inverted index of the runs of some queries: (key, print, runs)."""

    def __init__(self, rows: list[tuple[int, bytes, list]]):
        self.keys, self.prints = [r[0] for r in rows], [np.frombuffer(r[1], "<u4") for r in rows]
        flat = np.array([(i, x["value"], x["at"], x["n"]) for i, r in enumerate(rows) for x in r[2]], np.int64).reshape(-1, 4)
        self.owner, self.value, self.at, self.n = flat[np.argsort(flat[:, 1], kind="stable")].T

    def votes(self, value: np.ndarray, at: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Runs of a recording -> (query, offset, frames that are equal there) at the corners of the histograms, by query and offset."""
        lo, hi = np.searchsorted(self.value, value, "left"), np.searchsorted(self.value, value, "right")
        ends, key, bend, base = np.cumsum(hi - lo), np.zeros(0, np.int64), np.zeros(0, np.int64), 1 << 31
        for a in range(0, int(ends[-1]) if len(ends) else 0, EXPAND):
            g = np.arange(a, min(a + EXPAND, int(ends[-1])))
            r = np.searchsorted(ends, g, "right")
            q = lo[r] + g - (ends[r] - (hi - lo)[r])
            low, short, long_ = at[r] - self.at[q] - self.n[q], np.minimum(self.n[q], n[r]), np.maximum(self.n[q], n[r])
            corner = np.concatenate([low, low + short, low + long_, low + short + long_]) + base
            key, where = np.unique(np.r_[key, np.tile(self.owner[q] << 32, 4) | corner], return_inverse=True)
            one = np.ones(len(g), np.int64)
            bend = np.bincount(where, np.r_[bend, one, -one, -one, one], len(key)).astype(np.int64)
        offset = (key & 0xFFFFFFFF) - base
        # the differences of each query add up to nothing, so that running sums need no reset
        return key >> 32, offset, offset * np.cumsum(bend) - np.cumsum(bend * offset)

    def matches(self, rec_print: np.ndarray, rec_runs: list, least_votes: int, most_errors: float, least_frames: int) -> list[tuple]:
        runs_ = np.array([(x["value"], x["at"], x["n"]) for x in rec_runs], np.int64).reshape(-1, 3)
        owner, offset, n = self.votes(*runs_.T)
        some = n >= least_votes
        owner, offset, n = owner[some], offset[some], n[some]
        order = np.lexsort((offset, -n, owner))
        out = []
        for i in order[np.diff(owner[order], prepend=-1) > 0].tolist():
            frames, errors = align(self.prints[owner[i]], rec_print, int(offset[i]))
            if frames >= least_frames and errors <= most_errors:
                out.append((self.keys[owner[i]], int(offset[i]), int(n[i]), frames, errors))
        return out


def search(prints: DataFrame, queries: DataFrame, least_votes: int = 6, most_errors: float = 0.2, least_frames: int = 24) -> DataFrame:
    """(key, print, runs) twice -> q, r, offset, votes, frames, bit_errors for every pair that aligns; queries go in blocks."""
    schema = "q long, r long, offset int, votes long, frames int, bit_errors double"
    names, kinds = ["q", "r", "offset", "votes", "frames", "bit_errors"], (pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.float64())
    n, out = max(1, -(-queries.count() // QUERY_BLOCK)), None
    for k in range(n):
        own = queries.where(F.pmod(F.xxhash64("key"), F.lit(n)) == k).select("key", "print", "runs").orderBy("key").collect()  # about QUERY_BLOCK rows
        block = QueryBlock([tuple(r) for r in own])

        def run(batches: Iterator[pa.RecordBatch], block=block) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                rows = [(m[0], key, *m[1:]) for key, p, found in zip(*(c.to_pylist() for c in batch.columns))
                        for m in block.matches(np.frombuffer(p, "<u4"), found, least_votes, most_errors, least_frames)]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [[]] * 6, kinds)], names=names)

        part = prints.select("key", "print", "runs").mapInArrow(run, schema)
        out = part if out is None else out.unionByName(part)
    return out


def align_media(media: DataFrame, id_col: str, col: str, decode: Callable[..., np.ndarray] = pcm16, rate: int = RATE, every: int = 50, scratch: Scratch | None = None) -> DataFrame:
    """One row a recording: rec_id, class_id (smallest id with an equal print; null where nothing can match), members, is_query, n_links (a query's number of recordings
    that align with it, itself included) and links, the classes that align with this one (class_id, members, offset, votes, frames, bit_errors), on one row of each class that holds a query.

    Queries are the rows whose id is divisible by `every`. Pairs of recordings are the pairs of classes times membership; they are never listed.
    """
    scratch = scratch or Scratch(media.sparkSession, "audio")
    marked = scratch.save(fingerprints(media, id_col, col, decode, rate).withColumn("hash", F.xxhash64("print")), "prints")
    asks = F.coalesce(F.col("rec_id") % every == 0, F.lit(False))
    # rows of one class meet in one partial sum a task: the print itself, not its hash, is the key
    classes = marked.where(F.size("runs") > 0).groupBy("print").agg(F.min("rec_id").alias("class_id"), F.count(F.lit(1)).alias("members"), F.max(asks).alias("asked"), F.first("runs").alias("runs"), F.min("hash").alias("hash"))
    classes = scratch.save(classes.withColumn("key", F.monotonically_increasing_id()), "classes")  # written: the numbers are fixed
    pairs = scratch.save(search(classes, classes.where("asked")), "pairs")
    sizes = classes.select(F.col("key").alias("r"), F.col("class_id").alias("to"), "members")
    link = F.struct(F.col("to").alias("class_id"), "members", "offset", "votes", "frames", "bit_errors")
    per = pairs.join(sizes, "r").groupBy("q").agg(F.sum("members").alias("n_links"), F.array_sort(F.collect_list(link)).alias("links"))  # as many as there are other classes alike
    known = classes.select("key", "hash", "print", "class_id", "members").join(per, F.col("key") == F.col("q"), "left").select("hash", F.col("print").alias("p"), "class_id", "members", "n_links", "links")
    known = scratch.save(known, "known")
    rows = marked.select("rec_id", "print", "hash", asks.alias("is_query"))
    # a class may hold a third of all rows: its row is repeated under salts
    salted = known.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    rows = rows.withColumn("salt", F.pmod(F.xxhash64("rec_id"), F.lit(SALTS)).cast("int"))
    out = rows.join(salted, (rows.hash == salted.hash) & (rows.salt == salted.salt) & (rows.print == salted.p), "left")
    first = F.col("rec_id").eqNullSafe(F.col("class_id"))
    return out.select("rec_id", "class_id", "members", "is_query", F.when(F.col("is_query"), F.coalesce("n_links", F.lit(0).cast("long"))).alias("n_links"), F.when(first, F.col("links")).alias("links"))


def pairs_of(media: DataFrame) -> DataFrame:
    """The aligned pairs listed, for tests and small results: query_id, rec_id, offset, votes, frames, bit_errors."""
    links = media.where("links IS NOT NULL").select(F.col("class_id").alias("q"), F.explode("links").alias("l")).select("q", "l.*").dropDuplicates(["q", "class_id"])
    asked = media.where("is_query").select(F.col("class_id").alias("q"), F.col("rec_id").alias("query_id"))
    held = media.select("class_id", "rec_id")
    return asked.join(links, "q").join(held, "class_id").select("query_id", "rec_id", "offset", "votes", "frames", "bit_errors")
