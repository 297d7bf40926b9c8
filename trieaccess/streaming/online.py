"""Online operation: codewords leave a stateful operator as soon as their phrases close, filled in for all three schemes; the open phrase stays in the state.

The state of a key is its open segment only: parents and symbols in two arrays, and a few counters. A segment is sealed when it reaches
`capacity` symbols, when a row with a null text ends its sequence, or when no row came for `idle_ms` (a new one then starts with an empty trie). The block size comes from `capacity`,
an upper bound of a segment's length, so that far ancestors are known while it grows.
Rows of a key are taken in the order of `order` within a micro-batch; rows behind the last one taken are late: they
cannot enter an append-only parse and come out with phrase_no -1, to be counted. Rows with a null key form a key of their own.
One writer appends; readers see what is committed.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from trieaccess import kernels as K

BASE = "seq_id long, seg_no int, phrase_no int, parent_no int, symbol int, depth int, start_pos long"
DENSE = f"{BASE}, jump_no int"
SPARSE = f"{DENSE}, special boolean, near_no int, special_depth int, chain_no int, word_off long, position_off long"
OUT = {"base": BASE, "dense": DENSE, "sparse": SPARSE}
CAPACITY = 1 << 16


class Segment:
    """The open segment of a key."""

    def __init__(self, key: int | None, capacity: int, alpha: float, grid: int | None, seed: int):
        self.key, self.how, self.no, self.last = key, (capacity, alpha, grid, seed), 0, None
        self._open()

    def _open(self) -> None:
        self.trie, self.fields, self.sent = K.Trie(), K.Fields(self.key or 0, *self.how), 1

    def dump(self) -> bytes:
        return pickle.dumps((self.key, self.how, self.no, self.last, self.trie.dump(), self.fields, self.sent))

    @classmethod
    def load(cls, raw: bytes) -> Segment:
        s = cls.__new__(cls)
        s.key, s.how, s.no, s.last, trie, s.fields, s.sent = pickle.loads(raw)
        s.trie = K.Trie.load(trie)
        return s

    def ready(self) -> list[tuple]:
        rows = [(self.key, self.no, *r) for r in self.fields.of(self.trie, self.sent)]
        self.sent = len(self.trie.parent)
        return rows

    def take(self, at, text: str | None) -> list[tuple]:
        if self.last is not None and at < self.last:
            return [(self.key, self.no, -1, 0, 0, 0, 0, None, False, 0, 0, None, 0, None)]
        self.last, out = at, []
        if text is None:
            return self.seal()
        symbols = K.to_symbols(text).tolist()
        while symbols:
            room = self.how[0] - self.trie.n
            self.trie.push(symbols[:room])
            symbols = symbols[room:]
            out += self.ready()
            if self.trie.n >= self.how[0]:
                out += self.seal()
        return out

    def seal(self) -> list[tuple]:
        if not self.trie.n:
            return []
        self.trie.close()
        out = self.ready()
        self.no += 1
        self._open()
        return out


def compress_stream(stream: DataFrame, key: str, order: str, text: str, scheme: str = "base", capacity: int = CAPACITY, alpha: float = 1 / 40, grid: int | None = 40, seed: int = 7,
                    idle_ms: int | None = None) -> DataFrame:
    """Append-mode stream of codewords with the fields of `scheme`."""
    names = [c.split()[0] for c in OUT[scheme].split(", ")]

    def run(k: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seg, out = Segment.load(state.get[0]) if state.exists else Segment(None if pd.isna(k[0]) else int(k[0]), capacity, alpha, grid, seed), []
        if state.hasTimedOut:
            out = seg.seal()
        else:
            rows = pd.concat(list(frames)).sort_values(order, kind="stable")
            for at, piece in zip(rows[order], rows[text]):
                out += seg.take(at, piece)
            if idle_ms:
                state.setTimeoutDuration(idle_ms)
        state.update((seg.dump(),))
        if out:
            got = pd.DataFrame([r[: len(names)] for r in out], columns=names)
            for c in set(names) & {"seq_id", "jump_no", "chain_no", "position_off"}:
                got[c] = got[c].astype("Int64")
            yield got

    rows = stream.select(F.col(key).cast("long").alias("_key"), order, text)
    timeout = GroupStateTimeout.ProcessingTimeTimeout if idle_ms else GroupStateTimeout.NoTimeout
    return rows.groupBy("_key").applyInPandasWithState(run, OUT[scheme], "segment binary", "append", timeout)


def replay(spark: SparkSession, df: DataFrame, build, out_dir: str, files: int = 1, by: str | None = None) -> DataFrame:
    """Runs `build(stream)` over the rows of `df`, written as `files` files taken one a micro-batch, into Parquet at out_dir; returns what was committed.
    With `by`, a column of 0..files-1, file i has its rows and comes i-th."""
    if by is None:
        df.repartition(files).write.mode("overwrite").parquet(f"{out_dir}/in")
    else:
        for i in range(files):
            df.where(F.col(by) == i).drop(by).coalesce(1).write.mode("append").parquet(f"{out_dir}/in")
        df = df.drop(by)
    stream = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(f"{out_dir}/in")
    result = build(stream)

    def sink(batch: DataFrame, no: int) -> None:  # one folder a micro-batch: a repeated one overwrites itself
        batch.write.mode("overwrite").parquet(f"{out_dir}/out/batch={no}")

    q = result.writeStream.outputMode("append").foreachBatch(sink)
    q = q.option("checkpointLocation", f"{out_dir}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    if q.exception():
        raise q.exception()
    return spark.read.schema(result.schema).parquet(f"{out_dir}/out/*")


def serve(requests: DataFrame, committed: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Positions of growing sequences, read from the dense codewords committed so far by the dense scheme's own search and climb: req_id, value (null where not yet encoded)."""
    from trieaccess.operators import access as A

    return A.access_codewords(committed.where("phrase_no > 0"), requests, capacity)
