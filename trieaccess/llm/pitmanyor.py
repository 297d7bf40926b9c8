"""LM scoring with a hierarchical Pitman-Yor model of words.

Restaurants: one for each context (the word before) seen in training, and one parent that they share.
The parent's base is uniform over the V training words and one unknown. Seats are sampled: a sweep re-seats every
(context, dish) by the Chinese-restaurant rule given the other tables, and the first table of each party sends a customer to the parent. `BURN`
sweeps are dropped, the predictive probabilities of the next `SAMPLES` are averaged. A context's size is its word's training count.

Plan, exchanges of packed columns, none of tokens one by one; the partition of a word is that of its hash:
1. documents become chunks of about `CHUNK` tokens over a chunk vocabulary, written once;
2. each chunk sends its words with training counts to their partitions; each partition ranks its words by count and sends sums and ranks back.
   (partition, rank) is a word's number from here on: small for frequent words, so that pairs pack into few bytes;
3. each chunk sends its (word, context) pairs with training counts to the partition of the word, where seats are sampled; sums, parties
   and tables go back to the chunks that asked. In a sweep a partition takes its own share of a context's
   tables, scaled to the context's size, for all of them, and its own share of the parent likewise; every kept sample ends with the parent seated on the tables just sampled;
4. tables of each context are summed in the partition of the context, and the exact sums go to the chunks that hold it: scores
   use exact sums only, so that the probabilities of each context add up to 1;
5. each chunk meets its answers and scores its documents. Only 1 + 2 totals a sample pass through the driver.
Customers beyond the 64th of a party are seated in runs that grow by an eighth, with the rate held within a run.
Words are told apart by 64-bit hashes. All pairs of one word meet in one task. A chunk sends one packed row to each partition it has words of.

Texts: A-Z lower-cased, words, then one end token, which is also the first word's context. Nulls: a null text is
empty (the end token only); a null doc_id teaches. Repeated rows count and are scored each. Without training documents
N = V = 0 and every probability is that of the unknown word. Empty table: empty result. Extra columns are ignored.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, crc_mod, text_bytes

CHUNK, BURN, SAMPLES, SEED = 1 << 21, 2, 3, 5
D_TOP, THETA_TOP, D_CTX, THETA_CTX = 0.7, 10.0, 0.6, 2000.0
EXACT = 64
CHUNKS = "chunk_id long, doc_ids array<long>, held array<boolean>, sizes array<int>, words binary, counts binary, tokens binary, n_train long"


def pack(*arrays: np.ndarray) -> bytes:
    """Integers are cut to the width they need and laid out in byte planes, which compress well."""
    import zstandard

    out = []
    for a in arrays:
        a = a.astype(np.min_scalar_type(int(a.max())) if len(a) and a.dtype.kind in "iu" else a.dtype)
        out.append((a.dtype.str, np.frombuffer(a.tobytes(), np.uint8).reshape(-1, a.dtype.itemsize).T.tobytes()))
    return zstandard.compress(pickle.dumps(out, 5), 1)


def unpack(blob: bytes) -> tuple[np.ndarray, ...]:
    import zstandard

    parts = pickle.loads(zstandard.decompress(blob))
    return tuple(np.frombuffer(np.frombuffer(raw, np.uint8).reshape(np.dtype(kind).itemsize, -1).T.tobytes(), kind) for kind, raw in parts)


class ChunkBuilder:
    def __init__(self, chunk_id: int):
        self.chunk_id, self.place, self.parts = chunk_id, {b"": 0}, []  # the empty word is the end token
        self.doc_ids, self.held, self.sizes, self.n = [], [], [], 0

    def add(self, doc_id: int | None, text: bytes, held: bool) -> None:
        words, place = text.lower().split(), self.place
        for w in words:
            if w not in place:
                place[w] = len(place)
        ids = np.fromiter(map(place.__getitem__, words), np.int64, len(words))
        self.parts += [ids, np.zeros(1, np.int64)]
        self.doc_ids.append(doc_id)
        self.held.append(held)
        self.sizes.append(len(words) + 1)
        self.n += len(words) + 1

    def row(self) -> list:
        from xxhash import xxh64_intdigest

        tokens = np.concatenate(self.parts)
        train = np.repeat(~np.array(self.held), self.sizes)
        order = np.argsort(-np.bincount(tokens, minlength=len(self.place)), kind="stable")
        rank = np.empty_like(order)
        rank[order] = np.arange(len(order))
        tokens = rank[tokens]
        words = np.array([xxh64_intdigest(w, SEED) for w in self.place], np.uint64)[order]
        counts = np.bincount(tokens[train], minlength=len(words))
        return [self.chunk_id, self.doc_ids, self.held, self.sizes, pack(words), pack(counts), pack(tokens), int(train.sum())]


_CHUNK_SCHEMA = pa.schema([("chunk_id", pa.int64()), ("doc_ids", pa.list_(pa.int64())), ("held", pa.list_(pa.bool_())), ("sizes", pa.list_(pa.int32())), ("words", pa.binary()),
                           ("counts", pa.binary()), ("tokens", pa.binary()), ("n_train", pa.int64())])


def _chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    base, k = TaskContext.get().partitionId() << 32, 0
    open_chunk = ChunkBuilder(base)

    def done(c):
        return pa.RecordBatch.from_arrays([pa.array([v], f.type) for v, f in zip(c.row(), _CHUNK_SCHEMA)], schema=_CHUNK_SCHEMA)

    for b in batches:
        for doc, text, held in zip(b.column(0), b.column(1), b.column(2)):
            open_chunk.add(doc.as_py(), text.as_py(), held.as_py())
            if open_chunk.n >= CHUNK:
                yield done(open_chunk)
                k += 1
                open_chunk = ChunkBuilder(base + k)
    if open_chunk.n:
        yield done(open_chunk)


def _slices(words: np.ndarray, parts: int) -> Iterator[tuple[int, np.ndarray]]:
    """(partition, its places in `words`), ascending; the same in each call."""
    part = (words % np.uint64(parts)).astype(np.int64)
    order = np.argsort(part, kind="stable")
    used, first = np.unique(part[order], return_index=True)
    yield from zip(used.tolist(), np.split(order, first[1:]))


def _blobs(rows: list[tuple[int, int, bytes]]) -> pa.RecordBatch:
    p, chunk, blob = list(zip(*rows)) or ((), (), ())
    return pa.RecordBatch.from_arrays([pa.array(p, pa.int32()), pa.array(chunk, pa.int64()), pa.array(blob, pa.binary())], names=["p", "chunk_id", "blob"])


def _word_counts(parts: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for chunk_id, w, c in zip(b.column(0), b.column(1), b.column(2)):
                (words,), (counts,) = unpack(w.as_py()), unpack(c.as_py())
                yield _blobs([(p, chunk_id.as_py(), pack(words[at], counts[at])) for p, at in _slices(words, parts)])

    return run


def _summed(key: tuple[pa.Scalar, ...], sent: pa.Table) -> pa.Table:
    """Words and counts of all chunks -> to each chunk, the sums and the ranks of its words; ties of rank go by hash."""
    ids, got = sent.column("chunk_id").to_pylist(), [unpack(x) for x in sent.column("blob").to_pylist()]
    words, of = np.unique(np.concatenate([g[0] for g in got]), return_inverse=True)
    sums = np.bincount(of, np.concatenate([g[1] for g in got]), len(words)).astype(np.int64)
    rank = np.empty(len(words), np.int64)
    rank[np.argsort(-sums, kind="stable")] = np.arange(len(words))
    cuts = np.cumsum([len(g[0]) for g in got])[:-1]
    back = [(key[0].as_py(), i, pack(x, r)) for i, x, r in zip(ids, np.split(sums[of], cuts), np.split(rank[of], cuts))]
    return pa.Table.from_batches([_blobs(back)])


def _context_tables(left: pa.Table, right: pa.Table) -> pa.Table:
    """Ranks of a partition's words by chunk, and tables of contexts by partition -> to each chunk, the tables of its words as contexts, a row a sample."""
    if not left.num_rows:
        return pa.Table.from_batches([_blobs([])])
    asked = [unpack(x)[1] for x in left.column("blob").to_pylist()]
    got = [unpack(x) for x in right.column("blob").to_pylist()]
    size = 1 + max(int(a.max()) for a in asked if len(a))
    none = np.zeros(0, np.int64)
    sums = [np.bincount(np.concatenate([none, *[g[0] for g in got]]).astype(np.int64), np.concatenate([none, *[g[1 + s] for g in got]]), size) for s in range(SAMPLES)]
    return pa.Table.from_batches([_blobs([(p, i, pack(*[x[a].astype(np.int64) for x in sums])) for p, i, a in zip(left.column("p").to_pylist(), left.column("chunk_id").to_pylist(), asked)])])


class Chunk:
    """A chunk's tokens and their contexts, the words before; a pair is word * width + context, both local."""

    def __init__(self, words: bytes, tokens: bytes, held: list[bool], sizes: list[int]):
        (self.words,), (self.tokens,) = unpack(words), unpack(tokens)
        self.tokens, self.sizes, self.held = self.tokens.astype(np.int64), np.array(sizes), np.array(held, bool)
        self.train = np.repeat(~self.held, self.sizes)
        self.width = len(self.words)
        end = self.tokens[-1]
        self.starts = np.concatenate([[0], np.cumsum(self.sizes)[:-1]])
        before = np.empty_like(self.tokens)
        before[1:], before[0] = self.tokens[:-1], end
        before[self.starts] = end
        self.pairs, self.pair_of = np.unique(self.tokens * self.width + before, return_inverse=True)

    def slices(self, parts: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """(partition, its local words, its pairs), both ascending; the same in each call."""
        part = (self.words % np.uint64(parts)).astype(np.int64)
        of_pair = part[self.pairs // self.width]
        by_word, by_pair = np.argsort(part, kind="stable"), np.argsort(of_pair, kind="stable")
        used = np.unique(part)
        w0, w1 = np.searchsorted(part[by_word], used, "left"), np.searchsorted(part[by_word], used, "right")
        p0, p1 = np.searchsorted(of_pair[by_pair], used, "left"), np.searchsorted(of_pair[by_pair], used, "right")
        for i, p in enumerate(used.tolist()):
            yield p, by_word[w0[i] : w1[i]], by_pair[p0[i] : p1[i]]


def _asked(parts: int):
    """A chunk and what `_summed` sent back -> its pairs to the partitions of the words: ranks and numbers of pairs of its words, numbers and sizes of contexts, pairs' contexts and counts."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        r = left.to_pylist()[0]
        chunk = Chunk(r["words"], r["tokens"], r["held"], r["sizes"])
        size, rank, sums = np.zeros(chunk.width, np.int64), np.zeros(chunk.width, np.int64), {x["p"]: x["blob"] for x in right.to_pylist()}
        for p, at in _slices(chunk.words, parts):
            size[at], rank[at] = unpack(sums[p])
        number = rank * parts + (chunk.words % np.uint64(parts)).astype(np.int64)
        counts = np.bincount(chunk.pair_of[chunk.train], minlength=len(chunk.pairs))
        rows = []
        for p, words, pairs in chunk.slices(parts):
            of_word = np.bincount(np.searchsorted(words, chunk.pairs[pairs] // chunk.width), minlength=len(words))
            ctx = chunk.pairs[pairs] % chunk.width
            contexts, first, local = np.unique(number[ctx], return_index=True, return_inverse=True)
            rows.append((p, r["chunk_id"], pack(rank[words], of_word, np.diff(contexts, prepend=0), size[ctx[first]], local, counts[pairs])))
        return pa.Table.from_batches([_blobs(rows)])

    return run


def seat(customers: np.ndarray, new: np.ndarray, discount: float, rng: np.random.Generator) -> np.ndarray:
    """Tables after seating each party one customer after another; `new` is (theta + d T) times the parent's probability."""
    order = np.argsort(-customers, kind="stable")
    c, a, t = customers[order], new[order], (customers[order] > 0).astype(np.int64)
    top = int(c[0]) if len(c) else 0
    for n in range(1, min(EXACT, top)):
        m = np.searchsorted(-c, -n)  # parties with more than n customers
        t[:m] += rng.random(m) < a[:m] / (n - discount * t[:m] + a[:m])
    n = EXACT
    while n < top:
        step = max(1, n // 8)
        m = np.searchsorted(-c, -n)
        k = np.minimum(step, c[:m] - n)
        t[:m] += rng.binomial(k, np.clip(a[:m] / (n + k / 2 - discount * t[:m] + a[:m]), 0, 1))
        n += step
    out = np.empty_like(t)
    out[order] = t
    return out


def sample_seats(party: np.ndarray, dish: np.ndarray, ctx: np.ndarray, n_dishes: int, size: np.ndarray, types: int, share: float, parts: int,
                 rng: np.random.Generator) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Gibbs sweeps over the restaurants of a partition -> SAMPLES times (tables of each pair, the parent's customers and tables of each dish).

    `size` has all customers of each context, `share` of all training tokens and one in `parts` of all words are here; sums over the other partitions are
    scaled up from these. A sweep seats the contexts given the parent, then the parent on their tables, so that each sample is consistent. With one partition nothing is scaled.
    """
    uniform, n_contexts = 1 / (types + 1), len(size)
    scale = size / np.maximum(1, np.bincount(ctx, party, n_contexts))
    tables, top_tables = (party > 0).astype(np.int64), (np.bincount(dish, party, n_dishes) > 0).astype(np.int64)
    kept = []
    for sweep in range(BURN + SAMPLES):
        top_party = np.bincount(dish, tables, n_dishes).astype(np.int64)
        new = (THETA_TOP + D_TOP * top_tables.sum() * parts) * uniform
        p_top = (top_party - D_TOP * top_tables + new) / (THETA_TOP + top_party.sum() / share)
        own = np.bincount(ctx, tables, n_contexts) * scale
        tables = seat(party, (THETA_CTX + D_CTX * own[ctx]) * p_top[dish], D_CTX, rng)
        top_party = np.bincount(dish, tables, n_dishes).astype(np.int64)
        top_tables = seat(top_party, np.full(n_dishes, new), D_TOP, rng)
        if sweep >= BURN:
            kept.append((tables, top_party, top_tables))
    return kept


def _restaurants(n_train: int, parts: int):
    """All requests of a partition -> answers to each chunk, one row of totals, and tables of contexts to the partitions of the contexts."""

    def run(key: tuple[pa.Scalar, ...], requests: pa.Table) -> pa.Table:
        p = key[0].as_py()
        ids, got = requests.column("chunk_id").to_pylist(), [unpack(x) for x in requests.column("blob").to_pylist()]
        order = np.argsort(ids)
        ids, got = [ids[i] for i in order], [got[i] for i in order]
        ranks = np.concatenate([np.repeat(g[0], g[1]) for g in got]).astype(np.int64)
        named = [np.cumsum(g[2].astype(np.int64)) for g in got]
        pairs, of_pair = np.unique(ranks << 40 | np.concatenate([c[g[4]] for c, g in zip(named, got)]), return_inverse=True)
        party = np.bincount(of_pair, np.concatenate([g[5] for g in got]), len(pairs)).astype(np.int64)
        dishes, dish = np.unique(pairs >> 40, return_inverse=True)
        contexts, ctx = np.unique(pairs & ((1 << 40) - 1), return_inverse=True)
        size = np.zeros(len(contexts))
        size[np.searchsorted(contexts, np.concatenate(named))] = np.concatenate([g[3] for g in got])
        count = np.bincount(dish, party, len(dishes)).astype(np.int64)
        types = int((count > 0).sum())
        share = max(1e-9, count.sum() / max(1, n_train))
        kept = sample_seats(party, dish, ctx, len(dishes), size, max(1, types) * parts, share, parts, np.random.default_rng([SEED, p]))
        totals = [types, *[int(x.sum()) for _, tp, tt in kept for x in (tp, tt)]]
        blobs = []
        for g, q in zip(got, np.split(of_pair, np.cumsum([len(g[4]) for g in got])[:-1])):
            w, many = np.searchsorted(dishes, g[0]), q[party[q] > 1]  # a party of one has one table
            blobs.append(pack(count[w], *[x[w] for _, tp, tt in kept for x in (tp, tt)], party[q], *[tb[many] for tb, _, _ in kept]))
        per = np.stack([np.bincount(ctx, tb, len(contexts)) for tb, _, _ in kept]).astype(np.int64)
        to, sums = [], []
        some = np.flatnonzero(per.any(0))
        for q, at in _slices(contexts[some].astype(np.uint64), parts):
            to.append(q)
            sums.append(pack(contexts[some[at]] // parts, *per[:, some[at]]))
        return pa.table({"p": pa.array([p] * (len(ids) + 1) + to, pa.int32()), "chunk_id": pa.array([*ids, None, *[None] * len(to)], pa.int64()),
                         "blob": pa.array([*blobs, None, *sums], pa.binary()), "totals": pa.array([*[None] * len(ids), totals, *[None] * len(to)], pa.list_(pa.int64()))})

    return run


def parent_probability(party: np.ndarray, tables: np.ndarray, all_party: float, all_tables: float, types: int) -> np.ndarray:
    return (party - D_TOP * tables + (THETA_TOP + D_TOP * all_tables) / (types + 1)) / (THETA_TOP + all_party)


def context_probability(party: np.ndarray, tables: np.ndarray, size: np.ndarray, all_tables: np.ndarray, parent: np.ndarray) -> np.ndarray:
    return (party - D_CTX * tables + (THETA_CTX + D_CTX * all_tables) * parent) / (THETA_CTX + size)


def _scores(n_train: int, parts: int, totals: list[int]):
    types = totals[0]
    per = np.array(totals[1:], float).reshape(SAMPLES, 2)

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        r = left.to_pylist()[0]
        chunk = Chunk(r["words"], r["tokens"], r["held"], r["sizes"])
        answers = {(x["p"], x["of_contexts"]): x["blob"] for x in right.to_pylist()}
        count = np.zeros(chunk.width)
        top = np.zeros((SAMPLES, 2, chunk.width))
        party, tables = np.zeros(len(chunk.pairs)), np.zeros((SAMPLES, len(chunk.pairs)))
        all_tables = np.zeros((SAMPLES, chunk.width))  # of each word as a context
        for p, words, pairs in chunk.slices(parts):
            got = unpack(answers[p, False])
            count[words] = got[0]
            party[pairs] = got[1 + 2 * SAMPLES]
            single, many = pairs[party[pairs] == 1], pairs[party[pairs] > 1]
            for s in range(SAMPLES):
                top[s, 0, words], top[s, 1, words] = got[1 + 2 * s], got[2 + 2 * s]
                tables[s, single], tables[s, many] = 1, got[2 + 2 * SAMPLES + s]
            all_tables[:, words] = np.stack(unpack(answers[p, True]))
        word, ctx = chunk.pairs // chunk.width, chunk.pairs % chunk.width
        p_pair = np.mean([context_probability(party, tables[s], count[ctx], all_tables[s, ctx], parent_probability(*top[s], *per[s], types)[word]) for s in range(SAMPLES)], axis=0)
        logs = np.log10(p_pair)[chunk.pair_of]
        base = np.log10((count + 0.1) / (n_train + 0.1 * (types + 1)))[chunk.tokens]
        known = (count > 0)[chunk.tokens].astype(np.int64)
        n = len(chunk.sizes)
        return pa.table({"doc_id": pa.array(r["doc_ids"], pa.int64()), "held_out": pa.array(chunk.held), "n_tokens": pa.array(chunk.sizes.astype(np.int64)), "n_known": pa.array(np.add.reduceat(known, chunk.starts)),
                         "train_tokens": pa.array(np.full(n, n_train, np.int64)), "base_score": pa.array(np.add.reduceat(base, chunk.starts)), "score": pa.array(np.add.reduceat(logs, chunk.starts))})

    return run


def score_texts(docs: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score (log10)."""
    spark = docs.sparkSession
    scratch = scratch or Scratch(spark, "lm")
    held = F.coalesce(crc_mod("doc_id", 10) == 0, F.lit(False))
    chunks = scratch.save(docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_bytes().alias("t"), held.alias("held")).mapInArrow(_chunks, CHUNKS), "chunks")
    sums = chunks.agg(F.coalesce(F.sum("n_train"), F.lit(0)).alias("n"), F.coalesce(F.sum(F.aggregate("sizes", F.lit(0).cast("long"), lambda a, x: a + x)), F.lit(0)).alias("all")).first()
    n_train = int(sums.n)
    parts = max(4, -(-int(sums["all"]) // CHUNK))
    sent = "p int, chunk_id long, blob binary"
    sums = chunks.select("chunk_id", "words", "counts").mapInArrow(_word_counts(parts), sent).groupBy("p").applyInArrow(_summed, sent)
    sums = scratch.save(sums, "sums")
    left = chunks.select("chunk_id", "held", "sizes", "words", "tokens").groupBy("chunk_id")
    asked = left.cogroup(sums.groupBy("chunk_id")).applyInArrow(_asked(parts), sent)
    answers = scratch.save(asked.groupBy("p").applyInArrow(_restaurants(n_train, parts), f"{sent}, totals array<long>"), "answers")
    totals = [r.v for r in answers.where("totals IS NOT NULL").select(F.posexplode("totals").alias("i", "x")).groupBy("i").agg(F.sum("x").alias("v")).orderBy("i").collect()]
    totals = totals or [0] * (1 + SAMPLES * 2)
    of_contexts = answers.where("chunk_id IS NULL AND totals IS NULL").select("p", "blob")
    context_tables = sums.groupBy("p").cogroup(of_contexts.groupBy("p")).applyInArrow(_context_tables, sent)
    left = chunks.select("chunk_id", "doc_ids", "held", "sizes", "words", "tokens").groupBy("chunk_id")
    right = answers.where("chunk_id IS NOT NULL").select("chunk_id", "p", "blob", F.lit(False).alias("of_contexts")).unionByName(context_tables.withColumn("of_contexts", F.lit(True)))
    return left.cogroup(right.groupBy("chunk_id")).applyInArrow(_scores(n_train, parts, totals),
                                                               "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")
