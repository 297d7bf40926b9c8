"""Parsing one segment and reading it back: numpy and plain Python, no Spark.

Phrases are numbered from 1, phrase 0 is empty. A phrase is an earlier phrase plus one symbol; a segment that ends inside a
known phrase closes with a second codeword for it, so every algorithm sees only complete phrases.

Packed stores are arrays of 64-bit words:
- base: one word a codeword, parent << 21 | symbol;
- dense: three words, (start, far ancestor or -1, parent word);
- sparse: simple = 1 word; special = 5 (delimiter, parent word, depth * B + residue of the special depth, special parent,
  special ancestor); position = 2 (delimiter, start of the next phrase). Pointers are word offsets + 1, 0 is the root.
  Without `tag` the residue is 0 and special edges are taken greedily. A spaced store is a sparse one whose specials are the marks of `spaced_marks`.

Byte stores have the same fields in fewer bytes, see `ByteStore`.
"""

from __future__ import annotations

import math
import struct
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np

SYMBOL_BITS = 21
SYMBOL_MASK = (1 << SYMBOL_BITS) - 1
SPECIAL, POSITION = -1, -2  # the two reserved words
MAX_SYMBOLS = 1 << 22  # default capacity of a segment
MASK32 = 0xFFFFFFFF


def block_size(capacity: int) -> int:
    """B = ceil(log2 capacity), at least 1; any upper bound of the length will do."""
    return max(1, math.ceil(math.log2(capacity))) if capacity > 1 else 1


def to_symbols(text: str, alphabet: str = "codepoint") -> np.ndarray:
    if alphabet == "codepoint":
        return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    raw = np.frombuffer(text.encode("utf-8"), np.uint8)
    if alphabet == "byte":
        return raw.astype(np.int64)
    if alphabet == "bit":
        return np.unpackbits(raw).astype(np.int64)
    raise ValueError(f"unknown alphabet {alphabet!r}")


def from_symbols(symbols: np.ndarray, alphabet: str = "codepoint") -> str:
    if alphabet == "codepoint":
        return np.asarray(symbols, "<u4").tobytes().decode("utf-32-le", "surrogatepass")
    if alphabet == "bit":
        symbols = np.packbits(np.asarray(symbols, np.uint8))
    return np.asarray(symbols, np.uint8).tobytes().decode("utf-8")


@dataclass
class Parse:
    """Columns of a segment's codewords; entry 0 is the root."""

    n: int
    parent: np.ndarray
    symbol: np.ndarray
    depth: np.ndarray
    start: np.ndarray

    @property
    def m(self) -> int:
        return len(self.parent) - 1


class Trie:
    """The incremental parser: `push` takes symbols, codewords are final as soon as they appear, `close` ends the segment."""

    def __init__(self):
        self.child: dict[int, int] = {}
        self.parent, self.symbol, self.depth, self.node, self.n = [0], [0], [0], 0, 0

    def push(self, symbols) -> None:
        child, parent, symbol, depth, node = self.child, self.parent, self.symbol, self.depth, self.node
        find = child.get
        for c in symbols:
            key = node << SYMBOL_BITS | c
            nxt = find(key)
            if nxt is None:
                child[key] = len(parent)
                parent.append(node)
                symbol.append(c)
                depth.append(depth[node] + 1)
                node = 0
            else:
                node = nxt
        self.node = node
        self.n += len(symbols)

    def close(self) -> None:
        if self.node:
            for column in (self.parent, self.symbol, self.depth):
                column.append(column[self.node])
            self.node = 0

    def parse(self) -> Parse:
        depth = np.array(self.depth, np.int64)
        start = np.cumsum(depth) - depth + 1
        start[0] = 0
        return Parse(self.n, np.array(self.parent, np.int64), np.array(self.symbol, np.int64), depth, start)

    def dump(self) -> bytes:
        """The open segment in a few arrays; the child map follows from them."""
        return struct.pack("<qqq", self.n, self.node, len(self.parent)) + np.array([self.parent, self.symbol], "<i4").tobytes()

    @classmethod
    def load(cls, raw: bytes) -> Trie:
        t = cls()
        t.n, t.node, m = struct.unpack_from("<qqq", raw)
        parent, symbol = np.frombuffer(raw, "<i4", offset=24).reshape(2, m).tolist()
        t.parent, t.symbol = parent, symbol
        for i in range(1, m):
            t.depth.append(t.depth[parent[i]] + 1)
            t.child.setdefault(parent[i] << SYMBOL_BITS | symbol[i], i)
        return t


@dataclass
class Fields:
    """How the codewords of a segment that still grows are filled in, each when its phrase closes: far ancestor, coin, special chain, word offset and position codewords."""

    seq_id: int
    capacity: int
    alpha: float = 1 / 40
    grid: int | None = 40
    seed: int = 7
    words: int = 0
    mark: int = 0

    def of(self, t: Trie, first: int) -> Iterator[tuple]:
        """(phrase_no, parent_no, symbol, depth, start, jump_no, special, near_no, special_depth, chain_no, word_off, position_off) from phrase `first` on."""
        B, m = block_size(max(self.capacity, 1)), len(t.parent)
        coin = coins(self.seed, self.seq_id, m - 1, self.alpha).tolist()
        self.mark = self.mark or (self.grid or 0)
        start = 1 + sum(t.depth[1:first])
        for i in range(first, m):
            path, v = [], t.parent[i]  # ancestors from the parent up
            while v:
                path.append(v)
                v = t.parent[v]
            d = t.depth[i]
            reach = B << min(d % B, 55)
            jump = None if reach > d else path[reach - 1] if reach < d else 0
            above = [u for u in path if coin[u]]
            special_depth = len(above) + coin[i]
            far = B << min(special_depth % B, 55)
            chain = above[far - 1] if coin[i] and far < special_depth else None
            at = None
            if self.grid and self.words >= self.mark:
                at, self.words = self.words, self.words + 2
                self.mark = self.words // self.grid * self.grid + self.grid
            yield i, t.parent[i], t.symbol[i], d, start, jump, coin[i], above[0] if above else 0, special_depth, chain, self.words, at
            self.words += 5 if coin[i] else 1
            start += d


def base_parse(symbols: np.ndarray) -> Parse:
    t = Trie()
    t.push(symbols.tolist())
    t.close()
    return t.parse()


def ancestors(up: np.ndarray, node: np.ndarray, distance: np.ndarray) -> np.ndarray:
    """The ancestor of each node at a distance, by doubling the parent table."""
    node, distance = node.copy(), distance.copy()
    while distance.any():
        odd = (distance & 1).astype(bool)
        node[odd] = up[node[odd]]
        distance >>= 1
        up = up[up]
    return node


def tree_jumps(parent: np.ndarray, depth: np.ndarray, B: int) -> np.ndarray:
    """Each node's far ancestor 2^(depth mod B) * B above it, -1 where there is none."""
    out = np.full(len(parent), -1, np.int64)
    reach = np.left_shift(np.int64(B), np.minimum(depth % B, 55))
    has = np.flatnonzero((depth > 0) & (reach <= depth))
    out[has] = ancestors(parent, has, reach[has])
    return out


def mix32(x: int | np.ndarray) -> int | np.ndarray:
    """A 32-bit finaliser of the murmur kind."""
    x = x ^ (x >> 16)
    x = x * 0x85EBCA6B & MASK32
    x = x ^ (x >> 13)
    x = x * 0xC2B2AE35 & MASK32
    return x ^ (x >> 16)


def coins(seed: int, seq_id: int, m: int, alpha: float) -> np.ndarray:
    """For phrases 0..m: special or not, the same in every run, partitioning and language."""
    key = mix32((seed * 2654435761 + seq_id) & MASK32)
    no = np.arange(m + 1, dtype=np.uint64)
    h = mix32((no * np.uint64(2654435761) & np.uint64(MASK32)) ^ np.uint64(key))
    out = h < np.uint64(int(alpha * 2**32))
    out[0] = False
    return out


def nearest_marked(parent: np.ndarray, depth: np.ndarray, marked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(closest proper ancestor that is marked, 0 if none; number of marked nodes on the path to the root, itself included)."""
    near, count = np.zeros(len(parent), np.int64), np.zeros(len(parent), np.int64)
    order = np.argsort(depth, kind="stable")
    cuts = np.searchsorted(depth[order], np.arange(1, depth.max() + 2 if len(depth) else 1))
    for a, b in zip(cuts[:-1], cuts[1:]):
        v = order[a:b]
        p = parent[v]
        near[v] = np.where(marked[p], p, near[p])
        count[v] = count[p] + marked[v]
    return near, count


@dataclass
class SparseLayout:
    """Where each codeword of a sparse segment lies, and its extra fields, by phrase number (entry 0: root)."""

    special: np.ndarray
    near: np.ndarray
    special_depth: np.ndarray
    jump: np.ndarray
    offset: np.ndarray
    position_offset: np.ndarray
    position_phrase: np.ndarray
    n_words: int


def sparse_layout(p: Parse, special: np.ndarray, grid: int | None, B: int, widths: tuple[int, int, int] = (1, 5, 2)) -> SparseLayout:
    """`widths`: what a simple, a special and a position codeword take; `grid` and offsets are in the same unit."""
    one, five, two = widths
    near, count = nearest_marked(p.parent, p.depth, special)
    chain_up = np.where(special, near, 0)
    jump = np.full(len(special), -1, np.int64)
    reach = np.left_shift(np.int64(B), np.minimum(count % B, 55))
    has = np.flatnonzero(special & (reach < count))  # the root is no special node
    jump[has] = ancestors(chain_up, has, reach[has])
    width = np.where(special, five, one)
    width[0] = 0
    plain = np.cumsum(width) - width  # offsets without position codewords
    at, total = [], int(plain[-1] + width[-1]) if p.m else 0
    if grid:
        mark = grid
        while True:
            k = len(at)
            j = int(np.searchsorted(plain[1:], mark - two * k)) + 1  # first codeword that starts on the mark or after it
            if j > p.m:
                break
            at.append(j)
            mark = (int(plain[j]) + two * k + two) // grid * grid + grid  # marks jumped over are skipped
    at = np.array(at, np.int64)
    before = np.searchsorted(at, np.arange(p.m + 1), "right")
    offset = plain + two * before
    return SparseLayout(special, near, count, jump, offset, offset[at] - two, at, total + two * len(at))


def pack_base(p: Parse) -> np.ndarray:
    return p.parent[1:] << SYMBOL_BITS | p.symbol[1:]


def pack_dense(p: Parse, B: int) -> np.ndarray:
    return np.stack([p.start[1:], tree_jumps(p.parent, p.depth, B)[1:], pack_base(p)], 1).ravel()


def pack_sparse(p: Parse, s: SparseLayout, B: int, tag: bool = True) -> np.ndarray:
    out = np.zeros(s.n_words, np.int64)
    pointer = s.offset + 1
    pointer[0] = 0
    word = pointer[p.parent] << SYMBOL_BITS | p.symbol
    special = np.flatnonzero(s.special)
    simple = np.flatnonzero(~s.special)[1:]
    out[s.offset[simple]] = word[simple]
    o = s.offset[special]
    out[o], out[o + 1], out[o + 2] = SPECIAL, word[special], p.depth[special] * B + (s.special_depth[special] % B if tag else 0)
    out[o + 3] = pointer[s.near[special]]
    out[o + 4] = np.where(s.jump[special] >= 0, pointer[np.maximum(s.jump[special], 0)], 0)
    out[s.position_offset], out[s.position_offset + 1] = POSITION, p.start[s.position_phrase]
    return out


@dataclass
class Reads:
    """Codewords touched by one access."""

    locate: int = 0
    align: int = 0
    jump: int = 0
    parent: int = 0

    @property
    def total(self) -> int:
        return self.locate + self.align + self.jump + self.parent


class DenseStore:
    def __init__(self, words: memoryview | list[int], n: int, B: int):
        self.w, self.n, self.B, self.m = words, n, B, len(words) // 3  # codeword t: words 3t-3 (start), 3t-2 (far ancestor), 3t-1 (parent and symbol)

    def _depth(self, t: int) -> int:  # not stored: the next codeword's start tells it
        return (self.w[3 * t] if t < self.m else self.n + 1) - self.w[3 * t - 3]

    def _locate(self, pos: int, r: Reads) -> int:
        w, lo, hi, reads = self.w, 1, self.m, 1
        while lo < hi:
            mid = (lo + hi + 1) // 2
            reads += 1
            if w[3 * mid - 3] <= pos:
                lo = mid
            else:
                hi = mid - 1
        r.locate += reads
        return lo

    def _climb(self, t: int, goal: int, r: Reads) -> int:
        """From phrase t up to the ancestor of depth `goal`: parents to residue B-1, then far edges unless they overshoot."""
        w, B, d = self.w, self.B, self._depth(t)
        while d > goal and d % B != B - 1:
            t, d = w[3 * t - 1] >> SYMBOL_BITS, d - 1
            r.align += 1
        while d > goal:
            reach = B << (d % B)
            if d - reach >= goal and w[3 * t - 2] >= 0:
                t, d = w[3 * t - 2], d - reach
                r.jump += 1
            else:
                t, d = w[3 * t - 1] >> SYMBOL_BITS, d - 1
                r.parent += 1
        return t

    def symbol(self, pos: int) -> tuple[int, Reads]:
        r = Reads()
        t = self._locate(pos, r)
        return self.w[3 * self._climb(t, pos - self.w[3 * t - 3] + 1, r) - 1] & SYMBOL_MASK, r

    def substring(self, first: int, last: int) -> tuple[list[int], Reads]:
        """Backwards: the node of `last`, up to the root, then the codewords before."""
        w, r, out, left = self.w, Reads(), [], last - first + 1
        t = self._locate(last, r)
        node = self._climb(t, last - w[3 * t - 3] + 1, r)
        r.parent += left
        while left:
            if node == 0:
                t -= 1
                node = t
            x = w[3 * node - 1]
            out.append(x & SYMBOL_MASK)
            node = x >> SYMBOL_BITS
            left -= 1
        return out[::-1], r


class SparseStore:
    """Depths found by climbing are kept for later requests. With `memo` their reads are counted once, without it each time."""

    unit = 1  # what a word takes in offsets

    def __init__(self, words: memoryview | list[int], n: int, B: int, grid: int, tag: bool = True, memo: bool = False):
        self.w, self.n, self.B, self.grid, self.tag, self.memo = words, n, B, grid or 0, tag, memo
        self.known: dict[int, tuple[int, int]] = {-1: (0, 1)}  # offset -> depth, reads to find it

    def kind(self, o: int) -> int:
        return self.w[o]

    def next(self, o: int) -> int:
        k = self.w[o]
        return o + (1 if k >= 0 else 5 if k == SPECIAL else 2)

    def link(self, o: int) -> tuple[int, int]:
        """(parent offset or -1, symbol) of the codeword at o."""
        w = self.w[o]
        if w < 0:
            w = self.w[o + 1]
        return (w >> SYMBOL_BITS) - 1, w & SYMBOL_MASK

    def level(self, o: int) -> int:
        """depth * B + residue of the special codeword at o."""
        return self.w[o + 2]

    def edges(self, o: int) -> tuple[int, int]:
        """(special parent, special ancestor), -1 if none."""
        return self.w[o + 3] - 1, self.w[o + 4] - 1

    def start_after(self, o: int) -> int:
        return self.w[o + 1]

    def end(self) -> int:
        return len(self.w)

    def _depth(self, o: int, r: Reads) -> int:
        known, path = self.known, []
        while o not in known and self.kind(o) != SPECIAL:
            path.append(o)
            o = self.link(o)[0]
        if o not in known:
            known[o] = self.level(o) // self.B, 1
        d, reads = known[o]
        if self.memo:
            r.locate += 1 + len(path)
        for x in reversed(path):
            d, reads = d + 1, reads + 1
            known[x] = d, reads
        if not self.memo:
            r.locate += reads
        return d

    def _mark(self, j: int, r: Reads) -> int:
        """Offset of the position codeword of grid mark j; marks jumped over are passed on to the next delimiter."""
        o, end = j * self.grid, self.end()
        r.locate -= o - 1
        while o < end and self.kind(o) != POSITION:
            o += 1
        r.locate += o
        return o

    def _bracket(self, pos: int, r: Reads) -> tuple[int, int]:
        """(offset, start) of the last known phrase start at or before pos."""
        at, start = 0, 1
        if self.grid:
            lo, hi = 0, max(0, self.end() - 1) // self.grid
            while lo < hi:
                mid = (lo + hi + 1) // 2
                o = self._mark(mid, r)
                if o < self.end() and self.start_after(o) <= pos:
                    lo, at, start = mid, self.next(o), self.start_after(o)
                else:
                    hi = mid - 1
        return at, start

    def _locate(self, pos: int, r: Reads) -> tuple[int, int, int, list[tuple[int, int]]]:
        """(offset, start, depth) of the phrase that holds pos, and the codewords before it in its bracket."""
        o, start = self._bracket(pos, r)
        passed = []
        while True:
            if self.kind(o) == POSITION:
                o = self.next(o)
            d = self._depth(o, r)
            if pos < start + d:
                return o, start, d, passed
            passed.append((o, start))
            o, start = self.next(o), start + d

    def _climb(self, o: int, d: int, goal: int, r: Reads) -> int:
        while d > goal and self.kind(o) != SPECIAL:
            o, d = self.link(o)[0], d - 1
            r.align += 1
        B, aligned = self.B, not self.tag
        while d > goal and o >= 0 and self.kind(o) == SPECIAL:
            aligned = aligned or self.level(o) % B == B - 1
            near, far = self.edges(o)
            step = next((x for x in ((far, near) if aligned else (near,)) if x >= 0 and self.level(x) // B >= goal), None)
            if step is None:
                break
            o, d = step, self.level(step) // B
            r.jump += 1
        while d > goal:
            o, d = self.link(o)[0], d - 1
            r.parent += 1
        return o

    def symbol(self, pos: int) -> tuple[int, Reads]:
        r = Reads()
        o, start, d, _ = self._locate(pos, r)
        return self.link(self._climb(o, d, pos - start + 1, r))[1], r

    def substring(self, first: int, last: int) -> tuple[list[int], Reads]:
        r, out, left, link = Reads(), [], last - first + 1, self.link
        o, start, d, passed = self._locate(last, r)
        node = self._climb(o, d, last - start + 1, r)
        r.parent += left
        while left:
            if node < 0:
                if not passed:  # the bracket is used up: decode the one before it forwards
                    passed = self._locate(start - 1, r)
                    passed = [*passed[3], (passed[0], passed[1])]
                node, start = passed.pop()
            node, c = link(node)
            out.append(c)
            left -= 1
        return out[::-1], r


class ByteStore(SparseStore):
    """Sparse or base codewords in bytes: pointer (4) and symbol (1, its number in the segment's alphabet; 3 where that has over 254 symbols).
    A special codeword is delimiter, pointer, symbol, level, special parent, special ancestor, a position codeword delimiter and start; 4 bytes each.
    Pointers are byte offsets + 1. Integers are big-endian and below 2^31, so that no delimiter appears across two fields.
    """

    def __init__(self, raw: bytes, at: int, n: int, B: int, grid: int, tag: bool, alphabet: list[int], memo: bool = False):
        super().__init__([], n, B, grid, tag, memo)
        self.raw, self.at, self.alphabet, self.s = raw, at, alphabet, symbol_bytes(len(alphabet))

    def _int(self, o: int) -> int:
        return int.from_bytes(self.raw[self.at + o : self.at + o + 4])

    def kind(self, o: int) -> int:
        x = self._int(o)
        return x - (1 << 32) if x >= (1 << 32) - 2 else x

    def next(self, o: int) -> int:
        k = self.kind(o)
        return o + (8 if k == POSITION else 4 + self.s + (16 if k == SPECIAL else 0))

    def link(self, o: int) -> tuple[int, int]:
        o += 4 * (self.kind(o) == SPECIAL)
        return self._int(o) - 1, self.alphabet[int.from_bytes(self.raw[self.at + o + 4 : self.at + o + 4 + self.s])]

    def level(self, o: int) -> int:
        return self._int(o + 8 + self.s)

    def edges(self, o: int) -> tuple[int, int]:
        return self._int(o + 12 + self.s) - 1, self._int(o + 16 + self.s) - 1

    def start_after(self, o: int) -> int:
        return self._int(o + 4)

    def end(self) -> int:
        return len(self.raw) - self.at


def symbol_bytes(sigma: int) -> int:
    return 1 if sigma <= 254 else 3


def pack_bytes(symbols: np.ndarray, alpha: float = 0.0, grid: int | None = None, seed: int = 7, seq_id: int = 0, capacity: int | None = None, tag: bool = True) -> bytes:
    """A segment in bytes: header, alphabet, codewords; alpha 0 and no grid is the base parse. `grid` is in codewords of the smallest size."""
    p = base_parse(symbols)
    capacity = max(capacity or p.n, p.n, 1)
    B, alphabet = block_size(capacity), np.unique(p.symbol[1:])
    s = symbol_bytes(len(alphabet))
    widths, step = (4 + s, 20 + s, 8), (grid or 0) * (4 + s)
    lay = sparse_layout(p, coins(seed, seq_id, p.m, alpha), step, B, widths)
    out = np.zeros(lay.n_words, np.uint8)
    pointer = lay.offset + 1
    pointer[0] = 0

    def put(at: np.ndarray, value: np.ndarray, size: int = 4) -> None:
        for k in range(size):
            out[at + k] = (value >> (8 * (size - 1 - k))) & 255

    own = lay.offset[1:] + 4 * lay.special[1:]
    put(own, pointer[p.parent[1:]])
    put(own + 4, np.searchsorted(alphabet, p.symbol[1:]), s)
    special = np.flatnonzero(lay.special)
    o = lay.offset[special]
    put(o, np.full(len(o), (1 << 32) + SPECIAL))
    put(o + 8 + s, p.depth[special] * B + (lay.special_depth[special] % B if tag else 0))
    put(o + 12 + s, pointer[lay.near[special]])
    put(o + 16 + s, np.where(lay.jump[special] >= 0, pointer[np.maximum(lay.jump[special], 0)], 0))
    put(lay.position_offset, np.full(len(lay.position_offset), (1 << 32) + POSITION))
    put(lay.position_offset + 4, p.start[lay.position_phrase])
    return _BYTES.pack(step, p.n, capacity, len(alphabet), tag) + alphabet.astype("<u4").tobytes() + out.tobytes()


_BYTES = struct.Struct("<IqqI?")


def open_bytes(blob: bytes, memo: bool = False) -> ByteStore:
    grid, n, capacity, sigma, tag = _BYTES.unpack_from(blob)
    return ByteStore(blob, _BYTES.size + 4 * sigma, n, block_size(capacity), grid, tag, np.frombuffer(blob, "<u4", sigma, _BYTES.size).tolist(), memo)


def expand_bytes(blob: bytes) -> np.ndarray:
    """All symbols of a byte store, read codeword by codeword."""
    store = open_bytes(blob)
    at, words, o = {-1: 0}, [], 0
    while o < store.end():
        if store.kind(o) != POSITION:
            parent, symbol = store.link(o)
            at[o] = len(words) + 1
            words.append(at[parent] << SYMBOL_BITS | symbol)
        o = store.next(o)
    return expand_base(np.array(words, np.int64))


class RankSelect:
    """Preprocessed locating: a bitmap of phrase starts with the number of ones before each block; select is the list of starts."""

    BLOCK = 512

    def __init__(self, starts: np.ndarray, n: int):
        bits = np.zeros(-(-(n + 1) // self.BLOCK) * self.BLOCK, np.uint8)
        bits[starts] = 1
        self.words, self.starts = np.packbits(bits, bitorder="little").view(np.uint64), starts
        ones = np.bitwise_count(self.words).reshape(-1, self.BLOCK // 64).sum(1)
        self.before = np.concatenate([[0], np.cumsum(ones)[:-1]]).astype(np.int64)

    def locate(self, pos: np.ndarray) -> np.ndarray:
        """Number (from 1) of the phrase that holds each position: ones up to it, by one block count and at most 8 words."""
        word, block = pos // 64, pos // self.BLOCK
        out = self.before[block].copy()
        for k in range(self.BLOCK // 64):
            w = block * (self.BLOCK // 64) + k
            out += np.where(w < word, np.bitwise_count(self.words[w]), 0)
        rest = (pos % 64).astype(np.uint64)
        return out + np.bitwise_count(self.words[word] & (np.uint64(0xFFFFFFFFFFFFFFFF) >> (np.uint64(63) - rest)))


class LevelAncestor:
    """Preprocessed climbing: tables of the 1st, 2nd, 4th, ... ancestors, a step for each set bit of the distance."""

    def __init__(self, parent: np.ndarray, deepest: int):
        self.up = [parent]
        while 1 << len(self.up) <= deepest:
            self.up.append(self.up[-1][self.up[-1]])

    def climb(self, node: np.ndarray, distance: np.ndarray) -> np.ndarray:
        for k, up in enumerate(self.up):
            node = np.where(distance >> k & 1, up[node], node)
        return node


class BaseStore:
    """Unmodified codewords: all of them before the target must be read to find it."""

    def __init__(self, words: memoryview, n: int):
        self.w, self.n = words, n

    def _walk(self, pos: int, r: Reads) -> tuple[int, list[int], int]:
        depth, start = [0], 1
        for t, w in enumerate(self.w.tolist(), 1):
            depth.append(depth[w >> SYMBOL_BITS] + 1)
            r.locate += 1
            if pos < start + depth[t]:
                return t, depth, start
            start += depth[t]
        raise IndexError(pos)

    def symbol(self, pos: int) -> tuple[int, Reads]:
        r = Reads()
        t, depth, start = self._walk(pos, r)
        for _ in range(depth[t] - (pos - start + 1)):
            t = int(self.w[t - 1]) >> SYMBOL_BITS
            r.parent += 1
        return int(self.w[t - 1]) & SYMBOL_MASK, r

    def substring(self, first: int, last: int) -> tuple[list[int], Reads]:
        r = Reads()
        self._walk(last, r)
        return expand_base(np.asarray(self.w))[first - 1 : last].tolist(), r


def expand_base(words: np.ndarray) -> np.ndarray:
    """All symbols: each position of a phrase but the last points to the same place of its parent; pointers are doubled until they end at last positions."""
    m = len(words)
    parent = np.concatenate([[0], words >> SYMBOL_BITS]).astype(np.int32)
    depth, up = np.ones(m + 1, np.int64), parent.copy()
    depth[0] = 0
    while up.any():
        depth += depth[up]
        up = up[up]
    start = np.cumsum(depth) - depth
    last = start + depth - 1
    n = int(depth.sum())
    out = np.zeros(n, np.int64)
    out[last[1:]] = words & SYMBOL_MASK
    source = np.arange(n, dtype=np.int32) + np.repeat(start[parent] - start, depth).astype(np.int32)
    source[last[1:]] = last[1:]
    while True:
        further = source[source]
        if (further == source).all():
            return out[source]
        source = further


def base_words(scheme: str, words: np.ndarray) -> np.ndarray:
    """The base codewords inside a store of any scheme, pointers as ordinals."""
    if scheme == "base":
        return words
    if scheme == "dense":
        return words[2::3]
    special, position = np.flatnonzero(words == SPECIAL), np.flatnonzero(words == POSITION)
    head = np.ones(len(words) + 5, bool)  # the first words of codewords; delimiters are the only negative words
    for k in (1, 2, 3, 4):
        head[special + k] = False
    head[position] = head[position + 1] = False
    at = np.flatnonzero(head[: len(words)])
    links = np.where(words[at] == SPECIAL, words[np.minimum(at + 1, max(len(words) - 1, 0))], words[at]) if len(at) else words[:0]
    number = np.zeros(len(words) + 1, np.int64)
    number[at + 1] = np.arange(1, len(at) + 1)
    return number[links >> SYMBOL_BITS] << SYMBOL_BITS | links & SYMBOL_MASK


_HEAD = struct.Struct("<BB?xIqq")  # scheme, alphabet, tag, grid, n, capacity
SCHEMES, ALPHABETS = ("base", "dense", "sparse", "spaced"), ("codepoint", "byte", "bit")


def pack(symbols: np.ndarray, scheme: str = "dense", alphabet: str = "codepoint", alpha: float = 1 / 40, grid: int | None = 40,
         seed: int = 7, seq_id: int = 0, capacity: int | None = None, tag: bool = True, every: int = 6, height_rule: bool = True) -> bytes:
    """A segment as one blob: header and 64-bit words. `every` and `height_rule` are of the spaced scheme."""
    p = base_parse(symbols)
    capacity = max(capacity or p.n, p.n, 1)
    B = block_size(capacity)
    if scheme == "base":
        words = pack_base(p)
    elif scheme == "dense":
        words = pack_dense(p, B)
    elif scheme in ("sparse", "spaced"):
        special = coins(seed, seq_id, p.m, alpha) if scheme == "sparse" else spaced_marks(p, every, height_rule)
        words = pack_sparse(p, sparse_layout(p, special, grid, B), B, tag)
    else:
        raise ValueError(f"unknown scheme {scheme!r}")
    gridded = (grid or 0) if scheme in ("sparse", "spaced") else 0
    return _HEAD.pack(SCHEMES.index(scheme), ALPHABETS.index(alphabet), tag, gridded, p.n, capacity) + words.astype("<i8").tobytes()


def open_store(blob: bytes, requests: int = 1, memo: bool = False):
    """(store, alphabet). For many requests the words become a list once, which is faster to read; else only the words asked for are touched."""
    scheme, alphabet, tag, grid, n, capacity = _HEAD.unpack_from(blob)
    words, B = memoryview(blob)[_HEAD.size :].cast("q"), block_size(capacity)
    if 64 * requests > len(words) and scheme:
        words = words.tolist()
    store = BaseStore(words, n) if scheme == 0 else DenseStore(words, n, B) if scheme == 1 else SparseStore(words, n, B, grid, tag, memo)
    return store, ALPHABETS[alphabet]


def dense_store(parent: np.ndarray, symbol: np.ndarray, start: np.ndarray, jump: np.ndarray, n: int, B: int) -> DenseStore:
    """A store over codewords 1..m that came as columns, jump -1 if none."""
    return DenseStore(memoryview(np.ascontiguousarray(np.stack([start, jump, parent << SYMBOL_BITS | symbol], 1, dtype=np.int64).ravel())), n, B)


def sparse_params(eps: float, c: int = 40, n: int | None = None) -> tuple[float, int | None]:
    """(special share eps / c, a position every c / eps words). With n, a segment too short for its eps (eps < c log n / sqrt n) has neither: (0, None), the base parse."""
    if n is not None and eps < c * math.log2(max(n, 2)) / math.sqrt(max(n, 2)):
        return 0.0, None
    return eps / c, round(c / eps)


def expand(blob: bytes) -> str:
    scheme, alphabet, *_ = _HEAD.unpack_from(blob)
    words = np.frombuffer(blob, "<i8", offset=_HEAD.size)
    return from_symbols(expand_base(base_words(SCHEMES[scheme], words)), ALPHABETS[alphabet])


def spaced_marks(p: Parse, k: int, height_rule: bool) -> np.ndarray:
    """Nodes whose depth is a multiple of k; with the height rule only those of height k or more."""
    out = (p.depth % k == 0) & (p.depth > 0)
    if height_rule:
        height = np.zeros(p.m + 1, np.int64)
        for v in range(p.m, 0, -1):  # children come after their parents
            u = p.parent[v]
            height[u] = max(height[u], height[v] + 1)
        out &= height >= k
    return out


def route_path(t: int, r: int, B: int) -> tuple[int, int, int]:
    """(aligning steps, far edges, single edges) from node t down to node r of the path."""
    a = j = s = 0
    while t > r and t % B != B - 1:
        t, a = t - 1, a + 1
    while t > r:
        far = max(t - (B << (t % B)), 0)
        t, j, s = (far, j + 1, s) if far >= r else (t - 1, j, s + 1)
    return a, j, s
