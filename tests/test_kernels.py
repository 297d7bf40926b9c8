"""Parsing, stores, jump graphs: worked examples, properties and round trips."""

import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from trieaccess import kernels as K

HOW = [dict(scheme="base"), dict(scheme="dense"), dict(scheme="sparse", alpha=1 / 4, grid=16), dict(scheme="sparse", alpha=1 / 16, grid=64), dict(scheme="sparse", alpha=0.0, grid=40),
       dict(scheme="sparse", alpha=0.1, grid=None), dict(scheme="sparse", alpha=0.5, grid=3),
       dict(scheme="sparse", alpha=0.3, grid=16, tag=False), dict(scheme="spaced", every=3, height_rule=False, grid=16), dict(scheme="spaced", every=4, grid=40)]
LINE = "".join("0" + "1" * j for j in range(150))
TEXTS = ["a", "aaaaaaaaaaaa", "abababababa", "é😀\n" * 40, "\n\n\n", LINE, "".join(random.Random(2).choices("ab", k=3000)), "".join(random.Random(3).choices("acgt", k=2000))]


def test_worked_example():
    p = K.base_parse(K.to_symbols("abababababa"))
    assert list(zip(p.parent[1:], map(chr, p.symbol[1:]))) == [(0, "a"), (0, "b"), (1, "b"), (3, "a"), (2, "a"), (2, "a")]
    assert p.start[1:].tolist() == [1, 2, 3, 5, 8, 10] and p.depth[1:].tolist() == [1, 1, 2, 3, 2, 2]
    store, _ = K.open_store(K.pack(K.to_symbols("abababababa")))
    assert chr(store.symbol(6)[0]) == "b" and K.from_symbols(store.substring(4, 9)[0]) == "bababa"


@pytest.mark.parametrize("how", HOW, ids=str)
@pytest.mark.parametrize("alphabet", ["codepoint", "byte", "bit"])
def test_round_trip_and_access(how, alphabet):
    rng = random.Random(5)
    for text in TEXTS:
        s = K.to_symbols(text, alphabet)
        blob = K.pack(s, alphabet=alphabet, seq_id=9, **how)
        assert K.expand(blob) == text
        store, _ = K.open_store(blob)
        for _ in range(15):
            a = rng.randint(1, len(s))
            b = min(len(s), a + rng.randint(0, 90))
            assert store.symbol(a)[0] == s[a - 1] and store.substring(a, b)[0] == s[a - 1 : b].tolist()


@settings(max_examples=60, deadline=None)
@given(st.text(alphabet="ab", min_size=1, max_size=400), st.integers(0, 10))
def test_any_text(text, seed):
    s = K.to_symbols(text)
    for how in HOW:
        store, _ = K.open_store(K.pack(s, seed=seed, **how))
        assert [store.symbol(i)[0] for i in range(1, len(s) + 1)] == s.tolist()


@pytest.mark.parametrize("alpha,grid", [(0.0, None), (1 / 4, None), (1 / 8, 16), (0.0, 9)])
def test_byte_stores(alpha, grid):
    rng = random.Random(6)
    for text in [*TEXTS, "".join(map(chr, range(32, 700))) * 2]:
        s = K.to_symbols(text)
        blob = K.pack_bytes(s, alpha, grid, seq_id=3)
        assert (K.expand_bytes(blob) == s).all()
        store, p = K.open_bytes(blob), K.base_parse(s)
        lay = K.sparse_layout(p, K.coins(7, 3, p.m, alpha), None, K.block_size(max(p.n, 1)))
        m2, sigma = int(lay.special.sum()), len(set(text))
        if grid is None:
            assert len(blob) == K._BYTES.size + 4 * sigma + (4 + store.s) * p.m + 16 * m2
        for _ in range(15):
            a = rng.randint(1, len(s))
            b = min(len(s), a + rng.randint(0, 90))
            assert store.symbol(a)[0] == s[a - 1] and store.substring(a, b)[0] == s[a - 1 : b].tolist()


def test_memo_changes_counts_only():
    s = K.to_symbols(TEXTS[6])
    blob = K.pack(s, "sparse", alpha=1 / 16, grid=64)
    plain, memo = K.open_store(blob)[0], K.open_store(blob, memo=True)[0]
    cold = [K.open_store(blob)[0].symbol(i)[1].total for i in range(1, 300)]
    warm = [plain.symbol(i)[1].total for i in range(1, 300)]
    assert cold == warm and sum(memo.symbol(i)[1].total for i in range(1, 300)) < sum(warm)


def test_preprocessed_structures():
    for text in (TEXTS[6], LINE):
        p = K.base_parse(K.to_symbols(text))
        pos = np.arange(1, p.n + 1)
        at = K.RankSelect(p.start[1:], p.n).locate(pos)
        assert (at == np.searchsorted(p.start[1:], pos, "right")).all()
        node = K.LevelAncestor(p.parent, int(p.depth.max())).climb(at, p.depth[at] - (pos - p.start[at] + 1))
        assert (p.symbol[node] == K.to_symbols(text)).all()


@pytest.mark.parametrize("text", [TEXTS[6], LINE[:3000], "abababababa"])
def test_growing_words_equal_batch_words(text):
    """Codewords filled in as their phrases close, the state dumped and loaded in between, against the layouts made at the end."""
    s = K.to_symbols(text)
    t, f, rows = K.Trie(), K.Fields(5, len(s), 1 / 8, 16, 7), []
    for part in np.array_split(s, 9):
        done = len(t.parent)
        t.push(part.tolist())
        rows += f.of(t, done)
        t = K.Trie.load(t.dump())
    done = len(t.parent)
    t.close()
    rows += f.of(t, done)
    p = K.base_parse(s)
    B = K.block_size(len(s))
    lay, jump = K.sparse_layout(p, K.coins(7, 5, p.m, 1 / 8), 16, B), K.tree_jumps(p.parent, p.depth, B)
    none = lambda x: int(x) if x >= 0 else None
    want = [(i, p.parent[i], p.symbol[i], p.depth[i], p.start[i], none(jump[i]), lay.special[i], lay.near[i], lay.special_depth[i], none(lay.jump[i]), lay.offset[i]) for i in range(1, p.m + 1)]
    assert [r[:11] for r in rows] == want and [(r[0], r[11]) for r in rows if r[11] is not None] == list(zip(lay.position_phrase, lay.position_offset))


def test_parameters():
    assert K.sparse_params(1.0) == (1 / 40, 40) and K.sparse_params(1.0, n=100) == (0.0, None) and K.sparse_params(1.0, n=1 << 24) == (1 / 40, 40)


def test_phrases_are_distinct_but_the_closing_one():
    p = K.base_parse(K.to_symbols(TEXTS[6]))
    pairs = list(zip(p.parent[1:].tolist(), p.symbol[1:].tolist()))
    assert len(set(pairs[:-1])) == len(pairs) - 1 and (p.parent[1:] < np.arange(1, p.m + 1)).all()
    assert (p.start[1:] == 1 + np.cumsum(p.depth[1:]) - p.depth[1:]).all() and p.depth[1:].sum() == p.n


@pytest.mark.parametrize("n", [2, 3, 17, 64, 300])
def test_path_stretch_and_residue(n):
    B = K.block_size(n)
    for t in range(n):
        far = t - (B << (t % B))
        assert far < 0 or far % B == t % B
        assert all(sum(K.route_path(t, r, B)) <= 4 * B for r in range(t))


def test_tree_stretch_on_a_line():
    s = K.to_symbols(LINE)
    store, _ = K.open_store(K.pack(s))
    for a in range(1, len(s) + 1, 7):
        r = store.symbol(a)[1]
        assert r.align + r.jump + r.parent <= 4 * store.B


def test_word_identities_and_ratio():
    p = K.base_parse(K.to_symbols(TEXTS[6]))
    B = K.block_size(p.n)
    assert len(K.pack_dense(p, B)) == 3 * p.m
    for alpha, grid in ((0.25, 16), (1 / 40, 40), (0.0, 7)):
        l = K.sparse_layout(p, K.coins(7, 1, p.m, alpha), grid, B)
        m2, m3 = int(l.special.sum()), len(l.position_phrase)
        assert l.n_words == p.m - m2 + 5 * m2 + 2 * m3
        assert all(0 <= o - (o // grid) * grid <= 4 for o in l.position_offset)
        for v in np.flatnonzero(l.special):
            for u in (l.near[v], l.jump[v]):
                assert u <= 0 or (l.special[u] and p.depth[u] < p.depth[v])


def test_sparse_is_competitive():
    p = K.base_parse(K.to_symbols("".join(random.Random(8).choices("ab", k=60_000))))
    over = sum(K.sparse_layout(p, K.coins(s, 0, p.m, 1 / 40), 40, 16).n_words > 2 * p.m for s in range(30))
    assert over == 0


def test_prefix_decodes():
    p = K.base_parse(K.to_symbols(TEXTS[6]))
    words = K.pack_base(p)
    for m in (1, 10, p.m - 1):
        assert TEXTS[6].startswith(K.from_symbols(K.expand_base(words[:m])))


def test_spacing():
    s = "".join(format(j, f"0{i}b") for i in range(1, 13) for j in range(1 << i))
    p = K.base_parse(K.to_symbols(s))
    plain, height = K.spaced_marks(p, 6, False).sum() / p.m, K.spaced_marks(p, 6, True).sum() / p.m
    assert plain > 0.5 and height < 1 / 6


def test_stream_trie_equals_batch():
    t = K.Trie()
    for part in ("abab", "", "ababa", "ba"):
        t.push(K.to_symbols(part).tolist())
    t.close()
    assert t.parse().parent.tolist() == K.base_parse(K.to_symbols("abababababa")).parent.tolist()
