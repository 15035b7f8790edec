"""Kernels of the pipeline operators against plain definitions."""

import random

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st

from neargraph.llm import bpe, embedding_dedup, exact_topk, html_extract, importance_sampling, simhash_dedup, source_mix, suffix_dedup, token_counts, toxicity

PATH = P.path("byte_bpe_multi_50k.tiktoken")


@pytest.fixture(scope="module")
def own():
    return bpe.codec(PATH, P.PATTERN)


@pytest.fixture(scope="module")
def reference(own):
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=own.ranks, special_tokens={})


TEXT = st.text(alphabet=st.sampled_from(list("abehst'lé ñ\n\t 0123²½中漢😀\x1c\x85 _.,!<|>ßæ")), max_size=40)


@settings(max_examples=300, deadline=None)
@given(TEXT)
def test_bpe_equals_reference(own, reference, text):
    ids = own.encode(text)
    assert ids == reference.encode_ordinary(text)
    assert own.decode(ids) == text and own.decode_bytes(np.array(ids, np.int64)) == text.encode() if ids else text == ""


@settings(max_examples=200, deadline=None)
@given(st.binary(max_size=30))
def test_transducer_equals_plain_merging(own, piece):
    assert own.transducer.run(piece) == bpe.merge_by_rank(piece, own.ranks)
    assert own.transducer.run(piece) == bpe.merge_by_rank(piece, own.ranks)  # now by kept moves


@settings(max_examples=60, deadline=None)
@given(st.lists(st.lists(st.one_of(st.binary(min_size=1, max_size=12), st.text("aethnors é", min_size=1, max_size=9).map(str.encode)), min_size=1, max_size=12), min_size=1, max_size=3), st.sampled_from([1, 30, 400_000]))
def test_many_pieces_equal_plain_merging(own, batches, most):
    own.many.max_states = most  # small: the table of states starts anew between batches
    for batch in batches:
        tokens, counts = own.many.encode(batch)
        expected = [bpe.merge_by_rank(piece, own.ranks) for piece in batch]
        assert tokens.tolist() == [t for e in expected for t in e] and counts.tolist() == [len(e) for e in expected]


def test_long_pieces_and_small_memory(reference, own):
    small = bpe.Codec(PATH, P.PATTERN, max_pieces=50)
    small.transducer.max_states = small.many.max_states = 20
    for text in ("a" * 5000, "ab" * 2000, "the cat sat on the mat " * 50, "é" * 700, "<|endoftext|>"):
        assert own.encode(text) == small.encode(text) == reference.encode_ordinary(text)


@settings(max_examples=100, deadline=None)
@given(st.binary(max_size=20), st.integers(1, 4))
def test_utf8_machine(data, step):
    machine = bpe.Utf8Machine()
    got = "".join(machine.feed(data[i : i + step]) for i in range(0, len(data), step)) + machine.close()
    assert got == data.decode("utf-8", "replace")


def test_utf8_waits_for_whole_characters():
    machine = bpe.Utf8Machine()
    raw = "a😀é".encode()
    assert [machine.feed(raw[i : i + 1]) for i in range(len(raw))] == ["a", "", "", "", "😀", "", "é"]


@settings(max_examples=200, deadline=None)
@given(TEXT, st.data())
def test_edits_equal_counting_anew(own, text, data):
    counted = token_counts.CountedText(own, text)
    for _ in range(3):
        a = data.draw(st.integers(0, len(counted.text)))
        b = data.draw(st.integers(a, len(counted.text)))
        counted.edit(a, b, data.draw(st.sampled_from(["", "0", " x", "'s", "\n\n", "abc 12"])))
        anew = token_counts.CountedText(own, counted.text)
        assert counted.ends.tolist() == anew.ends.tolist()
        assert [x.tolist() for x in counted.tree.levels] == [x.tolist() for x in anew.tree.levels]
        assert counted.n_tokens == len(own.encode(counted.text))
        assert [counted.tree.prefix(i) for i in range(len(counted.tree) + 1)] == [int(v) for v in np.r_[0, np.cumsum(counted.tree.levels[0])]]


def test_edit_encodes_little(own):
    text = "word " * 2000 + "12345 " + "word " * 2000
    counted = token_counts.CountedText(own, text)
    (edit,) = token_counts.digit_edits(text)
    counted.edit(*edit)
    assert counted.encoded < 8 and counted.n_tokens == len(own.encode(counted.text))
    with pytest.raises(ValueError):
        counted.edit(5, 3, "")


def _pairs(v, budget):
    d = np.bitwise_count(v[:, None] ^ v[None, :])
    return {(i, j) for i, j in zip(*np.nonzero(np.triu(d <= budget, 1)), strict=True)}


def test_trie_join_finds_all_pairs():
    rng = np.random.default_rng(0)
    v = rng.integers(0, 2**63, 400, dtype=np.uint64)
    near = np.repeat(v[:40], 6)
    for _ in range(4):
        near ^= np.uint64(1) << rng.integers(0, 64, len(near)).astype(np.uint64)
    v = np.unique(np.concatenate([v, near]))
    for budget in (0, 1, 3, 4):
        got = set()
        for i, j in simhash_dedup.trie_pairs(np.zeros(len(v), np.int64), v, budget, leaf=4, chunk=500):
            got |= {(min(a, b), max(a, b)) for a, b in zip(i.tolist(), j.tolist(), strict=True)}
        assert got == _pairs(v, budget)
    a, b = simhash_dedup.link_forest(np.zeros(len(v), np.int64), v, np.arange(len(v)), 4)
    parent = list(range(len(v)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for x, y in _pairs(v, 4):
        parent[max(root(x), root(y))] = min(root(x), root(y))
    label = np.arange(len(v))
    label[a] = b
    assert label.tolist() == [root(i) for i in range(len(v))]


def test_simhash_by_definition():
    import xxhash

    def plain(text):
        words = text.encode().lower().split()
        grams = [b" ".join(words[i : i + 4]) for i in range(len(words) - 3)] or ([b" ".join(words)] if words else [])
        h = [xxhash.xxh64_intdigest(g, 42) for g in grams]
        return sum(1 << k for k in range(64) if 2 * sum(x >> k & 1 for x in h) > len(h)) if h else 0

    texts = ["", " \n", "a", "A b C", "a b c d", "a b c d e", "é B\tc  d e f " * 200, "x " * 300]
    hashes = [simhash_dedup.shingle_hashes(t) for t in texts]
    got = simhash_dedup.majority_bits(np.array(sum(hashes, []), np.uint64), np.array(list(map(len, hashes))))
    assert got.tolist() == [plain(t) for t in texts]


def test_minimisers_and_run_hashes():
    h = np.random.default_rng(0).integers(0, 2**63, 200, dtype=np.uint64)
    base = int(suffix_dedup._BASES[0])
    for length in (1, 2, 5, 24, 50):
        want = [sum(int(h[i + j]) * pow(base, length - 1 - j, 2**64) for j in range(length)) % 2**64 for i in range(len(h) - length + 1)]
        assert suffix_dedup.run_hashes(h, length, suffix_dedup._BASES[0]).tolist() == want
    assert suffix_dedup.minimisers(h, 27).tolist() == sorted({i + int(np.argmin(h[i : i + 27])) for i in range(174)})
    keys, at = suffix_dedup.anchors(h, 50, 8, 24)
    at, low, high = suffix_dedup.unpacked(at)
    for s in range(151):  # each window has a kept suffix of its own, not too far from its start
        own = (at - high <= s) & (s <= at - low)
        assert own.sum() == 1 and 0 <= at[own][0] - s <= 26


def test_cut_text():
    assert suffix_dedup.cut_text("a b  c\nd e", [(1, 3)]) == "a d e"
    assert suffix_dedup.cut_text(" é b", [(0, 2)]) == " "


def test_pivotal_rounding_keeps_words_and_expectations():
    rng = np.random.default_rng(0)
    sizes = rng.integers(1, 50, 40)
    mass = sizes * 0.37
    total = np.zeros(40)
    for seed in range(600):
        out, held = source_mix.settle(np.arange(40), sizes, mass, seed)
        assert abs(out.sum() - mass.sum()) < 1e-6
        free = (out > 0) & (out < sizes)
        assert free.sum() <= 1 and (held < 0 or not free.any() or free[held])
        total += out
    assert np.abs(total / 600 / sizes - 0.37).max() < 0.1


def test_topk_terms():
    rng = np.random.default_rng(1)
    w = rng.integers(-3, 4, (50, 12)) * (rng.random((50, 12)) < 0.4)
    lists = exact_topk.postings(w)
    scores = np.zeros(50, np.int64)
    exact_topk.accumulate(w[7], lists, scores)
    assert (scores == w @ w[7]).all()
    assert exact_topk._best(np.array([5, 3, 9, 1]), np.array([2, 7, 7, 2]), 3).tolist() == [1, 2, 3]


def test_range_search_is_complete_here():
    rng = np.random.default_rng(4)
    x = rng.normal(size=(500, 32))
    x[400:] = x[rng.integers(0, 20, 100)] + 0.1 * rng.normal(size=(100, 32))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    adj = embedding_dedup.robust_graph(x)
    width = max(map(len, adj))
    table = np.array([np.pad(a, (0, width - len(a)), constant_values=-1) for a in adj])
    q, c = embedding_dedup.range_search(x, table, np.arange(500), 0.93)
    s = x @ x.T >= 0.93
    np.fill_diagonal(s, False)
    want = set(zip(*np.nonzero(s), strict=True))
    got = set(zip(q.tolist(), c.tolist(), strict=True))
    assert len(want) > 100 and got <= want and len(got) >= 0.99 * len(want)


PAGE = """<html><head><title>t</title><style>p{}</style><script>var a="</p><article>";</script></head><body>
<header><h1>Site</h1></header><nav><ul><li><a href=x>Home</a></ul></nav><div class="ad">Buy this</div>
<article class="post-12"><h1>Title &amp; more</h1><p>First  <b>bold</b><br>line.<p>Second &#233;<form><input value=x>Sign up</form>
<ul><li>one<li>two</ul><aside>See also</aside><div class="comments"><p>I disagree with all of this very much indeed.</p></div></article><footer>&copy; 2024</footer>"""


def test_extraction():
    text = "Title & more\n\nFirst bold line.\n\nSecond é\n\none\n\ntwo"
    assert html_extract.extract(PAGE, []) == text
    path = html_extract.vote(PAGE)
    assert path == "html>body>article.post-#" and html_extract.extract(PAGE, [path]) == text
    assert html_extract.extract(PAGE, ["html>body>main"]) == text
    for odd in ("", None, "plain text", "<p>a<b>b", "<", "<a <b", "</p></div>", "<!-- x", "<div>" * 3000 + "deep", "<script>x", "&amp; &am &#xZZ; &#0;"):
        html_extract.extract(odd, ["html"])
    assert html_extract.extract("plain &lt; text", []) == "plain < text"
    assert [html_extract.host_of(u) for u in ("http://www.A.example:80/x", "https://u@m.b.org?q", None, "x")] == ["a.example", "b.org", "", ""]


def test_gradient():
    rng = np.random.default_rng(0)
    p = {k: v.astype(np.float64) for k, v in toxicity._initial(rng).items()}
    gates = rng.normal(size=(3, 7, 6 * toxicity.HIDDEN))
    mask = np.ones((3, 7), bool)
    mask[0, 5:] = False
    y = np.array([1.0, 0.0, 1.0])
    loss = lambda: float((np.logaddexp(0, z := toxicity._forward(p, lambda t: gates[:, t], mask)[0]) - y * z).sum())
    traced = toxicity._forward(p, lambda t: gates[:, t], mask, trace=True)
    grad, dgates = toxicity._backward(p, mask, traced, toxicity._sigmoid(traced[0]) - y)
    for name, table in [*((k, p[k]) for k in ("Uf", "Nb", "a", "o", "c")), ("gates", gates)]:
        at = np.unravel_index(rng.integers(table.size), table.shape)
        old = table[at]
        table[at] = old + 1e-3
        up = loss()
        table[at] = old - 1e-3
        down = loss()
        table[at] = old
        assert abs((up - down) / 2e-3 - (dgates if name == "gates" else grad[name])[at]) < 2e-3, name


def test_toxicity_learns_and_odd_texts():
    rng = random.Random(0)
    calm = [f"w{i}" for i in range(300)]
    texts, labels = [], []
    for i in range(300):
        words = [rng.choice(calm) for _ in range(rng.randint(5, 300))]
        if i % 4 == 0:
            for _ in range(2):
                words.insert(rng.randint(0, len(words)), rng.choice(["nasty", "vile", "rotten"]) + rng.choice(["", "ish", "ly"]))
        texts.append(" ".join(words)), labels.append(int(i % 4 == 0))
    model = toxicity.fit(texts[:200], labels[:200])
    scores = toxicity.Scorer(model).score(texts[200:])
    y = np.array(labels[200:])
    assert ((scores >= 0.3) == y).mean() > 0.95
    odd = toxicity.Scorer(model).score([None, "", "!!!", "w1"])
    assert (odd < 0.3).all()
    starts = [toxicity.window_starts(n) for n in (0, 1, 96, 97, 176, 1000)]
    assert starts[0] == [] and all(s[-1] + toxicity.WINDOW >= n and np.all(np.diff(s) <= toxicity.STRIDE) for s, n in zip(starts[1:], (1, 96, 97, 176, 1000), strict=True))
    assert toxicity.Scorer(toxicity.fit([], [])).score(["a"]).tolist() == [0.0]
    assert toxicity.Scorer(toxicity.fit(["a b", "c"], [1, 1])).score(["a", None]).tolist() == [1.0, 1.0]


def test_log_ratio_buckets():
    h = importance_sampling.Hasher(limit=3)
    assert len(h.buckets("a b c d e")) == 9 and len(h.buckets("A")) == 1 and not len(h.buckets(None)) and not len(h.buckets(" "))
    assert (h.buckets("a b") == importance_sampling.Hasher().buckets("A  B")).all()
