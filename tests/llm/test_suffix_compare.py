"""Suffix comparison: against brute force, on crowded starts, repeated ids and a very long text."""

from collections import Counter, defaultdict

import numpy as np
import pytest

from neargraph.llm import suffix_dedup


def brute(texts, length=50):
    """Spans of texts given as (doc, words)."""
    places = defaultdict(list)
    for doc, w in texts:
        for s in range(len(w) - length + 1):
            places[tuple(w[s : s + length])].append((doc, s))
    marks = defaultdict(list)
    for own in places.values():
        if len(own) > 1:
            first = min(own)
            for doc, s in own:
                marks[doc, (doc, s) > first].append((s, first[0]))
    out = Counter()
    for (doc, later), starts in marks.items():
        starts.sort()
        run = [starts[0]]
        for x in [*starts[1:], (10**9, 0)]:
            if x[0] - run[-1][0] > length:
                out[doc, run[0][0], run[-1][0] + length, later, min(f for _, f in run) if later else doc] += 1
                run = []
            run.append(x)
    return out


def spans(df):
    return Counter((r.doc_id, r.start_word, r.end_word, r.later, r.first_doc_id) for r in df.collect())


@pytest.fixture(scope="module")
def texts():
    """Passages of many lengths around the limit in other surroundings, near copies, copies, a passage in every text, a text that repeats itself."""
    rng = np.random.default_rng(4)
    draw = lambda n: [f"w{i}" for i in rng.integers(0, 3000, n)]
    common, shared = draw(55), [draw(n) for n in (49, 50, 51, 60, 75, 120)]
    out = []
    for i in range(60):
        w = draw(int(rng.integers(0, 60)))
        for _ in range(int(rng.integers(1, 3))):
            part = shared[int(rng.integers(len(shared)))]
            w += part[int(rng.integers(0, 3)) :] + draw(int(rng.integers(0, 4)))
        out.append((i, w + common + draw(int(rng.integers(0, 9)))))
    base = draw(400)
    for i in range(60, 70):
        w = list(base)
        for at in rng.integers(0, 400, 3):
            w[at] = "changed"
        out.append((i, w))
    out += [(70, base), (71, base), (72, ["a", "b"] * 100), (73, draw(30_000) + common + base)]
    return out


@pytest.mark.parametrize("crowd", [10_000, 12, 1])
def test_spans_equal_brute_force_however_crowded(spark, texts, crowd):
    df = spark.createDataFrame([(i, " ".join(w)) for i, w in texts], "doc_id long, text string").repartition(3)
    got = spans(suffix_dedup.repeated_spans(df, crowd=crowd))
    want = brute(texts)
    assert got == want and len(want) > 100


def test_window_classes_by_definition():
    rng = np.random.default_rng(5)
    length, key = 9, 4
    rows = [[f"{int(x)}" for x in rng.random(int(rng.integers(4, length + 1))) < 0.1] for _ in range(200)]
    back = [[f"{int(x)}" for x in rng.random(int(rng.integers(0, length - key + 1))) < 0.1] for _ in range(200)]
    place = rng.permutation(200)
    low = rng.integers(0, length - key + 1, 200)
    high = np.maximum(low, rng.integers(0, length - key + 1, 200))
    got = set(zip(*(x.tolist() for x in suffix_dedup.window_classes([" ".join(r).encode() for r in rows], [" ".join(b).encode() for b in back], place, low, high, length, key)[:3]), strict=True))
    want = set()
    for o in range(length - key + 1):
        groups = defaultdict(list)
        for i in range(200):
            if low[i] <= o <= high[i] and len(rows[i]) >= length - o and len(back[i]) >= o:
                groups[tuple(back[i][:o]), tuple(rows[i][: length - o])].append(i)
        for g in groups.values():
            if len(g) > 1:
                want |= {(i, o, min(g, key=place.__getitem__)) for i in g}
    assert got == want and len(want) > 30


def test_texts_that_share_an_id_are_texts_of_their_own(spark):
    passage = " ".join(f"p{i}" for i in range(70))
    long, short = passage + " " + " ".join(f"x{i}" for i in range(900)), "a few words before " + passage
    df = spark.createDataFrame([(1, long), (1, short), (1, short), (2, "other " + passage), (None, long)], "doc_id long, text string")
    got = suffix_dedup.spans_of_texts(df).collect()
    assert len(got) == 3 and sorted(r.doc_id for r in got) == [1, 1, 2] and sorted(r.later for r in got) == [False, True, True]
    assert {r.first_doc_id for r in got} == {1} and all(r.end_word - r.start_word == 70 for r in got)
    cut = sorted((r.doc_id or 9, len(r.text.split())) for r in suffix_dedup.cut_repeats(df).collect())
    assert cut in ([(1, 4), (1, 4), (1, 970), (2, 1), (9, 970)], [(1, 74), (1, 74), (1, 900), (2, 1), (9, 970)])
