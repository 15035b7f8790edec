"""Every stage of the pipeline on the smallest given table, against plain versions written another way."""

import hashlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
import xxhash

import corpus_pipeline
from neargraph.llm import bpe, toxicity

FOLDER = "/root/testdata/sf0.001"
WHITE = " \t\n\x0b\x0c\r"


def split(text):
    return (text or "").encode("utf-8", "surrogatepass").split()


@pytest.fixture(scope="module")
def stages(spark):
    """(rows before, rows after) of each stage as (doc_id, text, source)."""
    at = spark.read.parquet(f"{FOLDER}/documents.parquet")
    out, rows = {}, lambda df: [(r.doc_id, r.text, r.source) for r in df.collect()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, at, FOLDER).cache()
        out[name] = rows(at), rows(after)
        at = after
    return out, at


def test_toxic_documents_go_and_no_others(spark, stages):
    before, after = stages[0]["toxicity"]
    model = toxicity.fit_on(spark.read.parquet(f"{FOLDER}/documents.parquet"), spark.read.parquet(f"{FOLDER}/labels.parquet"))
    scorer = toxicity.Scorer(model)
    assert Counter(after) == Counter(r for r in before if scorer.score([r[1]])[0] < toxicity.THRESHOLD)


def test_one_document_of_each_group_stays(stages):
    before, after = stages[0]["simhash_dedup"]

    def fingerprint(text):
        w = [x.lower() for x in split(text)]
        grams = [b" ".join(w[i : i + 4]) for i in range(len(w) - 3)] or ([b" ".join(w)] if w else [])
        h = [xxhash.xxh64_intdigest(g, 42) for g in grams]
        return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))

    v = np.array([fingerprint(t) for _, t, _ in before], np.uint64)
    close = np.bitwise_count(v[:, None] ^ v[None, :]) <= 4
    ids = np.array([i for i, _, _ in before])
    component = ids.copy()
    while True:
        new = np.where(close, component[None, :], ids.max() + 1).min(axis=1)
        if (new == component).all():
            break
        component = new
    assert Counter(after) == Counter(r for r, c in zip(before, component, strict=True) if r[0] == c)
    assert len(after) < len(before)


def test_repeated_passages_are_cut_at_all_but_the_first_place(stages):
    before, after = stages[0]["suffix_dedup"]
    texts = {i: t or "" for i, t, _ in before}
    places = defaultdict(list)
    for i, t in texts.items():
        w = split(t)
        for s in range(len(w) - 49):
            places[tuple(w[s : s + 50])].append((i, s))
    gone = defaultdict(set)
    for own in places.values():
        for i, s in sorted(own)[1:]:
            gone[i].update(range(s, s + 50))
    want = Counter()
    for i, t, source in before:
        if not gone[i]:
            want[i, t, source] += 1
            continue
        out, word, inside = [], -1, False
        for c in t:  # a word and the white space behind it stay or go together; what stands before the first word stays
            if c not in WHITE and not inside:
                word += 1
            inside = c not in WHITE
            if word < 0 or word not in gone[i]:
                out.append(c)
        if "".join(out).strip(WHITE):
            want[i, "".join(out), source] += 1
    assert Counter(after) == want


def test_sources_meet_their_targets(stages):
    before, after = stages[0]["source_mix"]
    size, weight = Counter(), {}
    for _, t, s in before:
        size[s] += len(split(t))
    for place, s in enumerate(sorted(size, key=lambda s: (s is None, s or ""))):
        weight[s] = (5, 2, 1)[place % 3]
    target, free = {}, set(size)
    left = 1.5 * sum(size.values())
    while free:
        level = left / sum(weight[s] for s in free)
        full = {s for s in free if level * weight[s] >= 2 * size[s]}
        if not full:
            target |= {s: level * weight[s] for s in free}
            break
        target |= {s: 2.0 * size[s] for s in full}
        left -= sum(2 * size[s] for s in full)
        free -= full
    mixed, of = Counter(), {i: t for i, t, _ in before}
    copies = Counter()
    for i, t, s in after:
        mixed[s] += len(split(t))
        copies[i] += len(split(t))
        assert of[i].startswith(t)
    assert all(abs(mixed[s] - target[s]) <= 1 for s in size)
    assert all(n <= 2 * len(split(of[i])) for i, n in copies.items())


def test_ids_are_those_of_the_reference_library(spark, stages):
    at = stages[1]
    ranks = bpe.load_ranks(P.path("byte_bpe_multi_50k.tiktoken"))
    plain = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    want = Counter()
    for r in at.select("doc_id", "text").collect():
        ids = plain.encode_ordinary(r.text)
        want[r.doc_id, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(r.text.encode()).hexdigest()] += 1
    got = corpus_pipeline.STAGES[-1][1](spark, at, FOLDER).collect()
    assert Counter((r.doc_id, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in got) == want


def test_the_stages_written_one_after_another_give_the_whole_run(spark, stages):
    """``run`` writes and rereads each stage; its result is that of the stages above."""
    got = Counter((r.doc_id, r.ids_sha256) for r in corpus_pipeline.run(spark, FOLDER).collect())
    assert got == Counter((r.doc_id, r.ids_sha256) for r in corpus_pipeline.STAGES[-1][1](spark, stages[1], FOLDER).collect())
