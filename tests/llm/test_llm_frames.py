"""The operators as frames: brute force on small tables, odd rows, empty tables and clashing columns."""

import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from pyspark.sql import functions as F

from neargraph.llm import bpe, embedding_dedup, exact_topk, html_extract, importance_sampling, simhash_dedup, source_mix, suffix_dedup, token_counts, toxicity

PATH = P.path("byte_bpe_multi_50k.tiktoken")
DOC = "doc_id long, text string, lang string, source string, n_chars long, score_ string, fp long, rep long, size long, taken long, component_id long, at string, t1 string"


def words(rng, n, vocabulary=4000):
    return [f"w{i}" for i in rng.integers(0, vocabulary, n)]


@pytest.fixture(scope="module")
def docs(spark):
    """Texts with copies, near copies, shared passages, nulls, ties and a long one; extra columns have names that operators use."""
    rng = np.random.default_rng(0)
    rows = []
    shared = words(rng, 60)
    for i in range(40):
        rows.append((i, " ".join(words(rng, int(rng.integers(1, 150))))))
    for i in range(40, 48):
        w = words(rng, 80)
        rows.append((i, " ".join([*w[:40], *shared, *w[40:]])))
    base = words(rng, 300)
    for i in range(48, 60):
        w = list(base)
        w[int(rng.integers(300))] = "changed"
        rows.append((i, " ".join(w)))
    for i in range(60, 66):
        rows.append((i, rows[41][1]))
    rows += [(66, None), (67, ""), (68, " \n\t"), (None, "text without an id"), (None, None), (69, "A b C"), (70, "a B c"), (71, " ".join(words(rng, 20000))), (72, "repeat me " * 200)]
    rows.append(rows[3])  # a repeated row
    return spark.createDataFrame([(i, t, "en", f"s{(i or 0) % 3}" if (i or 0) % 7 else None, len(t or ""), "x", 1, 2, 3, 4, 5, "y", "z") for i, t in rows], DOC).cache()


def test_importance_takes_exactly_k_of_rows_that_tie(spark, labels):
    rows = [(5, "the same")] * 30 + [(None, None)] * 20 + [(None, "x")] * 7
    frame = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    outcome = []
    for keep, k in ((0.5, 29), (0.1, 6), (1.0, 57), (0.0, 0)):
        got = [collected(importance_sampling.importance_sample(frame.repartition(parts), labels, keep=keep)) for parts in (2, 7)]
        assert [sum(r["selected"] for r in g) for g in got] == [k, k]
        outcome.append([Counter((r["doc_id"], r["n_grams"], r["selected"]) for r in g) for g in got])
    assert all(a == b for a, b in outcome)  # reruns agree


def test_importance_draws_in_proportion_to_the_ratios(spark):
    # raw texts half "a", half "b"; target texts three quarters "a": ratios 1.5 and 0.5, so "a" goes in three times as often
    n, k = 8000, 400
    docs = spark.createDataFrame([(i, "ab"[i % 2]) for i in range(n)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, 1) for i in range(n) if i % 2 == 0 or i % 6 == 1], "doc_id long, quality int")
    got = [r for r in collected(importance_sampling.importance_sample(docs, labels, keep=k / n)) if r["selected"]]
    assert len(got) == k
    share = sum(r["doc_id"] % 2 == 0 for r in got) / k
    assert abs(share - 0.74) < 0.07  # 3 / 4, a little less as the "a" run out; three standard deviations


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(i, 1, int(i % 9 == 0)) for i in range(60)] + [(None, 1, 1), (5000, 0, 1), (3, None, None)], "doc_id long, quality int, toxic int")


def collected(df):
    return [r.asDict() for r in df.collect()]


def test_simhash(spark, docs):
    got = collected(simhash_dedup.simhash_dedup(docs, block_rows=20))  # so small a block that segment nodes are split
    same = collected(simhash_dedup.simhash_dedup(docs))
    key = lambda r: (r["doc_id"] is None, r["doc_id"], r["fingerprint"], str(r["component_id"]))
    assert sorted(got, key=key) == sorted(same, key=key)
    source = [(r.doc_id, r.text) for r in docs.collect()]
    hashes = [simhash_dedup.shingle_hashes(t) for _, t in source]
    fps = simhash_dedup.majority_bits(np.array(sum(hashes, []), np.uint64), np.array([len(h) for h in hashes]))
    near = np.bitwise_count(fps[:, None] ^ fps[None, :]) <= 4
    reach = near.copy()
    for _ in range(len(fps)):
        new = reach @ near
        if (new == reach).all():
            break
        reach = new
    want = []
    for i, (doc, _) in enumerate(source):
        ids = [source[j][0] for j in np.flatnonzero(reach[i]) if source[j][0] is not None]
        want.append((doc, f"{int(fps[i]):016x}", min(ids) if ids else None))
    assert Counter((r["doc_id"], r["fingerprint"], r["component_id"]) for r in got) == Counter(want)
    assert simhash_dedup.simhash_dedup(docs.where("false")).count() == 0


def test_suffix(spark, docs):
    got = Counter((r["doc_id"], r["start_word"], r["end_word"], r["later"], r["first_doc_id"]) for r in collected(suffix_dedup.repeated_spans(docs)))
    texts = {(r.doc_id, r.text) for r in docs.collect() if r.doc_id is not None and r.text}
    places = defaultdict(list)
    for doc, text in texts:
        w = text.encode().split()
        for s in range(len(w) - 49):
            places[tuple(w[s : s + 50])].append((doc, s))
    marks = defaultdict(list)
    for own in places.values():
        if len(own) > 1:
            first = min(own)
            for doc, s in own:
                marks[doc, (doc, s) > first].append((s, first[0]))
    want = Counter()
    for (doc, later), starts in marks.items():
        starts.sort()
        run = [starts[0]]
        for x in [*starts[1:], (10**9, 0)]:
            if x[0] - run[-1][0] > 50:
                want[doc, run[0][0], run[-1][0] + 50, later, min(f for _, f in run) if later else doc] += 1
                run = []
            run.append(x)
    assert got == want and len(want) > 20
    cut = {r.doc_id: r.text for r in suffix_dedup.cut_repeats(docs).where("doc_id is not null").collect()}
    assert not {60, 61, 62, 63, 64, 65} & set(cut) and {66, 67, 68, 40} <= set(cut)
    assert cut[66] is None and len(cut[42].split()) == 80
    assert suffix_dedup.repeated_spans(docs.where("false")).count() == 0
    assert suffix_dedup.cut_repeats(docs.where("false")).columns == docs.columns


def test_mix(spark, docs):
    got = collected(source_mix.mix(docs, group_rows=4))
    again = collected(source_mix.mix(docs.repartition(3), group_rows=4))
    order = lambda rows: sorted(map(str, rows))
    assert order(got) == order(again) and len(got) == docs.count()
    sizes = defaultdict(int)
    for r in docs.collect():
        sizes[r.source] += len((r.text or "").encode().split())
    names = sorted(n for n in sizes if n is not None) + [None]
    weight = {n: (5, 2, 1)[i % 3] for i, n in enumerate(names)}
    target = {}
    left, rest = set(names), 1.5 * sum(sizes.values())
    while True:
        unit = rest / sum(weight[n] for n in left)
        over = {n for n in left if unit * weight[n] >= 2 * sizes[n]}
        if not over:
            break
        for n in over:
            target[n] = 2.0 * sizes[n]
            rest -= target[n]
        left -= over
    target |= {n: unit * weight[n] for n in left}
    by_size = {v: k for k, v in sizes.items()}
    taken = defaultdict(int)
    for r in got:
        n = by_size[r["source_size"]]
        assert abs(r["target"] - target[n]) < 1e-6 * max(1, target[n]) and 0 <= r["taken"] <= 2 * r["size"]
        taken[n] += r["taken"]
    assert all(abs(taken[n] - target[n]) <= 1 for n in names)
    whole = docs.where("doc_id between 0 and 60")
    mixed = source_mix.apply_mix(whole)
    assert mixed.columns == docs.columns
    want = {r["doc_id"]: r["taken"] for r in collected(source_mix.mix(whole)) if r["taken"] and r["doc_id"] != 3}
    count = Counter()
    for r in mixed.where("doc_id <> 3").collect():
        count[r.doc_id] += len(r.text.encode().split())
    assert count == Counter(want)
    assert source_mix.mix(docs.where("false")).count() == 0


def test_bpe_and_counts(spark, docs):
    import hashlib

    own = bpe.codec(PATH, P.PATTERN)
    reference = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=own.ranks, special_tokens={})
    want, counts = Counter(), Counter()
    for r in docs.collect():
        ids = reference.encode_ordinary(r.text or "")
        want[r.doc_id, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256((r.text or "").encode()).hexdigest()] += 1
        edited = token_counts.DIGITS.sub("0", r.text or "")
        counts[r.doc_id, len(ids), len(reference.encode_ordinary(edited)), len(token_counts.DIGITS.findall(r.text or ""))] += 1
    assert Counter((r["doc_id"], r["n_tokens"], r["ids_sha256"], r["decoded_sha256"]) for r in collected(bpe.bpe_digests(docs, PATH, P.PATTERN))) == want
    assert Counter((r["doc_id"], r["n_tokens"], r["n_tokens_edited"], r["n_edits"]) for r in collected(token_counts.edit_aware_counts(docs, PATH, P.PATTERN))) == counts
    assert bpe.bpe_encode(docs.where("doc_id = 69"), PATH, P.PATTERN).first().ids == reference.encode_ordinary("A b C")
    assert bpe.bpe_digests(docs.where("false"), PATH, P.PATTERN).count() == token_counts.edit_aware_counts(docs.where("false"), PATH, P.PATTERN).count() == 0


def test_toxicity_frame(spark, docs, labels):
    got = collected(toxicity.toxicity(docs, labels, per_class=30, rounds=1, epochs=1))
    assert len(got) == docs.count() and all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.3) for r in got)
    assert all(r["held_out"] == (r["doc_id"] is not None and zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) for r in got)
    assert {r["score"] for r in collected(toxicity.toxicity(docs, labels.where("false")))} == {0.0}
    assert toxicity.toxicity(docs.where("false"), labels).count() == 0


def test_toxicity_learns_from_its_own_rows_only(spark, docs, labels):
    """A label of a held-out row changes no score."""
    held = [i for i in range(60) if zlib.crc32(str(i).encode()) % 4 == 2]
    flipped = labels.withColumn("toxic", F.when(F.col("doc_id").isin(held), 1 - F.col("toxic")).otherwise(F.col("toxic")))
    a, b = (sorted((str(r["doc_id"]), r["score"]) for r in collected(toxicity.toxicity(docs, lab, per_class=20, rounds=1, epochs=1))) for lab in (labels, flipped))
    assert a == b


def test_importance(spark, docs, labels):
    got = collected(importance_sampling.importance_sample(docs, labels, keep=0.5))
    n = docs.count()
    assert len(got) == n and sum(r["selected"] for r in got) == -(-n // 2)
    low = min(r["gumbel_key"] for r in got if r["selected"])
    assert all(r["gumbel_key"] <= low for r in got if not r["selected"])
    h = importance_sampling.Hasher()
    raw, target = np.zeros(importance_sampling.BUCKETS), np.zeros(importance_sampling.BUCKETS)
    good = {r.doc_id for r in labels.collect() if r.quality == 1}
    for r in docs.collect():
        own = np.bincount(h.buckets(r.text), minlength=importance_sampling.BUCKETS)
        raw += own
        target += own * (r.doc_id in good and r.doc_id is not None)
    ratio = importance_sampling.log_ratios(raw, target)
    want = Counter((r.doc_id, round(float(ratio[h.buckets(r.text)].sum()), 6)) for r in docs.collect())
    assert Counter((r["doc_id"], round(r["log_ratio"], 6)) for r in got) == want
    assert importance_sampling.importance_sample(docs.where("false"), labels).count() == 0
    assert all(r["selected"] and r["log_ratio"] == 0 for r in collected(importance_sampling.importance_sample(docs, labels.where("false"))))
    keys = spark.createDataFrame([(float(v),) for v in [5, 1, 3, 3, 3, -2, 8]], "v double")
    assert [importance_sampling.kth_largest(keys, "v", k, bins=3, rounds=60) for k in range(1, 8)] == [8, 5, 3, 3, 3, 1, -2]


@pytest.fixture(scope="module")
def vectors(spark):
    rng = np.random.default_rng(5)
    x = rng.normal(size=(120, 8))
    x[60:90] = x[rng.integers(0, 6, 30)] + 0.12 * rng.normal(size=(30, 8))
    x[90:100] = x[0]
    rows = [(i, [float(np.float32(c)) for c in v], i % 2) for i, v in enumerate(x)]
    rows += [(200, None, 0), (201, [0.0] * 8, 0), (202, [float("nan")] * 8, 1), (203, [None, *[1.0] * 7], 1), (204, rows[0][1], None), (None, rows[0][1], 0), (205, [], 0), (206, [float("inf"), *[0.0] * 7], 0), (207, [3 * c for c in rows[0][1]], 0)]
    rows.append(rows[5])
    return spark.createDataFrame([(*r, 7, "q") for r in rows], "vec_id long, embedding array<float>, label int, rep long, links string").cache()


def test_embedding_dedup(spark, vectors):
    got = {}
    for r in collected(embedding_dedup.embedding_dedup(vectors, shard_rows=40, slice_rows=16)):
        got.setdefault(r["vec_id"], []).append((r["n_links"], r["component_id"], r["kept"]))
    rows = [r for r in vectors.collect()]
    ok = [r for r in rows if r.vec_id is not None and r.label is not None and r.embedding and all(c is not None and np.isfinite(c) for c in r.embedding) and any(r.embedding)]
    x = np.array([r.embedding for r in ok])
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    lab = np.array([r.label for r in ok])
    link = (x @ x.T >= 0.93) & (lab[:, None] == lab[None, :])
    reach = link.copy()
    for _ in range(8):
        reach = reach @ reach
    for i, r in enumerate(ok):
        c = min(ok[j].vec_id for j in np.flatnonzero(reach[i]))
        assert (int(link[i].sum()) - 1, c, c == r.vec_id) in got[r.vec_id], r.vec_id
    for i in (200, 201, 202, 203, 204, 205, 206):
        assert got[i] == [(0, i, True)]
    assert got[None] == [(0, None, False)] and sum(map(len, got.values())) == len(rows)
    assert embedding_dedup.embedding_dedup(vectors.where("false")).count() == 0


def test_embedding_dedup_exact_when_audit_is_short(spark):
    """Near (not equal) copies over many small shards: most linked pairs share none, so only the exact comparison counts them all."""
    rng = np.random.default_rng(5)
    x = np.r_[rng.normal(size=(1, 24)) + 0.25 * rng.normal(size=(500, 24)), rng.normal(size=(100, 24))].astype(np.float32)
    df = spark.createDataFrame([(i, int(i % 50 == 7), v.tolist()) for i, v in enumerate(x)], "vec_id long, label long, embedding array<float>").repartition(4)
    u = x.astype(np.float64) / np.linalg.norm(x.astype(np.float64), axis=1, keepdims=True)
    label = np.arange(600) % 50 == 7
    link = (u @ u.T >= 0.93) & (label[:, None] == label[None, :]) & ~np.eye(600, dtype=bool)
    got = collected(embedding_dedup.embedding_dedup(df, shard_rows=24, overlap=24))
    assert [r["n_links"] for r in sorted(got, key=lambda r: r["vec_id"])] == link.sum(axis=1).tolist()
    assert {r["audit_recall"] for r in got} == {1.0}


def test_exact_links(spark):
    """Blocks, slices and visits against brute force: dense and sparse cells, weights, two lengths, several labels."""
    from neargraph.runtime import Scratch

    rng = np.random.default_rng(6)
    centres = rng.normal(size=(12, 8))
    x = np.concatenate([c + 0.3 * rng.normal(size=(n, 8)) for c, n in zip(centres, [300, *[30] * 11], strict=True)])
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    rows = [(int(i % 5 == 0), i, i % 3 + 1, bytearray(v.astype("<f8").tobytes())) for i, v in enumerate(x)]
    short = np.array([[3.0, 4.0], [4.0, 3.0], [-1.0, 0.0]]) / np.array([[5.0], [5.0], [1.0]])
    rows += [(0, 1000 + i, 1, bytearray(v.astype("<f8").tobytes())) for i, v in enumerate(short)]
    classes = spark.createDataFrame(rows, "label long, rep long, mult long, vec binary").repartition(4)
    sample = classes.where("rep < 1000").select("label", "rep", "vec").toPandas()
    found = embedding_dedup.exact_links(classes, sample, len(rows), 0.93, Scratch(spark, "test"), block_rows=40).toPandas()
    label, mult = np.arange(len(x)) % 5 == 0, np.arange(len(x)) % 3 + 1
    link = (x @ x.T >= 0.93) & (label[:, None] == label[None, :]) & ~np.eye(len(x), dtype=bool)
    want = {i: int(n) for i, n in enumerate(link @ mult) if n} | {1000: 1, 1001: 1}
    assert {int(r): int(n) for r, n in found.groupby("rep")["links"].sum().items() if n} == want
    joined = {i: i for i in want}
    for _ in range(len(want)):
        low = {i: min([joined[i], *(joined[j] for j in np.flatnonzero(link[i]))]) if i < 1000 else 1000 for i in joined}
        if low == joined:
            break
        joined = low
    edges = found[found["rep"] != found["other"]]
    a, b = embedding_dedup._forest(edges["rep"].to_numpy(), edges["other"].to_numpy())
    assert {i: joined[i] for i in joined if joined[i] != i} == {int(i): int(j) for i, j in zip(a, b, strict=True)}


def test_topk(spark, vectors):
    table = vectors.where("vec_id is null or vec_id <> 5")
    rows = exact_topk.integer_weights(table)
    w = {r.vec_id: np.array(r.weights) for r in rows.collect() if len(r.weights) == 8}
    got = collected(exact_topk.topk(rows, rows.where("vec_id % 10 = 0"), 5, chunk=4))
    want = set()
    for q in w:
        if q % 10 == 0:
            best = sorted((-int(w[q] @ v), i) for i, v in {**w, 205: np.zeros(8, int)}.items() if i != q)[:5]
            want |= {(q, k, i, -s) for k, (s, i) in enumerate(best, 1)}
    assert {(r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in got} == want
    assert exact_topk.topk_self(vectors.where("false")).count() == 0
    assert {r["query_id"] for r in collected(exact_topk.topk_self(table))} == {0, 50, 100, 200, *()} - {200}


def test_pages(spark):
    page = "<html><body><nav><a>Home page of the site</a></nav><div class='c{}'><p>Story {} is told here at some length.<p>It ends.</div><div class='comments'>No, it does not end here, said a reader at great length indeed, again and again.</div></body></html>"
    rows = [(i, f"http://a.example/{i}", page.format(i, i), "x", 1) for i in range(6)] + [(10, None, None, "x", 1), (11, "odd", "", "x", 1), (12, "http://b.example", "only text", "x", 1), (None, "http://a.example/", page.format(7, 7), "x", 1)]
    df = spark.createDataFrame(rows + rows[:1], "page_id long, url string, html string, host string, n long")
    got = collected(html_extract.extract_pages(df))
    assert len(got) == 11
    text = {r["page_id"]: r["text"] for r in got}
    assert text[3] == "Story 3 is told here at some length.\n\nIt ends." and text[10] == text[11] == "" and text[12] == "only text"
    assert all(r["n_chars"] == len(r["text"]) for r in got)
    paths = {r["host"]: r["paths"] for r in collected(html_extract.host_paths(df))}
    assert paths["a.example"] == ["html>body>div.c#"]
    assert html_extract.extract_pages(df.where("false")).count() == 0


def test_pipeline_stages(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names, at = [], docs
    kept = {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        at = stage(spark, at, sf).cache()
        assert tuple(at.columns) == corpus_pipeline.COLUMNS
        names.append(name)
        kept[name] = {r.doc_id for r in at.select("doc_id").collect()}
    assert names == ["toxicity", "simhash_dedup", "suffix_dedup", "source_mix"]
    assert kept["simhash_dedup"] <= kept["toxicity"] and kept["suffix_dedup"] <= kept["simhash_dedup"] and kept["source_mix"] <= kept["suffix_dedup"]
    last = corpus_pipeline.STAGES[-1][1](spark, at, sf)
    assert last.count() == at.count() and "ids_sha256" in last.columns


def piped(spark, rows, sf):
    """(id, text, source) rows through the stages after the first; the rows after each."""
    import corpus_pipeline

    at = spark.createDataFrame([(i, t, "en", s, len(t)) for i, t, s in rows], "doc_id long, text string, lang string, source string, n_chars long")
    out = {}
    for name, stage in corpus_pipeline.STAGES[1:-1]:
        at = stage(spark, at.repartition(3), sf).cache()
        assert tuple(at.columns) == corpus_pipeline.COLUMNS
        out[name] = [(r.doc_id, r.text, r.source) for r in at.collect()]
    return out


def targets(rows):
    """Words that the mix takes of each of two sources: 1.5 times all, dealt 5 to 2, at most twice a source."""
    size = Counter()
    for _, t, s in rows:
        size[s] += len(t.split())
    whole = 1.5 * sum(size.values())
    a = min(2 * size["a"], whole * 5 / 7)
    b = min(2 * size["b"], whole - a)
    return {"a": min(2 * size["a"], whole - b), "b": b}


def test_pipeline_null_ids(spark, sf):
    """Documents without an id are deduplicated, cut and mixed like others."""
    rng = np.random.default_rng(8)
    text = lambda n: " ".join(words(rng, n, 100_000))
    plain = [(i, text(120), "ab"[i % 2]) for i in range(8)]
    alone, twice, passage = text(120), text(120), text(60)
    start, end = text(90), text(90)
    cut = [(20, f"{passage} {text(100)}", "a"), (None, f"{start} {passage} {end}", "b")]
    rows = [*plain, (None, alone, "a"), (None, twice, "b"), (None, twice, "b"), (None, plain[3][1], "b"), *cut]
    out = piped(spark, rows, sf)
    want = [*plain, (None, alone, "a"), (None, twice, "b"), *cut]
    assert Counter(out["simhash_dedup"]) == Counter(want)
    want[-1] = (None, f"{start} {end}", "b")
    assert Counter(out["suffix_dedup"]) == Counter(want)
    mixed = Counter()
    for _, t, s in out["source_mix"]:
        mixed[s] += len(t.split())
    assert all(abs(mixed[s] - n) <= 1 for s, n in targets(want).items())
    assert {t for i, t, _ in out["source_mix"] if i is None}


def test_pipeline_repeated_ids(spark, sf):
    """One row of exact copies stays though they share an id; different texts under one id are documents of their own."""
    rng = np.random.default_rng(9)
    text = lambda n: " ".join(words(rng, n, 100_000))
    plain = [(i, text(120), "ab"[i % 2]) for i in range(8)]
    passage, start, end, other = text(60), text(90), text(90), text(200)
    rows = [*plain, *plain[2:5], plain[2], (30, f"{passage} {text(100)}", "a"), (31, f"{start} {passage} {end}", "b"), (31, other, "a")]
    out = piped(spark, rows, sf)
    want = [*plain, *rows[-3:]]
    assert Counter(out["simhash_dedup"]) == Counter(want)
    want[-2] = (31, f"{start} {end}", "b")
    assert Counter(out["suffix_dedup"]) == Counter(want)
    mixed = Counter()
    for _, t, s in out["source_mix"]:
        mixed[s] += len(t.split())
    assert all(abs(mixed[s] - n) <= 1 for s, n in targets(want).items())
