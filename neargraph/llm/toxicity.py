"""Toxicity by a bidirectional gated recurrent network with attention pooling, trained and run in numpy.

Input of a word: an embedding of its hash beside the mean of the embeddings of its hashed character n-grams. One column of both
tables is counted, not trained: how much more often toxic texts of the training sample hold the word or n-gram (of n-grams the
greatest); the other columns start at random and are trained with the network. Texts are cut into overlapping windows; two gated
recurrent layers run over a window, one each way; attention pools their states; a text scores as its worst window does.
Everything that depends on a word alone is computed once for each distinct word of a worker.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from neargraph.llm.kernels import documents_of, pieces, record, resident, tidy
from neargraph.runtime import prepare

WINDOW, STRIDE = 96, 80
HIDDEN, WORD_DIM, CHAR_DIM = 8, 4, 4
CHAR_BITS = 16
WORD_BUCKETS, CHAR_BUCKETS = 1 << 16, 1 << CHAR_BITS
_BYTE, _SPREAD = np.uint64(0x100000001B3), np.uint64(0x9E3779B97F4A7C15)
#: Most labelled texts of each class that a fit reads, in the order of a hash of the id.
SAMPLE_PER_CLASS = 1000
THRESHOLD = 0.3
#: Folds of the training texts, so that no text meets odds it has itself made.
FOLDS = 5
#: Steps of descent in each round, however few texts there are.
LEAST_STEPS = 60

_WORD = re.compile(r"\w+", re.UNICODE)


def words_of(text: str | None) -> list[str]:
    return _WORD.findall(text.lower()) if text else []


def word_bucket(word: str) -> int:
    return zlib.crc32(word.encode("utf-8", "surrogatepass")) % WORD_BUCKETS


def _buckets(words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word buckets; buckets of all words' runs of 3 to 6 bytes, ends marked, in a row; how many of them belong to each word."""
    raw = [word.encode("utf-8", "surrogatepass") for word in words]
    own = np.fromiter(map(zlib.crc32, raw), np.int64, len(raw)) % WORD_BUCKETS
    if not words:
        return own.astype(np.int32), np.zeros(0, np.int32), np.zeros(0, np.int32)
    data = np.frombuffer(b"".join([b"<%b>" % r for r in raw]), np.uint8).astype(np.uint64)
    size = np.fromiter(map(len, raw), np.int64, len(raw)) + 2
    begin = np.cumsum(size) - size
    of, place = np.repeat(np.arange(len(raw)), size), np.arange(len(data)) - np.repeat(begin, size)
    count = np.maximum(size[:, None] - np.arange(2, 6), 0)  # runs of 3, 4, 5 and 6 bytes
    total = count.sum(axis=1)
    first = (np.cumsum(total) - total)[:, None] + np.cumsum(count, axis=1) - count
    flat = np.empty(int(total.sum()), np.int32)
    with np.errstate(over="ignore"):
        run = (data[:-1] * _BYTE + data[1:]) if len(data) > 1 else data[:0]
        for i, n in enumerate((3, 4, 5, 6)):
            run = run[: len(data) - n + 1] * _BYTE + data[n - 1 :]
            at = np.flatnonzero(place[: len(run)] + n <= size[of[: len(run)]])
            mixed = (run[at] ^ (run[at] >> np.uint64(29))) * _SPREAD
            flat[first[of[at], i] + place[at]] = (mixed >> np.uint64(64 - CHAR_BITS)).astype(np.int32)
    return own.astype(np.int32), flat, total.astype(np.int32)


def char_grams(word: str) -> list[int]:
    """Buckets of a word's runs of bytes."""
    return _buckets([word])[1].tolist()


def window_starts(n: int) -> list[int]:
    """Starts of the overlapping windows of ``n`` words; the last one ends at the last word or beyond it."""
    return [0, *range(STRIDE, max(STRIDE, n - (WINDOW - STRIDE)), STRIDE)] if n else []


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * np.tanh(0.5 * x) + 0.5


@dataclass
class Model:
    """Parameters (float32). ``shift`` and ``scale`` map a window's logit to the reported score."""

    word: np.ndarray
    char: np.ndarray
    p: dict[str, np.ndarray] = field(default_factory=dict)
    shift: float = 0.0
    scale: float = 1.0
    base: float = 0.0

    def inputs(self, words: list[str]) -> np.ndarray:
        """One input row for each word."""
        return self.rows(*_buckets(words))

    def rows(self, own: np.ndarray, flat: np.ndarray, counts: np.ndarray, block: int = 20_000) -> np.ndarray:
        out = np.empty((len(own), WORD_DIM + CHAR_DIM), np.float32)
        ends = np.cumsum(counts, dtype=np.int64)
        for at in range(0, len(own), block):
            to = min(len(own), at + block)
            base = ends[at] - counts[at]
            rows, first = self.char[flat[base : ends[to - 1]]], ends[at:to] - counts[at:to] - base
            out[at:to, :WORD_DIM] = self.word[own[at:to]]
            out[at:to, WORD_DIM] = np.maximum.reduceat(rows[:, 0], first)
            out[at:to, WORD_DIM + 1 :] = np.add.reduceat(rows[:, 1:], first, axis=0) / counts[at:to, None]
        return out

    def project(self, x: np.ndarray) -> np.ndarray:
        """Input part of the gates of both directions."""
        return np.concatenate([x @ self.p["Wf"] + self.p["bf"], x @ self.p["Wb"] + self.p["bb"]], axis=1)

    def logits(self, gates: np.ndarray, index: np.ndarray) -> np.ndarray:
        """Logits of windows: ``index`` (windows, WINDOW) into the rows of ``gates``; row 0 is padding and keeps the state."""
        return _forward(self.p, lambda t: gates[index[:, t]], index != 0)[0]


def _forward(p: dict, gates_at, mask: np.ndarray, trace: bool = False):
    n, steps = mask.shape
    h = HIDDEN
    states = np.zeros((n, steps, 2 * h), np.float32)
    kept = {}
    for d, name in enumerate("fb"):
        u, un = p[f"U{name}"], p[f"N{name}"]
        s = np.zeros((n, h), np.float32)
        for t in range(steps) if d == 0 else range(steps - 1, -1, -1):
            g = gates_at(t)[:, d * 3 * h : (d + 1) * 3 * h]
            zr = _sigmoid(g[:, : 2 * h] + s @ u)
            z, r = zr[:, :h] * mask[:, t, None], zr[:, h:]
            c = np.tanh(g[:, 2 * h :] + (r * s) @ un)
            if trace:
                kept[d, t] = (s, z, r, c)
            s = s + z * (c - s)
            states[:, t, d * h : (d + 1) * h] = s
    score = np.where(mask, states @ p["a"][:, 0], np.float32(-1e9))
    weight = np.exp(score - score.max(axis=1, keepdims=True))
    weight /= weight.sum(axis=1, keepdims=True)
    pooled = np.einsum("nt,nth->nh", weight, states)
    logit = pooled @ p["o"][:, 0] + p["c"][0]
    return (logit, states, weight, pooled, kept) if trace else (logit,)


def _backward(p: dict, mask: np.ndarray, traced, dlogit: np.ndarray) -> tuple[dict, np.ndarray]:
    _, states, weight, pooled, kept = traced
    h = HIDDEN
    n, steps = mask.shape
    grad = {k: np.zeros_like(v) for k, v in p.items()}
    grad["o"][:, 0], grad["c"][0] = pooled.T @ dlogit, dlogit.sum()
    dpool = dlogit[:, None] * p["o"][:, 0]
    dstates = weight[:, :, None] * dpool[:, None, :]
    dweight = np.einsum("nth,nh->nt", states, dpool)
    dscore = weight * (dweight - (weight * dweight).sum(axis=1, keepdims=True))
    grad["a"][:, 0] = np.einsum("nt,nth->h", dscore, states)
    dstates += dscore[:, :, None] * p["a"][:, 0]
    dgates = np.zeros((n, steps, 6 * h), np.float32)
    for d, name in enumerate("fb"):
        u, un = p[f"U{name}"], p[f"N{name}"]
        carry = np.zeros((n, h), np.float32)
        for t in range(steps - 1, -1, -1) if d == 0 else range(steps):
            s, z, r, c = kept[d, t]
            ds = carry + dstates[:, t, d * h : (d + 1) * h]
            dc = ds * z * (1 - c * c)
            m = mask[:, t, None]
            dz = ds * (c - s) * z * (1 - z) * m
            drs = dc @ un.T
            dr = drs * s * r * (1 - r)
            grad[f"N{name}"] += (r * s).T @ dc
            dzr = np.concatenate([dz, dr], axis=1)
            grad[f"U{name}"] += s.T @ dzr
            carry = ds * (1 - z) + drs * r + dzr @ u.T
            dgates[:, t, d * 3 * h : (d + 1) * 3 * h] = np.concatenate([dzr, dc], axis=1)
    return grad, dgates


def _grams_of(words: np.ndarray, flat: np.ndarray, ends: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """n-gram buckets of some words in a row, and the place of the word that each belongs to."""
    count = counts[words].astype(np.int64)
    of = np.repeat(np.arange(len(words)), count)
    return flat[np.arange(len(of)) + np.repeat(ends[words] - counts[words] - (np.cumsum(count) - count), count)], of


def _log_odds(buckets: list[np.ndarray], labels: np.ndarray, size: int) -> np.ndarray:
    """How much more often positive texts hold a bucket, in logarithms, shrunk towards 0 where there is little to go by."""
    up, down = np.zeros(size), np.zeros(size)
    for own, y in zip(buckets, labels, strict=True):
        (up if y else down)[own] += 1
    n1, n0 = max(1, labels.sum()), max(1, (1 - labels).sum())
    prior = 6.0
    p1, p0 = prior * n1 / (n1 + n0), prior * n0 / (n1 + n0)
    return np.log(((up + p1) / n1) / ((down + p0) / n0)).astype(np.float32)


def fit(texts: list[str | None], labels: list[int], *, seed: int = 11, rounds: int = 2, epochs: int = 3, batch: int = 256, rate: float = 0.01, table_rate: float = 0.002) -> Model:
    """Fits on whole texts with one label each: a positive text is taught by its worst window, a negative one by its worst and one more."""
    rng = np.random.default_rng(seed)
    y = np.asarray(labels, np.int64)
    vocabulary: dict[str, int] = {}
    ids = [np.fromiter((vocabulary.setdefault(w, len(vocabulary)) for w in words_of(t)), np.int32) for t in texts]
    words = list(vocabulary)
    if not words or len(set(y.tolist())) < 2:
        return Model(np.zeros((WORD_BUCKETS, WORD_DIM), np.float32), np.zeros((CHAR_BUCKETS, CHAR_DIM), np.float32), _initial(rng), base=float(y.mean()) if len(y) else 0.0, scale=0.0)
    del vocabulary
    buckets, flat_grams, counts = _buckets(words)
    ends = np.cumsum(counts, dtype=np.int64)
    own = [np.unique(t) for t in ids]
    own_words = [np.unique(buckets[o]) for o in own]
    own_grams = [np.unique(np.concatenate([flat_grams[ends[i] - counts[i] : ends[i]] for i in o])) if len(o) else np.zeros(0, np.int32) for o in own]
    model = Model(rng.normal(0, 0.1, (WORD_BUCKETS, WORD_DIM)).astype(np.float32), rng.normal(0, 0.1, (CHAR_BUCKETS, CHAR_DIM)).astype(np.float32), _initial(rng))

    def inputs_without(fold: int) -> np.ndarray:
        """Inputs as the texts of a fold meet them: the odds come from the other folds' texts (-1: from all)."""
        use = [i for i in range(len(texts)) if i % FOLDS != fold]
        model.word[:, 0] = _log_odds([own_words[i] for i in use], y[use], WORD_BUCKETS)
        model.char[:, 0] = _log_odds([own_grams[i] for i in use], y[use], CHAR_BUCKETS)
        return np.concatenate([np.zeros((1, WORD_DIM + CHAR_DIM), np.float32), model.rows(buckets, flat_grams, counts)])

    x = np.concatenate([inputs_without(f) for f in range(FOLDS)])
    inputs_without(-1)
    windows, of = [], []
    for d, t in enumerate(ids):
        for start in window_starts(len(t)):
            row = np.zeros(WINDOW, np.int32)
            part = t[start : start + WINDOW]
            row[: len(part)] = part + 1 + (d % FOLDS) * (len(words) + 1)
            windows.append(row), of.append(d)
    windows, of = np.array(windows), np.array(of)
    apart = np.arange(len(texts)) % FOLDS == 0  # texts that only the cut between the classes is found on
    if len(set(y[apart].tolist())) < 2 or len(set(y[~apart].tolist())) < 2:
        apart[:] = False
    score = (x[:, 0] + x[:, WORD_DIM])[windows].max(axis=1)
    trained = model.p | {"word": model.word[:, 1:], "char": model.char[:, 1:]}  # the tables as views
    flat = {k: (np.zeros_like(v), np.zeros_like(v)) for k, v in trained.items()}

    def refreshed(rows: np.ndarray) -> np.ndarray:
        """Inputs as the tables stand now; row 0 is padding."""
        out, w = x[rows], (rows - 1) % (len(words) + 1)
        real = np.flatnonzero(rows > 0)
        part = w[real]
        out[real, 1:WORD_DIM] = model.word[buckets[part], 1:]
        grams, of_word = _grams_of(part, flat_grams, ends, counts)
        for c in range(1, CHAR_DIM):
            out[real, WORD_DIM + c] = np.bincount(of_word, weights=model.char[grams, c], minlength=len(part)) / counts[part]
        return out

    def table_gradients(rows: np.ndarray, dx: np.ndarray) -> dict[str, np.ndarray]:
        real = rows > 0
        part, dx = (rows[real] - 1) % (len(words) + 1), dx[real]
        grams, of_word = _grams_of(part, flat_grams, ends, counts)
        share = dx[:, WORD_DIM + 1 :] / counts[part, None]
        to_words = [np.bincount(buckets[part], weights=dx[:, c], minlength=WORD_BUCKETS) for c in range(1, WORD_DIM)]
        to_grams = [np.bincount(grams, weights=share[of_word, c], minlength=CHAR_BUCKETS) for c in range(CHAR_DIM - 1)]
        return {"word": np.stack(to_words, axis=1).astype(np.float32), "char": np.stack(to_grams, axis=1).astype(np.float32)}

    step = 0
    for _ in range(rounds):
        order = np.lexsort((-score, of))
        order = order[~apart[of[order]]]
        first = np.r_[True, of[order][1:] != of[order][:-1]]
        worst = order[first]
        others = order[~first]
        others = others[y[of[others]] == 0]
        extra = rng.permutation(others)[: len(worst)]
        chosen = np.concatenate([worst, extra])
        target = y[of[chosen]].astype(np.float32)
        share = target.mean()
        weight = np.where(target > 0, 0.5 / share, 0.5 / (1 - share))  # both classes count alike
        size = min(batch, max(32, len(chosen) // 16))
        for _ in range(max(epochs, -(-LEAST_STEPS * size // len(chosen)))):
            mixed = rng.permutation(len(chosen))
            for at in range(0, len(mixed), size):
                pick = mixed[at : at + size]
                index = windows[chosen[pick]]
                mask = index != 0
                used, spot = np.unique(index, return_inverse=True)
                xs = refreshed(used)[spot.reshape(index.shape)]
                gates = np.concatenate([xs @ model.p["Wf"] + model.p["bf"], xs @ model.p["Wb"] + model.p["bb"]], axis=2)
                traced = _forward(model.p, lambda t, g=gates: g[:, t], mask, trace=True)
                delta = ((_sigmoid(traced[0]) - target[pick]) * weight[pick] / len(pick)).astype(np.float32)
                grad, dg = _backward(model.p, mask, traced, delta)
                h3 = 3 * HIDDEN
                for d, name in enumerate("fb"):
                    part = dg[:, :, d * h3 : (d + 1) * h3]
                    grad[f"W{name}"] = np.einsum("ntx,ntg->xg", xs, part)
                    grad[f"b{name}"] = part.sum(axis=(0, 1))
                dxs = (dg[:, :, :h3] @ model.p["Wf"].T + dg[:, :, h3:] @ model.p["Wb"].T).reshape(-1, WORD_DIM + CHAR_DIM)
                dx = np.stack([np.bincount(spot.ravel(), weights=dxs[:, c], minlength=len(used)) for c in range(dxs.shape[1])], axis=1)
                if table_rate:
                    grad |= table_gradients(used, dx)
                step += 1
                for k, g in grad.items():
                    m, v = flat[k]
                    m += 0.1 * (g - m)
                    v += 0.01 * (g * g - v)
                    trained[k] -= ((table_rate if k in ("word", "char") else rate) * m / (1 - 0.9**step) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)).astype(np.float32)
        score = np.empty(len(windows), np.float32)
        for f in range(FOLDS):  # one fold's gate inputs at a time
            low = f * (len(words) + 1)
            gates = model.project(refreshed(np.r_[0, np.arange(low + 1, low + len(words) + 1)]))
            part = np.flatnonzero(of % FOLDS == f)
            for at in range(0, len(part), 512):
                score[part[at : at + 512]] = model.logits(gates, np.maximum(windows[part[at : at + 512]] - low, 0))
    top = np.full(len(texts), -np.inf)
    np.maximum.at(top, of, score)
    judged = apart if apart.any() else ~apart
    model.shift = _cut(top[judged], y[judged])
    return model


def _initial(rng) -> dict[str, np.ndarray]:
    x, h = WORD_DIM + CHAR_DIM, HIDDEN
    draw = lambda *shape: (rng.normal(0, 1, shape) / np.sqrt(shape[0])).astype(np.float32)
    out = {}
    for name in "fb":
        out |= {f"W{name}": draw(x, 3 * h), f"b{name}": np.zeros(3 * h, np.float32), f"U{name}": draw(h, 2 * h), f"N{name}": draw(h, h)}
    return out | {"a": draw(2 * h, 1), "o": draw(2 * h, 1), "c": np.zeros(1, np.float32)}


def _cut(top: np.ndarray, y: np.ndarray) -> float:
    """The best cut between the classes' logits (a false alarm costs three misses), in the middle of its gap."""
    finite = np.isfinite(top)
    order = np.argsort(-top[finite], kind="stable")
    s, t = top[finite][order], y[finite][order]
    hits = np.cumsum(t)
    alarms = np.cumsum(1 - t)
    best = int(np.argmax(hits / max(1, t.sum()) - 3 * alarms / max(1, (1 - t).sum())))
    low = s[best + 1] if best + 1 < len(s) else s[best] - 1
    return float((s[best] + low) / 2)


def _scores(model: Model, logit: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(model.scale * (logit - model.shift) + np.log(THRESHOLD / (1 - THRESHOLD)), -30, 30)))


class Scorer:
    """Scores texts with one model; remembers the gate inputs of up to ``max_words`` distinct words."""

    def __init__(self, model: Model, *, max_words: int = 50_000) -> None:
        self.model, self.max_words = model, max_words
        self._start()

    def _start(self) -> None:
        self.index: dict[str, int] = {}
        self.gates = np.zeros((1024, 6 * HIDDEN), np.float32)

    def _learn(self, tokens: list[list[str]]) -> None:
        new = [w for w in set().union(*tokens) if w not in self.index]
        if not new:
            return
        at = len(self.index) + 1
        while at + len(new) > len(self.gates):
            self.gates = np.concatenate([self.gates, np.zeros_like(self.gates)])
        for s in range(0, len(new), 20_000):
            part = new[s : s + 20_000]
            self.gates[at + s : at + s + len(part)] = self.model.project(self.model.inputs(part))
        self.index.update(zip(new, range(at, at + len(new)), strict=True))

    def score(self, texts: list[str | None]) -> np.ndarray:
        if self.model.scale == 0:
            return np.full(len(texts), self.model.base)
        if len(self.index) > self.max_words:
            self._start()
        tokens = [words_of(t) for t in texts]
        self._learn(tokens)
        get = self.index.__getitem__
        ids = [np.fromiter(map(get, t), np.int32, len(t)) for t in tokens]
        top = np.full(len(texts), -np.inf)
        rows, of = [], []
        for d, own in enumerate(ids):
            if not len(own):
                continue
            starts = np.array(window_starts(len(own)))
            padded = np.zeros(starts[-1] + WINDOW, np.int32)
            padded[: len(own)] = own[: len(padded)]
            rows.append(np.lib.stride_tricks.sliding_window_view(padded, WINDOW)[starts])
            of.append(np.full(len(starts), d))
        if rows:
            windows, of = np.concatenate(rows), np.concatenate(of)
            logit = np.concatenate([self.model.logits(self.gates, windows[at : at + 1024]) for at in range(0, len(windows), 1024)])
            np.maximum.at(top, of, logit)
        return _scores(self.model, np.maximum(top, -1e6))


_SCHEMA = pa.schema([("doc_id", pa.int64()), ("score", pa.float64())])


def _score_batches(batches: Iterator[pa.RecordBatch], shared) -> Iterator[pa.RecordBatch]:
    resident("toxicity")  # what other kernels have kept goes
    scorer = Scorer(shared.value)
    for ids, texts in pieces(batches, 1_500_000):
        yield record(_SCHEMA, ids, scorer.score(texts))


def fit_on(docs: DataFrame, labels: DataFrame, *, per_class: int = SAMPLE_PER_CLASS, **options) -> Model:
    """Fits on a bounded sample of labelled rows: at most ``per_class`` texts of each class, by a hash of the id.

    Rows whose crc32(doc_id as text) leaves 2 modulo 4 are held out and never read for learning.
    """
    marks = labels.select(F.col("doc_id").cast("long").alias("label_id"), F.col("toxic").cast("int").alias("toxic")).where("toxic in (0, 1)")
    marks = marks.where(F.crc32(F.col("label_id").cast("string").cast("binary")) % 4 != 2).groupBy("label_id").agg(F.max("toxic").alias("toxic"))
    texts = documents_of(docs)
    chosen = None
    for side in (1, 0):  # ids first, and texts only of a few more than are needed, as some labels have no text
        part = marks.where(F.col("toxic") == side).select("label_id", "toxic")
        part = part.join(texts.select("doc_id"), F.col("label_id") == F.col("doc_id"), "left_semi").orderBy(F.xxhash64("label_id"), "label_id").limit(per_class)
        chosen = part if chosen is None else chosen.union(part)
    rows = texts.join(F.broadcast(chosen), F.col("doc_id") == F.col("label_id")).select("doc_id", "text", "toxic").toPandas()  # at most 2 * per_class labels
    rows = rows.sort_values("doc_id", kind="stable").drop_duplicates("doc_id")
    return fit(rows["text"].tolist(), rows["toxic"].tolist(), **options)


def toxicity(docs: DataFrame, labels: DataFrame, *, threshold: float = THRESHOLD, per_class: int = SAMPLE_PER_CLASS, **options) -> DataFrame:
    """``documents``, ``labels`` -> ``(doc_id, held_out, score, predicted)``, one row for each input row.

    ``score`` is between 0 and 1 and comes from the whole text alone. Null, empty and wordless texts score near 0.
    Repeated rows score alike. A null id is not held out. Without labels of both classes every score is the share of
    positive ones (0 without any). Labels without a text, null labels and clashing columns do no harm.
    """
    spark = prepare(docs.sparkSession)
    model = fit_on(docs, labels, per_class=per_class, **options)
    shared = spark.sparkContext.broadcast(model)  # fixed size: two tables and a few small matrices
    scored = documents_of(docs).mapInArrow(lambda it: tidy(_score_batches(it, shared)), "doc_id long, score double")
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2, F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def annotate(docs: DataFrame, labels: DataFrame, *, threshold: float = THRESHOLD, per_class: int = SAMPLE_PER_CLASS, **options) -> DataFrame:
    """The rows of ``docs`` themselves with ``score`` and ``predicted`` added, without a join by id.

    Null, empty and wordless texts score near 0; repeated rows, rows without an id and other columns come back as they came; an empty
    table gives an empty result.
    """
    spark = prepare(docs.sparkSession)
    shared = spark.sparkContext.broadcast(fit_on(docs, labels, per_class=per_class, **options))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        resident("toxicity")
        scorer = Scorer(shared.value)
        for batch in batches:
            texts = batch.column(batch.schema.get_field_index("text")).to_pylist()
            scores = np.concatenate([scorer.score(texts[i : i + 256]) for i in range(0, len(texts), 256)]) if texts else np.zeros(0)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(scores, pa.float64())], names=[*batch.schema.names, "score"])

    if "score" in docs.columns:
        raise ValueError("the documents have a column named score already")
    schema = T.StructType([*docs.schema.fields, T.StructField("score", T.DoubleType())])
    return docs.mapInArrow(lambda it: tidy(run(it)), schema).withColumn("predicted", (F.col("score") >= threshold).cast("int"))
