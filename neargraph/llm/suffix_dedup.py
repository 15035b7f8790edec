"""Repeated passages by a sparse suffix array over words.

Suffixes are kept only where the hash of eight words is smallest among its neighbours (a minimiser), so equal passages keep
equal suffixes: every window of ``length`` words holds a kept suffix at most ``length - key`` words from its start. A hash of a
suffix's first ``key`` words finds those that may repeat; for them the words to the right and to the left are fetched. Suffixes with
the same first words meet in one task in order of their words, and neighbours are compared word by word: the common words of
neighbours cut the order into classes that agree so far to the right, and the order of the words to the left, read backwards, cuts it
into classes that agree so far to the left. A window is repeated if both extensions together reach over it. Where very many
suffixes share a start (a passage in a large part of all texts) they are dealt out by text, and the classes of all parts are put
together by the hashes of their windows before each part judges its own suffixes. Exact copies of a text count as one text until the end.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neargraph.llm.kernels import ascii_words, documents_of, record, resident, tidy
from neargraph.runtime import Scratch, shuffle_partitions

LENGTH = 50
GRAM = 8
KEY = 24
#: Suffixes of one start that a task compares (some 25 MB of words); more of them are dealt out by text, about so many to a part.
CROWD = 50_000
#: Suffixes that a comparison holds at a time, whole groups of equal starts.
COMPARED = 20_000
#: Texts that a kernel holds at a time.
BATCH_TEXTS = 512
_BASES = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93))
_MIX = np.uint64(0xFF51AFD7ED558CCD)


class WordHashes:
    """64-bit hashes of words; remembers up to ``limit`` of them, common words longest."""

    def __init__(self, limit: int = 150_000) -> None:
        self.limit, self.known = limit, {}

    def of(self, words: list[bytes]) -> np.ndarray:
        known = self.known
        try:
            return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
        except KeyError:
            if len(known) > self.limit:
                for w in list(known)[self.limit // 2 :]:
                    del known[w]
            digest = xxhash.xxh3_64_intdigest
            for w in words:
                if w not in known:
                    known[w] = digest(w)
            return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))


def run_hashes(h: np.ndarray, length: int, base: np.uint64) -> np.ndarray:
    """Hash of every run of ``length`` words, put together from runs of powers of two."""
    if len(h) < length:
        return np.zeros(0, np.uint64)
    out, done = None, 0
    power, level, size = base, h, 1  # power = base ** size
    rest = length
    with np.errstate(over="ignore"):
        while rest:
            if rest & 1:
                out = level if out is None else out[: len(level) - done] * power + level[done:][: len(out)]
                done += size
            rest >>= 1
            if rest:
                level = level[:-size] * power + level[size:]
                power *= power
                size *= 2
    return out[: len(h) - length + 1]


def _slide(x: np.ndarray, width: int, op) -> np.ndarray:
    """``op`` (minimum or maximum) over every ``width`` neighbours."""
    out, size = x, 1
    while size * 2 <= width:
        out = op(out[:-size], out[size:])
        size *= 2
    return op(out[: len(x) - width + 1], out[width - size :][: len(x) - width + 1])


def minimisers(grams: np.ndarray, width: int) -> np.ndarray:
    """Positions that hold the smallest value of at least one run of ``width`` neighbours."""
    if len(grams) < width:
        return np.zeros(0, np.int64)
    least = _slide(grams, width, np.minimum)
    padded = np.concatenate([np.zeros(width - 1, np.uint64), least, np.zeros(width - 1, np.uint64)])
    return np.flatnonzero(_slide(padded, width, np.maximum) == grams)


#: Bits for an offset in a packed place.
_OFFSET = 12


def anchors(h: np.ndarray, length: int, gram: int, key: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes of the first ``key`` words, packed places) of the kept suffixes of a text with word hashes ``h``.

    A place holds the suffix's first word and the least and greatest offset of the windows whose smallest hash it has: other windows
    over it are looked up at their own. A window with several smallest ones belongs to all of them.
    """
    if len(h) < length:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    with np.errstate(over="ignore"):
        grams = run_hashes(h, gram, _BASES[1])[: len(h) - key + 1]  # no window's suffix begins further right
        grams = (grams ^ (grams >> np.uint64(33))) * _MIX
    width = length - key + 1
    least = _slide(grams, width, np.minimum)
    at = minimisers(grams, width)
    s = at[:, None] - np.arange(width)
    mine = (s >= 0) & (s < len(least)) & (least[np.clip(s, 0, len(least) - 1)] == grams[at][:, None])
    low, high = mine.argmax(axis=1), width - 1 - mine[:, ::-1].argmax(axis=1)
    return run_hashes(h, key, _BASES[0])[at], at << 2 * _OFFSET | low << _OFFSET | high


def unpacked(places: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first word, least offset, greatest offset) of packed places."""
    part = (1 << _OFFSET) - 1
    return places >> 2 * _OFFSET, places >> _OFFSET & part, places & part


def text_hashes():
    """Two hashes that stand for a text; null counts as empty."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return F.xxhash64(text).alias("t1"), F.xxhash64(text, F.lit(1)).alias("t2")


_TEXTS = "doc_id long, t1 long, t2 long, n_words int, keys array<long>, at array<long>"


def _anchor_batches(batches: Iterator[pa.RecordBatch], length: int, gram: int, key: int) -> Iterator[pa.RecordBatch]:
    """(doc_id, text, t1, t2) -> the kept suffixes of each text as places and hashes of their first words."""
    schema = pa.schema([("doc_id", pa.int64()), ("t1", pa.int64()), ("t2", pa.int64()), ("n_words", pa.int32()), ("keys", pa.list_(pa.int64())), ("at", pa.list_(pa.int64()))])
    resident("words")  # what other kernels have kept goes
    hashes = WordHashes()
    for whole in batches:
        for start in range(0, whole.num_rows, BATCH_TEXTS):
            batch = whole.slice(start, BATCH_TEXTS)
            n, keys, at = [], [], []
            for text in batch.column(1).to_pylist():
                words = ascii_words(text)
                k, p = anchors(hashes.of(words), length, gram, key) if len(words) >= length else (np.zeros(0, np.uint64), np.zeros(0, np.int64))
                n.append(len(words)), keys.append(k.view(np.int64)), at.append(p)
            yield record(schema, batch.column(0), batch.column(2), batch.column(3), n, keys, at)


def _slices(column: pa.Array) -> list[np.ndarray]:
    """The lists of a column as slices of one array; a null list is empty."""
    at, values, valid = column.offsets.to_numpy(), column.values.to_numpy(zero_copy_only=False), column.is_valid().to_numpy(zero_copy_only=False)
    return [values[a:b] if ok else values[:0] for a, b, ok in zip(at[:-1].tolist(), at[1:].tolist(), valid.tolist(), strict=True)]


_CONTEXT = pa.schema([("k", pa.int64()), ("part", pa.int32()), ("rep", pa.int64()), ("t1", pa.int64()), ("at", pa.int64()), ("right", pa.binary()), ("left", pa.binary())])
_CONTEXTS = "k long, part int, rep long, t1 long, at long, right binary, left binary"


def _context_batches(batches: Iterator[pa.RecordBatch], length: int, key: int) -> Iterator[pa.RecordBatch]:
    """(doc_id, t1, text, places, parts) -> for each place the words to its right and, last word first, to its left that its windows hold."""
    resident("words")  # what other kernels have kept goes
    hashes = WordHashes()
    for whole in batches:
        for start in range(0, whole.num_rows, 64):
            batch = whole.slice(start, 64)
            held: list[tuple] = []
            for doc, t1, text, at, parts in zip(*(batch.column(i).to_pylist() for i in range(3)), _slices(batch.column(3)), _slices(batch.column(4)), strict=True):
                words = ascii_words(text)
                first = run_hashes(hashes.of(words), key, _BASES[0]).view(np.int64)
                ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
                joined = b" ".join(words) + b" "
                for place, part, p, low, high in zip(at.tolist(), parts.tolist(), *(x.tolist() for x in unpacked(at)), strict=True):
                    begin = int(ends[p - 1]) if p else 0
                    held.append((int(first[p]), part, doc, t1, place, joined[begin : int(ends[p + length - low - 1])], b" ".join(words[p - high : p][::-1])))
            if held:
                yield record(_CONTEXT, *zip(*held, strict=True))


def _codes(contexts: list[bytes], width: int) -> np.ndarray:
    """Words as numbers, one row for each context, 0 beyond its end. Equal numbers are equal words."""
    number: dict[bytes, int] = {}
    out = np.zeros((len(contexts), width), ">u4")
    for i, context in enumerate(contexts):
        own = [number.setdefault(w, len(number) + 1) for w in context.split()]
        out[i, : len(own)] = own
    return out


def _agreement(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order of the rows by their numbers, and how many first ones each has in common with the row before it (the first row: -1)."""
    order = np.argsort(rows.view(f"S{4 * rows.shape[1]}")[:, 0], kind="stable")
    same = rows[order][1:] == rows[order][:-1]
    common = np.where(same.all(axis=1), rows.shape[1], same.argmin(axis=1))
    return order, np.r_[-1, common] if len(rows) else np.zeros(0, np.int64)


def window_classes(right: list[bytes], left: list[bytes], places: np.ndarray, low: np.ndarray, high: np.ndarray, length: int, key: int, least: int = 2) -> tuple[np.ndarray, ...]:
    """For suffixes at distinct ``places`` (sorted numbers): (suffix, offset, first suffix, size) of the windows that ``least`` or more share.

    A window of an offset begins so many words left of the suffix; a suffix has windows of the offsets ``low`` to ``high``. Suffixes
    share it if they agree on that many words to the left and on the rest to the right; neighbours in order that agree on fewer are
    the borders between classes that agree. ``first`` is the one of the class at the smallest place.
    """
    n, most = len(right), length - key
    r, l = _codes(right, length), _codes(left, most)
    by_right, common_right = _agreement(r)
    by_left, common_left = _agreement(l)
    size_right, size_left = (r != 0).sum(axis=1), (l != 0).sum(axis=1)
    out = [tuple(np.zeros(0, np.int64) for _ in range(4))]
    to_right, to_left = np.empty(n, np.int64), np.empty(n, np.int64)
    for offset in range(most + 1):
        live = np.flatnonzero((low <= offset) & (offset <= high) & (size_right >= length - offset) & (size_left >= offset))
        if len(live) < least:
            continue
        to_right[by_right] = np.cumsum(common_right < length - offset)
        to_left[by_left] = np.cumsum(common_left < offset)
        both = to_right[live] * (n + 1) + to_left[live]
        order = np.lexsort((places[live], both))
        fresh = np.r_[True, both[order][1:] != both[order][:-1]]
        run = np.cumsum(fresh) - 1
        size = np.bincount(run)[run]
        first = live[order][np.flatnonzero(fresh)][run]
        several = size >= least
        out.append((live[order][several], np.full(int(several.sum()), offset), first[several], size[several]))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


class _Block:
    """Suffixes that are compared together. Rows that repeat id, text and place count once."""

    def __init__(self, rep: np.ndarray, t1: np.ndarray, places: np.ndarray, right: list[bytes], left: list[bytes]) -> None:
        at, low, high = unpacked(places)
        order = np.lexsort((at, t1, rep))
        same = (np.diff(rep[order]) == 0) & (np.diff(t1[order]) == 0) & (np.diff(at[order]) == 0)
        number = np.empty(len(at), np.int64)
        number[order] = np.r_[0, np.cumsum(~same)]  # in order of document, text and word
        pick = np.sort(np.unique(number, return_index=True)[1])
        self.rep, self.t1, self.at, self.low, self.high, self.place = (x[pick] for x in (rep, t1, at, low, high, number))
        self.right, self.left = [right[i] for i in pick.tolist()], [left[i] for i in pick.tolist()]

    def classes(self, length: int, key: int, least: int) -> tuple[np.ndarray, ...]:
        return window_classes(self.right, self.left, self.place, self.low, self.high, length, key, least)

    def hashes(self, suffix: np.ndarray, offset: np.ndarray, length: int) -> np.ndarray:
        """128-bit hashes of windows, as two columns."""
        out = np.empty((len(suffix), 2), np.int64)
        for i, (own, o) in enumerate(zip(suffix.tolist(), offset.tolist(), strict=True)):
            digest = xxhash.xxh3_128_digest(b" ".join(self.left[own].split(None, o)[:o][::-1] + self.right[own].split(None, length - o)[: length - o]))
            out[i] = np.frombuffer(digest, "<i8")
        return out

    def runs(self, suffix: np.ndarray, offset: np.ndarray, later: np.ndarray, first_doc: np.ndarray) -> list[np.ndarray]:
        """Verdicts on windows as runs of starts of one text with one verdict, in the columns of ``_VERDICT``."""
        rep, t1, start = self.rep[suffix], self.t1[suffix], self.at[suffix] - offset
        order = np.lexsort((start, t1, rep))
        rep, t1, start, later, first_doc = (x[order] for x in (rep, t1, start, later, first_doc))
        other = np.r_[True, (np.diff(rep) != 0) | (np.diff(t1) != 0)][: len(rep)]
        own = other | np.r_[True, np.diff(start) != 0][: len(rep)]  # a window may have several suffixes, which agree on it
        other, rep, t1, start, later, first_doc = (x[own] for x in (other, rep, t1, start, later, first_doc))
        new = other | np.r_[True, (np.diff(start) != 1) | (later[1:] != later[:-1]) | (np.diff(first_doc) != 0)][: len(rep)]
        begin = np.flatnonzero(new)
        end = np.r_[begin[1:], len(start)][: len(begin)] - 1
        return [rep[begin], t1[begin], start[begin], start[end], later[begin], first_doc[begin]]


_VERDICT = pa.schema([("rep", pa.int64()), ("t1", pa.int64()), ("low", pa.int32()), ("high", pa.int32()), ("later", pa.bool_()), ("first_doc", pa.int64())])
_VERDICTS = "rep long, t1 long, low int, high int, later boolean, first_doc long"


def _compare_batches(batches: Iterator[pa.RecordBatch], length: int, key: int) -> Iterator[pa.RecordBatch]:
    """Suffixes sorted by (k, words to the right) -> verdicts. Whole groups of one start are held together, several at a time."""
    held: list[pa.Table] = []
    rows = 0

    def judge(table: pa.Table) -> pa.RecordBatch:
        rep, t1, places, right, left = (table.column(c) for c in ("rep", "t1", "at", "right", "left"))
        block = _Block(rep.to_numpy(), t1.to_numpy(), places.to_numpy(), right.to_pylist(), left.to_pylist())
        suffix, offset, first, _ = block.classes(length, key, 2)
        return record(_VERDICT, *block.runs(suffix, offset, block.place[suffix] != block.place[first], block.rep[first]))

    for batch in batches:
        if not batch.num_rows:
            continue
        held.append(pa.Table.from_batches([batch]))
        rows += batch.num_rows
        if rows >= COMPARED:
            table = pa.concat_tables(held)
            k = table.column("k").to_numpy()
            if cut := int(np.searchsorted(k, k[-1])):  # the last group may go on
                yield judge(table.slice(0, cut))
            held = [table.slice(cut)]
            rows = len(k) - cut
    if rows:
        yield judge(pa.concat_tables(held))


def _block_of(pdf: pd.DataFrame) -> _Block:
    return _Block(pdf["rep"].to_numpy(), pdf["t1"].to_numpy(), pdf["at"].to_numpy(), pdf["right"].tolist(), pdf["left"].tolist())


def _part_classes(pdf: pd.DataFrame, length: int, key: int) -> pd.DataFrame:
    """The suffixes of crowded starts in one part of the texts -> their classes of windows: hash, first place and size."""
    block = _block_of(pdf)
    suffix, offset, first, size = block.classes(length, key, 1)
    heads = np.flatnonzero(suffix == first)
    own, o = suffix[heads], offset[heads]
    h = block.hashes(own, o, length)
    return pd.DataFrame({"part": pdf["part"].iloc[0], "w1": h[:, 0], "w2": h[:, 1], "rep": block.rep[own], "t1": block.t1[own], "s": (block.at[own] - o).astype(np.int32), "n": size[heads]})


def _part_verdicts(pdf: pd.DataFrame, shared: pd.DataFrame, length: int, key: int) -> pd.DataFrame:
    """The suffixes of one part and those of its classes that repeat anywhere, with their first places -> verdicts."""
    names = [f.name for f in _VERDICT]
    if not len(pdf) or not len(shared):
        return pd.DataFrame({n: [] for n in names})
    block = _block_of(pdf)
    suffix, offset, first, _ = block.classes(length, key, 1)
    heads = np.flatnonzero(suffix == first)
    known = {tuple(h): i for i, h in enumerate(shared[["w1", "w2"]].to_numpy().tolist())}
    found = np.full((len(block.at), length - key + 1), -1, np.int64)
    found[suffix[heads], offset[heads]] = [known.get(tuple(h), -1) for h in block.hashes(suffix[heads], offset[heads], length).tolist()]
    to = found[first, offset]
    suffix, offset, to = suffix[to >= 0], offset[to >= 0], to[to >= 0]
    first_rep, first_t1, first_s = (shared[c].to_numpy()[to] for c in ("first_rep", "first_t1", "first_s"))
    itself = (block.rep[suffix] == first_rep) & (block.t1[suffix] == first_t1) & (block.at[suffix] - offset == first_s)
    return pd.DataFrame(dict(zip(names, block.runs(suffix, offset, ~itself, first_rep), strict=True)))


def _cover(starts: np.ndarray, length: int) -> list[tuple[int, int]]:
    """Runs of words covered by the windows that begin at the given starts (sorted)."""
    if not len(starts):
        return []
    cut = np.flatnonzero(np.diff(starts) > length) + 1
    return [(int(r[0]), int(r[-1]) + length) for r in np.split(starts, cut)]


def _span_batches(batches: Iterator[pa.RecordBatch], length: int) -> Iterator[pa.RecordBatch]:
    """Per text: spans that stand earlier elsewhere already, and spans that later places repeat."""
    schema = pa.schema([("doc_id", pa.int64()), ("t1", pa.int64()), ("start_word", pa.int32()), ("end_word", pa.int32()), ("later", pa.bool_()), ("first_doc_id", pa.int64())])
    for batch in batches:
        out: list[tuple] = []
        for doc, t1, n, copied, low, high, later, first in zip(*(batch.column(i).to_pylist() for i in range(4)), *(_slices(batch.column(i)) for i in range(4, 8)), strict=True):
            size = high.astype(np.int64) - low + 1
            s = np.repeat(low.astype(np.int64) - (np.cumsum(size) - size), size) + np.arange(size.sum())
            s, at = np.unique(s, return_index=True)  # suffixes agree on the windows that they share
            later, first = np.repeat(later.astype(bool), size)[at], np.repeat(first.astype(np.int64), size)[at]
            again = s[later]
            here = np.setdiff1d(np.arange(n - length + 1), again) if copied else s[~later]
            for a, b in _cover(again, length):
                inside = (again >= a) & (again + length <= b)
                out.append((doc, t1, a, b, True, int(first[later][inside].min())))
            out += [(doc, t1, a, b, False, doc) for a, b in _cover(here, length)]
        if out:
            yield record(schema, *(list(c) for c in zip(*out, strict=True)))


def spans_of_texts(docs: DataFrame, *, length: int = LENGTH, gram: int = GRAM, key: int = KEY, crowd: int = CROWD) -> DataFrame:
    """As ``repeated_spans``, with the hash ``t1`` of the text beside the id: rows of one id and different texts are texts of their own."""
    if not 0 < gram <= key < length < 1 << _OFFSET:
        raise ValueError("gram, key and length must grow, up to 4095 words")
    spark = docs.sparkSession
    scratch = Scratch(spark, "suffix")
    n = shuffle_partitions(spark)
    rows = documents_of(docs).where("doc_id is not null").select("doc_id", "text", *text_hashes())
    texts = scratch.keep(rows.mapInArrow(lambda it: tidy(_anchor_batches(it, length, gram, key)), _TEXTS))
    long = texts.where(F.col("n_words") >= length)
    # a text's first document stands for all of its copies
    classes = scratch.keep(long.groupBy("t1", "t2").agg(F.min("doc_id").alias("rep"), F.max("n_words").alias("n_words"), (F.min("doc_id") < F.max("doc_id")).alias("copied")))
    reps = classes.select(F.col("t1").alias("c1"), F.col("t2").alias("c2"), "rep")
    own = long.select("doc_id", "t1", "t2", "keys", "at").join(reps, (F.col("t1") == F.col("c1")) & (F.col("t2") == F.col("c2")) & (F.col("doc_id") == F.col("rep")), "left_semi")
    own = own.dropDuplicates(["doc_id", "t1", "t2"])  # on the partitions of the join
    suffixes = own.select(F.col("doc_id").alias("rep"), "t1", F.explode(F.arrays_zip("keys", "at")).alias("x")).select("rep", "t1", F.col("x.keys").alias("k"), F.col("x.at").alias("at"))
    # written, so that both sides of the join come straight from a shuffle and a common start's rows can be split
    often = scratch.keep(suffixes.groupBy("k").agg(F.count("*").alias("n")).where("n > 1").select(F.col("k").alias("again"), "n"))
    in_crowds = often.where(F.col("n") > crowd).agg(F.sum("n")).first()[0] or 0
    # a text's suffixes with crowded starts stay together
    part = F.when(F.col("n") <= crowd, F.lit(-1)).otherwise(F.pmod(F.xxhash64("rep", "t1"), F.lit(max(1, -(-in_crowds // crowd)))).cast("int"))
    kept = suffixes.join(often, F.col("k") == F.col("again")).select("rep", "t1", F.struct("at", part.alias("part")).alias("x"))
    # at most one place for each few words of a text
    work = kept.groupBy("rep", "t1").agg(F.collect_list("x").alias("x")).select("rep", F.col("t1").alias("rep_t1"), F.col("x.at").alias("places"), F.col("x.part").alias("parts"))
    candidates = rows.join(work, (F.col("doc_id") == F.col("rep")) & (F.col("t1") == F.col("rep_t1"))).select("doc_id", "t1", "text", "places", "parts")
    contexts = scratch.keep(candidates.mapInArrow(lambda it: tidy(_context_batches(it, length, key)), _CONTEXTS))
    ordered = contexts.where("part < 0").repartition(n, "k").sortWithinPartitions("k", "right")
    verdicts = ordered.mapInArrow(lambda it: tidy(_compare_batches(it, length, key)), _VERDICTS)
    crowded = contexts.where("part >= 0")
    if in_crowds:
        parts = scratch.keep(crowded.groupBy("part").applyInPandas(lambda pdf: _part_classes(pdf, length, key), "part int, w1 long, w2 long, rep long, t1 long, s int, n long"))
        twice = parts.groupBy("w1", "w2").agg(F.min(F.struct("rep", "t1", "s")).alias("first"), F.sum("n").alias("n")).where("n > 1")
        twice = scratch.keep(twice.select("w1", "w2", F.col("first.rep").alias("first_rep"), F.col("first.t1").alias("first_t1"), F.col("first.s").alias("first_s")))
        shared = parts.select("part", "w1", "w2").join(twice, ["w1", "w2"])
        judged = crowded.groupBy("part").cogroup(shared.groupBy("part")).applyInPandas(lambda pdf, own: _part_verdicts(pdf, own, length, key), _VERDICTS)
        verdicts = verdicts.unionByName(judged)
    verdicts = scratch.keep(verdicts)
    grouped = verdicts.groupBy("rep", "t1").agg(F.collect_list(F.struct("low", "high", "later", "first_doc")).alias("v")).select(F.col("rep").alias("g_rep"), F.col("t1").alias("g_t1"), "v")
    known = classes.join(grouped, (classes.rep == F.col("g_rep")) & (classes.t1 == F.col("g_t1")), "left").where("copied or v is not null")
    spans = scratch.keep(known.select("rep", "t1", "n_words", "copied", "v.low", "v.high", "v.later", "v.first_doc").mapInArrow(lambda it: _span_batches(it, length), "doc_id long, t1 long, start_word int, end_word int, later boolean, first_doc_id long"))
    firsts = spans.where("later").groupBy(F.col("doc_id").alias("f_rep"), F.col("t1").alias("f_t1")).agg(F.min("first_doc_id").alias("first_doc_id"))
    whole = classes.where("copied").join(firsts, (classes.rep == F.col("f_rep")) & (classes.t1 == F.col("f_t1")), "left").select("t1", "t2", "rep", F.coalesce("first_doc_id", "rep").alias("first_doc_id"))
    copies = long.select("doc_id", "t1", "t2", "n_words").distinct().join(whole, ["t1", "t2"]).where("doc_id <> rep")
    copies = copies.select("doc_id", "t1", F.lit(0).alias("start_word"), F.col("n_words").alias("end_word"), F.lit(True).alias("later"), "first_doc_id")
    scratch.drop(contexts, verdicts)
    return spans.unionByName(copies)


def repeated_spans(docs: DataFrame, **options) -> DataFrame:
    """``documents`` -> ``(doc_id, start_word, end_word, later, first_doc_id)``: the spans of words that repeat.

    A span is a longest run of words covered by windows of ``length`` words that stand in two places or more, in one document or
    several. ``later`` spans have an earlier place (smaller document, or further left in the same) for each window, ``first_doc_id``
    being the smallest document with one; the other spans hold first places. Words are as in ``ascii_words``, case kept. Texts
    below ``length`` words, null and empty ones have no spans. Rows that repeat id and text count once; different texts under one id
    are texts of their own, in order of a hash. Rows without an id take no part. No repeats or an empty table give an empty result.
    """
    return spans_of_texts(docs, **options).drop("t1")


_WORD = re.compile(rb"[^\x20\x09-\x0D]+")


def cut_text(text: str, spans: list[tuple[int, int]]) -> str:
    """The text without the words of the spans and the white space behind them."""
    raw = text.encode("utf-8", "surrogatepass")
    starts = [m.start() for m in _WORD.finditer(raw)] + [len(raw)]
    out, at = [], 0
    for a, b in sorted(spans):
        out.append(raw[at : starts[a]])
        at = starts[b]
    return b"".join([*out, raw[at:]]).decode("utf-8", "surrogatepass")


def _cut_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        at = {f.name: i for i, f in enumerate(batch.schema)}
        texts, starts, ends = (batch.column(at[c]).to_pylist() for c in ("text", "cut_starts", "cut_ends"))
        new = [t if not s else cut_text(t, list(zip(s, e, strict=True))) for t, s, e in zip(texts, starts, ends, strict=True)]
        keep = pa.array([not s or bool(x.strip(" \t\n\r\x0b\x0c")) for x, s in zip(new, starts, strict=True)])
        fields = [f for f in batch.schema if f.name not in ("cut_starts", "cut_ends")]
        columns = [pa.array(new, f.type) if f.name == "text" else batch.column(at[f.name]) for f in fields]
        yield pa.RecordBatch.from_arrays(columns, schema=pa.schema(fields)).filter(keep)


def cut_repeats(docs: DataFrame, **options) -> DataFrame:
    """The documents without their ``later`` spans, so that of each repeated passage the first place stays.

    A document of which nothing stays goes; others keep their columns, with ``n_chars`` counted anew where the text changed. Null and
    empty texts and rows without an id stay as they are. Rows that repeat id and text are cut alike.
    """
    cuts = spans_of_texts(docs, **options).where("later").groupBy(F.col("doc_id").alias("cut_id"), F.col("t1").alias("cut_t1")).agg(F.sort_array(F.collect_set(F.struct("start_word", "end_word"))).alias("cut"))
    joined = docs.join(cuts, (docs.doc_id == cuts.cut_id) & (text_hashes()[0] == F.col("cut_t1")), "left")
    rows = joined.select(*(docs[c] for c in docs.columns), F.col("cut.start_word").alias("cut_starts"), F.col("cut.end_word").alias("cut_ends"))
    out = rows.mapInArrow(lambda it: tidy(_cut_batches(it)), docs.schema)
    return out.withColumn("n_chars", F.coalesce(F.length("text").cast("long"), F.col("n_chars"))) if "n_chars" in docs.columns else out
