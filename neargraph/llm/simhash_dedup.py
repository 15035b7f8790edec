"""SimHash near-duplicates by a binary-trie self-join of the fingerprints.

Fingerprints are first reduced to distinct ones, so exact copies cost one row. Five tries hold every fingerprint, each
rotated so that another of five bit segments comes first: two fingerprints within four bits agree in at least one whole
segment, so below a segment's node nothing is lost. Below it a trie is joined with itself: pairs of nodes go down
together, differing bits add up, and a pair goes as soon as they exceed the budget. A node with too many fingerprints for one
task is cut again: what is left of its bits makes five segments once more, one of which must agree. Only a spanning forest of
the links leaves a task, so a dense group costs its members and not its pairs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neargraph.llm.kernels import ascii_words, documents_of, pieces, record, tidy
from neargraph.operators.linking import _forest, components
from neargraph.runtime import Scratch, shuffle_partitions

#: Byte value -> eight byte lanes that hold its bits.
_LANES = ((np.arange(256)[:, None] >> np.arange(8)) & 1).astype(np.uint8).view("<u8")[:, 0]

_FP_SCHEMA = pa.schema([("doc_id", pa.int64()), ("fp", pa.int64())])
_EDGE_SCHEMA = pa.schema([("a", pa.int64()), ("b", pa.int64())])

SHINGLE_WORDS = 4
BUDGET_BITS = 4
#: A node with more distinct fingerprints than this is cut by segments of its other bits, ``LEVELS`` times in all. Below the
#: last level some 31 of 64 bits are shared, and at most 46,000 fingerprints lie within four bits of any one there.
BLOCK_ROWS, LEVELS = 20_000, 3
#: Keys of crowded nodes that are sent to every task; more of them are joined by a shuffle.
BROADCAST_KEYS = 100_000


def shingle_hashes(text: str | None, width: int = SHINGLE_WORDS, seed: int = 42) -> list[int]:
    """XXH64 of every run of ``width`` words, repeats included; the whole sequence where there are fewer words."""
    words = ascii_words(text, lower=True)
    if not words:
        return []
    joined = b" ".join(words)
    if len(words) <= width:
        return [xxhash.xxh64_intdigest(joined, seed)]
    lens = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(lens + 1) - 1
    digest = xxhash.xxh64_intdigest
    return [digest(joined[i:j], seed) for i, j in zip((ends - lens)[: 1 - width].tolist(), ends[width - 1 :].tolist(), strict=True)]


def majority_bits(hashes: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """One fingerprint for each consecutive run of ``counts[i]`` hashes: the bits set in over half of them; none: 0."""
    out = np.zeros(len(counts), np.uint64)
    full = np.flatnonzero(counts)
    if not len(full):
        return out
    n = counts[full]
    parts = -(-n // 255)  # a byte lane holds at most 255
    first = np.cumsum(n) - n
    step = np.arange(parts.sum()) - np.repeat(np.cumsum(parts) - parts, parts)
    lanes = np.add.reduceat(_LANES[hashes.view(np.uint8).reshape(-1, 8)], np.repeat(first, parts) + 255 * step, axis=0)
    sums = np.add.reduceat(lanes.view(np.uint8).reshape(-1, 64).astype(np.int64), np.cumsum(parts) - parts, axis=0)
    out[full] = np.packbits(2 * sums > n[:, None], axis=1, bitorder="little").view("<u8")[:, 0]
    return out


def _fingerprint_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for ids, texts in pieces(batches, 1_000_000):
        hashes: list[int] = []
        counts = np.zeros(len(texts), np.int64)
        for i, text in enumerate(texts):
            own = shingle_hashes(text)
            counts[i] = len(own)
            hashes += own
        fps = majority_bits(np.array(hashes, np.uint64), counts)
        yield record(_FP_SCHEMA, ids, fps.view(np.int64))


def fingerprints(docs: DataFrame) -> DataFrame:
    """``documents`` -> ``(doc_id, fp long)``. Null and empty texts have fingerprint zero."""
    return documents_of(docs).mapInArrow(lambda it: tidy(_fingerprint_batches(it)), "doc_id long, fp long")


def trie_pairs(group: np.ndarray, values: np.ndarray, budget: int, known: np.ndarray | None = None, *, leaf: int = 64, chunk: int = 1 << 16) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs (i, j) of one group whose values differ in at most ``budget`` bits, by walking the trie with itself.

    ``group`` and ``values`` (uint64) are sorted by (group, value) and distinct. A trie node is an interval of the sorted
    values. ``known`` may give labels of vertices already linked: a pair of nodes under one label is not gone into. At most
    ``chunk`` pairs of nodes go down together and the deepest go first, so that few wait at any time.
    """
    n = len(values)
    starts = np.flatnonzero(np.r_[True, group[1:] != group[:-1]]).astype(np.int32) if n else np.zeros(0, np.int32)
    ends = np.r_[starts[1:], np.int32(n)].astype(np.int32)
    run_end = None
    if known is not None and n:
        cut = np.flatnonzero(np.r_[known[1:] != known[:-1], True]) + 1
        run_end = np.repeat(cut, np.diff(np.r_[0, cut])).astype(np.int32)
    ones: dict[int, np.ndarray] = {}

    def middle(lo, hi, depth):
        if depth not in ones:
            ones[depth] = np.r_[np.int32(0), np.cumsum((values >> np.uint64(63 - depth)) & np.uint64(1), dtype=np.int32)]
        c = ones[depth]
        return hi - (c[hi] - c[lo])

    stack = [(0, starts, ends, starts, ends, np.zeros(len(starts), np.int8))]
    while stack:
        depth, *nodes = stack.pop()
        if len(nodes[0]) > chunk:  # the rest waits
            stack.append((depth, *(x[chunk:].copy() for x in nodes)))
            nodes = [x[:chunk] for x in nodes]
        a0, a1, b0, b1, err = nodes
        live = (a1 > a0) & (b1 > b0) & (err <= budget) & ~((a0 == b0) & (a1 - a0 == 1))
        if run_end is not None:
            i, j = np.minimum(a0, n - 1), np.minimum(b0, n - 1)
            live &= ~((run_end[i] >= a1) & (run_end[j] >= b1) & (known[i] == known[j]))
        a0, a1, b0, b1, err = (x[live] for x in (a0, a1, b0, b1, err))
        if not len(a0):
            continue
        size = (a1 - a0).astype(np.int64) * (b1 - b0)
        small = (size <= leaf) | (depth >= 64)
        if small.any():
            order = np.flatnonzero(small)
            for at in range(0, len(order), max(1, chunk // leaf)):
                o = order[at : at + max(1, chunk // leaf)]
                count = size[o]
                k = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
                wide = np.repeat(b1[o] - b0[o], count)
                i, j = np.repeat(a0[o], count) + k // wide, np.repeat(b0[o], count) + k % wide
                hit = (np.bitwise_count(values[i] ^ values[j]) <= budget) & (i != j)
                if hit.any():
                    yield i[hit], j[hit]
        big = ~small
        if not big.any():
            continue
        a0, a1, b0, b1, err = (x[big] for x in (a0, a1, b0, b1, err))
        am, bm, same = middle(a0, a1, depth), middle(b0, b1, depth), a0 == b0
        other = ~same  # of a node with itself, one of the two mixed pairs is enough
        high = err < budget  # mixed pairs differ in one more bit
        cross = other & high
        stack.append((depth + 1, np.r_[a0, am, a0[high], am[cross]], np.r_[am, a1, am[high], a1[cross]], np.r_[b0, bm, bm[high], b0[cross]], np.r_[bm, b1, b1[high], bm[cross]], np.r_[err, err, err[high] + 1, err[cross] + 1]))


#: Links that are held before they are taken into the forest.
WAITING = 250_000


def link_forest(group: np.ndarray, values: np.ndarray, reps: np.ndarray, budget: int) -> tuple[np.ndarray, np.ndarray]:
    """Spanning forest, as (rep, rep), of the links inside the groups. Small budgets go first: what they link is skipped later."""
    order = np.lexsort((values, group))
    group, values, reps = group[order], values[order], reps[order]
    fresh = np.r_[True, (group[1:] != group[:-1]) | (values[1:] != values[:-1])] if len(values) else np.zeros(0, bool)
    group, values, reps = group[fresh], values[fresh], reps[fresh]
    everyone = np.arange(len(values))
    label = everyone
    for most in sorted({1, 2, budget} & set(range(budget + 1))):
        start, held, waiting = label, [], 0

        def settle() -> None:
            nonlocal label
            x, y = (np.concatenate([h[side] for h in held]) for side in (0, 1))
            member, root = _forest(np.r_[label[x], everyone], np.r_[label[y], label])
            label = everyone.copy()
            label[member] = root

        for i, j in trie_pairs(group, values, most, start):
            apart = label[i] != label[j]
            held.append((i[apart], j[apart]))
            waiting += int(apart.sum())
            if waiting > WAITING:
                settle()
                held, waiting = [], 0
        if held:
            settle()
    off = label != everyone
    return reps[off], reps[label[off]]


def _join_partition(batches: Iterator[pa.RecordBatch], budget: int, most: int = 100_000) -> Iterator[pa.RecordBatch]:
    """Rows (key, value, rep) sorted by key: whole groups are gathered up to ``most`` rows and joined."""
    keys, values, reps, n = [], [], [], 0

    def flush(k, v, r):
        a, b = link_forest(k, v.view(np.uint64), r, budget)
        return record(_EDGE_SCHEMA, a, b)

    for batch in batches:
        k, v, r = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(3))
        if not len(k):
            continue
        if n + len(k) >= most:
            keys, values, reps = [np.concatenate([*keys, k])], [np.concatenate([*values, v])], [np.concatenate([*reps, r])]
            cut = int(np.searchsorted(keys[0], keys[0][-1]))  # the last group may go on
            if cut:
                yield flush(keys[0][:cut], values[0][:cut], reps[0][:cut])
                keys, values, reps = [keys[0][cut:]], [values[0][cut:]], [reps[0][cut:]]
            n = len(keys[0])
        else:
            keys.append(k), values.append(v), reps.append(r)
            n += len(k)
    if n:
        yield flush(np.concatenate(keys), np.concatenate(values), np.concatenate(reps))


def _cut(rows: DataFrame, budget: int) -> DataFrame:
    """Each row of (rep, key, fixed, value) once for each segment of its bits below the first ``fixed`` ones: the segment comes next and belongs to the key."""
    n, width = budget + 1, F.lit(64) - F.col("fixed")
    rows = rows.select("rep", "key", "fixed", "value", F.explode(F.array(*map(F.lit, range(n)))).alias("s"))
    rows = rows.withColumn("at", F.floor(width * F.col("s") / n).cast("int")).withColumn("size", (F.floor(width * (F.col("s") + 1) / n)).cast("int") - F.col("at"))
    low = "(value & shiftrightunsigned(-1L, fixed))"
    turned = F.expr(f"(value & ~shiftrightunsigned(-1L, fixed)) | ((shiftleft({low}, at) | shiftrightunsigned({low}, 64 - fixed - at)) & shiftrightunsigned(-1L, fixed))")
    rows = rows.select("rep", "key", "s", (F.col("fixed") + F.col("size")).alias("fixed"), turned.alias("value"))
    # two keys under one hash would only mean more to compare
    return rows.select("rep", F.xxhash64("key", "s", F.expr("shiftrightunsigned(value, 64 - fixed)")).alias("key"), "fixed", "value")


def hamming_components(classes: DataFrame, scratch: Scratch, *, budget: int = BUDGET_BITS, block_rows: int = BLOCK_ROWS, levels: int = LEVELS) -> DataFrame:
    """``classes(fp long, rep long)``, fingerprints distinct and reps not null -> ``(id, component_id)`` of the linked reps."""
    rows = _cut(classes.select("rep", F.lit(0).cast("long").alias("key"), F.lit(0).alias("fixed"), F.col("fp").alias("value")), budget)
    settled = None
    for _ in range(levels - 1):
        crowded = scratch.keep(rows.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > block_rows).select(F.col("key").alias("crowded")))
        if not (keys := crowded.count()):
            break
        side = F.broadcast(crowded) if keys <= BROADCAST_KEYS else crowded
        calm = rows.join(side, F.col("key") == F.col("crowded"), "left_anti")
        settled = calm if settled is None else settled.union(calm)
        rows = _cut(rows.join(side, F.col("key") == F.col("crowded"), "left_semi"), budget)
    if settled is not None:
        rows = settled.union(rows)
    rows = rows.select("key", "value", "rep").repartition(shuffle_partitions(scratch.spark), "key").sortWithinPartitions("key")
    edges = rows.mapInArrow(lambda it: tidy(_join_partition(it, budget)), "a long, b long")
    return components(edges, scratch, are_forests=True)


def simhash_dedup(docs: DataFrame, *, budget: int = BUDGET_BITS, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """``documents`` -> ``(doc_id, fingerprint, component_id)``, one row for each input row.

    Fingerprints link at ``budget`` or fewer differing bits; ``component_id`` is the smallest ``doc_id`` reachable, itself
    included. Null and empty texts: fingerprint zero, linked like any other. Repeated rows come back as often as they
    came. A null ``doc_id`` takes no part in the choice of the smallest, and gets the component of its fingerprint (null if
    no row with an id reaches it). An empty table gives an empty result. Columns other than doc_id and text are not read.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "simhash")
    fps = scratch.keep(fingerprints(docs))
    classes = scratch.keep(fps.groupBy("fp").agg(F.min("doc_id").alias("rep")))
    linked = hamming_components(classes.where("rep is not null"), scratch, budget=budget, block_rows=block_rows)
    classes = classes.join(linked, classes.rep == linked.id, "left").select("fp", F.coalesce("component_id", "rep").alias("component_id"))
    return fps.join(classes, "fp").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
