"""Edit-aware token counts: a segment tree over the pre-tokens of each document.

The leaves hold the token counts of the pre-tokens, inner nodes their sums, so the root is the document's count. An edit
re-encodes only the pre-tokens that it touches and as much context as the splitting pattern can look across; behind it,
as soon as a new pre-token ends where an old one did, the old leaves serve again.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from neargraph.llm.bpe import BATCH_CHARS, Codec, codec
from neargraph.llm.kernels import documents_of, pieces, record
from neargraph.runtime import prepare

#: Characters before an edit that the splitting pattern may have looked at, white space runs aside.
LOOK = 4


class SegmentTree:
    """Sums over leaves; ``levels[0]`` are the leaves, each further level halves them."""

    def __init__(self, leaves: np.ndarray) -> None:
        self.levels = [np.asarray(leaves, np.int64)]
        while len(self.levels[-1]) > 1:
            below = self.levels[-1]
            self.levels.append(np.add.reduceat(below, np.arange(0, len(below), 2)))

    @property
    def total(self) -> int:
        return int(self.levels[-1][0]) if len(self.levels[-1]) else 0

    def __len__(self) -> int:
        return len(self.levels[0])

    def prefix(self, n: int) -> int:
        """Sum of the first ``n`` leaves, from O(log) nodes."""
        out, level = 0, 0
        while n:
            if n & 1:
                out += int(self.levels[level][n - 1])
            n >>= 1
            level += 1
        return out

    def splice(self, at: int, gone: int, new: list[int]) -> None:
        """Replaces ``gone`` leaves from ``at``. Where their number stays, only the sums above them are made anew."""
        if gone == len(new):
            self.levels[0][at : at + gone] = new
            low, high = at, at + gone
            for below, level in zip(self.levels, self.levels[1:], strict=False):
                low, high = low // 2, (high + 1) // 2
                if high > low:
                    level[low:high] = np.add.reduceat(below[2 * low : 2 * high], np.arange(0, min(2 * high, len(below)) - 2 * low, 2))
            return
        leaves = np.concatenate([self.levels[0][:at], np.asarray(new, np.int64), self.levels[0][at + gone :]])
        kept = at // 2  # nodes left of the change stay
        levels = [leaves]
        for old in [*self.levels[1:], *[np.zeros(0, np.int64)] * 2]:
            below = levels[-1]
            if len(below) <= 1:
                break
            keep = min(kept, len(old), len(below) // 2)
            levels.append(np.concatenate([old[:keep], np.add.reduceat(below[2 * keep :], np.arange(0, len(below) - 2 * keep, 2))]))
            kept = keep // 2
        while len(levels[-1]) > 1:
            levels.append(np.add.reduceat(levels[-1], np.arange(0, len(levels[-1]), 2)))
        self.levels = levels


class CountedText:
    """A text, the ends of its pre-tokens and the tree of their token counts."""

    def __init__(self, own: Codec, text: str, found: list[str] | None = None) -> None:
        self.own, self.text = own, text
        found = own.split([text])[0] if found is None else found
        self.ends = np.cumsum(np.fromiter(map(len, found), np.int64, len(found)))
        self.tree = SegmentTree(own.token_counts(found))
        self.encoded = 0

    @property
    def n_tokens(self) -> int:
        return self.tree.total

    def edit(self, start: int, end: int, new: str) -> None:
        """Replaces ``text[start:end]``. Characters outside the pre-tokens count nothing."""
        if not 0 <= start <= end <= len(self.text):
            raise ValueError("an edit lies outside the text")
        text = self.text[:start] + new + self.text[end:]
        safe = max(0, start - LOOK)
        while safe and text[safe - 1].isspace():
            safe -= 1
        if safe:
            safe -= 1
        first = bisect_left(self.ends, safe) if safe else 0  # the first pre-token that ends at or after it
        at = int(self.ends[first - 1]) if first else 0
        shift = len(new) - (end - start)
        ends, counts, last = [], [], None
        for m in self.own.match(text, at):
            stop = m.end()
            piece = m.group()
            ends.append(stop)
            counts.append(len(self.own.encode_one(piece)))
            old = stop - shift
            if stop >= start + len(new) and old >= end:
                i = bisect_left(self.ends, old)
                if i < len(self.ends) and self.ends[i] == old:
                    last = i + 1
                    break
        last = len(self.ends) if last is None else last
        self.tree.splice(first, last - first, counts)
        self.ends = np.concatenate([self.ends[:first], np.asarray(ends, np.int64), self.ends[last:] + shift])
        self.text = text
        self.encoded += len(counts)


#: The edit that the query applies: runs of three or more digits give way to one zero (numbers of people and accounts).
DIGITS = re.compile(r"[0-9]{3,}")
MASK = "0"


def digit_edits(text: str) -> list[tuple[int, int, str]]:
    return [(m.start(), m.end(), MASK) for m in DIGITS.finditer(text)]


def count_with_edits(own: Codec, text: str | None, edits: list[tuple[int, int, str]], found: list[str] | None = None) -> tuple[int, int, int, int, int]:
    """(tokens, pre-tokens, edits, tokens after them, pre-tokens encoded again); edits as places in the text as it was, not overlapping.

    ``found`` gives the pre-tokens of the text where ``Codec.split`` has been asked for them already.
    """
    counted = CountedText(own, text or "", found)
    before = counted.n_tokens, len(counted.ends)
    for start, end, new in sorted(edits, reverse=True):  # from the end, so that places hold
        counted.edit(start, end, new)
    return (*before, len(edits), counted.n_tokens, counted.encoded)


_SCHEMA = pa.schema([("doc_id", pa.int64()), *((n, pa.int64()) for n in ("n_tokens", "n_pretokens", "n_edits", "n_tokens_edited", "n_reencoded"))])


def _count_batches(batches: Iterator[pa.RecordBatch], path: str, pattern: str, edits) -> Iterator[pa.RecordBatch]:
    own = codec(path, pattern)
    for ids, texts in pieces(batches, BATCH_CHARS):
        rows = [count_with_edits(own, t, edits(t or ""), found) for t, found in zip(texts, own.split(texts), strict=True)]
        yield record(_SCHEMA, ids, *(list(c) for c in zip(*rows, strict=True)))


def edit_aware_counts(docs: DataFrame, path: str, pattern: str, edits=digit_edits) -> DataFrame:
    """``documents`` -> ``(doc_id, n_tokens, n_pretokens, n_edits, n_tokens_edited, n_reencoded)``, one row for each input row.

    ``edits`` gives the edits of a text as (start, end, replacement). Null and empty texts count 0. Repeated rows and null ids
    come back as they came; other columns are not read.
    """
    prepare(docs.sparkSession)
    return documents_of(docs).mapInArrow(lambda it: _count_batches(it, path, pattern, edits), "doc_id long, n_tokens long, n_pretokens long, n_edits long, n_tokens_edited long, n_reencoded long")
