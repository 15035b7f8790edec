"""Byte-level BPE as a lazily determinised finite-state transducer, and a streaming decoder with a UTF-8 state machine.

The encoding of a prefix ends in one token, and that token depends only on the encoding before it: a token may follow
another exactly if the merges leave the two apart ("stable" pair). So after each byte, the only open questions are the
positions from which a longer token might still start. A transducer state is that set of positions - for each, the trie
node of the bytes since then and the tokens before it that are not yet emitted. Reading a byte moves the trie nodes,
drops dead positions, finds the one token that ends here, and emits every token on which all open positions agree. The lookahead is bounded by the longest token. States and moves are made when first met and kept.

``Transducer`` streams one piece. ``PieceEncoder`` runs many pieces through states of the same kind at once: the pieces are sorted,
so those that share a beginning share its states, the moves that a step meets for the first time are made together in arrays, and
a piece's tokens are read back from the state of its last byte.
"""

from __future__ import annotations

import base64
import hashlib
import re
from array import array
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from neargraph.llm.kernels import documents_of, pieces, record, resident
from neargraph.runtime import prepare


def load_ranks(path: str) -> dict[bytes, int]:
    """Token bytes -> rank of a rank file."""
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


def merge_by_rank(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Plain definition: merge the leftmost pair of lowest rank until none is left. Used for stable pairs and in tests."""
    parts = [piece[i : i + 1] for i in range(len(piece))]
    while len(parts) > 1:
        best = min(((ranks.get(parts[i] + parts[i + 1], 1 << 60), i) for i in range(len(parts) - 1)), default=(1 << 60, 0))
        if best[0] == 1 << 60:
            break
        i = best[1]
        parts[i : i + 2] = [parts[i] + parts[i + 1]]
    return [ranks[p] for p in parts]


_NEVER = (1 << 32) - 1
_HEAD = 6


class Transducer:
    """Encodes pieces of bytes. ``max_states`` and ``max_stable`` bound the memory: the tables start anew beyond them."""

    def __init__(self, ranks: dict[bytes, int], *, max_states: int = 100_000, max_stable: int = 200_000) -> None:
        self.ranks = ranks
        self.token_bytes = {r: t for t, r in ranks.items()}
        self.max_states, self.max_stable = max_states, max_stable
        self._step: dict[int, int] = {}  # trie node << 8 | byte -> trie node
        self._token_at: list[int] = [-1]
        self._inner: list[bool] = [True]
        for token, rank in ranks.items():
            node = 0
            for byte in token:
                self._inner[node] = True
                nxt = self._step.get(node << 8 | byte)
                if nxt is None:
                    nxt = self._step[node << 8 | byte] = len(self._token_at)
                    self._token_at.append(-1)
                    self._inner.append(False)
                node = nxt
            self._token_at[node] = rank
        missing = [b for b in range(256) if bytes([b]) not in ranks]
        if missing:
            raise ValueError(f"no token for the single bytes {missing[:5]}")
        self._edge_cache: dict[int, tuple[array, array] | None] = {}
        self._stable: dict[int, bool] = {}
        self._reset()

    def _reset(self) -> None:
        start = (-1, ((0, ()),))  # last emitted token; open positions: (trie node, tokens not yet emitted before it)
        self._states: list[tuple] = [start]
        self._ids: dict[tuple, int] = {start: 0}
        self._moves: list[dict[int, tuple[int, tuple[int, ...]]]] = [{}]
        self._missed: set[int] = set()
        self._heads: dict[bytes, tuple[int, tuple[int, ...]]] = {}

    def _edges(self, token: int) -> tuple[array, array] | None:
        """Along the right and the left edge of a token's merges, single byte first: tokens, each beside the time at which it is merged away.

        A token and its time are packed into one number, as all tokens keep their edges. None for a token that its own merges do not
        give: it is never the result of a merge.
        """
        if token in self._edge_cache:
            return self._edge_cache[token]
        piece = self.token_bytes[token]
        out = None
        last = token << 32 | _NEVER
        if len(piece) == 1:
            out = (array("Q", [last]), array("Q", [last]))
        elif (halves := self._last_merge(piece)) is not None:
            left, right = self._edges(halves[0]), self._edges(halves[1])
            if left is not None and right is not None:
                out = (right[0][:-1], left[1][:-1])
                for edge, half in zip(out, halves[::-1], strict=True):
                    edge.append(half << 32 | token)
                    edge.append(last)
        self._edge_cache[token] = out
        return out

    def _last_merge(self, piece: bytes) -> tuple[int, int] | None:
        ranks = self.ranks
        parts = [piece[i : i + 1] for i in range(len(piece))]
        while len(parts) > 2:
            best, at = _NEVER, -1
            for i in range(len(parts) - 1):
                r = ranks.get(parts[i] + parts[i + 1], _NEVER)
                if r < best:
                    best, at = r, i
            if at < 0:
                return None
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return ranks[parts[0]], ranks[parts[1]]

    def _is_stable(self, first: int, second: int) -> bool:
        """Whether the merges leave two tokens side by side: no two of their edge tokens meet and merge before they go."""
        if (got := self._stable.get(first << 32 | second)) is None:
            if len(self._stable) >= self.max_stable:
                self._stable.clear()
            ends, starts, i, j, got = self._edges(first)[0], self._edges(second)[1], 0, 0, True
            ranks, names = self.ranks, self.token_bytes
            while True:
                a, gone_a, b, gone_b = ends[i] >> 32, ends[i] & _NEVER, starts[j] >> 32, starts[j] & _NEVER
                merged = ranks.get(names[a] + names[b], _NEVER)
                if merged < gone_a and merged <= gone_b:  # of equal merges the left one goes first
                    got = False
                    break
                if gone_a == gone_b == _NEVER:
                    break
                if gone_a <= gone_b:
                    i += 1
                else:
                    j += 1
            self._stable[first << 32 | second] = got
        return got

    def _move(self, state: int, byte: int) -> tuple[int, tuple[int, ...]]:
        base, opens = self._states[state]
        step, token_at, inner = self._step, self._token_at, self._inner
        new, found = [], None
        for node, pending in opens:
            child = step.get(node << 8 | byte)
            if child is None:
                continue
            if found is None and (token := token_at[child]) >= 0 and self._edges(token) is not None:
                last = pending[-1] if pending else base
                if last < 0 or self._is_stable(last, token):
                    found = (*pending, token)
            if inner[child]:
                new.append((child, pending))
        new.append((0, found))
        # what all open positions agree on is emitted
        k, first = 0, new[0][1]
        if len(new) == 1:
            k = len(first)
        elif first:
            least = min(len(p) for _, p in new)
            while k < least and all(p[k] == first[k] for _, p in new):
                k += 1
        emitted = ()
        if k:
            emitted = first[:k]
            base = emitted[-1]
            new = [(node, p[k:]) for node, p in new]
        key = (base, tuple(new))
        got = self._ids.get(key)
        if got is None:
            got = self._ids[key] = len(self._states)
            self._states.append(key)
            self._moves.append({})
        out = self._moves[state][byte] = (got, emitted)
        return out

    def run(self, piece: bytes) -> list[int]:
        """Token ids of one piece by the merges alone.

        At a move that is not yet known, the rest of the piece is followed through the open positions themselves; the move
        is made and kept when it is missed a second time, as a state that only one piece ever visits is not worth keeping.
        The state after the first ``_HEAD`` bytes is kept by itself.
        """
        if max(len(self._states), len(self._missed) // 4, len(self._heads) // 2) > self.max_states:
            self._reset()
        moves, head = self._moves, piece[:_HEAD]
        if known := self._heads.get(head):
            state, out = known[0], list(known[1])
            at = len(head)
        else:
            state, out, at = 0, [], 0
        for at in range(at, len(piece)):
            nxt = moves[state].get(piece[at])
            if nxt is None:
                miss = state << 8 | piece[at]
                if miss not in self._missed:
                    self._missed.add(miss)
                    return out + self._follow(state, piece[at:])
                nxt = self._move(state, piece[at])
            state = nxt[0]
            if nxt[1]:
                out += nxt[1]
            if at + 1 == _HEAD:
                self._heads[head] = (state, tuple(out))
        out += self._states[state][1][-1][1]  # the open position at the end of the piece
        return out

    def _follow(self, state: int, rest: bytes) -> list[int]:
        """Tokens from a state to the end of the piece, without making states."""
        base, opens = self._states[state]
        step, token_at, inner, edges, stable = self._step.get, self._token_at, self._inner, self._edge_cache, self._stable.get
        live = []
        for node, pending in opens:
            chain = None
            for token in pending:
                chain = (token, chain)
            live.append((node, chain))
        for byte in rest:
            new, found = [], None
            for node, chain in live:
                child = step(node << 8 | byte)
                if child is None:
                    continue
                if found is None and (token := token_at[child]) >= 0 and (edges.get(token) or self._edges(token)) is not None:
                    last = chain[0] if chain else base
                    if last < 0 or ((apart := stable(last << 32 | token)) is None and self._is_stable(last, token)) or apart:
                        found = (token, chain)
                if inner[child]:
                    new.append((child, chain))
            new.append((0, found))
            live = new
        out, chain = [], live[-1][1]
        while chain is not None:
            out.append(chain[0])
            chain = chain[1]
        return out[::-1]

    def encode_piece(self, piece: bytes) -> list[int]:
        """As ``run``; a piece that is itself a token gives that token, even one that merges cannot reach."""
        if not piece:
            return []
        whole = self.ranks.get(piece)
        return [whole] if whole is not None else self.run(piece)


class PieceEncoder:
    """The transducer for many pieces at a time. A state stands for a beginning of pieces and holds the trie node and the state of origin
    of each open position; beside it stands the token that ends there and the state before that token. States and moves are made in
    arrays when first met and serve later batches, until there are more than ``max_states``; then the table starts anew.
    """

    def __init__(self, own: Transducer, *, max_states: int = 250_000) -> None:
        self.own, self.max_states = own, max_states
        edges = np.fromiter(own._step.keys(), np.int64, len(own._step))
        order = np.argsort(edges)
        self._edges = edges[order]
        self._child = np.fromiter(own._step.values(), np.int32, len(own._step))[order]
        self._token = np.array([t if t < 0 or own._edges(t) is not None else -1 for t in own._token_at], np.int32)
        self._inner = np.array(own._inner)
        self._reset()

    def _reset(self) -> None:
        self._n = 1
        # by state: the token that ends here (-1: none yet), the state before it, where its open positions stand
        self._last, self._origin = np.full(1024, -1, np.int32), np.zeros(1024, np.int32)
        self._first, self._opens = np.zeros(1024, np.int64), np.zeros(1024, np.int32)
        self._opens[0] = 1
        self._held = 1
        self._node, self._from = np.zeros(4096, np.int32), np.zeros(4096, np.int32)  # state 0: at the root, since itself
        self._moves: dict[int, int] = {}

    @staticmethod
    def _room(x: np.ndarray, n: int) -> np.ndarray:
        return x if n <= len(x) else np.concatenate([x, np.zeros(max(len(x) // 2, n - len(x)), x.dtype)])

    def _apart(self, first: np.ndarray, second: np.ndarray) -> np.ndarray:
        """Whether each pair of tokens stays apart; the start of a piece (-1) leaves everything apart."""
        keys = first.astype(np.int64) << 32 | second
        out = np.fromiter(map(self.own._stable.get, keys.tolist(), repeat(2)), np.int8, len(keys))
        out[first < 0] = 1
        for i in np.flatnonzero(out == 2).tolist():
            out[i] = self.own._is_stable(int(first[i]), int(second[i]))
        return out == 1

    def _make(self, states: np.ndarray, byte: np.ndarray) -> int:
        """Makes the states that given (state, byte) lead to; the number of the first one. All are live: every byte is a token."""
        n, count, begin = len(states), self._opens[states].astype(np.int64), self._n
        row = np.repeat(np.arange(n), count)
        at = np.arange(len(row)) + np.repeat(self._first[states] - (np.cumsum(count) - count), count)
        key, origin = self._node[at].astype(np.int64) << 8 | byte[row], self._from[at]
        place = np.minimum(np.searchsorted(self._edges, key), len(self._edges) - 1)
        alive = np.flatnonzero(self._edges[place] == key)
        row, origin, child = row[alive], origin[alive], self._child[place[alive]]
        token = self._token[child]
        ends = np.flatnonzero(token >= 0)
        good = ends[self._apart(self._last[origin[ends]], token[ends])]
        self._n += n
        self._last, self._origin, self._first, self._opens = (self._room(x, self._n) for x in (self._last, self._origin, self._first, self._opens))
        mine = begin + row[good][::-1]  # exactly one for each state, as one encoding ends here
        self._last[mine], self._origin[mine] = token[good][::-1], origin[good][::-1]
        on = self._inner[child]
        row, origin, child = row[on], origin[on], child[on]
        # its open positions, and the root from here on behind them
        count = np.bincount(row, minlength=n) + 1
        first = np.cumsum(count) - count
        held = self._held + int(count.sum())
        self._node, self._from = self._room(self._node, held), self._room(self._from, held)
        spot = self._held + np.arange(len(row)) + row
        self._node[spot], self._from[spot] = child, origin
        root = self._held + first + count - 1
        self._node[root], self._from[root] = 0, begin + np.arange(n)
        self._first[begin : self._n], self._opens[begin : self._n] = self._held + first, count
        self._held = held
        return begin

    def encode(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all pieces in a row, number of ids of each). Pieces are not empty."""
        if self._n > self.max_states:
            self._reset()
        n = len(pieces)
        order = sorted(range(n), key=pieces.__getitem__)
        flat = np.frombuffer(b"".join([pieces[i] for i in order]), np.uint8)
        size = np.fromiter((len(pieces[i]) for i in order), np.int64, n)
        begin = np.cumsum(size) - size
        state = np.zeros(n, np.int32)
        live, step, old = np.arange(n), 0, self._n
        while len(live):
            key = state[live].astype(np.int64) << 8 | flat[begin[live] + step]
            new = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])  # sorted pieces: equal beginnings stand side by side
            distinct, shared = key[new], np.diff(np.r_[new, len(key)]) > 1
            to = np.full(len(distinct), -1, np.int32)
            before = np.flatnonzero(distinct >> 8 < old)  # only older states can have moves
            to[before] = np.fromiter(map(self._moves.get, distinct[before].tolist(), repeat(-1)), np.int32, len(before))
            unknown = np.flatnonzero(to < 0)
            if len(unknown):
                missed = distinct[unknown]
                made = self._make(missed >> 8, missed & 255)
                to[unknown] = np.arange(made, made + len(missed))
                kept = unknown[shared[unknown]]  # a move that one piece alone takes is not worth keeping
                self._moves.update(zip(distinct[kept].tolist(), to[kept].tolist(), strict=True))
            state[live] = np.repeat(to, np.diff(np.r_[new, len(key)]))
            step += 1
            live = live[size[live] > step]
        back = []  # (piece, token) from the last token of each piece to its first
        row, s = np.arange(n), state
        while len(row):
            back.append((row, self._last[s]))
            s = self._origin[s]
            going = s > 0
            row, s = row[going], s[going]
        rows = np.concatenate([r for r, _ in back[::-1]]) if back else np.zeros(0, np.int64)
        tokens = np.concatenate([t for _, t in back[::-1]]) if back else np.zeros(0, np.int32)
        given = np.asarray(order, np.int64)[rows]
        return tokens[np.argsort(given, kind="stable")], np.bincount(given, minlength=n)


class Utf8Machine:
    """Incremental UTF-8 decoding: bytes in any cut, whole characters out; unfinished characters wait for more bytes.

    States count the continuation bytes to come and bound the next one (overlong forms, surrogates and values beyond
    the last plane are errors). Well-formed stretches go through in bulk: only the tail of a cut is stepped by the machine.
    """

    #: Lead byte ranges: (first, last, bytes to come, least and greatest next byte). Fixed values of the UTF-8 format.
    LEADS = [
        (0xC2, 0xDF, 1, 0x80, 0xBF), (0xE0, 0xE0, 2, 0xA0, 0xBF), (0xE1, 0xEC, 2, 0x80, 0xBF), (0xED, 0xED, 2, 0x80, 0x9F), (0xEE, 0xEF, 2, 0x80, 0xBF),
        (0xF0, 0xF0, 3, 0x90, 0xBF), (0xF1, 0xF3, 3, 0x80, 0xBF), (0xF4, 0xF4, 3, 0x80, 0x8F),
    ]

    def __init__(self) -> None:
        self._lead = {b: (more, low, high) for first, last, more, low, high in self.LEADS for b in range(first, last + 1)}
        self._held = b""

    def _unfinished(self, data: bytes) -> int:
        """Length of the unfinished character at the end of ``data``: 0 to 3."""
        for back in range(1, min(3, len(data)) + 1):
            byte = data[-back]
            if byte < 0x80:
                return 0
            if byte >= 0xC0:
                more, low, high = self._lead.get(byte, (0, 0, 0))
                follow = data[len(data) - back + 1 :]
                good = all((low if i == 0 else 0x80) <= x <= (high if i == 0 else 0xBF) for i, x in enumerate(follow))
                return back if more > len(follow) and good else 0
        return 0

    def feed(self, data: bytes) -> str:
        data = self._held + data
        cut = len(data) - self._unfinished(data)
        self._held = data[cut:]
        return data[:cut].decode("utf-8", "replace")

    def close(self) -> str:
        rest, self._held = self._held, b""
        return rest.decode("utf-8", "replace")


def decode_stream(ids: Iterator[int], token_bytes: dict[int, bytes]) -> Iterator[str]:
    """Text of a stream of ids, character-complete after each id."""
    machine = Utf8Machine()
    for i in ids:
        if out := machine.feed(token_bytes[i]):
            yield out
    if out := machine.close():
        yield out


#: Characters among which letters, digits and white space mean the same to both regular expression libraries: Latin
#: without the superscript and fraction digits and without the information separators.
_PLAIN = re.compile(r"[\x00-\x1b\x20-\x84\x86-\xb1\xb4-\xb8\xba\xbb\xbf-\u02af\u2010-\u2027\u20ac]*")
_LATIN_LETTERS = r"A-Za-z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-\u02af"


def splitter(pattern: str):
    """``findall`` of a pattern; texts of plain Latin characters take the faster of two equivalent expressions."""
    find = regex.compile(pattern).findall
    if r"\p{L}" not in pattern or r"\p{N}" not in pattern:
        return find
    plain = re.compile(pattern.replace(r"[^\s\p{L}\p{N}]", rf"[^\s0-9{_LATIN_LETTERS}]").replace(r"\p{L}", rf"[{_LATIN_LETTERS}]").replace(r"\p{N}", "[0-9]")).findall
    return lambda text: plain(text) if _PLAIN.fullmatch(text) else find(text)


#: Longer pieces go through the transducer one by one, as a step in arrays serves all pieces of a batch and few are so long.
LONG_PIECE = 64


class Codec:
    """Encoder and decoder of one vocabulary, with a bounded memory of encoded pieces."""

    def __init__(self, path: str, pattern: str, *, max_pieces: int = 150_000) -> None:
        self.ranks = load_ranks(path)
        self.transducer = Transducer(self.ranks, max_states=20_000)
        self.many = PieceEncoder(self.transducer)
        self.find = splitter(pattern)
        self._finditer = regex.compile(pattern).finditer
        self.table = np.empty(max(self.ranks.values()) + 1, object)
        for token, rank in self.ranks.items():
            self.table[rank] = token
        self.max_pieces = max_pieces
        self._packed: dict[str, bytes] = {}

    def split(self, texts: list[str | None]) -> list[list[str]]:
        """Pieces of each text; all of them are known afterwards."""
        found = [self.find(t) if t else [] for t in texts]
        self._learn(set().union(*found))
        return found

    def packed(self, found: list[str]) -> bytes:
        """Ids of the pieces of a text as little-endian unsigned 32-bit integers."""
        return b"".join(map(self._packed.__getitem__, found))

    def token_counts(self, found: list[str]) -> np.ndarray:
        """Number of ids of each piece."""
        return np.fromiter(map(len, map(self._packed.__getitem__, found)), np.int64, len(found)) >> 2

    def _learn(self, wanted: set[str]) -> None:
        """Encodes the pieces that are not known. Beyond the bound the younger half goes first: common pieces come early."""
        known = self._packed
        if len(known) > self.max_pieces:
            for piece in list(known)[self.max_pieces // 2 :]:
                del known[piece]
        new = list(wanted.difference(known))
        batch, raw, ranks = [], [], self.ranks
        for piece in new:
            data = piece.encode("utf-8", "surrogatepass")
            if (whole := ranks.get(data)) is not None:
                known[piece] = whole.to_bytes(4, "little")
            elif len(data) > LONG_PIECE:
                known[piece] = array("I", self.transducer.run(data)).tobytes()
            else:
                batch.append(piece), raw.append(data)
        if batch:
            tokens, counts = self.many.encode(raw)
            flat, ends = tokens.astype("<u4").tobytes(), np.cumsum(4 * counts).tolist()
            known.update(zip(batch, [flat[a:b] for a, b in zip([0, *ends], ends, strict=False)], strict=True))

    def match(self, text: str, at: int):
        """Matches of the pattern from a place on; what stands before it is not looked at."""
        return self._finditer(text, at)

    def encode_one(self, piece: str) -> list[int]:
        return self.transducer.encode_piece(piece.encode("utf-8", "surrogatepass"))

    def encode(self, text: str | None) -> list[int]:
        return np.frombuffer(self.packed(self.split([text])[0]), "<u4").tolist()

    def decode_bytes(self, ids: np.ndarray) -> bytes:
        return b"".join(self.table[ids].tolist())

    def decode(self, ids) -> str:
        return "".join(decode_stream(iter(ids), self.transducer.token_bytes))


def codec(path: str, pattern: str) -> Codec:
    """One codec per worker process, kept between tasks."""
    return resident("bpe", (path, pattern), lambda: Codec(path, pattern))


_DIGEST = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())])
#: Characters of the texts whose pieces are encoded together.
BATCH_CHARS = 1_000_000
#: Ids that are decoded at a time; the UTF-8 machine carries a character across the cut.
DECODE_IDS = 1 << 16


def _digest_batches(batches: Iterator[pa.RecordBatch], path: str, pattern: str) -> Iterator[pa.RecordBatch]:
    own = codec(path, pattern)
    for ids, texts in pieces(batches, BATCH_CHARS):
        n, a, b = [], [], []
        for found in own.split(texts):
            packed = own.packed(found)
            tokens = np.frombuffer(packed, "<u4")
            decoded, machine = hashlib.sha256(), Utf8Machine()
            for at in range(0, len(tokens), DECODE_IDS):
                decoded.update(machine.feed(own.decode_bytes(tokens[at : at + DECODE_IDS])).encode("utf-8", "surrogatepass"))
            decoded.update(machine.close().encode())
            n.append(len(tokens)), a.append(hashlib.sha256(packed).hexdigest()), b.append(decoded.hexdigest())
        yield record(_DIGEST, ids, n, a, b)


def _id_batches(batches: Iterator[pa.RecordBatch], path: str, pattern: str) -> Iterator[pa.RecordBatch]:
    own = codec(path, pattern)
    schema = pa.schema([("doc_id", pa.int64()), ("ids", pa.list_(pa.int32()))])
    for ids, texts in pieces(batches, BATCH_CHARS):
        yield record(schema, ids, [np.frombuffer(own.packed(found), "<i4") for found in own.split(texts)])


def bpe_encode(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """``documents`` -> ``(doc_id, ids array<int>)``: the token ids of every whole text. Null text: no ids."""
    prepare(docs.sparkSession)
    return documents_of(docs).mapInArrow(lambda it: _id_batches(it, path, pattern), "doc_id long, ids array<int>")


def bpe_digests(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """``documents`` -> ``(doc_id, n_tokens, ids_sha256, decoded_sha256)``, one row for each input row.

    Each match of ``pattern`` is encoded by itself and without special tokens; then the ids are decoded again. Null and
    empty texts give no ids. Repeated rows and null ids come back as they came; other columns are not read. ``path`` must
    be readable on every executor (the vocabulary is installed with the library, never shipped).
    """
    prepare(docs.sparkSession)
    return documents_of(docs).mapInArrow(lambda it: _digest_batches(it, path, pattern), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
