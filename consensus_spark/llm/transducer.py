"""A byte-pair tokenizer compiled to a finite-state transducer over bytes.

The transducer reads the bytes of one pre-token.  Its state stands for all that
later merges can depend on: the longest suffix read that starts some vocabulary
token, and, at each cut inside that suffix, the last token of the encoding up to
the cut with the number of tokens emitted there relative to now.  The next last
token is the one suffix token that fits its left neighbour; the transition is
annotated with the change in the number of emitted tokens.  Transitions are
compiled when first met and kept in arrays, so whole batches of pre-tokens advance
one byte per vector operation.  The last byte of a pre-token is read as a symbol of
its own (it carries the end-of-word mark).
"""

from __future__ import annotations

import json
import struct
from typing import NamedTuple

import numpy as np

# Contractions that the pre-tokenizer cuts off whole.
CONTRACTIONS = (b"'s", b"'t", b"'re", b"'ve", b"'m", b"'ll", b"'d")
SPECIAL_MARK = "<|"
MAX_STATES = 300_000


def byte_symbols() -> list[str]:
    """The printable character that byte-level vocabularies write for each byte."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    symbol, spare = {b: chr(b) for b in shown}, 256
    for b in range(256):
        if b not in symbol:
            symbol[b] = chr(spare)
            spare += 1
    return [symbol[b] for b in range(256)]


class Bpe:
    """Vocabulary, merges and the fit of neighbouring tokens.

    A symbol string is a tuple of ints: byte b, or 256 + b for a byte that ends its
    pre-token.
    """

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        back = {c: b for b, c in enumerate(byte_symbols())}
        suffix = model["end_of_word_suffix"]

        def spell(token: str) -> tuple[int, ...] | None:
            last = token.endswith(suffix) and len(token) > len(suffix)
            body = token[: -len(suffix)] if last else token
            if not all(c in back for c in body):
                return None
            out = [back[c] for c in body]
            if last:
                out[-1] += 256
            return tuple(out)

        self.id_of: dict[tuple[int, ...], int] = {}
        self.spelling: dict[int, tuple[int, ...]] = {}
        by_name = {}
        for name, i in model["vocab"].items():
            if (s := spell(name)) is not None:
                self.id_of[s], self.spelling[i], by_name[name] = i, s, i
        self.rank: dict[tuple[int, int], tuple[int, int]] = {}
        self.halves: dict[int, tuple[int, int]] = {}
        for r, (a, b) in enumerate(model["merges"]):
            whole = by_name.get(a + b)
            if a in by_name and b in by_name and whole is not None:
                self.rank[by_name[a], by_name[b]] = (r, whole)
        self._fits: dict[int, bool] = {}
        self.starts = {s[:n] for s in self.id_of for n in range(1, len(s) + 1)}

    def encode(self, symbols: tuple[int, ...]) -> tuple[int, ...]:
        """Merge by rank until nothing merges: the definition, used on short strings."""
        ids = [self.id_of[(s,)] for s in symbols]
        while len(ids) > 1:
            best = min(
                ((self.rank[p][0], i) for i, p in enumerate(zip(ids, ids[1:], strict=False)) if p in self.rank),
                default=None,
            )
            if best is None:
                break
            pair = (ids[best[1]], ids[best[1] + 1])
            whole, out, i = self.rank[pair][1], [], 0
            while i < len(ids):
                if i + 1 < len(ids) and (ids[i], ids[i + 1]) == pair:
                    out.append(whole)
                    i += 2
                else:
                    out.append(ids[i])
                    i += 1
            ids = out
        return tuple(ids)

    def fits(self, left: int, right: int) -> bool:
        """Whether the two tokens stand next to each other in an encoding."""
        key = left << 32 | right
        if key not in self._fits:
            both = self.encode(self.spelling[left] + self.spelling[right])
            self._fits[key] = both == (left, right)
        return self._fits[key]

    def whole(self, token: int) -> bool:
        key = -1 - token
        if key not in self._fits:
            self._fits[key] = self.encode(self.spelling[token]) == (token,)
        return self._fits[key]


class _State(NamedTuple):
    suffix: tuple[int, ...]
    #: at each cut from the suffix's start to its end: last token before it (-1: none
    #: read yet; -2: no token can go on from here) and tokens emitted there minus now
    cuts: tuple[tuple[int, int], ...]

    def packed(self) -> bytes:
        """A compact key; hundreds of thousands of states are held."""
        flat = [v for c in self.cuts for v in c]
        return struct.pack(f"<H{len(self.suffix)}H{len(flat)}i", len(self.suffix), *self.suffix, *flat)

    @staticmethod
    def unpacked(key: bytes) -> _State:
        n = int.from_bytes(key[:2], "little")
        v = struct.unpack(f"<H{n}H{2 * n + 2}i", key)
        return _State(v[1 : n + 1], tuple(zip(v[n + 1 :: 2], v[n + 2 :: 2], strict=True)))


class Transducer:
    """Lazily compiled states; ``next``, ``emit`` and ``last`` are the tables."""

    def __init__(self, bpe: Bpe, max_states: int = MAX_STATES):
        self.bpe, self.max_states = bpe, max_states
        self.column = np.full(512, -1, np.int64)
        self.width = 0
        self._clear()

    def _clear(self) -> None:
        self.states: list[bytes] = []
        self.number: dict[bytes, int] = {}
        rows = 1 << 12
        self.next = np.full((rows, max(self.width, 64)), -1, np.int32)
        self.emit = np.zeros((rows, max(self.width, 64)), np.int8)
        self.last = np.zeros(rows, np.int32)
        self.last_len = np.zeros(rows, np.int32)
        self._state(_State((), ((-1, 0),)), -1)

    def _state(self, s: _State, last: int) -> int:
        key = s.packed()
        n = self.number.get(key)
        if n is None:
            n = self.number[key] = len(self.states)
            self.states.append(key)
            if n >= len(self.next):
                grow = lambda x, v: np.concatenate([x, np.full_like(x[: len(x) // 4], v)])
                self.next, self.emit = grow(self.next, -1), grow(self.emit, 0)
                self.last, self.last_len = grow(self.last, 0), grow(self.last_len, 0)
            self.last[n] = last
            self.last_len[n] = len(self.bpe.spelling[last]) if last >= 0 else 0
        return n

    def _column(self, symbol: int) -> int:
        c = self.column[symbol]
        if c < 0:
            c = self.column[symbol] = self.width
            self.width += 1
            if self.width > self.next.shape[1]:
                wide = lambda x, v: np.concatenate([x, np.full_like(x[:, :16], v)], axis=1)
                self.next, self.emit = wide(self.next, -1), wide(self.emit, 0)
        return int(c)

    def _connect(self, state: int, symbol: int, to: int, step: int) -> None:
        column = self._column(symbol)
        self.next[state, column], self.emit[state, column] = to, step

    def compile(self, state: int, symbol: int) -> None:
        """Add one transition: find the suffix token that fits its left neighbour."""
        s, bpe = _State.unpacked(self.states[state]), self.bpe
        read = (*s.suffix, symbol)
        for cut, (left, ago) in enumerate(s.cuts):
            token = bpe.id_of.get(read[cut:])
            if token is None or left == -2 or not (bpe.whole(token) if left < 0 else bpe.fits(left, token)):
                continue
            step = ago + 1
            if symbol >= 256:  # nothing follows: only the last token is left to know
                self._connect(state, symbol, self._state(_State((), ((token, 0),)), token), step)
                return
            cuts = [*((t, a - step) for t, a in s.cuts), (token, 0)]
            drop = next(i for i in range(len(read) + 1) if read[i:] in bpe.starts or i == len(read))
            # a cut is forgotten once no token can begin there and go on
            live = tuple(
                c if i == len(read) or read[i:] in bpe.starts else (-2, 0)
                for i, c in enumerate(cuts[drop:], drop)
            )
            self._connect(state, symbol, self._state(_State(read[drop:], live), token), step)
            return
        raise ValueError(f"no token ends an encoding of {read}")

    def refresh(self) -> None:
        """Forget all states if they have become too many."""
        if len(self.states) > self.max_states:
            self._clear()

    def run(self, data: np.ndarray, start: np.ndarray, length: np.ndarray, keep: bool = False):
        """Tokens of each whole pre-token; with ``keep`` also the state after every byte."""
        self.refresh()
        count, _, trail = self.advance(data, start, length, np.zeros(len(start), np.int64), np.ones(len(start), bool), keep)
        return count, trail

    def advance(self, data, start, length, entry, closes, keep: bool = False):
        """Emitted tokens and exit state of each run of bytes, entered in state ``entry``.

        ``closes``: whether the run's last byte ends its pre-token.  All runs advance
        together, longest first, so those still running are a prefix.  State numbers
        hold until ``refresh``.
        """
        order = np.argsort(-length, kind="stable")
        at, size = start[order], length[order]
        running = np.searchsorted(-size, -np.arange(int(size[0]) if len(size) else 0), side="left")
        state = entry[order]
        ends = np.where(closes[order], size, 0)
        count = np.zeros(len(at), np.int64)
        trail = np.zeros(len(data), np.int32) if keep else None
        for j, n in enumerate(running):
            symbol = data[at[:n] + j].astype(np.int64)
            symbol[ends[:n] == j + 1] += 256
            here = state[:n]
            column = self.column[symbol]
            to = np.where(column < 0, -1, self.next[here, column])
            if (missing := to < 0).any():
                for k in np.unique(here[missing] * 512 + symbol[missing]):
                    self.compile(int(k) >> 9, int(k) & 511)
                column = self.column[symbol]
                to = self.next[here, column]
            count[:n] += self.emit[here, column]
            state[:n] = to
            if keep:
                trail[at[:n] + j] = to
        out, exits = np.empty_like(count), np.empty_like(count)
        out[order], exits[order] = count, state
        return out, exits, trail

    def tokens(self, data: np.ndarray, start: np.ndarray, length: np.ndarray):
        """Ids of all pre-tokens end to end, and how many each has."""
        count, trail = self.run(data, start, length, keep=True)
        border = np.cumsum(count)
        ids = np.empty(int(border[-1]) if len(border) else 0, np.int32)
        put, at = border - 1, start + length - 1
        live = np.arange(len(start))
        while len(live):  # walk each encoding back from its last token
            state = trail[at[live]]
            ids[put[live]] = self.last[state]
            at[live] -= self.last_len[state]
            put[live] -= 1
            live = live[at[live] >= start[live]]
        return ids, count


# Byte classes of the vectorised pre-tokenizer.
_SPACE, _LETTER, _DIGIT, _OTHER, _UNSAFE = range(5)
_CLASS = np.full(256, _UNSAFE, np.uint8)
_CLASS[0x21:0x7F] = _OTHER
_CLASS[[0x20, 0x09, 0x0A, 0x0D]] = _SPACE
_CLASS[ord("0") : ord("9") + 1] = _DIGIT
for _first in (ord("A"), ord("a")):
    _CLASS[_first : _first + 26] = _LETTER
_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[ord("A") : ord("Z") + 1] += 32


def pretokens(data: np.ndarray, off: np.ndarray):
    """Lower-cased bytes, pre-token starts and lengths, and which texts are unsafe.

    Safe texts consist of ASCII printing characters, blanks, line ends and the
    letters of U+00C0-U+00FF; there normalisation and classes are known byte by
    byte.  Other texts go to the library.
    """
    kind, low = _CLASS[data], _FOLD[data]
    lead = np.flatnonzero(data == 0xC3)
    if len(lead):
        tail = np.minimum(lead + 1, len(data) - 1)
        second = data[tail]
        good = (second >= 0x80) & (second < 0xC0) & (second != 0x97) & (second != 0xB7) & (tail > lead)
        lead, tail, second = lead[good], tail[good], second[good]
        kind[lead] = kind[tail] = _LETTER
        low[tail] = np.where(second < 0x9F, second + 0x20, second)  # capital to small
    unsafe = np.zeros(len(off) - 1, bool)
    if (bad := np.flatnonzero(kind == _UNSAFE)).size:
        unsafe[np.searchsorted(off, bad, side="right") - 1] = True
    if (mark := np.flatnonzero((data[:-1] == 0x3C) & (data[1:] == 0x7C))).size:
        unsafe[np.searchsorted(off, mark, side="right") - 1] = True
    new = np.ones(len(data), bool)
    new[1:] = (kind[1:] != kind[:-1]) | (kind[1:] == _DIGIT)
    inner = off[:-1][off[:-1] < len(data)]
    new[inner] = True
    start = np.flatnonzero(new)
    length = np.diff(np.append(start, len(data)))
    real = kind[start] != _SPACE
    start, length = start[real], length[real]
    # a lone apostrophe takes the contraction that follows it
    lone = np.flatnonzero((data[start] == 0x27) & (length == 1))
    lone = lone[lone + 1 < len(start)]
    text_end = off[np.searchsorted(off, start[lone], side="right")] if len(lone) else off[:0]
    cut = np.zeros(len(start), np.int64)
    for i, end in zip(lone, text_end, strict=True):
        a = start[i]
        for c in CONTRACTIONS:
            if a + len(c) <= end and low[a : a + len(c)].tobytes() == c:
                cut[i] = len(c) - 1
                break
    if cut.any():
        length = length + cut
        after = np.concatenate([[0], cut[:-1]])
        start, length = start + after, length - after
        real = length > 0
        start, length = start[real], length[real]
    return low, start, length, unsafe
