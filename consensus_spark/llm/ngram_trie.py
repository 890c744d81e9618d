"""Elias-Fano n-gram tries with quantised smoothed probabilities, and LM scoring.

A trie level holds, for each context, the words seen after it.  Contexts, the
monotone pointers to their ranges and the words (numbered relative to their
context, so the whole level rises) are Elias-Fano sequences, kept packed as they lie
in the file, with a count of ones per 64 bits to select by; probabilities and
back-off weights are codes of a uniform book of logarithms, rounded down.  Levels
are written to one file and memory-mapped; a query is a successor search for the
context and another for the word inside the range between the context's pointers.
Contexts are hashed whole at every level, so a common word's longer contexts lie in
many shards; levels are not linked to each other.

The trie is cut by hash of the context.  Document blocks send each shard their
distinct n-grams with training counts; the shard builds its trie from them and
answers every n-gram from the mapped levels, so no machine holds the whole model.
Words are not counted apart: every word of a text is followed by a token, so its count is
the total of its bigram context, and the end token's is that of the text's beginning.

Smoothing: interpolated absolute discounting down to the unigram level, with one
discount per order from the counts of all shards; the discounted unigram mass belongs to the class of unknown words.

Defined cases: a null text is its end token alone; a null id is held out;
repeated rows are counted each; without training rows every token is unknown, with
probability one; an empty table gives no rows.
"""

from __future__ import annotations

import tempfile
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from consensus_spark.llm.blocks import (
    SHARD_KEYS,
    by_shard,
    closed,
    each_block,
    in_blocks,
    opened,
    pair_ranks,
    ragged,
    ranked,
)
from consensus_spark.llm.simhash import _LOWER
from consensus_spark.llm.textbytes import mixed, pack, run_hashes, unpack, words_of

ORDER = 2
QUERY_ORDER = 3
HELD_OUT_MODULUS = 10
ADDED = 0.1
WORD_BITS = 32
#: Words that messages name by their place in a common book (the others by their hash), and
#: about how many blocks it is taken from.  The book bears on the size of messages alone.
BOOK_WORDS = 65_535
BOOK_BLOCKS = 16
#: A block's texts; larger blocks send fewer distinct n-grams.
BLOCK_BYTES = 8_000_000
END = np.uint64(0x0E9D0E9D0E9D0E9D)
BEGIN = np.uint64(0xBE61BE61BE61BE61)
LOWEST, LEVELS = -12.0, 65535

_U = np.uint64


def quantise(p: np.ndarray) -> np.ndarray:
    """Codes 1..LEVELS of log10 p, rounded down; 0 stands for no probability."""
    with np.errstate(divide="ignore"):
        at = np.floor((np.log10(p) - LOWEST) / -LOWEST * (LEVELS - 1)) + 1
    return np.where(p > 0, np.clip(at, 1, LEVELS), 0).astype(np.uint16)


def value(code: np.ndarray) -> np.ndarray:
    p = 10.0 ** (LOWEST + (code.astype(float) - 1) / (LEVELS - 1) * -LOWEST)
    return np.where(code > 0, p, 0.0)


class Bits:
    """A packed bit string; positions of its ones and zeros by number."""

    def __init__(self, words: np.ndarray, ones: np.ndarray):
        self.words, self.ones = words, ones

    @staticmethod
    def counted(words: np.ndarray) -> Bits:
        """With the number of ones before each word."""
        before = np.zeros(len(words) + 1, np.uint32)
        np.cumsum(np.bitwise_count(words), out=before[1:], dtype=np.uint32)
        return Bits(words, before[:-1])

    def _inside(self, word: np.ndarray, i: np.ndarray) -> np.ndarray:
        """Place of one number i of each word, by halves."""
        word, at, i = word.copy(), np.zeros(len(i), np.uint8), i.astype(np.uint8)
        for half in (32, 16, 8, 4, 2, 1):
            below = np.bitwise_count(word & _U((1 << half) - 1))
            over = i >= below
            i -= below * over
            step = over * np.uint8(half)
            at += step
            word >>= step.astype(_U)
        return at.astype(np.int64)

    def one(self, i: np.ndarray) -> np.ndarray:
        """Position of one number i (from 0)."""
        w = np.searchsorted(self.ones, i.astype(np.uint32), side="right") - 1
        return 64 * w + self._inside(self.words[w], i - self.ones[w].astype(np.int64))

    def zero(self, i: np.ndarray) -> np.ndarray:
        """Position of zero number i (from 0)."""
        zeros = 64 * np.arange(len(self.words), dtype=np.int64) - self.ones.astype(np.int64)
        w = np.searchsorted(zeros, i, side="right") - 1
        return 64 * w + self._inside(~self.words[w], i - zeros[w])

    def next_zero(self, p: np.ndarray, i: np.ndarray) -> np.ndarray:
        """Position of zero number i, known to be the first from p on."""
        left = ~self.words[p >> 6] >> (p & 63).astype(_U)
        at = p + np.bitwise_count((left & (~left + _U(1))) - _U(1))
        far = np.flatnonzero(left == 0)  # a run of ones goes on into other words
        at[far] = self.zero(i[far])
        return at


class EliasFano:
    """A rising sequence above ``base``: low bits packed, high bits as gaps in unary."""

    def __init__(self, n: int, low_bits: int, base: int, low: np.ndarray, high: Bits):
        self.n, self.low_bits, self.base, self.low, self.high = n, low_bits, _U(base), low, high
        self._mask = _U((1 << low_bits) - 1)

    @staticmethod
    def encode(values: np.ndarray) -> EliasFano:
        n = len(values)
        v = values.astype(_U)
        base = int(v[0]) if n else 0
        v -= _U(base)
        spread = (int(v[-1]) if n else 0) + 1
        b = max(0, (spread // max(1, n)).bit_length() - 1)
        low = np.zeros(n * b // 64 + 2, _U)
        if b and n:
            own, bit = v & _U((1 << b) - 1), np.arange(n, dtype=np.int64) * b
            word, shift = bit >> 6, bit & 63
            first = np.flatnonzero(np.diff(word, prepend=-1))
            low[word[first]] = np.bitwise_or.reduceat(own << shift.astype(_U), first)
            over = np.flatnonzero(shift + b > 64)  # at most one value spills into a word
            low[word[over] + 1] |= own[over] >> (64 - shift[over]).astype(_U)
        top = (v >> _U(b)).astype(np.int64)
        bits = np.zeros((n + (int(top[-1]) if n else 0) + 2 + 63) // 64 * 64, np.uint8)
        bits[top + np.arange(n)] = 1
        return EliasFano(n, b, base, low, Bits.counted(np.packbits(bits, bitorder="little").view("<u8")))

    def _low_at(self, i: np.ndarray) -> np.ndarray:
        if not self.low_bits:
            return np.zeros(len(i), _U)
        bit = i * self.low_bits
        word, shift = bit >> 6, (bit & 63).astype(_U)
        over = np.where(shift > 0, self.low[word + 1] << ((_U(64) - shift) & _U(63)), _U(0))
        return ((self.low[word] >> shift) | over) & self._mask

    def at(self, i: np.ndarray) -> np.ndarray:
        """Values by position."""
        return (((self.high.one(i) - i).astype(_U) << _U(self.low_bits)) | self._low_at(i)) + self.base

    def successor(
        self, q: np.ndarray, begin: np.ndarray | None = None, end: np.ndarray | None = None
    ) -> tuple[np.ndarray, np.ndarray]:
        """Position of the first value >= q (from begin on, end if none), and whether it is q."""
        q = q.astype(_U)
        small = q < self.base
        q = np.where(small, _U(0), q - self.base)
        low = q & self._mask
        # zeros of the high part enclose the values that share q's high part
        most = 64 * len(self.high.words) - self.n - 1
        top = np.minimum((q >> _U(self.low_bits)).astype(np.int64), most)
        run = np.where(top > 0, self.high.zero(np.maximum(top - 1, 0)) + 1, 0)
        a = run - top
        z = np.maximum(np.minimum(self.high.next_zero(run, top) - top, self.n), a)
        if begin is not None:
            a, z = np.clip(a, begin, end), np.clip(z, begin, end)
        a, z = np.minimum(a, self.n), np.minimum(z, self.n)
        last = z.copy()
        while (open_ := np.flatnonzero(a < z)).size:
            mid = (a[open_] + z[open_]) >> 1
            less = self._low_at(mid) < low[open_]
            a[open_] = np.where(less, mid + 1, a[open_])
            z[open_] = np.where(less, z[open_], mid)
        hit = (a < last) & ~small
        k = np.flatnonzero(hit)
        hit[k] = self._low_at(a[k]) == low[k]
        return a, hit


@dataclass
class TrieLevel:
    """One context-to-word level; arrays may be views of a mapped file."""

    contexts: EliasFano
    pointers: EliasFano
    words: EliasFano
    probability: np.ndarray
    backoff: np.ndarray

    @staticmethod
    def build(context: np.ndarray, word: np.ndarray, count: np.ndarray, d: float) -> TrieLevel:
        """From distinct (context, word) rising together, with counts of at least one, and the order's discount."""
        new = np.ones(len(context), bool)
        new[1:] = context[1:] != context[:-1]
        rank, first = np.cumsum(new) - 1, np.flatnonzero(new)
        total = np.add.reduceat(count, first) if len(first) else np.zeros(0)
        kinds = np.diff(np.append(first, len(context)))
        return TrieLevel(
            EliasFano.encode(context[new]),
            EliasFano.encode(np.append(first, len(context))),
            EliasFano.encode((rank.astype(_U) << _U(WORD_BITS)) | word),
            quantise((count - d) / total[rank] if len(first) else np.zeros(0)),
            quantise(d * kinds / total if len(first) else np.zeros(0)),
        )

    def save(self, f) -> list[tuple]:
        """Append all arrays to an open file; the table of contents is returned."""
        toc = []
        for e in (self.contexts, self.pointers, self.words):
            toc.append((e.n, e.low_bits, int(e.base), *(_put(f, x) for x in (e.low, e.high.words, e.high.ones))))
        return [*toc, _put(f, self.probability), _put(f, self.backoff)]

    @staticmethod
    def map(path: str, toc: list[tuple]) -> TrieLevel:
        data = np.memmap(path, np.uint8, "r")
        get = lambda t, kind="<u8": data[t[0] : t[0] + t[1]].view(kind)
        parts = [EliasFano(n, b, base, get(low), Bits(get(high), get(ones, "<u4"))) for n, b, base, low, high, ones in toc[:3]]
        return TrieLevel(*parts, get(toc[3], np.uint16), get(toc[4], np.uint16))

    def look_up(self, context: np.ndarray, of: np.ndarray, word: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Codes of each word's discounted probability after ``context[of]``, and of each context's
        back-off weight (LEVELS: context unseen)."""
        c, seen = self.contexts.successor(context)
        back = np.full(len(context), LEVELS, np.uint16)
        k = np.flatnonzero(seen)
        back[k] = self.backoff[c[k]]
        begin, end = np.zeros((2, len(context)), np.int64)
        begin[k], end[k] = (self.pointers.at(c[k] + i).astype(np.int64) for i in (0, 1))
        prob = np.zeros(len(word), np.uint16)
        w = np.flatnonzero(seen[of])
        mine = of[w]
        at, hit = self.words.successor((c[mine].astype(_U) << _U(WORD_BITS)) | word[w], begin[mine], end[mine])
        prob[w[hit]] = self.probability[at[hit]]
        return prob, back


def _put(f, x: np.ndarray) -> tuple[int, int]:
    f.write(b"\0" * (-f.tell() % 8))
    at, raw = f.tell(), np.ascontiguousarray(x).tobytes()
    f.write(raw)
    return at, len(raw)


def discount(once: int, twice: int) -> float:
    return min(0.95, max(0.05, once / (once + 2 * twice))) if once + twice else 0.5


def held_out(doc_id: int | None) -> bool:
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % HELD_OUT_MODULUS == 0


_PARTS = ("size", "key", "count", "code")


def _by_count(count: np.ndarray) -> np.ndarray:
    """Numbers of a block's tokens, the most frequent first."""
    return np.argsort(-count.astype(np.int64), kind="stable")


def _close(table: pa.Table) -> bytes:
    """A block as ids, tokens per text, distinct token hashes with their counts, and the texts as places by count."""
    w = words_of(table.column("text"))
    h = run_hashes(_LOWER[w.data], w.start, w.end)
    n = table.num_rows
    token = np.full(len(h) + n, END, _U)
    token[np.arange(len(h)) + np.repeat(np.arange(n), np.diff(w.first))] = h
    key, code = ranked(token)
    count = np.bincount(code, minlength=len(key))
    place = np.empty(len(key), np.int64)
    place[_by_count(count)] = np.arange(len(key))  # small numbers for frequent tokens
    parts = [pack(np.diff(w.first) + 1, False), pack(key), pack(count, False), pack(place[code], False)]
    ids = table.column("doc_id").combine_chunks()
    return closed(pa.table({"ids": pa.array([ids.to_pylist()], pa.list_(pa.int64()))} | {c: [p] for c, p in zip(_PARTS, parts, strict=True)}))


class _Tokens:
    """Hashed tokens of a block: each text's lower-cased words, then its end."""

    def __init__(self, table: pa.Table, bits: int):
        ids = table.column("ids")[0].as_py()
        size, key, count, code = (table.column(c)[0].as_py() for c in _PARTS)
        self.ids = ids
        self.key = unpack(key)
        self.code = _by_count(unpack(count, False))[unpack(code, False).astype(np.int64)]
        self.first = np.concatenate([[0], np.cumsum(unpack(size, False).astype(np.int64))])
        self.out = np.array([held_out(i) for i in ids], bool)
        self.trains = np.repeat(~self.out, np.diff(self.first))
        self._bits = bits

    def pairs(self, order: int):
        """Distinct contexts of ``order - 1`` tokens, numbers of distinct (context, word), each token's pair."""
        token = self.key[self.code]
        back = np.zeros(len(token), _U)
        place = np.arange(len(token)) - np.repeat(self.first[:-1], np.diff(self.first))
        for k in range(1, order):
            left = np.full(len(token), BEGIN, _U)
            left[k:] = token[:-k]
            left[place < k] = BEGIN
            back = left if k == 1 else mixed(back * _U(0x9E3779B97F4A7C15) + left)
        bits = _key_bits(order, self._bits)
        context, of = ranked(back >> _U(64 - bits))
        own, word, group = pair_ranks(of, self.code)
        return context, own, word, group

    def as_contexts(self) -> np.ndarray:
        """The bigram context whose total is each distinct token's count."""
        return np.where(self.key == END, BEGIN, self.key) >> _U(64 - _key_bits(2, self._bits))


_MESSAGE = "block long, shard int, kind int, keys binary, sizes binary, words binary, rare binary, counts binary"
#: ``first``: the distinct codes after each context; ``kinds``: how many those are; ``ranks``: each pair's
#: among them; ``second``: back-off codes of contexts; ``totals``: their counts (bigrams only).
_REPLY = "block long, shard int, kind int, first binary, kinds binary, ranks binary, second binary, totals binary"
_STATS = "kind int, n long, v long, once long, twice long"
_KINDS = {"int": pa.int32(), "binary": pa.binary(), "long": pa.int64()}


def _table(schema: str, rows: list[tuple]) -> pa.Table:
    fields = [f.strip().split(" ") for f in schema.split(",")]
    cols = list(zip(*rows, strict=True)) or [[] for _ in fields]
    return pa.table({n: pa.array(c, _KINDS[t]) for (n, t), c in zip(fields, cols, strict=True)})


def _borders(own: np.ndarray, n: int) -> np.ndarray:
    """Where the pairs of each of n contexts begin."""
    return np.searchsorted(own, np.arange(n + 1))


def _often(table: pa.Table, block: int) -> pa.Table:
    """Words that occur in a block more than once, with their counts there."""
    key, count = (unpack(table.column(c)[0].as_py(), c == "key") for c in ("key", "count"))
    more = count > 1
    return pa.table({"word": (key[more] >> _U(64 - WORD_BITS)).astype(np.int64), "n": count[more].astype(np.int64)})


def _book(blocks: DataFrame, n_blocks: int) -> np.ndarray:
    """Hashes of frequent words, the most frequent first, after a place for all others."""
    some = blocks.where(F.pmod(F.xxhash64("block"), F.lit(max(1, n_blocks // BOOK_BLOCKS))) == 0)
    words = some.select("block", "body").mapInArrow(each_block(_often), "word long, n long").groupBy("word").agg(F.sum("n").alias("n"))
    top = words.orderBy(F.desc("n"), "word").limit(BOOK_WORDS).select("word").toArrow()
    return np.concatenate([np.zeros(1, _U), top.column(0).to_numpy().astype(_U)])


def _places(book: np.ndarray, word: np.ndarray) -> np.ndarray:
    """Each word's place in the book, or 0."""
    order = np.argsort(book[1:])
    had = book[1:][order]
    if not len(had):
        return np.zeros(len(word), np.int64)
    at = np.minimum(np.searchsorted(had, word), len(had) - 1)
    return np.where(had[at] == word, order[at] + 1, 0)


def _key_bits(order: int, width: int) -> int:
    """Bits that tell an order's contexts apart: more for single words, which they count."""
    return min(64, width + 8) if order == 2 else width


def _orders(order: int) -> range:
    """Orders of which pairs are sent; bigrams always, for the words' counts."""
    return range(2, max(2, order) + 1)


def _send(order: int, bits: int, width: int, book: np.ndarray):
    def send(table: pa.Table, block: int) -> pa.Table:
        t = _Tokens(table, width)
        name = t.key >> _U(64 - WORD_BITS)
        place = _places(book, name)
        rows = []
        for n in _orders(order):
            context, own, word, group = t.pairs(n)
            count = np.bincount(group, weights=t.trains, minlength=len(own))
            border = _borders(own, len(context))
            for s, cut in by_shard(context, bits, _key_bits(n, width)):
                part = slice(border[cut.start], border[cut.stop])
                at = place[word[part]]
                rows.append(
                    (block, s + (n - 1 << bits), n, pack(context[cut]), pack(np.diff(border[cut.start : cut.stop + 1]), False),
                     pack(at, False), pack(name[word[part][at == 0]], False), pack(count[part], False))
                )
        return _table(_MESSAGE, rows)

    return each_block(send)


def _gather(table: pa.Table, column: str, sort: bool = False):
    return ragged([unpack(x.as_py(), sort) for x in table.column(column)])


def _pair_totals(table: pa.Table, width: int, book: np.ndarray):
    """Contexts of all messages, their borders and sizes, distinct pairs with totals, and contexts' totals."""
    context, border = _gather(table, "keys", True)
    sizes = _gather(table, "sizes")[0].astype(np.int64)
    at, pairs = _gather(table, "words")
    word = book[at.astype(np.int64)]
    word[at == 0] = _gather(table, "rare")[0]
    key, of = ranked(context)
    names, w = ranked(word)
    own, called, group = pair_ranks(np.repeat(of, sizes), w)
    count = _gather(table, "counts")[0].astype(np.int64)
    total = np.bincount(group, weights=count, minlength=len(own)).astype(np.int64)
    after = np.bincount(own, weights=total, minlength=len(key)).astype(np.int64)
    return border, pairs, sizes, of, key, own, names[called], group, total, after


def _stats(width: int, book: np.ndarray):
    def count(table: pa.Table) -> pa.Table:
        kind = table.column("kind")[0].as_py()
        *_, pairs, contexts = _pair_totals(table, width, book)
        told = {kind: pairs} | ({1: contexts} if kind == 2 else {})
        return _table(
            _STATS,
            [(k, int(t.sum()), *(int(x.sum()) for x in (t > 0, t == 1, t == 2))) for k, t in told.items()],
        )

    return count


def _answer(width: int, book: np.ndarray):
    def answer(table: pa.Table) -> pa.Table:
        kind = table.column("kind")[0].as_py()
        blocks, shards = table.column("block").to_pylist(), table.column("shard").to_pylist()
        border, pairs, sizes, of, key, own, word, group, total, after = _pair_totals(table, width, book)
        seen = total > 0
        d = discount(*(table.column(x)[0].as_py()[kind - 1] for x in ("once", "twice")))
        with tempfile.NamedTemporaryFile() as f:
            toc = TrieLevel.build(key[own[seen]], word[seen], total[seen], d).save(f)
            f.flush()
            level = TrieLevel.map(f.name, toc)
            first, second = level.look_up(key, own, word)
            del level
        # pairs after one context share few codes, so each is sent once and pairs name theirs
        of_pair = np.repeat(np.arange(len(sizes), dtype=_U), sizes)
        code, rank = ranked((of_pair << _U(16)) | first[group])
        start = np.searchsorted(code >> _U(16), np.arange(len(sizes) + 1, dtype=_U))
        rank -= start[of_pair.astype(np.int64)]
        code &= _U(LEVELS)
        codes = [
            (code[start[b] : start[y]], np.diff(start[b : y + 1]), rank[a:z], second[of[b:y]], after[of[b:y]] if kind == 2 else None)
            for a, z, b, y in zip(pairs, pairs[1:], border, border[1:], strict=False)
        ]
        rows = [
            (block, shard, kind, *(None if part is None else pack(part, False) for part in parts))
            for block, shard, parts in zip(blocks, shards, codes, strict=True)
        ]
        return _table(_REPLY, rows)

    return answer


_RESULT = (
    "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, "
    "base_score double, score double"
)


def _score(order: int, bits: int, width: int):
    def score(table: pa.Table, replies: pa.Table) -> pa.Table:
        names = [f.strip().split(" ")[0] for f in _RESULT.split(",")]
        kinds = [pa.int64(), pa.bool_(), *[pa.int64()] * 3, pa.float64(), pa.float64()]
        if not table.num_rows:
            return pa.table([pa.array([], k) for k in kinds], names)
        t = _Tokens(opened(table.column("body")[0].as_buffer()), width)
        col = {c: replies.column(c).to_pylist() for c in ("shard", "first", "kinds", "ranks", "second", "totals")}
        at = {s: i for i, s in enumerate(col["shard"])}
        n, v, once, twice = (replies.column(c)[0].as_py() for c in ("n", "v", "once", "twice"))

        def read(shards: list[int], side: str) -> np.ndarray:
            return np.concatenate([unpack(col[side][at[s]], False) for s in shards]).astype(np.int64)

        for k in _orders(order):
            context, own, _, group = t.pairs(k)
            shards = [s + (k - 1 << bits) for s, _ in by_shard(context, bits, _key_bits(k, width))]
            if k == 2:
                c = read(shards, "totals")[np.searchsorted(context, t.as_contexts())][t.code]
                d = discount(once[0], twice[0])
                p = np.where(c > 0, (c - d) / n, d * v / n) if n else np.ones(len(c))
            if k > order:
                break
            weight = value(read(shards, "second"))
            many = read(shards, "kinds")
            first = read(shards, "first")[(np.cumsum(many) - many)[own] + read(shards, "ranks")]
            p = value(first)[group] + weight[own][group] * p
        first = t.first[:-1]
        base = np.log10((c + ADDED) / (n + ADDED * (v + 1)))
        known = np.add.reduceat((c > 0).astype(np.int64), first)
        cols = [
            t.ids,
            t.out,
            np.diff(t.first),
            known,
            np.full(len(first), n),
            np.add.reduceat(base, first),
            np.add.reduceat(np.log10(p), first),
        ]
        return pa.table([pa.array(x, k) for x, k in zip(cols, kinds, strict=True)], names)

    return score


def score_documents(
    docs: DataFrame, order: int = ORDER, shard_keys: int = SHARD_KEYS, block_bytes: int = BLOCK_BYTES
) -> DataFrame:
    """Train on rows not held out and score every row."""
    blocks, layout = in_blocks(docs, block_bytes, shard_keys, _close)
    bits, width = layout.shard_bits, layout.key_bits
    book = _book(blocks, layout.n_blocks)
    sent = blocks.select("block", "body").mapInArrow(_send(order, bits, width, book), _MESSAGE).repartition("shard")
    of = lambda k, c: F.coalesce(F.sum(F.when(F.col("kind") == k, F.col(c))), F.lit(0))
    stats = (
        sent.groupBy("shard")
        .applyInArrow(_stats(width, book), _STATS)
        .agg(
            *[of(1, c).alias(c) for c in ("n", "v")],
            *[F.array(*[of(k, c) for k in range(1, order + 1)]).alias(c) for c in ("once", "twice")],
        )
        .withColumn("_all", F.lit(0))
    )
    # stats is one row; every order's discount is known before its shards smooth
    counted = sent.withColumn("_all", F.lit(0)).join(F.broadcast(stats.select("_all", "once", "twice")), "_all")
    replies = counted.drop("_all").groupBy("shard").applyInArrow(_answer(width, book), _REPLY).withColumn("_all", F.lit(0))
    replies = replies.join(F.broadcast(stats), "_all").drop("_all")
    scored = blocks.select("block", "body").groupBy("block").cogroup(replies.groupBy("block"))
    return scored.applyInArrow(_score(order, bits, width), _RESULT)


def op4_ngram_scores(spark, sf_dir: str) -> DataFrame:
    """Trigram scores of all documents."""
    return score_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"), QUERY_ORDER)
