"""Token counts by a compiled transducer over chunks, joined by a prefix scan.

A text is cut into chunks of about equal size, inside words as a rule.  A chunk's state
map takes the transducer's state at its start to the state at its end and the number of
tokens emitted on the way.  Only the bytes up to the chunk's first pre-token border
depend on the entry state; what follows is counted once.  So a map is that head, the
count behind it and the exit state; a chunk without a border is all head.  Composing
two maps runs the right one's head from the left one's exit state; composition is
associative, and a doubling scan over the chunks of each text gives its count.

Defined cases: a null text is empty and has no tokens; an empty text likewise;
repeated rows are counted each; texts with characters outside the transducer's
classes, or with the marks of special tokens, are counted by the library; an empty
table gives no rows.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from consensus_spark.llm.textbytes import flat_bytes
from consensus_spark.llm.transducer import Bpe, Transducer, pretokens

CHUNK_BYTES = 1 << 14
SLICE_BYTES = 1 << 20
LIMIT = 2048

_COMPILED: dict[str, Transducer] = {}
_LIBRARY: dict[str, object] = {}


def vocabulary_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def transducer(path: str) -> Transducer:
    """One per worker process; it keeps what it has compiled."""
    if path not in _COMPILED:
        _COMPILED[path] = Transducer(Bpe(path))
    return _COMPILED[path]


def library_ids(path: str, texts: list[str]) -> list[list[int]]:
    if path not in _LIBRARY:
        from tokenizers import Tokenizer

        _LIBRARY[path] = Tokenizer.from_file(path)
    return [_LIBRARY[path].encode(t, add_special_tokens=False).ids for t in texts]


def slices(off: np.ndarray, most: int = SLICE_BYTES):
    """Ranges of texts of about ``most`` bytes; a longer text is a range of its own."""
    a = 0
    while a < len(off) - 1:
        z = max(a + 1, int(np.searchsorted(off, off[a] + most, side="right")) - 1)
        yield a, z
        a = z


@dataclass
class Maps:
    """State maps of consecutive chunks (or runs of chunks) over the bytes ``data``.

    ``open``: no pre-token border inside, so the exit state is not known without the
    entry state.  ``closes``: the head's last byte ends its pre-token.
    """

    tr: Transducer
    data: np.ndarray
    text: np.ndarray
    head: np.ndarray
    length: np.ndarray
    closes: np.ndarray
    open: np.ndarray
    count: np.ndarray
    exit: np.ndarray

    _ARRAYS = ("text", "head", "length", "closes", "open", "count", "exit")

    def take(self, at) -> Maps:
        at = np.asarray(at, np.int64)
        return Maps(self.tr, self.data, *(getattr(self, c)[at] for c in self._ARRAYS))

    @staticmethod
    def joined(a: Maps, b: Maps) -> Maps:
        return Maps(a.tr, a.data, *(np.concatenate([getattr(a, c), getattr(b, c)]) for c in Maps._ARRAYS))

    def compose(self, right: Maps) -> Maps:
        """Maps of each left run followed by its right run."""
        emitted, after, _ = self.tr.advance(
            self.data, right.head, np.where(self.open, 0, right.length), self.exit, right.closes
        )
        # an open left run prolongs the right one's head; the heads lie side by side
        return Maps(
            self.tr,
            self.data,
            self.text,
            self.head,
            np.where(self.open, self.length + right.length, self.length),
            np.where(self.open, right.closes, self.closes),
            self.open & right.open,
            np.where(self.open, right.count, self.count + emitted + right.count),
            np.where(right.open & ~self.open, after, right.exit),
        )

    def scan(self) -> Maps:
        """Each chunk's map of all its text up to its end: after round r, of 2^r chunks."""
        done, step, n = self, 1, len(self.text)
        while step < n:
            later = np.flatnonzero(self.text[step:] == self.text[:-step]) + step
            if not len(later):
                break
            whole = done.take(later - step).compose(done.take(later))
            arrays = {c: getattr(done, c).copy() for c in Maps._ARRAYS}
            for c, v in arrays.items():
                v[later] = getattr(whole, c)
            done, step = Maps(self.tr, self.data, **arrays), step * 2
        return done


_LETTERS = np.zeros(256, bool)
for _first in (ord("A"), ord("a")):
    _LETTERS[_first : _first + 26] = True


def chunks(data: np.ndarray, off: np.ndarray, chunk: int) -> tuple[np.ndarray, np.ndarray]:
    """Offsets of chunks and the text of each.

    Cuts lie between two letters that no contraction reaches, so the byte before a cut
    never ends its pre-token; the next such place after every ``chunk`` bytes is taken.
    """
    letter = _LETTERS[data]
    fine = np.zeros(len(data), bool)
    fine[1:] = letter[1:] & letter[:-1]
    for back in range(1, 5):
        fine[back:] &= data[:-back] != 0x27
    place = np.flatnonzero(fine)
    n = np.maximum(0, (np.diff(off) - 1) // chunk)
    text = np.repeat(np.arange(len(n)), n)
    wish = off[text] + chunk * (np.arange(len(text)) - np.repeat(np.cumsum(n) - n, n) + 1)
    at = np.searchsorted(place, wish)
    have = at < len(place)
    cut = place[at[have]]
    inside = cut < off[text[have] + 1]
    cut = np.unique(np.concatenate([off[:-1][np.diff(off) > 0], cut[inside]]))
    return np.append(cut, len(data)), np.searchsorted(off, cut, side="right") - 1


def state_maps(tr: Transducer, data: np.ndarray, off: np.ndarray, chunk: int) -> tuple[Maps, np.ndarray]:
    """The map of every chunk, and which texts the transducer can't read."""
    cut, text = chunks(data, off, chunk)
    low, start, length, bad = pretokens(data, cut)
    n = len(text)
    begins = np.ones(n, bool)
    begins[1:] = text[1:] != text[:-1]
    ends = np.ones(n, bool)
    ends[:-1] = begins[1:]
    owner = np.searchsorted(cut, start, side="right") - 1
    first = np.searchsorted(owner, np.arange(n))
    last = np.searchsorted(owner, np.arange(n), side="right") - 1
    some = last >= first  # a chunk of blanks has no pre-token
    pending = np.zeros(len(start), bool)  # pre-tokens that go on in the next chunk
    pending[last[some & ~ends]] = True
    heads = np.zeros(len(start), bool)  # pre-tokens that began in the chunk before
    heads[first[some & ~begins]] = True
    inner = np.flatnonzero(~heads)
    tr.refresh()
    zero = np.zeros(len(inner), np.int64)
    emitted, state, _ = tr.advance(low, start[inner], length[inner], zero, ~pending[inner])
    count = np.bincount(owner[inner], weights=emitted, minlength=n).astype(np.int64)
    exits = np.zeros(n, np.int64)
    tails = pending[inner]
    exits[owner[inner[tails]]] = state[tails]
    head, size, closes = cut[:-1].copy(), np.zeros(n, np.int64), np.ones(n, bool)
    own = np.flatnonzero(heads)
    head[owner[own]], size[owner[own]], closes[owner[own]] = start[own], length[own], ~pending[own]
    opened = np.zeros(n, bool)
    opened[owner[own]] = pending[own]
    unsafe = np.zeros(len(off) - 1, bool)
    unsafe[text[bad]] = True
    return Maps(tr, low, text, head, size, closes, opened, count, exits), unsafe


def count_bytes(tr: Transducer, data: np.ndarray, off: np.ndarray, chunk: int = CHUNK_BYTES):
    """Tokens of each text, and which texts the transducer can't read."""
    total = np.zeros(len(off) - 1, np.int64)
    if not len(data):
        return total, np.zeros(len(total), bool)
    maps, unsafe = state_maps(tr, data, off, chunk)
    whole = maps.scan()
    total[whole.text] = whole.count  # the last chunk's map is that of the whole text
    return total, unsafe


def _counts(path: str):
    def count(batches):
        tr = transducer(path)
        for batch in batches:
            data, off = flat_bytes(batch.column("text"))
            tokens = np.zeros(batch.num_rows, np.int64)
            for a, z in slices(off):
                part = data[off[a] : off[z]]
                tokens[a:z], unsafe = count_bytes(tr, part, off[a : z + 1] - off[a])
                odd = np.flatnonzero(unsafe)
                texts = [part[off[a + t] - off[a] : off[a + t + 1] - off[a]].tobytes().decode() for t in odd]
                for t, ids in zip(odd, library_ids(path, texts) if texts else [], strict=True):
                    tokens[a + t] = len(ids)
            yield pa.record_batch(
                [batch.column("doc_id"), pa.array(np.diff(off), pa.int64()), pa.array(tokens)],
                ["doc_id", "n_bytes", "n_tokens"],
            )

    return count


def count_tokens(docs: DataFrame, path: str | None = None, limit: int = LIMIT) -> DataFrame:
    """``doc_id``, ``n_bytes``, ``n_tokens``, ``over_limit`` of every row; one pass, no shuffle."""
    path = path or vocabulary_path()
    return (
        docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
        .mapInArrow(_counts(path), "doc_id long, n_bytes long, n_tokens long")
        .withColumn("over_limit", F.col("n_tokens") > limit)
    )


def op8_token_counts(spark, sf_dir: str) -> DataFrame:
    """Token counts of all documents."""
    return count_tokens(spark.read.parquet(f"{sf_dir}/documents.parquet"))
