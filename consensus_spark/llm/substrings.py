"""Substring dedup: word windows seen in an earlier document are removed.

Rabin-Karp hashes of every 13-word window are counted across documents in two
rounds of messages between document blocks and hash shards.  The first sends 48
leading hash bits and finds windows that may occur in two documents; the second
sends 96 bits of those alone, with the smallest document id, and answers exactly
which windows also start in a smaller document.  Repeated windows then merge into
maximal removal intervals.

Defined cases: a null text has no words; a text shorter than a window keeps all;
rows that repeat a document id are one document for "smaller" and are each
reported; a null id is smaller than none and larger than none; an empty table
gives no rows.
"""

from __future__ import annotations

import hashlib
from itertools import compress

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from consensus_spark.llm.blocks import (
    BLOCK_BYTES,
    SHARD_KEYS,
    by_shard,
    each_block,
    in_blocks,
    opened,
    ragged,
    ranked,
)
from consensus_spark.llm.textbytes import (
    pack,
    run_hashes,
    unpack,
    whole_windows,
    window_hashes,
    words_of,
)

WINDOW = 13
_FIRST_BITS = np.uint64(16)  # dropped in the first round
_TOP = np.uint64(1 << 63)

_MESSAGE = "block long, shard int, keys binary, more binary, owner binary, flags binary"
_REPLY = "block long, shard int, flags binary, hit binary"
_RESULT = (
    "doc_id long, n_words long, n_removed long, kept_sha256 string, text string, "
    "removed array<struct<from:long,to:long>>"
)


class _Block:
    """The windows of one block, in a fixed order; every round derives the same."""

    def __init__(self, table: pa.Table, k: int):
        self.ids = table.column("doc_id").to_pandas().to_numpy()
        self.words = w = words_of(table.column("text"))
        self.k = k
        h = run_hashes(w.data, w.start, w.end)
        whole = whole_windows(w.first, k)
        self.at = np.flatnonzero(whole)
        self.hash = window_hashes(h, k)[self.at]
        ids = table.column("doc_id").combine_chunks()
        known = np.asarray(ids.is_valid())
        self.id_of = np.asarray(ids.fill_null(0)).astype(np.int64)[w.text_of[self.at]]
        self.known = known[w.text_of[self.at]]
        self._h = h
        self.short = self.hash >> _FIRST_BITS
        self.keys, self.key_of = ranked(self.short)

    def second(self) -> np.ndarray:
        """Independent 32-bit hash of the same windows."""
        w = self.words
        h = run_hashes(w.data, w.start, w.end, seed=2)
        return window_hashes(h, self.k, 0xD6E8FEB86659FD93)[self.at] >> np.uint64(32)

    def in_two(self) -> np.ndarray:
        """Keys that two different documents of this block hold."""
        low = np.full(len(self.keys), np.iinfo(np.int64).max)
        high = np.full(len(self.keys), np.iinfo(np.int64).min)
        np.minimum.at(low, self.key_of, self.id_of)
        np.maximum.at(high, self.key_of, self.id_of)
        return low < high


def _bits(mask: np.ndarray) -> bytes:
    return np.packbits(mask).tobytes()


def _mask(blob: bytes, n: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(blob, np.uint8), count=n).astype(bool)


def _rows(schema: str, rows: list[tuple]) -> pa.Table:
    kinds = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary()}
    fields = [f.strip().split(" ") for f in schema.split(",")]
    cols = list(zip(*rows, strict=True)) or [[] for _ in fields]
    return pa.table({n: pa.array(c, kinds[t]) for (n, t), c in zip(fields, cols, strict=True)})


def _split(keys: np.ndarray, bits: int):
    """Shard cuts of first-round keys (48 bits wide)."""
    yield from by_shard(keys << _FIRST_BITS, bits)


def _ask(k: int, bits: int):
    def send(table: pa.Table, block: int) -> pa.Table:
        b = _Block(table, k)
        two = b.in_two()
        return _rows(
            _MESSAGE,
            [
                (block, shard, pack(b.keys[cut]), None, None, _bits(two[cut]))
                for shard, cut in _split(b.keys, bits)
            ],
        )

    return each_block(send)


def _seen_twice(table: pa.Table) -> pa.Table:
    """Per message, the keys that another block holds too or two of its documents do."""
    blocks, shards = table.column("block").to_pylist(), table.column("shard").to_pylist()
    keys, border = ragged([unpack(x.as_py()) for x in table.column("keys")])
    order = np.argsort(keys, kind="stable")
    same = keys[order][1:] == keys[order][:-1]
    twice = np.zeros(len(keys), bool)
    twice[order[1:]] |= same
    twice[order[:-1]] |= same
    rows = []
    for i, x in enumerate(table.column("flags")):
        a, z = border[i], border[i + 1]
        rows.append((blocks[i], shards[i], _bits(twice[a:z] | _mask(x.as_py(), z - a)), None))
    return _rows(_REPLY, rows)


def _candidates(b: _Block, replies: pa.Table, bits: int):
    """Windows of flagged keys, grouped as distinct (hash, second hash)."""
    flag = {s: f for s, f in zip(replies.column("shard").to_pylist(), replies.column("flags").to_pylist(), strict=True)}
    marked = np.zeros(len(b.keys), bool)
    for shard, cut in _split(b.keys, bits):
        marked[cut] = _mask(flag[shard], cut.stop - cut.start)
    at = np.flatnonzero(marked[b.key_of] & b.known)
    one, two, ids = b.hash[at], b.second()[at], b.id_of[at]
    order = np.lexsort((ids, two, one))
    one, two, ids = one[order], two[order], ids[order]
    new = np.ones(len(at), bool)
    new[1:] = (one[1:] != one[:-1]) | (two[1:] != two[:-1])
    return at[order], np.cumsum(new) - 1, one[new], two[new], ids[new], flag


def _tell(k: int, bits: int):
    def send(table: pa.Table, replies: pa.Table) -> pa.Table:
        if not table.num_rows:
            return _rows(_MESSAGE, [])
        b = _Block(opened(table.column("body")[0].as_buffer()), k)
        _, _, one, two, ids, flag = _candidates(b, replies, bits)
        block = table.column("block")[0].as_py()
        cuts = dict(by_shard(one, bits))
        rows = []
        for shard, f in flag.items():
            cut = cuts.get(shard, slice(0, 0))
            owner = ids[cut].astype(np.uint64) ^ _TOP
            rows.append(
                (block, shard, pack(one[cut]), pack(two[cut], False), pack(owner, False), f)
            )
        return _rows(_MESSAGE, rows)

    return send


def _owned_before(table: pa.Table) -> pa.Table:
    """Per message, the windows whose smallest document id is smaller than the block's own."""
    read = lambda c, s: [unpack(x.as_py(), s) for x in table.column(c)]
    one, border = ragged(read("keys", True))
    two, owner = ragged(read("more", False))[0], ragged(read("owner", False))[0]
    order = np.lexsort((owner, two, one))
    o, t = one[order], two[order]
    new = np.ones(len(one), bool)
    new[1:] = (o[1:] != o[:-1]) | (t[1:] != t[:-1])
    least = owner[order][new][np.cumsum(new) - 1]
    hit = np.zeros(len(one), bool)
    hit[order] = least < owner[order]
    rows = []
    for i, (block, shard, f) in enumerate(
        zip(*[table.column(c).to_pylist() for c in ("block", "shard", "flags")], strict=True)
    ):
        rows.append((block, shard, f, _bits(hit[border[i] : border[i + 1]])))
    return _rows(_REPLY, rows)


def _remove(k: int, bits: int, whole: bool):
    def finish(table: pa.Table, replies: pa.Table) -> pa.Table:
        if not table.num_rows:
            return _result([], [], [], [], [], [])
        table = opened(table.column("body")[0].as_buffer())
        n_docs, b = table.num_rows, _Block(table, k)
        w = b.words
        gone = np.zeros(len(w.start) + 1, np.int32)
        if len(b.keys):
            at, group, one, _, least, _ = _candidates(b, replies, bits)
            hit = np.zeros(len(one), bool)
            answer = dict(zip(replies.column("shard").to_pylist(), replies.column("hit").to_pylist(), strict=True))
            for shard, cut in by_shard(one, bits):
                hit[cut] = _mask(answer[shard], cut.stop - cut.start)
            bad = b.at[at[hit[group] | (b.id_of[at] > least[group])]]
            np.add.at(gone, bad, 1)
            np.add.at(gone, bad + k, -1)
        kept = np.cumsum(gone)[:-1] == 0
        n_words = np.diff(w.first)
        n_kept = np.add.reduceat(np.append(kept, False), np.minimum(w.first[:-1], len(kept)), dtype=np.int64)
        n_kept[n_words == 0] = 0
        sha, texts, spans = [], [], []
        for t in range(n_docs):
            words = w.text_bytes(t).split()
            mine = kept[w.first[t] : w.first[t + 1]]
            if n_kept[t] < n_words[t]:
                words = compress(words, mine)
            body = b" ".join(words)
            sha.append(hashlib.sha256(body).hexdigest())
            if whole:
                texts.append(body.decode("utf-8"))
                edge = np.flatnonzero(np.diff(np.concatenate([[False], ~mine, [False]]).astype(np.int8)))
                spans.append([{"from": int(a), "to": int(z)} for a, z in edge.reshape(-1, 2)])
            else:
                texts.append(None)
                spans.append(None)
        return _result(table.column("doc_id"), n_words, n_words - n_kept, sha, texts, spans)

    return finish


def _result(ids, n_words, n_removed, sha, texts, spans) -> pa.Table:
    span = pa.list_(pa.struct([("from", pa.int64()), ("to", pa.int64())]))
    return pa.table(
        {
            "doc_id": ids if isinstance(ids, pa.ChunkedArray) else pa.array(ids, pa.int64()),
            "n_words": pa.array(n_words, pa.int64()),
            "n_removed": pa.array(n_removed, pa.int64()),
            "kept_sha256": pa.array(sha, pa.string()),
            "text": pa.array(texts, pa.string()),
            "removed": pa.array(spans, span),
        }
    )


def dedup_substrings(
    docs: DataFrame, window: int = WINDOW, whole: bool = True, shard_keys: int = SHARD_KEYS, block_bytes: int = BLOCK_BYTES
) -> DataFrame:
    """Per row: word counts, digest, and with ``whole`` the kept text and removed intervals."""
    blocks, layout = in_blocks(docs, block_bytes, shard_keys)
    bits = layout.shard_bits
    texts = blocks.select("block", "body")
    asked = texts.mapInArrow(_ask(window, bits), _MESSAGE)
    maybe = asked.groupBy("shard").applyInArrow(_seen_twice, _REPLY)
    told = texts.groupBy("block").cogroup(maybe.groupBy("block")).applyInArrow(_tell(window, bits), _MESSAGE)
    known = told.groupBy("shard").applyInArrow(_owned_before, _REPLY)
    return texts.groupBy("block").cogroup(known.groupBy("block")).applyInArrow(_remove(window, bits, whole), _RESULT)


def op6_substrings(spark, sf_dir: str) -> DataFrame:
    """Removal of repeated 13-word windows from all documents."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return dedup_substrings(docs, whole=False).select("doc_id", "n_words", "n_removed", "kept_sha256")
