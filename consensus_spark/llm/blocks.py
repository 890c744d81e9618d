"""Blocks of documents and shards of hashed keys, and messages between them.

Statistics of very many keys (windows, n-grams) are not sent as one row per key.
The rows a task reads are bundled, as they come, into compressed blocks of a bounded
number of bytes and written to the shared folder in buckets, so no text is shuffled to
form them or to meet their answers, and a lost executor costs a re-read.  A block sends each shard one compressed message
with its sorted distinct keys, the shard answers with a message whose entries stand in
the same order.  A key that every document holds costs one entry per block.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from consensus_spark.llm.durable import bucketed
from consensus_spark.llm.textbytes import flat_bytes

BLOCK_BYTES = 4_000_000
SHARD_KEYS = 1_500_000
#: A token and the blank after it are taken to be so many bytes.
TOKEN_BYTES = 6
BLOCKS_A_BUCKET = 2
#: Spark's own limit, unless a session raises it.
MOST_BUCKETS = 100_000
_BLOCK = "block long, n_bytes long, body binary"


@dataclass(frozen=True)
class Layout:
    """``shard_bits``: leading key bits that name a shard; ``key_bits``: bits that tell keys apart."""

    n_blocks: int
    shard_bits: int
    key_bits: int


def closed(table: pa.Table) -> bytes:
    """A table as one compressed value."""
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, table.schema) as out:
        out.write_table(table)
    return zstandard.ZstdCompressor(level=3).compress(sink.getvalue())


def opened(body: bytes) -> pa.Table:
    return pa.ipc.open_stream(zstandard.ZstdDecompressor().decompress(body)).read_all()


def _bundles(block_bytes: int, close: Callable[[pa.Table], bytes]):
    def bundle(batches):
        task, made = TaskContext.get().partitionId() << 32, 0
        held: list[pa.Table] = []
        size = 0

        def emit():
            body = close(pa.concat_tables(held).combine_chunks())
            row = [[task + made], [size], [body]]
            return pa.record_batch([pa.array(c, k) for c, k in zip(row, (pa.int64(), pa.int64(), pa.binary()), strict=True)], ["block", "n_bytes", "body"])

        for b in batches:
            table = pa.Table.from_batches([b])
            _, off = flat_bytes(b.column("text"))
            off = off + 64 * np.arange(len(off))  # rows without text weigh something
            a = 0
            while a < b.num_rows:
                z = max(a + 1, int(np.searchsorted(off, off[a] + block_bytes - size, side="right")) - 1)
                held.append(table.slice(a, z - a))
                size += int(off[z] - off[a])
                a = z
                if size >= block_bytes or a < b.num_rows:
                    yield emit()
                    held, size, made = [], 0, made + 1
        if held:
            yield emit()

    return bundle


def in_blocks(
    docs: DataFrame,
    block_bytes: int = BLOCK_BYTES,
    shard_keys: int = SHARD_KEYS,
    close: Callable[[pa.Table], bytes] = closed,
) -> tuple[DataFrame, Layout]:
    """``block``, ``n_bytes``, ``body`` (what ``close`` makes of the block's doc_id and text), on disk.

    Keys are cut to the bits that leave one in a million of them with a double.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    text_bytes = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = min(MOST_BUCKETS, 1 + text_bytes // (BLOCKS_A_BUCKET * block_bytes))
    blocks = bucketed(rows.mapInArrow(_bundles(block_bytes, close), _BLOCK), "block", buckets)
    total, n = blocks.agg(F.sum("n_bytes"), F.count(F.lit(1))).first()
    tokens = max(1, (total or 0) / TOKEN_BYTES)
    bits = max(0, math.ceil(math.log2(max(1, tokens / shard_keys))))
    return blocks, Layout(n, bits, min(64, max(32, math.ceil(math.log2(tokens)) + 20)))


def each_block(make: Callable[[pa.Table, int], pa.Table]):
    """``make(table, block)`` over blocks, one at a time, for ``mapInArrow``."""

    def run(batches):
        for b in batches:
            for block, body in zip(b.column("block").to_pylist(), b.column("body"), strict=True):
                yield from make(opened(body.as_buffer()), block).to_batches()

    return run


def by_shard(keys: np.ndarray, bits: int, width: int = 64):
    """Cuts of a rising array of keys of ``width`` bits at the borders of shards (their leading bits)."""
    if not len(keys):
        return
    if bits == 0:
        yield 0, slice(0, len(keys))
        return
    shard = (keys >> np.uint64(width - bits)).astype(np.int64)
    at = np.flatnonzero(np.diff(shard)) + 1
    for a, b in zip([0, *at], [*at, len(keys)], strict=True):
        yield int(shard[a]), slice(int(a), int(b))


def ragged(parts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """All parts end to end, and the border of each."""
    border = np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int64)
    return (np.concatenate(parts) if parts else np.zeros(0, np.uint64)), border


def ranked(keys: np.ndarray, width: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys, rising, and each key's rank among them.

    Sorts values that carry their place in the low bits, several times faster than
    sorting places; leading bits that all keys share make room (``width`` bits follow
    them; found if not given).  Where keys that differ in the bits left out alone stand
    wrong, all are sorted the plain way.
    """
    n = len(keys)
    bits = max(1, n.bit_length())
    low = np.uint64((1 << bits) - 1)
    if width is None:
        width = int(keys.max() ^ keys.min()).bit_length() if n else 0
    high = keys << np.uint64(min(bits, 64 - width))
    order = (np.sort((high & ~low) | np.arange(n, dtype=np.uint64)) & low).astype(np.int64)
    k = keys[order]
    if (k[1:] < k[:-1]).any():
        order = np.argsort(keys, kind="stable")
        k = keys[order]
    new = np.ones(n, bool)
    new[1:] = k[1:] != k[:-1]
    rank = np.empty(n, np.int64)
    rank[order] = np.cumsum(new) - 1
    return k[new], rank


def pair_ranks(first: np.ndarray, second: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct pairs of two rank arrays, rising, and each row's pair number."""
    if not len(first):
        return first, second, first
    wide = int(second.max()).bit_length()
    own = np.uint64(wide)
    both, row = ranked((first.astype(np.uint64) << own) | second.astype(np.uint64))
    return (both >> own).astype(np.int64), (both & np.uint64((1 << wide) - 1)).astype(np.int64), row
