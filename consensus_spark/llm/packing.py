"""Best-fit packing of token sequences by minimum bin slack.

The number of distinct piece lengths is bounded by the capacity, so the packing is
solved once on the histogram of lengths: for each bin the longest remaining piece is
set and a bitset subset-sum program over the available lengths finds the fullest
feasible combination.  That combination is taken as often as the histogram allows
before the next is sought, which is what bin-by-bin removal would do.  Pieces are
ranked within their length and ranks are dealt to combinations.

Defined cases: a null or empty text is its end token alone; a text longer than the
capacity is cut into full pieces and a rest; repeated rows are packed each; an empty
table gives no rows.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from consensus_spark.llm.durable import materialise
from consensus_spark.llm.prefix import hash_bucket, running_start
from consensus_spark.llm.textbytes import flat_bytes
from consensus_spark.llm.token_counts import library_ids, slices, transducer, vocabulary_path
from consensus_spark.llm.transducer import pretokens

CAPACITY = 4096
END_ID = 1

_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def _tokenised(path: str, capacity: int):
    def emit(batches):
        tr = transducer(path)
        for batch in batches:
            data, off = flat_bytes(batch.column("text"))
            ids_of_doc = batch.column("doc_id")
            rows: list[tuple[int, int, int, int, int]] = []
            for a, z in slices(off):
                part, local = data[off[a] : off[z]], off[a : z + 1] - off[a]
                low, start, length, unsafe = pretokens(part, local)
                ids, count = tr.tokens(low, start, length)
                owner = np.searchsorted(local, start, side="right") - 1
                border = np.concatenate([[0], np.cumsum(np.bincount(owner, weights=count, minlength=z - a))]).astype(np.int64)
                odd = np.flatnonzero(unsafe)
                own = dict(zip(odd, library_ids(path, [part[local[t] : local[t + 1]].tobytes().decode() for t in odd]), strict=True)) if len(odd) else {}
                for t in range(z - a):
                    mine = np.array(own[t], np.uint32) if t in own else ids[border[t] : border[t + 1]]
                    mine = np.append(mine, END_ID).astype("<u4")
                    for k, s in enumerate(range(0, len(mine), capacity)):
                        cut = mine[s : s + capacity]
                        rows.append((a + t, k, s, len(cut), zlib.crc32(cut.tobytes())))
            at, piece, start_, size, crc = (np.array(c, np.int64) for c in zip(*rows, strict=True)) if rows else (np.zeros(0, np.int64),) * 5
            yield pa.record_batch(
                [ids_of_doc.take(pa.array(at)), pa.array(piece.astype(np.int32)), pa.array(start_), pa.array(size), pa.array(crc)],
                ["doc_id", "piece", "start", "length", "ids_crc32"],
            )

    return emit


def pieces(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """Token pieces of every row, end token included, cut at the capacity."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return rows.mapInArrow(_tokenised(path or vocabulary_path(), capacity), _PIECES)


@dataclass(frozen=True)
class Combination:
    """``times`` equal bins; each holds ``items`` as (length, copies), longest first."""

    items: tuple[tuple[int, int], ...]
    times: int


def fullest(available: list[tuple[int, int]], room: int) -> list[tuple[int, int]]:
    """The multiset of lengths with the largest sum within ``room``.

    Bit s of ``reach`` says that sum s is reachable; copies are added in powers of two.
    """
    reach, mask, layers = 1, (1 << (room + 1)) - 1, []
    for length, count in available:
        if length > room:
            continue
        left, step = min(count, room // length), 1
        while left and not reach >> room & 1:
            take = min(step, left)
            layers.append((length, take, reach))
            reach = (reach | reach << (take * length)) & mask
            left, step = left - take, step * 2
        if reach >> room & 1:
            break
    best, chosen = reach.bit_length() - 1, {}
    for length, take, before in reversed(layers):
        if not before >> best & 1:
            best -= take * length
            chosen[length] = chosen.get(length, 0) + take
    return list(chosen.items())


def minimum_bin_slack(histogram: dict[int, int], capacity: int = CAPACITY) -> list[Combination]:
    """Combinations that use up the histogram."""
    left, out = {k: v for k, v in histogram.items() if v > 0}, []
    if left and max(left) > capacity:
        raise ValueError("a piece is longer than the capacity")
    order = sorted(left, reverse=True)
    while order:
        top = order[0]
        have = [(k, left[k] - (k == top)) for k in order if left[k] - (k == top) > 0]
        items = {top: 1}
        for k, n in fullest(have, capacity - top):
            items[k] = items.get(k, 0) + n
        times = min(left[k] // n for k, n in items.items())
        for k, n in items.items():
            left[k] -= n * times
        out.append(Combination(tuple(sorted(items.items(), reverse=True)), times))
        order = [k for k in order if left[k]]
    return out


def _deal(plan: list[Combination]) -> dict[int, np.ndarray]:
    """Per length, rows (first rank, copies, first sequence, offset) rising in rank."""
    used: dict[int, int] = {}
    rows: dict[int, list] = {}
    sequence = 0
    for c in plan:
        offset = 0
        for length, copies in c.items:
            first = used.get(length, 0)
            rows.setdefault(length, []).append((first, copies, sequence, offset))
            used[length] = first + copies * c.times
            offset += length * copies
        sequence += c.times
    return {k: np.array(v, np.int64) for k, v in rows.items()}


def _placed(deal: dict[int, np.ndarray]):
    def place(batches):
        for batch in batches:
            length = np.asarray(batch.column("length"))
            rank = np.asarray(batch.column("_rank"))
            sequence, offset = np.zeros(len(rank), np.int64), np.zeros(len(rank), np.int64)
            for k in np.unique(length):
                rows, at = deal[int(k)], np.flatnonzero(length == k)
                r = rows[np.searchsorted(rows[:, 0], rank[at], side="right") - 1]
                inside = rank[at] - r[:, 0]
                sequence[at] = r[:, 2] + inside // r[:, 1]
                offset[at] = r[:, 3] + inside % r[:, 1] * k
            names = ["doc_id", "piece", "start", "length", "ids_crc32"]
            yield pa.record_batch(
                [*[batch.column(n) for n in names], pa.array(sequence), pa.array(offset)],
                [*names, "sequence_id", "offset"],
            )

    return place


def pack(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    """Every piece with its sequence and its place there."""
    cut = materialise(pieces(docs, path, capacity))
    histogram = {r[0]: r[1] for r in cut.groupBy("length").count().collect()}  # at most ``capacity`` rows
    deal = _deal(minimum_bin_slack(histogram, capacity))
    ranked = running_start(
        cut.withColumn("_hash", F.xxhash64("doc_id", "piece", "ids_crc32")),
        ["length"],
        hash_bucket(F.col("_hash")),
        ["_hash", "doc_id", "piece", "ids_crc32"],
        F.lit(1).cast("long"),
        "_rank",
    ).drop("_hash")
    return ranked.mapInArrow(_placed(deal), f"{_PIECES}, sequence_id long, offset long")


def op7_packing(spark, sf_dir: str) -> DataFrame:
    """All documents packed into sequences of at most 4096 tokens."""
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"))
