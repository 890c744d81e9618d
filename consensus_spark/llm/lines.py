"""Line dedup by a log-template tree.

A line is parsed along a fixed-depth path: its token count, then its leading tokens,
with tokens that hold digits generalised to a variable field.  Lines in one leaf that
agree in three quarters of all their places share a template, whose differing places
become fields as well.  Lines of fewer than three tokens (headings, and sentences of
scripts without spaces) are counted as they are, digits too.  A template found in
several different texts recurs: its lines go from all documents but those that share
the text of the first (smallest id) that holds it.  Exact copies of one text count
once, so copies alone make nothing recur.

Leaves of any size are compared.  A leaf with many different lines is dealt into
blocks by hash of the line; each block emits its templates, and a second round merges
the templates of all blocks of the leaf.  Every line of a template agrees with it in
all places that are no fields, in both rounds.

Defined cases: a null text has no lines and stays null; blank lines always stay;
repeated rows fare alike; a null id comes after all others; an empty table gives no
rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from consensus_spark.llm.durable import materialise
from consensus_spark.llm.textbytes import flat_bytes, mixed, run_hashes
from consensus_spark.llm.textbytes import words_of as token_spans
from consensus_spark.llm.token_counts import slices

MIN_TOKENS = 3
MIN_TEXTS = 2
SIMILARITY = 0.75
DEPTH = 3
BLOCK_LINES = 256
#: From so many lines on, candidate templates come from an index.
INDEXED = 200
#: A template's lines are dealt over so many cells wherever they meet their template.
CELLS = 64
_CELLS = 1 << 20

_U = np.uint64
_FIELD = _U(0xF1E1DF1E1DF1E1D)
_LINES = "doc_id long, whole long, line_at int, line long, leaf long"
#: The places of a line, four bytes each.
_SKETCHES = "line long, places binary"
_FIRST = "leaf long, line long, texts long, least long, whole long, template long, places binary"


def _names(schema: str) -> list[str]:
    return [f.strip().split(" ")[0] for f in schema.split(",")]


def _signed(values: np.ndarray) -> pa.Array:
    return pa.array(values.view(np.int64), pa.int64())


def _lines_of(column):
    """Lines that are not blank: text, place in it, hash, first token, size, and all tokens."""
    data, off = flat_bytes(column)
    w = token_spans(column)
    token = run_hashes(w.data, w.start, w.end)
    digit = (w.data >= 0x30) & (w.data <= 0x39)
    seen = np.concatenate([[0], np.cumsum(digit)])
    breaks = np.flatnonzero(data == 0x0A)
    line_of = np.searchsorted(breaks, w.start) + np.searchsorted(off[1:-1], w.start, side="right")
    first = np.flatnonzero(np.concatenate([[True], line_of[1:] != line_of[:-1]])) if len(token) else np.zeros(0, np.int64)
    size = np.diff(np.append(first, len(token)))
    token[(seen[w.end] > seen[w.start]) & np.repeat(size >= MIN_TOKENS, size)] = _FIELD
    n = len(first)
    text = np.searchsorted(w.first, first, side="right") - 1
    at = np.searchsorted(breaks, w.start[first]) - np.searchsorted(breaks, off[text])

    weight = mixed(np.arange(int(size.max()) if n else 0, dtype=_U))
    place = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
    own = mixed(token[np.repeat(first, size) + place] + weight[place]) if n else np.zeros(0, _U)
    line = mixed(np.add.reduceat(own, np.cumsum(size) - size) + size.astype(_U)) if n else own
    return text, at, line, first, size, token


def _paths(token: np.ndarray, first: np.ndarray, size: np.ndarray, depth: int) -> np.ndarray:
    """Hash of each line's token count and leading tokens."""
    key = mixed(size.astype(_U))
    take = np.minimum(size, depth)
    for k in range(int(take.max()) if len(size) else 0):
        go = take > k
        key[go] = mixed(key[go] * _U(0x9E3779B97F4A7C15) + token[first[go] + k])
    return key


def _parse(part: pa.RecordBatch) -> pa.RecordBatch:
    text, at, line, first, size, token = _lines_of(part.column("text"))
    own = pa.array(text)
    return pa.record_batch(
        [
            part.column("doc_id").take(own),
            part.column("whole").take(own),
            pa.array(at.astype(np.int32)),
            _signed(line),
            _signed(_paths(token, first, size, DEPTH)),
        ],
        _names(_LINES),
    )


def _sketch(part: pa.RecordBatch) -> pa.RecordBatch:
    """All places of each different line that can share a leaf."""
    _, _, line, first, size, token = _lines_of(part.column("text"))
    _, at = np.unique(line, return_index=True)
    at = at[size[at] > DEPTH]  # shorter lines are alone in their leaf
    line, first, size = line[at], first[at], size[at]
    inside = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
    cells = np.maximum(token[np.repeat(first, size) + inside] >> _U(32), _U(1)).astype("<u4")
    off = np.concatenate([[0], np.cumsum(4 * size)]).astype(np.int32)
    places = pa.Array.from_buffers(pa.binary(), len(line), [None, pa.py_buffer(off), pa.py_buffer(cells.tobytes())])
    return pa.record_batch([_signed(line), places], _names(_SKETCHES))


def _each(make):
    """``make`` over bounded slices of the texts."""

    def run(batches):
        for b in batches:
            _, off = flat_bytes(b.column("text"))
            for a, z in slices(off):
                yield make(b.slice(a, z - a))

    return run


def _segments(cells: np.ndarray, edges: np.ndarray):
    """Hash of each run of places between edges, and whether it holds no field."""
    salt = mixed(np.arange(1, cells.shape[1] + 1, dtype=_U))
    step = max(1, _CELLS // cells.shape[1])
    for a in range(0, len(cells), step):
        part = cells[a : a + step]
        keys = np.add.reduceat(mixed(part.astype(_U) + salt), edges, axis=1)
        whole = np.logical_and.reduceat(part > 0, edges, axis=1)
        for k, w in zip(keys.tolist(), whole, strict=True):
            yield [(j, k[j]) for j in np.flatnonzero(w).tolist()]


def _match(cells: np.ndarray, similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """Template number of each row, in order: the best match or a new one; and the templates.

    Places that agree throughout need no comparison.  Two rows that may differ in d
    places agree in one of d + 1 segments, so an index of segments finds all matches.
    """
    n, places = cells.shape
    which = np.zeros(n, np.int64)
    need = int(np.ceil(similarity * places - 1e-9))
    differ = places - need
    varies = ((cells != cells[0]) | (cells == 0)).any(axis=0)
    if varies.sum() <= differ:
        return which, np.where(varies, 0, cells[:1]).astype(cells.dtype)
    own = np.ascontiguousarray(cells[:, varies])
    need -= places - own.shape[1]
    index: dict[tuple[int, int], list[int]] = {}
    segments = None
    if n > INDEXED:
        segments = _segments(own, np.arange(differ + 1) * own.shape[1] // (differ + 1))
    templates, count = np.zeros((min(n, 16), own.shape[1]), cells.dtype), 0
    for i, s in enumerate(own):
        keys = next(segments) if segments else []
        if segments:
            near = np.array(sorted({t for k in keys for t in index.get(k, ())}), np.int64)
        else:
            near = np.arange(count)
        if len(near):
            same = ((templates[near] == s) & (s > 0)).sum(axis=1)
            best = int(same.argmax())
            if same[best] >= need:
                t = templates[near[best]]
                t[t != s] = 0
                which[i] = near[best]
                continue
        if count == len(templates):
            templates = np.concatenate([templates, np.zeros_like(templates)])
        templates[count], which[i] = s, count
        for k in keys:
            index.setdefault(k, []).append(count)
        count += 1
    out = np.repeat(cells[:1], count, axis=0)
    out[:, varies] = templates[:count]
    return which, out


def match_templates(sketches: np.ndarray, similarity: float = SIMILARITY) -> np.ndarray:
    """Template number of each line of a leaf, in order: the best match or a new one.

    A template's places become fields (0) where its lines differ.
    """
    return _match(sketches, similarity)[0]


def _lead(table: pa.Table, emit: bool) -> tuple[np.ndarray, list[bytes | None]]:
    """The line that leads each line's template (in most texts); with ``emit`` leaders' templates."""
    line, texts = (np.asarray(table.column(c)) for c in ("line", "texts"))
    data, off = flat_bytes(table.column("places"))
    template, vectors = np.zeros(len(line), np.int64), [None] * len(line)
    for width in np.unique(np.diff(off)):
        own = np.flatnonzero(np.diff(off) == width)
        own = own[np.lexsort((line[own], -texts[own]))]
        cells = np.stack([data[a : a + width] for a in off[own]]).view("<u4")
        which, found = _match(cells, SIMILARITY)
        _, lead = np.unique(which, return_index=True)
        template[own] = line[own][lead[which]]
        if emit:
            for i, v in zip(own[lead], found, strict=True):
                vectors[i] = v.tobytes()
    return template, vectors


def _cluster(table: pa.Table) -> pa.Table:
    """Lines of a block of a leaf with ``template``; ``places`` of templates if there are more blocks."""
    template, vectors = _lead(table, table.column("blocks")[0].as_py() > 1)
    named = table.select(["leaf", "line", "texts", "least", "whole"]).append_column("template", pa.array(template))
    return named.append_column("places", pa.array(vectors, pa.binary()))


def _merge(table: pa.Table) -> pa.Table:
    """Templates of all blocks of a leaf, and those they merge into."""
    merged, _ = _lead(table, False)
    return pa.table([table.column("line"), pa.array(merged)], ["template", "merged"])


def text_key(text: Column) -> Column:
    return F.xxhash64(text)


def _spread(rows: DataFrame, facts: DataFrame, how: str = "inner") -> DataFrame:
    """``rows`` (line, template) with the facts of their template; ``rows`` are on disk.

    Only the cells of a template, at most ``CELLS`` rows, meet its facts; its lines, however
    many, then meet their own cell.
    """
    dealt = rows.withColumn("_cell", F.pmod(F.xxhash64("line"), F.lit(CELLS)).cast("int"))
    cells = dealt.select("template", "_cell").distinct().join(facts, "template")
    return dealt.join(cells, ["template", "_cell"], how).drop("_cell")


def recurring(docs: DataFrame, min_texts: int = MIN_TEXTS) -> DataFrame:
    """Lines to drop: ``doc_id``, ``whole`` (hash of the text), ``line_at`` (from 0)."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", text_key(F.col("text")).alias("whole"))
    parsed = materialise(rows.mapInArrow(_each(_parse), _LINES))
    # one row per line and text, then one per line
    held = parsed.groupBy("leaf", "line", "whole").agg(
        F.min(F.coalesce("doc_id", F.lit((1 << 63) - 1))).alias("least")
    )
    lines = materialise(
        held.groupBy("leaf", "line")
        .agg(F.count(F.lit(1)).alias("texts"), F.min(F.struct("least", "whole")).alias("first"))
        .select("leaf", "line", "texts", "first.*")
    )
    # a template lies in one leaf, so only leaves of enough texts go on
    leaves = lines.groupBy("leaf").agg(F.count(F.lit(1)).alias("n"), F.sum("texts").alias("in_texts"))
    wide = lines.join(leaves.filter(F.col("in_texts") >= min_texts).drop("in_texts"), "leaf")
    about = ["line", "texts", "least", "whole"]
    blocks = F.ceil(F.col("n") / BLOCK_LINES).cast("int")
    grouped = wide.filter("n > 1").select(
        "leaf", blocks.alias("blocks"), F.pmod(F.xxhash64("line"), blocks).cast("int").alias("block"), *about
    )
    # only lines that share a leaf are compared; a second parse gives their places
    places = (
        docs.select("text")
        .mapInArrow(_each(_sketch), _SKETCHES)
        .groupBy("line")
        .agg(F.min("places").alias("places"))
    )
    blockwise = materialise(
        grouped.join(places, "line").groupBy("leaf", "block").applyInArrow(_cluster, _FIRST)
    )
    merged = (
        blockwise.filter("places IS NOT NULL")
        .select("leaf", "line", "texts", "places")
        .groupBy("leaf")
        .applyInArrow(_merge, "template long, merged long")
    )
    matched = _spread(blockwise.drop("leaf", "places"), merged, "left").select(
        *about, F.coalesce("merged", "template").alias("template")
    )
    alone = (
        wide.filter("n = 1").select(*about)
        .filter(F.col("texts") >= min_texts)
        .withColumn("template", F.col("line"))
    )
    named = materialise(matched.unionByName(alone))
    # a template's texts: those of its one line, or counted again over all its lines
    single = named.groupBy("template").agg(
        F.count(F.lit(1)).alias("members"),
        F.sum("texts").alias("texts"),
        F.min(F.struct("least", "whole")).getField("whole").alias("stays"),
    ).filter(F.col("texts") >= min_texts)
    several = (
        _spread(named.select("line", "template"), single.filter("members > 1").select("template"))
        .join(held.select("line", "whole"), "line")
        .select("template", "whole")
        .distinct()
        .groupBy("template")
        .count()
        .filter(F.col("count") >= min_texts)
        .select("template")
    )
    again = single.filter("members = 1").select("template", "stays").unionByName(
        single.join(several, "template", "left_semi").filter("members > 1").select("template", "stays")
    )
    doomed = _spread(named.select("line", "template"), again).select("line", "stays")
    return (
        parsed.select("doc_id", "whole", "line_at", "line")
        .join(doomed, "line")
        .filter(F.col("whole") != F.col("stays"))
        .select("doc_id", "whole", "line_at")
    )


def drop_lines(docs: DataFrame, min_texts: int = MIN_TEXTS) -> DataFrame:
    """The rows with recurring lines cut out of ``text``; ``n_chars``, if there, follows.

    All columns stay; ``_n_lines`` and ``_n_dropped`` are added.
    """
    names = docs.columns
    clash = {c: f"_in_{i}" for i, c in enumerate(names)}
    held = docs.select(*[F.col(c).alias(x) for c, x in clash.items()])
    text = F.col(clash["text"])
    gone = recurring(docs, min_texts).groupBy(
        F.coalesce("doc_id", F.lit(-1)).alias("_id"), F.col("whole").alias("_whole")
    ).agg(F.collect_set("line_at").alias("_gone"))
    held = held.withColumn("_id", F.coalesce(F.col(clash["doc_id"]).cast("long"), F.lit(-1))).withColumn(
        "_whole", text_key(text)
    )
    joined = held.join(gone, ["_id", "_whole"], "left")
    # places left by a hashed set difference, then the lines there: linear in the text
    stay = lambda ls: F.array_except(F.sequence(F.lit(0), F.size(ls) - 1), F.col("_gone"))
    own = F.transform(F.array(F.split(text, "\n")), lambda ls: F.transform(stay(ls), lambda i: F.get(ls, i)))
    kept = F.array_join(F.element_at(own, 1), "\n")
    out = joined.withColumn("_new", F.when(F.col("_gone").isNull(), text).otherwise(kept))
    columns = []
    for c, x in clash.items():
        value = F.col(x)
        if c == "text":
            value = F.col("_new")
        elif c == "n_chars":
            value = F.when(F.col("_gone").isNull(), value).otherwise(F.length("_new").cast(docs.schema[c].dataType))
        columns.append(value.alias(c))
    n_lines = F.coalesce(F.size(F.split(text, "\n")), F.lit(0)).cast("long")
    dropped = F.coalesce(F.size("_gone"), F.lit(0))
    return out.select(
        *columns,
        F.when(text.isNull(), F.lit(0)).otherwise(n_lines).cast("long").alias("_n_lines"),
        F.when(F.col("_gone").isNull(), F.lit(0)).otherwise(dropped).cast("long").alias("_n_dropped"),
    )


def op9_line_templates(spark, sf_dir: str) -> DataFrame:
    """Recurring lines cut from all documents: counts and the kept text."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return drop_lines(docs).select(
        "doc_id", F.col("_n_lines").alias("n_lines"), F.col("_n_dropped").alias("n_dropped"), "text"
    )
