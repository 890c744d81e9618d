"""Approximate nearest neighbours by learned partitions.

A bounded, documented sample of vectors gives a neighbour graph; the graph is cut
into balanced parts that keep neighbours together; a small classifier learns which
parts a vector's neighbours lie in.  Every vector is indexed under its most probable
part, a query is routed to several most probable parts, and all vectors of those
parts are reranked by exact distance.  How many parts a query needs is measured on
sample vectors that the classifier has not seen.

A part is searched in cells of candidate block and query block.  A part has as many
blocks as its own size needs, so a part that holds a third of all rows is spread over
many tasks of bounded size and small parts are not copied about.  Within a cell,
distances come from matrix products over tiles of queries; those near the edge of the
k best are computed again exactly.  The share of rows reranked is what the data allow:
on vectors without clusters most parts are probed, and the work per query then grows
with the table.

Defined cases: vectors that are null, zero, of another dimension than the most
common one, or with null or non-finite components take no part; rows with the
query's id are its own; repeated query rows answer once, and of different vectors
under one query id the least by components asks; ties go to the smaller id; with fewer
candidates than asked, all are returned; an empty table gives no rows.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

SAMPLE = 6_000
#: Parts grow with the root of the table up to what the sample can teach.
PARTS = (16, 64)
GRAPH_DEGREE = 10
HIDDEN = 128
AIM = 0.93
CELL_ROWS = 65_536
QUERY_ROWS = 65_536
#: Distances held at once within a cell.
TILE = 1 << 22
K = 10


def parts_for(n: int) -> int:
    return min(PARTS[1], max(PARTS[0], round(math.sqrt(n) / 4)))


def usable(vector: Column, dim: int) -> Column:
    """Whether the vector takes part."""
    fine = F.forall(vector, lambda x: x.isNotNull() & (F.abs(x) < float("inf")) & ~F.isnan(x))
    return vector.isNotNull() & (F.size(vector) == dim) & fine & F.exists(vector, lambda x: x != 0)


def neighbour_lists(x: np.ndarray, k: int) -> np.ndarray:
    """Exact nearest rows of each row, itself left out."""
    out = np.empty((len(x), k), np.int64)
    square = (x * x).sum(axis=1)
    for a in range(0, len(x), 1024):
        d = square - 2 * x[a : a + 1024] @ x.T
        d[np.arange(d.shape[0]), a + np.arange(d.shape[0])] = np.inf
        out[a : a + 1024] = np.argpartition(d, k - 1, axis=1)[:, :k]
    return out


def balanced_parts(x: np.ndarray, near: np.ndarray, parts: int, slack: float = 1.1, rounds: int = 12):
    """Cut the graph: equal halves along leading directions, then moves that keep more edges.

    A row moves to the part that holds most of its neighbours while that part has room.
    """
    label = np.zeros(len(x), np.int64)
    groups = [np.arange(len(x))]
    while len(groups) < parts:
        groups.sort(key=len)
        g = groups.pop()
        centred = x[g] - x[g].mean(axis=0)
        axis = np.linalg.eigh(centred.T @ centred)[1][:, -1]
        order = g[np.argsort(centred @ axis, kind="stable")]
        groups += [order[: len(g) // 2], order[len(g) // 2 :]]
    for i, g in enumerate(groups):
        label[g] = i
    room = math.ceil(slack * len(x) / parts)
    sizes = np.bincount(label, minlength=parts)
    back: list[list[int]] = [[] for _ in range(len(x))]
    for i, row in enumerate(near.tolist()):
        for j in row:
            back[j].append(i)
    ties = [np.array([*near[i], *back[i]], np.int64) for i in range(len(x))]
    for _ in range(rounds):
        moved = 0
        for i in range(len(x)):
            votes = np.bincount(label[ties[i]], minlength=parts)
            votes[(sizes >= room) & (np.arange(parts) != label[i])] = -1
            best = int(votes.argmax())
            if votes[best] > votes[label[i]]:
                sizes[label[i]] -= 1
                sizes[best] += 1
                label[i] = best
                moved += 1
        if moved < len(x) // 200:
            break
    return label


@dataclass
class Classifier:
    """One hidden layer; ``probabilities`` ranks the parts of each vector."""

    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: np.ndarray

    def probabilities(self, x: np.ndarray) -> np.ndarray:
        z = np.maximum(x @ self.w1 + self.b1, 0) @ self.w2 + self.b2
        z = np.exp(z - z.max(axis=1, keepdims=True))
        return z / z.sum(axis=1, keepdims=True)

    @staticmethod
    def fit(x: np.ndarray, target: np.ndarray, hidden: int = HIDDEN, epochs: int = 40, seed: int = 5):
        """Cross-entropy to soft part shares, by adaptive moments."""
        rng = np.random.default_rng(seed)
        d, parts = x.shape[1], target.shape[1]
        w = [
            rng.normal(0, math.sqrt(2 / d), (d, hidden)),
            np.zeros(hidden),
            rng.normal(0, math.sqrt(1 / hidden), (hidden, parts)),
            np.zeros(parts),
        ]
        m, v, step = [np.zeros_like(p) for p in w], [np.zeros_like(p) for p in w], 0
        for _ in range(epochs):
            order = rng.permutation(len(x))
            for a in range(0, len(x), 256):
                part = order[a : a + 256]
                h = np.maximum(x[part] @ w[0] + w[1], 0)
                delta = (Classifier(*w).probabilities(x[part]) - target[part]) / len(part)
                dh = (delta @ w[2].T) * (h > 0)
                grads = [x[part].T @ dh, dh.sum(axis=0), h.T @ delta, delta.sum(axis=0)]
                step += 1
                for p, g, mm, vv in zip(w, grads, m, v, strict=True):
                    mm *= 0.9
                    mm += 0.1 * g
                    vv *= 0.999
                    vv += 0.001 * g * g
                    p -= 2e-3 * (mm / (1 - 0.9**step)) / (np.sqrt(vv / (1 - 0.999**step)) + 1e-8)
        return Classifier(*w)


@dataclass
class Index:
    """What is broadcast: a classifier of fixed size, and how many parts to probe."""

    model: Classifier
    parts: int
    probes: int
    scale: float


def learn(x: np.ndarray, parts: int = PARTS[0], k: int = K, aim: float = AIM) -> Index:
    """Graph, parts, classifier and the number of probes that reaches ``aim`` on unseen rows."""
    scale = float(np.sqrt((x * x).sum(axis=1)).mean()) / math.sqrt(x.shape[1]) or 1.0
    x = x / scale
    unseen = max(1, len(x) // 10)
    train, held = x[unseen:], x[:unseen]
    if len(train) <= max(parts, GRAPH_DEGREE + 1):
        blank = Classifier(np.zeros((x.shape[1], 1)), np.zeros(1), np.zeros((1, parts)), np.zeros(parts))
        return Index(blank, parts, parts, scale)
    near = neighbour_lists(train, GRAPH_DEGREE)
    label = balanced_parts(train, near, parts)
    share = np.zeros((len(train), parts))
    np.add.at(share, (np.arange(len(train))[:, None], label[near]), 1.0)
    share[np.arange(len(train)), label] += 1.0
    model = Classifier.fit(train, share / share.sum(axis=1, keepdims=True))
    home = model.probabilities(train).argmax(axis=1)
    d = (train * train).sum(axis=1) - 2 * held @ train.T
    true = np.argpartition(d, k - 1, axis=1)[:, :k]
    route = np.argsort(-model.probabilities(held), axis=1, kind="stable")
    place = np.argsort(route, axis=1)  # place of each part in the query's route
    depth = np.take_along_axis(place, home[true], axis=1)
    found = [(depth < m).mean() for m in range(1, parts + 1)]
    probes = next((m for m, r in enumerate(found, 1) if r >= aim), parts)
    return Index(model, parts, probes, scale)


def _matrix(column) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    flat = column.flatten().cast(pa.float64())
    return np.asarray(flat).reshape(len(column), -1) if len(column) else np.zeros((0, 1))


def _homes(index: Index):
    def assign(batches):
        for b in batches:
            if b.num_rows:
                p = index.model.probabilities(_matrix(b.column("vector")) / index.scale)
                yield b.append_column("part", pa.array(p.argmax(axis=1).astype(np.int32)))

    return assign


def _routes(index: Index, sizes: dict[int, int], k: int):
    size = np.array([sizes.get(p, 0) for p in range(index.parts)])

    def route(batches):
        for b in batches:
            if not b.num_rows:
                continue
            p = index.model.probabilities(_matrix(b.column("vector")) / index.scale)
            order = np.argsort(-p, axis=1, kind="stable")
            # enough parts to hold k candidates besides the query itself
            enough = (np.cumsum(size[order], axis=1) < k + 1).sum(axis=1) + 1
            n = np.minimum(np.maximum(index.probes, enough), index.parts)
            row = np.repeat(np.arange(len(n)), n)
            column = np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n)
            taken = b.take(pa.array(row))
            yield taken.append_column("part", pa.array(order[row, column].astype(np.int32)))

    return route


_FOUND = "query_id long, vec_id long, score double"


def _own(ids: np.ndarray, asked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(query, row) places of the rows that bear the query's own id."""
    order = np.argsort(ids, kind="stable")
    a, z = (np.searchsorted(ids[order], asked, side=s) for s in ("left", "right"))
    query = np.repeat(np.arange(len(asked)), z - a)
    return query, order[np.arange(len(query)) - np.repeat(np.cumsum(z - a) - (z - a), z - a) + np.repeat(a, z - a)]


def nearest(x: np.ndarray, ids: np.ndarray, asked: np.ndarray, own: np.ndarray, k: int):
    """The k nearest rows of each query in one cell: query id, row id, exact distance."""
    out = []
    square = (x * x).sum(axis=1)
    step = max(1, TILE // max(1, len(x)))
    for a in range(0, len(asked), step):
        q, mine = asked[a : a + step], own[a : a + step]
        rough = square - 2 * (q @ x.T)
        rough[_own(ids, mine)] = np.inf
        near = rough < np.inf
        if len(x) > k:
            edge = np.partition(rough, k - 1, axis=1)[:, k - 1 : k]
            with np.errstate(invalid="ignore"):
                near &= rough <= edge + 1e-9 * (1 + np.abs(edge) + (q * q).sum(axis=1)[:, None])
        query, row = np.nonzero(near)
        exact = np.sqrt(((x[row] - q[query]) ** 2).sum(axis=1))
        order = np.lexsort((ids[row], exact, query))
        query, row, exact = query[order], row[order], exact[order]
        place = np.arange(len(query)) - np.searchsorted(query, query)
        best = place < k
        out.append((mine[query[best]], ids[row[best]], exact[best]))
    return [np.concatenate(c) for c in zip(*out, strict=True)]


def _nearest(k: int):
    def search(rows: pa.Table, queries: pa.Table) -> pa.Table:
        cols = [[], [], []]
        if rows.num_rows and queries.num_rows:
            cols = nearest(
                _matrix(rows.column("vector")), np.asarray(rows.column("vec_id")),
                _matrix(queries.column("vector")), np.asarray(queries.column("vec_id")), k,
            )
        kinds = (pa.int64(), pa.int64(), pa.float64())
        return pa.table([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], ["query_id", "vec_id", "score"])

    return search


def search(
    vectors: DataFrame,
    is_query: Column,
    k: int = K,
    parts: int | None = None,
    sample: int = SAMPLE,
    id_column: str = "vec_id",
    vector_column: str = "embedding",
) -> DataFrame:
    """Each query's k nearest found: ``query_id``, ``rank``, ``vec_id``, ``score``."""
    rows = vectors.select(
        F.col(id_column).cast("long").alias("vec_id"),
        F.col(vector_column).alias("vector"),
        is_query.alias("_query"),
    ).filter("vec_id IS NOT NULL")
    common = (
        rows.filter("vector IS NOT NULL")
        .groupBy(F.size("vector").alias("dim"))
        .count()
        .orderBy(F.desc("count"), "dim")
        .first()
    )
    dim, n = (common[0], common[1]) if common else (0, 0)
    rows = rows.filter(usable(F.col("vector"), dim))
    picked = rows.select("vector").orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample).toPandas()
    if not len(picked):
        return vectors.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    index = learn(np.array(picked["vector"].tolist(), np.float64), parts or parts_for(n), k)
    kind = rows.schema["vector"].dataType.simpleString()  # moved as given, computed in double precision
    homes = rows.select("vec_id", "vector").mapInArrow(_homes(index), f"vec_id long, vector {kind}, part int")
    sizes = {r[0]: r[1] for r in homes.groupBy("part").count().collect()}  # at most ``parts`` rows
    asking = rows.filter("_query").groupBy("vec_id").agg(F.min("vector").alias("vector"))
    routed = asking.mapInArrow(_routes(index, sizes, k), f"vec_id long, vector {kind}, part int")
    query_blocks = max(1, -(-asking.count() // QUERY_ROWS))
    blocks = F.element_at(F.array(*[F.lit(max(1, -(-sizes.get(p, 0) // CELL_ROWS))) for p in range(index.parts)]), F.col("part") + 1)
    hashed = lambda m: F.pmod(F.xxhash64("vec_id"), m).cast("int")
    every = lambda m: F.explode(F.sequence(F.lit(0), m - 1))
    stored = homes.withColumn("block", hashed(blocks)).withColumn("asked", every(F.lit(query_blocks)))
    probing = routed.withColumn("asked", hashed(F.lit(query_blocks))).withColumn("block", every(blocks))
    cell = ["part", "block", "asked"]
    found = stored.groupBy(*cell).cogroup(probing.groupBy(*cell)).applyInArrow(_nearest(k), _FOUND)
    best = W.partitionBy("query_id").orderBy("score", "vec_id")
    return (
        found.withColumn("rank", F.row_number().over(best))
        .filter(F.col("rank") <= k)
        .select("query_id", "rank", "vec_id", "score")
    )


def op3_neighbours(spark, sf_dir: str) -> DataFrame:
    """Ten nearest of every hundredth vector among all vectors."""
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return search(vectors, F.col("vec_id") % 100 == 0)
