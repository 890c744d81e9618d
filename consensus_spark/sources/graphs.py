"""Communication graphs: small link lists on the driver, edges as DataFrames."""

from __future__ import annotations

import itertools
import random
from collections import deque

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from consensus_spark.sources.tables import EDGE, LINK

Links = list[tuple[int, int]]

# The seeded six-worker graph and its cover, and the worked four-worker example.
SIX: Links = [(0, 3), (3, 4), (1, 4), (1, 2), (2, 5), (0, 4), (2, 4), (3, 5)]
SIX_COVER: Links = [(0, 3), (3, 4), (1, 4), (1, 2), (2, 5)]
FOUR: Links = [(0, 1), (1, 2), (2, 3), (0, 2)]
FOUR_COVER: Links = [(0, 1), (1, 2), (2, 3)]


def norm(links) -> Links:
    return sorted({(min(a, b), max(a, b)) for a, b in links if a != b})


def neighbours(links: Links, n: int) -> list[set[int]]:
    near: list[set[int]] = [set() for _ in range(n)]
    for a, b in links:
        near[a].add(b)
        near[b].add(a)
    return near


def components(links: Links, n: int) -> list[int]:
    """Smallest reachable worker of each worker."""
    near, label = neighbours(links, n), [-1] * n
    for s in range(n):
        if label[s] < 0:
            todo = deque([s])
            label[s] = s
            while todo:
                for v in near[todo.popleft()]:
                    if label[v] < 0:
                        label[v] = s
                        todo.append(v)
    return label


def is_connected(links: Links, n: int) -> bool:
    return n <= 1 or set(components(links, n)) == {0}


def diameter(links: Links, n: int) -> int:
    near, worst = neighbours(links, n), 0
    for s in range(n):
        far, todo = {s: 0}, deque([s])
        while todo:
            u = todo.popleft()
            for v in near[u]:
                if v not in far:
                    far[v] = far[u] + 1
                    todo.append(v)
        if len(far) < n:
            raise ValueError("graph is not connected")
        worst = max(worst, *far.values())
    return worst


def graph(kind: str, n: int, seed: int = 0, degree: int = 2, chance: float = 0.4) -> Links:
    """``random`` (repaired by a random tree), ``ring``, ``path``, ``star``, ``complete``,
    ``grid``, ``tree``, ``regular``."""
    rng = random.Random(seed)
    pairs = list(itertools.combinations(range(n), 2))
    if kind == "random":
        links = [p for p in pairs if rng.random() < chance]
        order = list(range(n))
        rng.shuffle(order)
        for i in range(1, n):
            if not is_connected([(order.index(a), order.index(b)) for a, b in norm(links) if order.index(a) <= i and order.index(b) <= i], i + 1):
                links.append((order[i], order[rng.randrange(i)]))
        while not is_connected(norm(links), n):
            label = components(norm(links), n)
            other = rng.choice([v for v in range(n) if label[v] != 0])
            links.append((rng.choice([v for v in range(n) if label[v] == 0]), other))
        return norm(links)
    if kind == "ring":
        return norm((i, (i + 1) % n) for i in range(n))
    if kind == "path":
        return norm((i, i + 1) for i in range(n - 1))
    if kind == "star":
        return norm((0, i) for i in range(1, n))
    if kind == "complete":
        return pairs
    if kind == "tree":
        return norm((i, rng.randrange(i)) for i in range(1, n))
    if kind == "grid":
        wide = max(w for w in range(1, n + 1) if n % w == 0 and w * w <= n)
        side = n // wide
        across = [(i, i + 1) for i in range(n) if (i + 1) % side]
        return norm(across + [(i, i + side) for i in range(n - side)])
    if kind == "regular":
        return norm((i, (i + k) % n) for i in range(n) for k in range(1, degree // 2 + 1))
    raise ValueError(f"no topology {kind}")


def edges(spark: SparkSession, links: Links) -> DataFrame:
    """Both directions of every link."""
    return spark.createDataFrame([p for a, b in links for p in ((a, b), (b, a))], EDGE)


def link_table(spark: SparkSession, links: Links) -> DataFrame:
    return spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(links)], LINK)


def links_of(edge: DataFrame, most: int = 1_000_000) -> Links:
    """A graph's links on the driver; its size is checked first."""
    if edge.count() > 2 * most:
        raise ValueError("graph too large to be searched on the driver")
    return norm((r["src"], r["dst"]) for r in edge.collect())


def nation_region_edges(nation: DataFrame) -> DataFrame:
    """A clique per region and a ring over each region's smallest nation."""
    n = nation.select(F.col("n_nationkey").cast("int").alias("id"), F.col("n_regionkey").cast("int").alias("region"))
    a, b = n.alias("a"), n.alias("b")
    clique = a.join(b, (F.col("a.region") == F.col("b.region")) & (F.col("a.id") != F.col("b.id"))).select(
        F.col("a.id").alias("src"), F.col("b.id").alias("dst")
    )
    heads = n.groupBy("region").agg(F.min("id").alias("id"))
    rings = heads.agg(F.array_sort(F.collect_list("id")).alias("h"))  # one head per region
    step = rings.select(F.posexplode("h").alias("i", "u"), "h").select(
        "u", F.element_at("h", (F.col("i") + 1) % F.size("h") + 1).alias("v")
    )
    ring = step.filter("u <> v").select(F.inline(F.array(F.struct(F.col("u").alias("src"), F.col("v").alias("dst")), F.struct(F.col("v").alias("src"), F.col("u").alias("dst")))))
    return clique.unionByName(ring).distinct()
