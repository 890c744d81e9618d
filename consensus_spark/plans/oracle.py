"""Shared parts of the DuckDB statements."""

from __future__ import annotations

from consensus_spark.sources.graphs import SIX, SIX_COVER, Links


def values(name: str, columns: str, rows) -> str:
    body = ", ".join("(" + ", ".join(map(str, r)) + ")" for r in rows)
    cols = columns.split(", ")
    casts = ", ".join(f"CAST({c} AS INT) AS {c}" for c in cols)
    return f"{name} AS (SELECT {casts} FROM (VALUES {body}) v({columns}))"


def edge_values(links: Links = SIX, name: str = "edges") -> str:
    return values(name, "src, dst", [p for a, b in links for p in ((a, b), (b, a))])


def cover_values(cover: Links = SIX_COVER) -> str:
    return values("cover", "lid, a, b", [(i, a, b) for i, (a, b) in enumerate(cover)])


def times(n: int = 6) -> str:
    return f"""ev AS (SELECT CAST(user_id % {n} AS INT) AS worker, value AS t,
    CAST(row_number() OVER (PARTITION BY user_id % {n} ORDER BY ts, event_id) AS INT) AS k FROM events WHERE value IS NOT NULL),
  times AS (SELECT k, worker, t FROM ev WHERE k IN (SELECT k FROM ev GROUP BY k HAVING count(*) = {n}))"""


LINKS = """lt AS (SELECT x.k, c.lid, greatest(x.t, y.t) AS c FROM cover c
    JOIN times x ON x.worker = c.a JOIN times y ON y.worker = c.b AND y.k = x.k)"""


def schedule(d: int = 5, shift: int = 0) -> str:
    """Needs times, cover, lt; recursion over the steps of all epochs at once."""
    return f"""ls AS (SELECT k, list(struct_pack(c := c, lid := lid) ORDER BY c, lid) AS links FROM lt GROUP BY k),
  st AS (SELECT k, CAST((k - 1 - {shift}) // {d} + {shift} AS INT) AS epoch, CAST((k - 1 - {shift}) % {d} + 1 AS INT) AS step, links
    FROM ls WHERE k > {shift}),
  fold AS (
    SELECT k, epoch, step, links[1].lid AS lid, links[1].c AS cutoff,
      CAST(len(list_filter(links, lambda x: x.c = links[1].c)) AS INT) AS n_tied, [links[1].lid] AS used
    FROM st WHERE step = 1
    UNION ALL
    SELECT k, epoch, step, free[1].lid, free[1].c, CAST(len(list_filter(free, lambda x: x.c = free[1].c)) AS INT),
      list_append(used, free[1].lid)
    FROM (SELECT s.k, s.epoch, s.step, f.used, list_filter(s.links, lambda x: NOT list_contains(f.used, x.lid)) AS free
      FROM fold f JOIN st s ON s.epoch = f.epoch AND s.step = f.step + 1) q),
  schedule AS (SELECT k, epoch, step, lid, cutoff, n_tied FROM fold)"""


ACTIVE = """active AS (SELECT x.k, e.src, e.dst FROM edges e JOIN times x ON x.worker = e.src
    JOIN times y ON y.worker = e.dst AND y.k = x.k JOIN schedule s ON s.k = x.k WHERE x.t <= s.cutoff AND y.t <= s.cutoff)"""

FULL = "active AS (SELECT t.k, e.src, e.dst FROM times t JOIN edges e ON e.src = t.worker)"

METROPOLIS = """deg AS (SELECT k, dst AS worker, count(*) AS q FROM active GROUP BY k, dst),
  offd AS (SELECT a.k, a.src, a.dst, 1.0::DOUBLE / (1 + greatest(x.q, y.q)) AS w FROM active a
    JOIN deg x ON x.k = a.k AND x.worker = a.src JOIN deg y ON y.k = a.k AND y.worker = a.dst),
  mix AS (SELECT * FROM offd UNION ALL
    SELECT t.k, t.worker, t.worker, 1.0::DOUBLE - coalesce((SELECT sum(w) FROM offd o WHERE o.k = t.k AND o.dst = t.worker), 0.0::DOUBLE)
    FROM times t)"""


def path_cover(d: int = 5, n: int = 6) -> str:
    """All parts of the six-worker plan, ready for a final select."""
    return f"WITH RECURSIVE {times(n)}, {edge_values()}, {cover_values()}, {LINKS}, {schedule(d)}, {ACTIVE}"


def full_wait(n: int = 6) -> str:
    return f"WITH {times(n)}, {edge_values()}, {FULL}"


DURATION = "SELECT t.k, max(t.t) AS duration FROM times t WHERE EXISTS (SELECT 1 FROM {a} a WHERE a.k = t.k AND a.src = t.worker) GROUP BY t.k"
