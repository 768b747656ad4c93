"""SQL that gives the rows of the graph queries, in DuckDB's dialect (keyed recursion)."""

from __future__ import annotations

from cellgraph.fixtures import EDGES_SQL, vertices_sql


def arcs(name: str, directed: bool = False) -> str:
    one = f"SELECT src, dst, weight FROM ({EDGES_SQL[name]})"
    return one if directed else f"{one} UNION ALL SELECT dst, src, weight FROM ({EDGES_SQL[name]})"


def spread(edges: str, vertices: str, greatest: bool = True, value: str = "vid") -> str:
    """``(v, lab)``: greatest (or least) value of each vertex's component over the given arcs."""
    pick, better = ("max", ">") if greatest else ("min", "<")
    return f"""
  WITH RECURSIVE e AS MATERIALIZED (SELECT DISTINCT src, dst FROM ({edges}) WHERE src <> dst), cc(v, lab) USING KEY (v) AS (
    SELECT vid, {value} FROM ({vertices})
    UNION
    SELECT e.dst, {pick}(u.lab) FROM cc u JOIN e ON u.v = e.src JOIN recurring.cc r ON r.v = e.dst WHERE u.lab {better} r.lab GROUP BY e.dst)
  SELECT v, lab FROM cc"""


def last_change(edges: str, vertices: str) -> str:
    """``n``: the round in which greatest ids that travel one arc a round change a value for the last time."""
    return f"""
  WITH RECURSIVE e AS MATERIALIZED (SELECT DISTINCT src, dst FROM ({edges}) WHERE src <> dst), cc(v, lab, round) USING KEY (v) AS (
    SELECT v, lab, 0 FROM ({vertices})
    UNION
    SELECT e.dst, max(u.lab), max(u.round) + 1 FROM cc u JOIN e ON u.v = e.src JOIN recurring.cc r ON r.v = e.dst WHERE u.lab > r.lab GROUP BY e.dst)
  SELECT max(round) AS n FROM cc"""


def components(name: str) -> str:
    return f"SELECT v AS vid, lab AS component FROM ({spread(arcs(name), vertices_sql(name))})"


def placed(name: str, pid: str) -> str:
    """Arcs with the parts of both ends; ``pid`` is an expression over {v}."""
    return f"SELECT src, dst, weight, {pid.format(v='src')} AS src_pid, {pid.format(v='dst')} AS dst_pid FROM ({arcs(name)})"


def cell_of(name: str, pid: str) -> str:
    inner = f"SELECT src, dst FROM ({placed(name, pid)}) WHERE src_pid = dst_pid"
    return f"SELECT v AS vid, {pid.format(v='v')} AS pid, lab AS cell_id FROM ({spread(inner, vertices_sql(name), False)})"


def links(name: str, pid: str) -> str:
    return f"""
  WITH cell AS MATERIALIZED ({cell_of(name, pid)})
  SELECT p.*, a.cell_id AS src_cell, b.cell_id AS dst_cell FROM ({placed(name, pid)}) p JOIN cell a ON a.vid = p.src JOIN cell b ON b.vid = p.dst"""


def distances(name: str, sources: list[int] | str, weighted: bool = False, directed: bool = False, kind: str = "BIGINT") -> str:
    """``sources``: ids, or SQL for one column of ids named v."""
    cost = f"weight::{kind}" if weighted else f"1::{kind}"
    seeds = f"SELECT v, 0::{kind} AS d FROM ({sources})" if isinstance(sources, str) else " UNION ALL ".join(f"SELECT {s}::BIGINT AS v, 0::{kind} AS d" for s in sources)
    return f"""
  WITH RECURSIVE e AS MATERIALIZED (SELECT src, dst, min({cost}) AS w FROM ({arcs(name, directed)}) WHERE src <> dst GROUP BY src, dst), sp(v, d) USING KEY (v) AS (
    SELECT v, d FROM ({seeds})
    UNION
    SELECT c.v, c.d FROM (SELECT e.dst AS v, min(u.d + e.w) AS d FROM sp u JOIN e ON e.src = u.v GROUP BY e.dst) c LEFT JOIN recurring.sp r ON r.v = c.v WHERE r.v IS NULL OR c.d < r.d)
  SELECT v AS vid, d AS dist FROM sp"""


def ranks(name: str, rounds: int, directed: bool = False, leak: bool = False, every_round: bool = False) -> str:
    lost = "0.0" if leak else "(SELECT coalesce(sum(r.rank), 0.0) FROM r JOIN deg d USING (vid) WHERE d.n = 0)"
    keep = "round, vid, rank" if every_round else "vid, rank"
    return f"""
  WITH RECURSIVE e AS MATERIALIZED (SELECT src, dst FROM ({arcs(name, directed)})), v AS MATERIALIZED (SELECT vid FROM ({vertices_sql(name)})),
  deg AS MATERIALIZED (SELECT v.vid, count(e.src) AS n FROM v LEFT JOIN e ON e.src = v.vid GROUP BY v.vid), total AS MATERIALIZED (SELECT count(*)::DOUBLE AS n FROM v),
  r(round, vid, rank) AS (
    SELECT 0, vid, 1.0::DOUBLE / (SELECT n FROM total) FROM v
    UNION ALL
    SELECT round + 1, vid, 0.15 / (SELECT n FROM total) + 0.85 * (sum(x) + max(loose) / (SELECT n FROM total)) FROM (
      SELECT round, e.dst AS vid, r.rank / d.n AS x, 0.0 AS loose FROM r JOIN deg d USING (vid) JOIN e ON e.src = r.vid WHERE round < {rounds}
      UNION ALL SELECT round, vid, 0.0, {lost} FROM r WHERE round < {rounds}) GROUP BY round, vid)
  SELECT {keep} FROM r {'' if every_round else f'WHERE round = {rounds}'}"""


def local_ranks(name: str, pid: str, rounds: int) -> str:
    """Ranks inside cells; in an undirected graph only one-vertex cells dangle, and those keep rank 1."""
    return f"""
  WITH RECURSIVE cell AS MATERIALIZED ({cell_of(name, pid)}), size AS MATERIALIZED (SELECT cell_id, count(*)::DOUBLE AS n FROM cell GROUP BY cell_id),
  e AS MATERIALIZED (SELECT src, dst FROM ({placed(name, pid)}) WHERE src_pid = dst_pid), deg AS MATERIALIZED (SELECT src AS vid, count(*) AS n FROM e GROUP BY src),
  r(round, vid, rank) AS (
    SELECT 0, vid, 1.0 / n FROM cell JOIN size USING (cell_id)
    UNION ALL
    SELECT round + 1, vid, max(base) + 0.85 * sum(x) FROM (
      SELECT round, e.dst AS vid, r.rank / d.n AS x, 0.0 AS base FROM r JOIN deg d USING (vid) JOIN e ON e.src = r.vid WHERE round < {rounds}
      UNION ALL SELECT round, r.vid, CASE WHEN d.n IS NULL THEN r.rank / s.n ELSE 0.0 END, 0.15 / s.n FROM r JOIN cell c ON c.vid = r.vid JOIN size s USING (cell_id) LEFT JOIN deg d ON d.vid = r.vid WHERE round < {rounds}) GROUP BY round, vid)
  SELECT r.vid, c.cell_id, r.rank FROM r JOIN cell c ON c.vid = r.vid WHERE round = {rounds}"""


def cell_ranks(name: str, pid: str, local_rounds: int, rounds: int) -> str:
    return f"""
  WITH RECURSIVE loc AS MATERIALIZED ({local_ranks(name, pid, local_rounds)}), lk AS MATERIALIZED ({links(name, pid)}),
  deg AS MATERIALIZED (SELECT src AS vid, count(*) AS n FROM lk GROUP BY src),
  w AS MATERIALIZED (SELECT src_cell, dst_cell, sum(loc.rank / deg.n) AS w FROM lk JOIN loc ON loc.vid = lk.src JOIN deg ON deg.vid = lk.src GROUP BY 1, 2),
  c AS MATERIALIZED (SELECT cell_id, count(*)::DOUBLE / (SELECT count(*) FROM loc) AS start, 1 - coalesce((SELECT sum(w.w) FROM w WHERE w.src_cell = loc.cell_id), 0) AS kept FROM loc GROUP BY cell_id),
  r(round, cell_id, rank) AS (
    SELECT 0, cell_id, start FROM c
    UNION ALL
    SELECT round + 1, cell_id, max(base) + 0.85 * sum(x) FROM (
      SELECT round, w.dst_cell AS cell_id, w.w * r.rank AS x, 0.0 AS base FROM r JOIN w ON w.src_cell = r.cell_id WHERE round < {rounds}
      UNION ALL SELECT round, r.cell_id, c.kept * r.rank, 0.15 * c.start FROM r JOIN c USING (cell_id) WHERE round < {rounds}) GROUP BY round, cell_id)
  SELECT cell_id, rank FROM r WHERE round = {rounds}"""
