"""DuckDB SQL for graphs, batches and whole rank runs, written from the
definitions and independent of the DataFrame code."""

from __future__ import annotations

from ..sources.catalog import GRID_WIDTH, NEIGHBOURS


def _name_id(expr: str) -> str:
    return f"CAST(('0x' || substr(md5({expr}), 1, 15)) AS BIGINT)"


_PARTIES = "SELECT c_custkey * 2 AS vid FROM customer UNION SELECT s_suppkey * 2 + 1 FROM supplier"

#: graph: (directed pairs, vertices, undirected)
PAIRS: dict[str, tuple[str, str, bool]] = {
    "trade": ("SELECT o_custkey * 2 AS src, l_suppkey * 2 + 1 AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey", _PARTIES, True),
    "catalog": ("SELECT l_partkey * 2 AS src, l_suppkey * 2 + 1 AS dst FROM lineitem", "SELECT p_partkey * 2 AS vid FROM part UNION SELECT s_suppkey * 2 + 1 FROM supplier", True),
    "web": (
        f"""SELECT {_name_id("'page ' || url")} AS src, {_name_id("'target ' || t")} AS dst FROM (SELECT url, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS t FROM pages)
        UNION ALL SELECT h, p FROM (SELECT {_name_id("'host ' || regexp_extract(url, '^[a-z]+://([^/]*)', 1)")} AS h, {_name_id("'page ' || url")} AS p FROM pages)
        UNION ALL SELECT p, h FROM (SELECT {_name_id("'host ' || regexp_extract(url, '^[a-z]+://([^/]*)', 1)")} AS h, {_name_id("'page ' || url")} AS p FROM pages)""",
        f"SELECT {_name_id(chr(39) + 'page ' + chr(39) + ' || url')} AS vid FROM pages",
        False,
    ),
    "geo": (
        """SELECT CAST(n_nationkey AS BIGINT) * 4 + 1 AS src, CAST(n_regionkey AS BIGINT) * 4 AS dst FROM nation
        UNION ALL SELECT c_custkey * 4 + 2, CAST(c_nationkey AS BIGINT) * 4 + 1 FROM customer
        UNION ALL SELECT s_suppkey * 4 + 3, CAST(s_nationkey AS BIGINT) * 4 + 1 FROM supplier""",
        "SELECT CAST(r_regionkey AS BIGINT) * 4 AS vid FROM region",
        True,
    ),
    "chain": ("SELECT o_orderkey AS src, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS dst FROM orders", "SELECT o_orderkey AS vid FROM orders", True),
    "line": ("SELECT a.o_orderkey AS src, b.o_orderkey AS dst FROM orders a JOIN orders b ON b.o_orderkey = a.o_orderkey + 1", "SELECT o_orderkey AS vid FROM orders", True),
    "grid": (
        f"SELECT a.o_orderkey AS src, b.o_orderkey AS dst FROM orders a JOIN orders b ON (b.o_orderkey = a.o_orderkey + 1 AND a.o_orderkey % {GRID_WIDTH} <> {GRID_WIDTH - 1}) OR b.o_orderkey = a.o_orderkey + {GRID_WIDTH}",
        "SELECT o_orderkey AS vid FROM orders",
        True,
    ),
    "turns": ("SELECT conv_id * 16 + turn AS src, lead(conv_id * 16 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM conversations", "SELECT conv_id * 16 + turn AS vid FROM conversations", False),
    "knn": (
        f"""SELECT src, dst FROM (SELECT a.vec_id AS src, b.vec_id AS dst,
          row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 9) DESC, b.vec_id) AS r
          FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE r <= {NEIGHBOURS}""",
        "SELECT vec_id AS vid FROM embeddings",
        False,
    ),
}
#: temporal graph: (rows with seq, vertices, undirected)
ROWS: dict[str, tuple[str, str, bool]] = {
    "handoff": (
        """SELECT row_number() OVER (ORDER BY ts, event_id) - 1 AS seq, src, dst FROM (SELECT ts, event_id, user_id AS src,
          lead(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL""",
        "SELECT DISTINCT user_id AS vid FROM events",
        False,
    ),
    "purchases": (
        """SELECT row_number() OVER (ORDER BY o_orderdate, l_orderkey, l_linenumber, l_partkey, l_suppkey) - 1 AS seq,
          o_custkey * 2 AS src, l_suppkey * 2 + 1 AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey""",
        _PARTIES,
        True,
    ),
}


def graph_ctes(name: str, prefix: str = "g", pairs: str | None = None, vertices: str | None = None, undirected: bool | None = None) -> str:
    """CTEs <prefix>_v(vid) and <prefix>_e(src, dst), loops included."""
    if name in PAIRS:
        own = PAIRS[name]
    elif name in ROWS:
        own = (f"SELECT src, dst FROM ({ROWS[name][0]})", *ROWS[name][1:])
    else:
        own = ("", "", False)
    pairs, vertices, undirected = pairs or own[0], vertices or own[1], own[2] if undirected is None else undirected
    turned = f" UNION ALL SELECT dst, src FROM {prefix}_p" if undirected else ""
    return f"""{prefix}_p AS MATERIALIZED (SELECT src, dst FROM ({pairs}) WHERE src IS NOT NULL AND dst IS NOT NULL
), {prefix}_v AS MATERIALIZED (SELECT vid FROM ({vertices}) UNION SELECT src FROM {prefix}_p UNION SELECT dst FROM {prefix}_p
), {prefix}_e AS MATERIALIZED (SELECT src, dst FROM {prefix}_p{turned} UNION SELECT vid, vid FROM {prefix}_v)"""


def batch_ctes(fraction: float, seed: int = 1, mix: str = "both", g: str = "g", b: str = "b") -> str:
    """CTE <b>(src, dst, op): the random batch of a fraction of all edges."""
    d, i = {"both": (1, 1), "del": (2, 0), "ins": (0, 2)}[mix]
    k = f"(SELECT greatest(1, CAST(floor(count(*) * {fraction} / 2) AS BIGINT)) FROM {g}_e)"
    return f"""{b}_d AS (
  SELECT src, dst, row_number() OVER (ORDER BY md5('d-' || src || '-' || dst || '-{seed}'), src, dst) AS r FROM {g}_e WHERE src <> dst
), {b}_s AS (SELECT vid AS src, row_number() OVER (ORDER BY md5('src-' || vid || '-{seed}'), vid) AS r FROM {g}_v
), {b}_t AS (SELECT vid AS dst, row_number() OVER (ORDER BY md5('dst-' || vid || '-{seed}'), vid) AS r FROM {g}_v
), {b}_i AS (
  SELECT s.src, t.dst, row_number() OVER (ORDER BY s.r) AS r FROM {b}_s s JOIN {b}_t t USING (r) ANTI JOIN {g}_e e ON e.src = s.src AND e.dst = t.dst
  WHERE s.src <> t.dst AND s.r <= 4 * {i} * {k}
), {b} AS MATERIALIZED (
  SELECT src, dst, '-' AS op FROM {b}_d WHERE r <= {d} * {k} UNION ALL SELECT src, dst, '+' FROM {b}_i WHERE r <= {i} * {k})"""


def applied_ctes(g: str = "g", b: str = "b", h: str = "h") -> str:
    """CTEs <h>_v and <h>_e: the snapshot after the batch."""
    return f"""{h}_v AS (SELECT vid FROM {g}_v
), {h}_e AS MATERIALIZED (SELECT src, dst FROM {g}_e e WHERE NOT EXISTS (SELECT 1 FROM {b} x WHERE x.op = '-' AND x.src = e.src AND x.dst = e.dst AND x.src <> x.dst)
  UNION SELECT src, dst FROM {b} WHERE op = '+' AND src IN (SELECT vid FROM {g}_v) AND dst IN (SELECT vid FROM {g}_v))"""


def links_cte(g: str) -> str:
    return f"{g}_l AS MATERIALIZED (SELECT src, dst, 1.0::DOUBLE / count(*) OVER (PARTITION BY src) AS w FROM {g}_e), {g}_n AS MATERIALIZED (SELECT CAST(count(*) AS DOUBLE) AS n FROM {g}_v)"


def marks_cte(g: str = "g", h: str = "h", b: str = "b", name: str = "m") -> str:
    return f"{name} AS MATERIALIZED (SELECT DISTINCT dst AS vid FROM (SELECT src, dst FROM {g}_e UNION ALL SELECT src, dst FROM {h}_e) WHERE src IN (SELECT src FROM {b}))"


def reach_cte(h: str = "h", start: str = "m", name: str = "reached") -> str:
    return f"{name} AS (SELECT vid FROM {start} UNION SELECT dst FROM {name} JOIN {h}_e ON src = vid)"


def sync_cte(out: str, h: str, ranks: str | None, affected: str | None, frontier_tol: float | None, passes: int, tol: float | None = None, alpha: float = 0.85) -> str:
    """CTE <out>(p, vid, rank, prev, aff, lin): all passes of a two-buffer run.
    ranks / affected: CTE names (vid, rank) / (vid). tol: stop when met."""
    first = f"coalesce(r.rank, 1 / n)" if ranks else "1 / n"
    join = f" LEFT JOIN {ranks} r ON r.vid = v.vid" if ranks else ""
    aff = f"v.vid IN (SELECT vid FROM {affected})" if affected else "true"
    mark = f"bool_or(abs(rank - prev) > {frontier_tol!r})" if frontier_tol is not None else "false"
    stop = f" AND (p = 0 OR md > {tol!r})" if tol is not None else ""
    return f"""{out} AS (
  SELECT 0 AS p, v.vid, {first} AS rank, {first} AS prev, {aff} AS aff, 0::BIGINT AS lin FROM {h}_v v CROSS JOIN {h}_n{join}
  UNION ALL
  SELECT p + 1, vid, CASE WHEN a THEN (1.0 - {alpha}) / n + {alpha} * mass ELSE own END, own, a, lin FROM (
    SELECT p, dst AS vid, bool_or(src = dst AND aff) OR {mark} AS a, max(CASE WHEN src = dst THEN rank END) AS own, sum(rank * w) AS mass, count(*) AS lin
    FROM (SELECT *, max(abs(rank - prev)) OVER () AS md FROM {out}) s JOIN {h}_l l ON l.src = s.vid WHERE p < {passes}{stop} GROUP BY p, dst) x CROSS JOIN {h}_n)"""


def async_cte(out: str, h: str, ranks: str | None, affected: str | None, frontier_tol: float | None, passes: int, blocks: int, tol: float = 1e-10, alpha: float = 0.85, close_rule: str = "marks", flag_rule: str = "reopen", until_closed: bool = False) -> str:
    """CTE <out>(i, vid, rank, prev, aff, open, just): all steps of an in-place
    run; a pass is ``blocks`` steps and one that only takes up marks."""
    first = f"coalesce(r.rank, 1 / n)" if ranks else "1 / n"
    join = f" LEFT JOIN {ranks} r ON r.vid = v.vid" if ranks else ""
    aff = f"v.vid IN (SELECT vid FROM {affected})" if affected else "true"
    opened = "false" if flag_rule == "literal" else aff
    mark = f"bool_or(abs(rank - prev) > {frontier_tol!r})" if frontier_tol is not None else "false"
    again = "mark AND NOT was_just" if close_rule == "marks" else "mark AND NOT was_aff"
    closes = "abs(new - own) > {t} AND o" if flag_rule != "reopen" else "abs(new - own) > {t}"
    per = blocks + 1
    stop = f" AND (i % {per} <> 0 OR i = 0 OR any_open)" if until_closed else ""
    return f"""{out} AS (
  SELECT 0 AS i, v.vid, {first} AS rank, {first} AS prev, {aff} AS aff, {opened} AS open, false AS just, 0::BIGINT AS lin FROM {h}_v v CROSS JOIN {h}_n{join}
  UNION ALL
  SELECT i + 1, vid, new, own, a, CASE WHEN now THEN {closes.format(t=repr(tol))} ELSE o END, now, lin FROM (
    SELECT *, CASE WHEN now THEN (1.0 - {alpha}) / n + {alpha} * mass ELSE own END AS new FROM (
      SELECT *, was_aff OR mark AS a, was_open OR ({again}) AS o, (was_aff OR mark) AND i % {per} < {blocks} AND ((vid % {blocks}) + {blocks}) % {blocks} = i % {per} AS now FROM (
        SELECT i, dst AS vid, bool_or(src = dst AND aff) AS was_aff, bool_or(src = dst AND open) AS was_open, bool_or(src = dst AND just) AS was_just,
               {mark} AS mark, max(CASE WHEN src = dst THEN rank END) AS own, sum(rank * w) AS mass, count(*) AS lin
        FROM (SELECT *, bool_or(open) OVER () AS any_open FROM {out}) s JOIN {h}_l l ON l.src = s.vid WHERE i < {passes * per}{stop} GROUP BY i, dst)) y CROSS JOIN {h}_n) z)"""


def last(out: str, step: str = "p") -> str:
    return f"(SELECT * FROM {out} WHERE {step} = (SELECT max({step}) FROM {out}))"


def pico(column: str = "rank") -> str:
    return f"CAST(round({column} * 1e12) AS BIGINT)"


def with_(ctes: list[str], body: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(ctes) + "\n" + body
