"""DuckDB statements with the same answers as the queries.

Components and paths are keyed recursions, PageRank is a recursion with one
aggregate per round; none of them shares code with the engine.
"""

from __future__ import annotations

EDGES = {
    "links": """
        SELECT page_id * 8 + 6 AS src, CAST('0x' || substr(md5(href), 1, 14) AS BIGINT) * 8 + 7 AS dst
        FROM (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages)""",
    "stars": "SELECT o_orderkey * 8 + 3 AS src, o_custkey * 8 + 2 AS dst FROM orders",
    "geo": """
        SELECT c_custkey * 8 + 2 AS src, c_nationkey::BIGINT * 8 + 4 AS dst FROM customer
        UNION ALL SELECT s_suppkey * 8 + 1, s_nationkey::BIGINT * 8 + 4 FROM supplier
        UNION ALL SELECT n_nationkey::BIGINT * 8 + 4, n_regionkey::BIGINT * 8 + 5 FROM nation""",
    "chain": """
        SELECT src, dst FROM (SELECT event_id AS src, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS dst FROM events)
        WHERE dst IS NOT NULL""",
    "supply": "SELECT l_partkey * 8 AS src, l_suppkey * 8 + 1 AS dst FROM lineitem",
    "trade": "SELECT o_custkey * 8 + 2 AS src, l_partkey * 8 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "basket": """
        SELECT DISTINCT a.l_partkey * 8 AS src, b.l_partkey * 8 AS dst
        FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey""",
    "talk": """
        SELECT src, dst FROM (SELECT conv_id * 1000 + turn AS src,
               lead(conv_id * 1000 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM conversations)
        WHERE dst IS NOT NULL""",
    "twins": """
        SELECT doc_id AS src, dst FROM (SELECT doc_id, min(doc_id) OVER (PARTITION BY md5(text)) AS dst FROM documents) WHERE doc_id <> dst""",
    "similar": """
        SELECT a.vec_id AS src, b.vec_id AS dst FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id
        WHERE list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) > 0.3""",
}


def base(name: str, directed: bool = False) -> str:
    """Common tables: edges ``e`` as the engine has them, vertices ``v``."""
    back = "" if directed else " UNION SELECT dst, src FROM raw WHERE src <> dst"
    return f"""raw AS ({EDGES[name]}),
e AS (SELECT src, dst FROM raw WHERE src <> dst{back if back else ' GROUP BY src, dst'}),
v AS (SELECT src AS id FROM e UNION SELECT dst FROM e)"""


def components(name: str, directed: bool = False) -> str:
    return f"""
WITH RECURSIVE {base(name, directed)},
c(id, component) USING KEY (id) AS (
  SELECT id, id FROM v
  UNION
  SELECT e.dst, min(n.component) FROM c n JOIN e ON e.src = n.id JOIN recurring.c o ON o.id = e.dst
  WHERE n.component < o.component GROUP BY e.dst
)
SELECT id, component FROM c"""


def paths(name: str) -> str:
    return f"""
WITH RECURSIVE {base(name)},
p(id, distance) USING KEY (id) AS (
  SELECT min(id), 0::BIGINT FROM v
  UNION
  SELECT e.dst, min(n.distance) + 1 FROM p n JOIN e ON e.src = n.id LEFT JOIN recurring.p o ON o.id = e.dst
  WHERE o.distance IS NULL OR n.distance + 1 < o.distance GROUP BY e.dst
)
SELECT v.id, p.distance FROM v LEFT JOIN p ON p.id = v.id"""


def weighted_paths() -> str:
    return """
WITH RECURSIVE raw AS (SELECT o_custkey * 8 + 2 AS src, l_partkey * 8 AS dst, count(*) AS weight
                       FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL),
e AS (SELECT * FROM raw UNION ALL SELECT dst, src, weight FROM raw),
v AS (SELECT DISTINCT src AS id FROM e),
p(id, distance) USING KEY (id) AS (
  SELECT min(id), 0::BIGINT FROM v
  UNION
  SELECT e.dst, min(n.distance + e.weight) FROM p n JOIN e ON e.src = n.id LEFT JOIN recurring.p o ON o.id = e.dst
  WHERE o.distance IS NULL OR n.distance + e.weight < o.distance GROUP BY e.dst
)
SELECT v.id, p.distance FROM v LEFT JOIN p ON p.id = v.id"""


def pagerank(name: str, directed: bool = False, rounds: int = 10, digits: int = 10, keep: int | None = None, spread: bool = False) -> str:
    """An edge of no weight from each vertex to itself keeps every vertex in
    every round.  ``keep`` cuts mailboxes at the lowest sender ids; with
    ``spread`` the rank of vertices without out-edges goes to all."""
    cut = f"QUALIFY row_number() OVER (PARTITION BY e.dst ORDER BY e.src) <= {keep}" if keep else ""
    if spread:
        step = f"""SELECT t + 1, w.dst, any_value(0.15 / n.n) + 0.85 * (sum(r.rank * w.share) + any_value(r.leak) / any_value(n.n)), any_value(w.dangles)
  FROM (SELECT r.*, coalesce(sum(CASE WHEN r.dangles THEN r.rank END) OVER (), 0) AS leak FROM r) r JOIN w ON w.src = r.id, n
  WHERE t < {rounds} GROUP BY t, w.dst"""
        return f"""
WITH RECURSIVE {base(name, directed)}, n AS (SELECT count(*)::DOUBLE AS n FROM v),
d AS (SELECT v.id, count(e.src) AS degree FROM v LEFT JOIN e ON e.src = v.id GROUP BY v.id),
w AS (SELECT e.src, e.dst, 1.0::DOUBLE / a.degree AS share, b.degree = 0 AS dangles FROM e JOIN d a ON a.id = e.src JOIN d b ON b.id = e.dst
      UNION ALL SELECT id, id, 0::DOUBLE, degree = 0 FROM d),
r(t, id, rank, dangles) AS (SELECT 0, id, 1 / n, degree = 0 FROM d, n UNION ALL {step})
SELECT id, round(rank, {digits}) AS rank FROM r WHERE t = {rounds}"""
    return f"""
WITH RECURSIVE {base(name, directed)}, n AS (SELECT count(*)::DOUBLE AS n FROM v),
d AS (SELECT src, count(*) AS degree FROM e GROUP BY src),
w AS (SELECT e.src, e.dst, 1.0::DOUBLE / degree AS share FROM e JOIN d USING (src) {cut} UNION ALL SELECT id, id, 0::DOUBLE FROM v),
r(t, id, rank) AS (
  SELECT 0, id, 1 / n FROM v, n
  UNION ALL
  SELECT t + 1, w.dst, any_value(0.15 / n.n) + 0.85 * sum(r.rank * w.share) FROM r JOIN w ON w.src = r.id, n WHERE t < {rounds} GROUP BY t, w.dst
)
SELECT id, round(rank, {digits}) AS rank FROM r WHERE t = {rounds}"""


def async_pagerank(name: str, passes: int = 10, blocks: int = 2, digits: int = 10) -> str:
    """Passes over blocks of the identifiers' range, one after another, as one
    table of shares for each turn."""
    tables, last = [], "s0"
    for turn in range(passes * blocks):
        tables.append(
            f"""s{turn + 1} AS MATERIALIZED (
  SELECT s.id, s.block, s.degree, CASE WHEN s.block = {turn % blocks} THEN 0.15 / n.n + 0.85 * coalesce(m.got, 0) ELSE s.rank END AS rank,
         CASE WHEN s.block = {turn % blocks} THEN (0.15 / n.n + 0.85 * coalesce(m.got, 0)) / s.degree ELSE s.share END AS share
  FROM {last} s, n LEFT JOIN (SELECT e.dst, sum(t.share) AS got FROM e JOIN {last} t ON t.id = e.src GROUP BY e.dst) m ON m.dst = s.id)"""
        )
        last = f"s{turn + 1}"
    return f"""
WITH {base(name)}, n AS (SELECT count(*)::DOUBLE AS n FROM v),
b AS (SELECT min(id) AS low, CAST(ceil((max(id) - min(id) + 1) / {blocks}.0) AS BIGINT) AS width FROM v),
d AS (SELECT src AS id, count(*) AS degree FROM e GROUP BY src),
s0 AS MATERIALIZED (SELECT d.id, (d.id - b.low) // b.width AS block, d.degree, 1 / n.n AS rank, 1 / n.n / d.degree AS share FROM d, b, n),
{", ".join(tables)}
SELECT id, round(rank, {digits}) AS rank FROM {last}"""


def component_rounds(name: str) -> str:
    """The work of spreading least labels: vertices that run, their messages, and
    outboxes probed in vain when all are pulled, superstep by superstep."""
    return f"""
WITH RECURSIVE {base(name)},
d AS (SELECT src AS id, count(*) AS degree FROM e GROUP BY src),
w AS (SELECT src, dst, 1 AS far FROM e UNION ALL SELECT id, id, 0 FROM v),
r(t, id, label, fell) AS (
  SELECT 0, id, id, true FROM v
  UNION ALL
  SELECT x.t + 1, x.id, x.label, x.label < x.own FROM (
    SELECT r.t, w.dst AS id, min(r.label) AS label, min(CASE WHEN w.far = 0 THEN r.label END) AS own, bool_or(r.fell) AS going
    FROM (SELECT *, bool_or(fell) OVER () AS any_fell FROM r) r JOIN w ON w.src = r.id WHERE r.any_fell GROUP BY r.t, w.dst
  ) x
),
sent AS (SELECT r.t, sum(d.degree) AS messages FROM r JOIN d USING (id) WHERE r.fell GROUP BY r.t),
woken AS (SELECT r.t + 1 AS t, count(DISTINCT e.dst) AS n FROM r JOIN e ON e.src = r.id WHERE r.fell GROUP BY r.t)
SELECT CAST(s.t AS INT) AS superstep, CASE WHEN s.t = 0 THEN (SELECT count(*) FROM v) ELSE w.n END AS ran,
       CAST(coalesce(a.messages, 0) AS BIGINT) AS messages,
       CASE WHEN s.t = 0 THEN 0::BIGINT ELSE (SELECT count(*) FROM e) END AS probes,
       CASE WHEN s.t = 0 THEN 0::BIGINT ELSE CAST((SELECT count(*) FROM e) - b.messages AS BIGINT) END AS wasted_probes
FROM (SELECT DISTINCT t FROM r) s LEFT JOIN sent a ON a.t = s.t LEFT JOIN sent b ON b.t = s.t - 1 LEFT JOIN woken w ON w.t = s.t
WHERE s.t = 0 OR w.n > 0"""


def path_rounds(name: str) -> str:
    """The work of paths with bypass: the senders of step t are the vertices at
    distance t, and what they tell runs in the next."""
    return f"""
WITH dist AS ({paths(name)}), {base(name)},
steps AS (SELECT unnest(generate_series(0, (SELECT max(distance) + 1 FROM dist))) AS t),
sent AS (SELECT d.distance AS t, count(*) AS messages, count(DISTINCT e.dst) AS woken FROM dist d JOIN e ON e.src = d.id WHERE d.distance IS NOT NULL GROUP BY d.distance),
rows AS (SELECT s.t, CASE WHEN s.t = 0 THEN (SELECT count(*) FROM v) ELSE b.woken END AS ran, coalesce(a.messages, 0) AS messages
         FROM steps s LEFT JOIN sent a ON a.t = s.t LEFT JOIN sent b ON b.t = s.t - 1 WHERE s.t = 0 OR b.woken > 0)
SELECT CAST(t AS INT) AS superstep, ran, ran AS checked, messages, 0::BIGINT AS probes FROM rows"""
