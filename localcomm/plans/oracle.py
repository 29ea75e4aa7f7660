"""SQL text of the methods, for an engine with recursive queries: what the DataFrame plans must give."""

from __future__ import annotations

from localcomm.functions.sets import PRIME, draw_sql
from localcomm.operators.graph import UNIT
from localcomm.params import Params, derive_params

PARTS = """attrs AS (SELECT p_partkey AS node, list_sort(list_distinct([p_brand, p_type, 'size' || CAST(p_size // 10 AS VARCHAR)] || list_filter(regexp_split_to_array(lower(p_name), '[^a-z]+'), lambda w: len(w) >= 1))) AS x FROM part),
member AS (SELECT DISTINCT l_orderkey AS g, l_partkey AS m FROM lineitem WHERE l_returnflag = 'R'),
edges AS (SELECT DISTINCT a.m AS src, b.m AS dst FROM member a JOIN member b ON a.g = b.g WHERE a.m < b.m)"""

DOCS = """dlines AS (SELECT DISTINCT doc_id AS m, md5(lower(trim(line, ' '))) AS g FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents)),
dwords AS (SELECT DISTINCT doc_id, word FROM (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS word FROM documents) WHERE len(word) >= 6),
dfs AS (SELECT word, count(*) AS df FROM dwords GROUP BY word HAVING count(*) > 1),
rare AS (SELECT doc_id, word FROM (SELECT doc_id, word, row_number() OVER (PARTITION BY doc_id ORDER BY df, word) AS nth FROM dwords JOIN dfs USING (word)) WHERE nth <= 20),
attrs AS (SELECT d.doc_id AS node, coalesce(list_sort(list(word) FILTER (word IS NOT NULL)), []) AS x FROM documents d LEFT JOIN rare r ON r.doc_id = d.doc_id GROUP BY d.doc_id),
member AS (SELECT m, g FROM dlines WHERE g IN (SELECT g FROM dlines GROUP BY g HAVING count(*) <= 20)),
edges AS (SELECT DISTINCT a.m AS src, b.m AS dst FROM member a JOIN member b ON a.g = b.g WHERE a.m < b.m)"""

PAGES = """plinks AS (SELECT DISTINCT page_id AS m, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS g FROM pages),
attrs AS (SELECT page_id AS node, list_sort(list_distinct(list_filter(regexp_split_to_array(lower(regexp_replace(html, '<[^>]*>', ' ', 'g')), '[^a-z]+'), lambda w: len(w) >= 1))) AS x FROM pages),
member AS (SELECT m, g FROM plinks WHERE g IN (SELECT g FROM plinks GROUP BY g HAVING count(*) <= 50)),
edges AS (SELECT DISTINCT a.m AS src, b.m AS dst FROM member a JOIN member b ON a.g = b.g WHERE a.m < b.m)"""

USERS = """attrs AS (SELECT user_id AS node, list_sort(list_distinct(list(event_type || props))) AS x FROM events GROUP BY user_id),
member AS (SELECT DISTINCT user_id AS m, date_trunc('hour', ts) || '|' || props AS g FROM events),
edges AS (SELECT DISTINCT a.m AS src, b.m AS dst FROM member a JOIN member b ON a.g = b.g WHERE a.m < b.m)"""

CUSTOMERS = """attrs AS (SELECT c_custkey AS node, list_sort(list_distinct([c_mktsegment, n_name, r_name, 'bal' || CAST(CAST(floor(c_acctbal / 1000) AS BIGINT) AS VARCHAR)])) AS x FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey),
member AS (SELECT DISTINCT c_custkey AS m, c_nationkey || '|' || l_partkey AS g FROM customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey),
edges AS (SELECT DISTINCT a.m AS src, b.m AS dst FROM member a JOIN member b ON a.g = b.g WHERE a.m < b.m)"""

GRAPHS = {"parts": PARTS, "docs": DOCS, "pages": PAGES, "users": USERS, "customers": CUSTOMERS}
SIM = "CASE WHEN len(list_distinct(a.x || b.x)) = 0 THEN 0.0 ELSE len(list_intersect(a.x, b.x)) / len(list_distinct(a.x || b.x)) END"


def combined(graph: str = "parts", floor: float = 0.05, removed: float = 0.0) -> str:
    keep = f" WHERE {draw_sql('src', 'dst')} >= {int(removed * PRIME)}" if removed else ""
    used = f"used AS (SELECT src, dst FROM edges{keep})"
    return f"""{GRAPHS[graph]}, {used},
sims AS (SELECT src, dst, {SIM} AS j FROM used JOIN attrs a ON a.node = src JOIN attrs b ON b.node = dst),
combined AS (SELECT src, dst, 1 + CASE WHEN j > 0 THEN j ELSE {floor} END AS w, CASE WHEN j > 0 THEN j ELSE {floor} END AS sim FROM sims),
both_b AS (SELECT src, dst, w FROM combined UNION ALL SELECT dst, src, w FROM combined),
deg_b AS (SELECT src AS node, sum(w) AS deg FROM both_b GROUP BY src)"""


def seeds(k: int, salt: int = 42, source: str = "edges") -> str:
    return f"seeds AS (SELECT node AS seed FROM (SELECT src AS node FROM {source} UNION SELECT dst FROM {source}) ORDER BY {draw_sql('node', salt=salt)}, node LIMIT {k})"


def walks(p: Params) -> str:
    coin = int(p.alpha_r * PRIME)
    return f"""adj AS (SELECT src, dst, CAST(sum(wi) OVER (PARTITION BY src ORDER BY dst) AS BIGINT) - wi AS lo, CAST(sum(wi) OVER (PARTITION BY src ORDER BY dst) AS BIGINT) AS hi, CAST(sum(wi) OVER (PARTITION BY src) AS BIGINT) AS total
  FROM (SELECT src, dst, greatest(1, CAST(round(w * {UNIT}) AS BIGINT)) AS wi FROM both_b)),
walkers AS (SELECT seed, CAST(r.w AS BIGINT) AS walk, CAST(0 AS BIGINT) AS hop, seed AS node FROM seeds, range({p.n_w}) AS r(w)
  UNION ALL SELECT k.seed, k.walk, k.hop + 1, a.dst FROM (SELECT *, {draw_sql('seed', 'walk', '2 * hop + 1', salt=p.salt)} AS u FROM walkers WHERE hop < {p.max_hops} AND {draw_sql('seed', 'walk', '2 * hop', salt=p.salt)} >= {coin}) k
  JOIN adj a ON a.src = k.node AND k.u * a.total // {PRIME} >= a.lo AND k.u * a.total // {PRIME} < a.hi),
visits AS (SELECT seed, node, count(*) AS hits FROM (SELECT DISTINCT seed, walk, node FROM walkers) GROUP BY seed, node),
cuts AS (SELECT seed, mu + sqrt(greatest(sq - mu * mu, 0)) / {p.t_s} AS cut FROM (SELECT seed, sum(CAST(hits AS DOUBLE)) / (SELECT count(*) FROM attrs) AS mu, sum(CAST(hits AS DOUBLE) * hits) / (SELECT count(*) FROM attrs) AS sq FROM visits GROUP BY seed)),
sub_nodes AS (SELECT v.seed, node, hits FROM visits v JOIN cuts c ON c.seed = v.seed WHERE hits > cut OR node = v.seed),
sub_edges AS (SELECT a.seed, src, dst, w, false AS predicted FROM combined JOIN sub_nodes a ON a.node = src JOIN sub_nodes b ON b.node = dst AND b.seed = a.seed)"""


def completion(t_e: float) -> str:
    return f"""new_edges AS (SELECT s.seed, s.node AS src, t.node AS dst, {SIM} AS w FROM sub_nodes s JOIN sub_nodes t ON s.seed = t.seed AND s.node < t.node JOIN attrs a ON a.node = s.node JOIN attrs b ON b.node = t.node
  WHERE NOT EXISTS (SELECT 1 FROM sub_edges e WHERE e.seed = s.seed AND e.src = s.node AND e.dst = t.node) AND {SIM} > {t_e}),
done AS (SELECT * FROM sub_edges UNION ALL SELECT seed, src, dst, w, true FROM new_edges)"""


def ranked(p: Params, steps: int, source: str, deg: str = "deg_b", name: str = "") -> str:
    """Rank, order, curve and chosen partition over edge rows (seed, src, dst, w, predicted) of `source`."""
    n = name
    half, a = (1 - p.alpha_n) / 2, p.alpha_n
    if p.measure == "ratio":
        cut = "CASE WHEN bool_and(inside > 0) THEN sum(CASE WHEN inside > 0 THEN (deg - inside) / inside END) END"
        score = f"CASE WHEN 2 * vol < (SELECT sum(deg) FROM {deg}) THEN cut / vol END"
    else:
        cut = "sum(deg - inside)"
        score = f"CASE WHEN least(vol, (SELECT sum(deg) FROM {deg}) - vol) > 1e-12 THEN cut / least(vol, (SELECT sum(deg) FROM {deg}) - vol) END"
    return f"""se{n} AS (SELECT seed, src, dst, w, predicted FROM {source} UNION ALL SELECT seed, dst, src, w, predicted FROM {source}),
dt{n} AS (SELECT seed, src AS node, sum(w) AS deg FROM se{n} GROUP BY seed, src),
tr{n} AS (SELECT e.seed, e.src, e.dst, {half} * e.w / d.deg AS p FROM se{n} e JOIN dt{n} d ON d.seed = e.seed AND d.node = e.src UNION ALL SELECT seed, node, node, {half} FROM dt{n} UNION ALL SELECT seed, node, seed, {a} FROM dt{n}),
rk{n} AS (SELECT 0 AS t, seed, seed AS node, CAST(1 AS DOUBLE) AS q FROM (SELECT DISTINCT seed FROM dt{n} WHERE node = seed)
  UNION ALL SELECT r.t + 1, r.seed, x.dst, sum(r.q * x.p) FROM rk{n} r JOIN tr{n} x ON x.seed = r.seed AND x.src = r.node WHERE r.t < {steps} GROUP BY r.t, r.seed, x.dst),
ranks{n} AS (SELECT r.seed, r.node, r.q AS rank, d.deg AS degt FROM rk{n} r JOIN dt{n} d ON d.seed = r.seed AND d.node = r.node WHERE r.t = {steps}),
ord{n} AS (SELECT * FROM (SELECT seed, node, rank, round(rank / degt, 12) AS share, row_number() OVER (PARTITION BY seed ORDER BY round(rank / degt, 12) DESC, node) AS position FROM ranks{n} WHERE rank > 0) WHERE position <= {p.n_s}),
fdeg{n} AS (SELECT o.seed, o.node, o.position, d.deg + coalesce((SELECT sum(w) FROM se{n} e WHERE e.seed = o.seed AND e.src = o.node AND e.predicted), 0) AS deg FROM ord{n} o JOIN {deg} d ON d.node = o.node),
gain{n} AS (SELECT e.seed, e.src AS node, greatest(a.position, b.position) AS step, sum(e.w) AS w FROM se{n} e JOIN ord{n} a ON a.seed = e.seed AND a.node = e.src JOIN ord{n} b ON b.seed = e.seed AND b.node = e.dst GROUP BY ALL),
pre{n} AS (SELECT f.seed, j.position AS j, f.node, f.deg, coalesce(sum(i.w), 0) AS inside FROM fdeg{n} f JOIN ord{n} j ON j.seed = f.seed AND f.position <= j.position LEFT JOIN gain{n} i ON i.seed = f.seed AND i.node = f.node AND i.step <= j.position GROUP BY ALL),
sums{n} AS (SELECT seed, j, {cut} AS cut, sum(deg) AS vol, count(*) FILTER (inside = 0) AS orphans FROM pre{n} GROUP BY seed, j),
curve{n} AS (SELECT seed, j AS position, cut, vol, orphans, {score} AS score FROM sums{n}),
best{n} AS (SELECT seed, min({{'score': round(score, 10), 'size': position}}) AS b FROM curve{n} WHERE score IS NOT NULL GROUP BY seed),
summary{n} AS (SELECT s.seed, coalesce(b.b.size, 1) AS size, b.b.score AS score, coalesce(b.b.score < {p.phi_o}, false) AS target_met FROM seeds s LEFT JOIN best{n} b ON b.seed = s.seed),
members{n} AS (SELECT o.seed, o.node, o.position FROM ord{n} o JOIN summary{n} s ON s.seed = o.seed WHERE o.position <= s.size UNION ALL SELECT seed, seed, 1 FROM summary{n} s WHERE NOT EXISTS (SELECT 1 FROM ord{n} o WHERE o.seed = s.seed))"""


def quality(members: str, edges: str = "edges") -> str:
    return f"""inn AS (SELECT a.seed, src, dst FROM {edges} JOIN {members} a ON a.node = src JOIN {members} b ON b.node = dst AND b.seed = a.seed),
tri AS (SELECT x.seed, count(*) AS t FROM inn x JOIN inn y ON y.seed = x.seed AND y.src = x.src AND y.dst > x.dst JOIN inn z ON z.seed = x.seed AND z.src = x.dst AND z.dst = y.dst GROUP BY x.seed),
quality AS (SELECT s.seed, s.nodes, coalesce(e.m, 0) AS edges, CASE WHEN nodes > 1 THEN 2 * coalesce(e.m, 0) / (nodes * (nodes - 1)) END AS density, 3 * coalesce(t.t, 0) AS triangles_x3, coalesce(t.t, 0) AS triangles
  FROM (SELECT seed, count(*) AS nodes FROM {members} GROUP BY seed) s LEFT JOIN (SELECT seed, count(*) AS m FROM inn GROUP BY seed) e ON e.seed = s.seed LEFT JOIN tri t ON t.seed = s.seed)"""


def steps_of(p: Params) -> int:
    """Rank steps when the bound of the graph's size is far above what is needed."""
    return derive_params(10_000, p).steps


def plain() -> str:
    """The structure graph in the combined graph's place."""
    return "gb AS (SELECT src, dst, CAST(1 AS DOUBLE) AS w FROM edges), gdeg AS (SELECT node, CAST(count(*) AS DOUBLE) AS deg FROM (SELECT src AS node FROM edges UNION ALL SELECT dst FROM edges) GROUP BY node), gsub AS (SELECT seed, src, dst, w, false AS predicted FROM gb, seeds)"


def query(*ctes: str, select: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(ctes) + "\n" + select
