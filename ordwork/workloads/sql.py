"""DuckDB SQL of the graphs and of distances, from which oracles are put together."""

from __future__ import annotations

from ordwork.sources.graphs import RMAT, SCALE


def rmat_sql(name: str, scale: int = SCALE) -> str:
    (a, b, c), most = RMAT[name]
    cuts = [f"{round(x * 2**32):08x}" for x in (a, a + b, a + b + c)]
    src, dst = ["0"], ["0"]
    for i in range(scale):
        digits = f"substr(m{i // 4}, {8 * (i % 4) + 1}, 8)"
        src.append(f"CASE WHEN {digits} < '{cuts[1]}' THEN 0 ELSE {1 << i} END")
        dst.append(f"CASE WHEN {digits} < '{cuts[0]}' OR ({digits} >= '{cuts[1]}' AND {digits} < '{cuts[2]}') THEN 0 ELSE {1 << i} END")
    digests = ", ".join(f"md5(concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey) || '-{k}') AS m{k}" for k in range(-(-scale // 4)))
    return f"""SELECT src, dst, min(w)::BIGINT AS w FROM (
  SELECT ({" + ".join(src)})::BIGINT AS src, ({" + ".join(dst)})::BIGINT AS dst,
    1 + (7919 * l_partkey + 104729 * l_suppkey + 31 * l_orderkey + l_linenumber) % {most} AS w
  FROM (SELECT *, {digests} FROM lineitem)) WHERE src <> dst GROUP BY src, dst"""


EDGES = {
    "rmat1": rmat_sql("rmat1"),
    "rmat2": rmat_sql("rmat2"),
    "trade": """SELECT src, dst, min(w)::BIGINT AS w FROM (
  SELECT 2 * o_custkey AS src, 2 * l_suppkey + 1 AS dst, l_quantity::BIGINT AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey
  UNION ALL SELECT 2 * l_suppkey + 1, 2 * o_custkey, l_quantity::BIGINT FROM lineitem JOIN orders ON l_orderkey = o_orderkey) GROUP BY src, dst""",
    "handoff": """SELECT src, dst, min(w)::BIGINT AS w FROM (
  SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst, 1 + event_id % 100 AS w FROM events) WHERE dst IS NOT NULL AND src <> dst GROUP BY src, dst""",
    "lattice": """SELECT src, dst, min(w)::BIGINT AS w FROM (
  WITH p AS (SELECT p_partkey AS a, p_size::BIGINT AS w, (SELECT count(*) FROM part) AS n, (SELECT floor(sqrt(count(*)))::BIGINT FROM part) AS s FROM part),
  e AS (SELECT a, a + 1 AS b, w FROM p WHERE (a + 1) % s <> 0 AND a + 1 < n UNION ALL SELECT a, a + s, w FROM p WHERE a + s < n)
  SELECT a AS src, b AS dst, w FROM e UNION ALL SELECT b, a, w FROM e) GROUP BY src, dst""",
    "copurchase": """SELECT a.l_partkey AS src, b.l_partkey AS dst, min(1 + (7 * (a.l_partkey + b.l_partkey) + a.l_orderkey) % 100)::BIGINT AS w
  FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey <> b.l_partkey GROUP BY 1, 2""",
    "nation_ring": "SELECT n_nationkey::BIGINT AS src, ((n_nationkey + 1) % 25)::BIGINT AS dst, (1 + n_regionkey)::BIGINT AS w FROM nation",
    "toy": "SELECT * FROM (VALUES (0::BIGINT, 1::BIGINT, 4::BIGINT), (0, 2, 1), (2, 1, 2), (1, 3, 1), (2, 3, 5), (3, 4, 3), (5, 0, 1)) t(src, dst, w)",
}
SMALL = """SELECT src, dst, min(w)::BIGINT AS w FROM (
  SELECT c_nationkey::BIGINT AS src, c_custkey % 25 AS dst, 1 + c_custkey % 97 AS w FROM customer) WHERE src <> dst GROUP BY src, dst"""
PAGE_LINKS = """SELECT DISTINCT 'page:' || url AS page, 'token:' || token AS token FROM (SELECT url, unnest(regexp_extract_all(html, 'href="/([^"]*)"', 1)) AS token FROM pages)"""
KNN = """SELECT src, dst, round(w, 6) AS w FROM (
  SELECT a.vec_id AS src, b.vec_id AS dst, 1 - list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) AS w,
    row_number() OVER (PARTITION BY a.vec_id ORDER BY 1 - list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), b.vec_id) AS r
  FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE r <= 5"""


def distances(graph: str, source: int = 0, weight: str = "e.w") -> str:
    """CTEs e and d(v, dist): distances from the source by keyed recursion."""
    return f"""WITH RECURSIVE e AS MATERIALIZED ({EDGES[graph]}), d(v, dist) USING KEY (v) AS (
  SELECT {source}::BIGINT, 0::BIGINT
  UNION
  SELECT e.dst, min(d.dist + {weight})::BIGINT FROM d JOIN e ON e.src = d.v LEFT JOIN recurring.d AS r ON r.v = e.dst
  WHERE r.v IS NULL OR d.dist + {weight} < r.dist GROUP BY e.dst)"""


def sssp(graph: str, source: int = 0) -> str:
    return distances(graph, source) + " SELECT v, dist FROM d"


def bfs(graph: str, source: int = 0) -> str:
    return distances(graph, source, "1") + " SELECT v, dist AS hops FROM d"


def components(graph: str) -> str:
    return f"""WITH RECURSIVE e AS MATERIALIZED (SELECT src, dst FROM ({EDGES[graph]}) UNION SELECT dst, src FROM ({EDGES[graph]})), d(v, label) USING KEY (v) AS (
  SELECT DISTINCT src, src FROM e
  UNION
  SELECT e.dst, min(d.label) FROM d JOIN e ON e.src = d.v JOIN recurring.d AS r ON r.v = e.dst WHERE d.label < r.label GROUP BY e.dst)
  SELECT v, label FROM d"""


def knn_distances(source: int = 0) -> str:
    """Distances over the nearest-neighbour graph's DOUBLE weights, rounded as sums depend on the path."""
    return f"""WITH RECURSIVE e AS MATERIALIZED ({KNN}), d(v, dist) USING KEY (v) AS (
  SELECT {source}::BIGINT, 0::DOUBLE
  UNION
  SELECT e.dst, min(d.dist + e.w)::DOUBLE FROM d JOIN e ON e.src = d.v LEFT JOIN recurring.d AS r ON r.v = e.dst
  WHERE r.v IS NULL OR d.dist + e.w < r.dist GROUP BY e.dst) SELECT v, round(dist, 6) AS dist FROM d"""


#: Work counts at sf0.01 recorded by a sequential model outside this engine (FIXTURES.md §4).
#: Drain plan, for task, socket and host: classes, rounds, processed, accepted, remote.
TIER_WORK = {
    "delta7_rmat1": "34,57,52575,2941,46064 34,55,50942,2921,38270 34,54,49799,2904,24919",
    "kla1_rmat1": "9,9,101240,6145,88825 9,9,101240,6145,76114 9,9,101240,6145,50714",
    "kla3_rmat1": "3,9,91820,5596,80557 3,9,87220,5331,65537 3,9,78283,4743,38965",
    "chaotic_rmat1": "1,9,83798,5375,73482 1,9,73890,4793,55477 1,7,60517,3806,29946",
    "delta7_trade": "10,17,104369,1665,91180 10,17,103316,1652,77225 10,16,101958,1635,50934",
    "kla1_trade": "8,8,183719,3306,160450 8,8,183719,3306,137322 8,8,183719,3306,91750",
    "kla3_trade": "3,8,237402,4932,207245 3,8,230844,4809,172671 3,8,207443,4192,103733",
    "chaotic_trade": "1,7,230457,4168,201421 1,7,179016,3237,133959 1,5,127691,2225,63631",
}
#: Lock-step, for delta3, delta7, delta25, kla1, kla2 and chaotic: classes, rounds, processed, accepted.
ROOT_WORK = {
    "trade": "23,30,99436,1632 10,18,100174,1624 3,10,160967,2876 8,8,183719,3306 4,8,183719,3306 1,8,183719,3306",
    "rmat1": "76,101,48761,2884 34,59,53402,2946 11,24,79777,3971 9,9,101240,6145 5,9,101240,6145 1,9,101240,6145",
}


def recorded(key: str, names: list[str], columns: list[str], cells: str) -> str:
    rows = ", ".join(f"('{name}', {cell})" for name, cell in zip(names, cells.split(), strict=True))
    return f"SELECT {key}, {', '.join(f'{c}::BIGINT AS {c}' for c in columns)} FROM (VALUES {rows}) t({key}, {', '.join(columns)})"


def recorded_work() -> dict[str, str]:
    """SQL of the recorded counts by query name."""
    counts = ["classes", "rounds", "processed", "accepted"]
    out = {f"tier_work_{name}": recorded("tier", ["task", "socket", "host"], [*counts, "remote"], cells) for name, cells in TIER_WORK.items()}
    return out | {f"root_work_{g}": recorded("root", ["delta3", "delta7", "delta25", "kla1", "kla2", "chaotic"], counts, cells) for g, cells in ROOT_WORK.items()}
