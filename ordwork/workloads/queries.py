"""Registered queries: graphs, every configuration of the machine, baselines, measures, answers and streams."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ordwork import measure
from ordwork.baselines import others, stabilize
from ordwork.core.machine import RunResult, run, shortest_paths
from ordwork.core.ordering import Relation, by_distance, chaotic, check_strict_weak, distance_bands, level_bands, then
from ordwork.core.tiers import TierTree, Tiered, all_variants, example_tree, tiered, tiered_tree
from ordwork.graph.model import EdgeSet
from ordwork.operators import answers, relational
from ordwork.plans import single
from ordwork.sources.graphs import GRAPHS, page_link_names, small, table
from ordwork.store import Store
from ordwork.streaming import streams
from ordwork.workloads import sql

Query = Callable[[SparkSession, str], DataFrame]


def stored(spark: SparkSession, sf_dir: str, name: str) -> EdgeSet:
    """The graph, materialised once for a run of many rounds."""
    return EdgeSet(Store(spark, f"graph-{name}").save(GRAPHS[name](spark, sf_dir).edges, "edges"))


def graph_query(name: str) -> Query:
    return lambda spark, d: GRAPHS[name](spark, d).edges


def small_sssp_query(graph: str, ordering, mode: str = "lockstep", tiers: Tiered | None = None) -> Query:
    """Distances, by one task where the seeds reach few edges (plans/single.py)."""
    return lambda spark, d: single.runs(spark, stored(spark, d, graph), [(ordering, mode, tiers)])[0].state


def solve(spark: SparkSession, sf_dir: str, graph: str, ordering, mode: str = "lockstep", tiers: Tiered | None = None) -> RunResult:
    return run(spark, shortest_paths(stored(spark, sf_dir, graph), 0, ordering), mode, tiers)


def sssp_query(graph: str, ordering, mode: str = "lockstep", tiers: Tiered | None = None) -> Query:
    return lambda spark, d: solve(spark, d, graph, ordering, mode, tiers).state


def measures_query(graph: str, ordering, columns: str, mode: str = "lockstep", tiers: Tiered | None = None) -> Query:
    def query(spark, d):
        m = solve(spark, d, graph, ordering, mode, tiers).measures.row()
        return spark.createDataFrame([tuple(int(m[c]) for c in columns.split())], ", ".join(f"{c} long" for c in columns.split()))

    return query


#: Orderings of the recorded work counts.
ROOTS = {"delta7": lambda: distance_bands(7), "kla1": lambda: level_bands(1), "kla3": lambda: level_bands(3), "chaotic": chaotic}
COUNTS = ["classes", "rounds", "processed", "accepted"]


def tier_work_query(graph: str, root: str) -> Query:
    """Work of the three local orders under a root order: a row a tier."""

    def query(spark, d):
        tiers, ordering = ("task", "socket", "host"), ROOTS[root]()
        found = single.runs(spark, stored(spark, d, graph), [(ordering, "drain", tiered(ordering, tier)) for tier in tiers])
        rows = [(tier, *[int(r.measures.row()[c]) for c in [*COUNTS, "remote"]]) for tier, r in zip(tiers, found, strict=True)]
        return spark.createDataFrame(rows, "tier string, " + ", ".join(f"{c} long" for c in [*COUNTS, "remote"]))

    return query


def root_work_query(graph: str) -> Query:
    """Work of the root orders in lock-step: a row an order."""

    def query(spark, d):
        orders = {"delta3": distance_bands(3), "delta7": distance_bands(7), "delta25": distance_bands(25), "kla1": level_bands(1), "kla2": level_bands(2), "chaotic": chaotic()}
        found = single.runs(spark, stored(spark, d, graph), [(ordering, "lockstep", None) for ordering in orders.values()])
        rows = [(name, *[int(r.measures.row()[c]) for c in COUNTS]) for name, r in zip(orders, found, strict=True)]
        return spark.createDataFrame(rows, "root string, " + ", ".join(f"{c} long" for c in COUNTS))

    return query


def profile_query(graph: str, ordering) -> Query:
    def query(spark, d):
        rows = measure.class_profile(spark, solve(spark, d, graph, ordering))
        return rows.select(F.col("class_key").cast("long").alias("class_key"), "items")

    return query


def agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows in which the configurations disagree with unordered lock-step, counted for each."""
    configs = {name: config for name, config in all_variants(7, 2).items() if name != "dijkstra"}
    want, *found = single.runs(spark, stored(spark, sf_dir, "trade"), [(chaotic(), "lockstep", None), *[(c.root, "drain", c) for c in configs.values()]])
    return disagreements(want.state, {name: r.state for name, r in zip(configs, found, strict=True)})


def disagreements(want: DataFrame, found: dict[str, DataFrame]) -> DataFrame:
    """(config, differences): rows that only one of a configuration's frame and want has, repeated ones too; one shuffle by row."""
    rows = want.select(F.explode(F.array(*[F.lit(name) for name in found])).alias("config"), "v", "dist", F.lit(-1).alias("n"))
    for name, got in found.items():
        rows = rows.union(got.select(F.lit(name), "v", "dist", F.lit(1)))
    return rows.groupBy("config", "v", "dist").agg(F.abs(F.sum("n")).alias("n")).groupBy("config").agg(F.sum("n").alias("differences"))


def violations_query(graph: str) -> Query:
    def query(spark, d):
        edges = stored(spark, d, graph)
        return stabilize.violations(edges, run(spark, shortest_paths(edges, 0, distance_bands(25))).state, 0)

    return query


def selfstab(graph: str, init: str, demon) -> Query:
    return lambda spark, d: stabilize.stabilize(spark, stored(spark, d, graph), 0, init, demon).state


def axioms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Violations of the axioms by every shipped ordering on the fives of quantities and the line numbers of lineitem, and by a relation that is no order."""
    dist, level = F.floor(F.col("l_quantity") / 5).cast("long"), F.col("l_linenumber").cast("long")
    pairs = table(spark, sf_dir, "lineitem").select(dist.alias("dist"), level.alias("level")).distinct()
    items = pairs.select((100 * F.col("dist") + F.col("level")).alias("v"), "dist", "level", F.lit(1).cast("long").alias("n"))
    items = Store(spark, "axioms").save(items, "items")
    out = None
    orders = [chaotic(), by_distance(), distance_bands(3), level_bands(2), then(distance_bands(3), by_distance())]
    for o in [*orders, Relation("gap", lambda a, b: b["dist"] - a["dist"] > 1)]:
        rows = check_strict_weak(spark, o, items).select(F.lit(o.name).alias("ordering"), "axiom", (F.col("violations") > 0).alias("violated"))
        out = rows if out is None else out.union(rows)
    return out


def placement(spark: SparkSession, sf_dir: str) -> DataFrame:
    tree = TierTree()
    v = F.col("v")
    return GRAPHS["trade"](spark, sf_dir).vertices().select("v", tree.task_of(v).alias("task"), tree.group_of(v, "socket").alias("socket"), tree.group_of(v, "host").alias("host"))


def bfs_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hops from the page of the smallest url over page-token links taken both ways; keys are texts."""
    names = page_link_names(spark, sf_dir)
    source = names.agg(F.min(F.xxhash64("page").bitwiseAND(F.lit((1 << 63) - 1))), F.min("page").alias("p"))
    first = source.select(F.xxhash64("p").bitwiseAND(F.lit((1 << 63) - 1)).alias("s")).first()["s"]
    graph = EdgeSet(Store(spark, "pages").save(GRAPHS["page_links"](spark, sf_dir).symmetric().edges, "edges"))
    state = others.bfs(spark, graph, first).state
    keys = names.select(F.explode(F.array("page", "token")).alias("name")).distinct().withColumn("v", F.xxhash64("name").bitwiseAND(F.lit((1 << 63) - 1)))
    return state.join(keys, "v").select("name", F.col("dist").alias("hops"))


def parents_trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    graph = stored(spark, sf_dir, "trade")
    return others.parents(run(spark, shortest_paths(graph, 0, distance_bands(7))).state, graph)


def knn_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distances over DOUBLE weights; they are rounded, as sums depend on the path."""
    state = single.runs(spark, stored(spark, sf_dir, "knn"), [(level_bands(1), "lockstep", None)])[0].state
    return state.select("v", F.round("dist", 6).alias("dist"))


def trade_state(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, EdgeSet]:
    graph = stored(spark, sf_dir, "trade")
    return run(spark, shortest_paths(graph, 0, distance_bands(7))).state, graph


def answer(of: Callable[[SparkSession, str, DataFrame, EdgeSet], DataFrame]) -> Query:
    return lambda spark, d: of(spark, d, *trade_state(spark, d))


def nations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "customer").select((2 * F.col("c_custkey")).alias("v"), F.col("c_nationkey").cast("long").alias("nation"))


def path_frame(spark, d, state, graph) -> DataFrame:
    target = state.orderBy(F.desc("dist"), "v").first()["v"]
    path = answers.path_to(state, graph, target)
    return spark.createDataFrame(list(enumerate(path)), "step long, v long").join(state, "v").select("step", "v", "dist")


def queries() -> dict[str, Query]:
    out: dict[str, Query] = {f"graph_{g}": graph_query(g) for g in GRAPHS if g != "page_links"}
    out["graph_page_links"] = page_link_names
    out["graph_toy"] = lambda spark, d: small(spark, d).edges
    out["out_degree_rmat1"] = lambda spark, d: GRAPHS["rmat1"](spark, d).out_degrees()
    out["in_degree_rmat1"] = lambda spark, d: GRAPHS["rmat1"](spark, d).in_degrees()
    out["tier_placement_trade"] = placement
    for g in ("trade", "copurchase", "rmat1", "rmat2"):
        out[f"sssp_chaotic_{g}"] = sssp_query(g, chaotic())
    out["sssp_dijkstra_trade"] = sssp_query("trade", by_distance())
    out["sssp_dijkstra_nation_ring"] = sssp_query("nation_ring", by_distance())
    for delta, g in ((3, "trade"), (5, "handoff"), (7, "copurchase"), (25, "rmat1"), (25, "rmat2")):
        out[f"sssp_delta{delta}_{g}"] = sssp_query(g, distance_bands(delta))
    for k, g in ((1, "rmat1"), (2, "copurchase"), (3, "rmat2")):
        out[f"sssp_kla{k}_{g}"] = sssp_query(g, level_bands(k))
    out["sssp_kla1_knn"] = knn_paths
    for name, config in all_variants(25, 2).items():
        if name != "dijkstra":
            out[f"tiered_{name}_rmat1"] = sssp_query("rmat1", config.root, "drain", config)
    for name in ("chaotic_task", "chaotic_host"):
        config = all_variants(25, 10)[name]
        out[f"tiered_{name}_copurchase"] = small_sssp_query("copurchase", config.root, "drain", config)
    out["tiered_chaotic_host_lattice"] = sssp_query("lattice", chaotic(), "drain", tiered(chaotic(), "host", TierTree(1, 1, 1)))
    out["sssp_dijkstra_handoff_one_group"] = sssp_query("handoff", chaotic(), "drain", tiered(chaotic(), "host", TierTree(1, 1, 1)))
    out["chaotic_task_lockstep_toy"] = sssp_query("toy", chaotic(), "lockstep", tiered(chaotic(), "task"))
    out["example_tree_trade"] = sssp_query("trade", distance_bands(7), "drain", example_tree(7))
    two = tiered_tree(distance_bands(25), TierTree(order={"host": distance_bands(5), "task": by_distance()}))
    out["two_tier_rmat1"] = sssp_query("rmat1", distance_bands(25), "drain", two)
    out["composed_order_trade"] = sssp_query("trade", then(distance_bands(3), by_distance()))
    out["chaotic_task_lockstep_trade"] = small_sssp_query("trade", chaotic(), "lockstep", tiered(chaotic(), "task"))
    out["sssp_kla10_lattice"] = small_sssp_query("lattice", level_bands(10))
    out["tiered_chaotic_task_lattice"] = small_sssp_query("lattice", chaotic(), "drain", tiered(chaotic(), "task"))
    out["tiered_delta_task_copurchase"] = small_sssp_query("copurchase", distance_bands(25), "drain", tiered(distance_bands(25), "task"))
    out["selfstab_central_nation_ring"] = selfstab("nation_ring", "random", stabilize.Central())
    for g in ("rmat1", "trade"):
        out[f"root_work_{g}"] = root_work_query(g)
        for r in ROOTS:
            out[f"tier_work_{r}_{g}"] = tier_work_query(g, r)
    out["selfstab_sync_trade"] = selfstab("trade", "infinite", stabilize.Synchronous())
    out["selfstab_sync_random_start_trade"] = selfstab("trade", "random", stabilize.Synchronous())
    out["selfstab_distributed_trade"] = selfstab("trade", "infinite", stabilize.Distributed(0.5, 1))
    out["selfstab_central_toy"] = selfstab("toy", "random", stabilize.Central())
    out["dijkstra_local_trade"] = lambda spark, d: others.dijkstra_local(GRAPHS["trade"](spark, d), 0)
    out["level_synchronous_trade"] = lambda spark, d: others.level_synchronous(spark, stored(spark, d, "trade"), 0).state
    out["bfs_trade"] = lambda spark, d: others.bfs(spark, stored(spark, d, "trade"), 0).state.withColumnRenamed("dist", "hops")
    out["bfs_page_links"] = bfs_pages
    out["components_trade"] = lambda spark, d: others.components(spark, stored(spark, d, "trade")).state.withColumnRenamed("dist", "label")
    out["components_handoff"] = lambda spark, d: others.components(spark, stored(spark, d, "handoff")).state.withColumnRenamed("dist", "label")
    out["parents_trade"] = parents_trade
    out["pagerank_trade"] = lambda spark, d: others.pagerank(spark, stored(spark, d, "trade"))
    out["independent_set_handoff"] = lambda spark, d: others.maximal_independent_set(spark, stored(spark, d, "handoff"))
    out["coloring_nation_ring"] = lambda spark, d: others.coloring(spark, stored(spark, d, "nation_ring"))
    out["dijkstra_measures_trade"] = measures_query("trade", by_distance(), "classes processed accepted")
    out["kla1_measures_copurchase"] = measures_query("copurchase", level_bands(1), "classes rounds processed accepted")
    out["drain_measures_rmat1"] = measures_query("rmat1", chaotic(), "classes rounds processed accepted remote", "drain", tiered(chaotic(), "host"))
    out["class_profile_dijkstra_trade"] = profile_query("trade", by_distance())
    out["class_profile_delta7_trade"] = profile_query("trade", distance_bands(7))
    out["fixpoint_violations_rmat1"] = violations_query("rmat1")
    out["order_axioms"] = axioms
    out["variant_agreement_trade"] = agreement
    out["ans_reach_within"] = answer(lambda spark, d, s, g: answers.reach_within(s, 5))
    out["ans_nearest"] = answer(lambda spark, d, s, g: answers.nearest(s, 10))
    out["ans_histogram"] = answer(lambda spark, d, s, g: answers.histogram(s, 4))
    out["ans_by_nation"] = answer(lambda spark, d, s, g: answers.by_group(s, nations(spark, d), "nation"))
    out["ans_nearest_by_nation"] = answer(lambda spark, d, s, g: answers.nearest_by_group(s, nations(spark, d), "nation", 3))
    out["ans_path_to"] = answer(path_frame)
    return out | relational.queries() | streams.queries()


def oracle_sql() -> dict[str, str]:
    out = {f"graph_{g}": f"SELECT src, dst, w FROM ({q})" for g, q in sql.EDGES.items()}
    out["graph_page_links"], out["graph_knn"], out["graph_toy"] = sql.PAGE_LINKS, sql.KNN, sql.SMALL
    out["out_degree_rmat1"] = f"SELECT src AS v, count(*) AS degree FROM ({sql.EDGES['rmat1']}) GROUP BY 1"
    out["in_degree_rmat1"] = f"SELECT dst AS v, count(*) AS degree FROM ({sql.EDGES['rmat1']}) GROUP BY 1"
    out["tier_placement_trade"] = f"""SELECT v, task, task // 2 AS socket, task // 4 AS host FROM (
      SELECT v, ((v % 2147483648) * 40503 // 16) % 8 AS task FROM (SELECT src AS v FROM ({sql.EDGES['trade']}) UNION SELECT dst FROM ({sql.EDGES['trade']})))"""
    own = queries_by_prefix()
    for name, graph in own.items():
        out[name] = sql.sssp(graph)
    state = sql.distances("trade")
    out["bfs_trade"] = sql.bfs("trade")
    out["components_trade"], out["components_handoff"] = sql.components("trade"), sql.components("handoff")
    out["bfs_page_links"] = f"""WITH RECURSIVE l AS MATERIALIZED ({sql.PAGE_LINKS}), e AS (SELECT page AS a, token AS b FROM l UNION SELECT token, page FROM l),
      d(name, hops) USING KEY (name) AS (SELECT min(page), 0::BIGINT FROM l UNION
      SELECT e.b, min(d.hops + 1)::BIGINT FROM d JOIN e ON e.a = d.name LEFT JOIN recurring.d AS r ON r.name = e.b WHERE r.name IS NULL OR d.hops + 1 < r.hops GROUP BY e.b) SELECT name, hops FROM d"""
    tight = "SELECT e.dst AS v, min(e.src) AS parent FROM e JOIN d a ON a.v = e.src JOIN d b ON b.v = e.dst WHERE a.dist + e.w = b.dist GROUP BY 1"
    out["parents_trade"] = f"{state} {tight}"
    out["pagerank_trade"] = pagerank_sql()
    out["dijkstra_measures_trade"] = f"""{state} SELECT (SELECT count(DISTINCT x) FROM (SELECT 0 AS x UNION ALL SELECT d.dist + e.w FROM d JOIN e ON e.src = d.v))::BIGINT AS classes,
      (SELECT 1 + count(*) FROM d JOIN e ON e.src = d.v)::BIGINT AS processed, (SELECT count(*) FROM d)::BIGINT AS accepted"""
    out["class_profile_dijkstra_trade"] = f"{state} SELECT x AS class_key, count(*) AS items FROM (SELECT 0::BIGINT AS x UNION ALL SELECT d.dist + e.w FROM d JOIN e ON e.src = d.v) GROUP BY 1"
    out["kla1_measures_copurchase"] = kla1_sql("copurchase")
    out |= sql.recorded_work()
    out["drain_measures_rmat1"] = "SELECT classes, rounds, processed, accepted, remote FROM ({}) WHERE tier = 'host'".format(out["tier_work_chaotic_rmat1"])
    out["sssp_kla1_knn"] = sql.knn_distances()
    out["fixpoint_violations_rmat1"] = f"""{sql.distances('rmat1')} SELECT count(*) AS violations FROM d JOIN e ON e.src = d.v LEFT JOIN d t ON t.v = e.dst WHERE t.v IS NULL OR d.dist + e.w < t.dist"""
    out["order_axioms"] = """SELECT o AS ordering, a AS axiom, o = 'gap' AND a = 'incomparability_transitive' AS violated
      FROM (SELECT unnest(['chaotic', 'dijkstra', 'delta', 'kla', 'delta+dijkstra', 'gap']) AS o), (SELECT unnest(['irreflexive', 'asymmetric', 'transitive', 'incomparability_transitive']) AS a)"""
    out["variant_agreement_trade"] = "SELECT r || '_' || t AS config, 0::BIGINT AS differences FROM (SELECT unnest(['delta', 'kla', 'chaotic']) AS r), (SELECT unnest(['fifo', 'task', 'socket', 'host']) AS t)"
    out["ans_reach_within"] = f"{state} SELECT v, dist FROM d WHERE dist <= 5"
    out["ans_nearest"] = f"{state} SELECT v, dist FROM d ORDER BY dist, v LIMIT 10"
    out["ans_histogram"] = f"{state} SELECT dist // 4 AS band, count(*) AS n FROM d GROUP BY 1"
    joined = "d JOIN (SELECT 2 * c_custkey AS v, c_nationkey::BIGINT AS nation FROM customer) c ON c.v = d.v"
    out["ans_by_nation"] = f"{state} SELECT nation, count(*) AS n, min(dist) AS least, max(dist) AS most, sum(dist)::BIGINT AS total FROM {joined} GROUP BY 1"
    out["ans_nearest_by_nation"] = f"{state} SELECT nation, v, dist, r FROM (SELECT nation, d.v, dist, row_number() OVER (PARTITION BY nation ORDER BY dist, d.v) AS r FROM {joined}) WHERE r <= 3"
    out["ans_path_to"] = f"""{state}, p AS MATERIALIZED ({tight}), w AS (SELECT v, 0 AS back FROM (SELECT v FROM d ORDER BY dist DESC, v LIMIT 1) UNION ALL SELECT p.parent, w.back + 1 FROM w JOIN p ON p.v = w.v)
      SELECT (SELECT max(back) FROM w) - w.back AS step, w.v, d.dist FROM w JOIN d ON d.v = w.v""".replace("AS step", "::BIGINT AS step")
    return out | relational.oracle_sql() | streams.oracle_sql()


def queries_by_prefix() -> dict[str, str]:
    """Queries whose result is the distances of a graph, whatever the configuration."""
    names = [n for n in queries() if n.startswith(("sssp_", "tiered_", "selfstab_", "example_tree", "two_tier", "dijkstra_local", "level_synchronous", "chaotic_task_lockstep", "composed_order"))]
    out = {}
    for n in names:
        found = [g for g in sql.EDGES if g in n]
        if n != "sssp_kla1_knn" and found:
            out[n] = max(found, key=len)
    return out


def pagerank_sql(iterations: int = 10) -> str:
    steps = [f"e AS MATERIALIZED ({sql.EDGES['trade']})", "g AS (SELECT src, count(*) AS k FROM e GROUP BY 1)", "n AS (SELECT src AS v FROM e UNION SELECT dst FROM e)", "r0 AS (SELECT v, 1.0::DOUBLE / (SELECT count(*) FROM n) AS r FROM n)"]
    for i in range(iterations):
        steps.append(f"r{i + 1} AS MATERIALIZED (SELECT n.v, 0.15::DOUBLE / (SELECT count(*) FROM n) + 0.85::DOUBLE * coalesce(s.x, 0) AS r FROM n LEFT JOIN (SELECT e.dst, sum(r{i}.r / g.k) AS x FROM e JOIN g ON g.src = e.src JOIN r{i} ON r{i}.v = e.src GROUP BY 1) s ON s.dst = n.v)")
    return f"WITH {', '.join(steps)} SELECT v, round(r, 9) AS rank FROM r{iterations}"


def kla1_sql(graph: str, levels: int = 14) -> str:
    """Level-synchronous counts by unrolled levels: s is the state, a what was accepted, p the items processed."""
    steps = [f"e AS MATERIALIZED ({sql.EDGES[graph]})", "a0 AS (SELECT 0::BIGINT AS v, 0::BIGINT AS dist)", "s0 AS (SELECT * FROM a0)", "p0 AS (SELECT 1::BIGINT AS n)"]
    for i in range(1, levels):
        steps.append(f"m{i} AS MATERIALIZED (SELECT e.dst AS v, min(a.dist + e.w) AS dist, count(*) AS n FROM a{i - 1} a JOIN e ON e.src = a.v GROUP BY 1)")
        steps.append(f"p{i} AS (SELECT coalesce(sum(n), 0)::BIGINT AS n FROM m{i})")
        steps.append(f"a{i} AS MATERIALIZED (SELECT m.v, m.dist FROM m{i} m LEFT JOIN s{i - 1} s ON s.v = m.v WHERE s.v IS NULL OR m.dist < s.dist)")
        steps.append(f"s{i} AS MATERIALIZED (SELECT v, min(dist) AS dist FROM (SELECT * FROM s{i - 1} UNION ALL SELECT * FROM a{i}) GROUP BY 1)")
    total = " + ".join(f"(SELECT n FROM p{i})" for i in range(levels))
    rounds = " + ".join(f"(SELECT (n > 0)::BIGINT FROM p{i})" for i in range(levels))
    accepted = " + ".join(f"(SELECT count(*) FROM a{i})" for i in range(levels))
    return f"WITH {', '.join(steps)} SELECT ({rounds})::BIGINT AS classes, ({rounds})::BIGINT AS rounds, ({total})::BIGINT AS processed, ({accepted})::BIGINT AS accepted"
