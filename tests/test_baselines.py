"""Self-stabilization, other algorithms on the machine, answers and measures."""

import pytest
from pyspark.sql import functions as F

from ordwork import measure
from ordwork.baselines import others, stabilize
from ordwork.core.machine import run, shortest_paths
from ordwork.core.ordering import by_distance, chaotic, distance_bands
from ordwork.graph.model import EdgeSet, GraphError
from ordwork.operators import answers
from ordwork.sources.graphs import GRAPHS, read_edges, write_state
from ordwork.store import Store

TOY = {0: 0, 1: 3, 2: 1, 3: 4, 4: 7}


def state(frame):
    return {r["v"]: r["dist"] for r in frame.collect()}


@pytest.mark.parametrize("init", ["infinite", "zero", "huge", "random"])
def test_stabilizes_from_any_start(spark, init):
    assert state(stabilize.stabilize(spark, GRAPHS["toy"](spark), 0, init).state) == TOY


@pytest.mark.parametrize("demon", [stabilize.Distributed(0.4, 3), stabilize.Central()])
def test_demons(spark, demon):
    assert state(stabilize.stabilize(spark, GRAPHS["toy"](spark), 0, "zero", demon).state) == TOY


def test_unreachable_cycle_settles_by_the_bound(spark):
    graph = EdgeSet.of(spark.createDataFrame([(0, 1, 1), (5, 6, 1), (6, 5, 1)], "src long, dst long, w long"))
    assert state(stabilize.stabilize(spark, graph, 0, "zero").state) == {0: 0, 1: 1}
    with pytest.raises(GraphError):
        stabilize.stabilize(spark, EdgeSet.of(spark.createDataFrame([(0, 1, 0)], "src long, dst long, w long")), 0)


def test_violations(spark):
    toy = GRAPHS["toy"](spark)
    good = run(spark, shortest_paths(toy, 0, chaotic())).state
    assert stabilize.violations(toy, good, 0).first()[0] == 0
    assert stabilize.violations(toy, good.withColumn("dist", F.when(F.col("v") == 3, 9).otherwise(F.col("dist"))), 0).first()[0] > 0


def test_other_algorithms(spark):
    toy = GRAPHS["toy"](spark)
    assert state(others.dijkstra_local(toy, 0)) == TOY
    assert state(others.bfs(spark, toy, 0).state) == {0: 0, 1: 1, 2: 1, 3: 2, 4: 3}
    two = EdgeSet.of(spark.createDataFrame([(1, 2, 1), (2, 3, 1), (8, 9, 1)], "src long, dst long, w long"))
    assert state(others.components(spark, two).state) == {1: 1, 2: 1, 3: 1, 8: 8, 9: 8}
    tree = {r["v"]: r["parent"] for r in others.parents(run(spark, shortest_paths(toy, 0, chaotic())).state, toy).collect()}
    assert tree == {1: 2, 2: 0, 3: 1, 4: 3}
    ranks = others.pagerank(spark, two).collect()
    assert 0 < sum(r["rank"] for r in ranks) <= 1


def test_independent_set_and_colors(spark, sf):
    graph = EdgeSet(Store(spark, "test").save(GRAPHS["handoff"](spark, sf).symmetric().edges, "e"))
    chosen = {r["v"] for r in others.maximal_independent_set(spark, graph).collect()}
    pairs = [(r["src"], r["dst"]) for r in graph.edges.collect()]
    assert not any(a in chosen and b in chosen for a, b in pairs)
    near = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
    assert all(v in chosen or near[v] & chosen for v in near)
    ring = GRAPHS["nation_ring"](spark, sf)
    colors = {r["v"]: r["color"] for r in others.coloring(spark, ring).collect()}
    assert all(colors[r["src"]] != colors[r["dst"]] for r in ring.edges.collect()) and len(colors) == 25


def test_answers(spark):
    toy = GRAPHS["toy"](spark)
    result = run(spark, shortest_paths(toy, 0, distance_bands(3)))
    s = result.state
    assert answers.path_to(s, toy, 4) == [0, 2, 1, 3, 4]
    assert answers.path_to(s, toy, 5) == []
    assert [r["v"] for r in answers.nearest(s, 3).collect()] == [0, 2, 1]
    assert answers.reach_within(s, 3).count() == 3
    assert {r["band"]: r["n"] for r in answers.histogram(s, 4).collect()} == {0: 3, 1: 2}


def test_measures(spark):
    toy = GRAPHS["toy"](spark)
    machine = shortest_paths(toy, 0, by_distance())
    result = run(spark, machine)
    row = measure.row(result, machine, None, "lockstep", "toy")
    assert (row["classes"], row["accepted"], row["redundant"], row["reached"]) == (6, 5, 0, 5)
    assert measure.class_profile(spark, result).agg(F.sum("items")).first()[0] == 7
    rows = [row | {"wall_s": 2.0}, row | {"wall_s": 4.0}, row | {"tier": "task", "wall_s": 1.0}]
    got = {x["tier"]: x for x in measure.summary(rows)}
    assert got["fifo"]["wall_mean_s"] == 3.0 and got["task"]["speedup"] == 3.0 and got["fifo"]["n"] == 2
    assert measure.weak_efficiency({1: 2.0, 4: 4.0}) == {1: 1.0, 4: 0.5}


def test_sources_and_sinks(spark, tmp_path):
    toy = GRAPHS["toy"](spark)
    want = sorted(map(tuple, toy.edges.collect()))
    toy.edges.write.parquet(f"{tmp_path}/p")
    toy.edges.write.option("header", True).csv(f"{tmp_path}/c")
    toy.edges.write.json(f"{tmp_path}/j")
    toy.edges.selectExpr("concat_ws(' ', src, dst, w) AS value").write.text(f"{tmp_path}/t")
    for path, fmt in (("p", "parquet"), ("c", "csv"), ("j", "json"), ("t", "text")):
        assert sorted(map(tuple, read_edges(spark, f"{tmp_path}/{path}", fmt).edges.collect())) == want
    write_state(run(spark, shortest_paths(toy, 0, chaotic())).state, f"{tmp_path}/s")
    assert state(spark.read.parquet(f"{tmp_path}/s")) == TOY


def test_stream_deletion(spark):
    from ordwork.streaming.streams import Repair

    toy = GRAPHS["toy"](spark)
    repair = Repair(spark, 0)
    repair.insert(EdgeSet(toy.edges.where("src < 2")), 0)
    repair.insert(EdgeSet(toy.edges.where("src >= 2")), 1)
    repair.insert(EdgeSet(toy.edges.where("src >= 2")), 1)
    assert state(repair.state) == TOY
    repair.delete(spark.createDataFrame([(2, 1)], "src long, dst long"))
    assert state(repair.state) == {0: 0, 1: 4, 2: 1, 3: 5, 4: 8}


def test_sql_surface(spark):
    from ordwork.functions import bands, sql

    GRAPHS["toy"](spark).edges.createOrReplaceTempView("toy_edges")
    sql.sssp(spark, "toy_edges", 0, "delta", 3, "toy_dist")
    assert spark.sql("SELECT max(dist) FROM toy_dist").first()[0] == 7
    sql.sssp(spark, "SELECT src, dst, w FROM toy_edges WHERE src <> 2", 0, "kla", 1, "toy_dist")
    assert spark.sql("SELECT dist FROM toy_dist WHERE v = 1").first()[0] == 4
    bands.register(spark)
    assert spark.sql("SELECT mean_distance(dist) FROM toy_dist WHERE v < 2").first()[0] == 2.0


def test_repair_goes_on_from_its_last_commit(spark, tmp_path):
    """Made again on its folder, a repair knows its edges, state and batches; a batch that comes twice changes nothing."""
    from ordwork.streaming.streams import Repair

    batch = lambda rows: EdgeSet.of(spark.createDataFrame(rows, "src long, dst long, w long"))
    folder = str(tmp_path / "repair")
    Repair(spark, 0, folder).insert(batch([(0, 1, 5), (1, 2, 5)]), 0)
    again = Repair(spark, 0, folder)
    assert again.last == 0 and {r["v"]: r["dist"] for r in again.state.collect()} == {0: 0, 1: 5, 2: 10}
    again.insert(batch([(0, 1, 1)]), 0)
    assert {r["v"]: r["dist"] for r in again.state.collect()} == {0: 0, 1: 5, 2: 10}
    again.insert(batch([(0, 2, 4), (2, 3, 1)]), 1)
    assert {r["v"]: r["dist"] for r in Repair(spark, 0, folder).state.collect()} == {0: 0, 1: 5, 2: 4, 3: 5}


def test_a_trigger_is_a_hop(spark):
    """A path of three edges: the seed, three hops, and the offers of the last vertex, of which there are none."""
    from ordwork.streaming.streams import hop_by_trigger

    edges = spark.createDataFrame([(0, 1, 2), (1, 2, 2), (2, 3, 2), (0, 3, 9)], "src long, dst long, w long")
    state, triggers = hop_by_trigger(spark, edges, 0)
    assert {r["v"]: r["dist"] for r in state.collect()} == {0: 0, 1: 2, 2: 4, 3: 6} and triggers == 4


def test_sequential_search_reads_batches(spark):
    """No group of all edges is handed over at once; weights of every kind, a source without edges, no edges."""
    from ordwork.graph.model import EdgeSet

    for kind in ("long", "double", "decimal(10,2)"):
        edges = spark.range(2000).selectExpr("id % 200 as src", "(id * 7 + 1) % 200 as dst", f"cast(1 + id % 300 as {kind}) as w")
        rows = others.dijkstra_local(EdgeSet(edges), 0)
        plan = rows._jdf.queryExecution().executedPlan().toString()
        assert "MapInArrow" in plan and "FlatMapGroups" not in plan
        best, todo = {0: 0}, [0]
        near = {}
        for e in edges.collect():
            near.setdefault(e["src"], []).append((e["dst"], e["w"]))
        while todo:
            v = todo.pop()
            for t, w in near.get(v, ()):
                if t not in best or best[v] + w < best[t]:
                    best[t] = best[v] + w
                    todo.append(t)
        assert {r["v"]: r["dist"] for r in rows.collect()} == best
    far = (1 << 62) + 1
    wide = spark.createDataFrame([(0, far, 3), (far, -5, (1 << 60) + 1), (-5, 7, 2)], "src long, dst long, w long")
    assert {r["v"]: r["dist"] for r in others.dijkstra_local(EdgeSet(wide), 0).collect()} == {0: 0, far: 3, -5: (1 << 60) + 4, 7: (1 << 60) + 6}
    assert [tuple(r) for r in others.dijkstra_local(EdgeSet(edges), 999).collect()] == [(999, 0)]
    assert others.dijkstra_local(EdgeSet(edges.limit(0)), 0).count() == 0
