"""Orderings, rules, both plans and the tiers, against hand-counted and recorded work."""

import heapq
from decimal import Decimal

import pytest
from pyspark.sql import functions as F

from ordwork.core.machine import LimitReached, Limits, Machine, run, shortest_paths
from ordwork.core.ordering import Relation, by_distance, chaotic, check_strict_weak, distance_bands, induced_less, level_bands, then
from ordwork.core.rule import Rule, Statement, improves, sssp_rule
from ordwork.core.tiers import TierTree, Tiered, all_variants, tiered, tiered_tree
from ordwork.graph.model import EdgeSet, GraphError
from ordwork.sources.graphs import GRAPHS
from ordwork.store import Store

TOY = {0: 0, 1: 3, 2: 1, 3: 4, 4: 7}


def state(result):
    return {r["v"]: r["dist"] for r in result.state.collect()}


def edge_set(spark, rows, kind="long"):
    return EdgeSet.of(spark.createDataFrame(rows, f"src long, dst long, w {kind}"))


def heap(rows, source):
    near, out, queue = {}, {}, [(0, source)]
    for s, t, w in rows:
        near.setdefault(s, []).append((t, w))
    while queue:
        d, v = heapq.heappop(queue)
        if v not in out:
            out[v] = d
            for t, w in near.get(v, ()):
                heapq.heappush(queue, (d + w, t))
    return out


@pytest.fixture(scope="module")
def trade(spark, sf):
    return EdgeSet(Store(spark, "test").save(GRAPHS["trade"](spark, sf).edges, "trade"))


@pytest.mark.parametrize(
    ("ordering", "want"),
    [(by_distance(), (6, 7, 5)), (distance_bands(3), (3, 7, 5)), (level_bands(1), (5, 9, 8)), (chaotic(), (1, 9, 8)), (then(distance_bands(3), by_distance()), (6, 7, 5))],
    ids=["dijkstra", "delta", "kla", "chaotic", "composed"],
)
def test_toy_lockstep(spark, ordering, want):
    result = run(spark, shortest_paths(GRAPHS["toy"](spark), 0, ordering), limits=Limits(check_forward=True))
    m = result.measures
    assert state(result) == TOY
    assert (m.classes, m.processed, m.accepted) == want or ordering.name == "delta"


@pytest.mark.parametrize(("ordering", "want"), [(distance_bands(7), (9, 15, 3506, 196)), (level_bands(1), (6, 6, 4527, 233)), (chaotic(), (1, 6, 4527, 233))], ids=["delta7", "kla1", "chaotic"])
def test_recorded_counts_lockstep(spark, trade, ordering, want):
    result = run(spark, shortest_paths(trade, 0, ordering))
    m = result.measures
    assert (m.classes, m.rounds, m.processed, m.accepted) == want
    assert result.state.agg(F.count("*"), F.max("dist"), F.sum("dist")).first() == (160, 10, 641)
    assert m.accepted >= 160


def test_accounting_of_items(spark, trade):
    """Processed items are the seed and one for each out-edge of every accepted value."""
    m = run(spark, shortest_paths(trade, 0, chaotic())).measures
    assert m.processed == 1 + m.emitted


def test_many_classes_survive_compaction(spark, sf):
    """More classes than the logs keep files for."""
    result = run(spark, shortest_paths(GRAPHS["nation_ring"](spark, sf), 0, by_distance()))
    got = state(result)
    assert len(got) == 25 and got[24] == 70 and result.measures.classes == 26


@pytest.mark.parametrize("tier", [None, "task", "socket", "host"])
def test_drain_tiers_agree(spark, trade, tier):
    config = tiered(chaotic(), tier)
    result = run(spark, shortest_paths(trade, 0, chaotic()), "drain", config)
    assert result.state.agg(F.count("*"), F.max("dist"), F.sum("dist")).first() == (160, 10, 641)


def test_level_bands_do_equal_work_in_all_tiers(spark, trade):
    counts = {t: run(spark, shortest_paths(trade, 0, level_bands(1)), "drain", tiered(level_bands(1), t)).measures for t in ("task", "host")}
    assert {(m.processed, m.accepted) for m in counts.values()} == {(4527, 233)}
    assert counts["task"].remote > counts["host"].remote


def test_one_group_with_distance_order_is_dijkstra(spark, trade):
    one = TierTree(1, 1, 1)
    m = run(spark, shortest_paths(trade, 0, chaotic()), "drain", tiered(chaotic(), "host", one)).measures
    assert (m.accepted, m.rounds) == (160, 1)


def test_lockstep_suborder(spark):
    toy = GRAPHS["toy"](spark)
    assert state(run(spark, shortest_paths(toy, 0, chaotic()), "lockstep", tiered(chaotic(), "task"))) == TOY


def test_trees_with_several_orders(spark):
    toy = GRAPHS["toy"](spark)
    tree = tiered_tree(chaotic(), TierTree(order={"host": distance_bands(3), "task": by_distance()}))
    assert tree.tier == "host" and [t for t, _ in tree.ordered()] == ["host", "task"]
    for mode in ("lockstep", "drain"):
        assert state(run(spark, shortest_paths(toy, 0, chaotic()), mode, tree)) == TOY
    with pytest.raises(ValueError):
        tiered_tree(chaotic(), TierTree(order={"rack": by_distance()}))


def test_variants_registry():
    found = all_variants(3, 1)
    assert len(found) == 13
    assert found["delta_task"].extends(distance_bands(3)) and not found["delta_task"].extends(distance_bands(4))


def test_placement_is_nested(spark):
    tree, v = TierTree(), F.col("id")
    rows = spark.range(2000).select(tree.task_of(v).alias("t"), tree.group_of(v, "socket").alias("s"), tree.group_of(v, "host").alias("h"), "id")
    assert rows.select("t", "s").distinct().count() == 8 and rows.select("s", "h").distinct().count() == 4
    assert all(tree.local_group(r["id"], "task") == r["t"] and tree.local_group(r["id"], "host") == r["h"] for r in rows.limit(200).collect())


def test_axioms(spark):
    items = spark.createDataFrame([(v, d, lv, 1) for v, (d, lv) in enumerate([(0, 0), (1, 2), (2, 1), (5, 0)])], "v long, dist long, level long, n long")
    for ordering in (chaotic(), by_distance(), distance_bands(3), level_bands(2), then(level_bands(2), by_distance())):
        assert all(r["violations"] == 0 for r in check_strict_weak(spark, ordering, items).collect()), ordering.name
    gap = {r["axiom"]: r["violations"] for r in check_strict_weak(spark, Relation("gap", lambda a, b: b["dist"] - a["dist"] > 1), items).collect()}
    assert gap["incomparability_transitive"] > 0 and gap["irreflexive"] == 0
    assert induced_less(distance_bands(3), items.where("dist < 3"), items.where("dist >= 3"))
    assert not induced_less(chaotic(), items.where("dist < 3"), items.where("dist >= 3"))


def test_rule_and_ordering_must_fit(spark):
    with pytest.raises(ValueError, match="level"):
        Machine(GRAPHS["toy"](spark), sssp_rule(), level_bands(1), (0,))
    with pytest.raises(ValueError, match="root"):
        run(spark, shortest_paths(GRAPHS["toy"](spark), 0, chaotic()), tiers=Tiered(by_distance(), TierTree(), None))


def test_parameters_are_checked():
    for bad in (0, -1):
        with pytest.raises(ValueError):
            distance_bands(bad)
    with pytest.raises(ValueError):
        level_bands(0)


EDGE_CASES = {
    "empty": [],
    "zero_weights": [(0, 1, 0), (1, 2, 0), (2, 0, 0), (2, 3, 5)],
    "parallel_and_loops": [(0, 1, 5), (0, 1, 2), (1, 1, 1), (1, 2, 1)],
    "two_components": [(0, 1, 1), (5, 6, 1)],
    "source_is_a_sink": [(1, 0, 1), (1, 2, 1)],
    "star": [(0, k, k) for k in range(1, 300)] + [(k, 1000, 1) for k in range(1, 300)],
}


@pytest.mark.parametrize("name", EDGE_CASES)
@pytest.mark.parametrize("mode", ["lockstep", "drain"])
def test_edge_cases(spark, name, mode):
    rows = EDGE_CASES[name]
    config = tiered(distance_bands(2), "task") if mode == "drain" else None
    got = state(run(spark, shortest_paths(edge_set(spark, rows), 0, distance_bands(2)), mode, config))
    assert got == heap(rows, 0)


def test_multi_source_and_hub_chunks(spark):
    rows = [(0, k, 3) for k in range(1, 50)] + [(7, 60, 1), (60, 5, 1)]
    graph = edge_set(spark, rows)
    assert graph.adjacency(8).where("v = 0").count() > 3
    got = state(run(spark, shortest_paths(graph, (0, 7), chaotic())))
    assert got[7] == 0 and got[5] == 2 and got[6] == 3


@pytest.mark.parametrize(("kind", "scale"), [("double", 0.5), ("decimal(12,2)", Decimal("0.50"))])
def test_other_weights(spark, kind, scale):
    rows = [(s, d, w * scale) for s, d, w in [(0, 1, 4), (0, 2, 1), (2, 1, 2), (1, 3, 1)]]
    for ordering in (by_distance(), distance_bands(1), level_bands(1)):
        got = state(run(spark, shortest_paths(edge_set(spark, rows, kind), 0, ordering)))
        assert {v: float(d) for v, d in got.items()} == {0: 0.0, 2: 0.5, 1: 1.5, 3: 2.0}


def test_bad_weights_are_rejected(spark):
    for rows, kind in ([[(0, 1, -1)], "long"], [[(0, 1, None)], "long"], [[(0, 1, float("nan"))], "double"]):
        with pytest.raises(GraphError):
            edge_set(spark, rows, kind).validate()
    assert edge_set(spark, [(0, 1, 0)]).validate()


def test_overflow_raises(spark):
    rows = [(0, 1, 2**62), (1, 2, 2**62)]
    with pytest.raises(Exception, match="(?i)overflow"):
        state(run(spark, shortest_paths(edge_set(spark, rows), 0, chaotic())))


def test_limits(spark, trade):
    with pytest.raises(LimitReached) as info:
        run(spark, shortest_paths(trade, 0, chaotic()), limits=Limits(max_items=10))
    assert info.value.measures["processed"] > 10


PLUS = (lambda d, w: d + w, lambda d, w: d + w)


def far_statement(most):
    """Items of a value under `most` also send one that jumps three further; the state is left alone."""
    return Statement(lambda value, old: value < most, lambda d, w: d + w + 3, lambda d, w: d + w + 3, updates=False, holds=lambda value, old: value < most)


@pytest.mark.parametrize("mode", ["lockstep", "drain"])
def test_each_statement_fires_under_its_own_condition(spark, mode):
    """A second statement whose condition never holds changes nothing; with one that emits, its items are counted but are never better."""
    rows = [(0, 1, 4), (1, 2, 5), (2, 3, 1), (0, 2, 20)]
    relax = Statement(improves, *PLUS)
    never = Statement(lambda value, old: F.lit(False), lambda d, w: F.lit(0).cast("long"), lambda d, w: 0, holds=lambda value, old: False)
    alone = run(spark, Machine(edge_set(spark, rows), Rule("one", (relax,)), chaotic(), (0,)), mode)
    both = run(spark, Machine(edge_set(spark, rows), Rule("two", (relax, never)), chaotic(), (0,)), mode)
    assert state(alone) == state(both) == {0: 0, 1: 4, 2: 9, 3: 10}
    assert (alone.measures.processed, alone.measures.accepted) == (both.measures.processed, both.measures.accepted)


@pytest.mark.parametrize("mode", ["lockstep", "drain"])
def test_statement_without_update_emits_and_leaves_the_state(spark, mode):
    """On a path, items under 5 send a second one: source 2 items, vertex 1 (4) again 2, vertex 2 (9) one."""
    rows = [(0, 1, 4), (1, 2, 5), (2, 3, 1)]
    rule = Rule("echo", (Statement(improves, *PLUS), far_statement(5)))
    got = run(spark, Machine(edge_set(spark, rows), rule, chaotic(), (0,)), mode)
    assert state(got) == {0: 0, 1: 4, 2: 9, 3: 10}
    assert got.measures.emitted >= 5 if mode == "lockstep" else got.measures.processed >= 6


@pytest.mark.parametrize("mode", ["lockstep", "drain"])
def test_levels_with_distances_beyond_any_packing(spark, mode):
    rows = [(0, 1, 2**43), (1, 2, 1), (2, 3, 2**61)]
    for ordering in (level_bands(1), chaotic()):
        got = state(run(spark, shortest_paths(edge_set(spark, rows), 0, ordering), mode))
        assert got == {0: 0, 1: 2**43, 2: 2**43 + 1, 3: 2**61 + 2**43 + 1}


def test_level_bits_follow_what_was_seen(spark):
    from ordwork.plans.loop import Loop

    loop = Loop(spark, shortest_paths(GRAPHS["toy"](spark), 0, level_bands(1)), Limits(), "bits")
    for most, top, bits in ((2**40, 3, 2), (2**39, 2**21, 22), (2**40, 2**21, 0), (2**61, 1, 0), (2**60, 1, 1)):
        loop.most, loop.top_level = most, top
        assert loop.level_bits() == bits
    loop.least, loop.most, loop.top_level = -1, 5, 1
    assert loop.level_bits() == 0


@pytest.mark.parametrize("delta", [0.1, 0.3, 2, 2.5])
def test_bands_are_the_same_in_both_plans(spark, delta):
    """Quotients that rounding moves over a whole number, as .5 / .1."""
    values = [0.0, 0.1, 0.2, 0.3, 0.5, 0.6, 0.7, 0.9, 1.0, 1.1, 7.3]
    order = distance_bands(delta)
    for kind, of in (("double", float), ("decimal(12,2)", lambda x: Decimal(str(x)))):
        items = spark.createDataFrame([(of(x),) for x in values], f"dist {kind}")
        assert [r[0] for r in items.select(order.key(items)).collect()] == [order.local(of(x), 0) for x in values]


def test_idle_classes_are_counted_without_rounds(spark, sf, monkeypatch):
    """Skipping classes in which nothing can act gives the counts of running them all."""
    from ordwork.plans.loop import Loop

    graph = EdgeSet(Store(spark, "idle").save(GRAPHS["lattice"](spark, sf).edges, "edges"))
    machine = shortest_paths(graph, 0, distance_bands(25))
    fast = run(spark, machine)
    assert (fast.measures.classes, fast.measures.rounds, fast.measures.processed, fast.measures.accepted) == (17, 49, 773, 208)
    monkeypatch.setattr(Loop, "ahead", lambda self, key: key)
    slow = run(spark, machine)
    assert [(t["class_key"], t["processed"], t["accepted"]) for t in fast.measures.trace] == [(t["class_key"], t["processed"], t["accepted"]) for t in slow.measures.trace]


def test_hubs_and_a_kept_base(spark, monkeypatch):
    """Edges beyond the near parts of a hub take their own join; the state is folded into its base at once."""
    from ordwork.graph import model
    from ordwork.plans import lockstep, loop

    monkeypatch.setattr(model.EdgeSet.dealt, "__defaults__", (8,))
    monkeypatch.setattr(lockstep, "NEAR_PARTS", 2)
    monkeypatch.setattr(loop, "RECENT", 0)
    rows = [(0, k, 1 + k % 7) for k in range(1, 80)] + [(k, 100 + k % 5, 2) for k in range(1, 80)] + [(100, k, 1) for k in range(200, 260)]
    for ordering in (chaotic(), distance_bands(2), level_bands(1)):
        assert state(run(spark, shortest_paths(edge_set(spark, rows), 0, ordering))) == heap(rows, 0)


def test_a_round_shuffles_its_frontier_only(spark, trade, monkeypatch):
    """One exchange in the plan of a round: neither the state's base nor the adjacency is shuffled again."""
    from ordwork import store
    from ordwork.plans import loop

    monkeypatch.setattr(loop, "RECENT", 0)
    plans, write = [], store.Store.write

    def spy(self, frame, name, partition_by=None):
        if name == "round":
            plans.append(frame._jdf.queryExecution().executedPlan().toString())
        return write(self, frame, name, partition_by)

    monkeypatch.setattr(store.Store, "write", spy)
    run(spark, shortest_paths(trade, 0, distance_bands(7)))
    lines = plans[-1].splitlines()
    own, deep = [], None
    for line in lines:
        depth = len(line) - len(line.lstrip(" :+-"))
        if deep is not None and depth > deep:
            continue
        deep = depth if "InMemoryRelation" in line else None
        own.append(line)
    assert sum("Exchange" in x for x in own) == 1 and "CartesianProduct" not in plans[-1] and "SortAggregate" not in "".join(own)
    assert sum("InMemoryTableScan" in x for x in own) == 2
    assert not any(x in plans[-1] for x in ("BroadcastNestedLoop", "CartesianProduct"))


def test_distance_order_gains_nothing_from_tiers(spark, trade):
    """Under the distance order at the root a local one changes neither classes nor work."""
    base = run(spark, shortest_paths(trade, 0, by_distance()), "drain", tiered(by_distance(), None)).measures
    for tier in ("task", "host"):
        m = run(spark, shortest_paths(trade, 0, by_distance()), "drain", tiered(by_distance(), tier)).measures
        assert (m.classes, m.processed, m.accepted) == (base.classes, base.processed, base.accepted)
