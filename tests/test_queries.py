"""Registered queries against their SQL on the smallest tables, and the layout of the entry module."""

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: SQL of these is written for the scale of sf0.01.
OTHER_SCALE = ("rmat",)
SOME = [
    "graph_trade", "graph_handoff", "graph_lattice", "graph_copurchase", "graph_page_links", "graph_knn", "tier_placement_trade", "sssp_kla2_copurchase",
    "sssp_delta5_handoff", "example_tree_trade", "selfstab_sync_random_start_trade", "bfs_page_links", "components_handoff", "parents_trade", "pagerank_trade",
    "kla1_measures_copurchase", "class_profile_dijkstra_trade", "order_axioms", "ans_by_nation", "ans_path_to", "stream_repair", "stream_session_users", "stream_running_minimum",
    *[n for n in entry.queries() if n.startswith("op_")],
]


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", SOME)
def test_query(spark, sf, duck, name):
    frame = entry.queries()[name](spark, sf)
    rows = frame.collect()
    assert len(set(frame.columns)) == len(frame.columns)
    if name in entry.oracle_sql():
        found = duck.execute(entry.oracle_sql()[name])
        names = [x[0] for x in found.description]
        assert sorted(frame.columns) == sorted(names)
        order = sorted(names)
        key = lambda row, columns: tuple(repr(row[columns.index(c)]) for c in order)
        assert sorted(key(r, frame.columns) for r in rows) == sorted(key(r, names) for r in found.fetchall())


@pytest.mark.parametrize("name", ["graph_rmat1", "graph_rmat2", "in_degree_rmat1", "sssp_delta25_rmat1"])
def test_matrix_graphs_have_the_scale_of_their_sql(spark, sf, duck, name):
    """At every size: here there are 6,000 draws, for which the number of rows would give another scale."""
    test_query(spark, sf, duck, name)


def reads(spark, sf, duck, name, table, column, tmp_path):
    """The query fails where its table is missing a column that it should read."""
    con = duckdb.connect()
    con.execute(f"COPY (SELECT * EXCLUDE ({column}) FROM '{sf}/{table}.parquet') TO '{tmp_path}/{table}.parquet' (FORMAT parquet)")
    with pytest.raises(Exception, match=column):
        entry.queries()[name](spark, str(tmp_path)).collect()
    test_query(spark, sf, duck, name)


def test_small_graph_reads_customers(spark, sf, duck, tmp_path):
    reads(spark, sf, duck, "graph_toy", "customer", "c_custkey", tmp_path)


def test_axioms_read_lineitem(spark, sf, duck, tmp_path):
    reads(spark, sf, duck, "order_axioms", "lineitem", "l_quantity", tmp_path)


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_nothing_else_imports_the_llm_subpackage():
    from pathlib import Path

    import ordwork

    root = Path(ordwork.__file__).parent
    for path in root.rglob("*.py"):
        if "llm" not in path.relative_to(root).parts:
            assert "ordwork.llm" not in path.read_text(), path
