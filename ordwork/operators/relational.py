"""Operators around the methods: scans, joins, aggregates, windows, sets and functions on graphs, states and the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ordwork.functions.bands import Unpack, band_udf, mean_distance
from ordwork.sources.graphs import GRAPHS, table

BANDS = [(0, 4, "near"), (4, 8, "middle"), (8, 1 << 40, "far")]


def asof_join(left: DataFrame, right: DataFrame, on: str, time: str, value: str) -> DataFrame:
    """left with `value` of the last row of right at or before its time, per key: a union and a running last value,
    so it costs one shuffle and no row pairs. Both sides have columns (on, time); ties take right's rows first."""
    a = left.select("*", F.lit(None).cast(right.schema[value].dataType).alias(value), F.lit(1).alias("side"))
    b = right.select(*[F.col(c) if c in (on, time) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns], F.col(value), F.lit(0).alias("side"))
    order = Window.partitionBy(on).orderBy(time, "side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return a.unionByName(b).withColumn(value, F.last(value, True).over(order)).where("side = 1").drop("side")


def range_join(points: DataFrame, ranges: DataFrame, value: str, low: str, high: str, width: int) -> DataFrame:
    """points with the ranges [low, high) that hold their value, by buckets of a width: an equi-join on the bucket, then the test."""
    last = F.expr(f"({high} - 1) div {width}")
    cut = ranges.select("*", F.explode(F.sequence(F.expr(f"{low} div {width}"), last)).alias("bucket"))
    return points.withColumn("bucket", F.expr(f"{value} div {width}")).join(cut, "bucket").where((F.col(value) >= F.col(low)) & (F.col(value) < F.col(high))).drop("bucket")


def interval_pairs(events: DataFrame, minutes: int) -> DataFrame:
    """(user_id, first, second): pairs of events of a user at most so many minutes apart; each event is in its own and the
    next bucket of that width, so pairs meet in an equi-join."""
    seconds = events.select("user_id", "event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    width = minutes * 60 * 1_000_000
    a = seconds.select("user_id", F.col("event_id").alias("first"), F.col("t").alias("t1"), F.explode(F.array(F.expr(f"t div {width}L"), F.expr(f"t div {width}L + 1"))).alias("b"))
    b = seconds.select("user_id", F.col("event_id").alias("second"), F.col("t").alias("t2"), F.expr(f"t div {width}L").alias("b"))
    near = (F.col("t2") - F.col("t1")).between(0, width) & ((F.col("t1") < F.col("t2")) | (F.col("first") < F.col("second")))
    return a.join(b, ["user_id", "b"]).where(near).select("user_id", "first", "second")


def edges(spark: SparkSession, d: str, name: str = "trade") -> DataFrame:
    return GRAPHS[name](spark, d).edges


def steps(spark: SparkSession, d: str) -> DataFrame:
    """(v, dist): lightest in-edge of each trade vertex, a small state to work on."""
    return edges(spark, d).groupBy(F.col("dst").alias("v")).agg(F.min("w").alias("dist"))


def parts_in_orders(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").join(table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))


def counted(frame: DataFrame, *keys: str) -> DataFrame:
    return frame.groupBy(*keys).agg(F.count("*").alias("n"))


def bands(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(BANDS, "lo long, hi long, band string")


def union_of(kind: str) -> Callable:
    def query(spark, d):
        a, b = edges(spark, d, "handoff").select("src", "dst"), edges(spark, d, "handoff").select(F.col("dst").alias("src"), F.col("src").alias("dst"))
        return {"union_all": lambda: a.unionAll(b), "union": lambda: a.union(b).distinct(), "intersect": lambda: a.intersect(b), "except": lambda: a.subtract(b), "except_all": lambda: a.unionAll(a).exceptAll(b)}[kind]()

    return query


def over(column: Column, *order: str, by: tuple[str, ...] = ()) -> Column:
    return column.over(Window.partitionBy(*by).orderBy(*order))


def win(kind: str) -> Callable:
    def query(spark, d):
        orders = table(spark, d, "orders").select("o_orderkey", "o_custkey", F.col("o_orderdate").cast("date").alias("day"), F.round("o_totalprice", 0).cast("long").alias("price"))
        by = Window.partitionBy("o_custkey")
        column = {
            "rank_dist": F.rank().over(by.orderBy("price")),
            "dense_rank": F.dense_rank().over(by.orderBy("price")),
            "running_items": F.sum("price").over(by.orderBy("day", "o_orderkey").rowsBetween(Window.unboundedPreceding, Window.currentRow)),
            "range_frame": F.count("*").over(by.orderBy("price").rangeBetween(-1000, 1000)),
            "ntile": F.ntile(4).over(by.orderBy("price", "o_orderkey")),
            "lead": F.lead("o_orderkey").over(by.orderBy("day", "o_orderkey")),
        }[kind]
        return orders.select("o_orderkey", column.cast("long").alias("x"))

    return query


def grouping(kind: str) -> Callable:
    def query(spark, d):
        rows = parts_in_orders(spark, d).select("n_name", "o_orderpriority", "o_orderstatus")
        if kind == "sets":
            rows.createOrReplaceTempView("ordwork_grouping")
            return spark.sql("SELECT n_name, o_orderpriority, count(*) AS n FROM ordwork_grouping GROUP BY GROUPING SETS ((n_name), (o_orderpriority), ())")
        return (rows.cube if kind == "cube" else rows.rollup)("n_name", "o_orderstatus").agg(F.count("*").alias("n"))

    return query


def queries() -> dict:
    t = table
    joined = lambda kind: lambda spark, d: t(spark, d, "customer").select((2 * F.col("c_custkey")).alias("v")).join(steps(spark, d), "v", kind)
    return {
        "op_scan_prune_lineitem": lambda spark, d: t(spark, d, "lineitem").where(F.col("l_quantity") >= 45).select("l_orderkey", "l_linenumber", F.col("l_quantity").cast("long").alias("q")),
        "op_filter_subgraph_dates": lambda spark, d: t(spark, d, "orders").where(F.col("o_orderdate") < F.lit("1997-01-01").cast("timestamp_ntz")).join(t(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).select((2 * F.col("o_custkey")).alias("src"), (2 * F.col("l_suppkey") + 1).alias("dst")).distinct(),
        "op_project_edge_weight": lambda spark, d: t(spark, d, "lineitem").select("l_orderkey", "l_partkey", (F.col("l_quantity").cast("long") * 2 + F.col("l_linenumber")).alias("w")),
        "op_join_inner": joined("inner"),
        "op_join_left_unreached": joined("left"),
        "op_join_semi_frontier": lambda spark, d: edges(spark, d, "handoff").join(t(spark, d, "customer").where("c_acctbal > 5000").select(F.col("c_custkey").alias("src")), "src", "left_semi").select("src", "dst", "w"),
        "op_join_anti_unreached": lambda spark, d: t(spark, d, "customer").select((2 * F.col("c_custkey")).alias("v")).join(steps(spark, d).where("dist < 2"), "v", "left_anti"),
        "op_join_full_compare": lambda spark, d: steps(spark, d).where("dist > 1").join(steps(spark, d).where("dist < 3").withColumnRenamed("dist", "dist2"), "v", "full").select("v", "dist", "dist2"),
        "op_join_broadcast_nation": lambda spark, d: counted(t(spark, d, "customer").join(F.broadcast(t(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")), "n_name"),
        "op_join_range_band": lambda spark, d: range_join(steps(spark, d), bands(spark).withColumn("hi", F.least("hi", F.lit(1000))), "dist", "lo", "hi", 4).select("v", "dist", "band"),
        "op_join_theta_pairs": lambda spark, d: t(spark, d, "nation").select(F.col("n_nationkey").alias("a"), F.col("n_regionkey").alias("ra")).join(t(spark, d, "nation").select(F.col("n_nationkey").alias("b"), F.col("n_regionkey").alias("rb")), F.expr("ra < rb and a > b")).select("a", "b"),
        "op_join_asof_events": lambda spark, d: asof_join(t(spark, d, "events").where("event_type = 'click'").select("user_id", "ts", "event_id"), t(spark, d, "events").where("event_type <> 'click'").groupBy("user_id", "ts").agg(F.max("event_id").alias("last")), "user_id", "ts", "last").select("event_id", "last"),
        "op_join_interval_events": lambda spark, d: interval_pairs(t(spark, d, "events"), 10),
        "op_agg_degree": lambda spark, d: edges(spark, d).groupBy("src").agg(F.count("*").alias("degree"), F.min("w").alias("least"), F.sum("w").alias("total")),
        "op_agg_distinct": lambda spark, d: t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("supps")),
        "op_agg_filter": lambda spark, d: edges(spark, d).groupBy("src").agg(F.count_if(F.col("w") <= 5).alias("light"), F.count_if(F.col("w") > 40).alias("heavy")),
        "op_agg_having": lambda spark, d: edges(spark, d).groupBy("dst").agg(F.count("*").alias("n")).where("n >= 70"),
        "op_grouping_sets": grouping("sets"),
        "op_cube": grouping("cube"),
        "op_rollup": grouping("rollup"),
        "op_win_lead_handoff": win("lead"),
        **{f"op_win_{k}": win(k) for k in ("rank_dist", "dense_rank", "running_items", "range_frame", "ntile")},
        "op_topk_nearest": lambda spark, d: steps(spark, d).orderBy("dist", "v").limit(20),
        "op_topk_per_nation": lambda spark, d: t(spark, d, "customer").withColumn("r", over(F.row_number(), F.desc("c_acctbal"), "c_custkey", by=("c_nationkey",)).cast("long")).where("r <= 3").select("c_nationkey", "c_custkey", "r"),
        "op_sort_limit": lambda spark, d: t(spark, d, "lineitem").orderBy("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").limit(50).select("l_orderkey", "l_partkey", "l_suppkey"),
        **{f"op_{k}": union_of(k) for k in ("union_all", "union", "intersect", "except", "except_all")},
        "op_str_keys": lambda spark, d: t(spark, d, "pages").select("page_id", F.md5(F.col("url").cast("binary")).alias("h"), F.regexp_extract("url", "://([^/?#]*)", 1).alias("host"), F.upper(F.substring("url", 1, 8)).alias("head"), F.size(F.split("url", "/")).cast("long").alias("parts")),
        "op_math_bands": lambda spark, d: steps(spark, d).select("v", F.expr("dist div 7").alias("band"), F.pmod("dist", F.lit(7)).alias("rest"), F.shiftleft("dist", 3).alias("up"), F.bit_count("v").cast("long").alias("ones")),
        "op_date_gaps": lambda spark, d: t(spark, d, "orders").select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1992-01-01").cast("date")).cast("long").alias("days"), F.date_trunc("month", "o_orderdate").cast("date").cast("string").alias("month")),
        "op_array_adjacency": lambda spark, d: edges(spark, d, "handoff").groupBy("src").agg(F.array_join(F.array_sort(F.collect_list("dst")), ",").alias("nbrs"), F.count("*").alias("n")),
        "op_array_explode": lambda spark, d: edges(spark, d, "handoff").groupBy("src").agg(F.collect_list(F.struct("dst", "w")).alias("nbrs")).select("src", F.explode("nbrs").alias("e")).select("src", "e.dst", "e.w"),
        "op_map_lookup": lambda spark, d: t(spark, d, "nation").agg(F.map_from_entries(F.collect_list(F.struct("n_nationkey", "n_name"))).alias("m")).crossJoin(t(spark, d, "customer")).select("c_custkey", F.element_at("m", F.col("c_nationkey")).alias("name")),
        "op_json_props": lambda spark, d: t(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.from_json("props", "k long")["k"].alias("k2")),
        "op_pandas_udf_band": lambda spark, d: steps(spark, d).select("v", band_udf(4)(F.col("dist")).alias("band")),
        "op_udtf_neighbors": udtf_neighbors,
        "op_udaf_class_stats": lambda spark, d: steps(spark, d).groupBy((F.col("v") % 2).alias("side")).agg(F.round(mean_distance("dist"), 6).alias("mean")),
        "op_approx_reached": lambda spark, d: edges(spark, d).agg(F.approx_count_distinct("dst").alias("about"), F.percentile_approx("w", 0.5).alias("median")),
        "op_percentile_exact": lambda spark, d: edges(spark, d).groupBy((F.col("src") % 2).alias("side")).agg(F.percentile("w", 0.9).alias("p90")),
        "op_recursive_hops": recursive_hops,
        "op_pivot_tiers": lambda spark, d: t(spark, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).select("o_orderpriority", *[F.coalesce(c, F.lit(0)).cast("long").alias(c.lower()) for c in "FOP"]),
        "op_null_safe_filter": lambda spark, d: joined("left")(spark, d).where(F.col("dist").eqNullSafe(F.lit(1))).select("v"),
    }


def udtf_neighbors(spark: SparkSession, d: str) -> DataFrame:
    spark.udtf.register("unpack_edges", Unpack)
    edges(spark, d, "handoff").groupBy("src").agg(F.collect_list(F.struct("dst", "w")).alias("nbrs")).createOrReplaceTempView("ordwork_adjacency")
    return spark.sql("SELECT a.src, t.dst, t.w FROM ordwork_adjacency a, LATERAL unpack_edges(a.nbrs) t")


def recursive_hops(spark: SparkSession, d: str) -> DataFrame:
    edges(spark, d, "nation_ring").createOrReplaceTempView("ordwork_ring")
    return spark.sql("WITH RECURSIVE h(v, hops) AS (SELECT CAST(0 AS BIGINT), CAST(0 AS BIGINT) UNION ALL SELECT e.dst, h.hops + 1 FROM h JOIN ordwork_ring e ON e.src = h.v WHERE h.hops < 24) SELECT v, hops FROM h")


def oracle_sql() -> dict[str, str]:
    from ordwork.workloads.sql import EDGES

    e, h = f"({EDGES['trade']})", f"({EDGES['handoff']})"
    steps_sql = f"(SELECT dst AS v, min(w) AS dist FROM {e} GROUP BY 1)"
    customers = "(SELECT 2 * c_custkey AS v FROM customer) c"
    one, two = f"SELECT src, dst FROM {h}", f"SELECT dst AS src, src AS dst FROM {h}"
    orders = "SELECT o_orderkey, o_custkey, o_orderdate::DATE AS day, round(o_totalprice)::BIGINT AS price FROM orders"
    windows = {
        "rank_dist": "rank() OVER (PARTITION BY o_custkey ORDER BY price)",
        "dense_rank": "dense_rank() OVER (PARTITION BY o_custkey ORDER BY price)",
        "running_items": "sum(price) OVER (PARTITION BY o_custkey ORDER BY day, o_orderkey ROWS UNBOUNDED PRECEDING)",
        "range_frame": "count(*) OVER (PARTITION BY o_custkey ORDER BY price RANGE BETWEEN 1000 PRECEDING AND 1000 FOLLOWING)",
        "ntile": "ntile(4) OVER (PARTITION BY o_custkey ORDER BY price, o_orderkey)",
        "lead_handoff": "lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY day, o_orderkey)",
    }
    grouped = "FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey"
    return {
        "op_scan_prune_lineitem": "SELECT l_orderkey, l_linenumber, l_quantity::BIGINT AS q FROM lineitem WHERE l_quantity >= 45",
        "op_filter_subgraph_dates": "SELECT DISTINCT 2 * o_custkey AS src, 2 * l_suppkey + 1 AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_orderdate < TIMESTAMP '1997-01-01'",
        "op_project_edge_weight": "SELECT l_orderkey, l_partkey, l_quantity::BIGINT * 2 + l_linenumber AS w FROM lineitem",
        "op_join_inner": f"SELECT v, dist FROM {customers} JOIN {steps_sql} USING (v)",
        "op_join_left_unreached": f"SELECT v, dist FROM {customers} LEFT JOIN {steps_sql} USING (v)",
        "op_join_semi_frontier": f"SELECT src, dst, w FROM {h} WHERE src IN (SELECT c_custkey FROM customer WHERE c_acctbal > 5000)",
        "op_join_anti_unreached": f"SELECT v FROM {customers} WHERE v NOT IN (SELECT v FROM {steps_sql} WHERE dist < 2)",
        "op_join_full_compare": f"SELECT v, a.dist, b.dist AS dist2 FROM (SELECT * FROM {steps_sql} WHERE dist > 1) a FULL JOIN (SELECT * FROM {steps_sql} WHERE dist < 3) b USING (v)",
        "op_join_broadcast_nation": "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1",
        "op_join_range_band": f"SELECT v, dist, CASE WHEN dist < 4 THEN 'near' WHEN dist < 8 THEN 'middle' ELSE 'far' END AS band FROM {steps_sql}",
        "op_join_theta_pairs": "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey < b.n_regionkey AND a.n_nationkey > b.n_nationkey",
        "op_join_asof_events": "SELECT a.event_id, b.last FROM (SELECT * FROM events WHERE event_type = 'click') a ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS last FROM events WHERE event_type <> 'click' GROUP BY 1, 2) b ON a.user_id = b.user_id AND a.ts >= b.ts",
        "op_join_interval_events": "SELECT a.user_id, a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE AND (a.ts < b.ts OR a.event_id < b.event_id)",
        "op_agg_degree": f"SELECT src, count(*) AS degree, min(w) AS least, sum(w)::BIGINT AS total FROM {e} GROUP BY 1",
        "op_agg_distinct": "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS supps FROM lineitem GROUP BY 1",
        "op_agg_filter": f"SELECT src, count(*) FILTER (w <= 5) AS light, count(*) FILTER (w > 40) AS heavy FROM {e} GROUP BY 1",
        "op_agg_having": f"SELECT dst, count(*) AS n FROM {e} GROUP BY 1 HAVING count(*) >= 70",
        "op_grouping_sets": f"SELECT n_name, o_orderpriority, count(*) AS n {grouped} GROUP BY GROUPING SETS ((n_name), (o_orderpriority), ())",
        "op_cube": f"SELECT n_name, o_orderstatus, count(*) AS n {grouped} GROUP BY CUBE (n_name, o_orderstatus)",
        "op_rollup": f"SELECT n_name, o_orderstatus, count(*) AS n {grouped} GROUP BY ROLLUP (n_name, o_orderstatus)",
        **{f"op_win_{k}": f"SELECT o_orderkey, ({w})::BIGINT AS x FROM ({orders})" for k, w in windows.items()},
        "op_topk_nearest": f"SELECT v, dist FROM {steps_sql} ORDER BY dist, v LIMIT 20",
        "op_topk_per_nation": "SELECT c_nationkey, c_custkey, r FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) WHERE r <= 3",
        "op_sort_limit": "SELECT l_orderkey, l_partkey, l_suppkey FROM lineitem ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey LIMIT 50",
        "op_union_all": f"{one} UNION ALL {two}",
        "op_union": f"{one} UNION {two}",
        "op_intersect": f"{one} INTERSECT {two}",
        "op_except": f"{one} EXCEPT {two}",
        "op_except_all": f"({one} UNION ALL {one}) EXCEPT ALL ({two})",
        "op_str_keys": "SELECT page_id, md5(url) AS h, regexp_extract(url, '://([^/?#]*)', 1) AS host, upper(substr(url, 1, 8)) AS head, len(string_split(url, '/'))::BIGINT AS parts FROM pages",
        "op_math_bands": f"SELECT v, dist // 7 AS band, dist % 7 AS rest, dist << 3 AS up, bit_count(v)::BIGINT AS ones FROM {steps_sql}",
        "op_date_gaps": "SELECT o_orderkey, year(o_orderdate)::BIGINT AS y, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::BIGINT AS days, date_trunc('month', o_orderdate)::DATE::VARCHAR AS month FROM orders",
        "op_array_adjacency": f"SELECT src, string_agg(dst, ',' ORDER BY dst) AS nbrs, count(*) AS n FROM {h} GROUP BY 1",
        "op_array_explode": f"SELECT src, dst, w FROM {h}",
        "op_map_lookup": "SELECT c_custkey, n_name AS name FROM customer JOIN nation ON c_nationkey = n_nationkey",
        "op_json_props": "SELECT event_id, (props->>'$.k')::BIGINT AS k, (props->>'$.k')::BIGINT AS k2 FROM events",
        "op_pandas_udf_band": f"SELECT v, dist // 4 AS band FROM {steps_sql}",
        "op_udtf_neighbors": f"SELECT src, dst, w FROM {h}",
        "op_udaf_class_stats": f"SELECT v % 2 AS side, round(avg(dist), 6) AS mean FROM {steps_sql} GROUP BY 1",
        "op_percentile_exact": f"SELECT src % 2 AS side, quantile_cont(w, 0.9) AS p90 FROM {e} GROUP BY 1",
        "op_recursive_hops": f"WITH RECURSIVE h(v, hops) AS (SELECT 0::BIGINT, 0::BIGINT UNION ALL SELECT e.dst, h.hops + 1 FROM h JOIN ({EDGES['nation_ring']}) e ON e.src = h.v WHERE h.hops < 24) SELECT v, hops FROM h",
        "op_pivot_tiers": "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o, count(*) FILTER (o_orderstatus = 'P') AS p FROM orders GROUP BY 1",
        "op_null_safe_filter": f"SELECT v FROM {customers} JOIN {steps_sql} USING (v) WHERE dist = 1",
    }
