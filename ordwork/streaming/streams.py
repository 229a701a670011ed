"""Streams of edges and events: repair of distances as edges arrive, relaxation by one hop a trigger, distances by window, event counts, sessions,
deduplication, and a stateful running minimum by key.

Results of streaming queries are Parquet tables, a folder a batch that is written over if the batch is delivered again; nothing is kept in the driver's memory.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ordwork.baselines.stabilize import stabilize
from ordwork.core.machine import Machine, RunResult, run, shortest_paths
from ordwork.core.ordering import chaotic
from ordwork.core.rule import sssp_rule
from ordwork.graph.model import EdgeSet
from ordwork.sources.graphs import table
from ordwork.store import Store


class Repair:
    """Distances kept right while edges are inserted or get cheaper.

    A batch of new edges seeds items d(src) + w for the reached sources; as distances only fall, running the machine to rest from
    there is enough. With a folder, each batch ends with a commit row (batch id, tables of edges and state) in it, so a Repair that is made
    again on the folder goes on after the last commit, and a batch that is delivered again changes nothing. Batch ids go up, as those of a streaming query do.
    """

    def __init__(self, spark: SparkSession, source: int, folder: str | None = None):
        self.spark, self.source, self.folder, self.store = spark, source, folder, Store(spark, "repair", folder)
        self.edges: DataFrame | None = None
        self.state: DataFrame | None = None
        self.last = -1
        if folder and self.store.exists(f"{folder}/commits"):
            done = spark.read.parquet(f"{folder}/commits").orderBy(F.desc("id")).first()
            self.last, self.edges, self.state = done["id"], spark.read.parquet(done["edges"]), spark.read.parquet(done["state"])

    def commit(self, edges: DataFrame, state: DataFrame, batch_id: int) -> None:
        paths = [self.store.write(edges, "edges"), self.store.write(state, "state")]
        self.edges, self.state = (self.spark.read.parquet(p) for p in paths)
        if self.folder:
            row = self.spark.createDataFrame([(batch_id, *paths)], "id long, edges string, state string")
            row.coalesce(1).write.mode("overwrite").parquet(f"{self.folder}/commits/batch={batch_id}")
        self.last = batch_id

    def insert(self, batch: EdgeSet, batch_id: int) -> None:
        if batch_id <= self.last:
            return
        new = self.store.save(batch.collapse().edges, "batch")
        if self.edges is None:
            self.commit(new, run(self.spark, shortest_paths(EdgeSet(new), self.source, chaotic())).state, batch_id)
            return
        edges = self.store.save(EdgeSet(self.edges.union(new)).collapse().edges, "edges")
        offers = new.join(self.state, F.col("src") == F.col("v")).select(F.col("dst").alias("u"), (F.col("dist") + F.col("w")).alias("offer"))
        better = offers.join(self.state, F.col("u") == F.col("v"), "left").where(F.col("dist").isNull() | (F.col("offer") < F.col("dist"))).groupBy(F.col("u").alias("v")).agg(F.min("offer").alias("dist"))
        better = self.store.save(better, "better")
        state = self.merged(better, edges) if better.limit(1).count() else self.state
        self.commit(edges, state, batch_id)

    def merged(self, better: DataFrame, edges: DataFrame) -> DataFrame:
        """State after draining the better offers: rounds that only look at what improved."""
        state = self.state.unionByName(better).groupBy("v").agg(F.min("dist").alias("dist"))
        frontier = better
        while True:
            state = self.store.save(state, "state")
            offers = frontier.join(edges, F.col("v") == F.col("src")).groupBy(F.col("dst").alias("u")).agg(F.min(F.col("dist") + F.col("w")).alias("offer"))
            gain = offers.join(state, F.col("u") == F.col("v"), "left").where(F.col("dist").isNull() | (F.col("offer") < F.col("dist"))).select(F.col("u").alias("v"), F.col("offer").alias("dist"))
            frontier = self.store.save(gain, "frontier")
            if not frontier.limit(1).count():
                return state
            state = state.unionByName(frontier).groupBy("v").agg(F.min("dist").alias("dist"))

    def delete(self, edges: DataFrame) -> RunResult:
        """Without the edges (src, dst): what might have used them is pulled anew from the present state, self-stabilizing."""
        rest = self.store.save(self.edges.join(edges.select("src", "dst"), ["src", "dst"], "left_anti"), "edges")
        graph = EdgeSet(rest)
        start = graph.vertices().union(self.state.select("v")).union(self.spark.createDataFrame([(self.source,)], "v long")).distinct().join(self.state, "v", "left").select("v", "dist")
        result = stabilize(self.spark, graph, self.source, start)
        self.commit(rest, result.state, self.last)
        return result


def replay(spark: SparkSession, sf_dir: str, each, chunks: int = 4) -> None:
    """Events as a file stream of so many chunks in order of time, one a trigger, handed to each(batch, batch_id)."""
    store = Store(spark, "replay")
    events = table(spark, sf_dir, "events")
    n = events.agg(F.max("event_id")).first()[0] + 1
    path = store.path("chunks")
    size = -(-n // chunks)
    for k in range(chunks):  # ids follow time in this table
        events.where(F.col("event_id").between(k * size, (k + 1) * size - 1)).coalesce(1).write.mode("append").parquet(path)
    source = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)
    query = source.writeStream.foreachBatch(each).option("checkpointLocation", store.path("progress")).trigger(availableNow=True).start()
    query.awaitTermination()


def sequence_edges(events: DataFrame) -> EdgeSet:
    """Each event as an edge of its user to the user of its props' k: an edge set that doesn't depend on batches."""
    k = F.get_json_object("props", "$.k").cast("long")
    return EdgeSet.of(events.where("user_id is not null").select(F.col("user_id").alias("src"), k.alias("dst"), (1 + F.col("event_id") % 100).alias("w")).where("dst is not null"))


def repair_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    source = 0
    repair = Repair(spark, source)
    replay(spark, sf_dir, lambda batch, i: repair.insert(sequence_edges(batch), i))
    return repair.state


def timed(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """ts as TIMESTAMP, which watermarks need, with a watermark."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def store_events(spark: SparkSession, sf_dir: str, store: Store) -> str:
    return store.write(table(spark, sf_dir, "events").coalesce(2), "events")


def event_stream(spark: SparkSession, sf_dir: str, path: str, **options) -> DataFrame:
    return spark.readStream.schema(table(spark, sf_dir, "events").schema).options(**options).parquet(path)


def drained(frame: DataFrame, store: Store, mode: str) -> DataFrame:
    """Rows of a streaming query that has run through what there is: in complete mode the last batch, in append mode all batches, each a folder of its own."""
    out = store.path("batches")

    def keep(batch: DataFrame, i: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={0 if mode == 'complete' else i}")

    query = frame.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", store.path("progress")).trigger(availableNow=True).start()
    query.awaitTermination()
    return frame.sparkSession.read.schema(frame.schema).parquet(f"{out}/*")


def collected(spark: SparkSession, sf_dir: str, build) -> DataFrame:
    """Final rows of a streaming query over all events, in complete mode."""
    store = Store(spark, "stream")
    return drained(build(event_stream(spark, sf_dir, store_events(spark, sf_dir, store))), store, "complete")


def windowed_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of each user in tumbling days."""
    rows = collected(spark, sf_dir, lambda s: s.withColumn("ts", F.col("ts").cast("timestamp")).groupBy(F.window("ts", "1 day").alias("w"), "user_id").agg(F.count("*").alias("degree")))
    return rows.select(F.unix_seconds(F.col("w.start")).alias("day"), "user_id", "degree")


def sliding_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of each user in windows of two days that start every day."""
    rows = collected(spark, sf_dir, lambda s: s.withColumn("ts", F.col("ts").cast("timestamp")).groupBy(F.window("ts", "2 days", "1 day").alias("w"), "user_id").agg(F.count("*").alias("degree")))
    return rows.select(F.unix_seconds(F.col("w.start")).alias("day"), "user_id", "degree")


#: Bits of a vertex id under its window's number.
WINDOW_BITS = 40
WINDOW_SECONDS = 10 * 86400


def window_distances(spark: SparkSession, sf_dir: str, source: int = 0) -> DataFrame:
    """(window, v, dist): distances from source in the graph of each tumbling window of ten days.

    The stream keeps the lightest edge of a window; one run of the machine then serves all windows, as vertices carry their window's number.
    """
    number = F.floor(F.unix_seconds("ts") / WINDOW_SECONDS)
    build = lambda s: sequence_rows(s.withColumn("ts", F.col("ts").cast("timestamp"))).groupBy(number.alias("window"), "src", "dst").agg(F.min("w").alias("w"))
    store = Store(spark, "windows")
    rows = store.save(collected(spark, sf_dir, build), "edges")
    name = lambda v: F.shiftleft("window", WINDOW_BITS) + v
    graph = EdgeSet.of(rows.select(name(F.col("src")).alias("src"), name(F.col("dst")).alias("dst"), "w"))
    seeds = rows.select(name(F.lit(source)).alias("v"), F.lit(0).cast("long").alias("dist")).distinct()
    state = run(spark, Machine(graph, sssp_rule(), chaotic(), seeds)).state
    return state.select(F.shiftright("v", WINDOW_BITS).alias("window"), F.col("v").bitwiseAND(F.lit((1 << WINDOW_BITS) - 1)).alias("v"), "dist")


def sequence_rows(events: DataFrame) -> DataFrame:
    """events with src, dst and w of sequence_edges."""
    rows = events.withColumns({"src": F.col("user_id"), "dst": F.get_json_object("props", "$.k").cast("long"), "w": 1 + F.col("event_id") % 100})
    return rows.where("src is not null and dst is not null")


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Number of sessions of each user, parted by gaps of 12 hours or more."""
    rows = collected(spark, sf_dir, lambda s: s.withColumn("ts", F.col("ts").cast("timestamp")).groupBy(F.session_window("ts", "12 hours").alias("w"), "user_id").agg(F.count("*").alias("n")))
    return rows.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("events"))


def running_minimum(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lightest weight that reached each user so far, by a custom stateful operator: the last value of each key."""
    store = Store(spark, "stateful")
    source = event_stream(spark, sf_dir, store_events(spark, sf_dir, store), maxFilesPerTrigger=1)

    def update(key, batches, state):
        least = state.get[0] if state.exists else None
        for pdf in batches:
            now = int(pdf["w"].min())
            least = now if least is None else min(least, now)
        state.update((least,))
        yield pd.DataFrame({"v": [key[0]], "least": [least]})

    edges = sequence_edges(source).edges
    values = edges.select(F.col("dst").alias("v"), "w").groupBy("v").applyInPandasWithState(update, "v long, least long", "least long", "append", "NoTimeout")
    return drained(values, store, "append").groupBy("v").agg(F.min("least").alias("least"))


def hop_by_trigger(spark: SparkSession, edges: DataFrame, source: int, most: int = 10_000) -> tuple[DataFrame, int]:
    """((v, dist), triggers): relaxation by one hop a trigger, each vertex a key of a stateful operator.

    The state of a vertex is its distance and its out-edges. Offers (v, dist) and edges (v, dst, w) come in as files; a vertex whose distance falls
    sends offers along its edges, and what a batch sends is written as the next trigger's input. It ends with a trigger that sends nothing.
    """
    store = Store(spark, "hops")
    inbox, known = store.path("inbox"), store.path("known")
    rows = edges.select(F.col("src").alias("v"), F.lit(None).cast("long").alias("dist"), "dst", "w")
    rows.union(spark.createDataFrame([(source, 0, None, None)], "v long, dist long, dst long, w long")).write.parquet(f"{inbox}/batch=-1")

    def update(key, batches, state):
        dist, dsts, ws = state.get if state.exists else (None, [], [])
        dsts, ws, offers, old = list(dsts), list(ws), [], len(dsts)
        for pdf in batches:
            offers += pdf["dist"].dropna().astype("int64").tolist()
            new = pdf[pdf["dst"].notna()]
            dsts += new["dst"].astype("int64").tolist()
            ws += new["w"].astype("int64").tolist()
        least = min(offers, default=None)
        fell = least is not None and (dist is None or least < dist)
        dist = least if fell else dist
        state.update((dist, dsts, ws))
        first = 0 if fell else old if dist is not None else len(dsts)  # edges that came after the distance was known hear of it too
        sent = [(d, dist + w, True) for d, w in zip(dsts[first:], ws[first:], strict=True)]
        out = sent + ([(key[0], dist, False)] if fell else [])
        yield pd.DataFrame(out, columns=["v", "dist", "offer"]).astype({"v": "int64", "dist": "int64", "offer": bool})

    sends: list[bool] = []

    def deliver(batch: DataFrame, i: int) -> None:
        batch = batch.persist()
        least = batch.where("offer").groupBy("v").agg(F.min("dist").alias("dist"))
        empty = F.lit(None).cast("long")
        least.select("v", "dist", empty.alias("dst"), empty.alias("w")).write.mode("overwrite").parquet(f"{inbox}/batch={i}")
        batch.where("not offer").select("v", "dist").write.mode("overwrite").parquet(f"{known}/batch={i}")
        sends.append(bool(batch.where("offer").limit(1).count()))
        batch.unpersist()

    progress, triggers = store.path("progress"), 0
    while triggers < most:
        stream = spark.readStream.schema("v long, dist long, dst long, w long").parquet(f"{inbox}/*")
        moved = stream.groupBy("v").applyInPandasWithState(update, "v long, dist long, offer boolean", "dist long, dsts array<long>, ws array<long>", "append", "NoTimeout")
        sends.clear()
        moved.writeStream.foreachBatch(deliver).option("checkpointLocation", progress).trigger(availableNow=True).start().awaitTermination()
        triggers += 1
        if not any(sends):
            break
    found = spark.read.schema("v long, dist long").parquet(f"{known}/*")
    return found.groupBy("v").agg(F.min("dist").alias("dist")), triggers


def hops_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    edges = Store(spark, "hop-edges").save(sequence_edges(table(spark, sf_dir, "events")).collapse().edges, "edges")
    return hop_by_trigger(spark, edges, 0)[0]


def deduplicated(events: DataFrame) -> DataFrame:
    """Events once each within the watermark; late insertions stay right as repair is monotone."""
    return timed(events).dropDuplicatesWithinWatermark(["event_id"])


def dedup_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of each user from a stream that delivers every file twice."""
    store = Store(spark, "dedup")
    events = table(spark, sf_dir, "events")
    path = store.path("twice")
    middle = events.agg(F.percentile_approx("event_id", 0.5)).first()[0]  # ids follow time in this table
    for half in (events.where(F.col("event_id") <= middle), events.where(F.col("event_id") > middle)):
        for _ in range(2):
            half.coalesce(1).write.mode("append").parquet(path)
    once = drained(deduplicated(event_stream(spark, sf_dir, path, maxFilesPerTrigger=1)), store, "append")
    return once.groupBy("user_id").agg(F.count("*").alias("events"), F.sum("event_id").alias("ids"))


def queries() -> dict:
    return {
        "stream_repair": repair_query, "stream_windowed_degree": windowed_degree, "stream_sliding_degree": sliding_degree, "stream_window_distances": window_distances,
        "stream_session_users": sessions, "stream_running_minimum": running_minimum, "stream_hop_by_trigger": hops_query, "stream_dedup": dedup_query,
    }


def oracle_sql() -> dict[str, str]:
    edge = "SELECT user_id AS src, (props->>'$.k')::BIGINT AS dst, (1 + event_id % 100)::BIGINT AS w FROM events"
    distances = f"""WITH RECURSIVE e AS MATERIALIZED ({edge}), d(v, dist) USING KEY (v) AS (SELECT 0::BIGINT, 0::BIGINT UNION
          SELECT e.dst, min(d.dist + e.w)::BIGINT FROM d JOIN e ON e.src = d.v LEFT JOIN recurring.d AS r ON r.v = e.dst WHERE e.dst IS NOT NULL AND (r.v IS NULL OR d.dist + e.w < r.dist) GROUP BY e.dst) SELECT v, dist FROM d"""
    return {
        "stream_repair": distances,
        "stream_hop_by_trigger": distances,
        "stream_dedup": "SELECT user_id, count(*) AS events, sum(event_id)::BIGINT AS ids FROM events GROUP BY 1",
        "stream_sliding_degree": "SELECT epoch(date_trunc('day', ts))::BIGINT - 86400 * back AS day, user_id, count(*) AS degree FROM events, (SELECT unnest([0, 1]) AS back) GROUP BY 1, 2",
        "stream_window_distances": f"""WITH RECURSIVE e AS MATERIALIZED (SELECT epoch(ts)::BIGINT // {WINDOW_SECONDS} AS win, src, dst, min(w) AS w FROM ({edge.replace('SELECT ', 'SELECT ts, ', 1)}) WHERE src IS NOT NULL AND dst IS NOT NULL GROUP BY 1, 2, 3),
          d(win, v, dist) USING KEY (win, v) AS (SELECT DISTINCT win, 0::BIGINT, 0::BIGINT FROM e UNION
          SELECT e.win, e.dst, min(d.dist + e.w)::BIGINT FROM d JOIN e ON e.win = d.win AND e.src = d.v LEFT JOIN recurring.d AS r ON r.win = e.win AND r.v = e.dst
          WHERE r.v IS NULL OR d.dist + e.w < r.dist GROUP BY 1, 2) SELECT win AS window, v, dist FROM d""",
        "stream_windowed_degree": "SELECT epoch(date_trunc('day', ts))::BIGINT AS day, user_id, count(*) AS degree FROM events GROUP BY 1, 2",
        "stream_session_users": """SELECT user_id, sum(new)::BIGINT AS sessions, count(*) AS events FROM (
          SELECT user_id, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w >= INTERVAL 12 HOUR THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)) GROUP BY 1""",
        "stream_running_minimum": f"SELECT dst AS v, min(w) AS least FROM ({edge}) WHERE dst IS NOT NULL AND src IS NOT NULL GROUP BY 1",
    }


