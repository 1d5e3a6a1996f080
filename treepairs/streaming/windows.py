"""Descriptions that arrive as a stream: windows of events searched as they close, and a set that grows."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..checkpoints import shared_folder
from ..functions.columns import ratio
from ..ontology import Ontology, node_key
from ..operators.min_join import mindist_topk, nearest, node_pairs
from ..operators.objects import subtree_minima
from ..operators.search import checkpoint, ranked
from ..sql import key_sql

#: A week of events is an object set; users are the objects.
WINDOW = "7 days"


def weekly_terms(events: DataFrame) -> DataFrame:
    """win, obj_id, k1, k2 of a (streaming or static) events table."""
    return events.select(F.window("ts", WINDOW).start.alias("win"), F.col("user_id").alias("obj_id"), F.col("event_type").alias("k1"), F.hour("ts").alias("k2"))


def windowed_counts(events: DataFrame, watermark: str | None = None) -> DataFrame:
    """win, event_type, n, users (approximate): plain windowed aggregates with a watermark on streams."""
    e = events.withWatermark("ts", watermark) if watermark else events
    return e.groupBy(F.window("ts", WINDOW).start.alias("win"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.approx_count_distinct("user_id").alias("users"))


def sessions(events: DataFrame, gap: str = "1 day", watermark: str | None = None) -> DataFrame:
    e = events.withWatermark("ts", watermark) if watermark else events
    return e.groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count(F.lit(1)).alias("n")).select(F.col("s.start").alias("start"), F.col("s.end").alias("end"), "user_id", "n")


def distinct_events(events: DataFrame, watermark: str) -> DataFrame:
    """Repeated event ids within the watermark are dropped."""
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def best_of_windows(terms: DataFrame, k: int) -> DataFrame:
    """win, rank, a, b, dist: the k closest users of each window under EMD, on the tree event type / hour.

    Windows are independent sets, so the window is part of every key: counts by (win, obj, node), shared sums by
    (win, node). Descriptions of one week are small.
    """
    from pyspark.sql import Window

    t = terms.dropna().distinct()
    n = t.groupBy("win", "obj_id").agg(F.count(F.lit(1)).alias("n"))
    c = t.groupBy("win", "obj_id", node_key([F.col("k1")]).alias("node")).agg(F.count(F.lit(1)).alias("c")).withColumn("w", F.lit(2)).unionByName(t.select("win", "obj_id", node_key([F.col("k1"), F.col("k2")]).alias("node"), F.lit(1).cast("long").alias("c"), F.lit(1).alias("w")))
    c = c.join(n, ["win", "obj_id"])
    x = c.select("win", "node", "w", F.col("obj_id").alias("a"), F.col("c").alias("ca"), F.col("n").alias("na"))
    y = c.select("win", "node", F.col("obj_id").alias("b"), F.col("c").alias("cb"), F.col("n").alias("nb"))
    shared = x.join(y, ["win", "node"]).filter("a < b").groupBy("win", "a", "b").agg(F.sum(F.col("w") * F.least(F.col("ca") * F.col("nb"), F.col("cb") * F.col("na"))).alias("s"))
    p = n.select("win", F.col("obj_id").alias("a"), F.col("n").alias("na")).join(n.select("win", F.col("obj_id").alias("b"), F.col("n").alias("nb")), "win").filter("a < b")
    d = p.join(shared, ["win", "a", "b"], "left").withColumn("dist", ratio(6 * F.col("na") * F.col("nb") - 2 * F.coalesce("s", F.lit(0)), 2 * F.col("na") * F.col("nb")))
    w = Window.partitionBy("win").orderBy("dist", "a", "b")
    return d.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).select("win", "rank", "a", "b", "dist")


def stream_topk_windows(spark: SparkSession, sf_dir: str, k: int = 3) -> DataFrame:
    """The events table read as a stream, file by file; terms are kept as they arrive and each window is answered.

    The terms go to a table in the shared folder, which survives lost executors; the answer is that of the batch query.
    """
    base = shared_folder(spark)
    out = f"{base}/stream-{uuid.uuid4()}"
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    # A stream reads a folder, of which only the events are taken.
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    terms = weekly_terms(stream.select("user_id", "event_type", "ts"))
    query = terms.writeStream.format("parquet").option("path", f"{out}/terms").option("checkpointLocation", f"{out}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return best_of_windows(spark.read.parquet(f"{out}/terms"), k)


def windows_topk_sql(k: int = 3) -> str:
    return f"""
WITH leaf AS (SELECT DISTINCT epoch_ms(CAST(floor(epoch_ms(ts) / 604800000.0) * 604800000 AS BIGINT)) AS win, user_id AS obj_id, event_type AS k1, hour(ts) AS k2 FROM events),
sz AS (SELECT win, obj_id, count(*) AS n FROM leaf GROUP BY ALL),
c AS (SELECT win, obj_id, {key_sql(1)} AS node, 2 AS w, count(*) AS c FROM leaf GROUP BY ALL UNION ALL SELECT win, obj_id, {key_sql(2)}, 1, count(*) FROM leaf GROUP BY ALL),
cn AS (SELECT c.*, n FROM c JOIN sz USING (win, obj_id)),
s AS (SELECT x.win, x.obj_id AS a, y.obj_id AS b, CAST(sum(x.w * least(x.c * y.n, y.c * x.n)) AS BIGINT) AS s FROM cn x JOIN cn y ON x.win = y.win AND x.node = y.node AND x.obj_id < y.obj_id GROUP BY ALL),
p AS (SELECT x.win, x.obj_id AS a, y.obj_id AS b, x.n AS na, y.n AS nb FROM sz x JOIN sz y ON x.win = y.win AND x.obj_id < y.obj_id),
d AS (SELECT p.win, p.a, p.b, CAST(6 * na * nb - 2 * coalesce(s, 0) AS DOUBLE) / CAST(2 * na * nb AS DOUBLE) AS dist FROM p LEFT JOIN s ON p.win = s.win AND p.a = s.a AND p.b = s.b),
r AS (SELECT *, row_number() OVER (PARTITION BY win ORDER BY dist, a, b) AS rank FROM d)
SELECT win, CAST(rank AS INTEGER) AS rank, a, b, dist FROM r WHERE rank <= {k}"""


class GrowingMinTopK:
    """MIN over a set that grows by batches: a new term only adds pairs, so the lists at the nodes and the best pairs so
    far are the whole state, bounded by the tree and k."""

    def __init__(self, tree: Ontology, k: int) -> None:
        self.tree, self.k = tree, k
        self.lists: DataFrame | None = None

    def add(self, objects: DataFrame) -> None:
        fresh = subtree_minima(objects, self.tree).select("node_id", "obj_id", "dist")
        if self.lists is not None:
            fresh = fresh.unionByName(self.lists).groupBy("node_id", "obj_id").agg(F.min("dist").alias("dist"))
        self.lists = checkpoint(nearest(fresh, self.k + 1).select("node_id", "obj_id", "dist"))

    def answer(self) -> DataFrame:
        pairs = node_pairs(nearest(self.lists, self.k + 1), self.k)
        return ranked(pairs.groupBy("a", "b").agg(ratio(F.min("d"), F.lit(self.tree.scale)).alias("dist")), self.k)

    def run(self, stream: DataFrame, checkpoint_dir: str):
        """A query that adds every micro-batch of (obj_id, term_id)."""
        return stream.writeStream.foreachBatch(lambda batch, _: self.add(batch.dropDuplicates())).option("checkpointLocation", checkpoint_dir).trigger(availableNow=True).start()


__all__ = ["GrowingMinTopK", "best_of_windows", "distinct_events", "mindist_topk", "sessions", "stream_topk_windows", "weekly_terms", "windowed_counts", "windows_topk_sql"]
