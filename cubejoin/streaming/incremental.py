"""Pattern counts that follow a stream of edges, and windowed views of events."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.frontier import frontier_join
from ..plans.planner import quick_plan
from ..query import Atom, ConjunctiveQuery


def delta_count(spark: SparkSession, query: ConjunctiveQuery, old: DataFrame, new: DataFrame) -> int:
    """Results that new edges add: for each atom, new rows there, old and new before it, old after it.

    ``new`` must be disjoint from ``old``; every atom reads the one edge relation.
    """
    both = old.unionAll(new)
    total = 0
    for j in range(len(query.atoms)):
        atoms, relations = [], {}
        for k, a in enumerate(query.atoms):
            relations[f"e{k}"] = both if k < j else new if k == j else old
            atoms.append(Atom(f"e{k}", a.vars))
        part = ConjunctiveQuery(query.head, tuple(atoms))
        total += frontier_join(spark, part, relations, quick_plan(part, lift="none"), mode="count", distinct_inputs=True).first().n
    return total


class IncrementalCount:
    """foreachBatch state, all of it on disk: an edge store and the counts (Parquet, one folder per batch).

    Batches are idempotent: a replayed batch id rewrites its own folders.  A new
    object over the same path goes on where the last one stopped, whatever was
    restarted in between.
    """

    def __init__(self, spark: SparkSession, query: ConjunctiveQuery, path: str):
        self.spark, self.query, self.path = spark, query, path

    def _stored(self, what: str, schema: str) -> DataFrame:
        sc = self.spark.sparkContext
        at = sc._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{what}")
        if not at.getFileSystem(sc._jsc.hadoopConfiguration()).exists(at):
            return self.spark.createDataFrame([], schema)
        return self.spark.read.schema(schema).parquet(f"{self.path}/{what}")

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        old = self._stored("edges", "src long, dst long, batch long").where(F.col("batch") < batch_id).select("src", "dst")
        new = batch.select("src", "dst").where("src is not null and dst is not null").distinct().join(old, ["src", "dst"], "left_anti")
        target = f"{self.path}/edges/batch={batch_id}"
        new.write.mode("overwrite").parquet(target)
        new = self.spark.read.schema("src long, dst long").parquet(target)
        n = delta_count(self.spark, self.query, old, new)
        self.spark.createDataFrame([(n,)], "n long").coalesce(1).write.mode("overwrite").parquet(f"{self.path}/counts/batch={batch_id}")

    @property
    def counts(self) -> dict[int, int]:
        """Results that each batch added."""
        return {r.batch: r.n for r in self._stored("counts", "n long, batch long").collect()}

    @property
    def total(self) -> int:
        return self._stored("counts", "n long, batch long").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).first().n


def incremental_counts(stream: DataFrame, query: ConjunctiveQuery, path: str):
    """Starts a streaming query over (src, dst); returns (streaming query, state)."""
    state = IncrementalCount(stream.sparkSession, query, path)
    started = stream.writeStream.foreachBatch(state).option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start()
    return started, state


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))  # watermarks need an instant


def windowed_edges(events: DataFrame, kind: str = "tumbling", length: str = "1 day", slide: str | None = None, gap: str = "30 minutes", late: str | None = "10 minutes") -> DataFrame:
    """Events and distinct users per time window: tumbling, sliding or session (per user).

    Distinct users are exact in batch; a stream counts them with a sketch, as
    Spark has no exact distinct over streams; ``late=None`` keeps a watermark set before.
    """
    stamped = events.withWatermark("ts", late) if events.isStreaming and late else events
    if kind == "session":
        grouped = stamped.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
        return grouped.select(F.col("w.start").alias("lo"), F.col("w.end").alias("hi"), "user_id", "n")
    window = F.window("ts", length, slide) if kind == "sliding" else F.window("ts", length)
    users = F.approx_count_distinct("user_id") if events.isStreaming else F.countDistinct("user_id")
    grouped = stamped.groupBy(window.alias("w")).agg(F.count("*").alias("n"), users.alias("users"))
    return grouped.select(F.col("w.start").alias("lo"), F.col("w.end").alias("hi"), "n", "users")


def deduplicated(events: DataFrame, keys: list[str], late: str = "10 minutes") -> DataFrame:
    """Repeats within the watermark dropped."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def windowed_triangles(events_edges: DataFrame, length: str = "1 day") -> DataFrame:
    """(lo, n): directed triangles among the edges (src, dst, ts) of each tumbling window.

    The window is one more variable that all three atoms share, so it is an
    ordinary partitioned join and no window's edges meet in one task.
    """
    spark = events_edges.sparkSession
    stamped = events_edges.select(F.unix_micros(F.window("ts", length)["start"].cast("timestamp")).alias("w"), "src", "dst").distinct()
    query = ConjunctiveQuery(("w", "x", "y", "z"), (Atom("e", ("w", "x", "y")), Atom("e", ("w", "y", "z")), Atom("e", ("w", "x", "z"))))
    from ..operators.executor import cube_join

    rows = cube_join(spark, query, {"e": stamped}, quick_plan(query))
    kind = events_edges.schema["ts"].dataType
    return rows.groupBy(F.timestamp_micros("w").cast(kind).alias("lo")).agg(F.count("*").alias("n"))


def degree_state(stream: DataFrame) -> DataFrame:
    """(v, degree) updates of a stream of edges, kept as state per vertex."""
    from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

    class Degree(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.held = handle.getValueState("degree", "n long")

        def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
            n = (self.held.get()[0] if self.held.exists() else 0) + sum(len(r) for r in rows)
            self.held.update((n,))
            yield pd.DataFrame({"v": [key[0]], "degree": [n]})

        def close(self) -> None:
            pass

    ends = stream.select(F.explode(F.array("src", "dst")).alias("v"))
    return ends.groupBy("v").transformWithStateInPandas(Degree(), "v long, degree long", "Update", "None")
