"""Edge streams: watermarked, de-duplicated, windowed, and an incremental depth table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.semiring import MIN_PLUS
from ..graph import Graph
from ..operators import kernels as K
from ..runtime import commit, new_path, persist

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def edge_stream(spark: SparkSession, path: str, watermark: str = "1 hour") -> DataFrame:
    """User-key edges of a folder of event files as they arrive: late rows dropped, repeats dropped within the watermark."""
    events = spark.readStream.schema(EVENTS).parquet(path)
    edges = events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), (2 * F.col("user_id")).alias("src"), (2 * F.get_json_object("props", "$.k").cast("bigint") + 1).alias("dst"))
    return edges.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def windowed_degrees(edges: DataFrame, kind: str = "tumbling") -> DataFrame:
    """(window start, end, src, n): edges of each source by tumbling, sliding or session windows."""
    w = {"tumbling": F.window("ts", "1 day"), "sliding": F.window("ts", "2 days", "1 day"), "session": F.session_window("ts", "30 minutes")}[kind]
    return edges.groupBy(w.alias("w"), "src").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("w_start"), F.col("w.end").alias("w_end"), "src", "n")


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over what is there and return its sink's table."""
    spark = stream.sparkSession
    if mode == "append":
        out, mark = new_path(spark, "sink"), new_path(spark, "mark")
        stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", mark).outputMode("append").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)
    root = new_path(spark, "sink")
    last: list[int] = []

    def keep(df: DataFrame, batch: int) -> None:
        """A batch is one folder, written whole, so a batch that runs again replaces itself."""
        df.write.mode("overwrite").parquet(f"{root}/batch={batch}")
        last.append(batch)

    stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", new_path(spark, "mark")).trigger(availableNow=True).start().awaitTermination()
    if not last:
        return spark.createDataFrame([], stream.schema)
    # a complete result is all of its last batch; updates are all batches, each row the state when it was given
    return spark.read.schema(stream.schema).parquet(f"{root}/batch={max(last)}" if mode == "complete" else root)


class DepthState:
    """Depths under edge insertion: new edges relax, and what improves goes on until nothing does."""

    def __init__(self, spark: SparkSession, source: int) -> None:
        self.spark, self.root, self.turn = spark, new_path(spark, "depths"), 0
        self.depths, _ = commit(spark.createDataFrame([(source, 0.0)], "id bigint, val double"), f"{self.root}/d0")
        self.edges: DataFrame | None = None

    def insert(self, batch: DataFrame) -> None:
        fresh = Graph.from_edges(batch.select("src", "dst")).edges
        self.edges = persist(fresh if self.edges is None else self.edges.unionByName(fresh).distinct(), "edges")
        front, nnz, g = None, 1, Graph(self.edges)
        while nnz:
            start = self.depths.join(fresh.select(F.col("src").alias("id")).distinct(), "id", "left_semi") if front is None else front
            y = K.col_mxv(Graph(g.edges.withColumn("val", F.lit(1.0))), start, MIN_PLUS)
            better = y.join(self.depths.withColumnRenamed("val", "old"), "id", "left").filter("old IS NULL OR val < old").select("id", "val")
            self.turn += 1
            front, nnz = commit(better, f"{self.root}/f{self.turn}")
            if nnz:
                self.depths, _ = commit(K.accumulate(self.depths, front, MIN_PLUS), f"{self.root}/d{self.turn}")


def incremental_depths(stream: DataFrame, source: int) -> DataFrame:
    """(id, depth) after the stream's batches, each repairing the depths of those before."""
    state = DepthState(stream.sparkSession, source)
    mark = new_path(stream.sparkSession, "mark")
    stream.writeStream.foreachBatch(lambda df, _: state.insert(df)).option("checkpointLocation", mark).trigger(availableNow=True).start().awaitTermination()
    return state.depths.select("id", F.col("val").cast("int").alias("depth"))


def stateful_degree(edges: DataFrame, idle_ms: int = 3_600_000) -> DataFrame:
    """(src, degree): a running degree of each source as batches arrive; ``edges`` has src, dst and the watermarked ts.

    A state goes once the watermark has passed its last edge by ``idle_ms``: time is the
    data's own, so a stream that has read all its input ends. Update mode: a source is
    given again whenever its degree grows.
    """
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def grow(key, batches, state):
        if state.hasTimedOut:
            state.remove()
            return
        n, latest = state.get if state.exists else (0, 0)
        for b in batches:
            n, latest = n + len(b), max(latest, int(b["ts"].max().timestamp() * 1000))
        state.update((n, latest))
        state.setTimeoutTimestamp(max(latest + idle_ms, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"src": [key[0]], "degree": [n]})

    return edges.groupBy("src").applyInPandasWithState(grow, "src bigint, degree bigint", "degree bigint, latest bigint", "update", GroupStateTimeout.EventTimeTimeout)
