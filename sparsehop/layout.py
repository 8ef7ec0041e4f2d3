"""Physical layouts: column store by source blocks, row store by vertex in growing segments, grid of edge blocks."""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation, Window
from pyspark.sql import functions as F

from .graph import Graph
from .runtime import new_path, persist

#: The first segment's neighbours, and how much each next segment grows.
FIRST_SEGMENT, GROWTH, LONGEST = 16, 16, 4096


def placed(edges: DataFrame, key: str = "dst", by: str = "src", name: str = "at") -> DataFrame:
    """Edges with their place, from 0, among those of the same ``key`` in the order of ``by``; no task holds a hub.

    Edges are dealt by ranges of (key, by) and numbered inside a range. A key that
    goes on in the next range begins there at the number of its edges before; as a
    range's end cuts one key at most, the table of such keys is never longer than
    twice the number of ranges and is sent to all.
    """
    ranged = persist(edges.repartitionByRange(key, by).withColumn("range", F.spark_partition_id()), "ranged")
    inside = F.row_number().over(Window.partitionBy("range", key).orderBy(by)) - 1
    counts = ranged.groupBy("range", key).agg(F.count(F.lit(1)).alias("n"))
    ends = ranged.groupBy("range").agg(F.min(key).alias("low"), F.max(key).alias("high"))
    edge = ends.select("range", F.explode(F.array_distinct(F.array("low", "high"))).alias(key))
    order = Window.partitionBy(key).orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    before = counts.join(F.broadcast(edge), ["range", key]).select("range", key, F.coalesce(F.sum("n").over(order), F.lit(0)).alias("before")).filter("before > 0")
    whole = ranged.withColumn("inside", inside).join(F.broadcast(before), ["range", key], "left")
    return whole.withColumn(name, (F.col("inside") + F.coalesce("before", F.lit(0))).cast("int")).drop("range", "inside", "before")


def segment(g: Graph, first: int = FIRST_SEGMENT, growth: int = GROWTH, longest: int = LONGEST) -> DataFrame:
    """(vertex, seg, nbrs): in-neighbours in ascending order, cut so that no row holds more than ``longest``.

    Segment 0 has the first few; a hub's later segments are rows of their own, so
    no task ever holds a hub's whole list in one array.
    """
    numbered = placed(g.pattern())
    number, low, size = F.lit(None).cast("int"), 0, first
    cuts = []
    while size < longest:
        cuts.append((low, low + size))
        low, size = low + size, size * growth
    number = (F.lit(len(cuts)) + F.floor((F.col("at") - low) / longest)).cast("int")
    for k, (a, b) in reversed([*enumerate(cuts)]):
        number = F.when(F.col("at") < b, F.lit(k)).otherwise(number)
    return numbered.groupBy(F.col("dst").alias("vertex"), number.alias("seg")).agg(F.array_sort(F.collect_list("src")).alias("nbrs"))


def stored_rows(g: Graph) -> tuple[DataFrame, bool]:
    """The written row table of a graph's searches, and whether a hub is several rows of it."""
    seen = Observation()
    rows = segment(g, LONGEST, 1)
    table = persist(rows.observe(seen, F.max("seg").alias("last")), "rows")
    return table, bool(seen.get["last"])


def write_edge_store(g: Graph, path: str | None = None, block_bits: int = 12) -> str:
    """Both orientations, partitioned by blocks of vertices and sorted inside: literal block filters prune files."""
    path = path or new_path(g.edges.sparkSession, "edges")
    by_src = g.edges.withColumn("src_block", F.shiftright("src", block_bits))
    by_src.repartition("src_block").sortWithinPartitions("src", "dst").write.mode("overwrite").partitionBy("src_block").parquet(f"{path}/by_src")
    rows = segment(g).withColumn("block", F.shiftright("vertex", block_bits))
    rows.repartition("block").sortWithinPartitions("seg", "vertex").write.mode("overwrite").partitionBy("block").parquet(f"{path}/by_dst")
    return path


class EdgeStore:
    def __init__(self, spark, path: str, block_bits: int = 12) -> None:
        self.spark, self.path, self.bits = spark, path, block_bits

    def edges(self, frontier: DataFrame | None = None, most_blocks: int = 1000) -> DataFrame:
        """Edges, or those of a frontier's blocks: the block list is a literal partition filter while it is short."""
        table = self.spark.read.parquet(f"{self.path}/by_src")
        if frontier is not None:
            blocks = [r.b for r in frontier.select(F.shiftright("id", self.bits).alias("b")).distinct().limit(most_blocks + 1).collect()]
            if len(blocks) <= most_blocks:
                table = table.filter(F.col("src_block").isin(blocks))
        return table

    def rows(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/by_dst")

    def graph(self) -> Graph:
        e = self.edges()
        return Graph(e.drop("src_block"))


def open_edge_store(spark, path: str, block_bits: int = 12) -> EdgeStore:
    return EdgeStore(spark, path, block_bits)


def bucket_edges(g: Graph, table: str | None = None, buckets: int | None = None) -> DataFrame:
    """A table bucketed and sorted by source, in the shared folder: joins on the source exchange the vector, never the edges."""
    spark = g.edges.sparkSession
    path = new_path(spark, "bucketed")
    table, buckets = table or "sparsehop_" + path.rsplit("-", 1)[1], buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
    g.edges.repartition(buckets, "src").write.mode("overwrite").option("path", path).bucketBy(buckets, "src").sortBy("src").saveAsTable(table)
    return spark.table(table)


def bucketed(g: Graph) -> Graph:
    """The graph on a bucketed table of its edges, written once for all the levels and rounds to come."""
    return Graph(bucket_edges(g), g.directed, g.vertex_table)


def grid(g: Graph, bits: int = 10) -> DataFrame:
    """Edges with (src_block, dst_block): each cell needs one slice of the vector on either side."""
    return g.edges.withColumns({"src_block": F.shiftright("src", bits), "dst_block": F.shiftright("dst", bits)})
