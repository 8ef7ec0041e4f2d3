"""Matrix-matrix products, masked or not, and what rests on them."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vector as V
from ..functions.semiring import PLUS_TIMES, Semiring
from ..graph import Graph
from ..runtime import persist


def mxm(a: DataFrame, b: DataFrame, sr: Semiring = PLUS_TIMES, mask: DataFrame | None = None, complement: bool = False) -> DataFrame:
    """(i, j, val) of A B for A, B as (i, j, val); a mask is a set of (i, j).

    A mask is taken first: its entries meet rows of A, and only partners in B of
    the wanted column are ever formed. The complement must form products and drop.
    """
    left, right = a.select("i", F.col("j").alias("k"), F.col("val").alias("x")), b.select(F.col("i").alias("k"), "j", F.col("val").alias("y"))
    value = sr.mul(F.col("x"), F.col("y")).cast(sr.kind)
    if mask is not None and not complement:
        wanted = mask.select("i", "j").distinct().join(left, "i")
        return wanted.join(right, ["k", "j"]).groupBy("i", "j").agg(sr.agg(value).alias("val"))
    out = left.join(right, "k").groupBy("i", "j").agg(sr.agg(value).alias("val"))
    if mask is None:
        return out
    on = mask.select("i", "j").distinct().withColumn("on", F.lit(True))
    return out.join(on, ["i", "j"], "left").filter("on IS NULL").select("i", "j", "val")


def oriented(g: Graph) -> DataFrame:
    """(a, b): each undirected edge once, from the end of the smaller (degree, id): out-lists stay short at hubs."""
    deg = g.out_degrees()
    ends = g.pattern().filter("src < dst").join(deg.select(F.col("id").alias("src"), F.col("degree").alias("ds")), "src").join(deg.select(F.col("id").alias("dst"), F.col("degree").alias("dd")), "dst")
    low = (F.col("ds") < F.col("dd")) | ((F.col("ds") == F.col("dd")) & (F.col("src") < F.col("dst")))
    return ends.select(F.when(low, F.col("src")).otherwise(F.col("dst")).alias("a"), F.when(low, F.col("dst")).otherwise(F.col("src")).alias("b"))


def triangles(g: Graph) -> DataFrame:
    """(a, b, c) with a < b < c of every triangle: stored edges as mask, the ends' out-lists intersected."""
    e = oriented(g)
    lists = e.groupBy("a").agg(F.collect_list("b").alias("out"))
    both = e.join(lists, "a").join(lists.select(F.col("a").alias("b"), F.col("out").alias("out_b")), "b")
    found = both.select("a", "b", F.explode(F.array_intersect("out", "out_b")).alias("c"))
    return found.select(F.array_sort(F.array("a", "b", "c")).alias("t")).select(F.col("t")[0].alias("a"), F.col("t")[1].alias("b"), F.col("t")[2].alias("c"))


def triangle_count(g: Graph) -> DataFrame:
    e = oriented(g)
    lists = e.groupBy("a").agg(F.collect_list("b").alias("out"))
    both = e.join(lists, "a").join(lists.select(F.col("a").alias("b"), F.col("out").alias("out_b")), "b")
    return both.agg(F.coalesce(F.sum(F.size(F.array_intersect("out", "out_b"))), F.lit(0)).cast("bigint").alias("triangles"))


def triangle_count_unmasked(g: Graph) -> DataFrame:
    """The same by wedges first: the unmasked product, then the filter. The baseline of the masked form."""
    return wedge_blocks(persist(oriented(g), "oriented")).agg(F.coalesce(F.sum("closed"), F.lit(0)).cast("bigint").alias("triangles"))


#: Wedges of one block of rows: what a worker meets in one group, and the most list entries that it holds.
BLOCK_WEDGES = 8_000_000


def wedge_blocks(e: DataFrame, most: int = BLOCK_WEDGES) -> DataFrame:
    """(wedges, outputs, closed) of blocks of rows of the unmasked product of an oriented edge table (a, b) with itself.

    Rows are cut into blocks of about ``most`` wedges. A block takes each list that any of
    its rows meets once, forms every wedge a, x, y in memory, row by row, and counts
    wedges, different (a, y), and wedges whose ends are an edge. So lists travel and
    wedges do not.
    """
    lists = persist(e.groupBy("a").agg(F.collect_list("b").alias("out")), "lists")
    sizes = lists.select(F.col("a").alias("b"), F.size("out").cast("bigint").alias("n"))
    work = e.join(sizes, "b").groupBy("a").agg(F.sum("n").alias("work"))
    blocks = persist(V.prefix_sum(work, "a", "work").select("a", F.floor(F.col("before") / most).cast("bigint").alias("block")), "blocks")
    own = lists.join(blocks, "a").select("block", F.lit(True).alias("own"), F.col("a").alias("key"), "out")
    asked = own.select("block", F.explode("out").alias("key")).distinct()
    met = asked.join(lists.withColumnRenamed("a", "key"), "key").select("block", F.lit(False).alias("own"), "key", "out")
    return own.unionByName(met).groupBy("block").applyInArrow(_wedge_counter(), "wedges bigint, outputs bigint, closed bigint")


def _wedge_counter():
    """Nested, so that workers take it by value and need not have the package."""

    def count(block: pa.Table) -> pa.Table:
        out = block.column("out").combine_chunks()
        ends, values = np.asarray(out.offsets, np.int64), np.asarray(out.values, np.int64)
        own, keys = block.column("own").to_numpy(), block.column("key").to_numpy()
        names, local = np.unique(values, return_inverse=True)
        met = {int(keys[i]): local[ends[i] : ends[i + 1]] for i in np.flatnonzero(~own)}
        reached, wanted = np.zeros(len(names), bool), np.zeros(len(names), bool)
        wedges = outputs = closed = 0
        for i in np.flatnonzero(own):
            mine = slice(ends[i], ends[i + 1])
            found = [met[x] for x in values[mine].tolist() if x in met]
            if not found:
                continue
            y = np.concatenate(found)
            reached[y], wanted[local[mine]] = True, True
            wedges, outputs, closed = wedges + len(y), outputs + int(np.count_nonzero(reached)), closed + int(np.count_nonzero(wanted[y]))
            reached[y], wanted[local[mine]] = False, False
        return pa.table({"wedges": pa.array([wedges], pa.int64()), "outputs": pa.array([outputs], pa.int64()), "closed": pa.array([closed], pa.int64())})

    return count


def sparse_layer(x: DataFrame, w: DataFrame, bias: float = 0.0, mask: DataFrame | None = None) -> DataFrame:
    """One layer: rectified x W + bias at the stored outputs, or at the outputs that a mask wants."""
    out = mxm(x, w, PLUS_TIMES, mask)
    return out.select("i", "j", F.greatest(F.col("val") + bias, F.lit(0.0)).alias("val")).filter("val > 0")


def sparse_layers(x: DataFrame, weights: list[DataFrame], bias: float = 0.0, mask: DataFrame | None = None) -> DataFrame:
    for k, w in enumerate(weights):
        x = sparse_layer(x, w, bias, mask if k == len(weights) - 1 else None)
    return x


def conv_masked(x: DataFrame, kernel: list[float], mask: DataFrame) -> DataFrame:
    """(part, pos, val): a centred one-dimensional convolution at the wanted positions alone, as a banded masked product.

    ``x`` is (part, pos, val); positions that are absent count as zero.
    """
    half = len(kernel) // 2
    taps = F.explode(F.array(*[F.struct(F.lit(k - half).alias("shift"), F.lit(float(c)).alias("c")) for k, c in enumerate(kernel)])).alias("tap")
    wanted = mask.select("part", "pos").distinct().select("part", "pos", taps).select("part", "pos", (F.col("pos") + F.col("tap.shift")).alias("at"), "tap.c")
    return wanted.join(x.select("part", F.col("pos").alias("at"), "val"), ["part", "at"]).groupBy("part", "pos").agg(F.sum(F.col("c") * F.col("val")).alias("val"))


def conv_window(x: DataFrame, kernel: list[float]) -> DataFrame:
    """The same by windows over every position: a cross-check."""
    order = Window.partitionBy("part").orderBy("pos")
    half = len(kernel) // 2
    terms = [F.lit(float(c)) * F.coalesce(F.lead("val", k - half).over(order) if k >= half else F.lag("val", half - k).over(order), F.lit(0.0)) for k, c in enumerate(kernel)]
    total = terms[0]
    for t in terms[1:]:
        total = total + t
    return x.select("part", "pos", total.alias("val"))
