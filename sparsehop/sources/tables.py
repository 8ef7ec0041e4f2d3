"""Typed scans of the given tables, and graphs built from them. Bipartite graphs use 2k and 2k + 1."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.vector import dense_ids
from ..graph import Graph, edges_from_cooccurrence, edges_from_pairs, edges_from_succession
from ..runtime import persist


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def even(c):
    return 2 * F.col(c)


def odd(c):
    return 2 * F.col(c) + 1


def ordpart(spark, sf_dir, weighted: bool = False) -> Graph:
    li = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", *(["l_quantity"] if weighted else []))
    pairs = edges_from_pairs(li, even("l_orderkey"), odd("l_partkey"), F.col("l_quantity").cast("bigint").cast("double") if weighted else None)
    return Graph.from_edges(pairs, weight="val" if weighted else None)


def custpart(spark, sf_dir) -> Graph:
    both = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey").join(load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey"), F.col("o_orderkey") == F.col("l_orderkey"))
    return Graph.from_edges(edges_from_pairs(both, even("o_custkey"), odd("l_partkey")))


def partsupp(spark, sf_dir) -> Graph:
    return Graph.from_edges(edges_from_pairs(load(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey"), even("l_partkey"), odd("l_suppkey")))


def copurchase(spark, sf_dir) -> Graph:
    return Graph.from_edges(edges_from_cooccurrence(load(spark, sf_dir, "lineitem"), "l_orderkey", "l_partkey"))


def custorder(spark, sf_dir) -> Graph:
    return Graph.from_edges(edges_from_pairs(load(spark, sf_dir, "orders"), even("o_custkey"), odd("o_orderkey")))


def geo(spark, sf_dir) -> Graph:
    """Regions, nations, customers and suppliers as a forest; ids are kind * 10**9 + key."""
    b = 10**9
    n, c, s = load(spark, sf_dir, "nation"), load(spark, sf_dir, "customer"), load(spark, sf_dir, "supplier")
    pairs = edges_from_pairs(n, F.col("n_regionkey").cast("bigint"), F.lit(b) + F.col("n_nationkey"))
    pairs = pairs.unionByName(edges_from_pairs(c, F.lit(b) + F.col("c_nationkey"), F.lit(2 * b) + F.col("c_custkey")))
    pairs = pairs.unionByName(edges_from_pairs(s, F.lit(b) + F.col("s_nationkey"), F.lit(3 * b) + F.col("s_suppkey")))
    return Graph.from_edges(pairs)


def token_pairs(df: DataFrame, id_: str, text: str) -> DataFrame:
    """(doc, token): distinct lower-case ASCII words of three letters or more."""
    return df.select(F.col(id_).alias("doc"), F.explode(F.regexp_extract_all(F.lower(F.coalesce(F.col(text), F.lit(""))), F.lit("([a-z]{3,})"), F.lit(1))).alias("token")).distinct()


def edges_from_tokens(df: DataFrame, id_: str, text: str, ids: str = "rank") -> DataFrame:
    """Document-token edges; tokens are numbered in bytewise order after the largest document id, or hashed to 62 bits."""
    pairs = token_pairs(df, id_, text)
    if ids == "hash":
        return pairs.select(F.col("doc").alias("src"), (F.pmod(F.xxhash64("token"), F.lit(2**62)) + F.lit(2**62)).alias("dst"))
    pairs = persist(pairs, "tokens")
    base = F.broadcast(df.agg((F.max(id_) + 1).cast("bigint").alias("base")))
    number = dense_ids(pairs, "token")
    return pairs.join(number, "token").join(base).select(F.col("doc").cast("bigint").alias("src"), (F.col("base") + F.col("id")).alias("dst"))


def word(spark, sf_dir) -> Graph:
    return Graph.from_edges(edges_from_tokens(load(spark, sf_dir, "documents", "doc_id", "text"), "doc_id", "text"))


def userkey(spark, sf_dir) -> Graph:
    e = load(spark, sf_dir, "events", "user_id", "props").withColumn("k", F.get_json_object("props", "$.k").cast("bigint"))
    return Graph.from_edges(edges_from_pairs(e, even("user_id"), odd("k")))


def usersucc(spark, sf_dir) -> Graph:
    """Users of consecutive events over all time, directed. The order of all events is one sequence: ranges, then their joints."""
    e = persist(load(spark, sf_dir, "events", "event_id", "ts", "user_id").repartitionByRange(16, "ts", "event_id").withColumn("part", F.spark_partition_id()), "events")
    w = Window.partitionBy("part").orderBy("ts", "event_id")
    inner = e.select(F.col("user_id").alias("src"), F.lead("user_id").over(w).alias("dst"))
    ends = e.groupBy("part").agg(F.max_by("user_id", F.struct("ts", "event_id")).alias("src"), F.min_by("user_id", F.struct("ts", "event_id")).alias("first"))
    joint = ends.select("src", F.lead("first").over(Window.partitionBy(F.lit(0)).orderBy("part")).alias("dst"))  # one row a range
    return Graph.from_edges(inner.unionByName(joint).select(F.col("src").cast("bigint").alias("src"), F.col("dst").cast("bigint").alias("dst")), directed=True)


def chain(spark, sf_dir) -> Graph:
    return Graph.from_edges(edges_from_succession(load(spark, sf_dir, "events"), "user_id", ["ts", "event_id"], "event_id"))


def ladder(spark, sf_dir) -> Graph:
    """Each user's event chain, with a rung every tenth event to the next user's event of the same rank."""
    e = load(spark, sf_dir, "events", "event_id", "ts", "user_id").withColumn("n", F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")))
    rungs = e.filter("n % 10 = 0").alias("a").join(e.alias("b"), (F.col("b.user_id") == F.col("a.user_id") + 1) & (F.col("a.n") == F.col("b.n"))).select(F.col("a.event_id").alias("src"), F.col("b.event_id").alias("dst"))
    return Graph.from_edges(edges_from_succession(e, "user_id", ["ts", "event_id"], "event_id").unionByName(rungs))


#: Vectors of a block of the nearest-neighbour join, queries that meet one at once, and the weight of a pair that has none.
BLOCK_VECTORS, BLOCK_QUERIES, NO_WEIGHT = 8192, 256, 2**48


def knn_pairs(df: DataFrame, k: int, blocks: int | None = None) -> DataFrame:
    """(src, dst, weight): exact top-k by cosine of unit vectors, ties by id; weight is round(1e6 * (1 - cos)).

    Vectors meet in pairs of blocks (all queries against all rows, block by block);
    each block keeps its k best before the final choice. A missing vector has no
    weight to any other (null, after all weights), a missing component counts as zero.
    """
    if blocks is None:
        n = df.count()
        blocks = max(1, min(8, -(-n // BLOCK_QUERIES)), -(-n // BLOCK_VECTORS))
    v = df.filter("vec_id IS NOT NULL").select(F.col("vec_id").cast("bigint").alias("id"), F.col("embedding").alias("e")).withColumn("b", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    queries = v.select("id", "e", F.lit(True).alias("query"), F.col("b").alias("p"), every.alias("c"))
    rows = v.select("id", "e", F.lit(False).alias("query"), every.alias("p"), F.col("b").alias("c"))
    near = queries.unionByName(rows).groupBy("p", "c").applyInArrow(_nearest(k), "src bigint, dst bigint, weight bigint")
    best = near.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy("weight", "dst"))).filter(F.col("r") <= k)
    return best.select("src", "dst", F.when(F.col("weight") < NO_WEIGHT, F.col("weight")).alias("weight"))


def _nearest(k: int):
    """The k best rows of each query of a cell; nested whole, so that workers take it by value and need not have the package."""
    block, none = BLOCK_QUERIES, NO_WEIGHT

    def matrix(e: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(vectors, which are there) of a list column; shorter ones and missing components are filled with zeros."""
        size = int(pc.max(pc.list_value_length(e)).as_py() or 0) if len(e) else 0
        out, there = np.zeros((len(e), size)), np.zeros(len(e), bool)
        for i, row in enumerate(e):
            if row.is_valid:
                one = row.values.fill_null(0).to_numpy(zero_copy_only=False)
                out[i, : len(one)], there[i] = one, len(one) > 0
        return out, there

    def run(cell: pa.Table) -> pa.Table:
        order = pc.sort_indices(cell, sort_keys=[("query", "ascending"), ("id", "ascending")])
        cell = cell.take(order)
        ids, query = cell.column("id").to_numpy(), cell.column("query").to_numpy(zero_copy_only=False)
        e, there = matrix(cell.column("e").combine_chunks())
        x, y, mine, theirs = e[query], e[~query], ids[query], ids[~query]
        if not np.isfinite(e).all():
            raise ValueError("a vector has a component that is no number")
        has_x, has_y, n, found = there[query], there[~query], len(theirs), []
        length = max(1.0, float((e * e).sum(1).max(initial=0.0)))
        if 4e6 * length > none:
            raise ValueError("vectors are much longer than one")
        for at in range(0, len(x) if n else 0, block):
            part = slice(at, at + block)
            raw = 1e6 * (1 - x[part] @ y.T)
            low = np.floor(raw)
            # a product of matrices sums in another order: near a half, sum again as one by one
            i, j = np.nonzero(np.abs(raw - low - 0.5) < 1e-4 * length)
            total = np.zeros(len(i))
            for d in range(e.shape[1]):
                total += x[at + i, d] * y[j, d]
            again = 1e6 * (1 - total)
            weight = np.where(raw - low >= 0.5, low + 1, low)
            weight[i, j] = np.copysign(np.floor(np.abs(again) + 0.5), again)
            weight[~has_x[part]], weight[:, ~has_y] = none, none
            key = weight.astype(np.int64) * n + np.arange(n)  # rows stand by id, so keys order by weight, then id
            key[mine[part, None] == theirs] = np.iinfo(np.int64).max
            top = np.sort(np.partition(key, k - 1, axis=1)[:, :k] if k < n else key, axis=1)
            r, c = np.nonzero(top < np.iinfo(np.int64).max)
            best = top[r, c]
            found.append(pa.table({"src": mine[at + r], "dst": theirs[best % n], "weight": best // n}))
        empty = pa.table({c: pa.array([], pa.int64()) for c in ("src", "dst", "weight")})
        return pa.concat_tables([empty, *found])

    return run


def knn(spark, sf_dir, k: int = 5) -> Graph:
    return Graph.from_edges(persist(knn_pairs(load(spark, sf_dir, "embeddings"), k), "knn"), weight="weight")


def links(df: DataFrame) -> DataFrame:
    return df.select("page_id", F.explode(F.regexp_extract_all(F.coalesce("html", F.lit("")), F.lit('href="([^"]*)"'), F.lit(1))).alias("href")).distinct()


def pages(spark, sf_dir) -> Graph:
    found = persist(links(load(spark, sf_dir, "pages", "page_id", "html")), "links")
    base = F.broadcast(load(spark, sf_dir, "pages", "page_id").agg((F.max("page_id") + 1).alias("base")))
    return Graph.from_edges(found.join(dense_ids(found, "href"), "href").join(base).select(F.col("page_id").alias("src"), (F.col("base") + F.col("id")).alias("dst")))


def conv(spark, sf_dir) -> Graph:
    t = load(spark, sf_dir, "conversations", "conv_id", "turn").withColumn("id", F.col("conv_id") * 1000 + F.col("turn"))
    return Graph.from_edges(edges_from_succession(t, "conv_id", ["turn"], "id"))


#: Edges of the worked example, A to H as 0 to 7 (our own drawing of its stated facts).
TOY = [(0, 1), (0, 2), (0, 3), (1, 4), (2, 4), (2, 5), (3, 5), (4, 6), (5, 6), (6, 7)]


def toy(spark, sf_dir=None) -> Graph:
    return Graph.from_edges(spark.createDataFrame(TOY, "src bigint, dst bigint"))


def edges_from_interval(df: DataFrame, part: str, id_: str, ts: str, seconds: int) -> DataFrame:
    """(src, dst): events of one part at most ``seconds`` apart, the earlier first: a bucketed range join."""
    at = F.col(ts).cast("timestamp")
    one = df.select(part, F.col(id_).alias("id"), at.alias("t"), F.floor(F.unix_micros(at) / (seconds * 1_000_000)).alias("bucket"))
    left = one.select(part, F.col("id").alias("src"), F.col("t").alias("t1"), F.explode(F.array("bucket", F.col("bucket") + 1)).alias("bucket"))
    right = one.select(part, F.col("id").alias("dst"), F.col("t").alias("t2"), "bucket")
    gap = F.unix_micros("t2") - F.unix_micros("t1")
    return left.join(right, [part, "bucket"]).filter((gap >= 0) & (gap <= seconds * 1_000_000) & ((gap > 0) | (F.col("src") < F.col("dst")))).select("src", "dst")


def asof_join(left: DataFrame, right: DataFrame, by: str, ts: str, value: str) -> DataFrame:
    """``left`` with ``match``: the latest ``value`` of ``right`` at or before each row, by one window over the union."""
    a = left.withColumns({"_side": F.lit(1), "_value": F.lit(None).cast(right.schema[value].dataType)})
    b = right.select(by, ts, F.lit(0).alias("_side"), F.col(value).alias("_value"))
    w = Window.partitionBy(by).orderBy(ts, "_side", "_value").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return a.unionByName(b, allowMissingColumns=True).withColumn("match", F.last("_value", ignorenulls=True).over(w)).filter("_side = 1").drop("_side", "_value")


GRAPHS = {
    "g_ordpart": ordpart, "g_custpart": custpart, "g_partsupp": partsupp, "g_copurchase": copurchase, "g_word": word, "g_geo": geo, "g_custorder": custorder,
    "g_userkey": userkey, "g_chain": chain, "g_ladder": ladder, "g_knn": knn, "g_pages": pages, "g_conv": conv, "g_toy": toy,
}
