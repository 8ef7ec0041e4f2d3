"""Baselines of the traversal: the same graph and source in, the same depths out."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import Graph
from ..options import BfsOptions
from ..plans.direction import BestOfBoth, EdgeRule, PullOnly, PushOnly
from ..runtime import commit, new_path
from .bfs import BfsResult, bfs


def push_la_gpu(g: Graph, source: int) -> BfsResult:
    """Column products of keys with values, merged by sorting; none of the five switches."""
    return bfs(g, source, PushOnly(), BfsOptions(mask=False, early_exit=False, operand_reuse=False, structure_only=False, merge="sort"))


def la_cpu(g: Graph, source: int) -> BfsResult:
    """Column products in one thread: the edge table in a single partition."""
    one = Graph(g.edges.coalesce(1), g.directed, g.vertex_table)
    one.__dict__["facts"] = g.facts
    return bfs(one, source, PushOnly(), BfsOptions(mask=False, early_exit=False, operand_reuse=False, structure_only=False))


def gas_gpu(g: Graph, source: int) -> BfsResult:
    """Gather, apply, scatter over all edges in every round, until no depth changes."""
    spark, root = g.edges.sparkSession, new_path(g.edges.sparkSession, "gas")
    state, _ = commit(g.vertices().select("id", F.when(F.col("id") == source, 0).cast("int").alias("depth")), f"{root}/0")
    trace, turn = [], 0
    while True:
        began = time.perf_counter()
        gathered = g.pattern().join(state.select(F.col("id").alias("src"), "depth"), "src").groupBy(F.col("dst").alias("id")).agg((F.min("depth") + 1).alias("near"))
        applied = state.join(gathered, "id", "left").select("id", F.least("depth", "near").alias("depth"))
        turn += 1
        after, _ = commit(applied, f"{root}/{turn}")
        changed = after.filter("depth IS NOT NULL").count() - state.filter("depth IS NOT NULL").count()
        trace.append({"iter": turn, "direction": "gather", "nnz_f": changed, "nnz_u": None, "r": None, "out_edges_f": g.nnz, "in_edges_u": None, "parents_checked": None, "ms": (time.perf_counter() - began) * 1000})
        state = after
        if not changed:
            return BfsResult(state.filter("depth IS NOT NULL"), trace)


def vc_cpu(g: Graph, source: int) -> BfsResult:
    """Vertex subsets with push and pull chosen by exact edge counts."""
    return bfs(g, source, EdgeRule(), BfsOptions(operand_reuse=False))


def fc_gpu(g: Graph, source: int, culling: bool = True, dup: bool = False, fused: bool = True, tiny_path: bool = True) -> BfsResult:
    """Frontier-centric: repeats culled map-side before any exchange, or kept; expansion and count in one job; short frontiers sent along."""
    opts = BfsOptions(mask=False, early_exit=False, operand_reuse=False, merge="none" if dup else "hash", mask_placement="pre" if culling else "post", join_strategy="broadcast" if tiny_path and g.M < 1_000_000 else "auto")
    found = bfs(g, source, PushOnly(), opts)
    if not fused:
        found.levels.count()
    return found


def best_of_both(g: Graph, source: int) -> BfsResult:
    return bfs(g, source, BestOfBoth())


def row_unmasked(g: Graph, source: int) -> BfsResult:
    """Row products of all rows on every level, filtered afterwards."""
    return bfs(g, source, PullOnly(), BfsOptions(mask=False, early_exit=False, operand_reuse=False, structure_only=False))


def sql_recursive(edges: DataFrame, source: int, hops: int) -> DataFrame:
    """A reference in recursive SQL for tiny inputs: depth-bounded, duplicates and all."""
    edges.createOrReplaceTempView("sparsehop_edges")
    return edges.sparkSession.sql(
        f"WITH RECURSIVE r(id, depth) AS (SELECT CAST({source} AS BIGINT), 0 UNION ALL SELECT e.dst, r.depth + 1 FROM r JOIN sparsehop_edges e ON e.src = r.id WHERE r.depth < {hops}) SELECT id, min(depth) AS depth FROM r GROUP BY id"
    )


BASELINES = {"push_la_gpu": push_la_gpu, "la_cpu": la_cpu, "gas_gpu": gas_gpu, "vc_cpu": vc_cpu, "fc_gpu": fc_gpu}
