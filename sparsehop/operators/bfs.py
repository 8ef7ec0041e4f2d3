"""Breadth-first search: one masked product a level, in the direction that a rule picks."""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.semiring import MIN_FIRST, OR_AND
from ..graph import Graph
from ..options import BfsOptions, MatvecOptions
from ..plans.direction import PULL, PushOnly, RatioRule
from ..plans.direction import Level as Seen
from ..runtime import commit, new_path, persist
from . import kernels as K


@dataclass
class BfsResult:
    levels: DataFrame
    trace: list[dict] = field(default_factory=list)

    def trace_table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.trace, "iter int, direction string, nnz_f long, nnz_u long, r double, out_edges_f long, in_edges_u long, parents_checked long, ms double")


def labels(result: BfsResult, g: Graph) -> DataFrame:
    """The other convention: the source has label 1, unreached vertices 0."""
    return g.vertices().join(result.levels, "id", "left").select("id", F.coalesce(F.col("depth") + 1, F.lit(0)).alias("label"))


def _matvec(opts: BfsOptions) -> MatvecOptions:
    return MatvecOptions(merge=opts.merge, mask_placement=opts.mask_placement, structure_only=opts.structure_only and not opts.with_parent, join_strategy=opts.join_strategy, broadcast_bytes=opts.broadcast_bytes)


#: Vertices that a push may send to every executor. Levels are tables whose files say little of their rows:
#: sorted, repeated ids take a few bits each, and a join that goes by files would send tens of millions.
SENT_ROWS = 1_000_000


def _push(g: Graph, front: DataFrame, visited: DataFrame, opts: BfsOptions, nnz: int = 0, reached: int = 0) -> DataFrame:
    """Unvisited vertices with a parent in the frontier; ``nnz`` and ``reached`` are the vertices of the frontier and of the visited set."""
    mv = _matvec(opts)
    if opts.join_strategy == "auto" and nnz > SENT_ROWS:
        mv = replace(mv, join_strategy="merge")
    if reached > SENT_ROWS:
        mv = replace(mv, mask_strategy="merge")
    done = visited.select("id")
    if opts.merge == "none":
        # repeats stay in what a level finds; sent on by each repeat, they would grow with the number of paths
        front, done = front.distinct(), done.distinct()
    if opts.with_parent:
        x = front.select("id", F.col("id").alias("val"))
        mv = replace(mv, merge="hash" if opts.merge == "none" else opts.merge, structure_only=None)
        return K.col_masked_mxv(g, x, done, MIN_FIRST, True, mv).select("id", F.col("val").alias("parent"))
    x = front.select("id", F.lit(True).alias("val"))
    if not opts.structure_only:
        mv = replace(mv, structure_only=False)
    return K.col_masked_mxv(g, x, done, OR_AND, True, mv).select("id")


def _pull(g: Graph, rows: DataFrame, front: DataFrame, visited: DataFrame, opts: BfsOptions, segments: tuple[DataFrame, int] | None) -> DataFrame:
    """Unvisited rows with a parent in the frontier; with operand reuse, in the visited set, which gives the same rows."""
    operand = visited if opts.operand_reuse else front
    mv = _matvec(opts)
    if not opts.mask:
        found = K.V.to_sparse(K.row_mxv(g, operand.select("id", F.lit(True).alias("val")), OR_AND, mv), OR_AND)
        return found.join(visited.select("id"), "id", "left_anti").select("id")
    if not opts.early_exit and not opts.with_parent:
        mv = MatvecOptions(early_exit=False, structure_only=False)
        return K.row_masked_mxv(g, operand.select("id", F.lit(True).alias("val")), visited.select("id"), OR_AND, True, mv).select("id")
    if segments:
        hit = K.probe_waves(g, operand, visited.select("id"), "left_anti", mv, *segments)
    else:
        hit = K.probe_rows(g, operand, visited.select("id"), "left_anti", mv, rows)
    return hit.select("id", "parent") if opts.with_parent else hit.select("id")


def _counts(g: Graph, front: DataFrame, visited: DataFrame, needs: tuple[str, ...]) -> dict[str, int]:
    from ..plans import cost

    out: dict[str, int] = {}
    if "out_edges_f" in needs:
        out["out_edges_f"] = cost.col(g, front).first()[0]
    unvisited = g.vertices().join(visited.select("id"), "id", "left_anti")
    if "in_edges_u" in needs:
        out["in_edges_u"] = cost.row_masked(g, unvisited).first()[0]
    if "parents_checked" in needs:
        out["parents_checked"] = cost.row_early(g, unvisited, front).first()[0]
    return out


def bfs(g: Graph, source: int, rule=None, opts: BfsOptions = BfsOptions(), count: bool = False, rows: DataFrame | None = None) -> BfsResult:
    """(id, depth[, parent]) of the vertices that a source reaches.

    Every level is a written table under one folder, named by its depth, so the
    visited set is that folder, plans stay the same size, and a lost executor
    costs one level. ``count`` adds the deterministic access counters to the trace.
    ``rows`` is a stored row table (``layout.segment``) that several searches share.
    """
    return bfs_many(g, [source], rule, opts, count, rows)


def bfs_many(g: Graph, sources: list[int], rule=None, opts: BfsOptions = BfsOptions(), count: bool = False, rows: DataFrame | None = None) -> BfsResult:
    """A search from the set of sources, all at depth 0."""
    if opts.operand_reuse and opts.max_depth is not None and len(sources) > 1:
        raise ValueError("operand reuse needs whole levels: not with capped searches from several sources")
    rule = rule or RatioRule()
    spark, root = g.edges.sparkSession, new_path(g.edges.sparkSession, "bfs")
    known = g.vertices().filter(F.col("id").isin(sources)).count()
    if known < len(set(sources)):
        raise ValueError("a source is not a vertex of the graph")
    fields = "id bigint, parent bigint" if opts.with_parent else "id bigint"
    start = spark.createDataFrame([(s, None) if opts.with_parent else (s,) for s in sorted(set(sources))], fields)
    front, nnz = commit(start, f"{root}/depth=0")
    segments = None
    trace, depth, reached = [], 0, nnz
    while nnz and (opts.max_depth is None or depth < opts.max_depth):
        visited = spark.read.schema(f"{fields}, depth int").parquet(root)
        needs = ("out_edges_f", "in_edges_u", "parents_checked") if count else rule.needs
        seen = Seen(nnz, g.M, g.M - reached, **_counts(g, front, visited, needs))
        direction = rule.next(seen)
        began = time.perf_counter()
        if direction == PULL:
            if opts.waves and segments is None:
                from ..layout import segment

                table = persist(segment(g).sortWithinPartitions("seg", "vertex"), "segments")  # a wave skips the row groups of others
                segments = (table, table.agg(F.max("seg")).first()[0] or 0)
            elif rows is None and not opts.waves:
                rows = g.row_store
            found = _pull(g, rows, front, visited, opts, segments)
        else:
            found = _push(g, front, visited, opts, nnz, reached)
        depth += 1
        front, nnz = commit(found.select(*start.columns), f"{root}/depth={depth}")
        if opts.merge == "none":  # repeats stay in the frontier, each vertex counts once
            nnz_distinct = front.select("id").distinct().count()
        else:
            nnz_distinct = nnz
        ms = (time.perf_counter() - began) * 1000
        trace.append({"iter": depth, "direction": direction, "nnz_f": seen.nnz_f, "nnz_u": seen.nnz_u, "r": seen.nnz_f / g.M, "out_edges_f": seen.out_edges_f, "in_edges_u": seen.in_edges_u, "parents_checked": seen.parents_checked, "ms": ms})
        nnz = nnz_distinct
        reached += nnz
    out = spark.read.schema(f"{fields}, depth int").parquet(root)
    if opts.merge == "none":
        out = out.groupBy("id").agg(F.min("depth").alias("depth"), *([F.min_by("parent", "depth").alias("parent")] if opts.with_parent else []))
    return BfsResult(out.select("id", "depth", *(["parent"] if opts.with_parent else [])), trace)


def bfs_multi(g: Graph, sources: DataFrame, max_depth: int | None = None) -> DataFrame:
    """(source, id, depth): one search for each source (column id), all levels in step as one keyed product."""
    spark, root = g.edges.sparkSession, new_path(g.edges.sparkSession, "bfs-multi")
    front, nnz = commit(sources.select(F.col("id").alias("source"), "id").distinct(), f"{root}/depth=0")
    depth = 0
    while nnz and (max_depth is None or depth < max_depth):
        seen = spark.read.schema("source bigint, id bigint, depth int").parquet(root)
        found = g.pattern().join(front.select("source", F.col("id").alias("src")), "src").select("source", F.col("dst").alias("id")).distinct()
        fresh = found.join(seen.select("source", "id", F.lit(True).alias("on")), ["source", "id"], "left").filter("on IS NULL").select("source", "id")
        depth += 1
        front, nnz = commit(fresh, f"{root}/depth={depth}")
    return spark.read.schema("source bigint, id bigint, depth int").parquet(root)


def bfs_packed(g: Graph, sources: list[int]) -> DataFrame:
    """(id, depth, bits): up to 64 searches in one word; bits are the sources that reach the vertex at that depth."""
    if len(sources) > 64:
        raise ValueError("a word holds 64 sources")
    spark, root = g.edges.sparkSession, new_path(g.edges.sparkSession, "bfs-packed")
    schema = "id bigint, bits bigint"
    ones = spark.createDataFrame([(s, (1 << i) - (1 << 64) * (i == 63)) for i, s in enumerate(sources)], schema).groupBy("id").agg(F.bit_or("bits").alias("bits"))
    front, nnz = commit(ones, f"{root}/depth=0")
    depth = 0
    while nnz:
        seen = spark.read.schema(f"{schema}, depth int").parquet(root).groupBy("id").agg(F.bit_or("bits").alias("old"))
        found = g.pattern().join(front.withColumnRenamed("id", "src"), "src").groupBy(F.col("dst").alias("id")).agg(F.bit_or("bits").alias("bits"))
        fresh = found.join(seen, "id", "left").select("id", F.col("bits").bitwiseAND(F.bitwise_not(F.coalesce("old", F.lit(0).cast("bigint")))).alias("bits")).filter("bits <> 0")
        depth += 1
        front, nnz = commit(fresh, f"{root}/depth={depth}")
    return spark.read.schema(f"{schema}, depth int").parquet(root)


#: Edges of a graph that one task may hold, 16 bytes each: as much as may be sent to an executor.
ONE_TASK_EDGES = (256 << 20) // 16


def double_sweep(g: Graph, start: int, most: int = ONE_TASK_EDGES) -> tuple[int, int]:
    """(farthest vertex, eccentricity): a lower bound of the diameter by two searches.

    A level is a Spark job, and roads have thousands: a graph of at most ``most`` edges is
    searched in one task, level by level all the same. Larger ones go level by level over Spark.
    """
    if g.nnz <= most:
        edges = g.pattern().filter("src IS NOT NULL AND dst IS NOT NULL").select(F.col("src").cast("bigint").alias("src"), F.col("dst").cast("bigint").alias("dst"))
        found = edges.repartition(1).mapInArrow(_sweeps(start), "far bigint, depth int").first()
        if found:
            return found.far, found.depth
        if g.vertices().filter(F.col("id") == start).isEmpty():
            raise ValueError("a source is not a vertex of the graph")
        return start, 0
    far, ecc = start, 0
    for _ in range(2):
        found = bfs(g, far, PushOnly()).levels
        row = found.orderBy(F.desc("depth"), "id").first()
        far, ecc = row.id, row.depth
    return far, ecc


def _sweeps(start: int, times: int = 2, step: int = 1 << 20):
    """Searches over all edges in one task, each from the farthest vertex of the one before; no row if ``start`` has no edge. Nested whole, so that workers need not have the package."""

    def run(batches):
        import numpy as np
        import pyarrow as pa

        ends = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches]
        src, dst = (np.concatenate([np.zeros(0, np.int64), *(e[k] for e in ends)]) for k in (0, 1))
        del ends
        ids = np.unique(np.concatenate([np.unique(src), np.unique(dst)]))
        tail = np.searchsorted(ids, src).astype(np.int32)
        head = np.searchsorted(ids, dst).astype(np.int32)
        del src, dst
        begin = np.concatenate([[0], np.cumsum(np.bincount(tail, minlength=len(ids)))])
        head = head[np.argsort(tail, kind="stable")]
        at = int(np.searchsorted(ids, start))
        if at == len(ids) or ids[at] != start:
            return
        depth = 0
        for _ in range(times):
            seen, front, depth = np.zeros(len(ids), bool), np.array([at]), 0
            seen[at] = True
            while True:
                fresh = []
                for part in np.array_split(front, int((begin[front + 1] - begin[front]).sum()) // step + 1):
                    low, n = begin[part], begin[part + 1] - begin[part]
                    near = head[np.repeat(low - np.cumsum(n) + n, n) + np.arange(n.sum())]
                    near = np.unique(near[~seen[near]])
                    seen[near] = True
                    fresh.append(near)
                fresh = np.sort(np.concatenate(fresh))
                if not len(fresh):
                    break
                front, depth = fresh, depth + 1
            at = int(front[0])  # ids are in order, so this is the least of the farthest
        yield pa.RecordBatch.from_arrays([pa.array([int(ids[at])], pa.int64()), pa.array([depth], pa.int32())], ["far", "depth"])

    return run
