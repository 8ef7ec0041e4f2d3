"""Algorithms on masked products: shortest paths, ranks, centrality, independent sets, components."""

from __future__ import annotations

from copy import copy

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.semiring import COUNT_TIMES, MIN_FIRST, MIN_PLUS, PLUS_TIMES
from ..graph import Graph
from ..plans.direction import PULL, RatioRule, TwoPhase
from ..plans.direction import Level as Seen
from ..runtime import commit, forget, new_path, persist
from . import kernels as K


def sssp(g: Graph, source: int, rule=None, operand_reuse: bool = False) -> DataFrame:
    """(id, dist) by Bellman-Ford over the changed set; pulls relax all rows, with reuse from all known distances.

    Weights are ``val`` (1 where the graph has none) and not negative cycles.
    """
    rule = rule or TwoPhase()
    spark, root = g.edges.sparkSession, new_path(g.edges.sparkSession, "sssp")
    weighted = Graph(g.valued(F.lit(1.0)).select("src", "dst", F.col("val").cast("double").alias("val")), g.directed)
    dist, nnz = commit(spark.createDataFrame([(source, 0.0)], "id bigint, val double"), f"{root}/0-dist")
    front, turn = dist, 0
    while nnz:
        if rule.next(Seen(nnz, g.M)) == PULL:
            y = K.row_masked_mxv(weighted, dist if operand_reuse else front, weighted.vertices(), MIN_PLUS)
        else:
            y = K.col_mxv(weighted, front, MIN_PLUS)
        turn += 1
        better = y.join(dist.select("id", F.col("val").alias("old")), "id", "left").filter("old IS NULL OR val < old").select("id", "val")
        front, nnz = commit(better, f"{root}/{turn}-front")
        if nnz:
            old, (dist, _) = dist, commit(K.accumulate(dist, front, MIN_PLUS), f"{root}/{turn}-dist")
            forget(old)
    return dist.select("id", F.col("val").alias("dist"))


def pagerank(g: Graph, damping: float = 0.85, iters: int = 10, freeze_tol: float | None = None, layout: str = "rows") -> DataFrame:
    """(id, rank, frozen_at) after a fixed number of rounds; the mass of vertices without out-edges is spread evenly.

    With ``freeze_tol``, a vertex whose rank moves less than that share of itself is
    frozen: later rounds compute the rows of the active vertices alone. ``grid``
    takes the edges by blocks of source and target and sums inside the cells first.
    """
    m = g.M
    out = g.out_degrees().withColumnRenamed("degree", "out")
    rank = persist(g.vertices().select("id", F.lit(1.0 / m).alias("val"), F.lit(None).cast("int").alias("frozen")), "rank")
    for i in range(1, iters + 1):
        share = rank.join(out, "id", "left")
        loose = F.broadcast(share.agg(F.coalesce(F.sum(F.when(F.col("out").isNull(), F.col("val"))), F.lit(0.0)).alias("loose")))
        x = share.filter("out IS NOT NULL").select("id", (F.col("val") / F.col("out")).alias("val"))
        pattern = Graph(g.pattern().withColumn("val", F.lit(1.0)), g.directed)
        if freeze_tol is not None and i > 1:
            y = K.row_masked_mxv(pattern, x, rank.filter("frozen IS NULL").select("id"), PLUS_TIMES)
        elif layout == "grid":
            from ..layout import grid

            cells = grid(pattern).join(x.select(F.col("id").alias("src"), F.col("val").alias("x")), "src")
            partial = cells.groupBy("src_block", "dst_block", "dst").agg(F.sum("x").alias("part"))
            y = partial.groupBy(F.col("dst").alias("id")).agg(F.sum("part").alias("val"))
        else:
            y = K.row_masked_mxv(pattern, x, g.vertices(), PLUS_TIMES)
        new = F.lit((1 - damping) / m) + damping * (F.coalesce(F.col("y"), F.lit(0.0)) + F.col("loose") / m)
        moved = rank.join(y.select("id", F.col("val").alias("y")), "id", "left").join(loose).withColumn("new", F.when(F.col("frozen").isNull(), new).otherwise(F.col("val")))
        frozen = F.col("frozen") if freeze_tol is None else F.when(F.col("frozen").isNull() & (F.abs(F.col("new") - F.col("val")) < freeze_tol * F.col("val")), F.lit(i)).otherwise(F.col("frozen"))
        old, rank = rank, persist(moved.select("id", F.col("new").alias("val"), frozen.alias("frozen")), "rank")
        forget(old)
    return rank.select("id", F.col("val").alias("rank"), F.col("frozen").alias("frozen_at"))


def personalized_pagerank(g: Graph, seeds: DataFrame, damping: float = 0.85, iters: int = 10, switch: float = 0.01, rule=None, operand_reuse: bool = True, tol: float = 0.0) -> DataFrame:
    """(id, rank): mass starts at and returns to the seeds; a rule picks columns or rows each round.

    A vertex without out-edges sends its mass back to the seeds. The frontier is the
    set of ranks that moved by more than ``tol`` in the last round, and a push sends
    on their changes alone. A pull with operand reuse reads the ranks themselves, which gives the
    same result; so does a push where ``tol`` is 0, as no rank is left out there.
    Changes up to ``tol`` are kept but not sent on.
    """
    rule = rule or RatioRule(switch, switch)
    base = seeds.select("id").distinct()
    n = base.count()
    if not n:
        return base.withColumn("rank", F.lit(0.0))
    start = persist(base.select("id", F.lit(1.0 / n).alias("val")), "seeds")
    rank, nnz = commit(start, new_path(g.edges.sparkSession, "ppr"))
    out = g.out_degrees().withColumnRenamed("degree", "out")
    pattern = Graph(g.pattern().withColumn("val", F.lit(1.0)), g.directed)
    before = None
    for _ in range(iters):
        pull = rule.next(Seen(nnz, g.M)) == PULL
        whole = before is None or (operand_reuse and (pull or tol == 0))
        share = (rank if whole else _changes(rank, before, tol)).join(out, "id", "left")
        loose = F.broadcast(share.agg(F.coalesce(F.sum(F.when(F.col("out").isNull(), F.col("val"))), F.lit(0.0)).alias("loose")))
        x = share.filter("out IS NOT NULL").select("id", (F.col("val") / F.col("out")).alias("val"))
        y = K.row_masked_mxv(pattern, x, g.vertices(), PLUS_TIMES) if pull else K.col_mxv(pattern, x, PLUS_TIMES)
        back = start.join(loose).select("id", (((1 - damping) * F.col("val") if whole else F.lit(0.0)) + damping * F.col("loose") * F.col("val")).alias("val"))
        after = K.accumulate(y.select("id", (damping * F.col("val")).alias("val")), back, PLUS_TIMES)
        gone, before = before, rank
        rank, nnz = commit(after if whole else K.accumulate(before, after, PLUS_TIMES), new_path(g.edges.sparkSession, "ppr"))
        if gone is not None:
            forget(gone)
        if tol > 0:
            nnz = _changes(rank, before, tol).count()
            if not nnz:
                break
    if before is not None:
        forget(before)
    return rank.select("id", F.col("val").alias("rank"))


def _changes(new: DataFrame, old: DataFrame, tol: float) -> DataFrame:
    """(id, val): by how much the values moved, where that is more than ``tol``."""
    both = new.select("id", F.col("val").alias("now")).join(old.select("id", F.col("val").alias("then")), "id", "full")
    return both.select("id", (F.coalesce("now", F.lit(0.0)) - F.coalesce("then", F.lit(0.0))).alias("val")).filter(F.abs("val") > tol)


def betweenness(g: Graph, sources: DataFrame, batch: int = 64, rule=None) -> DataFrame:
    """(id, score): dependency sums over the given sources, in batches that advance in step.

    Forward: path counts by masked products over (source, vertex), the mask being
    each source's unvisited vertices; a rule picks the direction by the share of
    (source, vertex) pairs in the frontier. Backward: by depth, each vertex gives its
    predecessors their share. A batch has at most 64 sources, the bits of a mask word.
    """
    if not 0 < batch <= 64:
        raise ValueError("a batch holds 1 to 64 sources")
    spark = g.edges.sparkSession
    ids = [r.id for r in sources.select("id").distinct().orderBy("id").collect()]  # the batch list is the caller's own
    if not ids:
        return g.vertices().select("id", F.lit(0.0).alias("score"))
    parts = [_betweenness_batch(g, spark.createDataFrame([(i, k) for k, i in enumerate(ids[at : at + batch])], "source bigint, k int"), copy(rule) if rule else RatioRule()) for at in range(0, len(ids), batch)]
    total = parts[0]
    for p in parts[1:]:
        total = total.unionByName(p)
    return g.vertices().join(total.groupBy("id").agg(F.sum("score").alias("score")), "id", "left").select("id", F.coalesce("score", F.lit(0.0)).alias("score"))


def _paths_pushed(g: Graph, front: DataFrame, seen: DataFrame) -> DataFrame:
    """(source, id, paths): column product of the frontier, masked after the merge."""
    grown = g.pattern().join(front.withColumnRenamed("id", "src"), "src").groupBy("source", F.col("dst").alias("id")).agg(F.sum("paths").alias("paths"))
    return grown.join(seen.select("source", "id", F.lit(True).alias("on")), ["source", "id"], "left").filter("on IS NULL").select("source", "id", "paths")


def _paths_pulled(g: Graph, front: DataFrame, seen: DataFrame, members: DataFrame, n: int) -> DataFrame:
    """The same by masked rows: a word for each vertex has the sources that have not visited it.

    Rows without an open bit are not read, and a neighbour's entries (one a
    source, at most 64) are sifted by the row's word before they are expanded.
    """
    numbers = F.broadcast(members)  # at most 64 rows
    bit = F.call_function("shiftleft", F.lit(1).cast("bigint"), F.col("k"))
    visited = seen.join(numbers, "source").groupBy("id").agg(F.bit_or(bit).alias("bits"))
    every = F.lit(-1 if n == 64 else (1 << n) - 1).cast("bigint")
    rows = g.vertices().join(visited, "id", "left").select(F.col("id").alias("dst"), every.bitwiseAND(F.bitwise_not(F.coalesce("bits", F.lit(0).cast("bigint")))).alias("open")).filter("open <> 0")
    lists = front.join(numbers, "source").groupBy(F.col("id").alias("src")).agg(F.collect_list(F.struct("k", "paths")).alias("entries"))
    read = g.pattern().join(rows, "dst").join(lists, "src")
    kept = read.select("dst", F.explode(F.filter("entries", lambda e: F.getbit(F.col("open"), e["k"]) == 1)).alias("e"))
    return kept.groupBy(F.col("e.k").alias("k"), F.col("dst").alias("id")).agg(F.sum("e.paths").alias("paths")).join(numbers, "k").select("source", "id", "paths")


def _betweenness_batch(g: Graph, members: DataFrame, rule) -> DataFrame:
    spark, root = g.edges.sparkSession, new_path(g.edges.sparkSession, "paths")
    front, nnz = commit(members.select("source", F.col("source").alias("id"), F.lit(1.0).alias("paths")), f"{root}/depth=0")
    n, depth = nnz, 0
    schema = "source bigint, id bigint, paths double, depth int"
    while nnz:
        seen = spark.read.schema(schema).parquet(root).select("source", "id")
        fresh = _paths_pulled(g, front, seen, members, n) if rule.next(Seen(nnz, g.M * n)) == PULL else _paths_pushed(g, front, seen)
        depth += 1
        front, nnz = commit(fresh, f"{root}/depth={depth}")
    all_paths = spark.read.schema(schema).parquet(root)
    down = persist(all_paths.filter(F.col("depth") == depth - 1).select("source", "id", "paths", "depth", F.lit(0.0).alias("delta")), "delta")
    done = down
    for d in range(depth - 2, -1, -1):
        give = down.select("source", F.col("id").alias("dst"), ((1 + F.col("delta")) / F.col("paths")).alias("part"))
        level = all_paths.filter(F.col("depth") == d)
        got = level.join(g.pattern().withColumnRenamed("src", "id"), "id").join(give, ["source", "dst"]).groupBy("source", "id").agg(F.sum("part").alias("part"))
        down = persist(level.join(got, ["source", "id"], "left").select("source", "id", "paths", "depth", (F.col("paths") * F.coalesce("part", F.lit(0.0))).alias("delta")), "delta")
        done = done.unionByName(down)
    return done.filter("source <> id").groupBy("id").agg(F.sum("delta").alias("score"))


def priority(seed: int = 0):
    """A vertex's fixed pseudo-random priority, in integers that stay below 2**63."""
    return F.pmod(F.pmod(F.col("id"), F.lit(1_000_003)) * 48_271 + seed * 7_919 + 12_345, F.lit(1_000_003))


def mis(g: Graph, seed: int = 0, log: list[DataFrame] | None = None) -> DataFrame:
    """(id): a maximal independent set. Each round the candidates whose (priority, id) beats all candidate neighbours join;
    they and their neighbours leave. The candidate set is the mask of each round's product; ``log`` takes each round's."""
    open_ = persist(g.vertices().select("id", F.struct(priority(seed).alias("p"), F.col("id").alias("i")).alias("rank")), "open")
    chosen = None
    while not open_.isEmpty():
        if log is not None:
            log.append(open_.select("id"))
        edges = g.pattern().join(open_.select(F.col("id").alias("src"), F.col("rank").alias("theirs")), "src").join(open_.select(F.col("id").alias("dst")), "dst", "left_semi")
        best = edges.groupBy(F.col("dst").alias("id")).agg(F.max("theirs").alias("best"))
        won = persist(open_.join(best, "id", "left").filter("best IS NULL OR rank > best").select("id"), "won")
        chosen = won if chosen is None else chosen.unionByName(won)
        near = g.pattern().join(won.withColumnRenamed("id", "src"), "src", "left_semi").select(F.col("dst").alias("id"))
        open_ = persist(open_.join(won.union(near).distinct(), "id", "left_anti"), "open")
    return chosen if chosen is not None else g.vertices().limit(0)


def components(g: Graph) -> DataFrame:
    """(id, component): the least id of each component, by least-label products over the changed set."""
    spark, root = g.edges.sparkSession, new_path(g.edges.sparkSession, "components")
    label, nnz = commit(g.vertices().select("id", F.col("id").alias("val")), f"{root}/0")
    front, turn = label, 0
    while nnz:
        y = K.col_mxv(g, front, MIN_FIRST)
        turn += 1
        better = y.join(label.select("id", F.col("val").alias("old")), "id").filter("val < old").select("id", "val")
        front, nnz = commit(better, f"{root}/{turn}-front")
        if nnz:
            old, (label, _) = label, commit(K.accumulate(label, front, MIN_FIRST), f"{root}/{turn}")
            forget(old)
    return label.select("id", F.col("val").alias("component"))


def path_counts(g: Graph, x: DataFrame, hops: int) -> DataFrame:
    """(id, val): walks of exactly ``hops`` edges from a weighted start vector."""
    for _ in range(hops):
        x = K.col_mxv(g, x, COUNT_TIMES)
    return x
