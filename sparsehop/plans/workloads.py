"""The experiment workloads: microbenchmarks, level breakdown, ablation, comparison, and their summaries."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import vector as V
from ..functions.semiring import OR_AND
from ..graph import Graph
from ..layout import placed
from ..operators import algorithms as A
from ..operators import baselines
from ..operators import kernels as K
from ..operators import matmat as M
from ..operators.bfs import bfs, bfs_multi, double_sweep
from ..options import BfsOptions, MatvecOptions
from ..runtime import persist
from ..sources.generators import sample_vertices
from . import cost
from .direction import PushOnly, RatioRule

ALPHAS = [0.001, 0.005, 0.01, 0.02, 0.05, 0.1, 0.2]


def sizes_of(m: int, n: int = 8) -> list[int]:
    """n sizes from 1 to m, geometrically."""
    return sorted({max(1, round(m ** (i / (n - 1)))) for i in range(n)})


def micro(g: Graph, variant: str, sizes: list[int]) -> DataFrame:
    """(variant, size, accesses): the counted cost of one product variant over random sets of growing size.

    ``row``: all rows, growing vector; ``row_masked``: growing mask; ``col``: growing
    vector; ``col_masked``: the same with a mask of two thirds of its size.
    """
    out = None
    for n in sizes:
        f = sample_vertices(g, n)
        count = {"row": lambda f=f: cost.row(g), "row_masked": lambda f=f: cost.row_masked(g, f), "col": lambda f=f: cost.col(g, f), "col_masked": lambda f=f: cost.col(g, f)}[variant]()
        one = count.select(F.lit(variant).alias("variant"), F.lit(n).cast("bigint").alias("size"), F.col("n").alias("accesses"))
        out = one if out is None else out.unionByName(one)
    return out


def micro_times(g: Graph, variant: str, sizes: list[int], runs: int = 3) -> list[dict]:
    """Wall-clock of the products themselves, the mean of several runs."""
    every = g.vertices().select("id", F.lit(True).alias("val"))
    rows = []
    for n in sizes:
        f = persist(sample_vertices(g, n).select("id", F.lit(True).alias("val")))
        mask = sample_vertices(g, max(1, 2 * n // 3), 1)
        run = {
            "row": lambda f=f: K.row_mxv(g, f, OR_AND), "row_masked": lambda f=f: K.row_masked_mxv(g, every, f.select("id"), OR_AND),
            "col": lambda f=f: K.col_mxv(g, f, OR_AND), "col_masked": lambda f=f, mask=mask: K.col_masked_mxv(g, f, mask, OR_AND),
        }[variant]
        spent = []
        for _ in range(runs):
            began = time.perf_counter()
            run().write.format("noop").mode("overwrite").save()
            spent.append(time.perf_counter() - began)
        rows.append({"variant": variant, "size": n, "ms": 1000 * sum(spent) / len(spent)})
    return rows


def micro_products(g: Graph, sizes: list[int]) -> DataFrame:
    """(variant, size, n, total): the four products run over random sets of growing size; how many outputs and the sum of their ids."""
    every = g.vertices().select("id", F.lit(True).alias("val"))
    out = None
    for n in sizes:
        f = persist(sample_vertices(g, n).select("id", F.lit(True).alias("val")))
        mask = sample_vertices(g, max(1, 2 * n // 3), 1)
        made = {
            "row": V.to_sparse(K.row_mxv(g, f, OR_AND), OR_AND), "row_masked": K.row_masked_mxv(g, every, f.select("id"), OR_AND),
            "col": K.col_mxv(g, f, OR_AND), "col_masked": K.col_masked_mxv(g, f, mask, OR_AND),
        }
        for variant, y in made.items():
            one = y.agg(F.lit(variant).alias("variant"), F.lit(n).cast("bigint").alias("size"), F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("id"), F.lit(0)).cast("bigint").alias("total"))
            out = one if out is None else out.unionByName(one)
    return out


def micro_merge(g: Graph, sizes: list[int]) -> DataFrame:
    """(kind, size, n, work, words): merges of an expansion by three kinds, in comparisons and sort words."""
    out = None
    facts = g.out_degrees().agg(F.count(F.lit(1)).alias("m"))
    for n in sizes:
        one = cost.col(g, sample_vertices(g, n)).crossJoin(facts)
        for kind in ("kway", "radix", "none"):
            row = one.select(F.lit(kind).alias("kind"), F.lit(n).cast("bigint").alias("size"), "n", F.round(cost.merge_cost(F.col("n"), F.lit(n), F.col("m"), kind), 4).alias("work"), cost.words(F.col("n"), kind == "none").alias("words"))
            out = row if out is None else out.unionByName(row)
    return out


def crossover(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: the least size at which series ``a`` costs more than ``b`` (null if never)."""
    both = a.select("size", F.col("accesses").alias("x")).join(b.select("size", F.col("accesses").alias("y")), "size")
    return both.agg(F.min(F.when(F.col("x") > F.col("y"), F.col("size"))).alias("size"))


def level_times(g: Graph, source: int, runs: int = 1) -> list[dict]:
    """Per level: counts, and the mean time of a push and of a pull from the same state."""
    levels = bfs(g, source).levels
    rows, trace = g.row_store, {x["iter"]: x.asDict() for x in cost.trace(g, levels, g.row_store).collect()}
    out, opts = [], MatvecOptions()
    for depth in range(max(trace)):
        front = persist(levels.filter(F.col("depth") == depth).select("id", F.lit(True).alias("val")))
        seen = persist(levels.filter(F.col("depth") <= depth).select("id"))
        spent = []
        for plan in (K.col_masked_mxv(g, front, seen, OR_AND, True), K.probe_rows(g, seen, seen, "left_anti", opts, rows)):
            spent.append(timed(lambda plan=plan: plan.write.format("noop").mode("overwrite").save(), runs)[0])
        out.append(trace[depth + 1] | {"push_ms": spent[0], "pull_ms": spent[1]})
    return out


def source_traces(g: Graph, many: DataFrame) -> DataFrame:
    """(source, iter, nnz_f, nnz_u, out_edges_f, in_edges_u, parents_checked) of searches (source, id, depth): both directions' cost at every level.

    As in ``cost.trace``: a vertex is passed over whole before the level of its parents and stops at the first of them there.
    """
    degree = g.in_degrees().withColumnRenamed("degree", "ins").join(g.out_degrees().withColumnRenamed("degree", "outs"), "id", "full").fillna(0)
    up = many.select("source", F.col("id").alias("src"), (F.col("depth") + 1).alias("depth"))
    edges = placed(g.pattern()).withColumn("place", F.col("at") + 1)
    first = edges.join(up, "src").join(many.withColumnRenamed("id", "dst"), ["source", "dst", "depth"]).groupBy("source", F.col("dst").alias("id")).agg(F.min("place").alias("first"))
    by = many.join(degree, "id").join(first, ["source", "id"], "left").groupBy("source", "depth")
    sums = by.agg(F.count(F.lit(1)).alias("n"), F.sum("ins").alias("ins"), F.sum("outs").alias("outs"), F.coalesce(F.sum("first"), F.lit(0)).alias("firsts"))
    order = Window.partitionBy("source").orderBy("depth")  # one row a level
    upto = order.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    left = F.lit(g.nnz) - F.sum("ins").over(upto)
    checked = left - F.coalesce(F.lead("ins").over(order), F.lit(0)) + F.coalesce(F.lead("firsts").over(order), F.lit(0))
    return sums.select("source", (F.col("depth") + 1).alias("iter"), F.col("n").alias("nnz_f"), (F.lit(g.M) - F.sum("n").over(upto)).alias("nnz_u"), F.col("outs").alias("out_edges_f"), left.alias("in_edges_u"), checked.cast("bigint").alias("parents_checked"))


def sample_sources(g: Graph, n: int) -> DataFrame:
    """``source_traces`` of n sampled sources (all, where the graph has fewer)."""
    return source_traces(g, persist(bfs_multi(g, sample_vertices(g, n))))


def parents_curve(tr: DataFrame) -> DataFrame:
    """(iter, parents_per_vertex): entries read for each unvisited vertex."""
    return tr.filter("nnz_u > 0").select("iter", F.round(F.col("parents_checked") / F.col("nnz_u"), 6).alias("parents_per_vertex"))


ABLATION = [
    ("baseline", PushOnly, BfsOptions(mask=False, early_exit=False, operand_reuse=False, structure_only=False, merge="sort")),
    ("structure only", PushOnly, BfsOptions(mask=False, early_exit=False, operand_reuse=False, structure_only=True, merge="sort")),
    ("change of direction", RatioRule, BfsOptions(mask=False, early_exit=False, operand_reuse=False, structure_only=True)),
    ("masking", RatioRule, BfsOptions(mask=True, early_exit=False, operand_reuse=False, structure_only=True)),
    ("early exit", RatioRule, BfsOptions(mask=True, early_exit=True, operand_reuse=False, structure_only=True)),
    ("operand reuse", RatioRule, BfsOptions()),
]


def timed(run, runs: int = 1) -> tuple[float, object]:
    spent, result = [], None
    for _ in range(runs):
        began = time.perf_counter()
        result = run()
        spent.append(1000 * (time.perf_counter() - began))
    return sum(spent) / len(spent), result


def ablation_times(g: Graph, source: int, runs: int = 1) -> list[dict]:
    """Time of each cumulative stack, with throughput over all stored entries and the gain over the row before."""
    rows: list[dict] = []
    for name, rule, opts in ABLATION:
        ms, _ = timed(lambda rule=rule, opts=opts: bfs(g, source, rule(), opts), runs)
        rows.append({"stack": name, "ms": ms, "mteps": g.nnz / ms / 1000, "gain": rows[-1]["ms"] / ms if rows else None})
    return rows


def compare(graphs: dict[str, tuple[Graph, int, str]], systems: list[str] | None = None, runs: int = 1) -> list[dict]:
    """graph, type, system, ms, mteps, status for each graph (graph, source, type) and system."""
    rows = []
    for name, (g, source, kind) in graphs.items():
        run = {"switching": lambda g=g, s=source: bfs(g, s)} | {k: (lambda g=g, s=source, f=f: f(g, s)) for k, f in baselines.BASELINES.items()}
        for system in systems or run:
            try:
                ms, _ = timed(run[system], runs)
                rows.append({"graph": name, "type": kind, "system": system, "ms": ms, "mteps": g.nnz / ms / 1000, "status": "ok"})
            except Exception as e:  # Spark wraps an executor's or the driver's error in its own
                if "OutOfMemory" not in str(e) and not isinstance(e, MemoryError):
                    raise
                rows.append({"graph": name, "type": kind, "system": system, "ms": None, "mteps": None, "status": "out of memory"})
    return rows


def slowdown(bench: DataFrame) -> DataFrame:
    """A bench table (graph, system, ms) with each row's ratio to its graph's fastest."""
    return bench.withColumn("slowdown", F.round(F.col("ms") / F.min("ms").over(Window.partitionBy("graph")), 6))


def geomean(bench: DataFrame, reference: str, by: list[str]) -> DataFrame:
    """(by..., system, speedup): geometric mean of other systems' time over the reference's."""
    ref = bench.filter((F.col("system") == reference) & F.col("ms").isNotNull()).select("graph", F.col("ms").alias("ref"))
    return bench.filter((F.col("system") != reference) & F.col("ms").isNotNull()).join(ref, "graph").groupBy(*by, "system").agg(F.round(F.exp(F.avg(F.log(F.col("ms") / F.col("ref")))), 6).alias("speedup"))


def describe(name: str, g: Graph) -> DataFrame:
    """(graph, v, e, max_degree, mean_degree) of one graph."""
    return g.out_degrees().agg(F.lit(name).alias("graph"), F.count(F.lit(1)).alias("v"), F.sum("degree").cast("bigint").alias("e"), F.max("degree").alias("max_degree"), F.round(F.avg("degree"), 6).alias("mean_degree"))


def describe_all(graphs: dict[str, tuple[Graph, int, str]]) -> list[dict]:
    """Descriptors with a lower bound of the diameter by double sweep."""
    return [describe(k, g).first().asDict() | {"type": kind, "diameter_lb": double_sweep(g, s)[1]} for k, (g, s, kind) in graphs.items()]


def masked_algorithms(g: Graph, dense: Graph, sources: DataFrame, x: DataFrame, w: DataFrame, wanted: DataFrame, iters: int = 6, tol: float = 0.05) -> DataFrame:
    """(algorithm, masked, unmasked, ratio, bound): entries read with the mask of known outputs and without, in five algorithms.

    ``bound`` is what the mask could save if all rows were alike: outputs without it over outputs with it.
    Ranks, centrality and independent sets run on ``g``, triangles on ``dense``, layers on ``x``, ``w`` and the mask ``wanted``.
    """
    ins = g.in_degrees()
    ranked = A.pagerank(g, 0.85, iters, tol).select("id", F.coalesce("frozen_at", F.lit(iters)).alias("rounds")).join(ins, "id")
    parts = [ranked.agg(F.lit("adaptive ranks").alias("algorithm"), F.sum(F.col("rounds") * F.col("degree")).alias("masked"), (F.sum("degree") * iters).alias("unmasked"), (F.count(F.lit(1)) * iters / F.sum("rounds")).alias("bound"))]
    e = persist(M.oriented(dense), "oriented")
    out = persist(e.groupBy("a").agg(F.count(F.lit(1)).alias("n")))
    lists = e.join(out.select(F.col("a").alias("b"), F.col("n").alias("m")), "b", "left").agg(F.sum("m").alias("masked"), F.count(F.lit(1)).alias("edges"))
    whole = M.wedge_blocks(e).agg(F.coalesce(F.sum("wedges"), F.lit(0)).alias("unmasked"), F.coalesce(F.sum("outputs"), F.lit(0)).alias("outputs"))
    parts.append(lists.crossJoin(whole).select(F.lit("triangles").alias("algorithm"), "masked", "unmasked", (F.col("outputs") / F.col("edges")).alias("bound")))  # each side is one row
    t = source_traces(g, persist(bfs_multi(g, sources)))
    parts.append(t.agg(F.lit("batched centrality").alias("algorithm"), F.sum("in_edges_u").alias("masked"), (F.count(F.lit(1)) * g.nnz).alias("unmasked"), (F.count(F.lit(1)) * g.M / F.sum("nnz_u")).alias("bound")))
    log: list[DataFrame] = []
    A.mis(g, log=log)
    open_ = [c.join(ins, "id").agg(F.sum("degree").alias("d"), F.count(F.lit(1)).alias("n")) for c in log]
    rounds = open_[0]
    for r in open_[1:]:
        rounds = rounds.unionByName(r)
    parts.append(rounds.agg(F.lit("independent set").alias("algorithm"), F.sum("d").alias("masked"), (F.count(F.lit(1)) * g.nnz).alias("unmasked"), (F.count(F.lit(1)) * g.M / F.sum("n")).alias("bound")))
    mine = wanted.join(x.groupBy("i").agg(F.count(F.lit(1)).alias("n")), "i").agg(F.sum("n").alias("masked"), F.count(F.lit(1)).alias("wanted"))
    formed = x.select("i", F.col("j").alias("k")).join(w.select(F.col("i").alias("k"), "j"), "k").agg(F.count(F.lit(1)).alias("unmasked"), F.count_distinct("i", "j").alias("outputs"))
    parts.append(mine.crossJoin(formed).select(F.lit("sparse layers").alias("algorithm"), "masked", "unmasked", (F.col("outputs") / F.col("wanted")).alias("bound")))
    both = parts[0]
    for p in parts[1:]:
        both = both.unionByName(p)
    return both.select("algorithm", F.col("masked").cast("bigint").alias("masked"), F.col("unmasked").cast("bigint").alias("unmasked"), F.round(F.col("unmasked") / F.col("masked"), 6).alias("ratio"), F.round("bound", 6).alias("bound"))


def generality(g: Graph, mask: DataFrame) -> DataFrame:
    """(masked, unmasked, ratio, bound): what a mask of known output saves on one row product."""
    sizes = mask.agg(F.count(F.lit(1)).alias("nm")).crossJoin(g.vertices().agg(F.count(F.lit(1)).alias("m")))
    one = cost.row_masked(g, mask).toDF("masked").crossJoin(cost.row(g).toDF("unmasked")).crossJoin(sizes)
    return one.select("masked", "unmasked", F.round(F.col("unmasked") / F.col("masked"), 6).alias("ratio"), F.round(F.col("m") / F.col("nm"), 6).alias("bound"))


def one_step(spark: SparkSession, g: Graph, source: int = 0) -> DataFrame:
    """(method, id): a source's second step by push, pull, pull with early exit and pull with operand reuse."""
    front = persist(g.pattern().filter(F.col("src") == source).select(F.col("dst").alias("id"), F.lit(True).alias("val")).distinct(), "front")
    seen = persist(front.select("id").union(spark.createDataFrame([(source,)], "id bigint")), "seen")
    whole = seen.withColumn("val", F.lit(True))
    exits, plain = MatvecOptions(early_exit=True), MatvecOptions(early_exit=False)
    found = {
        "push": K.col_masked_mxv(g, front, seen, OR_AND, True), "pull": K.row_masked_mxv(g, front, seen, OR_AND, True, plain),
        "pull early exit": K.row_masked_mxv(g, front, seen, OR_AND, True, exits), "pull reuse": K.row_masked_mxv(g, whole, seen, OR_AND, True, exits),
    }
    out = None
    for k, v in found.items():
        one = v.select(F.lit(k).alias("method"), "id")
        out = one if out is None else out.unionByName(one)
    return out

