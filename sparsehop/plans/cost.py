"""Deterministic cost measures: matrix accesses, merge work, words moved, and whole traces from a depth table."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..graph import Graph
from ..layout import LONGEST, placed


def _sum_degrees(degrees: DataFrame, ids: DataFrame) -> DataFrame:
    return degrees.join(ids.select("id").distinct(), "id").agg(F.coalesce(F.sum("degree"), F.lit(0)).cast("bigint").alias("n"))


def edge_count(g: Graph, ids: DataFrame, direction: str = "out") -> DataFrame:
    """Edges that leave (or enter) a set of vertices."""
    return _sum_degrees(g.out_degrees() if direction == "out" else g.in_degrees(), ids)


def row(g: Graph) -> DataFrame:
    """Row product: every stored entry."""
    return g.edges.agg(F.count(F.lit(1)).alias("n"))


def row_masked(g: Graph, mask: DataFrame) -> DataFrame:
    """Masked row product: the entries of the admitted rows."""
    return edge_count(g, mask, "in")


def col(g: Graph, f: DataFrame) -> DataFrame:
    """Column product: the entries of the selected columns."""
    return edge_count(g, f, "out")


def row_early(g: Graph, mask: DataFrame, f: DataFrame) -> DataFrame:
    """With early exit: the place of each admitted row's first hit in ascending order, or the row's length."""
    rows = placed(g.pattern().join(mask.select(F.col("id").alias("dst")).distinct(), "dst", "left_semi")).withColumn("place", F.col("at") + 1)
    hits = rows.join(f.select(F.col("id").alias("src"), F.lit(True).alias("hit")).distinct(), "src", "left")
    return hits.groupBy("dst").agg(F.coalesce(F.min(F.when(F.col("hit"), F.col("place"))), F.count(F.lit(1))).alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("bigint").alias("n"))


def merge_cost(n: Column, k: Column, m: Column, kind: str) -> Column:
    """Comparisons of a merge of n entries from k lists over m rows: k-way, radix, or none."""
    if kind == "kway":
        return F.when(k <= 1, 0.0).otherwise(n * F.log2(k.cast("double")))
    return n * F.log2(m.cast("double")) if kind == "radix" else n.cast("double")


def words(n: Column, structure_only: bool) -> Column:
    """Sort words moved: keys alone, or keys with values."""
    return n if structure_only else 2 * n


def mask_speedup(m: int, nnz_m: int) -> float:
    """Largest gain that a mask can give."""
    return m / nnz_m if nnz_m else math.inf


def table1(g: Graph, f: DataFrame, m: DataFrame) -> DataFrame:
    """(variant, measured, expected): accesses of the four variants against their expected forms."""
    facts = g.out_degrees().agg(F.count(F.lit(1)).alias("M"), F.sum("degree").alias("nnz"))
    sizes = f.agg(F.count(F.lit(1)).alias("nf")).crossJoin(m.agg(F.count(F.lit(1)).alias("nm")))
    counts = row(g).toDF("c1").crossJoin(row_masked(g, m).toDF("c2")).crossJoin(col(g, f).toDF("c4"))
    one = facts.crossJoin(sizes).crossJoin(counts)  # each side is one row
    d = F.col("nnz") / F.col("M")
    merge = F.when(F.col("nf") <= 1, 1.0).otherwise(F.log2(F.col("nf").cast("double")))
    made = F.array(
        *[
            F.struct(F.lit(v).alias("variant"), measured.cast("bigint").alias("measured"), F.round(expected, 4).alias("expected"))
            for v, measured, expected in (
                ("row", F.col("c1"), d * F.col("M")), ("row masked", F.col("c2"), d * F.col("nm")),
                ("column", F.col("c4"), d * F.col("nf") * merge), ("column masked", F.col("c4"), d * F.col("nf") * merge),
            )
        ]
    )
    return one.select(F.inline(made))


def trace(g: Graph, levels: DataFrame, rows: DataFrame | None = None) -> DataFrame:
    """All per-level counters of a search in one pass over the graph, from its depth table.

    Row ``iter`` = L + 1 describes the state in which depth L is the frontier:
    nnz_f, nnz_u, r, C4 = out_edges_f, C2 = in_edges_u, C3 = parents_checked. A
    vertex of depth D is passed over whole at every level before D - 1 and stops
    at its first neighbour of depth D - 1 there; so three sums by depth are enough,
    and the running sums over levels are over a table of one row a level. With a
    graph's stored rows, that neighbour's place is looked up there and no edge is numbered.
    """
    depths = g.vertices().join(levels.select("id", "depth"), "id", "left")
    up = levels.select(F.col("id").alias("src"), F.col("depth").alias("theirs"))
    if rows is None:
        edges = placed(g.pattern()).withColumn("place", F.col("at") + 1)
        of = depths.select(F.col("id").alias("dst"), F.col("depth").alias("own"))
        both = edges.join(of, "dst").join(up, "src", "left")
        per = both.groupBy("dst", "own").agg(F.count(F.lit(1)).alias("indeg"), F.min(F.when(F.col("theirs") == F.col("own") - 1, F.col("place"))).alias("first"))
    else:
        of = levels.select(F.col("id").alias("dst"), F.col("depth").alias("own"))
        least = g.pattern().join(up, "src").join(of, "dst").filter("theirs = own - 1").groupBy(F.col("dst").alias("vertex")).agg(F.min("src").alias("parent"))
        at = F.array_position("nbrs", F.col("parent"))
        per = rows.join(least, "vertex", "left").groupBy(F.col("vertex").alias("dst")).agg(F.sum(F.size("nbrs")).alias("indeg"), F.min(F.when(at > 0, F.col("seg") * LONGEST + at)).alias("first"))
    out = g.out_degrees().withColumnRenamed("degree", "outdeg")
    each = depths.join(per.select(F.col("dst").alias("id"), "indeg", "first"), "id", "left").join(out, "id", "left").fillna(0, ["indeg", "outdeg"])
    by = each.groupBy("depth").agg(F.count(F.lit(1)).alias("n"), F.sum("indeg").alias("ins"), F.sum("outdeg").alias("outs"), F.sum("first").alias("firsts"))
    total = by.agg(F.sum("n").alias("M"), F.sum("ins").alias("all_ins"))
    order = Window.partitionBy(F.lit(0)).orderBy("depth")  # one row a level
    upto = order.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    seen = by.filter("depth IS NOT NULL").crossJoin(total)
    seen = seen.withColumns({"n_upto": F.sum("n").over(upto), "ins_upto": F.sum("ins").over(upto), "next_first": F.lead("firsts").over(order), "next_ins": F.lead("ins").over(order)})
    return seen.select(
        (F.col("depth") + 1).cast("int").alias("iter"), F.col("n").alias("nnz_f"), (F.col("M") - F.col("n_upto")).alias("nnz_u"), (F.col("n") / F.col("M")).alias("r"),
        F.col("outs").alias("out_edges_f"), (F.col("all_ins") - F.col("ins_upto")).alias("in_edges_u"),
        (F.col("all_ins") - F.col("ins_upto") - F.coalesce("next_ins", F.lit(0)) + F.coalesce("next_first", F.lit(0))).cast("bigint").alias("parents_checked"),
    )


def decisions(rows: list[dict], rule, m: int) -> list[str]:
    """Directions that a rule takes over a trace; ``m`` is the number of vertices."""
    from .direction import Level

    return [rule.next(Level(x["nnz_f"], m, x["nnz_u"], x["out_edges_f"], x["in_edges_u"], x["parents_checked"])) for x in rows]


def ratio_directions(tr: DataFrame, alpha: float = 0.01, beta: float = 0.01) -> DataFrame:
    """A trace with the ratio rule's direction, as windows over levels: the last level that moved it decides."""
    order = Window.partitionBy(F.lit(0)).orderBy("iter")
    last = F.coalesce(F.lag("r").over(order), F.lit(0.0))
    move = F.when((F.col("r") > last) & (F.col("r") > alpha), "pull").when((F.col("r") < last) & (F.col("r") < beta), "push")
    moved = tr.withColumn("move", move)
    return moved.withColumn("direction", F.coalesce(F.last("move", ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)), F.lit("push"))).drop("move")


def ablation(tr: DataFrame, alpha: float = 0.01) -> DataFrame:
    """(step, stack, accesses, words): the cumulative stack of the five switches, in gathered entries and sort words.

    Operand reuse and structure-only change words moved, not entries read.
    """
    t = ratio_directions(tr, alpha, alpha)
    pull = F.col("direction") == "pull"
    nnz = F.col("out_edges_f")
    all_rows = t.crossJoin(g_total(tr)).agg(
        F.sum(nnz).alias("a0"),
        F.sum(F.when(pull, F.col("nnz")).otherwise(nnz)).alias("a2"),
        F.sum(F.when(pull, F.col("in_edges_u")).otherwise(nnz)).alias("a3"),
        F.sum(F.when(pull, F.col("parents_checked")).otherwise(nnz)).alias("a4"),
        F.sum(F.when(pull, 0).otherwise(nnz)).alias("pushed"),
        F.sum(F.when(pull, F.col("nnz_f")).otherwise(0)).alias("packed"),
    )
    steps = [("baseline", "a0", 2 * F.col("a0")), ("structure only", "a0", F.col("a0")), ("change of direction", "a2", F.col("pushed") + F.col("packed")), ("masking", "a3", F.col("pushed") + F.col("packed")), ("early exit", "a4", F.col("pushed") + F.col("packed")), ("operand reuse", "a4", F.col("pushed"))]
    made = F.array(*[F.struct(F.lit(i).alias("step"), F.lit(s).alias("stack"), F.col(a).cast("bigint").alias("accesses"), w.cast("bigint").alias("words")) for i, (s, a, w) in enumerate(steps)])
    return all_rows.select(F.inline(made))


def g_total(tr: DataFrame) -> DataFrame:
    """nnz(A) of a search's graph, from its trace: what is behind the first frontier and what is in it."""
    return tr.filter("iter = 1").select((F.col("in_edges_u") + F.col("out_edges_f")).alias("nnz"))


def regret(tr: DataFrame, alphas: list[float]) -> DataFrame:
    """(alpha, accesses, best, regret): the ratio rule at several switch points against the cheaper direction a level."""
    out = None
    for a in alphas:
        t = ratio_directions(tr, a, a)
        mine = F.sum(F.when(F.col("direction") == "pull", F.col("parents_checked")).otherwise(F.col("out_edges_f"))).cast("bigint")
        best = F.sum(F.least("parents_checked", "out_edges_f")).cast("bigint")
        one = t.agg(F.lit(a).alias("alpha"), mine.alias("accesses"), best.alias("best")).withColumn("regret", F.round(F.col("accesses") / F.col("best") - 1, 6))
        out = one if out is None else out.unionByName(one)
    return out
