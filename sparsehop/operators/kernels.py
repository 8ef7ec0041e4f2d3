"""Matrix-vector products, row- and column-wise, masked or not.

A vector is (id, val); a mask is (id[, mval]). ``y[dst]`` sums over edges (src,
dst) the product of the edge's value and ``x[src]``. The row form starts at the
rows that the mask admits; the column form starts at the entries of x.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import vector as V
from ..functions.semiring import OR_AND, Semiring
from ..graph import Graph
from ..options import MatvecOptions


@dataclass
class MatvecResult:
    vector: DataFrame
    counters: dict[str, DataFrame] = field(default_factory=dict)


def _hinted(df: DataFrame, strategy: str) -> DataFrame:
    return df if strategy == "auto" else df.hint({"broadcast": "broadcast", "shuffle_hash": "shuffle_hash", "merge": "merge"}[strategy])


def _structure_only(sr: Semiring, opts: MatvecOptions) -> bool:
    if opts.structure_only and not sr.is_boolean_or:
        raise ValueError(f"structure-only products need a Boolean OR, not {sr.name}")
    return sr.is_boolean_or if opts.structure_only is None else opts.structure_only


def _early_exit(sr: Semiring, opts: MatvecOptions) -> bool:
    if opts.early_exit and not sr.is_boolean_or:
        raise ValueError(f"early exit needs a Boolean OR, not {sr.name}")
    return sr.is_boolean_or if opts.early_exit is None else opts.early_exit


def on_mask(mask: DataFrame, opts: MatvecOptions) -> DataFrame:
    """Ids at which a mask is on: entries whose value is not the mask identity, or all where it has no values."""
    return (mask.filter(F.col("mval") != F.lit(opts.mask_identity)) if "mval" in mask.columns else mask).select("id")


def expand(g: Graph, x: DataFrame, sr: Semiring, opts: MatvecOptions) -> DataFrame:
    """(id, val) of every edge that leaves an entry of x, not merged."""
    if _structure_only(sr, opts):
        return g.pattern().join(_hinted(x.select(F.col("id").alias("src")), opts.join_strategy), "src").select(F.col("dst").alias("id"))
    edges = g.valued(F.lit(sr.one))
    return edges.join(_hinted(x.select(F.col("id").alias("src"), F.col("val").alias("x")), opts.join_strategy), "src").select(F.col("dst").alias("id"), sr.mul(F.col("val"), F.col("x")).cast(sr.kind).alias("val"))


def merge(pairs: DataFrame, sr: Semiring, opts: MatvecOptions) -> DataFrame:
    """Sum expanded entries by id: hash aggregate, sorted aggregate, or not at all."""
    if opts.merge == "none":
        if not sr.is_idempotent:
            raise ValueError(f"unmerged results need an idempotent sum, not {sr.name}")
        return pairs if "val" in pairs.columns else pairs.withColumn("val", F.lit(sr.one).cast(sr.kind))
    if opts.merge == "sort":
        pairs = pairs.repartition("id").sortWithinPartitions("id")
    if "val" not in pairs.columns:
        return pairs.distinct().withColumn("val", F.lit(sr.one).cast(sr.kind))
    return pairs.groupBy("id").agg(sr.agg(F.col("val")).cast(sr.kind).alias("val"))


def col_mxv(g: Graph, x: DataFrame, sr: Semiring = OR_AND, opts: MatvecOptions = MatvecOptions()) -> DataFrame:
    """Column product: sparse in, sparse out."""
    return merge(expand(g, x, sr, opts), sr, opts)


def col_masked_mxv(g: Graph, x: DataFrame, mask: DataFrame, sr: Semiring = OR_AND, complement: bool = False, opts: MatvecOptions = MatvecOptions()) -> DataFrame:
    """Column product with a mask after the merge, or under it (``mask_placement='pre'``).

    After the merge, the mask is an outer join and a null test: the optimizer
    would push a semi or anti join below the aggregate, onto the edge scan,
    whenever the mask could be broadcast. A mask under the merge that must not
    be broadcast is such an outer join too, or all edges would be exchanged for it.
    """
    on = on_mask(mask, opts)

    def admitted(y: DataFrame, on: DataFrame) -> DataFrame:
        flagged = y.join(_hinted(on.withColumn("on", F.lit(True)), opts.mask_strategy), "id", "left")
        return flagged.filter(F.col("on").isNull() if complement else F.col("on").isNotNull()).select(*y.columns)

    if opts.mask_placement == "post":
        return admitted(col_mxv(g, x, sr, opts), on).select("id", "val")
    pairs = expand(g, x, sr, opts)
    if opts.mask_strategy in ("shuffle_hash", "merge"):
        return merge(admitted(pairs, on if complement else on.distinct()), sr, opts)
    return merge(pairs.join(_hinted(on, opts.mask_strategy), "id", "left_anti" if complement else "left_semi"), sr, opts)


def row_mxv(g: Graph, x: DataFrame, sr: Semiring = OR_AND, opts: MatvecOptions = MatvecOptions()) -> DataFrame:
    """Row product without a mask: every row reduced over all its entries; a value for every vertex."""
    edges = g.valued(F.lit(sr.one)).select(F.col("dst").alias("id"), "src", "val")
    read = edges.join(_hinted(x.select(F.col("id").alias("src"), F.col("val").alias("x")), opts.join_strategy), "src", "left")
    summed = read.groupBy("id").agg(sr.agg(F.when(F.col("x").isNotNull(), sr.mul(F.col("val"), F.col("x"))).otherwise(sr.zero_column())).cast(sr.kind).alias("val"))
    return V.to_dense(summed, g.vertices(), sr)


def row_masked_mxv(g: Graph, x: DataFrame, mask: DataFrame, sr: Semiring = OR_AND, complement: bool = False, opts: MatvecOptions = MatvecOptions()) -> DataFrame:
    """Row product of the admitted rows alone; for Boolean OR each row may stop at its first hit."""
    how, on = ("left_anti" if complement else "left_semi"), on_mask(mask, opts)
    if _early_exit(sr, opts):
        return probe_rows(g, x, on, how, opts).select("id").withColumn("val", F.lit(sr.one).cast(sr.kind))
    rows = g.valued(F.lit(sr.one)).select(F.col("dst").alias("id"), "src", "val").join(on, "id", how)
    read = rows.join(_hinted(x.select(F.col("id").alias("src"), F.col("val").alias("x")), opts.join_strategy), "src")
    return read.groupBy("id").agg(sr.agg(sr.mul(F.col("val"), F.col("x"))).cast(sr.kind).alias("val"))


def fits_words(g: Graph, opts: MatvecOptions) -> bool:
    """Whether a bit for every vertex id is small enough to send to every executor."""
    return g.facts["min_id"] >= 0 and (g.facts["max_id"] + 64) // 8 <= opts.broadcast_bytes


def _words(g: Graph, x: DataFrame) -> DataFrame:
    return V.all_words(x.select("id"), max(g.facts["max_id"], 0))


def probe_rows(g: Graph, x: DataFrame, on: DataFrame, how: str, opts: MatvecOptions, rows: DataFrame | None = None, words: DataFrame | None = None) -> DataFrame:
    """(id, parent): admitted rows with an in-neighbour in x, and the least such neighbour.

    The mask is joined before any list is read. Vertices whose bits fit the budget
    are probed by a bit test that stops at the first hit; beyond it the lists'
    entries meet x in an equi-join. Rows are segments, so a hub is many of them
    and its finds are united, unless the graph's stored rows are known to have no hub.
    ``words`` are x's bits where a caller has packed them.
    """
    stored, split = g.__dict__.get("stored_rows", (None, True))
    split = split or rows is not stored
    if rows is None:
        from ..layout import LONGEST, segment

        rows = segment(g, LONGEST, 1)
    open_rows = rows.join(on.select(F.col("id").alias("vertex")), "vertex", how)
    if fits_words(g, opts):
        words = F.broadcast(_words(g, x) if words is None else words)
        read = open_rows.join(words, F.exists("nbrs", lambda n: F.getbit(F.get("words", F.shiftright(n, 6).cast("int")), n.bitwiseAND(63).cast("int")) == 1))
        first = F.aggregate(
            "nbrs",
            F.lit(None).cast("bigint"),
            lambda s, n: F.when(s.isNotNull(), s).when(F.getbit(F.get("words", F.shiftright(n, 6).cast("int")), n.bitwiseAND(63).cast("int")) == 1, n),
        )
        found = read.select(F.col("vertex").alias("id"), first.alias("parent"))
        return found.groupBy("id").agg(F.min("parent").alias("parent")) if split else found
    entries = open_rows.select("vertex", F.explode("nbrs").alias("src"))
    return entries.join(x.select(F.col("id").alias("src")), "src", "left_semi").groupBy(F.col("vertex").alias("id")).agg(F.min("src").alias("parent"))


def probe_waves(g: Graph, x: DataFrame, on: DataFrame, how: str, opts: MatvecOptions, segments: DataFrame, last: int) -> DataFrame:
    """``probe_rows`` in waves of segments: only rows without a hit reach their next ones, so hubs' tails stay unread.

    A wave reads as many segments as all waves before it, so a hub of many segments
    takes their logarithm in waves; the last wave is the one after which no open row
    has a segment left. x is packed once for all waves.
    """
    from ..runtime import persist

    words = persist(_words(g, x), "words") if fits_words(g, opts) else None
    found, low = None, 0
    while low <= last:
        rest = segments
        if found is not None:
            rest = rest.join(found.select(F.col("id").alias("vertex")), "vertex", "left_anti")
            # segments have no gaps: who has more than ``low`` of them has that one
            if rest.filter(F.col("seg") == low).join(on.select(F.col("id").alias("vertex")), "vertex", how).isEmpty():
                break
        upto = max(1, 2 * low)
        hit = persist(probe_rows(g, x, on, how, opts, rest.filter((F.col("seg") >= low) & (F.col("seg") < upto)).select("vertex", "nbrs"), words), "wave")
        found = hit if found is None else found.unionByName(hit)
        low = upto
    return found


def accumulate(out: DataFrame, y: DataFrame, sr: Semiring) -> DataFrame:
    """Add a product to a prior result instead of replacing it."""
    return V.ewise_add(out, y, sr)


def mask_values(y: DataFrame, mask: DataFrame, op) -> DataFrame:
    """Generalised mask: ``op`` of value and mask value, where both are."""
    return y.join(mask.select("id", "mval"), "id").select("id", op(F.col("val"), F.col("mval")).alias("val"))


def balanced_expand(g: Graph, x: DataFrame, parts: int = 8) -> DataFrame:
    """(part, src, dst): a frontier's edges dealt evenly by the running sum of list lengths, hubs split over parts."""
    lengths = g.out_degrees().join(x.select("id"), "id")
    starts = V.prefix_sum(lengths, "id", "degree", parts)
    total = F.broadcast(lengths.agg(F.sum("degree").alias("total")))
    from ..layout import placed

    lists = placed(g.pattern().join(starts.select(F.col("id").alias("src"), "before"), "src").withColumnRenamed("before", "start"), "src", "dst")
    place = F.col("start") + F.col("at")
    return lists.join(total).select(F.floor(place * parts / F.col("total")).cast("int").alias("part"), "src", "dst")


def matvec(g: Graph, x: DataFrame, sr: Semiring = OR_AND, mask: DataFrame | None = None, complement: bool = False, direction: str = "auto", accum: bool = False, out: DataFrame | None = None, opts: MatvecOptions = MatvecOptions(), nnz: int | None = None) -> MatvecResult:
    """One call for all variants; ``auto`` pulls when nnz(x) / M is above the switch point."""
    from ..plans import cost

    if direction == "auto":
        nnz = x.count() if nnz is None else nnz
        direction = "pull" if g.M and nnz / g.M > opts.switch_point else "push"
    if direction == "push":
        y = col_mxv(g, x, sr, opts) if mask is None else col_masked_mxv(g, x, mask, sr, complement, opts)
        counters = {"accesses": cost.col(g, x)}
    elif mask is None:
        y, counters = V.to_sparse(row_mxv(g, x, sr, opts), sr), {"accesses": cost.row(g)}
    else:
        y = row_masked_mxv(g, x, mask, sr, complement, opts)
        on = on_mask(mask, opts)
        counters = {"accesses": cost.row_masked(g, g.vertices().join(on, "id", "left_anti") if complement else on)}
    return MatvecResult(accumulate(out, y, sr) if accum and out is not None else y, counters)


def khop(g: Graph, seeds: DataFrame, hops: int) -> DataFrame:
    """(id, hop) within ``hops`` of a seed set, at the least hop."""
    seen = seeds.select("id").distinct().withColumn("hop", F.lit(0))
    front = seen
    for h in range(1, hops + 1):
        front = col_masked_mxv(g, front.select("id", F.lit(True).alias("val")), seen.select("id"), OR_AND, True).select("id", F.lit(h).alias("hop"))
        seen = seen.unionByName(front)
    return seen
