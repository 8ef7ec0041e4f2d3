"""Registered queries of the engine and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import sqltext as Q
from .functions import semiring as S
from .functions import vector as V
from .graph import Graph, canonicalize_report, degree_quantiles, edges_from_pairs, subgraph, top_hubs
from .layout import bucketed
from .operators import algorithms as A
from .operators import baselines as B
from .operators import bfs as X
from .operators import kernels as K
from .operators import matmat as M
from .options import BfsOptions, MatvecOptions
from .plans import cost as C
from .plans import workloads as W
from .plans.direction import BytesRule, PullOnly, PushOnly, RatioRule, Schedule, TwoPhase
from .plans.metrics import physical
from .runtime import persist
from .sources import generators as G
from .sources import tables as T

QUERIES: dict = {}
SQL: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def _kron(spark) -> Graph:
    return Graph(persist(G.kron(spark, 10, 16).edges, "kron"))


def _stored(g: Graph) -> Graph:
    """A graph whose edges are written once, bucketed by source, as every traversal joins them there many times."""
    return bucketed(g)


def _ids(df: DataFrame, id_) -> DataFrame:
    return df.select(id_.cast("bigint").alias("id")).distinct()


KRON_SOURCE = "(SELECT min(id) FROM (SELECT src AS id, count(*) AS g FROM e GROUP BY 1) WHERE g = (SELECT min(g) FROM (SELECT count(*) AS g FROM e GROUP BY src)))"


def _kron_source(g: Graph) -> int:
    return g.out_degrees().orderBy("degree", "id").first().id


# --- products -------------------------------------------------------------------------------------

PART_X = "x AS (SELECT 2 * p_partkey + 1 AS id, CAST(p_size AS DOUBLE) AS val FROM part)"


def _part_x(spark, sf):
    return T.load(spark, sf, "part").select((2 * F.col("p_partkey") + 1).alias("id"), F.col("p_size").cast("double").alias("val"))


W_ORDPART = "p AS MATERIALIZED (SELECT 2 * l_orderkey AS src, 2 * l_partkey + 1 AS dst, CAST(sum(CAST(l_quantity AS BIGINT)) AS DOUBLE) AS val FROM lineitem GROUP BY 1, 2), e AS MATERIALIZED (SELECT src, dst, val FROM p UNION ALL SELECT dst, src, val FROM p), vx AS (SELECT DISTINCT src AS id FROM e)"


@register("row_mxv_plus_times", f"WITH {W_ORDPART}, {PART_X} SELECT vx.id, coalesce(s, 0) AS val FROM vx LEFT JOIN (SELECT e.dst AS id, sum(e.val * x.val) AS s FROM e JOIN x ON x.id = e.src GROUP BY 1) USING (id)")
def _(spark, sf):
    return K.row_mxv(T.ordpart(spark, sf, True), _part_x(spark, sf), S.PLUS_TIMES)


MASK_CUST = "mk AS (SELECT 2 * c_custkey AS id, CAST(c_nationkey AS BIGINT) AS mval FROM customer WHERE c_nationkey < 5)"


def _mask_cust(spark, sf):
    return T.load(spark, sf, "customer").filter("c_nationkey < 5").select((2 * F.col("c_custkey")).alias("id"), F.col("c_nationkey").cast("bigint").alias("mval"))


ROWS_CUST = f"WITH {Q.graph('g_custpart')}, {PART_X}, {MASK_CUST} SELECT e.dst AS id, sum(x.val) AS val FROM e JOIN x ON x.id = e.src"


@register("row_masked_mxv", ROWS_CUST + " WHERE e.dst IN (SELECT id FROM mk) GROUP BY 1")
def _(spark, sf):
    return K.row_masked_mxv(T.custpart(spark, sf), _part_x(spark, sf), _mask_cust(spark, sf).select("id"), S.PLUS_TIMES)


@register("row_masked_mxv_complement", ROWS_CUST + " WHERE e.dst NOT IN (SELECT id FROM mk) GROUP BY 1")
def _(spark, sf):
    return K.row_masked_mxv(T.custpart(spark, sf), _part_x(spark, sf), _mask_cust(spark, sf).select("id"), S.PLUS_TIMES, True)


@register("row_masked_early_exit", f"WITH {Q.graph('g_word')} SELECT DISTINCT e.dst AS id FROM e JOIN labels ON labels.doc_id = e.src WHERE quality = 1 AND e.dst NOT IN (SELECT doc_id FROM labels)")
def _(spark, sf):
    lab = T.load(spark, sf, "labels")
    return K.row_masked_mxv(_stored(T.word(spark, sf)), _ids(lab.filter("quality = 1"), F.col("doc_id")).withColumn("val", F.lit(True)), _ids(lab, F.col("doc_id")), S.OR_AND, True, MatvecOptions(early_exit=True)).select("id")


@register("row_segment_waves", SQL["row_masked_early_exit"])
def _(spark, sf):
    from .layout import segment

    g, lab = _stored(T.word(spark, sf)), T.load(spark, sf, "labels")
    table = persist(segment(g), "segments")
    hit = K.probe_waves(g, _ids(lab.filter("quality = 1"), F.col("doc_id")), _ids(lab, F.col("doc_id")), "left_anti", MatvecOptions(), table, table.agg(F.max("seg")).first()[0])
    return hit.select("id").distinct()


@register("col_mxv_min_plus", f"WITH {W_ORDPART}, {PART_X} SELECT e.dst AS id, min(e.val + x.val) AS val FROM e JOIN x ON x.id = e.src GROUP BY 1")
def _(spark, sf):
    return K.col_mxv(T.ordpart(spark, sf, True), _part_x(spark, sf), S.MIN_PLUS)


COL_WORD = f"WITH {Q.graph('g_word')} SELECT DISTINCT e.dst AS id FROM e JOIN labels ON labels.doc_id = e.src WHERE toxic = 1"
SEEN_WORD = " AND e.dst NOT IN (SELECT e.dst FROM e WHERE e.src < 10)"


def _toxic(spark, sf):
    return _ids(T.load(spark, sf, "labels").filter("toxic = 1"), F.col("doc_id")).withColumn("val", F.lit(True))


def _near_first(g):
    return g.pattern().filter("src < 10").select(F.col("dst").alias("id")).distinct()


@register("col_masked_mxv", COL_WORD + SEEN_WORD)
def _(spark, sf):
    g = _stored(T.word(spark, sf))
    return K.col_masked_mxv(g, _toxic(spark, sf), _near_first(g), S.OR_AND, True).select("id")


@register("col_masked_mxv_pre", COL_WORD + SEEN_WORD)
def _(spark, sf):
    g = _stored(T.word(spark, sf))
    return K.col_masked_mxv(g, _toxic(spark, sf), _near_first(g), S.OR_AND, True, MatvecOptions(mask_placement="pre")).select("id")


@register("col_mxv_struct_only", COL_WORD)
def _(spark, sf):
    return K.col_mxv(T.word(spark, sf), _toxic(spark, sf), S.OR_AND, MatvecOptions(structure_only=True)).select("id")


@register("col_mxv_merge_sort", f"WITH {Q.graph('g_custpart')}, {PART_X} SELECT e.dst AS id, sum(x.val) AS val FROM e JOIN x ON x.id = e.src GROUP BY 1")
def _(spark, sf):
    return K.col_mxv(T.custpart(spark, sf), _part_x(spark, sf), S.PLUS_TIMES, MatvecOptions(merge="sort"))


@register("col_mxv_merge_none", f"WITH {Q.graph('g_custpart')}, {PART_X} SELECT e.dst AS id, x.val AS val FROM e JOIN x ON x.id = e.src")
def _(spark, sf):
    return K.col_mxv(T.custpart(spark, sf), _part_x(spark, sf), S.MAX_TIMES, MatvecOptions(merge="none"))


for _name, _sr, _agg in (("max_second", S.MAX_SECOND, "max(x.val)"), ("plus_pair", S.PLUS_PAIR, "count(*)"), ("min_first", S.MIN_FIRST, "min(x.val)"), ("bitor_and", S.BITOR_AND, "bit_or(x.val)")):

    def _semiring_query(spark, sf, sr=_sr):
        x = T.load(spark, sf, "part").select((2 * F.col("p_partkey") + 1).alias("id"), F.col("p_size").cast("bigint").alias("val"))
        return K.col_mxv(T.custpart(spark, sf), x, sr)

    register(f"col_mxv_{_name}", f"WITH {Q.graph('g_custpart')}, x AS (SELECT 2 * p_partkey + 1 AS id, CAST(p_size AS BIGINT) AS val FROM part) SELECT e.dst AS id, {_agg} AS val FROM e JOIN x ON x.id = e.src GROUP BY 1")(_semiring_query)


@register("matvec_accumulate", f"WITH {W_ORDPART}, {PART_X}, w AS (SELECT 2 * o_orderkey AS id, CAST(o_custkey AS DOUBLE) AS val FROM orders), y AS (SELECT e.dst AS id, sum(e.val * x.val) AS val FROM e JOIN x ON x.id = e.src GROUP BY 1) SELECT coalesce(w.id, y.id) AS id, coalesce(w.val, 0) + coalesce(y.val, 0) AS val FROM w FULL JOIN y ON w.id = y.id")
def _(spark, sf):
    out = T.load(spark, sf, "orders").select((2 * F.col("o_orderkey")).alias("id"), F.col("o_custkey").cast("double").alias("val"))
    return K.matvec(T.ordpart(spark, sf, True), _part_x(spark, sf), S.PLUS_TIMES, direction="push", accum=True, out=out).vector


@register("matvec_auto_direction", ROWS_CUST + " WHERE e.dst IN (SELECT id FROM mk) GROUP BY 1")
def _(spark, sf):
    return K.matvec(T.custpart(spark, sf), _part_x(spark, sf), S.PLUS_TIMES, mask=_mask_cust(spark, sf).select("id")).vector


@register("matvec_mask_values", f"WITH {Q.graph('g_custpart')}, {PART_X}, {MASK_CUST}, y AS (SELECT e.dst AS id, sum(x.val) AS val FROM e JOIN x ON x.id = e.src GROUP BY 1) SELECT id, val * mval AS val FROM y JOIN mk USING (id) WHERE mval <> 0")
def _(spark, sf):
    mask = _mask_cust(spark, sf)
    y = K.row_masked_mxv(T.custpart(spark, sf), _part_x(spark, sf), mask, S.PLUS_TIMES, opts=MatvecOptions(mask_identity=0))
    return K.mask_values(y, mask, lambda v, m: v * m)


NATION_U = "(SELECT CAST(c_nationkey AS BIGINT) AS id, count(*) AS val FROM customer GROUP BY 1)"
NATION_W = "(SELECT CAST(s_nationkey AS BIGINT) AS id, count(*) AS val FROM supplier GROUP BY 1)"


def _nation(spark, sf, table, key):
    return T.load(spark, sf, table).groupBy(F.col(key).cast("bigint").alias("id")).agg(F.count("*").alias("val"))


@register("ewise_mult", f"SELECT u.id, u.val * w.val AS val FROM {NATION_U} u JOIN {NATION_W} w ON u.id = w.id")
def _(spark, sf):
    return V.ewise_mult(_nation(spark, sf, "customer", "c_nationkey"), _nation(spark, sf, "supplier", "s_nationkey"), S.COUNT_TIMES)


@register("ewise_add", f"SELECT coalesce(u.id, w.id) AS id, coalesce(u.val, 0) + coalesce(w.val, 0) AS val FROM {NATION_U} u FULL JOIN {NATION_W} w ON u.id = w.id")
def _(spark, sf):
    return V.ewise_add(_nation(spark, sf, "customer", "c_nationkey"), _nation(spark, sf, "supplier", "s_nationkey"), S.COUNT_TIMES)


@register("vector_reduce", f"SELECT CAST(sum(val) AS BIGINT) AS val FROM {NATION_U}")
def _(spark, sf):
    return V.reduce(_nation(spark, sf, "customer", "c_nationkey"), S.COUNT_TIMES)


@register("vector_assign", "SELECT doc_id AS id, 0 AS depth FROM labels WHERE toxic = 1 UNION ALL SELECT doc_id, 1 FROM labels WHERE toxic = 0")
def _(spark, sf):
    lab = T.load(spark, sf, "labels")
    return V.assign(lab.filter("toxic = 1").select(F.col("doc_id").alias("id"), F.lit(0).alias("depth")), lab.filter("toxic = 0").select(F.col("doc_id").alias("id")), 1)


@register("convert_roundtrip", "SELECT DISTINCT doc_id AS id FROM labels")
def _(spark, sf):
    return V.unpack_words(V.pack_words(_ids(T.load(spark, sf, "labels"), F.col("doc_id"))))


@register("convert_dense", "SELECT doc_id AS id, coalesce(q, 0) AS val FROM documents LEFT JOIN (SELECT doc_id, CAST(max(quality) AS BIGINT) AS q FROM labels GROUP BY 1) USING (doc_id)")
def _(spark, sf):
    q = T.load(spark, sf, "labels").groupBy(F.col("doc_id").alias("id")).agg(F.max("quality").cast("bigint").alias("val"))
    return V.to_dense(q, T.load(spark, sf, "documents", "doc_id").withColumnRenamed("doc_id", "id"), S.COUNT_TIMES)


@register("edge_count_set", f"WITH {Q.graph('g_word')} SELECT count(*) AS n FROM e WHERE src IN (SELECT doc_id FROM labels WHERE toxic = 1)")
def _(spark, sf):
    return C.edge_count(T.word(spark, sf), _ids(T.load(spark, sf, "labels").filter("toxic = 1"), F.col("doc_id")))


@register("balanced_expand", f"WITH {Q.graph('g_custpart')} SELECT src, dst FROM e WHERE src IN (SELECT 2 * c_custkey FROM customer WHERE c_nationkey < 5)")
def _(spark, sf):
    return K.balanced_expand(T.custpart(spark, sf), _mask_cust(spark, sf)).select("src", "dst")


# --- traversal ------------------------------------------------------------------------------------

BFS_ORD, BFS_WORD = Q.bfs("g_ordpart", "1"), Q.bfs("g_word", "0")


def _bfs_query(graph, source, rule, opts=BfsOptions()):
    return lambda spark, sf: X.bfs(_stored(graph(spark, sf)), source, rule(), opts).levels.select("id", "depth")


register("bfs_switching", BFS_WORD)(_bfs_query(T.word, 0, RatioRule))
register("bfs_push", BFS_ORD)(_bfs_query(T.ordpart, 1, PushOnly))
register("bfs_pull", BFS_ORD)(_bfs_query(T.ordpart, 1, PullOnly))
register("bfs_pull_unmasked", BFS_ORD)(_bfs_query(T.ordpart, 1, PullOnly, BfsOptions(mask=False, operand_reuse=False)))
register("bfs_pull_masked_no_exit", BFS_ORD)(_bfs_query(T.ordpart, 1, PullOnly, BfsOptions(early_exit=False, operand_reuse=False)))
register("bfs_operand_reuse", BFS_WORD)(_bfs_query(T.word, 0, RatioRule, BfsOptions(operand_reuse=True)))
register("bfs_no_operand_reuse", BFS_WORD)(_bfs_query(T.word, 0, RatioRule, BfsOptions(operand_reuse=False)))
register("bfs_struct_only", BFS_ORD)(_bfs_query(T.ordpart, 1, PushOnly, BfsOptions(structure_only=True, merge="sort")))
register("bfs_key_value", BFS_ORD)(_bfs_query(T.ordpart, 1, PushOnly, BfsOptions(structure_only=False)))
register("bfs_bytes_rule", BFS_ORD)(_bfs_query(T.ordpart, 1, BytesRule))
register("bfs_schedule", BFS_ORD)(_bfs_query(T.ordpart, 1, lambda: Schedule(["push", "push", "pull", "pull", "pull", "push"])))
register("bfs_duplicates_kept", BFS_ORD)(_bfs_query(T.ordpart, 1, PushOnly, BfsOptions(merge="none", mask_placement="pre")))
register("bfs_segment_waves", BFS_WORD)(_bfs_query(T.word, 0, RatioRule, BfsOptions(waves=True)))
register("bfs_block_join", BFS_WORD)(_bfs_query(T.word, 0, RatioRule, BfsOptions(broadcast_bytes=0)))
register("bfs_capped", Q.bfs("g_ladder", "(SELECT event_id FROM events ORDER BY user_id, ts, event_id LIMIT 1)", 20))(
    lambda spark, sf: X.bfs(_stored(T.ladder(spark, sf)), T.load(spark, sf, "events").orderBy("user_id", "ts", "event_id").first().event_id, RatioRule(), BfsOptions(max_depth=20)).levels.select("id", "depth")
)


@register("bfs_parents", f"WITH RECURSIVE {Q.graph('g_partsupp')}, {Q.levels('1', 10)} SELECT lv.id, lv.depth, min(up.id) AS parent FROM lv LEFT JOIN e ON e.dst = lv.id LEFT JOIN lv up ON up.id = e.src AND up.depth = lv.depth - 1 GROUP BY 1, 2")
def _(spark, sf):
    return X.bfs(_stored(T.partsupp(spark, sf)), 1, RatioRule(), BfsOptions(with_parent=True)).levels


@register("bfs_parents_push", SQL["bfs_parents"])
def _(spark, sf):
    return X.bfs(_stored(T.partsupp(spark, sf)), 1, PushOnly(), BfsOptions(with_parent=True)).levels


@register("bfs_labels", f"WITH RECURSIVE {Q.graph('g_geo')}, {Q.levels('0', 10)} SELECT vx.id, CAST(coalesce(depth + 1, 0) AS INTEGER) AS label FROM vx LEFT JOIN lv USING (id)")
def _(spark, sf):
    g = _stored(T.geo(spark, sf))
    return X.labels(X.bfs(g, 0, PushOnly()), g)


MULTI = f"WITH RECURSIVE {Q.graph('g_geo')}, r(source, id, depth) AS (SELECT CAST(r_regionkey AS BIGINT), CAST(r_regionkey AS BIGINT), 0 FROM region UNION SELECT r.source, e.dst, r.depth + 1 FROM r JOIN e ON e.src = r.id WHERE r.depth < 8), lv AS (SELECT source, id, CAST(min(depth) AS INTEGER) AS depth FROM r GROUP BY 1, 2)"


def _regions(spark, sf):
    return T.load(spark, sf, "region").select(F.col("r_regionkey").cast("bigint").alias("id"))


@register("bfs_multi_source", MULTI + " SELECT source, id, depth FROM lv")
def _(spark, sf):
    return X.bfs_multi(_stored(T.geo(spark, sf)), _regions(spark, sf))


@register("bfs_packed_words", MULTI + ", s AS (SELECT source, row_number() OVER (ORDER BY source) - 1 AS i FROM (SELECT DISTINCT source FROM lv)) SELECT id, depth, bit_or(CAST(1 AS BIGINT) << CAST(i AS INTEGER)) AS bits FROM lv JOIN s USING (source) GROUP BY 1, 2")
def _(spark, sf):
    return X.bfs_packed(_stored(T.geo(spark, sf)), [0, 1, 2, 3, 4])


TRACE_KRON = Q.trace("g_kron10", KRON_SOURCE, 10)
TRACE_WORD = Q.trace("g_word", "0", 12)
TRACE_ORD = Q.trace("g_ordpart", "1", 12)


def _trace(g: Graph, source: int) -> DataFrame:
    return persist(C.trace(g, persist(X.bfs(g, source).levels)), "trace")


def _kron_trace(spark):
    g = _kron(spark)
    return _trace(g, _kron_source(g))


@register("bfs_trace", TRACE_KRON + f", {Q.directions()} SELECT iter, nnz_f, nnz_u, r, out_edges_f, in_edges_u, parents_checked, direction FROM dr")
def _(spark, sf):
    return C.ratio_directions(_kron_trace(spark))


@register("bfs_trace_driver", TRACE_KRON + f", {Q.directions()} SELECT iter, nnz_f, nnz_u, out_edges_f, in_edges_u, parents_checked, direction FROM dr")
def _(spark, sf):
    g = _kron(spark)
    return X.bfs(g, _kron_source(g), RatioRule(), count=True).trace_table(spark).select("iter", "nnz_f", "nnz_u", "out_edges_f", "in_edges_u", "parents_checked", "direction")


@register("heuristic_edge_vs_ratio", TRACE_WORD + f", {Q.directions()} SELECT iter, direction AS ratio_rule, out_edges_f > 0.01 * in_edges_u AS edge_rule_pulls, CASE WHEN parents_checked < out_edges_f THEN 'pull' ELSE 'push' END AS best FROM dr")
def _(spark, sf):
    t = C.ratio_directions(_trace(_stored(T.word(spark, sf)), 0))
    return t.select("iter", F.col("direction").alias("ratio_rule"), (F.col("out_edges_f") > 0.01 * F.col("in_edges_u")).alias("edge_rule_pulls"), F.when(F.col("parents_checked") < F.col("out_edges_f"), "pull").otherwise("push").alias("best"))


@register("cost_early_exit", TRACE_WORD + " SELECT iter, round(parents_checked / nnz_u, 6) AS parents_per_vertex FROM tr WHERE nnz_u > 0")
def _(spark, sf):
    return W.parents_curve(_trace(_stored(T.word(spark, sf)), 0))


def _ablation_sql(head: str) -> str:
    return head + f""", {Q.directions()}, s AS (SELECT sum(out_edges_f) AS a0, sum(CASE direction WHEN 'pull' THEN (SELECT in_edges_u + out_edges_f FROM tr WHERE iter = 1) ELSE out_edges_f END) AS a2,
 sum(CASE direction WHEN 'pull' THEN in_edges_u ELSE out_edges_f END) AS a3, sum(CASE direction WHEN 'pull' THEN parents_checked ELSE out_edges_f END) AS a4, sum(CASE direction WHEN 'pull' THEN 0 ELSE out_edges_f END) AS p, sum(CASE direction WHEN 'pull' THEN nnz_f ELSE 0 END) AS q FROM dr)
SELECT step, stack, CAST(accesses AS BIGINT) AS accesses, CAST(words AS BIGINT) AS words FROM (SELECT 0 AS step, 'baseline' AS stack, a0 AS accesses, 2 * a0 AS words FROM s UNION ALL SELECT 1, 'structure only', a0, a0 FROM s UNION ALL SELECT 2, 'change of direction', a2, p + q FROM s UNION ALL SELECT 3, 'masking', a3, p + q FROM s UNION ALL SELECT 4, 'early exit', a4, p + q FROM s UNION ALL SELECT 5, 'operand reuse', a4, p FROM s)"""


@register("ablation_accesses", _ablation_sql(TRACE_WORD))
def _(spark, sf):
    return C.ablation(_trace(_stored(T.word(spark, sf)), 0))


@register("ablation_accesses_kron", _ablation_sql(TRACE_KRON))
def _(spark, sf):
    return C.ablation(_kron_trace(spark))


@register(
    "heuristic_regret",
    TRACE_ORD + "".join(f", {Q.directions(str(a), str(a), f'd{i}')}" for i, a in enumerate(W.ALPHAS)) + " " + " UNION ALL ".join(
        f"SELECT CAST({a} AS DOUBLE) AS alpha, accesses, best, round(accesses / best - 1, 6) AS regret FROM (SELECT CAST(sum(CASE direction WHEN 'pull' THEN parents_checked ELSE out_edges_f END) AS BIGINT) AS accesses, CAST(sum(least(parents_checked, out_edges_f)) AS BIGINT) AS best FROM d{i})" for i, a in enumerate(W.ALPHAS)
    ),
)
def _(spark, sf):
    return C.regret(_trace(_stored(T.ordpart(spark, sf)), 1), W.ALPHAS)


# --- cost and microbenchmarks ---------------------------------------------------------------------

SIZES = [1, 4, 16, 64, 256, 800]
SAMPLE = "(SELECT id, row_number() OVER (ORDER BY ((id % 2147483647) * 48271) % 2147483647, id) AS n FROM vx)"


def _micro_sql(variant: str, side: str, name: str = "g_kron10") -> str:
    total = "SELECT count(*) FROM e" if variant == "row" else f"SELECT count(*) FROM e JOIN smp ON smp.id = e.{side} WHERE smp.n <= z.size"
    return f"WITH RECURSIVE {Q.graph(name)}, smp AS MATERIALIZED {SAMPLE} SELECT '{variant}' AS variant, CAST(z.size AS BIGINT) AS size, ({total}) AS accesses FROM (SELECT unnest({SIZES}) AS size) z"


register("micro_row", _micro_sql("row", "src", "g_partsupp"))(lambda spark, sf: W.micro(_stored(T.partsupp(spark, sf)), "row", SIZES))
for _variant, _side in (("row_masked", "dst"), ("col", "src"), ("col_masked", "src")):
    register(f"micro_{_variant}", _micro_sql(_variant, _side))(lambda spark, sf, v=_variant: W.micro(_kron(spark), v, SIZES))


@register("micro_crossover", _micro_sql("col", "src").replace("SELECT 'col'", ", z1 AS (SELECT 'col'", 1).replace(str(SIZES), str(W.sizes_of(875))) + ") SELECT min(size) AS size FROM z1 WHERE accesses * greatest(1, log2(size)) > (SELECT count(*) FROM e)")
def _(spark, sf):
    """Where the column product with its merge (accesses times the logarithm of the lists) overtakes the row product, over sizes up to all vertices."""
    g = _kron(spark)
    sizes = W.sizes_of(g.M)
    return W.crossover(W.micro(g, "col", sizes).withColumn("accesses", F.col("accesses") * F.greatest(F.lit(1.0), F.log2("size"))), W.micro(g, "row", sizes))


SAMPLE_1 = SAMPLE.replace("48271) %", "48271 + 1000003) %")
_MICRO = {  # outputs of each variant at size z.size
    "row": "SELECT DISTINCT e.dst AS id FROM e JOIN smp ON smp.id = e.src WHERE smp.n <= z.size", "row_masked": "SELECT DISTINCT e.dst AS id FROM e JOIN smp ON smp.id = e.dst WHERE smp.n <= z.size",
    "col": "SELECT DISTINCT e.dst AS id FROM e JOIN smp ON smp.id = e.src WHERE smp.n <= z.size",
    "col_masked": "SELECT DISTINCT e.dst AS id FROM e JOIN smp ON smp.id = e.src JOIN sm1 ON sm1.id = e.dst WHERE smp.n <= z.size AND sm1.n <= greatest(1, 2 * z.size // 3)",
}


@register(
    "micro_products",
    f"WITH RECURSIVE {Q.graph('g_kron10')}, smp AS MATERIALIZED {SAMPLE}, sm1 AS MATERIALIZED {SAMPLE_1}, z AS (SELECT unnest({[1, 32, 256, 875]}) AS size) "
    + " UNION ALL ".join(f"SELECT '{v}' AS variant, CAST(z.size AS BIGINT) AS size, (SELECT count(*) FROM ({q})) AS n, CAST((SELECT coalesce(sum(id), 0) FROM ({q})) AS BIGINT) AS total FROM z" for v, q in _MICRO.items()),
)
def _(spark, sf):
    return W.micro_products(_kron(spark), [1, 32, 256, 875])


@register(
    "micro_merge",
    f"WITH RECURSIVE {Q.graph('g_kron10')}, smp AS MATERIALIZED {SAMPLE}, z AS (SELECT unnest([4, 64, 800]) AS size), c AS (SELECT z.size, (SELECT count(*) FROM e JOIN smp ON smp.id = e.src WHERE smp.n <= z.size) AS n, (SELECT count(*) FROM vx) AS m FROM z) "
    "SELECT 'kway' AS kind, CAST(size AS BIGINT) AS size, n, round(n * log2(CAST(size AS DOUBLE)), 4) AS work, 2 * n AS words FROM c UNION ALL SELECT 'radix', size, n, round(n * log2(CAST(m AS DOUBLE)), 4), 2 * n FROM c UNION ALL SELECT 'none', size, n, round(CAST(n AS DOUBLE), 4), n FROM c",
)
def _(spark, sf):
    return W.micro_merge(_kron(spark), [4, 64, 800])


@register(
    "cost_table1",
    f"WITH RECURSIVE {Q.graph('g_kron10')}, smp AS MATERIALIZED {SAMPLE}, c AS (SELECT count(*) AS nnz, (SELECT count(*) FROM vx) AS m, count(*) FILTER (src IN (SELECT id FROM smp WHERE n <= 64)) AS c4, count(*) FILTER (dst IN (SELECT id FROM smp WHERE n <= 256)) AS c2 FROM e) "
    "SELECT 'row' AS variant, nnz AS measured, round(nnz / m * m, 4) AS expected FROM c UNION ALL SELECT 'row masked', c2, round(nnz / m * 256, 4) FROM c UNION ALL SELECT 'column', c4, round(nnz / m * 64 * log2(64.0::DOUBLE), 4) FROM c UNION ALL SELECT 'column masked', c4, round(nnz / m * 64 * log2(64.0::DOUBLE), 4) FROM c",
)
def _(spark, sf):
    g = _kron(spark)
    return C.table1(g, G.sample_vertices(g, 64), G.sample_vertices(g, 256))


TRACES = """rk AS MATERIALIZED (SELECT src, dst, row_number() OVER (PARTITION BY dst ORDER BY src) AS place FROM e), dg AS MATERIALIZED (SELECT src AS id, count(*) AS g FROM e GROUP BY 1),
 ft AS (SELECT a.source, k.dst AS id, min(k.place) AS first FROM rk k JOIN lv a ON a.id = k.src JOIN lv t ON t.source = a.source AND t.id = k.dst WHERE a.depth = t.depth - 1 GROUP BY 1, 2),
 b AS (SELECT lv.source, lv.depth, count(*) AS n, sum(g) AS ins, coalesce(sum(first), 0) AS firsts FROM lv JOIN dg USING (id) LEFT JOIN ft ON ft.source = lv.source AND ft.id = lv.id GROUP BY 1, 2),
 st AS (SELECT source, depth + 1 AS iter, n AS nnz_f, CAST((SELECT count(*) FROM vx) - sum(n) OVER w AS BIGINT) AS nnz_u, CAST(ins AS BIGINT) AS out_edges_f, CAST((SELECT count(*) FROM e) - sum(ins) OVER w AS BIGINT) AS in_edges_u,
  CAST((SELECT count(*) FROM e) - sum(ins) OVER w - coalesce(lead(ins) OVER w, 0) + coalesce(lead(firsts) OVER w, 0) AS BIGINT) AS parents_checked FROM b WINDOW w AS (PARTITION BY source ORDER BY depth))"""


def _many(sources: str, bound: int) -> str:
    return f"r(source, id, depth) AS ({sources} UNION SELECT r.source, e.dst, r.depth + 1 FROM r JOIN e ON e.src = r.id WHERE r.depth < {bound}), lv AS MATERIALIZED (SELECT source, id, min(depth) AS depth FROM r GROUP BY 1, 2)"


@register("sample_sources", f"WITH RECURSIVE {Q.graph('g_kron10')}, smp AS {SAMPLE}, {_many('SELECT id, id, 0 FROM smp WHERE n <= 1000', 6)}, {TRACES} SELECT * FROM st")
def _(spark, sf):
    """1000 sampled sources (this graph has 875): cost of push and of pull at every level of every search."""
    return W.sample_sources(_kron(spark), 1000)


@register("demo_one_step", f"WITH RECURSIVE {Q.graph('g_partsupp')}, {Q.levels('1', 2)} SELECT m AS method, id FROM (VALUES ('push'), ('pull'), ('pull early exit'), ('pull reuse')) a(m), lv WHERE depth = 2")
def _(spark, sf):
    return W.one_step(spark, _stored(T.partsupp(spark, sf)), 1)


@register("generality_mask_gain", f"WITH {Q.graph('g_custpart')}, {MASK_CUST} SELECT masked, unmasked, round(unmasked / masked, 6) AS ratio, round((SELECT count(*) FROM vx) / (SELECT count(*) FROM mk WHERE id IN (SELECT id FROM vx)), 6) AS bound FROM (SELECT count(*) FILTER (dst IN (SELECT id FROM mk)) AS masked, count(*) AS unmasked FROM e)")
def _(spark, sf):
    g = T.custpart(spark, sf)
    return W.generality(g, _mask_cust(spark, sf).select("id").join(g.vertices(), "id", "left_semi"))


def _generality_sql() -> str:
    five = "SELECT CAST(2 * s_suppkey + 1 AS BIGINT) AS id, CAST(2 * s_suppkey + 1 AS BIGINT) AS source, 0 FROM supplier WHERE s_suppkey < 8"
    ins = f"(WITH {Q.graph('g_partsupp')} SELECT dst AS id, count(*) AS degree FROM e GROUP BY 1)"
    ranks = f"SELECT 'adaptive ranks' AS algorithm, sum(coalesce(frozen_at, 6) * degree) AS masked, 6 * sum(degree) AS unmasked, count(*) * 6 / sum(coalesce(frozen_at, 6)) AS bound FROM ({Q.pagerank_adaptive('g_partsupp', 6, 0.05)}) JOIN {ins} USING (id)"
    tri = f"""(WITH {Q.graph('g_copurchase')}, dg AS MATERIALIZED (SELECT src AS id, count(*) AS g FROM e GROUP BY 1), o AS MATERIALIZED (SELECT e.src AS a, e.dst AS b FROM e JOIN dg x ON x.id = e.src JOIN dg y ON y.id = e.dst WHERE (x.g, e.src) < (y.g, e.dst)),
 n AS (SELECT a, count(*) AS n FROM o GROUP BY 1) SELECT 'triangles' AS algorithm, (SELECT sum(n) FROM o JOIN n ON n.a = o.b) AS masked, count(*) AS unmasked, count(DISTINCT (x.a, y.b)) / (SELECT count(*) FROM o) AS bound FROM o x JOIN o y ON y.a = x.b)"""
    centre = f"(WITH RECURSIVE {Q.graph('g_partsupp')}, {_many(five.replace('AS id, CAST', 'AS source, CAST').replace('AS source, 0', 'AS id, 0'), 8)}, {TRACES} SELECT 'batched centrality' AS algorithm, sum(in_edges_u) AS masked, count(*) * (SELECT count(*) FROM e) AS unmasked, count(*) * (SELECT count(*) FROM vx) / sum(nnz_u) AS bound FROM st)"
    rounds = " UNION ALL ".join(f"SELECT sum(g) AS d, count(*) AS n FROM c{i} JOIN dg USING (id)" for i in range(12))
    mis = "(" + Q.mis("g_partsupp", 12, f", dg AS (SELECT src AS id, count(*) AS g FROM e GROUP BY 1), t AS ({rounds}) SELECT 'independent set' AS algorithm, sum(d) AS masked, count(*) * (SELECT count(*) FROM e) AS unmasked, count(*) * (SELECT count(*) FROM vx) / sum(n) AS bound FROM t WHERE n > 0") + ")"
    layer = f"(WITH {_X} SELECT 'sparse layers' AS algorithm, (SELECT sum(n) FROM x y JOIN (SELECT i, count(*) AS n FROM x GROUP BY 1) USING (i) WHERE y.j < 8) AS masked, count(*) AS unmasked, count(DISTINCT (x.i, w.j)) / (SELECT count(*) FROM x WHERE j < 8) AS bound FROM x JOIN w ON w.i = x.j)"
    both = " UNION ALL ".join(f"SELECT * FROM {p}" for p in (f"({ranks})", tri, centre, mis, layer))
    return f"SELECT algorithm, CAST(masked AS BIGINT) AS masked, CAST(unmasked AS BIGINT) AS unmasked, round(unmasked / masked, 6) AS ratio, round(bound, 6) AS bound FROM ({both})"


DESCRIBED = ["g_ordpart", "g_custpart", "g_partsupp", "g_copurchase", "g_word", "g_geo", "g_custorder", "g_userkey", "g_chain", "g_ladder", "g_pages", "g_conv", "g_toy"]


def _describe_sql(name: str) -> str:
    return f"SELECT '{name}' AS graph, count(*) AS v, CAST(sum(g) AS BIGINT) AS e, max(g) AS max_degree, round(avg(g), 6) AS mean_degree FROM (WITH RECURSIVE {Q.graph(name)} SELECT src, count(*) AS g FROM e GROUP BY 1)"


@register("graph_describe", " UNION ALL ".join(map(_describe_sql, DESCRIBED)))
def _(spark, sf):
    out = None
    for name in DESCRIBED:
        one = W.describe(name, T.GRAPHS[name](spark, sf))
        out = one if out is None else out.unionByName(one)
    return out


@register("graph_canonicalize", Q.graph("g_ordpart").join(["WITH ", " SELECT src, dst FROM e"]))
def _(spark, sf):
    return T.ordpart(spark, sf).edges


_RAW = Q.PAIRS["g_ordpart"]


@register("graph_canonicalize_report", f"WITH p AS ({_RAW}) SELECT '0 input' AS step, count(*) AS n FROM p UNION ALL SELECT '1 no nulls', count(*) FROM p WHERE src IS NOT NULL AND dst IS NOT NULL UNION ALL SELECT '2 no loops', count(*) FROM p WHERE src <> dst UNION ALL SELECT '3 both ways', 2 * count(*) FROM p WHERE src <> dst UNION ALL SELECT '4 distinct', count(*) FROM (SELECT src, dst FROM p WHERE src <> dst UNION SELECT dst, src FROM p WHERE src <> dst)")
def _(spark, sf):
    return canonicalize_report(edges_from_pairs(T.load(spark, sf, "lineitem"), T.even("l_orderkey"), T.odd("l_partkey")))


@register("recursive_matrix_edges", Q.kron_pairs(8, "(SELECT event_id FROM events)"))
def _(spark, sf):
    """Each event draws one pair."""
    return G.recursive_pairs_of(T.load(spark, sf, "events").select(F.col("event_id").alias("id")), 8)


@register("random_geometric", "WITH p AS (SELECT c_custkey AS x, CAST(floor(c_acctbal) AS BIGINT) AS y FROM customer) SELECT count(*) AS pairs FROM p a JOIN p b ON b.x >= a.x - 100 AND b.x <= a.x + 100 AND a.x <> b.x AND (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= 10000")
def _(spark, sf):
    """Customers as points: keys run along one side, balances along the other."""
    points = T.load(spark, sf, "customer").select(F.col("c_custkey").alias("id"), F.col("c_custkey").alias("x"), F.floor("c_acctbal").cast("bigint").alias("y"))
    return G.geometric(points, 100).edges.agg(F.count("*").alias("pairs"))


# --- algorithms -----------------------------------------------------------------------------------

KNN_W = Q.PAIRS["g_knn"].replace("weight AS val", "CAST(weight AS DOUBLE) AS val", 1)
ORD_W = "SELECT 2 * l_orderkey AS src, 2 * l_partkey + 1 AS dst, CAST(sum(CAST(l_quantity AS BIGINT)) AS DOUBLE) AS val FROM lineitem GROUP BY 1, 2"
register("sssp_bellman_ford", Q.sssp(ORD_W, "1", 24))(lambda spark, sf: A.sssp(_stored(T.ordpart(spark, sf, True)), 1, PushOnly()))
register("sssp_two_phase", Q.sssp(ORD_W, "1", 24))(lambda spark, sf: A.sssp(_stored(T.ordpart(spark, sf, True)), 1, TwoPhase()))
register("sssp_operand_reuse", Q.sssp(KNN_W, "0", 24))(lambda spark, sf: A.sssp(_stored(T.knn(spark, sf)), 0, PullOnly(), True))


def _ranked(df: DataFrame) -> DataFrame:
    return df.withColumn("rank", F.round("rank", 8))


register("pagerank", Q.pagerank("g_custpart", 5))(lambda spark, sf: _ranked(A.pagerank(_stored(T.custpart(spark, sf)), 0.85, 5).select("id", "rank")))
register("pagerank_grid", Q.pagerank("g_partsupp", 3))(lambda spark, sf: _ranked(A.pagerank(_stored(T.partsupp(spark, sf)), 0.85, 3, layout="grid").select("id", "rank")))
register("pagerank_adaptive", Q.pagerank_adaptive("g_partsupp", 6, 0.05))(lambda spark, sf: _ranked(A.pagerank(_stored(T.partsupp(spark, sf)), 0.85, 6, 0.05)))
register("personalized_pagerank", Q.personalized("g_partsupp", "SELECT 2 * s_suppkey + 1 AS id FROM supplier WHERE s_suppkey < 3", 5))(
    lambda spark, sf: _ranked(A.personalized_pagerank(_stored(T.partsupp(spark, sf)), T.load(spark, sf, "supplier").filter("s_suppkey < 3").select((2 * F.col("s_suppkey") + 1).alias("id")), 0.85, 5))
)
_EIGHT = "SELECT 2 * s_suppkey + 1 AS id FROM supplier WHERE s_suppkey < 8"


@register("betweenness_batch", Q.betweenness("g_partsupp", _EIGHT, 5))
def _(spark, sf):
    src = T.load(spark, sf, "supplier").filter("s_suppkey < 8").select((2 * F.col("s_suppkey") + 1).alias("id"))
    return A.betweenness(_stored(T.partsupp(spark, sf)), src, 8).withColumn("score", F.round("score", 6))


@register("betweenness", Q.betweenness("g_copurchase", "SELECT CAST(p_partkey AS BIGINT) AS id FROM part WHERE p_partkey < 4", 4))
def _(spark, sf):
    src = T.load(spark, sf, "part").filter("p_partkey < 4").select(F.col("p_partkey").cast("bigint").alias("id"))
    return A.betweenness(_stored(T.copurchase(spark, sf)), src, 1).withColumn("score", F.round("score", 6))


register("mis", Q.mis("g_partsupp", 12))(lambda spark, sf: A.mis(_stored(T.partsupp(spark, sf))))
register("components", f"WITH RECURSIVE {Q.graph('g_geo')}, r(id, root) AS (SELECT id, id FROM vx UNION SELECT e.dst, r.root FROM r JOIN e ON e.src = r.id WHERE r.root < e.dst) SELECT id, min(root) AS component FROM r GROUP BY id")(lambda spark, sf: A.components(_stored(T.geo(spark, sf))))
_TRI = f"WITH {Q.graph('g_copurchase')} SELECT x.src AS a, x.dst AS b, y.dst AS c FROM e x JOIN e y ON y.src = x.dst AND x.src < x.dst AND x.dst < y.dst JOIN e z ON z.src = x.src AND z.dst = y.dst"
register("triangle_list", _TRI.replace(Q.graph("g_copurchase"), Q.graph("g_knn")))(lambda spark, sf: M.triangles(_stored(T.knn(spark, sf))))
register("triangle_count", f"SELECT count(*) AS triangles FROM ({_TRI})")(lambda spark, sf: M.triangle_count(_stored(T.copurchase(spark, sf))))
register("triangle_count_unmasked", f"SELECT count(*) AS triangles FROM ({_TRI})")(lambda spark, sf: M.triangle_count_unmasked(_stored(T.copurchase(spark, sf))))

_A = "a AS (SELECT 2 * l_partkey AS i, 2 * l_suppkey + 1 AS j, CAST(count(*) AS BIGINT) AS val FROM lineitem GROUP BY 1, 2)"


def _counts(spark, sf):
    return T.load(spark, sf, "lineitem").groupBy((2 * F.col("l_partkey")).alias("i"), (2 * F.col("l_suppkey") + 1).alias("j")).agg(F.count("*").alias("val"))


def _transposed(a: DataFrame) -> DataFrame:
    return a.select(F.col("j").alias("i"), F.col("i").alias("j"), "val")


_MM = f"WITH {_A}, b AS (SELECT j AS i, i AS j, val FROM a), c AS (SELECT x.i, y.j, sum(x.val * y.val) AS val FROM b x JOIN a y ON y.i = x.j GROUP BY 1, 2) SELECT i, j, CAST(val AS BIGINT) AS val FROM c"
register("mxm", _MM)(lambda spark, sf: M.mxm(_transposed(_counts(spark, sf)), _counts(spark, sf), S.COUNT_TIMES))
register("mxm_masked", _MM + " WHERE i < j AND j < 40")(lambda spark, sf: _mxm_masked(spark, sf, False))
register("mxm_masked_complement", _MM + " WHERE NOT (i < j AND j < 40)")(lambda spark, sf: _mxm_masked(spark, sf, True))


def _mxm_masked(spark, sf, complement):
    ids = _counts(spark, sf).select("j").distinct().filter("j < 40")
    mask = ids.select(F.col("j").alias("i")).join(ids, F.col("i") < F.col("j"))
    return M.mxm(_transposed(_counts(spark, sf)), _counts(spark, sf), S.COUNT_TIMES, mask, complement)


def _layer_weights(spark, n: int) -> DataFrame:
    """Integer-derived sparse weights: every third entry of an n by n matrix."""
    return spark.range(n * n).select(F.floor(F.col("id") / n).alias("i"), (F.col("id") % n).alias("j"), ((F.col("id") * 37 % 11) - 5).cast("double").alias("val")).filter("(i + j) % 3 = 0 AND val <> 0")


_X = "x AS (SELECT CAST(vec_id AS BIGINT) AS i, CAST(k - 1 AS BIGINT) AS j, CAST(round(CAST(embedding[k] AS DOUBLE) * 1000) AS DOUBLE) AS val FROM embeddings, (SELECT unnest(range(1, 65)) AS k)), w AS (SELECT * FROM (SELECT id // 64 AS i, id % 64 AS j, CAST((id * 37 % 11) - 5 AS DOUBLE) AS val FROM range(4096) t(id)) WHERE (i + j) % 3 = 0 AND val <> 0)"


def _activations(spark, sf):
    return T.load(spark, sf, "embeddings").select(F.col("vec_id").cast("bigint").alias("i"), F.posexplode("embedding").alias("j", "v")).select("i", F.col("j").cast("bigint").alias("j"), F.round(F.col("v").cast("double") * 1000).alias("val"))


@register("generality_algorithms", _generality_sql())
def _(spark, sf):
    """The gain of masks in all five algorithms that have one."""
    src = T.load(spark, sf, "supplier").filter("s_suppkey < 8").select((2 * F.col("s_suppkey") + 1).alias("id"))
    x = _activations(spark, sf)
    return W.masked_algorithms(_stored(T.partsupp(spark, sf)), _stored(T.copurchase(spark, sf)), src, x, _layer_weights(spark, 64), x.filter("j < 8").select("i", "j"))


register("sparse_layer", f"WITH {_X} SELECT * FROM (SELECT x.i, w.j, greatest(sum(x.val * w.val) - 10, 0) AS val FROM x JOIN w ON w.i = x.j GROUP BY 1, 2) WHERE val > 0")(lambda spark, sf: M.sparse_layer(_activations(spark, sf), _layer_weights(spark, 64), -10.0))
register("sparse_layers_masked", f"WITH {_X}, y AS (SELECT * FROM (SELECT x.i, w.j, greatest(sum(x.val * w.val) - 10, 0) AS val FROM x JOIN w ON w.i = x.j GROUP BY 1, 2) WHERE val > 0) SELECT * FROM (SELECT y.i, w.j, greatest(sum(y.val * w.val) - 10, 0) AS val FROM y JOIN w ON w.i = y.j WHERE w.j < 8 GROUP BY 1, 2) WHERE val > 0")(
    lambda spark, sf: M.sparse_layers(_activations(spark, sf), [_layer_weights(spark, 64)] * 2, -10.0, _activations(spark, sf).filter("j < 8").select("i", "j"))
)

_SERIES = "x AS (SELECT user_id AS part, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1 AS pos, round(value * 100) AS val FROM events)"


def _series(spark, sf):
    return T.load(spark, sf, "events").select(F.col("user_id").alias("part"), (F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")) - 1).cast("bigint").alias("pos"), F.round(F.col("value") * 100).alias("val"))


register("conv_masked", f"WITH {_SERIES}, c AS (SELECT part, pos, coalesce(lag(val) OVER w, 0) + 2 * val + 3 * coalesce(lead(val) OVER w, 0) AS val FROM x WINDOW w AS (PARTITION BY part ORDER BY pos)) SELECT * FROM c WHERE pos % 5 = 0")(
    lambda spark, sf: M.conv_masked(_series(spark, sf), [1.0, 2.0, 3.0], _series(spark, sf).filter("pos % 5 = 0"))
)
register("conv_window", f"WITH {_SERIES} SELECT part, pos, coalesce(lag(val) OVER w, 0) + 2 * val + 3 * coalesce(lead(val) OVER w, 0) AS val FROM x WINDOW w AS (PARTITION BY part ORDER BY pos)")(lambda spark, sf: M.conv_window(_series(spark, sf), [1.0, 2.0, 3.0]))
register("path_counts", f"WITH {Q.graph('g_partsupp')}, a AS (SELECT dst AS id, count(*) AS val FROM e WHERE src = 1 GROUP BY 1) SELECT e.dst AS id, CAST(sum(val) AS BIGINT) AS val FROM a JOIN e ON e.src = a.id GROUP BY 1")(
    lambda spark, sf: A.path_counts(_stored(T.partsupp(spark, sf)), spark.createDataFrame([(1, 1)], "id bigint, val bigint"), 2)
)

@register("cost_physical", "SELECT 'push' AS plan, CAST(0 AS BIGINT) AS edge_exchanges UNION ALL SELECT 'plain', 1")
def _(spark, sf):
    """Exchanges of the edge table in one product: none on the bucketed store, one on plain files (the vector is too large to be sent along)."""
    g, plain = _stored(T.custpart(spark, sf)), Graph(persist(T.custpart(spark, sf).edges, "edges"))
    rows = []
    for name, graph in (("push", g), ("plain", plain)):
        x = graph.vertices().select("id", F.lit(True).alias("val"))
        moved = physical(K.expand(graph, x, S.OR_AND, MatvecOptions(join_strategy="merge")))
        rows.append((name, int(moved["shuffle_rows"] >= graph.nnz + graph.M)))
    return spark.createDataFrame(rows, "plan string, edge_exchanges long")


for _name, _base in B.BASELINES.items():
    register(f"baseline_{_name}", BFS_ORD)(lambda spark, sf, f=_base: f(_stored(T.ordpart(spark, sf)), 1).levels.select("id", "depth"))
register("baseline_fc_duplicates", BFS_ORD)(lambda spark, sf: B.fc_gpu(_stored(T.ordpart(spark, sf)), 1, dup=True).levels.select("id", "depth"))
register("baseline_best_of_both", BFS_ORD)(lambda spark, sf: B.best_of_both(_stored(T.ordpart(spark, sf)), 1).levels.select("id", "depth"))
register("baseline_row_unmasked", BFS_ORD)(lambda spark, sf: B.row_unmasked(_stored(T.ordpart(spark, sf)), 1).levels.select("id", "depth"))
@register("baseline_sql_recursive", Q.bfs("g_custorder", "(SELECT min(id) FROM vx)", 4))
def _(spark, sf):
    g = _stored(T.custorder(spark, sf))
    return B.sql_recursive(g.edges, g.facts["min_id"], 4)


from . import support as _support  # noqa: E402, F401
