import random

import pytest
from pyspark.sql import functions as F

from sparsehop.functions import semiring as S
from sparsehop.functions import vector as V
from sparsehop.graph import Graph
from sparsehop.layout import LONGEST, bucketed, placed, segment
from sparsehop.operators import algorithms as A
from sparsehop.operators import baselines as B
from sparsehop.operators import kernels as K
from sparsehop.operators import matmat as M
from sparsehop.operators.bfs import bfs, bfs_many, double_sweep
from sparsehop.options import BfsOptions, MatvecOptions
from sparsehop.plans import cost as C
from sparsehop.plans import workloads as W
from sparsehop.plans.direction import BestOfBoth, EdgeRule, PullOnly, PushOnly, RatioRule, Schedule
from sparsehop.plans.metrics import physical
from sparsehop.sources import generators as G
from sparsehop.sources import tables as T
from sparsehop.streaming import edges as E

from .reference import adjacency, depths, parents, trace


def graph(spark, pairs):
    return Graph.from_edges(spark.createDataFrame(pairs, "src bigint, dst bigint"))


def random_pairs(seed, n=40, m=90):
    r = random.Random(seed)
    return [(r.randrange(n), r.randrange(n)) for _ in range(m)] + [(n + 1, n + 2)]


def found(result):
    return {r.id: r.depth for r in result.levels.collect()}


def test_one_step_all_methods_agree(spark):
    rows = W.one_step(spark, T.toy(spark)).collect()
    by = {}
    for r in rows:
        by.setdefault(r.method, set()).add(r.id)
    assert set(map(frozenset, by.values())) == {frozenset({4, 5})} and len(by) == 4


@pytest.mark.parametrize("seed", [1, 2])
def test_every_switch_gives_the_reference_depths(spark, seed):
    pairs = random_pairs(seed)
    near = adjacency(pairs)
    g = Graph(graph(spark, pairs).edges.cache())
    source = min(near)
    want = depths(near, source)
    for rule in (PushOnly(), PullOnly(), RatioRule(), Schedule(["push", "pull"]), EdgeRule(), BestOfBoth()):
        assert found(bfs(g, source, rule)) == want
    for opts in (BfsOptions(mask=False, operand_reuse=False), BfsOptions(early_exit=False, operand_reuse=False), BfsOptions(operand_reuse=False), BfsOptions(waves=True), BfsOptions(broadcast_bytes=0)):
        assert found(bfs(g, source, PullOnly(), opts)) == want
    for opts in (BfsOptions(structure_only=False, merge="sort"), BfsOptions(merge="none"), BfsOptions(mask_placement="pre")):
        assert found(bfs(g, source, PushOnly(), opts)) == want
    tree = {r.id: r.parent for r in bfs(g, source, RatioRule(), BfsOptions(with_parent=True)).levels.collect()}
    assert tree == parents(near, want)
    for name, base in B.BASELINES.items():
        assert found(base(g, source)) == want, name


def test_trace_equals_level_by_level_counts(spark):
    pairs = random_pairs(5)
    near = adjacency(pairs)
    g = Graph(graph(spark, pairs).edges.cache())
    want = trace(near, depths(near, 0))
    got = sorted(tuple(r)[:3] + tuple(r)[4:] for r in C.trace(g, bfs(g, 0).levels).collect())
    assert got == want
    driver = bfs(g, 0, RatioRule(), count=True).trace
    assert [(x["iter"], x["nnz_f"], x["nnz_u"], x["out_edges_f"], x["in_edges_u"], x["parents_checked"]) for x in driver] == want


def test_shapes_and_errors(spark):
    path = graph(spark, [(0, 1), (1, 2), (2, 3), (7, 8), (5, 5), (1, 0)])
    assert found(bfs(path, 0)) == {0: 0, 1: 1, 2: 2, 3: 3}
    assert path.M == 6 and path.nnz == 8 and path.max_degree == 2
    assert double_sweep(path, 1) == (0, 3) or double_sweep(path, 1)[1] == 3
    with pytest.raises(ValueError):
        bfs(path, 99)
    with pytest.raises(ValueError):
        bfs(path, 5)  # a loop alone is no edge
    with pytest.raises(ValueError):
        bfs_many(path, [0, 7], opts=BfsOptions(max_depth=1))
    assert found(bfs(path, 0, opts=BfsOptions(max_depth=1))) == {0: 0, 1: 1}
    empty = graph(spark, [(None, 1), (2, 2)])
    assert empty.edges.count() == 0 and empty.M == 0
    directed = Graph.from_edges(spark.createDataFrame([(0, 1), (1, 2), (2, 0), (3, 0)], "src bigint, dst bigint"), directed=True)
    assert found(bfs(directed, 0, PullOnly())) == {0: 0, 1: 1, 2: 2} == found(bfs(directed, 0, PushOnly()))
    assert directed.transpose().edges.filter("src = 0 AND dst = 3").count() == 1


def test_illegal_switches_are_refused(spark):
    g, x = T.toy(spark), spark.createDataFrame([(0, 1.0)], "id bigint, val double")
    with pytest.raises(ValueError):
        K.row_masked_mxv(g, x, x.select("id"), S.MIN_PLUS, opts=MatvecOptions(early_exit=True))
    with pytest.raises(ValueError):
        K.col_mxv(g, x, S.PLUS_TIMES, MatvecOptions(structure_only=True))
    with pytest.raises(ValueError):
        K.col_mxv(g, x, S.PLUS_TIMES, MatvecOptions(merge="none"))
    with pytest.raises(ValueError):
        MatvecOptions(switch_point=0)


def test_rows_and_columns_agree_for_every_semiring(spark):
    g = Graph(graph(spark, random_pairs(3)).edges.withColumn("val", F.lit(2).cast("bigint")).cache())
    mask = spark.range(0, 40, 3)
    for sr in (S.PLUS_TIMES, S.COUNT_TIMES, S.MIN_PLUS, S.MAX_SECOND, S.MIN_FIRST, S.PLUS_PAIR, S.BITOR_AND):
        x = g.vertices().filter("id % 2 = 0").select("id", F.col("id").cast(sr.kind).alias("val"))
        whole = {r.id: r.val for r in K.col_mxv(g, x, sr).collect()}
        dense = {r.id: r.val for r in K.row_mxv(g, x, sr).collect()}
        assert {k: v for k, v in dense.items() if k in whole} == whole
        assert all(v == sr.zero for k, v in dense.items() if k not in whole)
        on = {r.id for r in mask.collect()}
        for complement in (False, True):
            want = {k: v for k, v in whole.items() if (k in on) != complement}
            assert {r.id: r.val for r in K.row_masked_mxv(g, x, mask, sr, complement).collect()} == want
            assert {r.id: r.val for r in K.col_masked_mxv(g, x, mask, sr, complement).collect()} == want
            assert {r.id: r.val for r in K.col_masked_mxv(g, x, mask, sr, complement, MatvecOptions(mask_placement="pre")).collect()} == want


def test_costs_are_ordered_and_monotone(spark):
    g = Graph(graph(spark, random_pairs(8)).edges.cache())
    n = lambda df: df.first()[0]
    all_ = n(C.row(g))
    last = 0
    for size in (1, 5, 20, g.M):
        f = G.sample_vertices(g, size)
        c2, c4 = n(C.row_masked(g, f)), n(C.col(g, f))
        assert n(C.row_early(g, f, f)) <= c2 <= all_ and c2 >= last and c4 == c2
        assert n(C.row_early(g, f, f.limit(0))) == c2
        last = c2
    assert last == all_


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_mask_placement_shows_in_the_plan(spark):
    g, x, m = T.toy(spark), spark.createDataFrame([(0, True)], "id bigint, val boolean"), spark.range(3)
    post = K.col_masked_mxv(g, x, m, S.OR_AND, True)._jdf.queryExecution().optimizedPlan().toString()
    pre = K.col_masked_mxv(g, x, m, S.OR_AND, True, MatvecOptions(mask_placement="pre"))._jdf.queryExecution().optimizedPlan().toString()
    assert post.index("LeftOuter") < post.index("Aggregate") and "LeftAnti" not in post
    assert pre.index("Aggregate") < pre.index("LeftAnti")


def test_structure_only_never_reads_values(spark, tmp_path):
    graph(spark, [(0, 1), (1, 2)]).edges.withColumn("val", F.lit(1.0)).write.parquet(str(tmp_path / "e"))
    g = Graph(spark.read.parquet(str(tmp_path / "e")))
    x = spark.createDataFrame([(0, True)], "id bigint, val boolean")
    assert "val:double" not in plan(K.col_mxv(g, x, S.OR_AND)).split("ReadSchema")[1]


def test_store_prunes_blocks_by_literals(spark, tmp_path):
    from sparsehop.layout import open_edge_store, write_edge_store

    store = open_edge_store(spark, write_edge_store(graph(spark, [(0, 1), (5000, 1), (9000, 3)]), str(tmp_path / "s")))
    pruned = store.edges(spark.range(2))
    assert "PartitionFilters: [" in plan(pruned) and pruned.filter("src > 4999").count() == 0


def test_segments_bound_rows(spark):
    star = graph(spark, [(0, i) for i in range(1, 400)])
    rows = segment(star, first=4, growth=4, longest=64).filter("vertex = 0").orderBy("seg").collect()
    assert [len(r.nbrs) for r in rows][:3] == [4, 16, 64] and max(len(r.nbrs) for r in rows) <= 64
    assert [n for r in rows for n in r.nbrs] == list(range(1, 400))


def test_words_roundtrip_and_hysteresis(spark):
    ids = spark.createDataFrame([(0,), (63,), (64,), (40_000,), (99_999,)], "id bigint")
    assert sorted(r.id for r in V.unpack_words(V.pack_words(ids)).collect()) == [0, 63, 64, 40_000, 99_999]
    c = V.Converter(100, 0.1)
    assert [c.next(n) for n in (5, 20, 15, 9, 9, 30)] == ["sparse", "dense", "dense", "sparse", "sparse", "dense"]
    r = RatioRule(0.01, 0.01)
    from sparsehop.plans.direction import Level

    assert [r.next(Level(n, 1000)) for n in (1, 10, 11, 11, 10, 9)] == ["push", "push", "pull", "pull", "pull", "push"]


def test_reference_traces_of_the_generated_graph(spark):
    """Known counts of the scale-13 graph: the three phases push, pull, push and the fall of parents checked."""
    g = Graph(G.kron(spark, 13, 16).edges.cache())
    assert (g.M, g.nnz, g.max_degree) == (6532, 204266, 2271)
    source = g.out_degrees().orderBy("degree", "id").first().id
    tr = C.ratio_directions(C.trace(g, bfs(g, source).levels)).orderBy("iter").collect()
    assert [x.nnz_f for x in tr] == [1, 1, 231, 5060, 1230, 7]
    assert [x.out_edges_f for x in tr] == [1, 232, 50192, 151434, 2398, 7]
    assert [x.parents_checked for x in tr] == [204077, 187110, 9263, 1243, 9, 2]
    assert [x.direction for x in tr] == ["push", "push", "pull", "pull", "pull", "push"]
    got = {r.stack: r.accesses for r in C.ablation(C.trace(g, bfs(g, source).levels)).collect()}
    assert (got["baseline"], got["change of direction"], got["masking"], got["early exit"]) == (204264, 613038, 156497, 10755)


def test_algorithms_on_small_graphs(spark):
    g = T.toy(spark)
    assert {r.id: r.dist for r in A.sssp(g, 0).collect()}[7] == 4.0
    ranks = {r.id: r.rank for r in A.pagerank(g, iters=30).collect()}
    assert abs(sum(ranks.values()) - 1) < 1e-9 and max(ranks, key=ranks.get) in (0, 6)
    seeds = spark.createDataFrame([(0,)], "id bigint")
    assert abs(sum(r.rank for r in A.personalized_pagerank(g, seeds).collect()) - 1) < 1e-9
    near = adjacency(T.TOY)
    chosen = {r.id for r in A.mis(g).collect()}
    assert all(not (set(near[v]) & chosen) for v in chosen) and all(v in chosen or set(near[v]) & chosen for v in near)
    two = graph(spark, [(0, 1), (1, 2), (9, 8)])
    assert {r.id: r.component for r in A.components(two).collect()} == {0: 0, 1: 0, 2: 0, 8: 8, 9: 8}
    tri = graph(spark, [(0, 1), (1, 2), (2, 0), (2, 3), (3, 0)])
    assert M.triangle_count(tri).first()[0] == 2 == M.triangle_count_unmasked(tri).first()[0]
    assert {tuple(r) for r in M.triangles(tri).collect()} == {(0, 1, 2), (0, 2, 3)}
    line = graph(spark, [(0, 1), (1, 2)])
    assert {r.id: r.score for r in A.betweenness(line, line.vertices()).collect()} == {0: 0.0, 1: 2.0, 2: 0.0}


def test_late_edges_are_dropped_and_counted(spark, tmp_path):
    from sparsehop.streaming.edges import edge_stream

    rows = lambda first, day: spark.createDataFrame([(first + i, f"2024-01-{day:02d} 0{i}:00:00", i, "view", 1.0, '{"k": 1}') for i in range(3)], "event_id bigint, ts string, user_id bigint, event_type string, value double, props string").withColumn("ts", F.col("ts").cast("timestamp"))
    folder = str(tmp_path / "in")
    rows(0, 9).coalesce(1).write.parquet(folder)
    q = edge_stream(spark, folder, "1 hour").writeStream.format("memory").queryName("late").option("checkpointLocation", str(tmp_path / "c")).start()
    try:
        q.processAllAvailable()
        rows(10, 1).coalesce(1).write.mode("append").parquet(folder)
        q.processAllAvailable()
        dropped = sum(int(o["numRowsDroppedByWatermark"]) for p in q.recentProgress for o in p["stateOperators"])
        assert spark.table("late").count() == 3 and dropped == 3
    finally:
        q.stop()


def test_geomeans_of_published_times(spark):
    from sparsehop import support

    got = {r.system: r.speedup for r in W.geomean(support._published(spark), "masked", []).collect()}
    assert abs(got["la_cpu"] - 82.7) < 0.1 and abs(got["push_la_gpu"] - 4.05) < 0.01 and abs(got["vc_cpu"] - 1.71) < 0.01


def test_timed_workloads_take_all_graphs_and_ten_runs(spark, monkeypatch):
    from sparsehop import support

    names, seen = {"kron", "rmat_64", "rmat_32", "rmat_16", "word", "ordpart", "copurchase", "pages", "knn", "geometric", "chain", "ladder"}, []
    graphs = {n: (None, 0, "mesh") for n in names}
    built = support._bench_graphs(spark, "/root/testdata/sf0.001")
    assert set(built) == names
    assert all(g.out_degrees().filter(f"id = {source}").count() == 1 for g, source, _ in built.values())
    monkeypatch.setattr(support, "_bench_graphs", lambda spark, sf, chosen=(): {n: graphs[n] for n in chosen or names})
    monkeypatch.setattr(W, "compare", lambda graphs, systems=None, runs=1: seen.append((set(graphs), runs)) or [{"g": n, "t": "mesh", "s": s, "ms": 1.0, "m": 1.0, "st": "ok"} for n in graphs for s in ("switching", "vc_cpu")])
    from sparsehop.catalogue import QUERIES as queries
    assert queries["workload_compare"](spark, "").count() == 2 * len(names)
    assert queries["workload_compare_by_type"](spark, "").count() == 1
    assert seen == [(names, 10), (names, 10)]


def test_a_hub_of_a_million_neighbours_is_many_rows(spark):
    n = 1_000_000
    g = Graph(spark.range(1, n + 1).select(F.col("id").alias("src"), F.lit(0).cast("bigint").alias("dst")).union(spark.createDataFrame([(1, 2), (5, 2)], "src bigint, dst bigint")), directed=True)
    rows = segment(g, LONGEST, 1).select("vertex", "seg", F.size("nbrs").alias("n"), F.element_at("nbrs", 1).alias("low")).filter("vertex = 0").collect()
    assert max(r.n for r in rows) == LONGEST and sum(r.n for r in rows) == n
    assert sorted((r.seg, r.low) for r in rows) == [(k, 1 + k * LONGEST) for k in range(-(-n // LONGEST))]
    x = spark.createDataFrame([(n,), (77,)], "id bigint")
    hit = K.probe_rows(g, x, spark.createDataFrame([(3,)], "id bigint"), "left_anti", MatvecOptions()).collect()
    assert [(r.id, r.parent) for r in hit] == [(0, 77)]


def test_places_do_not_depend_on_ranges(spark):
    pairs = [(s, d) for d in range(3) for s in range(d, 4000 * (d + 1), d + 1)]
    df = spark.createDataFrame(pairs, "src bigint, dst bigint").repartition(7)
    got = {(r.src, r.dst): r.at for r in placed(df).collect()}
    want, seen = {}, {}
    for s, d in sorted(pairs, key=lambda p: (p[1], p[0])):
        want[s, d] = seen[d] = seen.get(d, -1) + 1
    assert got == want


def test_words_of_many_ids(spark):
    ids = spark.range(0, 3_000_000, 7)
    words = V.all_words(ids, 3_000_000).first().words
    assert sum(bin(w & (2**64 - 1)).count("1") for w in words) == len(range(0, 3_000_000, 7))
    assert all((words[i >> 6] >> (i & 63)) & 1 for i in range(0, 3_000_000, 70_007) if i % 7 == 0)
    assert V.unpack_words(V.pack_words(ids)).agg(F.count("*"), F.sum("id")).first()[:] == (428_572, sum(range(0, 3_000_000, 7)))


def test_levels_on_the_bucketed_store_exchange_no_edges(spark):
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        g = bucketed(G.kron(spark, 8, 8))
        x = g.vertices().select("id", F.lit(True).alias("val"))
        joined = plan(K.expand(g, x, S.OR_AND, MatvecOptions()))
        assert "Bucketed: true" in joined
        moved = physical(K.expand(g, x, S.OR_AND, MatvecOptions()))
        assert moved["rows"] == g.nnz and 0 < moved["shuffle_rows"] < g.nnz
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_stateful_degrees_end_with_the_data(spark, tmp_path):
    rows = [(i, f"2024-01-0{1 + i // 4} 00:00:00", i % 3, "view", 1.0, '{"k": %d}' % (i % 2)) for i in range(12)]
    events = spark.createDataFrame(rows, "event_id bigint, ts string, user_id bigint, event_type string, value double, props string")
    events.withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.parquet(str(tmp_path / "events"))
    stream = E.edge_stream(spark, str(tmp_path / "events"), "1 hour").select("src", "dst", "ts")
    got = {r.src: r.degree for r in E.drain(E.stateful_degree(stream), "update").groupBy("src").agg(F.max("degree").alias("degree")).collect()}
    assert got == {0: 4, 2: 4, 4: 4}


def test_a_search_that_runs_out_of_memory_is_reported(spark, monkeypatch):
    def fails(g, source):
        raise RuntimeError("java.lang.OutOfMemoryError: Java heap space")

    monkeypatch.setattr(B, "BASELINES", {"fails": fails})
    rows = W.compare({"toy": (T.toy(spark), 0, "mesh")}, ["fails"])
    assert [(r["system"], r["status"], r["ms"]) for r in rows] == [("fails", "out of memory", None)]


@pytest.mark.parametrize("seed", [3])
def test_ranks_and_centrality_agree_in_every_direction(spark, seed):
    g = Graph(graph(spark, random_pairs(seed)).edges.cache())
    seeds = g.vertices().filter("id < 3").select("id")
    ranks = [
        {r.id: r.rank for r in A.personalized_pagerank(g, seeds, iters=4, **how).collect()}
        for how in ({"rule": PushOnly()}, {"rule": PullOnly()}, {"rule": PullOnly(), "operand_reuse": False}, {"rule": Schedule(["push", "pull", "push"]), "tol": 1e-14})
    ]
    for other in ranks[1:]:
        assert other.keys() == ranks[0].keys() and all(abs(other[i] - ranks[0][i]) < 1e-9 for i in other)
    some = g.vertices().filter("id < 5").select("id")
    pushed, pulled, mixed = ({r.id: round(r.score, 9) for r in A.betweenness(g, some, 3, rule).collect()} for rule in (PushOnly(), PullOnly(), Schedule(["push", "pull"])))
    assert pushed == pulled == mixed and max(pushed.values()) > 0
    assert A.personalized_pagerank(g, seeds.limit(0)).count() == 0 and {r.score for r in A.betweenness(g, seeds.limit(0)).collect()} == {0.0}


def test_waves_read_a_hub_in_the_logarithm_of_its_segments(spark, monkeypatch):
    from sparsehop import runtime

    n = 60 * LONGEST
    g = Graph(spark.range(1, n + 1).select(F.col("id").alias("src"), F.lit(0).cast("bigint").alias("dst")).union(spark.createDataFrame([(1, 2), (5, 2)], "src bigint, dst bigint")), directed=True)
    table = segment(g).cache()
    last = table.agg(F.max("seg")).first()[0]
    waves, write = [], runtime.persist
    monkeypatch.setattr(runtime, "persist", lambda df, name="table": waves.append(name) or write(df, name))
    for x, want in ((n, [(0, n)]), (5, [(0, 5), (2, 5)]), (n + 7, [])):
        waves.clear()
        hit = K.probe_waves(g, spark.createDataFrame([(x,)], "id bigint"), spark.createDataFrame([(3,)], "id bigint"), "left_anti", MatvecOptions(), table, last)
        assert sorted((r.id, r.parent) for r in hit.collect()) == want
        assert waves.count("words") == 1 and waves.count("wave") == (1 if x == 5 else 7) < last


def test_unmasked_products_count_wedges_block_by_block(spark):
    g = Graph(graph(spark, random_pairs(11, 30, 160)).edges.cache())
    e = {(r.a, r.b) for r in M.oriented(g).collect()}
    wedges = [(a, x, y) for a, x in e for z, y in e if z == x]
    want = (len(wedges), len({(a, y) for a, _, y in wedges}), sum((a, y) in e for a, _, y in wedges))
    for most in (1, 40, M.BLOCK_WEDGES):
        cut = M.wedge_blocks(M.oriented(g), most)
        assert cut.agg(F.sum("wedges"), F.sum("outputs"), F.sum("closed")).first()[:] == want
        assert most != 40 or 1 < cut.count() < 30
    assert M.triangle_count_unmasked(g).first()[0] == M.triangle_count(g).first()[0] == want[2]
    assert M.triangle_count_unmasked(graph(spark, [(0, 1)])).first()[0] == 0
    assert "Join" not in plan(M.wedge_blocks(M.oriented(g))).split("FlatMapGroupsInArrow")[0]  # no wedge is a row


def test_nearest_neighbours_with_ties_halves_and_missing_vectors(spark):
    r = random.Random(4)
    rows = [(i, [round(r.gauss(0, 0.2), 2) for _ in range(5)]) for i in range(40)]
    rows += [(100 + i, rows[0][1]) for i in range(9)]  # copies: ties by id
    rows += [(200, [1.0, 0.0, 0.0, 0.0, 0.0]), (201, [0.9999995, 0.0, 0.0, 0.0, 0.0]), (202, [0.5, None, 0.0, 0.0, 0.0]), (300, None), (301, [])]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")

    def weight(x, y):
        if not x or not y:
            return None
        total = 0.0
        for p, q in zip(x, y):
            total += (p or 0.0) * (q or 0.0)
        w = 1e6 * (1 - total)
        return int(abs(w) + 0.5) * (1 if w >= 0 else -1)

    want = set()
    for i, x in rows:
        near = sorted(((weight(x, y), j) for j, y in rows if i != j), key=lambda t: (t[0] is None, t[0] or 0, t[1]))[:5]
        want |= {(i, j, w) for w, j in near}
    for blocks in (1, 3, None):
        assert {(t.src, t.dst, t.weight) for t in T.knn_pairs(df, 5, blocks).collect()} == want
    assert T.knn_pairs(df.limit(0), 5).count() == 0 == T.knn_pairs(df.limit(1), 5).count()


def test_repeats_that_stay_in_a_level_do_not_multiply(spark, monkeypatch):
    from sparsehop.operators import bfs as X

    # layers of 8, each joined whole with the next: 8 ** 6 paths reach the last, but 64 edges
    g = Graph(graph(spark, [(0, i) for i in range(1, 9)] + [(8 * k + i + 1, 8 * k + j + 9) for k in range(6) for i in range(8) for j in range(8)]).edges.cache())
    sizes, write = [], X.commit
    monkeypatch.setattr(X, "commit", lambda df, path: (lambda out: sizes.append(out[1]) or out)(write(df, path)))
    got = found(bfs(g, 0, PushOnly(), BfsOptions(merge="none", mask_placement="pre")))
    assert len(got) == 57 and max(got.values()) == 7 and max(sizes) == 64


def test_large_levels_are_never_sent_whole_whatever_their_files_weigh(spark, monkeypatch):
    from sparsehop.operators import bfs as X

    monkeypatch.setattr(X, "SENT_ROWS", 2, raising=False)
    g = Graph(graph(spark, [(i, j) for k in range(3) for i in range(4 * k, 4 * k + 4) for j in range(4 * k + 4, 4 * k + 8)]).edges.cache())
    plans, write = [], X.commit
    monkeypatch.setattr(X, "commit", lambda df, path: plans.append(df._jdf.queryExecution().executedPlan().toString()) or write(df, path))
    got = found(bfs(g, 0, PushOnly(), BfsOptions(merge="none", mask_placement="pre")))
    assert got == {0: 0, **{4 + i: 1 for i in range(4)}, **{i: 2 for i in (1, 2, 3, 8, 9, 10, 11)}, **{12 + i: 3 for i in range(4)}}
    # the third level: 7 vertices ask and 12 are known
    assert "Broadcast" not in plans[3] and "LeftAnti" not in plans[3] and "Broadcast" in plans[1]


def test_words_are_packed_with_one_exchange_of_ids(spark):
    from sparsehop.functions import vector as V

    ids = spark.createDataFrame([(i,) for i in (0, 1, 7, 8, 62, 63, 63, 64, 32_767, 32_768, 90_000, 200_000, -5, None)], "id bigint")
    packed = V.all_words(ids, 100_000)
    words = packed.first().words
    assert [i for i in range(64 * len(words)) if words[i >> 6] >> (i & 63) & 1] == [0, 1, 7, 8, 62, 63, 64, 32_767, 32_768, 90_000] and len(words) == 4 * 512
    # one by block, one to lay the blocks end to end
    assert packed._jdf.queryExecution().executedPlan().toString().count("Exchange ") == 2


def test_double_sweep_of_a_long_road_is_no_job_for_each_level(spark, monkeypatch):
    from sparsehop.operators import bfs as X

    road = Graph(graph(spark, [(i, i + 1) for i in range(5, 300)] + [(900, 901)]).edges.cache())
    levels, write = [], X.commit
    monkeypatch.setattr(X, "commit", lambda df, path: levels.append(path) or write(df, path))
    assert X.double_sweep(road, 290) == (300, 295) and len(levels) < 10
    near = Graph(graph(spark, [(0, 1), (1, 2), (2, 0), (2, 3), (2, 4), (4, 5), (3, 6), (8, 9)]).edges.cache())
    oneway = Graph(graph(spark, [(0, 1), (0, 2), (2, 3)]).edges.filter("src < dst"), True)
    for g, start in ((near, 0), (near, 5), (near, 9), (oneway, 0), (oneway, 3)):
        assert X.double_sweep(g, start) == X.double_sweep(g, start, 0)
    alone = Graph(near.edges, False, spark.range(20))
    assert X.double_sweep(alone, 15) == (15, 0)
    for most in (0, 100):
        with pytest.raises(ValueError):
            X.double_sweep(near, 77, most)


@pytest.mark.parametrize("name, table", [("baseline_sql_recursive", "orders"), ("demo_one_step", "lineitem"), ("micro_row", "lineitem"), ("random_geometric", "customer"), ("recursive_matrix_edges", "events"), ("support_geomean", "events"), ("support_geomean_by_type", "events"), ("support_slowdown", "events")])
def test_queries_that_made_up_their_data_read_a_table(spark, monkeypatch, name, table):
    from sparsehop.catalogue import QUERIES as queries

    read, load = [], T.load
    monkeypatch.setattr(T, "load", lambda spark, sf, name, *columns: read.append(name) or load(spark, sf, name, *columns))
    assert queries[name](spark, "/root/testdata/sf0.001").count() > 0 and table in read


def test_searches_on_a_graph_share_its_rows(spark, monkeypatch):
    from sparsehop import layout

    made, cut = [], layout.segment
    monkeypatch.setattr(layout, "segment", lambda g, *how: made.append(how) or cut(g, *how))
    g = Graph(graph(spark, [(0, 1), (1, 2), (7, 8)]).edges.cache())
    assert [found(bfs(g, s, PullOnly())) for s in (0, 2)] == [{0: 0, 1: 1, 2: 2}, {2: 0, 1: 1, 0: 2}] and len(made) == 1


def test_words_of_few_blocks_take_no_exchange_by_block(spark, monkeypatch):
    ids = spark.createDataFrame([(0,), (5,), (63,), (64,), (40_000,), (40_000,), (70_001,), (90_000,), (-3,), (None,)], "id bigint")
    packed = V.all_words(ids, 70_001)
    assert plan(packed).count("Exchange") == 1
    monkeypatch.setattr(V, "FEW_BLOCKS", 0)
    assert packed.first().words == V.all_words(ids, 70_001).first().words


def test_stored_rows_without_a_hub_are_pulled_without_a_merge(spark):
    star = lambda n: Graph.from_edges(spark.range(1, n + 1).select(F.lit(0).cast("bigint").alias("src"), F.col("id").alias("dst")))
    for n, split in ((50, False), (LONGEST + 9, True)):
        g, x = star(n), spark.createDataFrame([(3,), (n,)], "id bigint")
        assert g.stored_rows[1] == split
        hit = K.probe_rows(g, x, spark.createDataFrame([(9,)], "id bigint"), "left_anti", MatvecOptions(), g.row_store)
        assert ("functions=[min(parent" in plan(hit)) == split
        assert [(r.id, r.parent) for r in hit.collect()] == [(0, 3)]


def test_traces_from_stored_rows_are_the_same(spark):
    hub = spark.range(1, LONGEST + 500).select(F.lit(0).cast("bigint").alias("src"), F.col("id").alias("dst"))
    tail = spark.createDataFrame([(LONGEST + 400, 9000), (9000, 9001), (9001, 9002), (7, 8), (9500, 9501)], "src bigint, dst bigint")
    g = Graph.from_edges(hub.union(tail))
    levels = bfs(g, 9002).levels
    assert sorted(C.trace(g, levels, g.row_store).collect()) == sorted(C.trace(g, levels).collect())


def test_edges_are_kept_once_before_they_are_turned(spark):
    df = spark.createDataFrame([(1, 2), (2, 1), (1, 2), (3, 3), (None, 4), (5, None), (9, 4)], "src int, dst bigint")
    g = Graph.from_edges(df)
    assert sorted((r.src, r.dst) for r in g.edges.collect()) == [(1, 2), (2, 1), (4, 9), (9, 4)] and g.edges.columns == ["src", "dst"]
    assert "Union" not in plan(g.edges)
