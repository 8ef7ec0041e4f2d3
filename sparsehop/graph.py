"""Graphs as edge tables: coordinates (src, dst[, val]), cleaning, degrees, subgraphs."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


@dataclass
class Graph:
    """Edges in both orientations unless ``directed``; vertices are the ends of edges unless a table is given."""

    edges: DataFrame
    directed: bool = False
    vertex_table: DataFrame | None = field(default=None)

    @classmethod
    def from_edges(cls, df: DataFrame, directed: bool = False, weight: str | None = None, vertices: DataFrame | None = None) -> Graph:
        return cls(canonicalize(df, directed, weight), directed, vertices)

    @property
    def weighted(self) -> bool:
        return "val" in self.edges.columns

    def pattern(self) -> DataFrame:
        """Edges without values: the value column never leaves the scan."""
        return self.edges.select("src", "dst")

    def valued(self, one: Column) -> DataFrame:
        return self.edges if self.weighted else self.edges.select("src", "dst", one.alias("val"))

    def transpose(self) -> Graph:
        cols = [F.col("dst").alias("src"), F.col("src").alias("dst"), *(["val"] if self.weighted else [])]
        return self if not self.directed else Graph(self.edges.select(*cols), True, self.vertex_table)

    def vertices(self) -> DataFrame:
        if self.vertex_table is not None:
            return self.vertex_table.select("id")
        ends = self.edges.select(F.col("src").alias("id"))
        return (ends.union(self.edges.select(F.col("dst").alias("id"))) if self.directed else ends).distinct()

    def out_degrees(self) -> DataFrame:
        return self.edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("degree"))

    def in_degrees(self) -> DataFrame:
        return self.edges.groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("degree"))

    def rows(self) -> DataFrame:
        """(vertex, nbrs): in-neighbours of each vertex, ascending, one row each; searches take the segments of ``layout``."""
        return self.edges.groupBy(F.col("dst").alias("vertex")).agg(F.array_sort(F.collect_list("src")).alias("nbrs"))

    @cached_property
    def facts(self) -> dict[str, int]:
        """M, nnz, largest id and largest degree, in one pass over degrees."""
        d = self.out_degrees().agg(F.count("*").alias("m"), F.sum("degree").alias("nnz"), F.max("degree").alias("top"), F.max("id").alias("last"), F.min("id").alias("first")).first()
        m = self.vertices().count() if self.directed or self.vertex_table is not None else d.m
        last = self.vertices().agg(F.max("id")).first()[0] if self.directed or self.vertex_table is not None else d.last
        return {"M": m or 0, "nnz": d.nnz or 0, "max_degree": d.top or 0, "max_id": -1 if last is None else last, "min_id": 0 if d.first is None else d.first}

    @cached_property
    def stored_rows(self) -> tuple[DataFrame, bool]:
        """``row_store`` and whether any vertex has several rows there."""
        from . import layout

        return layout.stored_rows(self)

    @property
    def row_store(self) -> DataFrame:
        """The stored row table that all searches on this graph share: a hub is several rows, all others are one."""
        return self.stored_rows[0]

    @property
    def M(self) -> int:  # noqa: N802
        return self.facts["M"]

    @property
    def nnz(self) -> int:
        return self.facts["nnz"]

    @property
    def d(self) -> float:
        return self.nnz / self.M if self.M else 0.0

    @property
    def max_degree(self) -> int:
        return self.facts["max_degree"]


def canonicalize(df: DataFrame, directed: bool = False, weight: str | None = None) -> DataFrame:
    """Drop null ends and loops, add the other orientation unless directed, keep each edge once (parallel weights: the least)."""
    cols = ["src", "dst", *([F.col(weight).alias("val")] if weight else [])]
    clean = df.filter(F.col("src").isNotNull() & F.col("dst").isNotNull() & (F.col("src") != F.col("dst"))).select(*cols)
    if not directed and not weight:
        # each edge is kept once before its other orientation is added, so half as many rows are exchanged
        once = clean.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).distinct()
        return once.select(F.inline(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst")))))
    if not directed:
        clean = clean.unionByName(clean.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "val"))
    return clean.groupBy("src", "dst").agg(F.min("val").alias("val")) if weight else clean.distinct()


def canonicalize_report(df: DataFrame) -> DataFrame:
    """(step, n): rows left after each cleaning step."""
    present = df.filter(F.col("src").isNotNull() & F.col("dst").isNotNull())
    loose = present.filter("src <> dst")
    both = loose.select("src", "dst").union(loose.select("dst", "src"))
    steps = [("0 input", df), ("1 no nulls", present), ("2 no loops", loose), ("3 both ways", both), ("4 distinct", both.distinct())]
    out = [x.agg(F.lit(name).alias("step"), F.count(F.lit(1)).alias("n")) for name, x in steps]
    first = out[0]
    for x in out[1:]:
        first = first.unionByName(x)
    return first


def edges_from_pairs(df: DataFrame, a: str | Column, b: str | Column, weight: Column | None = None) -> DataFrame:
    """Any relation as edges; weights of parallel edges add up."""
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    pairs = df.select(a.cast("bigint").alias("src"), b.cast("bigint").alias("dst"), *([weight.alias("val")] if weight is not None else []))
    return pairs if weight is None else pairs.groupBy("src", "dst").agg(F.sum("val").alias("val"))


def edges_from_succession(df: DataFrame, part: str, order: list[str], id_: str) -> DataFrame:
    """Consecutive rows of each part."""
    follow = F.lead(id_).over(Window.partitionBy(part).orderBy(*order))
    return df.select(F.col(id_).alias("src"), follow.alias("dst")).filter("dst IS NOT NULL")


def edges_from_cooccurrence(df: DataFrame, key: str, item: str) -> DataFrame:
    """Pairs of different items that share a key."""
    one = df.select(F.col(key).alias("k"), F.col(item).cast("bigint").alias("i")).distinct()
    return one.alias("x").join(one.alias("y"), (F.col("x.k") == F.col("y.k")) & (F.col("x.i") < F.col("y.i"))).select(F.col("x.i").alias("src"), F.col("y.i").alias("dst"))


def subgraph(g: Graph, keep: DataFrame) -> Graph:
    """Edges with both ends in ``keep``."""
    ids = keep.select("id")
    inner = g.edges.join(ids.withColumnRenamed("id", "src"), "src", "left_semi").join(ids.withColumnRenamed("id", "dst"), "dst", "left_semi")
    return Graph(inner.select(*g.edges.columns), g.directed)


def edge_filter(g: Graph, predicate: Column) -> Graph:
    return Graph(g.edges.filter(predicate), g.directed, g.vertex_table)


def top_hubs(g: Graph, k: int) -> DataFrame:
    return g.out_degrees().orderBy(F.desc("degree"), "id").limit(k)


def degree_quantiles(g: Graph, at: tuple[float, ...] = (0.5, 0.9, 0.99), exact: bool = True) -> DataFrame:
    f = F.percentile if exact else F.percentile_approx
    return g.out_degrees().agg(*[f("degree", F.lit(q)).cast("double").alias(f"p{round(q * 100)}") for q in at])
