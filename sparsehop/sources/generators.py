"""Generated graphs and samples, in integer arithmetic that SQL can follow."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph import Graph

MODULUS, STEP = 2**31 - 1, 48_271


def recursive_pairs(spark: SparkSession, scale: int, edge_factor: int) -> DataFrame:
    """(src, dst): edge_factor * 2**scale raw pairs."""
    return recursive_pairs_of(spark.range(edge_factor << scale), scale)


def recursive_pairs_of(draws: DataFrame, scale: int) -> DataFrame:
    """(src, dst): a raw pair for each row of ``draws`` (id); each round picks a quadrant by thousandths 570, 190, 190, 50."""
    h = F.pmod(F.col("id") * 2_654_435_761 + 12_345, F.lit(MODULUS))
    start = draws.select(h.alias("h"))
    # round k draws start * STEP**k, so the rounds are columns of one projection and not a tower of them
    draws = start.select(*[(F.pmod(F.col("h") * pow(STEP, k, MODULUS), F.lit(MODULUS)) % 1000).cast("int").alias(f"t{k}") for k in range(scale)])

    def number(bit):
        total = F.lit(0).cast("bigint")
        for k in range(scale):
            total = total + F.when(bit(F.col(f"t{k}")), F.lit(1 << (scale - 1 - k)).cast("bigint")).otherwise(F.lit(0).cast("bigint"))
        return total

    return draws.select(number(lambda t: t >= 760).alias("src"), number(lambda t: ((t >= 570) & (t < 760)) | (t >= 950)).alias("dst"))


def kron(spark: SparkSession, scale: int, edge_factor: int) -> Graph:
    return Graph.from_edges(recursive_pairs(spark, scale, edge_factor))


def random_geometric(spark: SparkSession, n: int, radius: float) -> Graph:
    """Points of an integer lattice square, joined within a radius."""
    side = 1_000_003
    reach = max(1, int(radius * side))
    x = F.pmod(F.col("id") * 7_368_787 + 11, F.lit(side))
    y = F.pmod(F.col("id") * 1_299_709 + F.pmod(F.col("id") * F.col("id"), F.lit(65_521)) * 31 + 7, F.lit(side))
    return geometric(spark.range(n).select("id", x.alias("x"), y.alias("y")), reach)


def geometric(points: DataFrame, reach: int) -> Graph:
    """Integer points (id, x, y) of different ids, joined within ``reach``: cells of that width meet their neighbours."""
    p = points.withColumns({"cx": F.floor(F.col("x") / reach), "cy": F.floor(F.col("y") / reach)})
    steps = F.explode(F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b")) for a in (-1, 0, 1) for b in (-1, 0, 1)])).alias("s")
    near = p.select(F.col("id").alias("src"), F.col("x").alias("x1"), F.col("y").alias("y1"), "cx", "cy", steps).select("src", "x1", "y1", (F.col("cx") + F.col("s.a")).alias("cx"), (F.col("cy") + F.col("s.b")).alias("cy"))
    met = near.join(p.select(F.col("id").alias("dst"), "x", "y", "cx", "cy"), ["cx", "cy"]).filter("src < dst")
    return Graph.from_edges(met.filter((F.col("x") - F.col("x1")) ** 2 + (F.col("y") - F.col("y1")) ** 2 <= float(reach) ** 2).select("src", "dst"))


def hash_order(seed: int = 0):
    return F.pmod(F.pmod(F.col("id"), F.lit(MODULUS)) * STEP + 1_000_003 * seed, F.lit(MODULUS))


def sample_vertices(g: Graph, n: int, seed: int = 0) -> DataFrame:
    """Exactly n vertices (or all) in the order of an integer hash."""
    return g.vertices().orderBy(hash_order(seed), "id").limit(n)
