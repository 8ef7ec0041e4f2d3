"""Sparse vectors (id, val), Boolean word blocks, and the operations between them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .semiring import Semiring

#: 64-bit words of one block; a block covers 32,768 vertices, as Spark's bitmaps do.
BLOCK_WORDS, BLOCK_SHIFT = 512, 15
#: Up to so many blocks are packed side by side as columns of one aggregate, without an exchange by block.
FEW_BLOCKS = 16


def _words_of_bitmap(bitmap: Column) -> Column:
    """The words of a bitmap whose bits were set at ``_bitmap_place``: eight bytes each, the highest first."""
    return F.transform(F.sequence(F.lit(0), F.lit(BLOCK_WORDS - 1)), lambda w: F.conv(F.hex(F.substring(bitmap, w * 8 + 1, F.lit(8))), 16, -10).cast("bigint"))


def _bitmap_place(id_: Column) -> Column:
    """An id's bit in its block's bitmap: bytes fill from their lowest bit, and a word's bytes stand from the highest."""
    return id_.bitwiseAND(64 * BLOCK_WORDS - 1).bitwiseXOR(F.lit(56).cast("bigint"))


def pack_words(ids: DataFrame) -> DataFrame:
    """(block, words): the Boolean dense form, one row for each block that has a set bit. Ids are not negative."""
    blocks = ids.filter("id IS NOT NULL").groupBy(F.shiftright("id", BLOCK_SHIFT).alias("block")).agg(F.bitmap_construct_agg(_bitmap_place(F.col("id"))).alias("bits"))
    return blocks.select("block", _words_of_bitmap(F.col("bits")).alias("words"))


def all_words(ids: DataFrame, max_id: int) -> DataFrame:
    """One row with the words of ids 0 to ``max_id``: blocks are packed in parallel and laid end to end, each word touched once."""
    if (many := (max_id >> BLOCK_SHIFT) + 1) <= FEW_BLOCKS:
        bits = [F.bitmap_construct_agg(F.when(F.shiftright("id", BLOCK_SHIFT) == k, _bitmap_place(F.col("id")))).alias(f"b{k}") for k in range(many)]
        packed = ids.filter(F.col("id").between(0, max_id)).agg(*bits)
        return packed.select(F.concat(*[_words_of_bitmap(F.col(f"b{k}")) for k in range(many)]).alias("words"))
    inside = ids.filter(F.col("id").between(0, max_id)).select(F.shiftright("id", BLOCK_SHIFT).alias("block"), _bitmap_place(F.col("id")).alias("at"))
    # every block stands there once without a place, so blocks without ids are noughts
    every = ids.sparkSession.range(0, (max_id >> BLOCK_SHIFT) + 1, 1, 1).select(F.col("id").alias("block"), F.lit(None).cast("bigint").alias("at"))
    blocks = inside.unionByName(every).groupBy("block").agg(F.bitmap_construct_agg("at").alias("bits")).select("block", _words_of_bitmap(F.col("bits")).alias("words"))
    laid = blocks.agg(F.array_sort(F.collect_list(F.struct("block", "words"))).alias("blocks"))
    return laid.select(F.flatten(F.transform("blocks", lambda b: b["words"])).alias("words"))


def unpack_words(blocks: DataFrame, block_words: int = BLOCK_WORDS) -> DataFrame:
    """(id): the set bits of word blocks."""
    words = blocks.select("block", F.posexplode("words").alias("w", "bits")).filter("bits <> 0")
    bits = words.select("block", "w", F.explode(F.filter(F.sequence(F.lit(0), F.lit(63)), lambda b: F.getbit(F.col("bits"), b) == 1)).alias("b"))
    return bits.select(((F.col("block") * block_words + F.col("w")) * 64 + F.col("b")).cast("bigint").alias("id"))


def test_bit(words: Column, offset: Column) -> Column:
    """Whether a bit of one block's words is set; the offset counts from the block's first vertex."""
    return F.getbit(F.get(words, F.shiftright(offset, 6).cast("int")), offset.bitwiseAND(63).cast("int")) == 1


def to_dense(vec: DataFrame, vertices: DataFrame, sr: Semiring) -> DataFrame:
    """A value for every vertex, zero where the vector has none."""
    return vertices.select("id").join(vec.select("id", "val"), "id", "left").select("id", F.coalesce("val", sr.zero_column()).alias("val"))


def to_sparse(vec: DataFrame, sr: Semiring) -> DataFrame:
    return vec.filter(F.col("val") != sr.zero_column())


class Converter:
    """Sparse or dense form by fill ratio and trend: dense when it rises above the switch, sparse when it falls below."""

    def __init__(self, m: int, switch: float = 0.01) -> None:
        self.m, self.switch, self.last, self.form = m, switch, 0.0, "sparse"

    def next(self, nnz: int) -> str:
        r = nnz / self.m if self.m else 0.0
        if r > self.last and r > self.switch:
            self.form = "dense"
        elif r < self.last and r < self.switch:
            self.form = "sparse"
        self.last = r
        return self.form


def ewise_mult(u: DataFrame, w: DataFrame, sr: Semiring) -> DataFrame:
    """Values where both vectors have one."""
    return u.alias("u").join(w.alias("w"), "id").select("id", sr.mul(F.col("u.val"), F.col("w.val")).alias("val"))


def ewise_add(u: DataFrame, w: DataFrame, sr: Semiring) -> DataFrame:
    """Values of the union of supports."""
    joined = u.select("id", F.col("val").alias("a")).join(w.select("id", F.col("val").alias("b")), "id", "full")
    return joined.select("id", F.when(F.col("a").isNull(), F.col("b")).when(F.col("b").isNull(), F.col("a")).otherwise(sr.add(F.col("a"), F.col("b"))).alias("val"))


def reduce(vec: DataFrame, sr: Semiring) -> DataFrame:
    """One row: the sum of all values, zero for an empty vector."""
    return vec.agg(F.coalesce(sr.agg(F.col("val")), sr.zero_column()).alias("val"))


def assign(visited: DataFrame, frontier: DataFrame, depth: int) -> DataFrame:
    """Visited labels with the frontier at ``depth``; old labels stay."""
    return visited.unionByName(frontier.select("id", F.lit(depth).alias("depth")))


def vec_union(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("id").union(b.select("id")).distinct()


def vec_intersect(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("id").intersect(b.select("id"))


def vec_difference(a: DataFrame, b: DataFrame, bag: bool = False) -> DataFrame:
    return a.select("id").exceptAll(b.select("id")) if bag else a.select("id").subtract(b.select("id"))


def prefix_sum(df: DataFrame, key: str, value: str, blocks: int = 16) -> DataFrame:
    """Exclusive running sum in the order of ``key``, in two levels: within ranges of keys, then over the ranges' totals."""
    from pyspark.sql import Window

    from ..runtime import persist

    ranged = persist(df.select(key, value).repartitionByRange(blocks, key).withColumn("part", F.spark_partition_id()))
    inside = Window.partitionBy("part").orderBy(key).rowsBetween(Window.unboundedPreceding, -1)
    totals = ranged.groupBy("part").agg(F.sum(value).alias("total"))
    # at most ``blocks`` rows: the only window without a partition
    before = totals.select("part", F.coalesce(F.sum("total").over(Window.partitionBy(F.lit(0)).orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    own = ranged.withColumn("own", F.coalesce(F.sum(value).over(inside), F.lit(0)))
    return own.join(F.broadcast(before), "part").select(key, value, (F.col("own") + F.col("base")).alias("before"))


def dense_ids(df: DataFrame, key: str, blocks: int = 16) -> DataFrame:
    """(key, id) with ids 0, 1, ... in the order of distinct keys, without a single-task sort."""
    keys = df.select(key).distinct().withColumn("one", F.lit(1).cast("bigint"))
    return prefix_sum(keys, key, "one", blocks).select(key, F.col("before").cast("bigint").alias("id"))
