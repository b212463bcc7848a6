"""Rows beside each other in pre-order, also where a single tree is too large for one task.

Small trees are windows by tree. A forest with a larger tree is cut into blocks of pre-order numbers; a block's first
and last rows go into a table of one row a block, whose own windows give every block the rows beyond its borders.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Nodes of a tree up to which it is left whole, and pre-order numbers in a block beyond.
BLOCK = 1 << 20


def block_of(block: int | None) -> list:
    return ["tree_id"] if block is None else ["tree_id", F.floor(F.col("pre") / block)]


def order(block: int | None = None):
    """A tree, or a block of it, in pre-order."""
    return Window.partitionBy(*block_of(block)).orderBy("pre")


def beside(nodes: DataFrame, before: dict[str, Column], after: dict[str, Column], block: int | None = None) -> DataFrame:
    """nodes with columns of the row before (names of ``before``) and of the row after, null at the tree's ends."""
    pick = lambda x: F.struct(*(c.alias(k) for k, c in x.items()))
    out = nodes
    if before:
        out = out.withColumn("_b", F.lag(pick(before)).over(order(block)))
    if after:
        out = out.withColumn("_a", F.lead(pick(after)).over(order(block)))
    if block is not None:
        blk = F.floor(F.col("pre") / block)
        ends = nodes.groupBy("tree_id", blk.alias("_blk")).agg(*([F.max_by(pick(before), "pre").alias("_last")] if before else []), *([F.min_by(pick(after), "pre").alias("_first")] if after else []))
        along = Window.partitionBy("tree_id").orderBy("_blk")  # a row for each block
        ends = ends.select("tree_id", "_blk", *([F.lag("_last").over(along).alias("_bb")] if before else []), *([F.lead("_first").over(along).alias("_aa")] if after else []))
        out = out.withColumn("_blk", blk).join(ends, ["tree_id", "_blk"]).drop("_blk")
        if before:
            out = out.withColumn("_b", F.coalesce("_b", "_bb")).drop("_bb")
        if after:
            out = out.withColumn("_a", F.coalesce("_a", "_aa")).drop("_aa")
    return out.select(*nodes.columns, *(F.col("_b").getField(k).alias(k) for k in before), *(F.col("_a").getField(k).alias(k) for k in after))


def numbered(nodes: DataFrame, name: str, block: int | None = None) -> DataFrame:
    """nodes with their running number in the tree."""
    if block is None:
        return nodes.withColumn(name, F.row_number().over(order()).cast("long"))
    blk = F.floor(F.col("pre") / block)
    many = nodes.groupBy("tree_id", blk.alias("_blk")).agg(F.count("*").alias("_n"))
    along = Window.partitionBy("tree_id").orderBy("_blk").rowsBetween(Window.unboundedPreceding, -1)
    many = many.select("tree_id", "_blk", F.coalesce(F.sum("_n").over(along), F.lit(0)).alias("_base"))
    return nodes.withColumn("_blk", blk).withColumn(name, F.row_number().over(order(block))).join(many, ["tree_id", "_blk"]).withColumn(name, F.col(name) + F.col("_base")).drop("_blk", "_base")
