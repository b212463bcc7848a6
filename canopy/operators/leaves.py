"""Absorption of leaf children into their parents.

A letter's parameters keep the numbers they had in the input letter at the root of its pattern: what is absorbed
leaves a gap, and no sibling is touched. Equal keys leave equal gaps, so equal letters have equal parameters.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.model import letter


def leaf_keys(nodes: DataFrame, ordered: bool = True) -> DataFrame:
    """(tree_id, parent, leaves): every parent's absorbable children as sorted (slot, sym)."""
    leaves = nodes.where("rank = 0 and parent is not null")
    out = leaves.groupBy("tree_id", "parent").agg(F.array_sort(F.collect_list(F.struct("slot", "sym"))).alias("leaves"))
    return out if ordered else out.withColumn("multiset", F.array_sort(F.transform("leaves", lambda x: x["sym"])))


def merge_leaves(nodes: DataFrame, ordered: bool = True, key: tuple[int, list[tuple[int, int]]] | None = None) -> DataFrame:
    """All leaf children of a snapshot go at once; there ``f`` holds the letter before and ``leaves`` the absorbed (slot, sym, w), else f is null.

    A parent that becomes a leaf by it waits for the next phase. Unordered, places are no part of a letter's key. With ``key``,
    a letter and its leaves as (slot, sym), only parents of that letter with just these leaves absorb.
    """
    extra = [F.col(c) for c in ("w",) if c in nodes.columns]
    leaf = nodes.where("rank = 0 and parent is not null")
    lists = leaf.groupBy("tree_id", "parent").agg(F.array_sort(F.collect_list(F.struct("slot", "sym", *extra))).alias("leaves")).withColumnRenamed("parent", "pre")
    inner = nodes.where("rank > 0 or parent is null")
    joined = inner.join(lists.hint("merge"), ["tree_id", "pre"], "left")  # as many lists as parents, and long: never broadcast
    hit = F.col("leaves").isNotNull()
    if key is not None:
        want = F.array(*(F.struct(F.lit(i).alias("slot"), F.lit(c).alias("sym")) for i, c in key[1])).cast("array<struct<slot:int,sym:bigint>>")
        hit = hit & (F.col("sym") == key[0]) & (F.transform("leaves", lambda x: F.struct(x["slot"], x["sym"])) == want)
        joined = joined.withColumn("leaves", F.when(F.coalesce(hit, F.lit(False)), F.col("leaves")))
        hit = F.col("leaves").isNotNull()
    if not ordered:  # leaves stand first, by letter; siblings that stay are numbered anew
        gone = lists.select("tree_id", F.col("pre").alias("parent"), F.transform("leaves", lambda x: x["slot"]).alias("_gone"))
        joined = joined.join(gone, ["tree_id", "parent"], "left").withColumn("slot", (F.col("slot") - F.coalesce(F.size(F.filter("_gone", lambda s: s < F.col("slot"))), F.lit(0))).cast("int")).drop("_gone")
        by_letter = F.array_sort(F.transform("leaves", lambda x: F.struct(x["sym"], *(x[c.name] for c in leaf.select(*extra).schema))))
        joined = joined.withColumn("leaves", F.transform(by_letter, lambda x, i: F.struct((i + 1).alias("slot"), x["sym"].alias("sym"), *(x[c.name].alias(c.name) for c in leaf.select(*extra).schema))))
    shown = F.transform("leaves", lambda x: F.struct(x["slot"].alias("slot"), x["sym"].alias("sym")))
    out = joined.withColumn("f", F.when(hit, F.col("sym"))).withColumn("sym", F.when(hit, letter(F.lit("leaf"), F.col("sym"), shown)).otherwise(F.col("sym")))
    out = out.withColumn("rank", (F.col("rank") - F.when(hit, F.size("leaves")).otherwise(0)).cast("int"))
    if key is not None:  # leaves of other parents stay
        kept = leaf.join(out.where("f is not null").select("tree_id", F.col("pre").alias("parent")), ["tree_id", "parent"], "left_anti")
        out = out.unionByName(kept, allowMissingColumns=True)
    return out


def absorb_leaves(nodes: DataFrame, ordered: bool = True, key: tuple[int, list[tuple[int, int]]] | None = None):
    """(nodes, new letters (sym, f, leaves, rank))."""
    out = merge_leaves(nodes, ordered, key)
    fresh = out.where("f is not null").select("sym", "f", F.transform("leaves", lambda x: F.struct(x["slot"].alias("slot"), x["sym"].alias("sym"))).alias("leaves"), "rank").dropDuplicates(["sym"])
    return out.select(*nodes.columns), fresh
