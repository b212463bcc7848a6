"""Runs of one unary letter: detection, compression and the rules that spell a run."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from canopy.model import letter
from canopy.operators.scan import beside, numbered, order

__all__ = ["order", "heads", "find_runs", "merge_runs", "compress_runs", "represent_runs", "run_weights"]


def heads(nodes: DataFrame, block: int | None = None, only=None) -> DataFrame:
    """nodes with ``first`` (a chain of unary letters begins), ``head`` (an island of one letter begins) and a running number ``_at``. ``only`` limits which letters make islands."""
    near = beside(numbered(nodes, "_at", block), {"_bs": F.col("sym"), "_br": F.col("rank")}, {}, block)
    unary = F.col("rank") == 1
    joined = unary & (F.col("_br") == 1) & (F.col("_bs") == F.col("sym"))
    joined = joined if only is None else joined & only
    return near.withColumn("first", unary & F.coalesce(F.col("_br") != 1, F.lit(True))).withColumn("head", ~F.coalesce(joined, F.lit(False))).drop("_bs", "_br")


def islands(marked: DataFrame, block: int | None = None) -> DataFrame:
    """The heads alone, with the length ``len`` of their island; a row below a unary one has the island's head as parent."""
    kept = beside(marked.where("head"), {"_bp": F.col("pre"), "_br": F.col("rank")}, {"_next": F.col("_at")}, block)
    out = kept.withColumn("len", F.coalesce(F.col("_next") - F.col("_at"), F.lit(1)).cast("int")).withColumn("parent", F.when(F.col("_br") == 1, F.col("_bp")).otherwise(F.col("parent")))
    return out.drop("_at", "_bp", "_br", "_next", "head", "first")


def find_runs(nodes: DataFrame, block: int | None = None) -> DataFrame:
    """(tree_id, head_pre, sym, len) of every maximal run, single nodes included."""
    return islands(heads(nodes, block), block).where("rank = 1").select("tree_id", F.col("pre").alias("head_pre"), "sym", "len")


def merge_runs(nodes: DataFrame, letters: list[int] | None = None, block: int | None = None) -> DataFrame:
    """Every run of two and more is one node; there ``base`` holds the letter before and ``len`` the length, else base is null."""
    only = None if letters is None else F.col("sym").isin(letters)
    cut = islands(heads(nodes, block, only), block)
    new = (F.col("rank") == 1) & (F.col("len") > 1)
    return cut.withColumn("base", F.when(new, F.col("sym"))).withColumn("sym", F.when(new, letter(F.lit("run"), F.col("sym"), F.col("len").cast("long"))).otherwise(F.col("sym")))


def compress_runs(nodes: DataFrame, letters: list[int] | None = None, block: int | None = None):
    """(nodes, new letters (sym, base, len)): every run of two and more becomes one node."""
    out = merge_runs(nodes, letters, block)
    return out.select(*nodes.columns), out.where("base is not null").select("sym", "base", "len").distinct()


def represent_runs(runs: DataFrame, scheme: str = "gap", accounting: str = "compact") -> DataFrame:
    """(base, m, parts, cost): the rules that spell the run letters of ``runs`` (base, len).

    direct: a run as its letters. binary: doubling letters up to the longest run, each length by its
    binary digits. gap: lengths sorted, doubling letters up to the widest gap, a letter for each gap and
    each length a gap's letter over the length before. parts are lengths of the letters on the right.
    compact counts letters of equal meaning once and makes no rule of one symbol; literal counts aliases.
    """
    lens = runs.select("base", F.col("len").cast("int").alias("len")).distinct()
    one = F.array(F.lit(1))
    digits = lambda m: F.filter(F.transform(F.sequence(F.lit(0), F.lit(30)), lambda i: F.when(F.call_function("shiftright", m, i).bitwiseAND(F.lit(1)) == 1, F.call_function("shiftleft", F.lit(1), i)).otherwise(0)), lambda p: p > 0)
    if scheme == "direct":
        return lens.select("base", F.col("len").alias("m"), F.array_repeat(F.lit(1), F.col("len")).alias("parts"), F.col("len").alias("cost"))
    if scheme == "gap":
        w = Window.partitionBy("base").orderBy("len")
        steps = lens.withColumn("before", F.coalesce(F.lag("len").over(w), F.lit(0))).withColumn("gap", F.col("len") - F.col("before"))
    else:
        steps = lens.withColumn("before", F.lit(0)).withColumn("gap", F.col("len"))
    top = steps.groupBy("base").agg(F.floor(F.log2(F.max("gap"))).cast("int").alias("top"))
    powers = top.where("top > 0").select("base", F.explode(F.sequence(F.lit(1), F.col("top"))).alias("i")).select("base", F.call_function("shiftleft", F.lit(1), F.col("i")).alias("m"), F.array(F.call_function("shiftleft", F.lit(1), F.col("i") - 1), F.call_function("shiftleft", F.lit(1), F.col("i") - 1)).alias("parts"))
    gaps = steps.select("base", F.col("gap").alias("m"), digits(F.col("gap")).alias("parts"))
    whole = steps.where("before > 0").select("base", F.col("len").alias("m"), F.array("gap", "before").alias("parts"))
    every = powers.withColumn("o", F.lit(0)).unionByName(gaps.withColumn("o", F.lit(1))).unionByName(whole.withColumn("o", F.lit(2)))
    if accounting == "compact":
        every = every.where((F.col("m") > 1) & (F.size("parts") > 1)).withColumn("n", F.row_number().over(Window.partitionBy("base", "m").orderBy("o", "parts"))).where("n = 1").drop("n")
    return every.select("base", "m", "parts", F.size("parts").alias("cost"))


def run_weights(runs: DataFrame) -> DataFrame:
    """(base, len, before, engine, direct, power): for each length of a letter the edge weights that could make it.

    engine: 1 + log2 of the gap to the length before; direct: the gap in single letters; power: 1 + log2 of the length.
    The least weight of a graph of lengths that uses any of these is at most what the engine's own edges weigh.
    """
    lens = runs.select("base", F.col("len").cast("long").alias("len")).distinct()
    held = lens.withColumn("before", F.coalesce(F.lag("len").over(Window.partitionBy("base").orderBy("len")), F.lit(0)))
    gap = F.col("len") - F.col("before")
    return held.select("base", "len", "before", (1 + F.log2(gap)).alias("engine"), gap.cast("double").alias("direct"), (1 + F.log2("len")).alias("power"))
