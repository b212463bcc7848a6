"""Forests, grammars and the helpers that cut lineage between phases.

A node is a row (tree_id, pre, parent, slot, sym, rank). In pre-order the only child of a unary node is the
next row of its tree, so chains are contiguous and stay so when the upper row of a merged group is kept.
A letter's id is the hash of what it stands for, so equal keys get equal letters in any tree, batch or
run without a global numbering.
"""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

NODE_COLUMNS = ("tree_id", "pre", "parent", "slot", "sym", "rank")

_own: list[str] = []


@dataclass
class Forest:
    """nodes, and the symbols(sym, kind, rank, name) of their letters."""

    nodes: DataFrame
    symbols: DataFrame


@dataclass
class Grammar:
    """rules(sym, phase, kind, rhs, cost, ...), symbols(sym, kind, rank, name, weight), starts(tree_id, sym, n), residual nodes of trees stopped early, and one dict of counts for each phase."""

    rules: DataFrame
    symbols: DataFrame
    starts: DataFrame
    residual: DataFrame
    run_letters: DataFrame
    stats: list[dict] = field(default_factory=list)


def scratch(spark: SparkSession) -> str:
    """The shared folder named by the session; a local one only where none is set and all runs in one process, as in tests."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    if not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    if not _own:
        _own.append(tempfile.mkdtemp(prefix="canopy-trees-"))
        atexit.register(lambda: shutil.rmtree(_own[0], ignore_errors=True))
    return f"file://{_own[0]}"


def settle(df: DataFrame) -> DataFrame:
    """Written to the shared folder and read back, so a phase never recomputes the one before. What nobody deletes before goes with the application."""
    spark = df.sparkSession
    path = f"{scratch(spark)}/canopy-trees/{uuid.uuid4().hex}"
    df.write.parquet(path)
    folder = spark._jvm.org.apache.hadoop.fs.Path(path)
    folder.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(folder)
    return spark.read.schema(df.schema).parquet(path)


def unsettle(df: DataFrame) -> None:
    """Delete the files behind a settled table, once nothing will read it again."""
    spark = df.sparkSession
    for f in df.inputFiles()[:1]:
        folder = spark._jvm.org.apache.hadoop.fs.Path(f).getParent()
        folder.getFileSystem(spark._jsc.hadoopConfiguration()).delete(folder, True)


def letter(*key) -> "F.Column":
    return F.xxhash64(*key)


def forest_of(labelled: DataFrame) -> Forest:
    """From rows (tree_id, pre, parent, slot, name, rank). A label with another rank is another letter."""
    named = labelled.withColumn("sym", letter(F.lit("input"), F.col("name"), F.col("rank")))
    symbols = named.groupBy("sym").agg(F.first("name").alias("name"), F.first("rank").alias("rank")).select("sym", F.lit("input").alias("kind"), "rank", "name")
    return Forest(named.select(F.col("tree_id").cast("long"), F.col("pre").cast("long"), F.col("parent").cast("long"), F.col("slot").cast("int"), "sym", F.col("rank").cast("int")), symbols)
