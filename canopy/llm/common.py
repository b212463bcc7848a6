"""What the operators share: loading tables, shipping code, cutting lineage, checked broadcasts."""

from __future__ import annotations

import atexit
import contextlib
import os
import re
import shutil
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A side with more rows than this is never broadcast.
BROADCAST_ROWS = 200_000

#: Rows of a batch sent to Python. A batch of texts stands several times in a JVM and its worker, and the operators work on smaller slices anyway.
ARROW_ROWS = 4096

_shipped: dict[str, bool] = {}
_own: list[str] = []
_made: list[list[tuple[SparkSession, str]]] = []
_paths: dict[int, tuple[DataFrame, tuple[str, ...]]] = {}


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def ship(spark: SparkSession) -> None:
    """Send this package to the executors through Spark's own file server, once per application."""
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    _shipped[app] = True
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", ARROW_ROWS)
    top = Path(__file__).resolve().parent.parent
    folder = tempfile.mkdtemp(prefix="canopy-code-")  # the file server reads it as long as the application runs
    atexit.register(lambda: shutil.rmtree(folder, ignore_errors=True))
    out = os.path.join(folder, f"{top.name}_code.zip")
    with zipfile.ZipFile(out, "w") as z:
        for p in sorted(top.rglob("*.py")):
            z.write(p, p.relative_to(top.parent))
    spark.sparkContext.addPyFile(out)


def scratch_root(spark: SparkSession) -> str:
    """The shared folder named by the session; a local one only where none is set and all runs in one process, as in tests."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    if not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
    if not _own:
        _own.append(tempfile.mkdtemp(prefix="canopy-"))
        atexit.register(lambda d=_own[0]: shutil.rmtree(d, ignore_errors=True))
    return f"file://{_own[0]}"


def folder_of(spark: SparkSession, path: str):
    """The file system of a path, and the path, on the JVM's side."""
    folder = spark._jvm.org.apache.hadoop.fs.Path(path)
    return folder.getFileSystem(spark._jsc.hadoopConfiguration()), folder


@contextlib.contextmanager
def temporary():
    """Deletes, at the end, the tables that cut() made inside, but for those added to the list it gives. What leaves must be cut itself."""
    _made.append([])
    kept: list[DataFrame] = []
    try:
        yield kept
    finally:
        made, paths = _made.pop(), {p for df in kept for p in _paths.get(id(df), (None, ()))[1]}
        for spark, path in made:
            if path in paths:
                if _made:
                    _made[-1].append((spark, path))
            else:
                fs, folder = folder_of(spark, path)
                fs.delete(folder, True)
        if not _made:
            _paths.clear()


def cut(df: DataFrame, label: str) -> DataFrame:
    """Write df to the shared folder and read it back: a lost executor costs no recomputation upstream.

    What nobody deletes before goes with the application.
    """
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/canopy/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    fs, folder = folder_of(spark, path)
    fs.deleteOnExit(folder)
    out = spark.read.schema(df.schema).parquet(path)
    if _made:
        _made[-1].append((spark, path))
        _paths[id(out)] = (out, (path,))
    return out


def drop_cut(df: DataFrame) -> None:
    """Delete the files behind a table made by cut(), once nothing will read it again."""
    spark = df.sparkSession
    for f in df.inputFiles()[:1]:
        fs, file = folder_of(spark, f)
        fs.delete(file.getParent(), True)


def small_enough(df: DataFrame, rows: int = BROADCAST_ROWS) -> bool:
    """Whether df has at most that many rows; reads no more than it must."""
    return df.limit(rows + 1).count() <= rows


#: Bits of the table that stands for a set of keys: 2 MB in rows of 4 kB, whatever the number of keys.
SET_BITS, ROW_BITS = 1 << 24, 1 << 15


def maybe_among(df: DataFrame, column: str, keys: DataFrame) -> DataFrame:
    """df without most rows whose long ``column`` is not among the values of that name in keys; no row of one that is gets lost.

    The keys' hashes set bits of a table of constant size, which is broadcast. With very many keys all
    bits are set and everything passes, so it only ever saves work: what passes must still be joined.
    """
    bit = F.pmod(F.xxhash64(F.col(column)), F.lit(SET_BITS))
    table = keys.select((bit + 1).alias("b")).groupBy(F.bitmap_bucket_number("b").alias("_row")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("b")).alias("_bits"))
    at = F.col("_bit") % ROW_BITS
    byte = F.conv(F.hex(F.substring("_bits", F.floor(at / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    held = df.withColumn("_bit", bit).withColumn("_row", F.floor(F.col("_bit") / ROW_BITS) + 1).join(F.broadcast(table), "_row")
    return held.where(F.call_function("shiftright", byte, (at % 8).cast("int")).bitwiseAND(F.lit(1)) == 1).select(df.columns)


def crc_bucket(doc_id, modulus: int):
    """crc32 of doc_id as text, modulo modulus; -1 for a null id."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % modulus, F.lit(-1))
