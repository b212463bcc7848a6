"""Packing token sequences by non-negative least squares over length combinations.

A document is cut into full windows and one remainder, so only the histogram of lengths 1 to window
matters. Shallow combinations of lengths that fill a window are the columns of a least squares problem
whose solution says how often each is used. Repeat counts are rounded down, what is left is packed
greedily, still by histogram, and the plan becomes a table of slots. Documents meet it by their
rank among pieces of equal length, so nothing but the histogram reaches the driver.
"""

from __future__ import annotations

import json
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from canopy.llm.bpe import byte_letters
from canopy.llm.common import BROADCAST_ROWS, cut, ship

WINDOW = 1024
END = 0
GRID = 64
ROWS_PER_SALT = 250_000
#: Fixed value: the splitting pattern of the byte-level vocabulary.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


@lru_cache(maxsize=2)
def encoder(path: str):
    """text -> uint32 ids, as the tokenizers library gives them with the file's special tokens.

    The ids of this vocabulary are its merge order, so the quicker library with ranks gives the same ids;
    a text it refuses (its regex engine gives up on some very long ones) goes to the other.
    """
    import tiktoken
    from tokenizers import Tokenizer

    with open(path, encoding="utf-8") as f:
        said = json.load(f)
    back = {c: b for b, c in enumerate(byte_letters())}
    special = {x["content"]: x["id"] for x in said["added_tokens"]}
    ranks = {bytes(back[c] for c in t): i for t, i in said["model"]["vocab"].items() if t not in special}
    quick = tiktoken.Encoding("window", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens=special)
    slow = []

    def ids(text: str) -> np.ndarray:
        try:
            return np.array(quick.encode(text, allowed_special="all"), dtype="<u4")
        except Exception:
            if not slow:
                slow.append(Tokenizer.from_file(path))
            return np.array(slow[0].encode(text, add_special_tokens=False).ids, dtype="<u4")

    return ids


def pieces(docs: DataFrame, path: str, window: int = WINDOW) -> DataFrame:
    """The pieces of each document's ids and end mark: full windows, then a remainder."""
    ship(docs.sparkSession)
    kind = dict(docs.dtypes)["doc_id"]

    def run(batches):
        ids = encoder(path)
        for batch in batches:
            rows, who = [], []
            for i, text in enumerate(pc.fill_null(batch.column("text"), "").to_pylist()):
                got = np.append(ids(text), np.uint32(END)).astype("<u4")
                for a in range(0, len(got), window):
                    part = got[a : a + window]
                    who.append(i)
                    rows.append((a, len(part), zlib.crc32(part.tobytes()), len(got)))
            cols = zip(*rows) if rows else [[]] * 4
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(pa.array(who, pa.int64())), *(pa.array(c, pa.int64()) for c in cols)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, start long, length long, ids_crc32 long, doc_tokens long")


def combinations(present: np.ndarray, window: int = WINDOW, grid: int = GRID) -> list[tuple[int, ...]]:
    """Pairs that fill the window, and triples with one length on a grid, of lengths that occur."""
    has = np.zeros(window + 1, dtype=bool)
    has[present] = True
    out = [(window - a, a) for a in range(1, window // 2 + 1) if has[a] and has[window - a]]
    for c in range(grid, window, grid):
        if has[c]:
            out += [tuple(sorted((a, window - c - a, c), reverse=True)) for a in range(1, (window - c) // 2 + 1) if has[a] and has[window - c - a]]
    return list(dict.fromkeys(out))


def least_squares(columns: list[tuple[int, ...]], target: np.ndarray, sweeps: int = 40) -> np.ndarray:
    """x >= 0 that makes the columns' sum near the target, by coordinate descent on the residual."""
    x = np.zeros(len(columns))
    rest = target.astype(float).tolist()
    weights = []
    for c in columns:
        m: dict[int, int] = {}
        for a in c:
            m[a] = m.get(a, 0) + 1
        weights.append((tuple(m.items()), sum(v * v for v in m.values())))
    for _ in range(sweeps):
        moved = 0.0
        for j, (m, norm) in enumerate(weights):
            step = max(-x[j], sum(rest[a] * v for a, v in m) / norm)
            if step:
                x[j] += step
                moved += abs(step)
                for a, v in m:
                    rest[a] -= step * v
        if moved < 0.5:
            break
    return x


def plan(histogram: dict[int, int], window: int = WINDOW) -> list[tuple[tuple[int, ...], int]]:
    """(lengths, repeats): each length used exactly as often as it occurs."""
    rest = np.zeros(window + 1, dtype=np.int64)
    for a, n in histogram.items():
        rest[a] = n
    out = [((window,), int(rest[window]))] if rest[window] else []
    rest[window] = 0
    columns = combinations(np.flatnonzero(rest), window)
    x = least_squares(columns, rest)
    for j in np.argsort(-x, kind="stable"):
        m: dict[int, int] = {}
        for a in columns[j]:
            m[a] = m.get(a, 0) + 1
        n = min(int(x[j] + 1e-9), *(int(rest[a]) // v for a, v in m.items()))
        if n > 0:
            out.append((columns[j], n))
            for a, v in m.items():
                rest[a] -= n * v
    while len(there := np.flatnonzero(rest)):
        first = int(there[-1])
        pattern, room, used = [first], window - first, {first: 1}
        at = len(there) - 1
        while at >= 0:
            a = int(there[at])
            if a <= room and rest[a] > used.get(a, 0):
                pattern.append(a)
                room -= a
                used[a] = used.get(a, 0) + 1
            else:
                at -= 1
        n = min(int(rest[a]) // v for a, v in used.items())
        out.append((tuple(pattern), n))
        for a, v in used.items():
            rest[a] -= n * v
    return out


def slots(patterns: list[tuple[tuple[int, ...], int]]) -> np.ndarray:
    """Rows (length, first rank, first sequence, offset), sorted: the pieces of a length by rank."""
    taken: dict[int, int] = {}
    out, sequence = [], 0
    for lengths, n in patterns:
        offset = 0
        for a in lengths:
            out.append((a, taken.get(a, 0), sequence, offset))
            taken[a] = taken.get(a, 0) + n
            offset += a
        sequence += n
    return np.array(sorted(out), dtype=np.int64).reshape(-1, 4)


def ranked(rows: DataFrame, total: int) -> DataFrame:
    """A gapless rank among rows of equal length. Lengths are salted, so one that holds a third of all rows is dealt over many tasks."""
    salts = max(1, -(-total // ROWS_PER_SALT))
    rows = rows.withColumn("salt", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32"), F.lit(salts)).cast("int"))
    tally = rows.groupBy("length", "salt").count()
    before = Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    base = tally.select("length", "salt", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("base"))
    if salts * WINDOW <= BROADCAST_ROWS:
        base = F.broadcast(base)
    inner = F.row_number().over(Window.partitionBy("length", "salt").orderBy("doc_id", "start", "ids_crc32"))
    return rows.withColumn("inner", inner).join(base, ["length", "salt"]).withColumn("rank", F.col("base") + F.col("inner") - 1).drop("salt", "base", "inner")


def pack(docs: DataFrame, path: str, window: int = WINDOW) -> DataFrame:
    """Every piece with its sequence and offset.

    A null text is an empty one and has the end mark alone. Repeated rows are packed as often as they
    occur; ranks among equal rows are interchangeable. An empty table gives no rows.
    """
    rows = cut(pieces(docs, path, window), "pieces")
    histogram = {int(a): int(n) for a, n in rows.groupBy("length").count().collect()}  # at most window rows
    table = docs.sparkSession.sparkContext.broadcast(slots(plan(histogram, window)))

    def run(batches):
        t = table.value
        key = t[:, 0] * (1 << 48) + t[:, 1]
        for batch in batches:
            length, rank = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("length", "rank"))
            at = np.searchsorted(key, length * (1 << 48) + rank, side="right") - 1
            seq = t[at, 2] + rank - t[at, 1] if len(at) else rank
            cols = [batch.column(c) for c in ("doc_id", "start", "length", "ids_crc32", "doc_tokens")]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(seq, pa.int64()), pa.array(t[at, 3] if len(at) else rank, pa.int64())], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"])

    kind = dict(docs.dtypes)["doc_id"]
    order = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", F.col("rank").cast("long").alias("rank")]
    return ranked(rows, sum(histogram.values())).select(*order).mapInArrow(run, f"doc_id {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")
