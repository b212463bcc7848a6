"""Array kernels on Arrow text columns: words, lines and windows of many documents at once.

A batch is one byte buffer plus document offsets. Every function works on the whole buffer with
numpy and keeps document borders, so the cost is a few passes over the bytes whatever the shapes
of the documents are.
"""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U = np.uint64
#: Seed of the byte table, the odd base of the prefix hash, the mixing constants of splitmix64.
BYTE_SEED = 20240229
BASE = 0x9E3779B97F4A7C15 | 5
MIX_A = U(0xBF58476D1CE4E5B9)
MIX_B = U(0x94D049BB133111EB)
#: The white space of the word contract, space and 9 to 13.
WHITE = (32, 9, 10, 11, 12, 13)

SPACE = np.zeros(256, dtype=bool)
SPACE[list(WHITE)] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
BYTE_CODE = np.random.default_rng(BYTE_SEED).integers(1, 2**63, 256, dtype=np.int64).astype(U) * U(2) + U(1)

#: Where the C library can return freed memory on request.
_LIBC = ctypes.CDLL(None) if hasattr(ctypes.CDLL(None), "malloc_trim") else None
_powers: dict[str, np.ndarray] = {}


def mix(x: np.ndarray) -> np.ndarray:
    """splitmix64's finaliser."""
    with np.errstate(over="ignore"):
        x = x ^ (x >> U(30))
        x = x * MIX_A
        x = x ^ (x >> U(27))
        x = x * MIX_B
        return x ^ (x >> U(31))


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE**i and BASE**-i modulo 2**64 for i up to n."""
    if "up" not in _powers or len(_powers["up"]) <= n:
        size = -(-5 * (n + 1) // 4 >> 16) << 16 or 1 << 16  # workers keep it: a quarter to spare, not up to as much again
        with np.errstate(over="ignore"):
            for name, base in (("up", BASE), ("down", pow(BASE, -1, 2**64))):
                steps = np.full(size, U(base % 2**64))
                steps[0] = U(1)
                _powers[name] = np.multiply.accumulate(steps)
    return _powers["up"], _powers["down"]


def prefix_hash(codes: np.ndarray) -> np.ndarray:
    """H with H[j] - H[i] = sum of codes[t] * BASE**t over i <= t < j."""
    up, _ = powers(len(codes))
    out = np.zeros(len(codes) + 1, dtype=U)
    with np.errstate(over="ignore"):
        np.cumsum(codes * up[: len(codes)], out=out[1:])
    return out


def span_hash(prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hashes of codes[start:end], equal for equal contents wherever they stand."""
    _, down = powers(len(prefix))
    with np.errstate(over="ignore"):
        return mix((prefix[end] - prefix[start]) * down[start] + (end - start).astype(U) * MIX_B)


def text_buffer(column) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and len+1 offsets into them; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column.cast(pa.large_string()), "").cast(pa.large_binary())
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8)[at[0] : at[-1]] if data is not None and at[-1] > at[0] else np.zeros(0, np.uint8)
    return raw, at - at[0]


def slices(batch: pa.RecordBatch, column: str, limit: int = 4 << 20):
    """Runs of rows of about limit bytes of text; a longer text stands alone."""
    if not batch.num_rows:
        return
    size = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    first, total = 0, 0
    for i, n in enumerate(size.tolist()):
        if i > first and total + n > limit:
            yield batch.slice(first, i - first)
            first, total = i, 0
        total += n
    yield batch.slice(first)


def marks(flags: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of maximal runs of true flags that don't cross documents."""
    n = len(flags)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    border = np.zeros(n + 1, dtype=bool)
    border[offsets] = True
    start = flags.copy()
    start[1:] &= ~flags[:-1] | border[1:n]
    end = flags.copy()
    end[:-1] &= ~flags[1:] | border[1:n]
    return np.flatnonzero(start), np.flatnonzero(end) + 1


def owner(offsets: np.ndarray, at: np.ndarray) -> np.ndarray:
    """The document of each position."""
    return np.searchsorted(offsets, at, side="right") - 1


def words(raw: np.ndarray, offsets: np.ndarray, lower: bool = False):
    """start, end, document and 64-bit hash of every word."""
    start, end = marks(~SPACE[raw], offsets)
    codes = BYTE_CODE[LOWER[raw]] if lower else BYTE_CODE[raw]
    return start, end, owner(offsets, start), span_hash(prefix_hash(codes), start, end)


def per_document(docs: np.ndarray, n: int) -> np.ndarray:
    """n+1 offsets into an array sorted by document."""
    return np.searchsorted(docs, np.arange(n + 1))


def shingle_sets(raw: np.ndarray, offsets: np.ndarray, width: int):
    """Distinct shingles of width words (A-Z lower-cased) by document: sorted hashes and offsets.

    A document with fewer words has its whole sequence as one shingle; one without words has none.
    """
    n = len(offsets) - 1
    _, _, doc, code = words(raw, offsets, lower=True)
    total = prefix_hash(code)
    at = per_document(doc, n)
    count = np.diff(at)
    many = np.where(count >= width, count - width + 1, np.minimum(count, 1))
    where = np.repeat(at[:-1] - np.concatenate(([0], np.cumsum(many)[:-1])), many) + np.arange(many.sum())
    who = np.repeat(np.arange(n), many)
    end = np.minimum(where + width, at[1:][who])
    hashes = span_hash(total, where, end)
    order = np.lexsort((hashes, who))
    hashes, who = hashes[order], who[order]
    keep = np.ones(len(hashes), dtype=bool)
    keep[1:] = (hashes[1:] != hashes[:-1]) | (who[1:] != who[:-1])
    return hashes[keep], per_document(who[keep], n)


def merge_spans(start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The union of half-open spans as maximal runs (touching spans join)."""
    if not len(start):
        return start, end
    order = np.argsort(start, kind="stable")
    start, reach = start[order], np.maximum.accumulate(end[order])
    new = np.ones(len(start), dtype=bool)
    new[1:] = start[1:] > reach[:-1]
    last = np.append(np.flatnonzero(new)[1:] - 1, len(start) - 1)
    return start[new], reach[last]


def give_back() -> None:
    """Return freed memory to the system: a worker lives on after its task, and keeps it beside the next stage's otherwise."""
    pa.default_memory_pool().release_unused()
    if _LIBC is not None:
        _LIBC.malloc_trim(0)


def tidy(run):
    """run, with what it freed given back when its task ends."""

    def held(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return held


def whole_groups(batches, by: tuple[str, ...], rows: int):
    """Batches of about that many rows that never part a group; the input is sorted by the columns ``by``."""
    held: list[pa.RecordBatch] = []
    count = 0

    def joined() -> pa.RecordBatch:
        return pa.Table.from_batches(held).combine_chunks().to_batches()[0]

    for b in batches:
        if not b.num_rows:
            continue
        held.append(b)
        count += b.num_rows
        if count >= rows:
            whole = joined()
            edge = np.flatnonzero(borders(whole, by)) + 1
            if len(edge):
                done, begin = int(edge[-1]), 0
                for stop in [*edge[np.searchsorted(edge, np.arange(rows, done, rows))].tolist(), done]:
                    if stop > begin:
                        yield whole.slice(begin, stop - begin)
                        begin = stop
                held, count = [whole.slice(done)], whole.num_rows - done
            else:
                held = [whole]
    if held:
        yield joined()


def borders(batch: pa.RecordBatch, by: tuple[str, ...]) -> np.ndarray:
    """Whether each row but the last differs from the next in the columns ``by``."""
    out = np.zeros(batch.num_rows - 1, dtype=bool)
    for c in by:
        x = batch.column(c).to_numpy(zero_copy_only=False)
        out |= x[1:] != x[:-1]
    return out
