"""Repeated passages by a depth-limited radix sort of suffixes.

Only windows of ``threshold`` tokens matter, so suffixes are ordered no deeper. The sort goes by
most significant digit. The first digit is a short gram, and not every suffix needs to be ordered by it:
of the grams in a window the one of least hash is its anchor, chosen by content alone, so equal windows have equal
anchors at equal places and one suffix in a few hundred stands for all. Groups of one are done.
Groups of equal anchors go on with the tokens around them: the suffixes from the gram on are ordered digit by digit
through the threshold, and so are the reversed prefixes before it, each pass splitting the groups of the pass before and
leaving out groups of one. Two windows with the gram at place p are equal just if they are in one group of prefixes
at depth p and in one of suffixes at depth threshold - p. Bytes are compared as they are, words by 64-bit codes.
A group too large for a task is dealt over several, and the windows of its parts are compared by 128-bit keys, so no group is cut.
"""

from __future__ import annotations

import hashlib
import sys

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.llm import kernels as K
from canopy.llm.common import cut, maybe_among, ship, temporary

BYTES, WORDS = "bytes", "words"
#: What is searched for in one pass: pairs of unit and threshold.
Units = tuple[tuple[str, int], ...]
#: First digit's length by unit.
GRAM = {BYTES: 64, WORDS: 8}
#: Anchors of one group that a task compares at once: 0.7 kB of context each, and about four times that in arrays, a tenth of a GB in all; two tasks stand beside a JVM that has grown to its full heap.
GROUP_LIMIT = 32_768
#: Bytes of text whose arrays are worked on at once; these fit a core's cache.
SLICE = 1 << 18
#: Contexts whose groups are compared together, many small ones or one large one.
TOGETHER = 8192
#: Contexts whose windows are hashed at once: a context has up to threshold windows, so a large group's arrays are made in pieces.
PIECE = 1024
#: Where a group's window keys are parted, so that they are compared a sixteenth at a time.
SHARE_EDGES = np.arange(1, 16).astype(K.U) << K.U(60)


def gram_of(unit: str, threshold: int) -> int:
    return min(GRAM[unit], threshold)


def tokens(raw: np.ndarray, offsets: np.ndarray, unit: str):
    """Codes, their offsets by document and, for words, where each begins."""
    if unit == BYTES:
        return raw, offsets, None
    start, _, doc, code = K.words(raw, offsets)
    return code, K.per_document(doc, len(offsets) - 1), start


def code_of(tok: np.ndarray, unit: str) -> np.ndarray:
    return K.BYTE_CODE[tok] if unit == BYTES else tok


def least_in_window(x: np.ndarray, w: int) -> np.ndarray:
    """Minimum of x[i : i + w] for each i, from block-wise running minima."""
    n = len(x)
    if n < w:
        return np.zeros(0, x.dtype)
    pad = np.concatenate((x, np.full(-n % w, np.iinfo(x.dtype).max, x.dtype))).reshape(-1, w)
    ahead = np.minimum.accumulate(pad, axis=1).ravel()
    back = np.minimum.accumulate(pad[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[: n - w + 1], ahead[w - 1 : n])


def anchors(tok: np.ndarray, at: np.ndarray, unit: str, threshold: int):
    """Document, place and gram hash of every anchor of every window."""
    gram = gram_of(unit, threshold)
    n = len(tok)
    none = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, K.U))
    if n < threshold:
        return none
    total = K.prefix_hash(code_of(tok, unit))
    where = np.arange(n - gram + 1)
    hashes = K.span_hash(total, where, where + gram)
    low = K.U((1 << 32) - 1)  # places, in the lower half; no Arrow string has as many tokens
    least = least_in_window((hashes & ~low) | where.astype(K.U), threshold - gram + 1)
    size = np.diff(at)
    many = np.maximum(size - threshold + 1, 0)
    first = np.repeat(at[:-1] - (np.cumsum(many) - many), many) + np.arange(many.sum())
    if not len(first):
        return none
    picked = (least[first] & low).astype(np.int64)
    doc = np.repeat(np.arange(len(size)), many)
    keep = np.ones(len(picked), dtype=bool)
    keep[1:] = (picked[1:] != picked[:-1]) | (doc[1:] != doc[:-1])
    return doc[keep], picked[keep] - at[doc[keep]], hashes[picked[keep]]


def text_keys(text):
    return F.xxhash64(text).alias("k1"), F.xxhash64(F.lit(7), F.length(text), text).alias("k2")


def find_anchors(texts: DataFrame, units: Units) -> DataFrame:
    """Anchors of every text for each unit; ``u`` numbers the unit, which is in the hash too."""

    def run(batches):
        for batch in batches:
            for part in K.slices(batch, "text", SLICE):
                raw, offsets = K.text_buffer(part.column("text"))
                for u, (unit, threshold) in enumerate(units):
                    tok, at, _ = tokens(raw, offsets, unit)
                    doc, place, h = anchors(tok, at, unit, threshold)
                    take = pa.array(doc)
                    yield pa.RecordBatch.from_arrays([*(part.column(c).take(take) for c in ("k1", "k2", "doc_id")), pa.array(place), pa.array((h ^ K.mix(np.array([u], K.U))).view(np.int64)), pa.array(np.full(len(doc), u, np.int32))], ["k1", "k2", "doc_id", "place", "h", "u"])

    return texts.select("k1", "k2", "doc_id", "text").mapInArrow(K.tidy(run), "k1 long, k2 long, doc_id long, place long, h long, u int")


CONTEXT = "h long, n long, u int, k1 long, k2 long, first long, left long, ctx binary"


def find_contexts(texts: DataFrame, units: Units) -> DataFrame:
    """For each anchor of ``list`` the bytes of all windows that hold it, with the gram's place in tokens among them."""

    def run(batches):
        for batch in batches:
            for part in K.slices(batch, "text", SLICE):
                raw, offsets = K.text_buffer(part.column("text"))
                lists = part.column("list").to_pylist()
                places = []
                for unit, _ in units:
                    if unit == BYTES:
                        places.append((offsets, None, None))
                    else:
                        start, end = K.marks(~K.SPACE[raw], offsets)
                        places.append((np.searchsorted(start, offsets), start, end))
                rows = []
                for i, found in enumerate(lists):
                    k1, k2 = part.column("k1")[i].as_py(), part.column("k2")[i].as_py()
                    for x in found:
                        (unit, threshold), (at, start, end) = units[x["u"]], places[x["u"]]
                        here = int(at[i]) + x["place"]
                        a, b = max(int(at[i]), here - (threshold - gram_of(unit, threshold))), min(int(at[i + 1]), here + threshold)
                        piece = raw[a:b] if unit == BYTES else raw[start[a] : end[b - 1]]
                        rows.append((x["h"], x["n"], x["u"], k1, k2, a - int(at[i]), here - a, piece.tobytes()))
                kinds = [pa.int64(), pa.int64(), pa.int32(), *[pa.int64()] * 4, pa.binary()]
                for f in range(0, max(len(rows), 1), 4096):
                    cols = list(zip(*rows[f : f + 4096])) or [[]] * 8
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], [c.split()[0] for c in CONTEXT.split(", ")])

    return texts.mapInArrow(K.tidy(run), CONTEXT)


def by_unit(batch: pa.RecordBatch, units: Units):
    """The rows of each unit, with its name and threshold. All rows of one group are of one unit."""
    u = column(batch, "u")
    for k, (unit, threshold) in enumerate(units):
        part = batch if (u == k).all() else batch.filter(pa.array(u == k))
        if part.num_rows:
            yield k, unit, threshold, part


def with_unit(out: pa.RecordBatch, k: int) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.full(out.num_rows, k, np.int32)), *out.columns], ["u", *out.schema.names])


def context_tokens(batch: pa.RecordBatch, unit: str) -> tuple[np.ndarray, np.ndarray]:
    """Tokens of the contexts (bytes, or codes of words) and offsets into them."""
    raw = pc.cast(batch.column("ctx"), pa.large_binary())
    _, off, data = raw.buffers()
    at = np.frombuffer(off, np.int64)[raw.offset : raw.offset + len(raw) + 1]
    flat = np.frombuffer(data, np.uint8)[at[0] : at[-1]]
    at = at - at[0]
    if unit == BYTES:
        return flat, at
    # words are hashed through arrays of 8 bytes for each byte of text: a piece at a time, or a large group's take a GB
    codes, many = [np.zeros(0, K.U)], [np.zeros(1, np.int64)]
    for f in range(0, len(raw), PIECE):
        edge = at[f : f + PIECE + 1]
        tok, of, _ = tokens(flat[edge[0] : edge[-1]], edge - edge[0], unit)
        codes.append(tok)
        many.append(np.diff(of))
    return np.concatenate(codes), np.cumsum(np.concatenate(many))


def column(batch: pa.RecordBatch, name: str) -> np.ndarray:
    return batch.column(name).to_numpy(zero_copy_only=False)


#: A second table of byte codes, for keys of 128 bits.
OTHER_CODE = K.mix(K.BYTE_CODE) | K.U(1)


def window_keys(batch: pa.RecordBatch, unit: str, threshold: int):
    """Row, start and both halves of the key of every window of the contexts. The key holds content, gram and the gram's place, so a window met through two anchors never equals itself."""
    flat, at = context_tokens(batch, unit)
    many = np.maximum(np.diff(at) - threshold + 1, 0)
    row = np.repeat(np.arange(len(many)), many)
    start = np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
    begin = at[:-1][row] + start
    halves = []
    with np.errstate(over="ignore"):
        place = K.mix(column(batch, "h").view(K.U))[row] ^ K.mix((column(batch, "left")[row] - start).astype(K.U) + K.U(1 << 40))
        for codes in (code_of(flat, unit), OTHER_CODE[flat] if unit == BYTES else K.mix(flat + K.U(1))):
            halves.append(K.span_hash(K.prefix_hash(codes), begin, begin + threshold) ^ place)
    return row, start, *halves


def cell_width(threshold: int) -> int:
    """Places that are looked at together before single windows are."""
    return max(1, threshold // 16)


def cell_keys(batch: pa.RecordBatch, unit: str, threshold: int):
    """Row, cell and both halves of the key of every cell of places: the tokens that all windows with the gram at these places share.

    Windows can only be equal where these are, and there are about a twentieth as many.
    """
    flat, at = context_tokens(batch, unit)
    left, reach, wide = column(batch, "left"), threshold - gram_of(unit, threshold), cell_width(threshold)
    here = at[:-1] + left
    low = np.arange(0, reach + 1, wide)
    high = np.minimum(low + wide - 1, reach)
    row, cell = np.nonzero(np.maximum(low, (threshold - (at[1:] - here))[:, None]) <= np.minimum(high, left[:, None]))
    begin, end = here[row] - low[cell], here[row] + threshold - high[cell]
    halves = []
    with np.errstate(over="ignore"):
        place = K.mix(column(batch, "h").view(K.U))[row] ^ K.mix(cell.astype(K.U) + K.U(1 << 40))
        for codes in (code_of(flat, unit), OTHER_CODE[flat] if unit == BYTES else K.mix(flat + K.U(1))):
            halves.append(K.span_hash(K.prefix_hash(codes), begin, end) ^ place)
    return row, cell, *halves


def among(mine: np.ndarray, also: np.ndarray, key: np.ndarray, other: np.ndarray) -> np.ndarray:
    """Whether each key, with its other half, is one of those given, which are sorted."""
    at = np.minimum(np.searchsorted(key, mine), len(key) - 1)
    return (key[at] == mine) & (other[at] == also)


def sides(batch: pa.RecordBatch, unit: str, threshold: int):
    """Digits and length of what follows each context's gram, gram included, and of what precedes it, read backwards."""
    tok, at = context_tokens(batch, unit)
    here, reach = at[:-1] + column(batch, "left"), threshold - gram_of(unit, threshold)
    out = []
    for depth, size, first, way in ((threshold, np.minimum(at[1:] - here, threshold), here, 1), (reach, np.minimum(here - at[:-1], reach), here - 1, -1)):
        wide = -(-depth // 8) * 8 if unit == BYTES else depth
        mat = np.zeros((len(here), wide), np.uint8 if unit == BYTES else K.U)
        step = np.arange(depth)[None]
        for f in range(0, len(here) if len(tok) else 0, PIECE):
            rows = slice(f, f + PIECE)
            mat[rows, :depth] = np.where(step < size[rows, None], np.take(tok, first[rows, None] + way * step, mode="clip"), 0)
        if unit == BYTES:  # in place: first byte first
            mat = mat.view(K.U)
            if sys.byteorder == "little":
                mat.byteswap(inplace=True)
        out += [mat, size]
    return out


def ordered(digits: np.ndarray, group: np.ndarray, per: int) -> tuple[np.ndarray, np.ndarray]:
    """Rank of each row by group and digits, and for each rank the tokens shared with the rank before (-1 in another group).

    One pass a digit: the groups that are left are split by it, and rows that stand alone leave.
    """
    m = len(group)
    order = np.argsort(group, kind="stable")
    which = group[order].copy()
    shared = np.full(m + 1, digits.shape[1] * per, np.int64)
    shared[0] = shared[m] = -1
    shared[1:m][which[1:] != which[:-1]] = -1
    pos = np.arange(m)
    pos = pos[(shared[pos] >= 0) | (shared[pos + 1] >= 0)]
    for d in range(digits.shape[1]):
        if not len(pos):
            break
        rows, c = order[pos], which[pos]
        key = digits[rows, d]
        same = c[1:] == c[:-1]
        if (same & (key[1:] < key[:-1])).any():
            o = np.lexsort((key, c))
            order[pos] = rows[o]
            key = key[o]
        parted = same & (key[1:] != key[:-1])
        if parted.any():
            x = key[1:][parted] ^ key[:-1][parted]
            shared[pos[1:][parted]] = d * per + (sum((x < K.U(1 << 8 * k)).astype(np.int64) for k in range(1, 8)) if per == 8 else 0)
            new = np.append(True, ~same | parted)
            which[pos] = np.cumsum(new)
            pos = pos[~(new & np.append(new[1:], True))]
    rank = np.empty(m, np.int64)
    rank[order] = np.arange(m)
    return rank, shared


def repeated_windows(batch: pa.RecordBatch, unit: str, threshold: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows, and [rows, places] whether the window with the gram at that place stands in another row too."""
    reach, per = threshold - gram_of(unit, threshold), 8 if unit == BYTES else 1
    after, n_after, before, n_before = sides(batch, unit, threshold)
    # one group for each anchor
    group = np.cumsum(np.append(0, borders_of(batch, ("h", "salt")))) if batch.num_rows else np.zeros(0, np.int64)
    (ra, sa), (rb, sb) = ordered(after, group, per), ordered(before, group, per)
    least = threshold - np.minimum(np.maximum(sa[ra], sa[ra + 1]), n_after)
    most = np.minimum(np.maximum(sb[rb], sb[rb + 1]), n_before)
    rows = np.flatnonzero(least <= most)
    hits = np.zeros((len(rows), reach + 1), dtype=bool)
    least, most, ra, rb = least[rows], most[rows], ra[rows], rb[rows]
    pair = np.bincount(group)[group[rows]] == 2  # two contexts share what each shares with its only neighbour, as far as both go
    ends = [np.full(group[-1] + 1, threshold) if len(group) else n_after for _ in range(2)]
    for x, n in zip(ends, (n_after, n_before)):
        np.minimum.at(x, group, n)
    places, mine = np.arange(reach + 1), group[rows][pair]
    hits[pair] = (places >= np.maximum(least[pair], threshold - ends[0][mine])[:, None]) & (places <= np.minimum(most[pair], ends[1][mine])[:, None])
    more = np.flatnonzero(~pair)
    for p in range(int(least[more].min()), int(most[more].max()) + 1) if len(more) else ():
        at = more[(least[more] <= p) & (p <= most[more])]
        if len(at) < 2:
            continue
        key = np.cumsum(sa[:-1] < threshold - p)[ra[at]] * (len(sb) + 1) + np.cumsum(sb[:-1] < p)[rb[at]]
        order = np.argsort(key, kind="stable")
        same = key[order][1:] == key[order][:-1]
        hits[at[order[1:][same]], p] = True
        hits[at[order[:-1][same]], p] = True
    return rows, hits


def borders_of(batch: pa.RecordBatch, by: tuple[str, ...]) -> np.ndarray:
    return K.borders(batch, by) if batch.num_rows > 1 else np.zeros(0, bool)


def place_runs(batch: pa.RecordBatch, rows: np.ndarray, hits: np.ndarray, threshold: int) -> pa.RecordBatch:
    """Maximal runs of places as token spans of their texts: a gram later in the window is a window that starts earlier."""
    found = [(np.zeros(0, np.int64),) * 3]
    for f in range(0, len(rows), PIECE):
        edge = np.diff(np.pad(hits[f : f + PIECE].view(np.int8), ((0, 0), (1, 1))), axis=1)
        (r, p0), (_, p1) = np.nonzero(edge == 1), np.nonzero(edge == -1)
        found.append((rows[f + r], p0, p1))
    r, p0, p1 = (np.concatenate(x) for x in zip(*found))
    gram = column(batch, "first")[r] + column(batch, "left")[r]
    take = pa.array(r)
    return pa.RecordBatch.from_arrays([batch.column("k1").take(take), batch.column("k2").take(take), pa.array(gram - (p1 - 1)), pa.array(gram - p0 + threshold)], ["k1", "k2", "s", "e"])


def runs(batch: pa.RecordBatch, row: np.ndarray, start: np.ndarray, hit: np.ndarray, threshold: int) -> pa.RecordBatch:
    """Maximal runs of repeated windows as token spans of their texts."""
    row, start = row[hit], start[hit]
    new = np.ones(len(row), dtype=bool)
    new[1:] = (row[1:] != row[:-1]) | (start[1:] != start[:-1] + 1)
    last = np.append(new[1:], True) if len(row) else new
    r = row[new]
    first = column(batch, "first")[r]
    take = pa.array(r)
    return pa.RecordBatch.from_arrays([batch.column("k1").take(take), batch.column("k2").take(take), pa.array(first + start[new]), pa.array(first + start[last] + threshold)], ["k1", "k2", "s", "e"])


def distinct_rows(batch: pa.RecordBatch) -> pa.RecordBatch:
    """One row for each anchor; rows that share an id and a text make copies of it."""
    a = np.stack([batch.column(c).to_numpy(zero_copy_only=False) for c in ("h", "k1", "k2", "first", "left")], 1)
    _, at = np.unique(a, axis=0, return_index=True)
    return batch if len(at) == batch.num_rows else batch.take(pa.array(np.sort(at)))


SPAN = "u int, k1 long, k2 long, s long, e long"
#: Of dealt groups, beside the spans found in each part: the contexts, and the keys of their cells.
FOUND = pa.schema([("u", pa.int32()), *((c, pa.int64()) for c in ("k1", "k2", "s", "e", "h", "salt", "n", "first", "left")), ("ctx", pa.binary()), ("key", pa.int64()), ("other", pa.int64())])
FOUND_SQL = "u int, k1 long, k2 long, s long, e long, h long, salt long, n long, first long, left long, ctx binary, key long, other long"


def found_rows(batch: pa.RecordBatch) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([batch.column(f.name) if f.name in batch.schema.names else pa.nulls(batch.num_rows, f.type) for f in FOUND], schema=FOUND)


def local_repeats(contexts: DataFrame, units: Units, group_limit: int) -> DataFrame:
    """Repeats inside each group or part of a group; parts go on with their cells' keys and their contexts, so that these are made and sent but once."""

    def run(batches):
        for batch in K.whole_groups(batches, ("h", "salt"), TOGETHER):
            for k, unit, threshold, part in by_unit(distinct_rows(batch), units):
                yield found_rows(with_unit(place_runs(part, *repeated_windows(part, unit, threshold), threshold), k))
                dealt = part.filter(pa.array(column(part, "n") > group_limit))
                for f in range(0, dealt.num_rows, PIECE):
                    yield found_rows(dealt.slice(f, PIECE))
                for one in single_groups(dealt):
                    for keys in distinct_keys(one, lambda piece: cell_keys(piece, unit, threshold)[2:]):
                        yield found_rows(keys)
            if batch.num_rows > 2 * TOGETHER:
                K.give_back()

    return contexts.mapInArrow(K.tidy(run), FOUND_SQL)


def single_groups(batch: pa.RecordBatch):
    if batch.num_rows:
        edge = np.concatenate(([0], np.flatnonzero(borders_of(batch, ("h", "salt"))) + 1, [batch.num_rows])).tolist()
        yield from (batch.slice(a, b - a) for a, b in zip(edge, edge[1:]))


KEYS = ("h", "salt", "key", "other")


def distinct_keys(batch: pa.RecordBatch, keys_of_piece):
    """Different keys of one part, whose pieces are given by their keys, as rows."""
    got = []
    for f in range(0, batch.num_rows, PIECE):
        found = np.unique(np.stack(keys_of_piece(batch.slice(f, PIECE)), 1), axis=0)
        got.append(np.split(found, np.searchsorted(found[:, 0], SHARE_EDGES)))
    for share in zip(*got):  # keys are sorted, so a share of them is as large as another and ends for all pieces at one key
        keys = np.unique(np.concatenate(share), axis=0).view(np.int64)
        for f in range(0, len(keys), 1 << 16):
            some = keys[f : f + (1 << 16)]
            same = [pa.array(np.full(len(some), batch.column(c)[0].as_py())) for c in ("h", "salt")]
            yield pa.RecordBatch.from_arrays([*same, pa.array(some[:, 0].copy()), pa.array(some[:, 1].copy())], KEYS)


def dealt_repeats(whole: DataFrame, cells: DataFrame, units: Units) -> DataFrame:
    """Repeats between the parts of groups that were dealt over several tasks.

    Cells of places come first, then the windows of those cells that two parts share: most windows reach into a text's own words and are never written.
    """
    def in_two_parts(keys: DataFrame) -> DataFrame:
        shared = keys.groupBy("key", "other").agg(F.min("salt").alias("lo"), F.max("salt").alias("hi")).where("lo < hi").select("key", "other")
        return keys.join(shared, ["key", "other"]).select(*KEYS)

    def opened(left: pa.Table, right: pa.Table):
        """Contexts of one part with their unit's number, name and threshold, and sorted keys."""
        batch = left.combine_chunks().to_batches()[0]
        k = batch.column("u")[0].as_py()
        key = right.column("key").to_numpy().view(K.U)
        order = np.argsort(key)
        return batch, k, *units[k], key[order], right.column("other").to_numpy().view(K.U)[order]

    def windows_of(left: pa.Table, right: pa.Table) -> pa.Table:
        kind = pa.schema([(c, pa.int64()) for c in KEYS])
        if not left.num_rows or not right.num_rows:
            return kind.empty_table()
        batch, _, unit, threshold, key, other = opened(left, right)

        def of_piece(piece: pa.RecordBatch):
            row, cell, mine, also = cell_keys(piece, unit, threshold)
            hit = np.zeros((piece.num_rows, threshold), bool)
            hit[row, cell] = among(mine, also, key, other)
            row, start, *halves = window_keys(piece, unit, threshold)
            kept = hit[row, (column(piece, "left")[row] - start) // cell_width(threshold)]
            return [x[kept] for x in halves]

        return pa.Table.from_batches(distinct_keys(batch, of_piece), kind)

    keys = cut(whole.groupBy("h", "salt").cogroup(in_two_parts(cells).groupBy("h", "salt")).applyInArrow(windows_of, "h long, salt long, key long, other long"), "window-keys")
    wanted = in_two_parts(keys)  # for one part at most GROUP_LIMIT x (threshold - gram + 1)

    def marked(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows or not right.num_rows:
            return pa.schema([("u", pa.int32()), *((c, pa.int64()) for c in ("k1", "k2", "s", "e"))]).empty_table()
        batch, k, unit, threshold, key, other = opened(left, right)
        found = []
        for f in range(0, batch.num_rows, PIECE):
            piece = batch.slice(f, PIECE)
            row, start, mine, also = window_keys(piece, unit, threshold)
            found.append(with_unit(runs(piece, row, start, among(mine, also, key, other), threshold), k))
        return pa.Table.from_batches(found)

    return whole.groupBy("h", "salt").cogroup(wanted.groupBy("h", "salt")).applyInArrow(marked, SPAN)


def repeated_spans(docs: DataFrame, units: Units, group_limit: int = GROUP_LIMIT):
    """(texts, spans): the distinct texts with a chance of repeats, and for each its list of token spans that are repeated anywhere, by unit."""
    ship(docs.sparkSession)
    text = F.coalesce(F.col("text"), F.lit(""))
    least = min(threshold if unit == BYTES else 2 * threshold - 1 for unit, threshold in units)
    texts = docs.select(*text_keys(text), F.coalesce(F.col("doc_id").cast("long"), F.lit(-1)).alias("doc_id"), text.alias("text")).where(F.octet_length("text") >= least)
    found = find_anchors(texts, units).groupBy("k1", "k2", "place", "h", "u").agg(F.min("doc_id").alias("doc_id"))
    found = cut(found, "anchors")
    again = cut(found.groupBy("h").agg(F.count("*").alias("n")).where("n > 1"), "again")  # read from a table, a frequent anchor's side of the join can be split
    lists = cut(found.join(again, "h").groupBy("k1", "k2", "doc_id").agg(F.collect_list(F.struct("place", "h", "n", "u")).alias("list")), "lists")  # bounded by a text's length
    near = maybe_among(texts, "k1", lists).join(lists, ["k1", "k2", "doc_id"])
    contexts = find_contexts(near.select("k1", "k2", "text", "list"), units)
    salts = F.ceil(F.col("n") / group_limit)
    dealt = contexts.withColumn("salt", F.when(F.col("n") <= group_limit, F.lit(0)).otherwise(F.pmod(F.xxhash64("k1", "k2", "first", "left"), salts)).cast("long"))
    most = again.agg(F.max("n")).first()[0] or 0
    grouped = dealt.repartition("h", "salt").sortWithinPartitions("h", "salt")
    if most <= group_limit:
        return texts, gathered(local_repeats(grouped, units, group_limit))
    found = cut(local_repeats(grouped, units, group_limit), "found")
    frequent = found.where("ctx is not null").select("u", "k1", "k2", "h", "salt", "n", "first", "left", "ctx")
    spans = found.where("s is not null").select("u", "k1", "k2", "s", "e")
    return texts, gathered(spans.union(dealt_repeats(frequent, found.where("key is not null").select(*(F.col(c).alias(f"{c}_") for c in KEYS)).toDF(*KEYS), units)))  # names of their own, or Spark takes the two for one table


def gathered(spans: DataFrame) -> DataFrame:
    return spans.groupBy("k1", "k2").agg(F.collect_set(F.struct("u", "s", "e")).alias("spans"))


def removed(raw: bytes, spans: list, unit: str, whole: bool, threshold: int) -> tuple[bytes, int, int, int]:
    """What is left, bytes removed, number of maximal runs removed and tokens in them."""
    flat = np.frombuffer(raw, np.uint8)
    if not (whole or spans):
        return raw, 0, 0, 0
    tok, at, begin = tokens(flat, np.array([0, len(flat)]), unit)
    if whole and len(tok) >= threshold:
        s, e = np.array([0]), np.array([len(tok)])
    elif spans:
        s, e = K.merge_spans(np.array([x["s"] for x in spans]), np.array([x["e"] for x in spans]))
    else:
        return raw, 0, 0, 0
    n_tokens = int((e - s).sum())
    if unit == WORDS:
        border = np.append(begin, len(flat))
        s, e = border[s], border[e]
    parts, last = [], 0
    for a, b in zip(s.tolist(), e.tolist()):
        parts.append(raw[last:a])
        last = b
    return b"".join([*parts, raw[last:]]), int((e - s).sum()), len(s), n_tokens


LOST = "k1 long, k2 long, n_removed long, n_spans long, kept_sha256 string, kept string, n_tokens long"


def cleaned(docs: DataFrame, units: Units, group_limit: int = GROUP_LIMIT, text_out: bool = False) -> DataFrame:
    """One row for each distinct text that loses something: what it loses by the first unit, what is left, and the tokens lost by the last unit."""
    with temporary() as kept_tables:
        texts, spans = repeated_spans(docs, units, group_limit)
        copies = texts.groupBy("k1", "k2").agg(F.count("*").alias("copies"), F.min("doc_id").alias("doc_id"))
        todo = cut(copies.join(cut(spans, "spans"), ["k1", "k2"], "left").where("copies > 1 or spans is not null").select("k1", "k2", "doc_id", "spans", (F.col("copies") > 1).alias("whole")), "todo")
        rows = maybe_among(texts, "k1", todo).join(todo, ["k1", "k2", "doc_id"])

        def run(batches):
            for batch in (part for b in batches for part in K.slices(b, "text", 1 << 20)):
                out = []
                for k1, k2, text, found, whole in zip(*(batch.column(c).to_pylist() for c in ("k1", "k2", "text", "spans", "whole"))):
                    raw = text.encode()
                    got = [removed(raw, [x for x in found or () if x["u"] == u], unit, whole, threshold) for u, (unit, threshold) in enumerate(units)]
                    kept, n, m, _ = got[0]
                    if n or got[-1][3]:
                        out.append((k1, k2, n, m, hashlib.sha256(kept).hexdigest(), kept.decode("utf-8", "ignore") if text_out else None, got[-1][3]))
                kinds = [pa.string() if c.endswith("string") else pa.int64() for c in LOST.split(", ")]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*out)) or [[]] * len(kinds), kinds)], [c.split()[0] for c in LOST.split(", ")])

        got = rows.select("k1", "k2", "text", "spans", "whole").mapInArrow(K.tidy(run), LOST)
        lost = cut(got.dropDuplicates(["k1", "k2"]), "cleaned")
        kept_tables.append(lost)
        return lost


def report(docs: DataFrame, threshold: int = 400, group_limit: int = GROUP_LIMIT, words: int = 50) -> DataFrame:
    """What each document loses when every byte inside a repeated string of ``threshold`` bytes goes.

    n_repeated_words counts the words inside passages of ``words`` words that stand elsewhere too, which may be of
    fewer bytes than the threshold. Null and empty texts lose nothing, nor do texts shorter than the threshold. A text that
    occurs in two rows is repeated as a whole. An empty table gives no rows.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    base = docs.select("doc_id", *text_keys(text), F.octet_length(text).cast("long").alias("n_bytes"), F.sha2(text, 256).alias("own"))
    lost = cleaned(docs, ((BYTES, threshold), (WORDS, words)), group_limit).drop("kept")
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("long")
    return base.join(lost, ["k1", "k2"], "left").select("doc_id", "n_bytes", zero("n_removed").alias("n_removed"), zero("n_spans").alias("n_spans"), F.coalesce("kept_sha256", "own").alias("kept_sha256"), zero("n_tokens").alias("n_repeated_words"))


def strip(docs: DataFrame, unit: str = WORDS, threshold: int = 50, group_limit: int = GROUP_LIMIT) -> DataFrame:
    """docs with the same columns and rows, repeated passages taken out of the texts. Null texts stay null."""
    text = F.coalesce(F.col("text"), F.lit(""))
    lost = cleaned(docs, ((unit, threshold),), group_limit, text_out=True).select(F.col("k1").alias("canopy_k1"), F.col("k2").alias("canopy_k2"), F.col("kept").alias("canopy_kept"), F.lit(True).alias("canopy_hit"))
    k1, k2 = text_keys(text)
    joined = docs.join(lost, (k1 == lost["canopy_k1"]) & (k2 == lost["canopy_k2"]), "left")
    return joined.withColumn("text", F.when(F.col("canopy_hit"), F.col("canopy_kept")).otherwise(F.col("text"))).select(docs.columns)
