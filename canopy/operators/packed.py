"""The phases of compress() over packed trees: a row holds many whole trees as arrays, and a phase is one pass over these rows.

Letters' ids are hashes of what they stand for, so packs need not know of each other to make the same letters, and the hashed
colouring needs sums over all packs and nothing else. Parents, slots and parameters are those of the engine by rows
(compressor.py), which goes on with forests that hold a tree too large for one task, and with every other configuration.
"""

from __future__ import annotations

import gc
import pickle
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.llm import kernels as K
from canopy.llm.common import ship
from canopy.model import scratch, settle
from canopy.operators import pairs as P

#: Nodes of a pack; a tree larger than that is a pack of its own.
PACK = 1 << 18
#: Pairs whose bits are counted at once.
PIECE = 1 << 17
#: Rows of rules handed over at once.
ROWS = 8192
STATE, RULE, START, USE = range(4)
#: What is written of new letters: whole rules, their right-hand sides alone, or only which labels' trees use them. HELD: of chains, their
#: right-hand sides stay with the pack, by numbers of its own, from which their ids follow; a row of them is written when the pack ends.
FULL, LEAN, NONE, HELD = "full", "lean", "none", "held"
#: Letters whose ids are compared at once, and most shares of them.
COMPARED, SHARES = 1 << 25, 6
#: Letters in use up to which a pack that holds its rules also keeps their ids; those of more follow from the rules.
KNOWN = 1 << 12
PART = pa.struct([("sym", pa.int64()), ("at", pa.int32())])
PARAM = pa.struct([("id", pa.int32()), ("off", pa.int64()), ("up", pa.int64()), ("at", pa.int32())])
OUT = pa.schema([
    ("what", pa.int32()), ("state", pa.binary()), ("tally", pa.list_(pa.int64())), ("tree_id", pa.int64()), ("label", pa.int64()), ("sym", pa.int64()), ("kind", pa.string()), ("rhs", pa.list_(PART)), ("cost", pa.int32()),
    ("rank", pa.int32()), ("weight", pa.int64()), ("params", pa.list_(PARAM)), ("own", pa.list_(PARAM)), ("weights", pa.list_(pa.int64())),
])
PARAMS_SQL = "array<struct<id:int,off:bigint,up:bigint,at:int>>"
OUT_SQL = f"what int, state binary, tally array<bigint>, tree_id bigint, label bigint, sym bigint, kind string, rhs array<struct<sym:bigint,at:int>>, cost int, rank int, weight bigint, params {PARAMS_SQL}, own {PARAMS_SQL}, weights array<bigint>"
COUNTS = ("nodes", "n0", "n1", "n2plus", "chains")

U = np.uint64
P1, P2, P3, P4, P5 = (U(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def rotl(x: np.ndarray, n: int) -> np.ndarray:
    return (x << U(n)) | (x >> U(64 - n))


def final(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> U(33))) * P2
    h = (h ^ (h >> U(29))) * P3
    return h ^ (h >> U(32))


def hash_long(x, seed) -> np.ndarray:
    """Spark's xxhash64 of longs, on top of what was hashed before."""
    x = np.atleast_1d(np.asarray(x, np.int64)).view(U)
    h = (np.asarray(seed, U) + P5 + U(8)) ^ (rotl(x * P2, 31) * P1)
    return final(rotl(h, 27) * P1 + P4)


def hash_int(x, seed) -> np.ndarray:
    x = np.atleast_1d(np.asarray(x, np.int64)).view(U) & U(0xFFFFFFFF)
    h = (np.asarray(seed, U) + P5 + U(4)) ^ (x * P1)
    return final(rotl(h, 23) * P2 + P3)


def hash_name(s: str) -> np.ndarray:
    """Of a name shorter than eight bytes, where Spark's hash functions start."""
    raw, h = s.encode(), np.array([42], U) + P5 + U(len(s.encode()))
    if len(raw) >= 4:
        h = rotl(h ^ (np.array([int.from_bytes(raw[:4], "little")], U) * P1), 23) * P2 + P3
        raw = raw[4:]
    for b in raw:
        h = rotl(h ^ (np.array([b], U) * P5), 11) * P1
    return final(h)


SEEDS = {k: hash_name(k) for k in ("run", "pair", "leaf", "dag", "digram")}


def ids(h: np.ndarray) -> np.ndarray:
    return h.view(np.int64)


def once(keys: np.ndarray, check: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Different letters among keys, where each stands first, and which one each key is."""
    u, first, which = np.unique(keys, return_index=True, return_inverse=True)
    if (check != check[first][which]).any():
        raise ValueError("one letter id for two keys")
    return u, first, which


class Letters:
    """The letters that a pack uses: ids, weights, parameters (one letter's beside each other), and the bits of the hashed colouring."""

    def __init__(self, sym, w, rank, param):
        self.sym, self.w, self.rank, self.param = sym, w, rank, param
        self.bits = (hash_int(5, hash_long(sym, 42)) & U(0xFFFFFFFF)).astype(np.uint32)

    def begin(self) -> np.ndarray:
        return np.concatenate(([0], np.cumsum(self.rank)))

    def cells(self, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The parameters of these letters: which of the letters each belongs to, and where it stands."""
        n, b = self.rank[codes], self.begin()[codes]
        row = np.repeat(np.arange(len(codes)), n)
        return row, np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(b, n)

    def of(self, codes: np.ndarray) -> pa.Array:
        row, at = self.cells(codes)
        return param_lists(np.bincount(row, minlength=len(codes)), [x[at] for x in self.param])

    def chosen(self, codes: np.ndarray) -> Letters:
        _, at = self.cells(codes)
        return Letters(self.sym[codes], self.w[codes], self.rank[codes], [x[at] for x in self.param])

    def add(self, sym, w, rank, param) -> np.ndarray:
        """Codes of these letters, each of them once; those that are there already keep their code."""
        order = np.argsort(self.sym)
        at = np.minimum(np.searchsorted(self.sym[order], sym), max(len(order) - 1, 0))
        codes = order[at]
        new = self.sym[codes] != sym
        codes[new] = len(self.sym) + np.arange(new.sum())
        cell = np.repeat(new, rank)
        self.__init__(np.concatenate((self.sym, sym[new])), np.concatenate((self.w, w[new])), np.concatenate((self.rank, rank[new])), [np.concatenate((x, y[cell])) for x, y in zip(self.param, param)])
        return codes


def list_array(many: np.ndarray, values: pa.Array) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(many))).astype(np.int32)), values)


def param_lists(many: np.ndarray, param: list[np.ndarray]) -> pa.Array:
    return list_array(many, pa.StructArray.from_arrays([pa.array(x.astype(np.int32 if i in (0, 3) else np.int64)) for i, x in enumerate(param)], fields=list(PARAM)))


def parts(many: np.ndarray, sym: np.ndarray, at: np.ndarray) -> pa.Array:
    return list_array(many, pa.StructArray.from_arrays([pa.array(sym), pa.array(at.astype(np.int32))], fields=list(PART)))


def rows_of(what: int, n: int, **columns) -> pa.RecordBatch:
    columns["what"] = pa.array(np.full(n, what, np.int32))
    held = [columns[f.name] if f.name in columns else pa.nulls(n, f.type) for f in OUT]
    return pa.RecordBatch.from_arrays([x if isinstance(x, pa.Array) else pa.array(x, f.type) for x, f in zip(held, OUT)], schema=OUT)


def sums(row, key, x_row, x_key, x_n, side: str) -> np.ndarray:
    """For each cell the total of the x of its row whose key is less ("left"), or no greater ("right")."""
    rank = np.unique(np.concatenate((key, x_key)), return_inverse=True)[1].reshape(-1)
    span = len(rank) + 1
    at, x = row * span + rank[: len(key)], x_row * span + rank[len(key) :]
    order = np.argsort(x, kind="stable")
    x, total = x[order], np.concatenate(([0], np.cumsum(x_n[order])))
    return total[np.searchsorted(x, at, side)] - total[np.searchsorted(x, row * span)]


class Pack:
    """Whole trees in pre-order. ``parent`` is a place in the pack, below zero at a root; a unary node's child is the next node."""

    def __init__(self, tree, label, code, rank, parent, slot, letters):
        self.tree, self.label, self.code, self.rank, self.parent, self.slot, self.letters = tree, label, code, rank, parent, slot, letters
        self.out: list[pa.RecordBatch] = []
        self.rules = FULL
        self.group, self.stop = 0, 1
        self.own: Own | None = None

    def dump(self) -> bytes:
        """Ranks are the letters', and parents are near: little is left once it is deflated."""
        x = self.letters
        near = np.where(self.parent >= 0, np.arange(len(self.code), dtype=np.int32) - self.parent, np.int32(0))
        if self.own is not None:
            return pickle.dumps((self.own.dump(), deflated((self.tree, self.label, planes(self.code), near, self.slot, x.sym if len(x.sym) <= KNOWN else None))), 5)
        return deflated((self.tree, self.label, self.code, near, self.slot, x.sym, x.w, x.rank, x.param, self.group, self.stop))

    @staticmethod
    def load(raw: bytes) -> Pack:
        size, held = pickle.loads(raw)
        if not isinstance(size, int):
            own, (tree, label, code, near, slot, sym) = Own.load(size), inflated(held)
            code, letters = unplanes(code), own.letters(sym)
            parent = np.where(near > 0, np.arange(len(code), dtype=np.int32) - near, np.int32(-1))
            pack = Pack(tree, label, code, letters.rank[code].astype(np.int32), parent, slot, letters)
            pack.own = own
            return pack
        tree, label, code, near, slot, sym, w, rank, param, group, stop = pickle.loads(pa.decompress(held, size, "zstd"))
        parent = np.where(near > 0, np.arange(len(code), dtype=np.int32) - near, np.int32(-1))
        pack = Pack(tree, label, code, rank[code].astype(np.int32), parent, slot, Letters(sym, w, rank, param))
        pack.group, pack.stop = group, stop
        return pack

    def keep(self, kept: np.ndarray) -> None:
        """Only these nodes; what stood below a node that goes hangs below the one kept before it."""
        to = np.cumsum(kept, dtype=np.int32) - 1
        up = self.parent[kept]
        self.parent = np.where(up >= 0, to[up], np.int32(-1))
        self.code, self.rank, self.slot = self.code[kept], self.rank[kept], self.slot[kept]

    def made(self, kind: str, place: np.ndarray, which: np.ndarray, sym, w, rank, param, rhs, cost, own, weights, check, local) -> None:
        """New letters at these nodes, with their rules; ``check`` is a second hash of what they stand for, ``local`` has their parts by code."""
        if self.own is not None:
            many, codes, at = local()
            known = len(self.letters.sym)
            codes = self.own.add(kind, many, codes, at), self.letters.add(sym, w, rank, param)
            self.own.number = np.concatenate((self.own.number, codes[0][codes[1] >= known]))
            self.code[place] = codes[1][which].astype(np.int32)
            return
        if self.rules != NONE:
            more = {"weight": w, "params": param_lists(rank, param), "own": own(), "weights": weights()} if self.rules == FULL else {}
            self.out.append(rows_of(RULE, len(sym), label=np.full(len(sym), self.group), rank=rank.astype(np.int32), sym=sym, kind=pa.array([kind] * len(sym), pa.string()), rhs=rhs(), cost=cost, **more))
        codes = self.letters.add(sym, w, rank, param)
        if self.label is not None:
            tree = np.cumsum(self.parent < 0)[place] - 1
            names, label = np.unique(self.label, return_inverse=True)
            used = np.unique(which * np.int64(len(names)) + label[tree])
            s = used // len(names)
            self.out.append(rows_of(USE, len(used), label=names[used % len(names)], sym=sym[s], cost=cost[s], weight=w[s], rank=(check[s] >> U(48)).astype(np.int32)))
        self.code[place] = codes[which].astype(np.int32)

    def ended(self) -> None:
        """Trees of one letter leave with it; those of at most ``stop`` nodes with their number of nodes."""
        root = np.flatnonzero(self.parent < 0)
        size = np.diff(np.append(root, len(self.code)))
        done = size <= self.stop
        label = np.full(len(root), self.group) if self.label is None else self.label
        if self.own is not None:
            self.own.ended(self.tree[done], self.code[root[done]])
        left = {"sym": self.letters.sym[self.code[root[done]]]} if self.stop == 1 else {"weight": size[done]}
        if self.own is None:
            self.out.append(rows_of(START, int(done.sum()), label=label[done], tree_id=self.tree[done], **left))
        self.keep(np.repeat(~done, size))
        self.tree, self.label = self.tree[~done], None if self.label is None else self.label[~done]
        used = np.zeros(len(self.letters.sym), bool)
        used[self.code] = True
        self.code = (np.cumsum(used, dtype=np.int32) - 1)[self.code]
        self.letters = self.letters.chosen(np.flatnonzero(used))
        if self.own is not None:
            self.own.number = self.own.number[used]

    def counts(self) -> list[int]:
        unary = self.rank == 1
        first = unary.copy()
        first[1:] &= ~unary[:-1]
        return [len(self.code), int((self.rank == 0).sum()), int(unary.sum()), int((self.rank > 1).sum()), int(first.sum())]

    def runs(self) -> None:
        unary, x = self.rank == 1, self.letters
        head = np.ones(len(self.code), bool)
        head[1:] = ~(unary[1:] & unary[:-1] & (self.code[1:] == self.code[:-1]))
        n = np.diff(np.append(np.flatnonzero(head), len(head)))
        self.keep(head)
        place = np.flatnonzero(n > 1)
        if not len(place):
            return
        key, which = np.unique(self.code[place] * np.int64(int(n.max()) + 1) + n[place], return_inverse=True)
        base, n = key // (int(n.max()) + 1), key % (int(n.max()) + 1)
        sym = ids(hash_long(n, hash_long(x.sym[base], SEEDS["run"])))
        once(sym, key)
        at = x.begin()[base]
        id_, off, up, hang = (p[at] for p in x.param)
        self.made("run", place, which, sym, n * x.w[base], np.ones(len(key), np.int64), [id_, n * off, (n - 1) * off + up, hang], lambda: parts(np.ones(len(key), np.int64), x.sym[base], n), n.astype(np.int32), lambda: x.of(base), lambda: list_array(np.ones(len(key), np.int64), pa.array(x.w[base])), hash_long(n, hash_long(x.sym[base], 77)), lambda: (np.ones(len(key), np.int64), base, n))

    def arcs(self) -> np.ndarray:
        """Unary nodes with a unary child, after runs."""
        return np.flatnonzero((self.rank[:-1] == 1) & (self.rank[1:] == 1))

    def covered(self) -> list[int]:
        """Arcs, and for every bit how many it takes from up to down and from down to up."""
        top, bits = self.arcs(), self.letters.bits
        got = np.zeros((P.TRIES, 2), np.int64)
        for f in range(0, len(top), PIECE):
            a, b = bits[self.code[top[f : f + PIECE]]], bits[self.code[top[f : f + PIECE] + 1]]
            for j, x in enumerate((a & ~b, b & ~a)):
                got[:, j] += np.unpackbits(x.astype("<u4").view(np.uint8).reshape(-1, 4), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        return [len(top), *got.reshape(-1).tolist()]

    def pairs(self, colour: P.Colouring) -> None:
        x = self.letters
        if colour.bit is not None:
            up = (x.bits >> np.uint32(colour.bit)) & np.uint32(1) == 1
        else:
            up = np.bitwise_count(hash_int(11, hash_long(x.sym, 42)) & U(0xFFFFFFFF) & U(colour.seed)) % 2 == 0
        up = (~up if colour.turned else up)[self.code]
        top = self.arcs()
        top = top[up[top] & ~up[top + 1]]
        if not len(top):
            return
        key, which = np.unique(self.code[top] * np.int64(len(x.sym)) + self.code[top + 1], return_inverse=True)
        a, b = key // len(x.sym), key % len(x.sym)
        sym = ids(hash_long(x.sym[b], hash_long(x.sym[a], SEEDS["pair"])))
        once(sym, key)
        p, q = x.begin()[a], x.begin()[b]
        off, two = x.param[1][p], np.full(len(key), 2)
        param = [x.param[0][q], off + x.param[1][q], off + x.param[2][q], x.param[3][q]]
        self.made("pair", top, which, sym, x.w[a] + x.w[b], np.ones(len(key), np.int64), param, lambda: parts(two, x.sym[np.ravel((a, b), "F")], np.tile([1, 2], len(key))), two.astype(np.int32), lambda: x.of(a), lambda: list_array(two, pa.array(x.w[np.ravel((a, b), "F")])), hash_long(x.sym[b], hash_long(x.sym[a], 78)), lambda: (two, np.ravel((a, b), "F"), np.tile([1, 2], len(key))))
        kept = np.ones(len(self.code), bool)
        kept[top + 1] = False
        self.keep(kept)

    def leaves(self) -> None:
        x = self.letters
        leaf = np.flatnonzero((self.rank == 0) & (self.parent >= 0))
        if not len(leaf):
            return
        leaf = leaf[np.argsort(self.parent[leaf], kind="stable")]
        place, first, many = np.unique(self.parent[leaf], return_index=True, return_counts=True)
        slot, code = self.slot[leaf].astype(np.int64), self.code[leaf]
        # different keys: a letter and its leaves, by the letter's id and by a second hash
        order = np.argsort(-many, kind="stable")
        deep = many[order]
        h, check = hash_long(x.sym[self.code[place]], SEEDS["leaf"])[order], hash_long(x.sym[self.code[place]], 77)[order]
        for j in range(int(many.max())):
            k = int(np.searchsorted(-deep, -j, "left"))
            cell = first[order[:k]] + j
            h[:k] = hash_long(x.sym[code[cell]], hash_int(slot[cell], h[:k]))
            check[:k] = hash_long(x.sym[code[cell]], hash_int(slot[cell], check[:k]))
        back = np.empty_like(order)
        back[order] = np.arange(len(order))
        sym, at, which = once(ids(h[back]), check[back])
        f, many_u = self.code[place[at]], many[at]
        x_row = np.repeat(np.arange(len(at)), many_u)
        cell = np.arange(len(x_row)) - np.repeat(np.cumsum(many_u) - many_u, many_u) + np.repeat(first[at], many_u)
        x_slot, x_code = slot[cell], code[cell]
        w = x.w[x_code]
        row, held = x.cells(f)
        id_, off, up, hang = (p[held].astype(np.int64) for p in x.param)
        key, want = (row << 32) + id_, (x_row << 32) + x_slot  # a letter's parameters stand by their numbers
        hit = np.minimum(np.searchsorted(key, want), max(len(key) - 1, 0))
        if not len(key) or (key[hit] != want).any():
            raise ValueError("a leaf at no parameter")
        rest = np.ones(len(row), bool)
        rest[hit] = False
        new_off, new_up = off + sums(row, id_, x_row, x_slot, w, "left"), up + sums(row, up, x_row, off[hit], w, "right")
        param = [y[rest] for y in (id_, new_off, new_up, hang)]
        n = many_u + 1
        head = np.cumsum(n) - n
        flat_sym, flat_at, flat_w = np.empty(int(n.sum()), np.int64), np.zeros(int(n.sum()), np.int64), np.empty(int(n.sum()), np.int64)
        body = np.ones(len(flat_sym), bool)
        body[head] = False
        flat_code = np.empty(len(flat_sym), np.int64)
        flat_code[head], flat_code[body] = f, x_code
        flat_sym[head], flat_sym[body], flat_at[body], flat_w[head], flat_w[body] = x.sym[f], x.sym[x_code], x_slot, x.w[f], w
        total = x.w[f] + np.bincount(x_row, w, len(at)).astype(np.int64)
        self.made("leaf", place, which, sym, total, x.rank[f] - many_u, param, lambda: parts(n, flat_sym, flat_at), n.astype(np.int32), lambda: x.of(f), lambda: list_array(n, pa.array(flat_w)), check[back][at], lambda: (n, flat_code, flat_at))
        self.rank[place] -= many.astype(np.int32)
        kept = np.ones(len(self.code), bool)
        kept[leaf] = False
        self.keep(kept)

    def flush(self) -> Iterator[pa.RecordBatch]:
        while self.out:
            x = self.out.pop(0)
            yield from (x.slice(f, ROWS) for f in range(0, x.num_rows, ROWS))

    def begun(self) -> Iterator[pa.RecordBatch]:
        """Done trees leave; runs of the phase are made, and what the phase needs to know of all packs is counted."""
        self.ended()
        yield from self.flush()
        if len(self.code):
            counts = self.counts()
            self.runs()
            yield from self.flush()
            yield rows_of(STATE, 1, label=[self.group], state=pa.array([self.dump()], pa.binary()), tally=pa.array([counts + self.covered()], pa.list_(pa.int64())))
        elif self.own is not None:
            yield rows_of(RULE, 1, label=[self.group], weight=[self.own.count()], state=pa.array([self.own.dump()], pa.binary()))


def deflated(x) -> bytes:
    raw = pickle.dumps(x, 5)
    return pickle.dumps((len(raw), pa.compress(raw, "zstd", asbytes=True)), 5)


def inflated(raw: bytes):
    size, held = pickle.loads(raw)
    return pickle.loads(pa.decompress(held, size, "zstd"))


def planes(x: np.ndarray) -> bytes:
    """Numbers byte by byte: all lowest bytes, then all next ones, for the high ones are mostly nothing."""
    return np.ascontiguousarray(x.astype("<i4").view(np.uint8).reshape(-1, 4).T).tobytes()


def unplanes(raw: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(4, -1).T).view("<i4").reshape(-1).astype(np.int32)


class Own:
    """The rules of a pack of chains, a block for each step of a phase. Letters are numbered as they come: those of the input, then block by block."""

    def __init__(self, sym: np.ndarray, rank: np.ndarray):
        self.sym, self.rank = sym, rank
        self.number = np.arange(len(sym), dtype=np.int32)  # of the letters in use
        self.blocks: list[tuple[str, int, bytes]] = []
        self.starts: list[tuple[np.ndarray, np.ndarray]] = []

    def dump(self) -> bytes:
        """Blocks were deflated when they were made, and go from phase to phase as they are."""
        return pickle.dumps((self.blocks, deflated((self.sym, self.rank, self.number, self.starts))), 5)

    @staticmethod
    def load(raw: bytes) -> Own:
        blocks, more = pickle.loads(raw)
        own = Own.__new__(Own)
        own.blocks, (own.sym, own.rank, own.number, own.starts) = blocks, inflated(more)
        return own

    def count(self) -> int:
        return len(self.sym) + sum(b[1] for b in self.blocks)

    def add(self, kind: str, many, codes, at) -> np.ndarray:
        """The numbers of a block's letters. First parts are in order, so their steps are small."""
        number, head = self.number[codes], np.cumsum(many) - many
        first = number[head]
        rest = np.ones(len(number), bool)
        rest[head] = False
        begin = self.count()
        self.blocks.append((kind, len(many), deflated(tuple(planes(x) for x in (many, np.diff(first, prepend=0), number[rest], at)))))
        return np.arange(begin, begin + len(many), dtype=np.int32)

    def ended(self, tree: np.ndarray, code: np.ndarray) -> None:
        if len(tree):
            self.starts.append((tree, self.number[code]))

    def opened(self) -> Iterator[tuple]:
        """(kind, number of the first letter, parts of each, parts by number, at) of each block."""
        begin = len(self.sym)
        for kind, n, raw in self.blocks:
            many, first, rest, at = inflated(raw)
            many = unplanes(many).astype(np.int64)
            head = np.cumsum(many) - many
            part, body = np.empty(int(many.sum()), np.int32), np.ones(int(many.sum()), bool)
            body[head] = False
            part[head], part[body] = np.cumsum(unplanes(first)), unplanes(rest)
            yield kind, begin, many, part, unplanes(at).astype(np.int64)
            begin += n

    def hashed(self, other: bool = False) -> tuple[np.ndarray, np.ndarray]:
        """All letters' ids by number, and with ``other`` a second hash of what the made ones stand for."""
        sym = np.concatenate((self.sym, np.zeros(self.count() - len(self.sym), np.int64)))
        out = sym.copy()
        for kind, begin, many, part, at in self.opened():
            head = np.cumsum(many) - many
            for to, seed in ((sym, SEEDS[kind]), (out, hash_int(77, SEEDS[kind])))[: 1 + other]:
                h = hash_long(sym[part[head]], seed)
                if kind == "run":
                    h = hash_long(at, h)
                elif kind == "pair":
                    h = hash_long(sym[part[head + 1]], h)
                else:
                    for j in range(1, int(many.max())):
                        k = many > j
                        cell = head[k] + j
                        h[k] = hash_long(sym[part[cell]], hash_int(at[cell], h[k]))
                held = ids(h)
                if to is sym:
                    made = held
                else:
                    to[begin : begin + len(many)] = held
            sym[begin : begin + len(many)] = made
        return sym, out

    def ranks(self) -> np.ndarray:
        """A leaf step takes a unary letter's only child."""
        return np.concatenate((self.rank, *(np.full(b[1], b[0] != "leaf", self.rank.dtype) for b in self.blocks)))

    def letters(self, sym: np.ndarray | None) -> Letters:
        """Those in use, by their ids if these were kept. Weights and offsets, which no right-hand side of a chain needs, are left out."""
        sym, rank = self.hashed()[0][self.number] if sym is None else sym, self.ranks()[self.number].astype(np.int64)
        one = np.ones(int(rank.sum()), np.int64)
        return Letters(sym, np.zeros(len(sym), np.int64), rank, [one, np.zeros_like(one), np.zeros_like(one), one])

    def chains(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Trees, the ids of their input letters beside each other, and which tree each is of."""
        tree, flat = (np.concatenate(x) for x in zip(*self.starts))
        row = np.arange(len(tree))
        for kind, begin, many, part, at in reversed(list(self.opened())):
            mine = (flat >= begin) & (flat < begin + len(many))
            rule = np.where(mine, flat - begin, 0)
            n = np.where(mine, at[rule] if kind == "run" else many[rule], 1)
            head = np.cumsum(n) - n
            inner, which = np.arange(int(n.sum())) - np.repeat(head, n), np.repeat(rule, n)
            cell = (np.cumsum(many) - many)[which] + (0 if kind == "run" else inner)
            flat, row = np.where(np.repeat(mine, n), part[np.minimum(cell, len(part) - 1)], np.repeat(flat, n)), np.repeat(row, n)
        return tree, self.sym[flat], row


def pack_of(trees: list[tuple], label, sym, rank, parent, slot) -> Pack:
    """From nodes of whole trees in pre-order: (number, size) of each tree, and columns of nodes, parents by number in the tree."""
    tree, size = (np.array(x, np.int64) for x in zip(*trees))
    begin = np.repeat(np.cumsum(size) - size, size)
    names, at, code = np.unique(sym, return_index=True, return_inverse=True)
    ranks = rank[at].astype(np.int64)
    id_ = np.arange(int(ranks.sum())) - np.repeat(np.cumsum(ranks) - ranks, ranks) + 1
    letters = Letters(names, np.ones(len(names), np.int64), ranks, [id_, np.ones_like(id_), np.zeros_like(id_), id_.copy()])
    return Pack(tree, label, code.astype(np.int32), rank.astype(np.int32), np.where(parent >= 0, parent + begin, -1).astype(np.int32), slot.astype(np.int32), letters)


def tree_packs(batches) -> Iterator[Pack]:
    """Packs of whole trees from rows of nodes by tree and number."""
    held, ahead = [], 0

    def packs(last: bool):
        nonlocal held, ahead
        t = pa.Table.from_batches(held) if held else None
        if t is None or not t.num_rows:
            return
        tree = t.column("tree_id").to_numpy()
        edge = np.flatnonzero(np.append(True, tree[1:] != tree[:-1]))
        end = len(tree) if last else int(edge[-1])  # the last tree may go on
        if end:
            u = edge[edge < end]
            size = np.diff(np.append(u, end))
            col = lambda name, fill=None: (t.column(name).fill_null(fill) if fill is not None else t.column(name)).to_numpy()[:end].astype(np.int64)
            pre, up, root = col("pre"), col("parent", 0), t.column("parent").is_null().to_numpy()[:end]
            number, span = np.repeat(np.arange(len(u)), size), int(pre.max()) + 1
            up = np.searchsorted(number * span + pre, number * span + up) - np.repeat(u, size)  # numbers may have gaps
            yield pack_of(list(zip(tree[u].tolist(), size.tolist())), None, col("sym"), col("rank"), np.where(root, -1, up), col("slot", 0))
        held = t.slice(end).combine_chunks().to_batches()
        ahead = 0

    for batch in batches:
        held.append(batch)
        ahead += batch.num_rows
        if ahead >= PACK:
            yield from packs(False)
    yield from packs(True)


def dealt(nodes: DataFrame, parts: int) -> DataFrame:
    return nodes.select("tree_id", "pre", "parent", "slot", "sym", "rank").repartition(parts, "tree_id").sortWithinPartitions("tree_id", "pre")


def subtrees(nodes: DataFrame, count: int) -> DataFrame:
    """(name, rank) of all different subtrees, named by hash from the leaves up."""

    def run(batches):
        for pack in tree_packs(batches):
            name, up, depth = hash_long(pack.letters.sym, SEEDS["dag"])[pack.code], pack.parent.copy(), (pack.parent >= 0).astype(np.int32)
            while (low := np.flatnonzero(up >= 0)).size:
                depth[low] += depth[up[low]]
                up[low] = up[up[low]]
            order = np.argsort(depth, kind="stable")
            edge = np.searchsorted(depth[order], np.arange(int(depth.max(initial=0)) + 2))
            for f, t in reversed(list(zip(edge[1:-1], edge[2:]))):
                kids = order[f:t]
                place, first, many = np.unique(pack.parent[kids], return_index=True, return_counts=True)
                wide = np.argsort(-many, kind="stable")
                place, first, many = place[wide], first[wide], many[wide]
                for j in range(int(many[0])):
                    k = int(np.searchsorted(-many, -j, "left"))
                    kid = kids[first[:k] + j]
                    name[place[:k]] = hash_long(ids(name[kid]), hash_int(pack.slot[kid], name[place[:k]]))
            u, at = np.unique(ids(name), return_index=True)
            yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(pack.rank[at].astype(np.int32))], ["name", "rank"])

    return dealt(nodes, count // PACK * 2 + 8).mapInArrow(K.tidy(run), "name long, rank int").distinct()


def from_nodes(nodes: DataFrame, count: int, rules: str = FULL, group: int = 0, stop: int = 1) -> DataFrame:
    """The first rows of a phase loop from rows of nodes. group: of forests that share the loop and nothing else. stop: as a configuration's stop_size."""

    def run(batches):
        for pack in tree_packs(batches):
            pack.rules, pack.group, pack.stop = rules, group, stop
            yield from pack.begun()

    return dealt(nodes, count // PACK * 2 + 8).mapInArrow(K.tidy(run), OUT_SQL)


def from_chains(chains: DataFrame, end: int, rules: str, indexed: bool = False) -> DataFrame:
    """The same from chains (tree_id, letters, and perhaps label): unary letters from the root down, above a leaf of id ``end``.

    indexed: a tree's label is the number of its pack's first tree, so it is known which pack uses which letters.
    """
    labelled = "label" in chains.columns

    def run(batches):
        for batch in batches:
            many = batch.column("letters").value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
            flat = batch.column("letters").flatten().to_numpy(zero_copy_only=False)
            tree = batch.column("tree_id").to_numpy(zero_copy_only=False)
            label = batch.column("label").to_numpy(zero_copy_only=False) if labelled else None
            stop = np.cumsum(many)
            f = 0
            while f < len(many):
                t = max(f + 1, int(np.searchsorted(stop, (stop[f - 1] if f else 0) + PACK, "right")))
                n = many[f:t]
                last = np.cumsum(n + 1) - 1
                sym, rank = np.full(int(n.sum()) + len(n), end, np.int64), np.ones(int(n.sum()) + len(n), np.int64)
                rank[last] = 0
                sym[rank == 1] = flat[int(stop[f] - many[f]) : int(stop[t - 1])]
                parent = np.arange(len(sym)) - np.repeat(last - n, n + 1) - 1
                pack = pack_of(list(zip(tree[f:t].tolist(), (n + 1).tolist())), np.full(t - f, tree[f], np.int64) if indexed else None if label is None else label[f:t].astype(np.int64), sym, rank, parent, (parent >= 0).astype(np.int64))
                pack.rules = rules
                if rules == HELD:
                    pack.own = Own(pack.letters.sym, pack.letters.rank)
                yield from pack.begun()
                f = t

    return chains.mapInArrow(K.tidy(run), OUT_SQL)


def next_phase(states: DataFrame, colours: dict[int, P.Colouring | None], rules: str = FULL) -> DataFrame:
    """Pairs, by their group's colouring, and leaves of the phase that was begun, and the runs of the next."""

    def run(batches):
        for batch in batches:
            for raw in batch.column("state"):
                pack = Pack.load(raw.as_py())
                pack.rules = rules
                if (colour := colours.get(pack.group)) is not None:
                    pack.pairs(colour)
                    yield from pack.flush()
                pack.leaves()
                yield from pack.flush()
                yield from pack.begun()

    return states.select("state").mapInArrow(K.tidy(run), OUT_SQL)


def pair_graph(states: DataFrame) -> DataFrame:
    """(a, b, occ) of the phase that was begun."""

    def run(batches):
        for batch in batches:
            for raw in batch.column("state"):
                pack = Pack.load(raw.as_py())
                top, n = pack.arcs(), np.int64(len(pack.letters.sym))
                key, occ = np.unique(pack.code[top] * n + pack.code[top + 1], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(pack.letters.sym[key // n]), pa.array(pack.letters.sym[key % n]), pa.array(occ.astype(np.int64))], ["a", "b", "occ"])

    return states.select("state").mapInArrow(run, "a long, b long, occ long").groupBy("a", "b").agg(F.sum("occ").alias("occ"))


def best(tally: list[int], graph: Callable[[], DataFrame]) -> P.Colouring | None:
    """As pairs.hashed_colouring chooses."""
    if not tally[0]:
        return None
    i = max(range(2 * P.TRIES), key=lambda i: (tally[1 + i], -i))
    return P.Colouring(i // 2, turned=i % 2 == 1) if 4 * tally[1 + i] >= tally[0] else P.linear_colouring(graph())


class Tables:
    """What the phases wrote: rules and starts by phase, counts, and the letters each label's trees use."""

    def __init__(self, spark, counts: int = len(COUNTS)):
        self.spark, self.path, self.counts = spark, f"{scratch(spark)}/canopy-packs/{uuid.uuid4().hex}", counts
        self.by_group: dict[int, list[dict]] = {}
        top = spark._jvm.org.apache.hadoop.fs.Path(self.path)
        top.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(top)

    @property
    def stats(self) -> list[dict]:
        return self.by_group.get(0, [])

    def write(self, df: DataFrame, phase: int) -> dict[int, list[int]]:
        """The sums of each group's counts."""
        path = f"{self.path}/phase={phase}"
        df.write.partitionBy("what").option("compression", "zstd").parquet(path)
        n = self.counts + 1 + 2 * P.TRIES
        got = self.read(STATE, phase).where("tally is not null").groupBy("label").agg(*(F.sum(F.col("tally")[i]) for i in range(n))).collect()
        return {r[0]: [int(x) for x in r[1:]] for r in got}

    def read(self, what: int, phase: int | None = None) -> DataFrame:
        schema = f"{OUT_SQL}, phase int"
        if phase is None:
            return self.spark.read.schema(schema).parquet(self.path).where(F.col("what") == what)
        return self.spark.read.schema(OUT_SQL).parquet(f"{self.path}/phase={phase}").where(F.col("what") == what)

    def drop_states(self, phase: int) -> None:
        folder = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/phase={phase}/what={STATE}")
        folder.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(folder, True)


@contextmanager
def one_by_one(spark):
    """Packs are read and handed over singly: a thousand rows of this size at once fit no task."""
    keys = ("spark.sql.parquet.columnarReaderBatchSize", "spark.sql.execution.arrow.maxRecordsPerBatch")
    before = [spark.conf.get(k) for k in keys]
    for k in keys:
        spark.conf.set(k, "1")
    try:
        yield
    finally:
        for k, v in zip(keys, before):
            spark.conf.set(k, v)


def phases(spark, begun: DataFrame, rules: str = FULL) -> Tables:
    """All phases, until every tree is one letter."""
    t, phase = Tables(spark), 1
    tally = t.write(begun, phase)
    while tally:
        states = t.read(STATE, phase)
        for group, counted in tally.items():
            t.by_group.setdefault(group, []).append({"phase": phase, **dict(zip(COUNTS, counted))})
        colours = {group: best(counted[len(COUNTS) :], lambda g=group: pair_graph(states.where(F.col("label") == g))) for group, counted in tally.items()}
        with one_by_one(spark):
            after = t.write(next_phase(states, colours, rules), phase + 1)
        t.drop_states(phase)
        tally, phase = after, phase + 1
    return t


def used(t: Tables, column: str) -> DataFrame:
    """(label, sym, column): the letters that each label's trees use, each once, dealt by letter. Fails where packs made one id of two keys."""
    dealt = t.read(USE).select("label", column, "sym", "rank").repartition("sym")  # what repeats stands together, so it deflates well
    once = dealt.groupBy("sym", "label").agg(F.max(column).alias(column), F.min("rank").alias("low"), F.max("rank").alias("high"))
    whole = once.groupBy("sym").agg(F.collect_list(F.struct("label", column)).alias("x"), F.min("low").alias("low"), F.max("high").alias("high"))
    same = F.when(F.col("low") == F.col("high"), F.col("x")).otherwise(F.raise_error(F.lit("one letter id for two keys")))
    return whole.select("sym", F.explode(same).alias("x")).select("x.label", "sym", f"x.{column}")


def right_sides(t: Tables) -> DataFrame:
    """(rules) of each pack that held them, every letter of a pack once. Fails where packs made one id of two keys, a share of the ids at a time."""
    held = t.read(RULE).select("state", "weight")
    shares = min(-(-int(held.agg(F.coalesce(F.sum("weight"), F.lit(0))).first()[0]) // COMPARED), SHARES)
    for share in range(shares):
        if clashes(held, share, shares).take(1):
            raise ValueError("one letter id for two keys")
        gc.collect()
        t.spark._jvm.System.gc()  # else the share's shuffle files stay
    return held.select(F.col("state").alias("rules"))


def clashes(held: DataFrame, share: int, shares: int) -> DataFrame:
    """(sym) of one share of the ids that stand for different keys."""

    def run(batches):
        for batch in batches:
            for raw in batch.column("state"):
                own = Own.load(raw.as_py())
                sym, check = own.hashed(other=True)
                mine = sym % shares == share
                yield pa.RecordBatch.from_arrays([pa.array(sym[mine]), pa.array((check[mine] >> 32).astype(np.int32))], ["sym", "check"])

    keys = held.select("state").mapInArrow(K.tidy(run), "sym long, check int")
    return keys.groupBy("sym").agg((F.min("check") != F.max("check")).alias("clash")).where("clash").select("sym")


def texts(t: Tables, rules: DataFrame, names: dict[int, int]) -> DataFrame:
    """(tree_id, text): chains of characters by their packs' rules; ``names`` has the characters by letter, below zero what is none."""
    letters, points = (np.array(x, np.int64) for x in (zip(*sorted(names.items())) if names else ((), ())))

    def run(batches):
        for batch in batches:
            for raw in batch.column("rules"):
                tree, sym, row = Own.load(raw.as_py()).chains()
                place = np.minimum(np.searchsorted(letters, sym), max(len(letters) - 1, 0))
                if len(sym) and (letters[place] != sym).any():
                    raise ValueError("a letter without a rule or a name")
                shown = points[place] >= 0  # the end leaf is no character
                yield pa.RecordBatch.from_arrays([pa.array(tree), pa.array(spelled(points[place][shown], row[shown], len(tree)), pa.string())], ["tree_id", "text"])

    return rules.mapInArrow(K.tidy(run), "tree_id long, text string")


def spelled(points: np.ndarray, row: np.ndarray, rows: int) -> list[str]:
    text, stop = points.astype("<u4"), np.cumsum(np.bincount(row, minlength=rows))
    return [text[a:b].tobytes().decode("utf-32-le", "surrogatepass") for a, b in zip(np.append(0, stop[:-1]), stop)]


def texts_of(mine: DataFrame, starts: DataFrame, names: dict[int, int]) -> DataFrame:
    """(tree_id, text) from each pack's rules and starts, which meet in one task; ``names`` has the characters by letter, below zero what is none."""
    letters, points = (np.array(x, np.int64) for x in (zip(*sorted(names.items())) if names else ((), ())))

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        sym, rhs = left.column("sym").to_numpy(), left.column("rhs").combine_chunks()
        order = np.argsort(sym)
        many = rhs.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
        fields = rhs.flatten()
        part, at = fields.field("sym").to_numpy(zero_copy_only=False), fields.field("at").to_numpy(zero_copy_only=False)
        is_run = np.array([k == "run" for k in left.column("kind").to_pylist()], bool)
        times = np.where(np.repeat(is_run, many), at, 1)  # a run is one part, as often as it says
        begin = np.cumsum(many) - many
        owner = np.repeat(np.arange(len(many)), many)
        part, owner = np.repeat(part, times), np.repeat(owner, times)
        many = np.bincount(owner, minlength=len(many))
        begin = np.cumsum(many) - many
        tree = right.column("tree_id").to_numpy()
        flat, row, keys = right.column("sym").to_numpy(), np.arange(len(tree)), sym[order]
        while len(flat) and len(keys):
            place = np.minimum(np.searchsorted(keys, flat), len(keys) - 1)
            made = keys[place] == flat
            if not made.any():
                break
            rule = order[place]
            n = np.where(made, many[rule], 1)
            first = np.where(made, begin[rule], 0)
            cell = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + np.repeat(first, n)
            flat = np.where(np.repeat(made, n), part[cell] if len(part) else 0, np.repeat(flat, n))
            row = np.repeat(row, n)
        place = np.minimum(np.searchsorted(letters, flat), max(len(letters) - 1, 0))
        if len(flat) and (letters[place] != flat).any():
            raise ValueError("a letter without a rule or a name")
        point = points[place] if len(flat) else flat
        shown = point >= 0  # the end leaf is no character
        text = point[shown].astype("<u4")
        stop = np.cumsum(np.bincount(row[shown], minlength=len(tree)))
        out = [text[a:b].tobytes().decode("utf-32-le", "surrogatepass") for a, b in zip(np.append(0, stop[:-1]), stop)]
        return pa.table({"tree_id": pa.array(tree), "text": pa.array(out, pa.string())})

    return mine.groupBy("label").cogroup(starts.groupBy("label")).applyInArrow(run, "tree_id long, text string")


def prepare(spark) -> None:
    ship(spark)
