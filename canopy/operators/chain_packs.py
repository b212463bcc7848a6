"""Recompression of chain grammars over packs: a row holds the grammar of many whole texts as arrays, and a phase is one pass over these rows.

The work is that of chains.py, on rules and without expanding them: a pack has every rule below its starts, each once, children
before parents, and pops, runs and pairs go by its levels. A rule that several packs need is in each of them; one of them owns it, and
counts of rules are taken by owners alone, so all counts and letters are those of the one grammar of all texts.
"""

from __future__ import annotations

import pickle

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.llm import kernels as K
from canopy.model import settle
from canopy.operators import packed
from canopy.operators import pairs as P
from canopy.operators.packed import OUT_SQL, RULE, SEEDS, STATE, USE, U, hash_long, hash_name, ids, once, rows_of

#: Letters of a pack's texts; a longer text is a pack of its own.
PACK = 1 << 17
#: Letters of the longest text that is one task's work.
LONGEST = 1 << 20
COUNTS = ("run_occurrences", "run_moved", "run_size", "pair_occurrences", "pair_moved", "pair_size")
MARKS = {k: hash_name(k) for k in ("empty", "part", "one", "whole", "start")}
#: Stands for the letter of an empty text, which has none.
EMPTY = int(ids(MARKS["empty"])[0])


def widths(n: np.ndarray) -> np.ndarray:
    """Bits of whole numbers."""
    return np.frexp(n.astype(np.float64))[1].astype(np.int64)


def side_of(colour: P.Colouring, sym: np.ndarray) -> np.ndarray:
    """Whether letters are on the upper side, as pairs.Colouring.up says."""
    letters, which = np.unique(sym, return_inverse=True)
    if colour.bit is not None:
        up = (packed.hash_int(5, hash_long(letters, 42)) >> U(colour.bit)) & U(1) == 1
    else:
        up = np.bitwise_count(packed.hash_int(11, hash_long(letters, 42)) & U(0xFFFFFFFF) & U(colour.seed)) % 2 == 0
    return (~up if colour.turned else up)[which.reshape(-1)] if len(sym) else np.zeros(0, bool)


class Rules:
    """Rules of whole texts by level, the starts as the last level. Items are a rule's letters, ``n`` times each, and places of other rules (``var``)."""

    def __init__(self, label, tree, start, level, ptr, sym, n, var, own, times):
        self.label, self.tree, self.start, self.level, self.ptr, self.sym, self.n, self.var, self.own, self.times = label, tree, start, level, ptr, sym, n, var, own, times
        self.out: list[pa.RecordBatch] = []

    def dump(self) -> bytes:
        raw = pickle.dumps((self.label, self.tree, self.start, self.level, self.ptr, self.sym, self.n, self.var, self.own, self.times), 5)
        return pickle.dumps((len(raw), pa.compress(raw, "zstd", asbytes=True)), 5)

    @staticmethod
    def load(raw: bytes) -> Rules:
        size, held = pickle.loads(raw)
        return Rules(*pickle.loads(pa.decompress(held, size, "zstd")))

    def owners(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.ptr) - 1), np.diff(self.ptr))

    def size(self) -> int:
        return int(np.diff(self.ptr)[self.own].sum())

    def popped(self, colour: P.Colouring | None = None) -> tuple[int, int]:
        """No crossing runs, or with a colouring no crossing pairs, as chains.popped; occurrences of rules in rules, and letters moved."""
        many, owner = len(self.ptr) - 1, self.owners()
        below = self.sym[self.var & self.own[owner]]
        left, left_n, lefts = np.zeros((many, 2), np.int64), np.zeros((many, 2), np.int64), np.zeros(many, np.int64)
        right, right_n, rights = np.zeros(many, np.int64), np.zeros(many, np.int64), np.zeros(many, np.int64)
        full, gone, bodies = np.zeros(many, np.int64), np.zeros(many, np.int64), []
        for lo, hi in zip(self.level[:-1], self.level[1:]):
            f, t = self.ptr[lo], self.ptr[hi]
            var, c = self.var[f:t], np.where(self.var[f:t], self.sym[f:t], 0)
            a, b, e = np.where(var, lefts[c], 0), np.where(var, full[c], 1), np.where(var, rights[c], 0)
            put = a + b + e
            at, row = np.cumsum(put) - put, np.repeat(owner[f:t] - lo, put)
            sym, n, is_var = np.zeros(len(row), np.int64), np.ones(len(row), np.int64), np.zeros(len(row), bool)
            for j in (0, 1):
                hit = a > j
                sym[at[hit] + j], n[at[hit] + j] = left[c[hit], j], left_n[c[hit], j]
            hit = b > 0
            to = (at + a)[hit]
            sym[to], n[to], is_var[to] = self.sym[f:t][hit], self.n[f:t][hit], var[hit]
            hit = e > 0
            to = (at + a + b)[hit]
            sym[to], n[to] = right[c[hit]], right_n[c[hit]]
            head = np.ones(len(row), bool)
            head[1:] = is_var[1:] | is_var[:-1] | (sym[1:] != sym[:-1]) | (row[1:] != row[:-1])
            n = np.add.reduceat(n, np.flatnonzero(head)) if len(n) else n
            sym, is_var, row = sym[head], is_var[head], row[head]
            k = np.bincount(row, minlength=hi - lo)
            first = np.cumsum(k) - k
            last = first + k - 1
            kept = np.ones(len(sym), bool)
            if hi < many:  # starts give nothing away
                off, end = np.zeros(hi - lo, bool), np.zeros(hi - lo, bool)
                if colour is None:
                    off, end = k > 0, k > 1
                else:
                    some = np.flatnonzero(k)
                    up = side_of(colour, sym)
                    off[some], end[some] = ~is_var[first[some]] & ~up[first[some]], ~is_var[last[some]] & up[last[some]]
                r = np.flatnonzero(off)
                left[lo + r, 0], left_n[lo + r, 0], lefts[lo + r] = sym[first[r]], n[first[r]], 1
                r = np.flatnonzero(end)
                right[lo + r], right_n[lo + r], rights[lo + r] = sym[last[r]], n[last[r]], 1
                kept[first[off]] = kept[last[end]] = False
                gone[lo:hi] = lefts[lo:hi] + rights[lo:hi]
                rest = k - off - end
                r = np.flatnonzero(rest == 1)
                r = r[~is_var[first[r] + off[r]]]  # a single letter is put in the rule's place
                place = first[r] + off[r]
                left[lo + r, lefts[lo + r]], left_n[lo + r, lefts[lo + r]] = sym[place], n[place]
                lefts[lo + r] += 1
                kept[place] = False
                rest[r] = 0
                full[lo:hi] = rest > 0
            bodies.append((np.bincount(row[kept], minlength=hi - lo), sym[kept], n[kept], is_var[kept]))
        size, self.sym, self.n, self.var = (np.concatenate(x) for x in zip(*bodies))
        self.ptr = np.concatenate(([0], np.cumsum(size)))
        return len(below), int(gone[below].sum())

    def made(self, kind: str, sym: np.ndarray, check: np.ndarray, many: int, parts) -> None:
        """Rules of new letters, each once; ``parts`` gives their right-hand sides by place."""
        if len(sym):
            u, first, _ = once(sym, check)
            self.out.append(rows_of(RULE, len(u), label=np.full(len(u), self.label), sym=u, kind=pa.array([kind] * len(u), pa.string()), rhs=packed.parts(np.full(len(u), many), *parts(first))))

    def runs(self) -> None:
        hit = np.flatnonzero(~self.var & (self.n > 1))
        base, n = self.sym[hit], self.n[hit]
        fresh = ids(hash_long(n, hash_long(base, SEEDS["run"])))
        self.made("run", fresh, hash_long(n, hash_long(base, 77)), 1, lambda i: (base[i], n[i]))
        self.sym[hit], self.n[hit] = fresh, 1

    def neighbours(self, counts: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Unequal neighbours in what the rules derive, and their weights: each pair once."""
        first, last = np.zeros(len(self.ptr) - 1, np.int64), np.zeros(len(self.ptr) - 1, np.int64)
        for lo, hi in zip(self.level[:-1], self.level[1:]):
            r = lo + np.flatnonzero(np.diff(self.ptr[lo : hi + 1]))
            for end, at in ((first, self.ptr[r]), (last, self.ptr[r + 1] - 1)):
                end[r] = np.where(self.var[at], end[np.where(self.var[at], self.sym[at], 0)], self.sym[at])
        owner = self.owners()
        i = np.flatnonzero(owner[1:] == owner[:-1])
        a = np.where(self.var[i], last[np.where(self.var[i], self.sym[i], 0)], self.sym[i])
        b = np.where(self.var[i + 1], first[np.where(self.var[i + 1], self.sym[i + 1], 0)], self.sym[i + 1])
        weight = (self.times if counts == "tree" else self.own.astype(np.int64))[owner[i]]
        hit = a != b
        a, b, weight = a[hit], b[hit], weight[hit]
        letters, code = np.unique(np.concatenate((a, b)), return_inverse=True)
        key = code.reshape(-1)[: len(a)] * np.int64(max(len(letters), 1)) + code.reshape(-1)[len(a) :]
        order = np.argsort(key, kind="stable")
        edge = np.flatnonzero(np.append(True, key[order][1:] != key[order][:-1])) if len(key) else np.zeros(0, np.int64)
        return a[order[edge]], b[order[edge]], np.add.reduceat(weight[order], edge) if len(key) else weight

    def covered(self, counts: str) -> list[int]:
        """Weight of all pairs, and for every bit what it takes from up to down and from down to up."""
        a, b, weight = self.neighbours(counts)
        x, y = (packed.hash_int(5, hash_long(s, 42)) for s in (a, b))
        got = [int(weight.sum())]
        for j in range(P.TRIES):
            got += [int(weight[(z >> U(j)) & U(1) == 1].sum()) for z in (x & ~y, y & ~x)]
        return got

    def pairs(self, colour: P.Colouring) -> None:
        owner, up = self.owners(), side_of(colour, self.sym)
        top = np.flatnonzero((owner[1:] == owner[:-1]) & ~self.var[:-1] & ~self.var[1:] & up[:-1] & ~up[1:])
        a, b = self.sym[top], self.sym[top + 1]
        fresh = ids(hash_long(b, hash_long(a, SEEDS["pair"])))
        self.made("pair", fresh, hash_long(b, hash_long(a, 78)), 2, lambda i: (np.ravel((a[i], b[i]), "F"), np.tile([1, 2], len(i))))
        self.sym[top] = fresh
        kept = np.ones(len(self.sym), bool)
        kept[top + 1] = False
        self.ptr = np.concatenate(([0], np.cumsum(np.bincount(owner[kept], minlength=len(self.ptr) - 1))))
        self.sym, self.n, self.var = self.sym[kept], self.n[kept], self.var[kept]

    def begun(self, counts: str, before: tuple[int, int, int] = (0, 0, 0)):
        """Runs of a phase, and what it needs to know of all packs."""
        occurrences, moved = self.popped()
        self.runs()
        while self.out:
            x = self.out.pop(0)
            yield from (x.slice(f, packed.ROWS) for f in range(0, x.num_rows, packed.ROWS))
        tally = [occurrences, moved, self.size(), *before, *self.covered(counts)]
        yield rows_of(STATE, 1, label=[0], state=pa.array([self.dump()], pa.binary()), tally=pa.array([tally], pa.list_(pa.int64())))

    def ends(self) -> pa.RecordBatch:
        """(label, tree_id, sym): the letter of each text, null for an empty one."""
        at = self.ptr[self.start]
        some = self.ptr[self.start + 1] > at
        sym = pa.array(self.sym[np.where(some, at, 0)] if len(self.sym) else np.zeros(len(at), np.int64), mask=~some)
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(at), self.label)), pa.array(self.tree), sym], ["label", "tree_id", "sym"])


def bisected(label: int, tree: np.ndarray, many: np.ndarray, flat: np.ndarray) -> Rules:
    """The rules that chains.bisection_grammar makes of these texts; ``own`` holds an id for each for now, and equal strings have equal ids in any pack."""
    o, n = (np.cumsum(many) - many)[many > 1], many[many > 1]
    depths = []
    while len(o):
        half = np.int64(1) << (widths(n - 1) - 1)
        at, size = np.ravel((o, o + half), "F"), np.ravel((half, n - half), "F")
        depths.append((n, at, size))
        o, n = at[size > 1], size[size > 1]
    nodes, below = [], np.zeros(0, np.int64)
    for n, at, size in reversed(depths):
        inner = size > 1
        child, mark = flat[at], ids(hash_long(flat[at], MARKS["one"]))
        child[inner] = mark[inner] = below
        below = ids(hash_long(mark[1::2], hash_long(mark[::2], MARKS["part"])))
        nodes.append((below, n, child.reshape(-1, 2), inner.reshape(-1, 2)))
    one = flat[(np.cumsum(many) - many)[many == 1]]
    whole = np.full(len(many), EMPTY)
    whole[many > 1] = below
    whole[many == 1] = ids(hash_long(one, MARKS["whole"]))
    start = ids(hash_long(whole, MARKS["start"]))
    none = np.zeros((int((many == 0).sum()), 2), np.int64)
    nodes.append((whole[many == 1], np.ones(len(one), np.int64), np.stack((one, np.zeros_like(one)), 1), np.zeros((len(one), 2), bool)))
    nodes.append((whole[many == 0], np.zeros(len(none), np.int64), none, none > 0))
    nodes.append((start, np.full(len(start), -1), np.stack((whole, np.zeros_like(whole)), 1), np.tile([True, False], (len(start), 1))))
    key, n, child, inner = (np.concatenate(x) for x in zip(*nodes))
    u, first, which = np.unique(key, return_index=True, return_inverse=True)
    same = first[which.reshape(-1)]
    if (n != n[same]).any() or (child != child[same]).any():
        raise ValueError("one id for two rules")
    n, child, inner = n[first], child[first], inner[first]
    depth = np.where(n > 1, widths(np.maximum(n - 1, 0)), 0)
    depth[n < 0] = depth.max(initial=0) + 1
    order = np.argsort(depth, kind="stable")
    place = np.empty_like(order)
    place[order] = np.arange(len(order))
    n, child, inner, depth = n[order], child[order], inner[order], depth[order]
    child = np.where(inner, place[np.minimum(np.searchsorted(u, child), len(u) - 1)], child)
    size = np.where(n > 1, 2, np.where(n == 0, 0, 1))
    cell = np.arange(2) < size[:, None]
    ptr = np.concatenate(([0], np.cumsum(size)))
    level = np.searchsorted(depth, np.arange(int(depth[-1]) + 2))
    at = place[np.searchsorted(u, start)]
    times = np.bincount(at, minlength=len(u)).astype(np.int64)
    sym, var = child[cell], inner[cell]
    owner = np.repeat(np.arange(len(u)), size)
    for lo, hi in reversed(list(zip(level[:-1], level[1:]))):
        i = ptr[lo] + np.flatnonzero(var[ptr[lo] : ptr[hi]])
        np.add.at(times, sym[i], times[owner[i]])
    return Rules(label, tree, at, level, ptr, sym, np.ones(len(sym), np.int64), var, u[order], times)


def from_letters(chains: DataFrame) -> DataFrame:
    """Packs of chains (tree_id, letters), and the ids of the rules in each."""

    def run(batches):
        made = 0
        for batch in batches:
            many = batch.column("letters").value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
            flat = batch.column("letters").flatten().to_numpy(zero_copy_only=False)
            tree, stop, f = batch.column("tree_id").to_numpy(zero_copy_only=False), np.cumsum(many), 0
            while f < len(many):
                t = max(f + 1, int(np.searchsorted(stop, (stop[f - 1] if f else 0) + PACK, "right")))
                label = (TaskContext.get().partitionId() << 32) + made
                pack = bisected(label, tree[f:t], many[f:t], flat[int(stop[f] - many[f]) : int(stop[t - 1])])
                yield rows_of(STATE, 1, label=[label], state=pa.array([pack.dump()], pa.binary()))
                x = rows_of(USE, len(pack.own), label=np.full(len(pack.own), label), sym=pack.own)
                yield from (x.slice(i, packed.ROWS) for i in range(0, x.num_rows, packed.ROWS))
                f, made = t, made + 1

    return chains.mapInArrow(K.tidy(run), OUT_SQL)


def first_phase(states: DataFrame, used: DataFrame, counts: str) -> DataFrame:
    """Each rule is owned by one of the packs that have it; then the runs of the first phase."""
    mine = used.groupBy("sym").agg(F.min("label").alias("label")).groupBy("label").agg(F.collect_list("sym").alias("mine"))

    def run(batches):
        for batch in batches:
            for raw, own in zip(batch.column("state"), batch.column("mine")):
                pack = Rules.load(raw.as_py())
                pack.own = np.isin(pack.own, own.values.to_numpy()) if own.is_valid else np.zeros(len(pack.own), bool)
                yield from pack.begun(counts)

    return states.select("label", "state").join(mine.hint("merge"), "label", "left").select("state", "mine").mapInArrow(K.tidy(run), OUT_SQL)


def next_phase(states: DataFrame, colour: P.Colouring, counts: str) -> DataFrame:
    """Pairs of the phase that was begun, and the runs of the next."""

    def run(batches):
        for batch in batches:
            for raw in batch.column("state"):
                pack = Rules.load(raw.as_py())
                occurrences, moved = pack.popped(colour)
                pack.pairs(colour)
                yield from pack.begun(counts, (occurrences, moved, pack.size()))

    return states.select("state").mapInArrow(K.tidy(run), OUT_SQL)


def pair_graph(states: DataFrame, counts: str) -> DataFrame:
    """(a, b, occ) of the phase that was begun."""

    def run(batches):
        for batch in batches:
            for raw in batch.column("state"):
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in Rules.load(raw.as_py()).neighbours(counts)], ["a", "b", "occ"])

    return states.select("state").mapInArrow(run, "a long, b long, occ long").groupBy("a", "b").agg(F.sum("occ").alias("occ"))


def recompress(spark, chains: DataFrame, counts: str, max_phases: int) -> tuple[packed.Tables, DataFrame, list[dict]]:
    """What the phases wrote, the texts' letters (label, tree_id, sym), and one dict of counts a phase, as chains.recompress has them."""
    t = packed.Tables(spark, len(COUNTS))
    weigh = lambda phase: counts if counts != "alternate" else ("tree", "grammar")[phase % 2 == 0]
    packed.prepare(spark)
    t.write(from_letters(chains), 0)
    with packed.one_by_one(spark):
        tally = t.write(first_phase(t.read(STATE, 0), t.read(USE, 0), weigh(1)), 1).get(0)
    stats, phase = [], 1
    while True:
        n = dict(zip(COUNTS, tally or [0] * len(COUNTS)))
        if stats:
            stats[-1] |= {"pair_occurrences": n["pair_occurrences"], "pair_moved": n["pair_moved"], "size": n["pair_size"]}
        t.drop_states(phase - 1)
        if phase > max_phases:
            break
        stats.append({"phase": phase, "run_occurrences": n["run_occurrences"], "run_moved": n["run_moved"], "pair_occurrences": 0, "pair_moved": 0, "size": n["run_size"]})
        states = t.read(STATE, phase)
        colour = packed.best(tally[len(COUNTS) :], lambda: pair_graph(states, weigh(phase))) if tally else None
        if colour is None:
            break
        with packed.one_by_one(spark):
            tally = t.write(next_phase(states, colour, weigh(phase + 1)), phase + 1).get(0)
        phase += 1
    with packed.one_by_one(spark):
        got = settle(ends(t.read(STATE, phase)))
    t.drop_states(phase)
    return t, got, stats


def ends(states: DataFrame) -> DataFrame:
    def run(batches):
        for batch in batches:
            for raw in batch.column("state"):
                yield Rules.load(raw.as_py()).ends()

    return states.select("state").mapInArrow(run, "label long, tree_id long, sym long")
