"""A tree or forest that one task holds: letters by the same ids as the engine's, and phases by plain search.

This is the reference of the engine's results, and the engine of grammars that are given explicitly.
"""

from __future__ import annotations

import struct
from collections import Counter
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field

import xxhash

from canopy.operators.pairs import TRIES

SEED = 42  # fixed value: where Spark's hash functions start


def hashed(*values) -> int:
    """Spark's xxhash64 of strings, longs (int) and ints (tuple of one), as a signed number."""
    h = SEED
    for v in values:
        raw = v.encode() if isinstance(v, str) else struct.pack("<i", v[0]) if isinstance(v, tuple) else struct.pack("<q", v)
        h = xxhash.xxh64(raw, seed=h).intdigest()
    return h - (1 << 64) if h >> 63 else h


def input_letter(name: str, rank: int) -> int:
    return hashed("input", name, (rank,))


def run_letter(a: int, n: int) -> int:
    return hashed("run", a, n)


def pair_letter(a: int, b: int) -> int:
    return hashed("pair", a, b)


def leaf_letter(f: int, leaves: Iterable[tuple[int, int]]) -> int:
    return hashed("leaf", f, *(x for slot, c in leaves for x in ((slot,), c)))


Up = Callable[[int], bool | None]


def hashed_up(pairs: Counter) -> Up:
    """The engine's hashed colouring for these pair counts."""
    total = sum(pairs.values())
    bits = {x: hashed(x, (5,)) & (1 << 64) - 1 for p in pairs for x in p}
    covered = [0] * (2 * TRIES)
    for (a, b), n in pairs.items():
        for k in range(TRIES):
            x, y = bits[a] >> k & 1, bits[b] >> k & 1
            covered[2 * k] += n * (x & ~y & 1)
            covered[2 * k + 1] += n * (y & ~x & 1)
    best = max(range(2 * TRIES), key=lambda i: (covered[i], -i))
    if 4 * covered[best] < total:
        return linear_up(pairs)
    return lambda x: (hashed(x, (5,)) >> best // 2 & 1) != best % 2


def linear_up(pairs: Counter) -> Up:
    short = lambda x: hashed(x, (11,)) & 0xFFFFFFFF
    arcs: Counter = Counter()
    for (a, b), n in pairs.items():
        arcs[short(a) ^ short(b)] += n
    seed = 0
    for t in range(32):
        odd = even = 0
        for x, n in arcs.items():
            if x and x.bit_length() - 1 == t:
                odd, even = (odd + n, even) if (x & seed).bit_count() % 2 else (odd, even + n)
        if even > odd:
            seed |= 1 << t
    flat = lambda x: (short(x) & seed).bit_count() % 2 == 0
    ud = sum(n for (a, b), n in pairs.items() if flat(a) and not flat(b))
    du = sum(n for (a, b), n in pairs.items() if flat(b) and not flat(a))
    return (lambda x: not flat(x)) if du > ud else flat


@dataclass
class Letters:
    """What letters stand for: rules (kind, parts), the numbers of their parameters and their weights."""

    rules: dict[int, tuple[str, tuple]] = field(default_factory=dict)
    slots: dict[int, tuple[int, ...]] = field(default_factory=dict)
    weight: dict[int, int] = field(default_factory=dict)
    names: dict[int, str] = field(default_factory=dict)

    def input(self, name: str, rank: int) -> int:
        x = input_letter(name, rank)
        self.slots[x], self.weight[x], self.names[x] = tuple(range(1, rank + 1)), 1, name
        return x

    def run(self, a: int, n: int) -> int:
        x = run_letter(a, n)
        self.rules[x], self.slots[x], self.weight[x] = ("run", (a, n)), self.slots[a], n * self.weight[a]
        return x

    def pair(self, a: int, b: int) -> int:
        x = pair_letter(a, b)
        self.rules[x], self.slots[x], self.weight[x] = ("pair", (a, b)), self.slots[b], self.weight[a] + self.weight[b]
        return x

    def leaf(self, f: int, leaves: tuple[tuple[int, int], ...]) -> int:
        x = leaf_letter(f, leaves)
        gone = {s for s, _ in leaves}
        self.rules[x], self.slots[x] = ("leaf", (f, leaves)), tuple(s for s in self.slots[f] if s not in gone)
        self.weight[x] = self.weight[f] + sum(self.weight[c] for _, c in leaves)
        return x


@dataclass
class Node:
    sym: int
    kids: list[tuple[int, "Node"]] = field(default_factory=list)


def trees_of(rows: Iterable[tuple], letters: Letters) -> dict[int, Node]:
    """Trees from (tree_id, pre, parent, slot, name, rank)."""
    roots, at = {}, {}
    for tree, pre, parent, slot, name, rank in sorted(rows, key=lambda r: (r[0], r[1])):
        at[tree, pre] = node = Node(letters.input(name, rank))
        if parent is None:
            roots[tree] = node
        else:
            at[tree, parent].kids.append((slot, node))
    for node in at.values():
        node.kids.sort(key=lambda x: x[0])
    return roots


def walk(roots: Iterable[Node]):
    todo = list(roots)
    while todo:
        node = todo.pop()
        yield node
        todo += [k for _, k in node.kids]


def compress_plain(roots: dict[int, Node], letters: Letters, colour: Callable[[Counter], Up] = hashed_up, max_phases: int | None = None) -> list[int]:
    """Phases in place until every tree is one letter; the nodes that were active in each phase."""
    active = []
    while max_phases is None or len(active) < max_phases:
        live = [r for r in roots.values() if r.kids]
        if not live:
            break
        nodes = list(walk(live))
        active.append(len(nodes))
        heads = set(map(id, live)) | {id(k) for n in nodes if len(n.kids) != 1 for _, k in n.kids} | {id(n.kids[0][1]) for n in nodes if len(n.kids) == 1 and n.kids[0][1].sym != n.sym}
        for n in nodes:
            if id(n) in heads and len(n.kids) == 1:
                size, low = 1, n
                while len(low.kids[0][1].kids) == 1 and low.kids[0][1].sym == n.sym:
                    size, low = size + 1, low.kids[0][1]
                if size > 1:
                    n.sym, n.kids = letters.run(n.sym, size), low.kids
        nodes = list(walk(live))
        pairs = Counter((n.sym, n.kids[0][1].sym) for n in nodes if len(n.kids) == 1 and len(n.kids[0][1].kids) == 1 and n.sym != n.kids[0][1].sym)
        if pairs:
            up = colour(pairs)
            for n in nodes:
                if len(n.kids) == 1 and len(n.kids[0][1].kids) == 1 and up(n.sym) is True and up(n.kids[0][1].sym) is False:
                    low = n.kids[0][1]
                    n.sym, n.kids, low.sym = letters.pair(n.sym, low.sym), low.kids, 0
                    low.kids = []
        nodes = list(walk(live))
        taken = [(n, tuple((s, k.sym) for s, k in n.kids if not k.kids)) for n in nodes]
        for n, leaves in taken:
            if leaves:
                n.sym, n.kids = letters.leaf(n.sym, leaves), [(s, k) for s, k in n.kids if s not in {x for x, _ in leaves}]
    return active


def preorder(labels: list[tuple[str, int]]) -> list[tuple]:
    """(pre, parent, slot, name, rank) of a pre-order list of names and ranks."""
    out, open_ = [], []
    for pre, (name, rank) in enumerate(labels):
        while open_ and open_[-1][1] == open_[-1][2]:
            open_.pop()
        if open_:
            open_[-1][1] += 1
            out.append((pre, open_[-1][0], open_[-1][1], name, rank))
        else:
            out.append((pre, None, None, name, rank))
        if rank:
            open_.append([pre, 0, rank])
    return out
