"""Tree grammars given explicitly: soundness, value, normal form, handle grammars, and recompression without expanding them.

A grammar is one task's work; many grammars are rows of one table, grouped by grammar. Rule trees are (kind, label,
children): kind "T" for letters (label a name), "N" for nonterminals, "Y" for parameters (label a number from 1).

In a handle grammar every nonterminal has at most one parameter and a rule is a sequence of items:
("U", letter, n, explicit, pieces): a unary letter n times, of which ``explicit`` stood in the rule and the rest came as popped
pieces; ("H", letter, hole, args): a letter of higher rank, args (slot, chain, tail) at all slots but the hole; ("N", A);
at the end of rules without parameter ("C", constant) or ("Z", A).
"""

from __future__ import annotations

import math
import sys
from collections import Counter
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame

from canopy.operators.small import Letters, Node, compress_plain, hashed_up, preorder, trees_of, walk

Tree = tuple


def T(name: str, *kids: Tree) -> Tree:  # noqa: N802
    return ("T", name, kids)


def N(name, *kids: Tree) -> Tree:  # noqa: N802
    return ("N", name, kids)


def Y(i: int) -> Tree:  # noqa: N802
    return ("Y", i, ())


@dataclass
class Grammar:
    """rules: nonterminal -> (rank, tree); start has rank 0."""

    rules: dict
    start: object


def nodes_in(tree: Tree):
    todo = [tree]
    while todo:
        t = todo.pop()
        yield t
        todo += reversed(t[2])


def size(g: Grammar, count_params: bool = False) -> int:
    return sum(t[0] != "Y" or count_params for _, tree in g.rules.values() for t in nodes_in(tree))


def ordered(g: Grammar) -> list:
    """Nonterminals, those on the right of a rule before its own; those on or above a cycle are missing."""
    uses = {a: {t[1] for t in nodes_in(tree) if t[0] == "N"} for a, (_, tree) in g.rules.items()}
    out, done = [], set()
    while ready := [a for a in g.rules if a not in done and uses[a] <= done]:
        out += ready
        done |= set(ready)
    return out


def violations(g: Grammar) -> list[tuple[object, str]]:
    """What keeps a grammar from being straight-line and linear, with parameters in order."""
    out = []
    used = {t[1] for _, tree in g.rules.values() for t in nodes_in(tree) if t[0] == "N"}
    sound = set(ordered(g))
    for a, (rank, tree) in g.rules.items():
        ys = [t[1] for t in nodes_in(tree) if t[0] == "Y"]
        if sorted(ys) != list(range(1, rank + 1)):
            out.append((a, "parameters are not each used once"))
        elif ys != sorted(ys):
            out.append((a, "parameters out of order"))
        if tree[0] == "Y":
            out.append((a, "derives its parameter alone"))
        for t in nodes_in(tree):
            if t[0] == "N" and t[1] not in g.rules:
                out.append((a, "no rule"))
            elif t[0] == "N" and len(t[2]) != g.rules[t[1]][0]:
                out.append((a, "wrong number of children"))
        if a != g.start and a not in used:
            out.append((a, "unused"))
        if a not in sound:
            out.append((a, "cycle"))
    if g.start not in g.rules or g.rules[g.start][0]:
        out.append((g.start, "start has parameters or no rule"))
    if g.start in used:
        out.append((g.start, "start inside a rule"))
    return out


def mapped(tree: Tree, change: Callable[[Tree], Tree]) -> Tree:
    """Bottom-up rewrite; a rule's tree is as deep as it was written."""
    return change((tree[0], tree[1], tuple(mapped(k, change) for k in tree[2])))


def derive_once(tree: Tree, g: Grammar, at: int) -> Tree:
    """The tree after the nonterminal at a pre-order number is replaced by its rule, its children put for the parameters."""
    count = -1

    def go(t: Tree) -> Tree:
        nonlocal count
        count += 1
        if count == at:
            if t[0] != "N":
                raise ValueError("no nonterminal there")
            return mapped(g.rules[t[1]][1], lambda x: t[2][x[1] - 1] if x[0] == "Y" else x)
        return (t[0], t[1], tuple(map(go, t[2])))

    return go(tree)


def in_order(g: Grammar) -> Grammar:
    """The same grammar with every rule's parameters numbered left to right; uses are permuted to match."""
    moved, rules = {}, {}
    for a in ordered(g):
        rank, tree = g.rules[a]
        tree = mapped(tree, lambda t: (t[0], t[1], tuple(t[2][i - 1] for i in moved[t[1]])) if t[0] == "N" else t)
        moved[a] = [t[1] for t in nodes_in(tree) if t[0] == "Y"]
        place = {y: i + 1 for i, y in enumerate(moved[a])}
        rules[a] = (rank, mapped(tree, lambda t: Y(place[t[1]]) if t[0] == "Y" else t))
    return Grammar(rules, g.start)


def value(g: Grammar, tree: Tree | None = None) -> list[tuple[str, int]]:
    """Names and ranks of the derived tree in pre-order."""
    out, todo = [], [(tree or N(g.start), None)]
    while todo:
        t, env = todo.pop()
        if t[0] == "Y":
            todo.append(env[t[1] - 1])
        elif t[0] == "N":
            todo.append((g.rules[t[1]][1], [(k, env) for k in t[2]]))
        else:
            out.append((t[1], len(t[2])))
            todo += [(k, env) for k in reversed(t[2])]
    return out


def normal_form(g: Grammar) -> tuple[dict, object]:
    """Rules of two forms only: ("T", name, rank), a letter over parameters, and ("C", B, i, C), B with C for its i-th parameter.

    Returns rules in order and the start; a nonterminal that only renames another is put aside.
    """
    rules, alias, letters = {}, {}, {}
    g = in_order(g)

    def letter(name: str, rank: int):
        if (name, rank) not in letters:
            letters[name, rank] = a = ("letter", name, rank)
            rules[a] = ("T", name, rank)
        return letters[name, rank]

    def build(tree: Tree):
        top = alias[tree[1]] if tree[0] == "N" else letter(tree[1], len(tree[2]))
        place = 1
        for k in tree[2]:
            if k[0] == "Y":
                place += 1
                continue
            low, rank = build(k)
            new = ("join", len(rules))
            rules[new] = ("C", top, place, low)
            top, place = new, place + rank
        return top, place - 1

    for a in ordered(g):
        alias[a], _ = build(g.rules[a][1])
    return rules, alias[g.start]


@dataclass
class Handles:
    """A handle grammar. kind: "1" and "0" for the first nonterminals by rank, "new" for those that popping makes; owner and phase of those."""

    rules: dict
    order: list
    start: object
    letters: Letters
    kind: dict = field(default_factory=dict)
    owner: dict = field(default_factory=dict)


def to_handles(g: Grammar) -> Handles:
    """Every nonterminal of the normal form has a skeleton: the branching nodes above its parameters, with what lies between as nonterminals of rank at most one.

    Skeleton nodes: ("Y",), ("0", end item), ("1", A, child) and ("f", letter, children).
    """
    rules, start = normal_form(g)
    letters, made, order = Letters(), {}, []

    def new(body: list):
        a = len(order)
        made[a] = body
        order.append(a)
        return a

    def params(t) -> int:
        return 1 if t[0] == "Y" else 0 if t[0] == "0" else params(t[2]) if t[0] == "1" else sum(map(params, t[2]))

    def chain(a, child):
        """A node of degree one over child; two of them on one another become one nonterminal."""
        if child[0] == "1":
            return ("1", new([("N", a), ("N", child[1])]), child[2])
        if child[0] == "0":
            return ("0", ("Z", new([("N", a), child[1]])))
        return ("1", a, child)

    def folded(f: int, kids: list):
        """A letter's node; with a single child that holds parameters it is a handle, without any a tree."""
        held = [i for i, k in enumerate(kids) if params(k)]
        if len(held) > 1:
            return ("f", f, kids)
        slots = letters.slots[f]
        hole = held[0] if held else 0
        args = tuple((slots[i], (), k[1]) for i, k in enumerate(kids) if i != hole)
        item = ("H", f, slots[hole], args) if args else ("U", f, 1, 1, ())
        if held:
            return chain(new([item]), kids[hole])
        return ("0", ("Z", new([item, kids[hole][1]])))

    places: dict = {}  # by list of children: the child looked at last, parameters before it, children that hold any

    def put_in(t, i: int, low):
        """The same for a branching node that no other skeleton uses: its children change in place, or a wide node takes a copy for each of them."""
        kids = t[2]
        j, at, held = places.pop(id(kids), None) or (0, 0, sum(params(k) > 0 for k in kids))
        if i <= at:
            j, at = 0, 0
        while at + (n := params(kids[j])) < i:
            j, at = j + 1, at + n
        kids[j] = put(kids[j], i - at, low)
        held -= not params(kids[j])
        if held < 2:
            return folded(t[1], kids)
        places[id(kids)] = j, at, held
        return t

    def put(t, i: int, low):
        """t with its i-th parameter replaced."""
        if t[0] == "Y":
            return low
        if t[0] == "1":
            return chain(t[1], put(t[2], i, low))
        kids, at = list(t[2]), 0
        for j, k in enumerate(kids):
            n = params(k)
            if at < i <= at + n:
                kids[j] = put(k, i - at, low)
                break
            at += n
        return folded(t[1], kids)

    skeleton = {}
    uses = Counter([start, *(b for rule in rules.values() if rule[0] == "C" for b in (rule[1], rule[3]))])
    once = {b for b, n in uses.items() if n == 1}
    for a, rule in rules.items():
        if rule[0] == "T":
            f = letters.input(rule[1], rule[2])
            skeleton[a] = ("0", ("C", f)) if not rule[2] else ("1", new([("U", f, 1, 1, ())]), ("Y",)) if rule[2] == 1 else ("f", f, [("Y",)] * rule[2])
        else:
            t, low = skeleton[rule[1]], skeleton[rule[3]]
            skeleton[a] = (put_in if t[0] == "f" and rule[1] in once else put)(t, rule[2], low)
            for b in (rule[1], rule[3]):
                uses[b] -= 1
                if not uses[b]:
                    places.pop(id(skeleton[b][2]) if skeleton[b][0] == "f" and skeleton[a] is not skeleton[b] else None, None)
                    del skeleton[b]
    top = skeleton[start][1]
    root = new([top])
    used, todo = {root}, [root]
    while todo:
        for b in references(made[todo.pop()]):
            if b not in used:
                used.add(b)
                todo.append(b)
    order = [a for a in order if a in used]
    h = Handles({a: made[a] for a in order}, order, root, letters)
    h.kind = {a: "1" if made[a][-1][0] not in "CZ" else "0" for a in order}
    return h


def references(body: list):
    for x in body:
        if x[0] in "NZ":
            yield x[1]
        elif x[0] == "H":
            yield from (tail[1] for _, _, tail in x[3] if tail[0] == "Z")


def handle_violations(h: Handles) -> list[tuple[object, str]]:
    """Rules that are no sequences of handles with at most two nonterminals of the right ranks."""
    out, seen = [], set()
    for a in h.order:
        body = h.rules[a]
        ends = body[-1][0] in "CZ" if body else False
        if not body or ends != (h.kind[a] != "1") or any(x[0] in "CZ" for x in body[:-1]):
            out.append((a, "form"))
        if sum(x[0] == "N" for x in body) + sum(x[0] == "Z" for x in body) > 2:
            out.append((a, "more than two nonterminals"))
        if any(b not in seen for b in references(body)):
            out.append((a, "order"))
        if h.kind[a] == "new" and any(x[0] not in "UCZ" for x in body):
            out.append((a, "a popped side tree is no chain"))
        for x in body:
            if x[0] == "H" and {x[2], *(s for s, _, _ in x[3])} != set(h.letters.slots[x[1]]):
                out.append((a, "slots"))
        seen.add(a)
    return out


def handle_value(h: Handles) -> list[int]:
    """Letters of the derived tree in pre-order."""
    out, todo = [], [(h.rules[h.start], 0, None)]
    while todo:
        body, i, after = todo.pop()
        if i == len(body):
            if after is not None:
                todo.append(after)
            continue
        x, rest = body[i], (body, i + 1, after)
        if x[0] == "U":
            out += [x[1]] * x[2]
            todo.append(rest)
        elif x[0] == "C":
            out.append(x[1])
        elif x[0] == "Z":
            todo.append((h.rules[x[1]], 0, None))
        elif x[0] == "N":
            todo.append((h.rules[x[1]], 0, rest))
        else:
            out.append(x[1])
            kids = {x[2]: rest, **{s: ([("U", a, n, n, ()) for a, n in chain] + [tail], 0, None) for s, chain, tail in x[3]}}
            todo += [kids[s] for s in reversed(h.letters.slots[x[1]])]
    return out


def push(body: list, x: tuple) -> None:
    if x[0] == "U" and body and body[-1][0] == "U" and body[-1][1] == x[1]:
        y = body[-1]
        body[-1] = ("U", x[1], y[2] + x[2], y[3] + x[3], y[4] + x[4])
    else:
        body.append(x)


def joined(chain: Iterable[tuple[int, int]]) -> tuple:
    out: list = []
    for a, n in chain:
        if out and out[-1][0] == a:
            out[-1] = (a, out[-1][1] + n)
        else:
            out.append((a, n))
    return tuple(out)


def replaced(body: list, subs: dict) -> tuple[list, int]:
    """A body after popping below it, and how many popped items came in. subs: A -> (before, what stays, after)."""
    out, came = [], 0
    for x in body:
        if x[0] in "NZ" and x[1] in subs:
            before, stays, after = subs[x[1]]
            came += len(before) + len(after)
            for y in (*before, *([stays] if stays else []), *after):
                push(out, y)
        elif x[0] == "H":
            args = []
            for s, chain, tail in x[3]:
                if tail[0] == "Z" and tail[1] in subs:
                    before, tail, _ = subs[tail[1]]
                    came += len(before)
                    chain = joined((*chain, *((y[1], y[2]) for y in before)))
                args.append((s, joined(chain), tail))
            out.append(("H", x[1], x[2], tuple(args)))
        else:
            push(out, x)
    return out, came


def popped_up_and_down(h: Handles, first: Callable[[int], bool], last: Callable[[int], bool], log: list | None = None) -> int:
    """Rules give away a first unary item that ``first`` wants and, with a parameter, a last one that ``last`` wants; number of items that came into rules."""
    subs, came, order = {}, 0, []
    for a in h.order:
        body, n = replaced([("U", x[1], x[2], x[2], ()) if x[0] == "U" else x for x in h.rules[a]], subs)
        came += n
        if log is not None:
            log += [(a, x) for x in body if x[0] == "U"] + [(a, ("U", c, n, n, ())) for x in body if x[0] == "H" for _, chain, _ in x[3] for c, n in chain]
        if a != h.start:
            before, after = [], []
            piece = lambda x: ("U", x[1], x[2], 0, (x[2],))
            if body[0][0] == "U" and first(body[0][1]):
                before.append(piece(body.pop(0)))
            if h.kind[a] == "1" and body and body[-1][0] == "U" and last(body[-1][1]):
                after.append(piece(body.pop()))
            if before or after or not body:
                subs[a] = (before, (("N" if h.kind[a] == "1" else "Z"), a) if body else None, after)
        if body:
            h.rules[a] = body
            order.append(a)
        else:
            del h.rules[a]
    h.order = order
    return came


def each_chain(h: Handles, change: Callable[[list], list]) -> None:
    """Rewrites all unary chains, (letter, n) lists, of bodies and of handles' arguments."""
    for a in h.order:
        out, held = [], []

        def flush() -> None:
            out.extend(("U", c, n, n, ()) for c, n in change(held))
            held.clear()

        for x in h.rules[a]:
            if x[0] == "U":
                held.append((x[1], x[2]))
                continue
            flush()
            out.append(("H", x[1], x[2], tuple((s, tuple(change(list(chain))), tail) for s, chain, tail in x[3])) if x[0] == "H" else x)
        flush()
        h.rules[a] = out


def edges(h: Handles) -> tuple[dict, dict]:
    """First and last letters of what nonterminals derive, None where they aren't unary."""
    first, last = {}, {}
    for a in h.order:
        x, y = h.rules[a][0], h.rules[a][-1]
        first[a] = x[1] if x[0] == "U" else first.get(x[1]) if x[0] in "NZ" else None
        last[a] = y[1] if y[0] == "U" else last.get(y[1]) if y[0] == "N" else None
    return first, last


def occurrences(h: Handles) -> dict:
    """How often each nonterminal stands in the whole derivation."""
    times = Counter({h.start: 1})
    for a in reversed(h.order):
        for b in references(h.rules[a]):
            times[b] += times[a]
    return times


def neighbours(h: Handles):
    """(nonterminal, upper letter, lower letter, across a border) of unary letters right above one another."""
    first, last = edges(h)
    for a in h.order:
        body = h.rules[a]
        for x, y in zip(body, body[1:]):
            up = x[1] if x[0] == "U" else last.get(x[1]) if x[0] == "N" else None
            low = y[1] if y[0] == "U" else first.get(y[1]) if y[0] in "NZ" else None
            if up is not None and low is not None:
                yield a, up, low, x[0] != "U" or y[0] != "U"
        for x in body:
            for _, chain, tail in x[3] if x[0] == "H" else ():
                letters = [c for c, _ in chain]
                yield from ((a, u, v, False) for u, v in zip(letters, letters[1:]))
                if letters and tail[0] == "Z" and first.get(tail[1]) is not None:
                    yield a, letters[-1], first[tail[1]], True


def pair_counts(h: Handles, counts: str) -> Counter:
    times = occurrences(h) if counts == "tree" else None
    out: Counter = Counter()
    for a, u, v, _ in neighbours(h):
        if u != v:
            out[u, v] += times[a] if times else 1
    return out


def crossing_pairs(h: Handles, up) -> set:
    return {(u, v) for _, u, v, across in neighbours(h) if across and u != v and up(u) is True and up(v) is False}


def crossing_leaves(h: Handles) -> int:
    """Borders of nonterminals that part a letter from a constant child of it."""
    single = {a: h.rules[a][0][0] == "C" for a in h.order}
    n = 0
    for a in h.order:
        body = h.rules[a]
        n += sum(x[0] == "H" and sum(tail[0] == "Z" and not chain and single[tail[1]] for _, chain, tail in x[3]) for x in body)
        n += sum(x[0] == "N" and (y[0] == "C" or y[0] == "Z" and single[y[1]]) for x, y in zip(body, body[1:]))
    return n


def pop_leaves(h: Handles, phase: int) -> tuple[int, list]:
    """No border parts a letter from a constant child: constants are put in place, and where a nonterminal stands right over one its last handle moves out.

    Side trees of a handle that moves become nonterminals owned by the one it leaves. Returns the letters that came into rules, and
    owners that already owned something alive.
    """
    subs, came, order = {}, 0, []
    uses = Counter(b for body in h.rules.values() for b in references(body))  # rules that use one come after it, so none has changed by then
    for a in h.order:
        body, n = replaced(h.rules[a], subs)
        came += n
        if a != h.start and body[0][0] == "C":
            subs[a] = ([], body[0], [])
            came += uses[a]
            del h.rules[a]
            continue
        h.rules[a] = body
        order.append(a)
    h.order = order
    marked = {x[1] for a in h.order for x, y in zip(h.rules[a], h.rules[a][1:]) if x[0] == "N" and y[0] == "C"}
    for a in reversed(h.order):
        if a in marked and h.rules[a][-1][0] == "N":
            marked.add(h.rules[a][-1][1])
    subs, order, twice = {}, [], []
    alive = set(h.order)
    for a in h.order:
        body, n = replaced(h.rules[a], subs)
        came += n
        if a in marked:
            x = body.pop()
            if x[0] == "H":
                if any(o == a and b in alive for b, (o, _) in h.owner.items()):
                    twice.append(a)
                args = []
                for s, chain, tail in x[3]:
                    if chain or tail[0] == "Z":
                        b = ("new", phase, a, s)
                        h.rules[b], h.kind[b], h.owner[b] = [("U", c, n, n, ()) for c, n in chain] + [tail], "new", (a, phase)
                        order.append(b)
                        tail = ("Z", b)
                    args.append((s, (), tail))
                x = ("H", x[1], x[2], tuple(args))
                came += sum(tail[0] == "C" for _, _, tail in args)
            subs[a] = ([], ("N", a) if body else None, [x])
        if body:
            h.rules[a] = body
            order.append(a)
        else:
            del h.rules[a]
    h.order = order
    return came, twice


def absorb(h: Handles) -> tuple[int, int, dict]:
    """Constant children go into their parents, in every rule by itself; letters consumed, letters made, and the new ones' costs."""
    consumed = made = 0
    costs: dict = {}

    def leaf(f: int, leaves: tuple) -> int:
        nonlocal consumed, made
        x = h.letters.leaf(f, leaves)
        consumed, made, costs[x] = consumed + len(leaves) + 1, made + 1, len(leaves) + 1
        return x

    for a in h.order:
        body, out = h.rules[a], []
        for i, x in enumerate(body):
            below = body[i + 1] if i + 1 < len(body) and body[i + 1][0] == "C" else None
            if x[0] == "C" and out and out[-1] == "gone":
                out.pop()
            elif x[0] == "U" and below:
                if x[2] > 1:
                    out.append(("U", x[1], x[2] - 1, x[2] - 1, ()))
                out += [("C", leaf(x[1], ((h.letters.slots[x[1]][0], below[1]),))), "gone"]
            elif x[0] == "H":
                eaten = [(s, tail[1]) for s, chain, tail in x[3] if not chain and tail[0] == "C"] + ([(x[2], below[1])] if below else [])
                rest = []
                for s, chain, tail in x[3]:
                    if chain and tail[0] == "C":
                        c, n = chain[-1]
                        rest.append((s, chain[:-1] + (((c, n - 1),) if n > 1 else ()), ("C", leaf(c, ((h.letters.slots[c][0], tail[1]),)))))
                    elif tail[0] == "Z":
                        rest.append((s, chain, tail))
                f = leaf(x[1], tuple(sorted(eaten))) if eaten else x[1]
                if not below:
                    out.append(("H", f, x[2], tuple(rest)) if rest else ("U", f, 1, 1, ()))
                elif not rest:
                    out += [("C", f), "gone"]
                else:
                    (hole, chain, tail), *others = rest
                    out.append(("H", f, hole, tuple(others)) if others else ("U", f, 1, 1, ()))
                    out += [*(("U", c, n, n, ()) for c, n in chain), tail, "gone"]
            else:
                out.append(x)
        h.rules[a] = [x for x in out if x != "gone"]
    return consumed, made, costs


def tree_nodes(h: Handles) -> int:
    """Nodes of the derived tree."""
    n: dict = {}
    for a in h.order:
        n[a] = sum(x[2] if x[0] == "U" else 1 if x[0] == "C" else n[x[1]] if x[0] in "NZ" else 1 + sum(sum(k for _, k in chain) + (1 if tail[0] == "C" else n[tail[1]]) for _, chain, tail in x[3]) for x in h.rules[a])
    return n[h.start]


def tally(h: Handles) -> dict:
    """Occurrences of nonterminals by kind, and of letters."""
    got: Counter = Counter(h.kind[b] for a in h.order for b in references(h.rules[a]))
    letters = sum(1 if x[0] in "UC" else 1 + sum(len(chain) + (tail[0] == "C") for _, chain, tail in x[3]) for a in h.order for x in h.rules[a] if x[0] in "UCH")
    return {"g1": got["1"], "g0": got["0"], "gt": got["new"], "letters": letters}


def run_costs(log: list) -> tuple[float, float, list]:
    """Weights of the graphs of lengths by the grammar's own representation and by the engine's, and the powers by rule.

    A run that joins pieces popped from two nonterminals is a power, at 1 + log of its length; any other adds its explicit letters to a piece.
    """
    best: dict = {}
    powers = []
    for a, (_, c, n, explicit, pieces) in log:
        if len(pieces) > 1:
            powers.append((a, n))
            cost = 1 + math.log2(n)
        elif explicit:
            cost = float(explicit)
        else:
            continue
        best[c, n] = min(best.get((c, n), math.inf), cost)
    engine, lens = 0.0, {}
    for c, n in best:
        lens.setdefault(c, []).append(n)
    for c, ns in lens.items():
        before = 0
        for n in sorted(ns):
            engine += 1 + math.log2(n - before)
            before = n
    return sum(best.values()), engine, powers


def recompress(h: Handles, counts: str = "tree", colour=hashed_up, max_phases: int | None = None) -> list[dict]:
    """Phases of runs, pairs and leaves on the rules until the start is one letter; a row of the ledger for each step.

    counts weighs pairs as the derived tree has them, as the rules have them ("grammar"), or in turn ("alternate"). With "tree" the letters
    are those of the tree engine. A row holds the credit issued for letters that came into rules (two each) and its bound, the credit released by
    letters that were replaced, what of it was paid for new letters and their rules, occurrences of nonterminals, and what is broken.
    """
    ledger, phase = [], 0
    r = max((len(s) for s in h.letters.slots.values()), default=0)
    first = tally(h)
    n1, n0, log_n = first["g1"], first["g0"], tree_nodes(h)
    powers: Counter = Counter()

    def row(step: str, nodes: int, was: dict, issued: int, bound: int, released: int = 0, paid: int = 0, **more) -> None:
        now = tally(h)
        broken = handle_violations(h)
        ok = now["g1"] <= was["g1"] and now["g0"] <= max(was["g0"], n0) and now["gt"] <= n1 * max(r - 1, 0)
        ledger.append({"phase": phase, "step": step, "nodes": nodes, **now, "issued": 2 * issued, "bound": bound, "released": released, "paid": paid, "broken": len(broken) + (not ok), "crossing": 0, "engine_weight": 0.0, "grammar_weight": 0.0, "power_log": 0.0, **more})

    while h.rules[h.start][0][0] != "C" and (max_phases is None or phase < max_phases):
        phase += 1
        nodes, was = tree_nodes(h), tally(h)
        log: list = []
        came = popped_up_and_down(h, lambda _: True, lambda _: True, log)
        crossing = sum(across and u == v for _, u, v, across in neighbours(h))
        grammar_weight, engine_weight, made = run_costs(log)
        for a, n in made:
            powers[a] += math.log2(n)
        each_chain(h, lambda chain: [(h.letters.run(c, n), 1) if n > 1 else (c, n) for c, n in joined(chain)])
        row("runs", nodes, was, came, 4 * was["g1"] + 2 * was["g0"] + 2 * was["gt"], crossing=crossing, engine_weight=engine_weight, grammar_weight=grammar_weight, power_log=max(powers.values(), default=0.0) / max(math.log2(max(log_n, 2)), 1))
        weigh = counts if counts != "alternate" else ("tree", "grammar")[phase % 2 == 0]
        pairs = pair_counts(h, weigh)
        nodes, was = tree_nodes(h), tally(h)
        if pairs:
            up = colour(pairs)
            came = popped_up_and_down(h, lambda c: up(c) is False, lambda c: up(c) is True)
            crossing = len(crossing_pairs(h, up))
            seen: Counter = Counter()

            def merged(chain: list) -> list:
                out, i = [], 0
                flat = [c for c, n in chain for _ in range(n)]
                while i < len(flat):
                    if i + 1 < len(flat) and flat[i] != flat[i + 1] and up(flat[i]) is True and up(flat[i + 1]) is False:
                        out.append((h.letters.pair(flat[i], flat[i + 1]), 1))
                        seen[out[-1][0]] += 1
                        i += 2
                    else:
                        out.append((flat[i], 1))
                        i += 1
                return out

            each_chain(h, merged)
            row("pairs", nodes, was, came, 4 * was["g1"] + 2 * was["g0"] + 2 * was["gt"], 4 * sum(seen.values()), 2 * sum(seen.values()) + 2 * len(seen), crossing=crossing)
        nodes, was = tree_nodes(h), tally(h)
        came, twice = pop_leaves(h, phase)
        crossing = crossing_leaves(h)
        consumed, new, costs = absorb(h)
        row("leaves", nodes, was, came, 2 * was["g1"] * r + 2 * was["g0"] + 2 * was["gt"], 2 * consumed, 2 * new + sum(costs.values()), crossing=crossing + len(twice))
    return ledger


def grammar_of_tree(root: Node, letters: Letters, max_phases: int | None = None) -> Grammar:
    """The compressor's own grammar of a tree, as explicit rules with parameters; what is left after max_phases is the start rule."""
    compress_plain({0: root}, letters, max_phases=max_phases)

    def over(x: int, kids: list[Tree]) -> Tree:
        return N(x, *kids) if x in letters.rules else T(letters.names[x], *kids)

    rules, todo = {}, []

    def written(node: Node) -> Tree:
        done: dict[int, Tree] = {}
        for n in reversed(list(walk([node]))):
            done[id(n)] = over(n.sym, [done[id(k)] for _, k in n.kids])
            todo.append(n.sym)
        return done[id(node)]

    rules["S"] = (0, written(root))
    while todo:
        x = todo.pop()
        if x in rules or x not in letters.rules:
            continue
        kind, what = letters.rules[x]
        if kind == "leaf":
            f, leaves = what
            at, given, y = dict(leaves), [], 0
            for s in letters.slots[f]:
                if s in at:
                    given.append(over(at[s], []))
                else:
                    y += 1
                    given.append(Y(y))
            rules[x] = (y, over(f, given))
            todo += [f, *at.values()]
        else:
            parts = [what[0]] * what[1] if kind == "run" else list(what)
            tree = Y(1)
            for p in reversed(parts):
                tree = over(p, [tree])
            rules[x] = (1, tree)
            todo += parts
    return Grammar(rules, "S")


def per_tree(nodes: DataFrame, work: Callable[[int, list[tuple]], list[dict]], schema: str) -> DataFrame:
    """work(tree_id, rows) for each tree of (tree_id, pre, parent, slot, name, rank); a tree is one task's work."""
    from pyspark.sql.types import _parse_datatype_string
    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(_parse_datatype_string(schema))
    columns = ("tree_id", "pre", "parent", "slot", "name", "rank")

    def run(table: pa.Table) -> pa.Table:
        sys.setrecursionlimit(max(sys.getrecursionlimit(), 50_000))  # rule trees are walked as deep as they are
        rows = list(zip(*(table.column(c).to_pylist() for c in columns)))
        return pa.Table.from_pylist(work(rows[0][0], rows), arrow)

    return nodes.select(*columns).groupBy("tree_id").applyInArrow(run, schema)


def through_handles(nodes: DataFrame, phases: int | None = 2) -> DataFrame:
    """(tree_id, pre, parent, slot, name, rank): each tree by the value of the handle grammar made of a grammar of it."""

    def work(tree: int, rows: list[tuple]) -> list[dict]:
        letters = Letters()
        h = to_handles(grammar_of_tree(trees_of(rows, letters)[tree], letters, phases))
        labels = [(h.letters.names[x], len(h.letters.slots[x])) for x in handle_value(h)]
        return [dict(zip(("tree_id", "pre", "parent", "slot", "name", "rank"), (tree, *r))) for r in preorder(labels)]

    return per_tree(nodes, work, "tree_id long, pre long, parent long, slot int, name string, rank int")


def ledgers(nodes: DataFrame, counts: str = "tree", phases: int | None = 2) -> DataFrame:
    """The ledger of each tree's grammar under recompression, and whether its last letter is the tree engine's."""
    columns = "tree_id long, phase int, step string, nodes long, g1 long, g0 long, gt long, letters long, issued long, bound long, released long, paid long, broken int, crossing int, engine_weight double, grammar_weight double, power_log double, same boolean"

    def work(tree: int, rows: list[tuple]) -> list[dict]:
        letters = Letters()
        h = to_handles(grammar_of_tree(trees_of(rows, letters)[tree], letters, phases))
        ledger = recompress(h, counts)
        plain = Letters()
        roots = trees_of(rows, plain)
        compress_plain(roots, plain)
        same = h.rules[h.start] == [("C", roots[tree].sym)]
        return [{"tree_id": tree, **x, "same": same} for x in ledger]

    return per_tree(nodes, work, columns)


def sizes_of_handles(nodes: DataFrame, phases: int | None = 2) -> DataFrame:
    """Size of each tree's grammar, its normal form and its handle grammar, with occurrences of nonterminals and the bounds of the conversion."""
    columns = "tree_id long, rank int, size long, normal long, handle long, g1 long, g0 long, wrong int, within boolean"

    def work(tree: int, rows: list[tuple]) -> list[dict]:
        letters = Letters()
        g = grammar_of_tree(trees_of(rows, letters)[tree], letters, phases)
        r = max(1, *(rank for *_, rank in rows))
        normal, _ = normal_form(g)
        h = to_handles(g)
        t = tally(h)
        m = len(normal)
        held = t["g1"] <= 8 * m and t["g0"] + t["letters"] <= 4 * (r + 1) * m
        return [{"tree_id": tree, "rank": r, "size": size(g), "normal": m, "handle": t["letters"] + t["g1"] + t["g0"], "g1": t["g1"], "g0": t["g0"], "wrong": len(violations(g)) + len(handle_violations(h)), "within": held}]

    return per_tree(nodes, work, columns)
