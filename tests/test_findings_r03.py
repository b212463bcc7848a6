"""One small test for each finding of round 3."""

from collections import Counter
from pathlib import Path

import numpy as np


def plain_rounds(names, code, rank, parent, slot, max_rank):
    """Digrams made and nodes left by whole rounds over all nodes; letters as (id, rank), nodes as [letter, children]."""
    from canopy.operators.packed import SEEDS, hash_int, hash_long, ids

    nodes = [[int(names[c]), []] for c in code]
    for i, p in enumerate(parent):
        if p >= 0:
            nodes[p][1].append(nodes[i])
    roots, made = [nodes[i] for i, p in enumerate(parent) if p < 0], 0

    def walk():
        todo = roots[::-1]
        while todo:
            yield (x := todo.pop())
            todo += x[1][::-1]

    while True:
        n = Counter((x[0], j, y[0]) for x in walk() for j, y in enumerate(x[1], 1) if len(x[1]) + len(y[1]) - 1 <= max_rank)
        order = {k: (-c, k) for k, c in n.items() if c > 1}
        best = {}
        for k, o in order.items():
            for x in {k[0], k[2]}:
                best[x] = min(best.get(x, o), o)
        tops = {k[0]: k for k, o in order.items() if best[k[0]] == o == best[k[2]]}
        if not tops:
            return made, sum(1 for _ in walk())
        made += len(tops)
        for x in walk():  # from the top: the upper node takes its child in before that is met
            if (k := tops.get(x[0])) and len(x[1]) >= k[1] and x[1][k[1] - 1][0] == k[2]:
                y = x[1][k[1] - 1]
                x[0] = int(ids(hash_long(k[2], hash_int(k[1], hash_long(k[0], SEEDS["digram"]))))[0])
                x[1][k[1] - 1 : k[1]] = y[1]


def random_forest(seed, size, letters, chain):
    """Columns of trees in pre-order, a letter's rank by its number."""
    rng = np.random.default_rng(seed)
    names = np.sort(rng.integers(-(2**62), 2**62, letters))
    ranks = np.array([0, 1, 1, 1, 1] if chain else [0, 0, 1, 2, 3, 12])[np.arange(letters) % (5 if chain else 6)]
    code, parent, slot = [], [], []
    while len(code) < size:
        todo, budget = [(-1, 0)], int(rng.integers(1, 200))
        while todo:
            up, at = todo.pop()
            budget -= 1
            fits = np.flatnonzero(ranks == 0) if budget < 0 else np.flatnonzero(ranks > 0) if chain else np.arange(letters)
            code.append(int(rng.choice(fits)))
            parent.append(up)
            slot.append(at)
            todo += [(len(code) - 1, j) for j in range(int(ranks[code[-1]]), 0, -1)]
    x = np.array(code)
    return names, x.astype(np.int32), ranks[x].astype(np.int32), np.array(parent, np.int32), np.array(slot, np.int32)


def test_f1_digram_rounds_touch_what_changes(monkeypatch):
    from canopy.operators import digrams

    met, rounds = [], []
    meet, replace = digrams.Rounds.meet, digrams.Rounds.replace
    monkeypatch.setattr(digrams.Rounds, "meet", lambda self, low: met.append(len(low)) or meet(self, low))
    monkeypatch.setattr(digrams.Rounds, "replace", lambda self, tops: rounds.append(len(tops)) or replace(self, tops))
    for seed in range(12):
        forest = random_forest(seed, 1500, 2 + seed if seed % 3 else 12 + seed, chain=seed % 2 == 0)
        want = plain_rounds(*forest, 8)
        met.clear(), rounds.clear()
        n = len(forest[1])
        assert digrams.Rounds(*(x.copy() for x in forest), 8).run() == want
        assert sum(met) < 6 * n and sum(rounds) == want[0]


def test_f1_digrams_of_packs_in_one_task(spark, monkeypatch):
    from canopy.model import Forest
    from canopy.operators import digrams, measures as M
    from canopy.operators import packed

    names, code, rank, parent, slot = random_forest(5, 900, 9, chain=False)
    tree = np.cumsum(parent < 0)
    rows = [(int(t), 3 * i, None if p < 0 else 3 * int(p), int(s), int(names[c]), int(r)) for i, (t, p, s, c, r) in enumerate(zip(tree, parent, slot, code, rank))]
    nodes = spark.createDataFrame(rows, "tree_id long, pre long, parent long, slot int, sym long, rank int")
    monkeypatch.setattr(packed, "PACK", 64)
    made, left = plain_rounds(names, code, rank, parent, slot, 8)
    assert len(rows) <= digrams.ONE_TASK and M.digram_size(Forest(nodes, None)) == 2 * made + left


def test_f2_rules_of_texts_take_less_disk_than_texts(spark, tmp_path, monkeypatch):
    from canopy import grammar_queries as G
    from canopy.operators import packed

    rng = np.random.default_rng(3)
    words = ["".join(chr(97 + x) for x in rng.integers(0, 26, rng.integers(2, 9))) for _ in range(400)]
    texts = [(i, " ".join(words[j] for j in rng.integers(0, 400, 900)) if i % 9 else [None, "", "a", "aaaaaaa", "\u00e9\U0001f600 b"][i // 9 % 5]) for i in range(45)]
    texts.append((99, texts[1][1]))
    spark.createDataFrame(texts, "doc_id long, text string").repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    monkeypatch.setattr(packed, "COMPARED", 5000)
    made, phases = [], packed.phases
    monkeypatch.setattr(packed, "phases", lambda *x: made.append(phases(*x)) or made[-1])
    assert sorted(map(tuple, G.QUERIES["w4_roundtrip_text"](spark, str(tmp_path)).collect())) == [(i, t or "") for i, t in texts]
    files = [p.stat().st_size for p in Path(made[0].path.removeprefix("file://")).rglob("what=*/*.parquet")]
    assert sum(files) < 2 * sum(len(t or "") for _, t in texts)


def test_f2_one_id_for_two_keys_is_found_in_any_share(spark):
    from canopy.operators import packed

    def held(names):
        own = packed.Own(np.array(names, np.int64), np.ones(len(names), np.int64))
        own.add("pair", np.array([2]), np.array([0, 1]), np.array([1, 2]))
        own.add("run", np.array([1]), np.array([0]), np.array([3]))
        return own

    one, same = held([5, 6]), held([5, 6])
    made = int(one.hashed()[0][2])
    other = held([made, 7])  # a letter of the input with the id of a pair
    rows = lambda *x: spark.createDataFrame([(bytearray(o.dump()), o.count()) for o in x], "state binary, weight long")
    for shares in (1, 3):
        assert not [r for i in range(shares) for r in packed.clashes(rows(one, same), i, shares).collect()]
        assert [r.sym for i in range(shares) for r in packed.clashes(rows(one, same, other), i, shares).collect()] == [made]
