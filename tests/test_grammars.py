"""Explicit grammars, the plain engine, and the engine's variants, against each other and the worked examples."""

import math
import random
from collections import Counter

import pytest

from canopy.model import forest_of
from canopy.operators import analytics as A
from canopy.operators import handles as G
from canopy.operators import measures as M
from canopy.operators import pairs as P
from canopy.operators import runs as R
from canopy.operators.compressor import Config, compress, expand, expand_symbol, grammar_size
from canopy.operators.leaves import absorb_leaves
from canopy.operators.small import Letters, compress_plain, hashed, input_letter, leaf_letter, pair_letter, preorder, run_letter, trees_of
from canopy.sources import relational as S

SCHEMA = "tree_id long, pre long, parent long, slot int, name string, rank int"


def random_tree(seed, k, tree=0, letters=2):
    rng, made, open_ = random.Random(seed), [], [(None, None)]
    while open_:
        parent, slot = open_.pop()
        rank = 0 if len(made) + len(open_) >= k else rng.choice([0, 1, 1, 1, 2, 2, 3])
        rank = max(rank, 1) if not open_ and len(made) + 1 < k else rank
        made.append((tree, len(made), parent, slot, "cabf"[rank] + str(rng.randrange(letters)), rank))
        open_ += [(len(made) - 1, j) for j in range(rank, 0, -1)]
    return made


def rows_of(df):
    return sorted(tuple(r) for r in df.select("tree_id", "pre", "parent", "slot", "sym", "rank").collect())


# ---- explicit grammars

T, N, Y = G.T, G.N, G.Y


def test_substitution_of_a_rule_of_two_parameters():
    g = G.Grammar({"A": (2, T("f", T("f", Y(1), T("c")), Y(2))), "S": (0, T("f", T("c"), N("A", T("a", T("f", T("c"), T("c"))), T("f", T("a", T("c")), T("c")))))}, "S")
    want = T("f", T("c"), T("f", T("f", T("a", T("f", T("c"), T("c"))), T("c")), T("f", T("a", T("c")), T("c"))))
    assert G.derive_once(g.rules["S"][1], g, 2) == want
    assert G.value(g) == G.value(g, want) and not G.violations(g)
    assert G.size(g) == 14 and G.size(g, count_params=True) == 16


def test_popping_leaves_one_rule():
    h = G.to_handles(G.Grammar({"A1": (1, T("a", Y(1))), "S": (0, N("A1", T("b", T("c"))))}, "S"))
    a, b = input_letter("a", 1), input_letter("b", 1)
    up = lambda x: x == a
    assert (a, b) in {(u, v) for _, u, v, _ in G.neighbours(h)}
    G.popped_up_and_down(h, lambda x: not up(x), up)
    assert not G.crossing_pairs(h, up) and any([x[:3] for x in body][:2] == [("U", a, 1), ("U", b, 1)] for body in h.rules.values())


def test_violations_are_found():
    bad = G.Grammar({"A": (2, T("f", Y(2), Y(1))), "B": (1, T("f", Y(1), Y(1))), "C": (0, N("C")), "S": (0, N("A", T("c"), N("X")))}, "S")
    assert {w for _, w in G.violations(bad)} == {"parameters out of order", "parameters are not each used once", "cycle", "no rule", "unused"}
    turned = G.in_order(G.Grammar({"A": (2, T("f", Y(2), Y(1))), "S": (0, N("A", T("c"), T("d")))}, "S"))
    assert not G.violations(turned) and [n for n, _ in G.value(turned)] == ["f", "d", "c"]


def test_eight_rules_of_one_letter():
    """Values of the rules of the worked example of run representation, and its powers."""
    words = {0: "a", 1: ["b", "c", "a", 0], 2: [0, "a", "b", "c"], 3: [0, "a", 0], 4: [1, "a", 0], 5: [0, "a", 2], 6: [1, "a", 2], 7: ["b", "a", "a", 3]}
    rules = {}
    for k, word in words.items():
        tree = Y(1)
        for x in reversed(word):
            tree = T(x, tree) if isinstance(x, str) else N(x, tree)
        rules[k] = (1, tree)
    text = lambda k: "".join(n for n, _ in G.value(G.Grammar({**rules, "S": (0, N(k, T("#")))}, "S")))[:-1]
    assert [text(k) for k in range(8)] == ["a", "bcaa", "aabc", "aaa", "bcaaaa", "aaaabc", "bcaaaaabc", "baaaaa"]
    tree = T("#")
    for k in range(8):
        tree = N(k, T("|", tree))
    h = G.to_handles(G.Grammar({**rules, "S": (0, tree)}, "S"))
    log = []
    G.popped_up_and_down(h, lambda _: True, lambda _: True, log)
    a = input_letter("a", 1)
    assert {n for _, (_, c, n, _, pieces) in log if c == a and len(pieces) > 1} >= {3, 5}
    grammar, engine, _ = G.run_costs(log)
    assert engine <= grammar + 1e-9


@pytest.mark.parametrize("seed", range(30))
def test_random_grammars_through_all_steps(seed):
    """Value, normal form, handles and recompression with every weighting; letters are the plain engine's; the ledger's bounds hold."""
    rows = random_tree(seed, random.Random(seed).randint(1, 90))
    want = [(r[4], r[5]) for r in rows]
    for phases in (None, 0, 1, 2):
        letters = Letters()
        g = G.grammar_of_tree(trees_of(rows, letters)[0], letters, phases)
        assert not G.violations(g) and G.value(g) == want
        h = G.to_handles(g)
        assert not G.handle_violations(h)
        assert [(h.letters.names[x], len(h.letters.slots[x])) for x in G.handle_value(h)] == want
        for counts in ("tree", "grammar", "alternate"):
            h = G.to_handles(g)
            ledger = G.recompress(h, counts)
            assert h.letters.weight[h.rules[h.start][0][1]] == len(rows)
            plain = Letters()
            roots = trees_of(rows, plain)
            active = compress_plain(roots, plain)
            if counts == "tree":
                assert h.rules[h.start] == [("C", roots[0].sym)] and [x["nodes"] for x in ledger if x["step"] == "runs"] == active
            for x in ledger:
                assert x["issued"] <= x["bound"] and x["paid"] <= x["released"] and not x["broken"] and not x["crossing"]
                assert x["engine_weight"] <= x["grammar_weight"] + 1e-9 and x["power_log"] <= 1 + 1e-9


# ---- the engine


def test_python_ids_are_sparks(spark):
    got = spark.sql("SELECT xxhash64('input', 'né', 2), xxhash64('run', -5L, 7L), xxhash64('pair', 1L, -2L), xxhash64('leaf', 9L, array(named_struct('slot', 1, 'sym', 5L), named_struct('slot', 3, 'sym', -6L))), xxhash64(77L, 5)").first()
    assert tuple(got) == (input_letter("né", 2), run_letter(-5, 7), pair_letter(1, -2), leaf_letter(9, ((1, 5), (3, -6))), hashed(77, (5,)))


@pytest.fixture(scope="module")
def forest(spark):
    rows = [r for t in range(12) for r in random_tree(t + 500, 5 + 9 * t, t)]
    return rows, forest_of(spark.createDataFrame(rows, SCHEMA))


def test_forest_letters_are_those_of_plain_search(spark, forest):
    rows, f = forest
    g = compress(f)
    plain = Letters()
    roots = trees_of(rows, plain)
    active = compress_plain(roots, plain)
    assert {r.tree_id: r.sym for r in g.starts.collect()} == {t: n.sym for t, n in roots.items()}
    assert [s["nodes"] for s in g.stats] == active
    got = {r.sym: (r.kind, r.weight) for r in g.rules.collect()}
    assert got == {x: (k, plain.weight[x]) for x, (k, _) in plain.rules.items()}
    assert rows_of(expand(g)) == rows_of(f.nodes)
    assert M.violations(g).count() == 0 and M.weight_conserved(g).count() == 0
    assert M.bounds_held(g, f)[1:] == (True,) * 5


@pytest.mark.parametrize("block", [1, 16])
def test_blocks_change_nothing(spark, forest, block):
    """Runs, pairs and parents across the borders of blocks of any size; a long run through many blocks."""
    rows, f = forest
    chain = [(99, i, i - 1 if i else None, 1 if i else None, "a0" if i < 40 else "a1" if i < 43 else "c0", 1 if i < 43 else 0) for i in range(44)]
    f = forest_of(spark.createDataFrame(rows + chain, SCHEMA))
    whole, parts = compress(f), compress(f, Config(block=block))
    assert sorted(r.sym for r in whole.rules.select("sym").collect()) == sorted(r.sym for r in parts.rules.select("sym").collect())
    assert sorted(whole.starts.collect()) == sorted(parts.starts.collect()) and whole.stats == parts.stats


def test_scopes(spark, forest):
    rows, f = forest
    one = compress(f, Config(scope="joined"))
    assert one.starts.count() == 1 and one.starts.first().n == len(rows) + 11
    assert M.bounds_held(one, f)[1]
    own = compress(f, Config(scope="tree"))
    used = Counter()
    for tree, sym in [(r.tree_id, r.sym) for r in own.starts.collect()]:
        used[sym] += 1
    assert max(used.values()) == 1 and own.rules.count() >= compress(f).rules.count()


@pytest.mark.parametrize("cfg", [Config(stop_size=12), Config(steps=("runs", "pairs")), Config(max_phases=1), Config(partition="greedy")])
def test_every_variant_derives_the_forest(spark, forest, cfg):
    rows, f = forest
    g = compress(f, cfg)
    assert rows_of(expand(g)) == rows_of(f.nodes)
    assert grammar_size(g) <= 2 * len(rows) - 1 or cfg.steps != ("runs", "pairs", "leaves")


def test_unordered_grammar_derives_the_same_multisets(spark, forest):
    rows, f = forest
    g = compress(f, Config(ordered_leaves=False))
    count = lambda df: sorted((r.tree_id, r.sym, r["count"]) for r in df.groupBy("tree_id", "sym").count().collect())
    assert count(expand(g)) == count(f.nodes)


def test_single_letter_pair_and_key_variants(spark):
    f = forest_of(S.from_terms(spark, {1: "a(a(b(b(g(c,a(c))))))", 2: "a(b(g(c,d)))"}))
    ids = {r.name: r.sym for r in f.symbols.collect()}
    only, keys = R.compress_runs(f.nodes, [ids["a"]])
    assert [(r.base, r.len) for r in keys.collect()] == [(ids["a"], 2)] and only.count() == f.nodes.count() - 1
    out, keys = P.compress_pairs(f.nodes, pair=(ids["a"], ids["b"]))
    assert [(r.a, r.b) for r in keys.collect()] == [(ids["a"], ids["b"])] and out.count() == f.nodes.count() - 2
    out, fresh = absorb_leaves(f.nodes, key=(ids["g"], [(1, ids["c"]), (2, ids["d"])]))
    assert fresh.count() == 1 and out.count() == f.nodes.count() - 2
    lists = {r.sym: r for r in P.neighbour_lists(P.pair_graph(f.nodes)).collect()}
    assert [tuple(x) for x in lists[ids["a"]].below] == [(ids["b"], 2)] and [tuple(x) for x in lists[ids["b"]].above] == [(ids["a"], 2)]


def test_random_colouring_covers_a_quarter_on_average(spark):
    rng = random.Random(1)
    arcs = Counter((rng.randrange(40), rng.randrange(40)) for _ in range(2000))
    arcs = spark.createDataFrame([(a, b, n) for (a, b), n in arcs.items() if a != b], "a long, b long, occ long")
    shares = [P.covered(arcs, P.by_hash(arcs, s))[1] / P.covered(arcs, P.by_hash(arcs, s))[0] for s in range(12)]
    assert abs(sum(shares) / len(shares) - 0.25) < 0.03


def test_pattern_heights_and_single_nodes(spark, forest):
    rows, f = forest
    g = compress(f)
    depth, high = {}, Counter()
    for t, pre, parent, *_ in rows:
        depth[t, pre] = 0 if parent is None else depth[t, parent] + 1
        high[t] = max(high[t], depth[t, pre])
    assert {r.tree_id: r.height for r in A.tree_heights(g).collect()} == dict(high)
    want = {(t, pre): (parent, slot, name) for t, pre, parent, slot, name, _ in rows if pre % 7 == 0}
    wanted = spark.createDataFrame(list(want), "tree_id long, pre long")
    assert {(r.tree_id, r.pre): (r.parent, r.slot, r.name) for r in A.node_at(g, wanted).collect()} == want
    sym = g.rules.where("kind = 'pair'").first()
    if sym:
        assert expand_symbol(g, sym.sym).count() == sym.weight
    classes = {r.tree_id: r["class"] for r in A.equal_trees(g).collect()}
    text = {t: [r[4:] for r in rows if r[0] == t] for t in range(12)}
    assert all((classes[a] == classes[b]) == (text[a] == text[b]) for a in text for b in text)


def test_written_and_read_again(spark, forest, tmp_path):
    rows, f = forest
    g = compress(f)
    A.write_grammar(g, f"file://{tmp_path}/g")
    assert rows_of(expand(A.read_grammar(spark, f"file://{tmp_path}/g"))) == rows_of(f.nodes)
    assert A.written_rules(g).count() == g.rules.count() and A.dot_lines(g).count() > 0


def test_one_id_for_two_keys_is_an_error(spark, monkeypatch):
    from canopy.operators import compressor

    monkeypatch.setattr(compressor, "letter", lambda *key: compressor.F.lit(7).cast("long"))
    with pytest.raises(ValueError, match="two keys"):
        compress(forest_of(S.from_terms(spark, {1: "a(a(c))", 2: "b(b(c))"})))


# ---- baselines and measures


def plain_dag(roots):
    seen = {}

    def go(n):
        key = (n.sym, tuple((s, go(k)) for s, k in n.kids))
        return seen.setdefault(key, len(seen))

    for r in roots.values():
        go(r)
    return sum(len(kids) + 1 for _, kids in seen if kids)


def test_dag_digram_and_trivial_sizes(spark, forest):
    rows, f = forest
    assert M.dag_size(f) == plain_dag(trees_of(rows, Letters()))
    assert M.trivial_size(f) == len(rows)
    assert M.digram_size(f) <= len(rows)


def test_phrases_of_strings(spark):
    def plain(s):
        known, n, at = set(), 0, 0
        while at < len(s):
            end = at + 1
            while end <= len(s) and s[at:end] in known:
                end += 1
            known.add(s[at:end])
            n, at = n + 1, min(end, len(s) + 1)
        return n

    texts = [None, "", "a", "aaaaaa", "abababab", "mississippi" * 3]
    df = spark.createDataFrame(list(enumerate(texts)), "k long, t string")
    assert {r.key: r.phrases for r in M.phrase_size(df, "k", "t").collect()} == {i: plain(t or "") for i, t in enumerate(texts)}


def test_online_grammar_derives_its_input_and_keeps_digrams_unique():
    rng = random.Random(4)
    for _ in range(60):
        word = [rng.choice("abc") for _ in range(rng.randrange(60))]
        rules = M.sequential_grammar(word)

        def text(n):
            return [c for x in rules[n] for c in (text(x[1]) if isinstance(x, tuple) else [x])]

        assert text(0) == word
        used = Counter(x[1] for body in rules.values() for x in body if isinstance(x, tuple))
        assert all(used[n] > 1 for n in rules if n)
        spots = Counter()
        for body in rules.values():
            last = None
            for i, key in enumerate(zip(body, body[1:])):
                if last == (key, i - 1):
                    continue
                spots[key] += 1
                last = (key, i)
        assert all(n == 1 for n in spots.values())


@pytest.mark.parametrize("kind,k", [("comb", 20), ("fibonacci", 10)])
def test_planted_families_stay_within_the_bound(spark, kind, k):
    r = M.planted_ratio(spark, kind, k).first()
    assert r.size / r.planted <= 2.5 and r.size <= M.bound(2, r.planted, r.nodes)


def test_preorder_and_families(spark):
    rows = random_tree(9, 50)
    assert preorder([(r[4], r[5]) for r in rows]) == [r[1:] for r in rows]
    f = forest_of(S.family(spark, "random", 40))
    assert rows_of(expand(compress(f))) == rows_of(f.nodes)
    assert math.isclose(M.bound(1, 4, 64), 4 + 4 * 4)
