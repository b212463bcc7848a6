"""Worked examples, closed forms and round trips."""

import math

import pytest

from canopy.model import forest_of
from canopy.operators import measures as M
from canopy.operators import pairs as P
from canopy.operators import runs as R
from canopy.operators.compressor import Config, compress, expand, grammar_size
from canopy.sources import relational as S


def run_cost(m):
    return 0 if m < 2 else 2 * int(math.log2(m)) + (bin(m).count("1") if bin(m).count("1") > 1 else 0)


def same(a, b):
    return sorted(map(tuple, a.collect()), key=str) == sorted(map(tuple, b.select(a.columns).collect()), key=str)


@pytest.mark.parametrize("term,size,phases", [("f(a(b(c)),a(b(d)))", 9, [7, 3]), ("b(a(a(a(c))))", 8, [5]), ("f(c,f(c,f(c,c)))", 7 + run_cost(2), [7, 3])])
def test_worked_examples(spark, term, size, phases):
    f = forest_of(S.from_terms(spark, {0: term}))
    g = compress(f)
    assert grammar_size(g) == size
    assert [s["nodes"] for s in g.stats] == phases
    assert same(f.nodes, expand(g))
    assert M.violations(g).count() == 0 and M.weight_conserved(g).count() == 0


@pytest.mark.parametrize("lens,gap,binary,direct", [([2, 5, 9], 10, 10, 16), (list(range(1001, 1011)), 43, 92, 10055), ([8], 6, 6, 8)])
def test_run_schemes(spark, lens, gap, binary, direct):
    keys = spark.createDataFrame([(1, m) for m in lens], "base long, len int")
    assert [R.represent_runs(keys, s).agg({"cost": "sum"}).first()[0] for s in ("gap", "binary", "direct")] == [gap, binary, direct]


def test_trivial_inputs(spark):
    g = compress(forest_of(S.from_terms(spark, {1: "c", 2: "a(c)", 3: "c"})))
    assert g.starts.count() == 3 and grammar_size(g) == 2
    empty = compress(forest_of(S.from_terms(spark, {1: "c"}).limit(0)))
    assert empty.starts.count() == 0 and grammar_size(empty) == 0


def test_early_stop_keeps_residual(spark):
    f = forest_of(S.family(spark, "binary", 6))
    g = compress(f, Config(stop_size=40))
    assert g.residual.count() == 31 and grammar_size(g) <= 2 * f.nodes.count() - 1


def test_colourings_cover_their_floor(spark):
    arcs = spark.createDataFrame([(1, 2, 5), (2, 3, 4), (3, 1, 7), (2, 1, 1), (4, 1, 2)], "a long, b long, occ long")
    best = P.covered(arcs, P.choose(arcs, "exact"))[1]
    for method in ("greedy", "linear", "random"):
        total, ud, du = P.covered(arcs, P.choose(arcs, method))
        assert best >= ud >= du
        assert method == "random" or 4 * ud >= total


def test_unordered_leaves_share_a_letter(spark):
    f = forest_of(S.from_terms(spark, {1: "f(c,d)", 2: "f(d,c)"}))
    assert compress(f, Config(ordered_leaves=False)).rules.count() == 1
    assert compress(f).rules.count() == 2
