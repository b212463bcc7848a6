"""Recompression of chain grammars against the tree engine on the expanded chains."""

import pytest
from pyspark.sql import functions as F

from canopy.model import forest_of
from canopy.operators import chains as C
from canopy.operators.compressor import Config, compress
from canopy.sources import relational as S

TEXTS = [(1, "abababab"), (2, "aaaabaaab"), (3, ""), (4, None), (5, "c"), (6, "mississippimississippi"), (7, "abababab"), (8, "aaaa")]


@pytest.fixture(scope="module")
def texts(spark):
    return spark.createDataFrame(TEXTS, "k long, t string")


@pytest.fixture(scope="module")
def built(spark, texts):
    return C.bisection_grammar(texts, "k", "t")


def test_bisection_grammar_is_sound(built):
    assert C.violations(built).count() == 0


def test_pair_counts_are_those_of_the_text(spark, built):
    free, _, _ = C.popped(built, "runs")
    free, _ = C.compress_runs(free)
    want = {}
    from itertools import groupby

    for _, t in TEXTS:
        runs = [(c, len(list(g))) for c, g in groupby(t or "")]
        for x, y in zip(runs, runs[1:]):
            want[x, y] = want.get((x, y), 0) + 1
    assert sorted(r["occ"] for r in C.pair_graph(free).collect()) == sorted(want.values())


def test_letters_equal_the_tree_engines(spark, texts, built):
    got = C.recompress(built, "greedy")
    tree = compress(forest_of(S.strings(texts, "k", "t", "char")), Config(steps=("runs", "pairs"), partition="greedy"))
    assert {r["sym"] for r in got.keys.collect()} == {r["sym"] for r in tree.rules.collect()}
    for s in got.stats:
        assert s["run_moved"] <= 2 * s["run_occurrences"] and s["pair_moved"] <= 2 * s["pair_occurrences"]


@pytest.mark.parametrize("counts", ["grammar", "alternate"])
def test_every_weighting_gives_the_texts_back(built, counts):
    got = {r["tree_id"]: r["text"] for r in C.unfold(C.recompress(built, "greedy", counts), built.names).collect()}
    assert got == {k: t or "" for k, t in TEXTS}


def test_no_pair_crosses_after_popping(spark, built):
    free, _ = C.compress_runs(C.popped(built, "runs")[0])
    sides = C.P.choose(C.pair_graph(free), "greedy")
    assert C.crossing_pairs(free, sides).count() > 0
    assert C.crossing_pairs(C.popped(free, "pairs", sides)[0], sides).count() == 0


def test_empty_table(spark, texts):
    g = C.bisection_grammar(texts.limit(0), "k", "t")
    assert C.unfold(C.recompress(g), g.names).count() == 0
