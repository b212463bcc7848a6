"""Measures of strings, against plain versions."""

import random

from canopy import queries as Q
from canopy.model import forest_of
from canopy.operators import measures as M
from canopy.sources import relational as S


def plain_factors(s: str) -> int:
    n = i = 0
    while i < len(s):
        j = i + 1
        while j <= len(s) and s.find(s[i:j]) < i:
            j += 1
        i, n = max(j - 1, i + 1), n + 1
    return n


def test_factor_counts():
    rng = random.Random(7)
    for _ in range(300):
        s = "".join(rng.choice("ab" if rng.random() < 0.5 else "abcd") for _ in range(rng.randrange(40)))
        assert M.count_factors(s) == plain_factors(s), s
    assert [M.count_factors(s) for s in ("", "a", "aaaa", "abababab", "abc")] == [0, 1, 2, 3, 3]


def test_factors_are_a_floor(spark):
    texts = spark.createDataFrame([(0, None), (1, "abab" * 40), (2, "a" * 300), (3, "mississippi" * 5)], "doc_id long, text string")
    got = {r.key: r.factors for r in M.factor_counts(texts, "doc_id", "text").collect()}
    assert got[0] == 0 and got[2] == 2
    assert all(got[i] <= M.bisection_size(texts.where(f"doc_id = {i}"), "doc_id", "text") for i in (1, 2, 3))


def plain_bisection(texts) -> int:
    seen, todo = set(), [t for t in texts if t]
    while todo:
        s = todo.pop()
        if len(s) > 1 and s not in seen:
            seen.add(s)
            half = 1 << (len(s) - 1).bit_length() - 1
            todo += [s[:half], s[half:]]
    return 2 * len(seen)


def test_bisection_of_all_documents(spark, tmp_path):
    rng = random.Random(3)
    texts = [None, "", "a", "ab", "aba", "é🙂é🙂é", "abcd" * 8, "abcd" * 8 + "x"] + ["".join(rng.choice("abc") for _ in range(rng.randrange(90))) for _ in range(60)]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    assert Q.QUERIES["baseline_bisection"](spark, str(tmp_path)).first()[0] == plain_bisection(texts)


def test_digrams_until_none_occurs_twice(spark):
    size = lambda terms: M.digram_size(forest_of(S.from_terms(spark, dict(enumerate(terms)))))
    assert size([f"f{i}(g{i})" for i in range(45)] * 3) == 2 * 45 + 3 * 45
    assert size(["f(g(a),h(b,c))"] * 3 + ["a(b(" * 16 + "c" + "))" * 16]) == 2 * 5 + 3 + 2 * 4 + 3
