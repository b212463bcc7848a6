"""Costs, bounds and baselines of a forest or grammar."""

from __future__ import annotations

import math
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from canopy.model import Forest, Grammar, settle, unsettle
from canopy.operators import digrams, packed, scan
from canopy.operators.analytics import occurrences
from canopy.operators.compressor import census


def chain_stats(nodes: DataFrame) -> DataFrame:
    """n, n0, n1, n2plus, chains and whether the inequalities n0 >= n2plus + trees and chains <= n2plus + n0 hold."""
    c = census(nodes)
    trees = nodes.where("parent is null").count()
    row = (c["nodes"], c["n0"], c["n1"], c["n2plus"], c["chains"], c["n0"] >= c["n2plus"] + trees, c["chains"] <= c["n2plus"] + c["n0"])
    return nodes.sparkSession.createDataFrame([row], "n long, n0 long, n1 long, n2plus long, chains long, leaf_bound boolean, chain_bound boolean")


def shrink(g: Grammar) -> list[float]:
    """Nodes of each phase over nodes of the phase before; below 3/4 with all three steps."""
    n = [s["nodes"] for s in g.stats]
    return [b / a for a, b in zip(n, n[1:])]


def bound(r: int, g: int, n: int) -> float:
    """The proved output size, without its constant."""
    return r * g + r * g * max(0.0, math.log2(n / (r * g)))


def bounds_held(g: Grammar, forest: Forest) -> tuple[int, bool, bool, bool, bool, bool]:
    """Nodes, and whether every phase shrinks below 3/4, all phases' nodes are at most 4n, phases at most log n to base 4/3 and one, no letter has more parameters than the input's, and the size is at most 2n - 1."""
    from canopy.operators.compressor import grammar_size

    n, r = forest.nodes.agg(F.count("*"), F.coalesce(F.max("rank"), F.lit(0))).first()
    most = g.rules.agg(F.coalesce(F.max("rank"), F.lit(0))).first()[0]
    return within({"nodes": int(n), "rank": r, "stats": g.stats, "most": most, "size": grammar_size(g)})


def within(x: dict) -> tuple[int, bool, bool, bool, bool, bool]:
    """The same from counts of nodes, rank, phases, the rules' highest rank and size."""
    n, nodes = x["nodes"], [s["nodes"] for s in x["stats"]]
    phases = len(nodes) <= math.log(max(n, 2), 4 / 3) + 1
    return n, all(b / a < 0.75 for a, b in zip(nodes, nodes[1:])), sum(nodes) <= 4 * n, phases, x["most"] <= x["rank"], x["size"] <= 2 * n - 1


def planted_size(kind: str, k: int) -> int:
    """Non-parameter nodes of a small grammar for a family of synthetic trees: an upper bound of the smallest one's size."""
    if kind == "doubling":  # k doubled letters over a leaf: (ab) ** 2 ** (k - 1)
        return 2 * k + 2
    if kind == "fibonacci":  # each of k rules joins the two before it
        return 2 * k + 2
    if kind == "power":
        return 2 * int(math.log2(k)) + (bin(k).count("1") if bin(k).count("1") > 1 else 0) + 2
    if kind == "comb":  # one inner node with its leaf as a unary rule, then a power of it
        return 2 + planted_size("power", k)
    raise ValueError(kind)


def planted_nodes(spark, kind: str, k: int) -> DataFrame:
    from canopy.sources import relational as S

    if kind == "doubling":
        return S.family(spark, "ab", 1 << (k - 1))
    if kind == "fibonacci":
        return S.family(spark, "fibonacci", k)
    return S.family(spark, kind, k)


def planted_ratio(spark, kind: str, k: int) -> DataFrame:
    """Size of the engine's grammar for a planted family beside the planted one, and beside the proved bound without its constant."""
    from canopy.model import forest_of
    from canopy.operators.compressor import compress, grammar_size

    f = forest_of(planted_nodes(spark, kind, k))
    n, r = f.nodes.agg(F.count("*"), F.max("rank")).first()
    got, small = grammar_size(compress(f)), planted_size(kind, k)
    top = bound(max(r, 1), small, n)
    row = (kind, k, int(n), small, got, got / small, got / top)
    return spark.createDataFrame([row], "family string, k int, nodes long, planted long, size long, ratio double, fitted double")


def sequential_grammar(letters: list) -> dict[int, list]:
    """Rules of the online compressor that reads letters left to right, keeps every digram unique and every rule in use twice or more.

    Rule 0 derives the input; a body holds letters and ("rule", number).
    """
    rules: dict[int, list] = {0: []}
    made = 0

    def digrams() -> dict:
        seen: dict = {}
        for r, body in rules.items():
            i = 0
            while i + 1 < len(body):
                key = (body[i], body[i + 1])
                if key in seen and not (seen[key][0] == r and seen[key][1] == i - 1):
                    return {"at": seen[key], "again": (r, i), "key": key}
                seen.setdefault(key, (r, i))
                i += 1
        return {}

    for x in letters:
        rules[0].append(x)
        while found := digrams():
            (r, i), (q, j), key = found["at"], found["again"], found["key"]
            whole = next((n for n, body in rules.items() if n and tuple(body) == key), None)
            if whole is None:
                made += 1
                whole = made
                rules[whole] = list(key)
            for n, body in rules.items():
                if n != whole:
                    out, at = [], 0
                    while at < len(body):
                        if tuple(body[at : at + 2]) == key:
                            out.append(("rule", whole))
                            at += 2
                        else:
                            out.append(body[at])
                            at += 1
                    body[:] = out
            used: dict[int, int] = {}
            for body in rules.values():
                for y in body:
                    if isinstance(y, tuple) and y[0] == "rule":
                        used[y[1]] = used.get(y[1], 0) + 1
            for n in [n for n in rules if n and used.get(n, 0) < 2]:
                inside = rules.pop(n)
                for body in rules.values():
                    for at, y in enumerate(body):
                        if y == ("rule", n):
                            body[at : at + 1] = inside
                            break
    return rules


def sequential_sizes(chains: DataFrame, key: str, letters: str) -> DataFrame:
    """(key, size): symbols of the online compressor's rules for each chain; a chain is one task's work."""

    def run(batches):
        for b in batches:
            sizes = [sum(map(len, sequential_grammar(x or []).values())) for x in b.column("x").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("key"), pa.array(sizes, pa.int64())], ["key", "size"])

    return chains.select(F.col(key).cast("long").alias("key"), F.col(letters).alias("x")).mapInArrow(run, "key long, size long")


def stored_bytes(tables: list[DataFrame]) -> int:
    """Bytes of tables written as Parquet with ZSTD."""
    import uuid

    from canopy.model import scratch

    total = 0
    for df in tables:
        spark = df.sparkSession
        path = f"{scratch(spark)}/canopy-bytes/{uuid.uuid4().hex}"
        df.write.option("compression", "zstd").parquet(path)
        folder = spark._jvm.org.apache.hadoop.fs.Path(path)
        fs = folder.getFileSystem(spark._jsc.hadoopConfiguration())
        total += fs.getContentSummary(folder).getLength()
        fs.delete(folder, True)
    return int(total)


def weight_conserved(g: Grammar) -> DataFrame:
    """Trees whose start letter doesn't weigh what the tree has nodes; none if all is well."""
    return g.starts.join(g.symbols.select("sym", "weight"), "sym").where("weight <> n").select("tree_id", "n", "weight")


def label_counts(g: Grammar) -> DataFrame:
    """(name, total) of input labels in the derived forest, from the rules alone: multiplicities pushed from the starts down the rules."""
    names = g.symbols.where("kind = 'input'").select("sym", "name")
    return occurrences(g).join(names, "sym").groupBy("name").agg(F.sum("times").cast("long").alias("total"))


def violations(g: Grammar) -> DataFrame:
    """What breaks a straight-line grammar: letters without rule or input kind, repeated rules, cycles by weight, unused rules."""
    part = g.rules.select("sym", "weight", F.explode("rhs").alias("x")).select("sym", "weight", F.col("x.sym").alias("part"))
    known = g.symbols.select(F.col("sym").alias("part"), F.col("kind"), F.col("weight").alias("pw"))
    used = part.select("part").union(g.starts.select("sym")).union(g.residual.select("sym")).distinct()
    return (
        part.join(known, "part", "left").where("kind is null").select("sym", F.lit("part without rule").alias("what"))
        .union(part.join(known, "part").where("pw >= weight").select("sym", F.lit("part not lighter").alias("what")))
        .union(g.rules.groupBy("sym").count().where("count > 1").select("sym", F.lit("two rules").alias("what")))
        .union(g.rules.join(used, F.col("sym") == F.col("part"), "left_anti").select("sym", F.lit("unused").alias("what")))
    )


def trivial_size(forest: Forest) -> int:
    """Every tree as its own start rule."""
    return forest.nodes.count()


def dag_size(forest: Forest) -> int:
    """Non-parameter nodes of the minimal DAG: each distinct inner subtree is a rule of its label and its children.

    Subtrees are named by hash from the leaves up: in packs of whole trees, or with a tree too large for a task, a level of height a round.
    """
    count, largest = forest.nodes.groupBy("tree_id").agg(F.count("*").alias("n")).agg(F.sum("n"), F.max("n")).first()
    if (largest or 0) <= scan.BLOCK:
        packed.prepare(forest.nodes.sparkSession)
        names = packed.subtrees(forest.nodes, count or 0)
        return int(names.agg(F.coalesce(F.sum(F.when(F.col("rank") > 0, F.col("rank") + 1)), F.lit(1))).first()[0])
    nodes = settle(forest.nodes.select("tree_id", "pre", "parent", "slot", "sym", "rank", F.when(F.col("rank") == 0, F.xxhash64(F.lit("dag"), "sym")).alias("name")))
    while True:
        kids = nodes.where("parent is not null").groupBy("tree_id", "parent").agg(F.array_sort(F.collect_list(F.struct("slot", "name"))).alias("kids")).withColumnRenamed("parent", "pre")
        ready = F.col("name").isNull() & (F.size(F.filter("kids", lambda k: k["name"].isNotNull())) == F.col("rank"))
        after = nodes.join(kids, ["tree_id", "pre"], "left").withColumn("name", F.when(ready, F.xxhash64(F.lit("dag"), "sym", "kids")).otherwise(F.col("name"))).drop("kids")
        nodes = settle(after)
        if not nodes.where("name is null").take(1):
            break
    return int(nodes.select("name", "rank").distinct().agg(F.coalesce(F.sum(F.when(F.col("rank") > 0, F.col("rank") + 1)), F.lit(1))).first()[0])


def digram_size(forest: Forest, max_rank: int = 8) -> int:
    """Digram replacement: common (parent, slot, child) of rank at most max_rank become letters, until none occurs twice.

    A round replaces every digram that is the commonest of all that share a letter with it; these share no letter, so their
    occurrences are disjoint. Occurrences of one digram that overlap (equal letters in a chain) are taken from the top.
    Once the nodes that are left fit a task, it makes all further rounds.
    """
    nodes = settle(forest.nodes)
    made = 0
    while True:
        if (count := nodes.count()) <= digrams.ONE_TASK:
            packed.prepare(nodes.sparkSession)
            more, left = digrams.replaced(nodes, max_rank, count)
            return 2 * (made + more) + left
        up = nodes.select("tree_id", F.col("pre").alias("parent"), F.col("sym").alias("a"), F.col("rank").alias("ra"))
        arcs = nodes.where("parent is not null").join(up, ["tree_id", "parent"])
        found = settle(arcs.where(F.col("ra") + F.col("rank") - 1 <= max_rank).groupBy("a", "slot", "sym").agg(F.count("*").alias("n"), F.first("rank").alias("rb")).where("n > 1"))
        letters = F.array_distinct(F.array("a", "sym"))
        best = found.select(F.explode(letters).alias("x"), F.struct((-F.col("n")).alias("n"), "a", "slot", "sym", "rb").alias("key")).groupBy("x").agg(F.min("key").alias("key"))
        top = settle(best.groupBy("key").agg(F.count("*").alias("m")).select("key.*", "m").where(F.col("m") == F.size(letters)).select("a", "slot", "sym", F.col("rb").alias("b_rank"), F.xxhash64(F.lit("digram"), "a", "slot", "sym").alias("new")))
        if not (more := top.count()):
            break
        made += more
        mine = settle(arcs.join(top, ["a", "slot", "sym"]).select("tree_id", F.col("pre").alias("low"), F.col("parent").alias("top"), F.col("slot").alias("i"), F.col("b_rank").alias("rb"), "new", (F.col("a") == F.col("sym")).alias("same")))
        links = mine.where("same").select("tree_id", "top", "low")
        if links.take(1):  # along a path of equal letters every second arc, counted from the top
            head = links.join(links.select("tree_id", F.col("low").alias("top")), ["tree_id", "top"], "left_anti")
            ladder = settle(head.select("tree_id", "top", "low", F.lit(0).alias("k")))
            chosen = ladder
            while True:
                ladder = settle(ladder.select("tree_id", F.col("low").alias("top"), "k").join(links, ["tree_id", "top"]).select("tree_id", "top", "low", (F.col("k") + 1).alias("k")))
                if not ladder.take(1):
                    break
                chosen = chosen.union(ladder)
            mine = settle(mine.where("not same").union(mine.where("same").join(chosen.where("k % 2 = 0").select("tree_id", "low"), ["tree_id", "low"], "left_semi").select(mine.columns)))
        gone = mine.select("tree_id", F.col("low").alias("pre"))
        hit = mine.select("tree_id", F.col("top").alias("pre"), "new", F.col("rb").alias("hit_rank"))
        child = mine.select("tree_id", F.col("low").alias("parent"), F.col("top").alias("new_parent"), F.col("i").alias("at"))
        sibling = mine.select("tree_id", F.col("top").alias("parent"), "i", "rb")
        out = nodes.join(gone, ["tree_id", "pre"], "left_anti").join(hit, ["tree_id", "pre"], "left").join(child, ["tree_id", "parent"], "left").join(sibling, ["tree_id", "parent"], "left")
        slot = F.when(F.col("new_parent").isNotNull(), F.col("slot") + F.col("at") - 1).when(F.col("slot") > F.col("i"), F.col("slot") + F.col("rb") - 1).otherwise(F.col("slot"))
        rank = F.when(F.col("new").isNotNull(), F.col("rank") + F.col("hit_rank") - 1).otherwise(F.col("rank"))
        after = settle(out.select("tree_id", "pre", F.coalesce("new_parent", "parent").alias("parent"), slot.cast("int").alias("slot"), F.coalesce("new", "sym").alias("sym"), rank.cast("int").alias("rank")))
        unsettle(nodes)
        nodes = after
    return 2 * made + nodes.count()


def bisection_size(texts: DataFrame, key: str, text: str) -> int:
    """Bisection grammar of strings: a string of n splits after the largest power of two below n; equal parts are one rule of size 2, shared by all strings."""
    # From the longest down, a class of lengths (half, 2 half] at a time: only longer strings make parts of it, so each part is met in one class alone.
    texts = texts.select(F.col(text).alias("s")).where(F.length("s") > 1)
    longest = texts.agg(F.max(F.length("s"))).first()[0] or 1
    rules, open_, above, even = 0, [texts], None, None
    for k in reversed(range((longest - 1).bit_length())):
        half = 1 << k
        due = reduce(DataFrame.union, [x.where((F.length("s") > half) & (F.length("s") <= 2 * half)) for x in open_] + ([even] if even is not None else []))
        due = settle(due.distinct())
        if above is not None:
            unsettle(above)
        rules += 2 * due.count()
        even = due.select(F.explode(F.array(F.substring("s", 1, half), F.substring("s", half + 1, half))).alias("s")).where(F.length("s") == half)
        open_.append(settle(due.where((F.length("s") < 2 * half) & (F.length("s") > half + 1)).select(F.substring("s", half + 1, half).alias("s"))))
        above = due
    for x in open_[1:] + ([above] if above is not None else []):
        unsettle(x)
    return rules


def phrase_size(texts: DataFrame, key: str, text: str) -> DataFrame:
    """(key, phrases): dictionary phrases of each string, the longest known one and a letter each time; two grammar symbols a phrase."""

    def run(batches):
        for b in batches:
            out = []
            for s in b.column("s").to_pylist():
                known: dict[tuple[int, str], int] = {}
                at = n = 0
                for ch in s or "":
                    if (to := known.get((at, ch))) is None:
                        n += 1
                        known[at, ch] = n
                        at = 0
                    else:
                        at = to
                out.append(n + (at > 0))
            yield pa.RecordBatch.from_arrays([b.column("key"), pa.array(out, pa.int64())], ["key", "phrases"])

    return texts.select(F.col(key).cast("long").alias("key"), F.col(text).alias("s")).mapInArrow(run, "key long, phrases long")


def count_factors(s: str) -> int:
    """Factors of a greedy left-to-right parse: each the longest string that also begins earlier, overlaps allowed, or one new letter.

    Walks the automaton of all substrings, whose states know where their strings end first; linear in the string.
    """
    go, link, long, ends = [{}], [-1], [0], [-1]

    def state(moves: dict, length: int, end: int) -> int:
        go.append(moves)
        link.append(0)
        long.append(length)
        ends.append(end)
        return len(go) - 1

    last = 0
    for i, ch in enumerate(s):
        new, p = state({}, long[last] + 1, i), last
        while p >= 0 and ch not in go[p]:
            go[p][ch] = new
            p = link[p]
        if p >= 0:
            q = go[p][ch]
            if long[q] > long[p] + 1:
                twin = state(dict(go[q]), long[p] + 1, ends[q])
                link[twin] = link[q]
                link[q] = twin
                while p >= 0 and go[p].get(ch) == q:
                    go[p][ch] = twin
                    p = link[p]
                q = twin
            link[new] = q
        last = new
    factors = i = 0
    while i < len(s):
        j, at = i, 0
        while j < len(s) and ends[to := go[at][s[j]]] < j:
            at, j = to, j + 1
        i = max(j, i + 1)
        factors += 1
    return factors


def factor_counts(texts: DataFrame, key: str, text: str) -> DataFrame:
    """(key, factors): a floor for grammars of strings, no grammar has fewer symbols than its string has such factors. A task holds one string's automaton."""

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column("key"), pa.array([count_factors(s or "") for s in b.column("s").to_pylist()], pa.int64())], ["key", "factors"])

    return texts.select(F.col(key).cast("long").alias("key"), F.col(text).alias("s")).mapInArrow(run, "key long, factors long")
