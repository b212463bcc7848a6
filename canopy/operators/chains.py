"""Recompression of grammars whose nonterminals derive chains, without expanding them.

A rule is a row (nt, body): body is an array of (sym, n, var), a letter n times or a nonterminal. Letters get the
ids that the tree engine gives them on the derived chains, so both ways can be compared letter by letter. Work goes level
by level of the nonterminal graph: a level's rules are rewritten side by side, and a balanced grammar has few levels.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.model import letter, settle
from canopy.operators import chain_packs, packed
from canopy.operators import pairs as P
from canopy.sources import relational as S

ITEM = "array<struct<sym:bigint,n:bigint,var:boolean>>"
KEYS = "sym long, kind string, a long, b long"


@dataclass
class ChainGrammar:
    """rules(nt, body), starts(tree_id, nt), names(sym, name) of input letters. No rule uses a start."""

    rules: DataFrame
    starts: DataFrame
    names: DataFrame


@dataclass
class Recompressed:
    """keys(sym, kind, a, b): run letters (base, length) and pair letters; starts(tree_id, sym): null for an empty chain; one dict of counts a phase.

    by_pack: the rules (label, sym, kind, rhs) and starts (label, tree_id, sym) of each pack, where packs made the letters.
    """

    keys: DataFrame
    starts: DataFrame
    stats: list[dict] = field(default_factory=list)
    by_pack: tuple[DataFrame, DataFrame] | None = None


def item(sym, n=1, var=False) -> "F.Column":
    return F.struct(F.col(sym).alias("sym") if isinstance(sym, str) else sym.alias("sym"), (F.lit(n) if isinstance(n, int) else n).cast("long").alias("n"), F.lit(var).alias("var"))


def unary(name) -> "F.Column":
    """The id of a unary input letter."""
    return letter(F.lit("input"), name, F.lit(1))


def bisection_grammar(texts: DataFrame, key: str, text: str) -> ChainGrammar:
    """Every distinct string of two and more letters is a rule of its two parts, cut after the largest power of two below its length.

    Each distinct text has a start above its rule; null and empty texts derive nothing. A text's depth is the logarithm of its length.
    """
    held = texts.select(F.col(key).cast("long").alias("tree_id"), F.coalesce(F.col(text), F.lit("")).alias("s"))
    nt = lambda s: F.xxhash64(F.lit("bisection"), s)
    side = lambda s: F.struct(F.when(F.length(s) > 1, nt(s)).otherwise(unary(s)).alias("sym"), F.lit(1).cast("long").alias("n"), (F.length(s) > 1).alias("var"))
    parts = settle(held.select("s").distinct())
    short = parts.where(F.length("s") < 2)
    rules = [short.select(nt(F.col("s")).alias("nt"), F.when(F.length("s") == 1, F.array(item(unary(F.col("s"))))).otherwise(F.array().cast(ITEM)).alias("body"))]
    seen, letters = parts, []
    while True:
        letters.append(parts.where(F.length("s") == 1))
        long = parts.where(F.length("s") > 1)
        if not long.take(1):
            break
        half = F.call_function("shiftleft", F.lit(1), F.floor(F.log2(F.length("s") - F.lit(0.5))).cast("int"))
        cut = settle(long.withColumn("x", F.substring("s", F.lit(1), half)).withColumn("y", F.substring("s", half + 1, F.length("s"))))
        rules.append(cut.select(nt(F.col("s")).alias("nt"), F.array(side(F.col("x")), side(F.col("y"))).alias("body")))
        parts = settle(cut.select(F.explode(F.array("x", "y")).alias("s")).distinct().join(seen, "s", "left_anti"))
        seen = settle(seen.unionByName(parts))
    top = held.select("s").distinct().select(F.xxhash64(F.lit("start"), "s").alias("nt"), F.array(F.struct(nt(F.col("s")).alias("sym"), F.lit(1).cast("long").alias("n"), F.lit(True).alias("var"))).alias("body"))
    rules.append(top)
    names = reduce(DataFrame.unionByName, letters).distinct().select(unary(F.col("s")).alias("sym"), F.col("s").alias("name"))
    return ChainGrammar(settle(reduce(DataFrame.unionByName, rules)), settle(held.select("tree_id", F.xxhash64(F.lit("start"), "s").alias("nt"))), settle(names))


def items(rules: DataFrame) -> DataFrame:
    return rules.select("nt", F.posexplode("body").alias("seq", "x")).select("nt", "seq", "x.sym", "x.n", "x.var")


def rules_size(rules: DataFrame) -> int:
    """Symbols of all right-hand sides, a counted run as one."""
    return int(rules.agg(F.coalesce(F.sum(F.size("body")), F.lit(0))).first()[0])


def violations(g: ChainGrammar) -> DataFrame:
    """(nt, what): nonterminals without or with two rules, unused ones, and those on a cycle."""
    used = items(g.rules).where("var").select(F.col("sym").alias("nt")).union(g.starts.select("nt")).distinct()
    ordered = levels(g.rules)
    return (
        used.join(g.rules, "nt", "left_anti").select("nt", F.lit("no rule").alias("what"))
        .union(g.rules.groupBy("nt").count().where("count > 1").select("nt", F.lit("two rules").alias("what")))
        .union(g.rules.join(used, "nt", "left_anti").select("nt", F.lit("unused").alias("what")))
        .union(g.rules.join(ordered, "nt", "left_anti").select("nt", F.lit("cycle").alias("what")))
        .union(items(g.rules).where("var").select(F.col("sym").alias("nt")).distinct().join(g.starts, "nt", "left_semi").select("nt", F.lit("start inside a rule").alias("what")))
    )


def levels(rules: DataFrame) -> DataFrame:
    """(nt, level): 0 without nonterminals in the body, else one above the highest in it. Nonterminals on or above a cycle or above a missing rule have none."""
    arcs = settle(items(rules).where("var").select("nt", "sym").distinct())
    done = settle(rules.join(arcs, "nt", "left_anti").select("nt", F.lit(0).alias("level")))
    k = 0
    while True:
        k += 1
        open_ = arcs.join(done.select("nt"), "nt", "left_anti")
        ready = open_.join(done.select(F.col("nt").alias("sym"), F.lit(True).alias("known")), "sym", "left").groupBy("nt").agg(F.every(F.coalesce("known", F.lit(False))).alias("all")).where("all")
        new = settle(ready.select("nt", F.lit(k).alias("level")))
        if not new.take(1):
            return done
        done = settle(done.unionByName(new))


def multiplicities(g: ChainGrammar) -> DataFrame:
    """(nt, times): how often each nonterminal stands in all derivations, pushed down from the starts."""
    arcs = settle(items(g.rules).where("var").groupBy("nt", "sym").agg(F.sum("n").alias("by")))
    use = settle(g.starts.groupBy("nt").agg(F.count("*").cast("decimal(38,0)").alias("times")))
    rounds = [use]
    while True:
        use = settle(use.join(arcs, "nt").groupBy(F.col("sym").alias("nt")).agg(F.sum(F.col("times") * F.col("by")).cast("decimal(38,0)").alias("times")))
        if not use.take(1):
            return settle(reduce(DataFrame.unionByName, rounds).groupBy("nt").agg(F.sum("times").cast("decimal(38,0)").alias("times")))
        rounds.append(use)


def merged(body) -> "F.Column":
    """Neighbouring equal letters as one item with the sum of their counts."""
    last = lambda s: F.try_element_at(s, F.lit(-1))
    joined = lambda s, x: F.concat(F.slice(s, 1, F.size(s) - 1), F.array(F.struct(x["sym"].alias("sym"), (last(s)["n"] + x["n"]).alias("n"), x["var"].alias("var"))))
    step = lambda s, x: F.when((F.size(s) > 0) & ~x["var"] & ~F.coalesce(last(s)["var"], F.lit(True)) & (last(s)["sym"] == x["sym"]), joined(s, x)).otherwise(F.concat(s, F.array(x)))
    return F.aggregate(body, F.array().cast(ITEM), step)


def popped(g: ChainGrammar, how: str, sides: DataFrame | None = None):
    """(grammar without crossing runs or pairs, letters moved, occurrences of nonterminals in rules).

    how "runs": a rule gives away its first and its last run. how "pairs": it gives away a first letter of side D and a last of side U.
    A rule that becomes empty vanishes, one of a single letter is put in place. Starts give nothing away.
    """
    order = settle(g.rules.join(levels(g.rules), "nt").join(g.starts.select("nt").distinct().withColumn("is_start", F.lit(True)), "nt", "left").withColumn("is_start", F.coalesce("is_start", F.lit(False))))
    top = order.agg(F.max("level")).first()[0]
    occurrences = items(g.rules).where("var").count()
    out, moved = None, 0
    empty = F.array().cast(ITEM)
    for k in range((top if top is not None else -1) + 1):
        now = order.where(F.col("level") == k)
        one = now.select("nt", "is_start", F.posexplode_outer("body").alias("seq", "x"))
        if out is None:
            put = one.withColumn("parts", F.when(F.col("x").isNull(), empty).otherwise(F.array("x")))
        else:
            below = out.select(F.col("nt").alias("ref"), "left", "body", "right")
            kept = F.when(F.size("body") > 0, F.array(F.col("x"))).otherwise(empty)
            put = one.join(below, (F.col("x.sym") == F.col("ref")) & F.col("x.var"), "left").withColumn("parts", F.when(F.col("x").isNull(), empty).when(F.col("ref").isNull(), F.array("x")).otherwise(F.concat("left", kept, "right")))
        whole = put.groupBy("nt", "is_start").agg(F.array_sort(F.collect_list(F.struct("seq", "parts"))).alias("all")).select("nt", "is_start", merged(F.flatten(F.transform("all", lambda x: x["parts"]))).alias("body"))
        if how == "runs":
            first = ~F.col("is_start") & (F.size("body") > 0)
            last = ~F.col("is_start") & (F.size("body") > 1)
        else:
            for end, at in (("first", 1), ("last", -1)):
                whole = whole.withColumn(f"{end}_sym", F.when(~F.try_element_at("body", F.lit(at))["var"], F.try_element_at("body", F.lit(at))["sym"]))
                whole = whole.join(sides.select(F.col("sym").alias(f"{end}_sym"), F.col("side").alias(f"{end}_side")), f"{end}_sym", "left")
            first = ~F.col("is_start") & F.coalesce(F.col("first_side") == P.DOWN, F.lit(False))
            last = ~F.col("is_start") & F.coalesce(F.col("last_side") == P.UP, F.lit(False))
        cut = whole.select("nt", "is_start", "body", first.alias("f"), last.alias("l")).select(
            "nt", "is_start", F.when(F.col("f"), F.slice("body", 1, 1)).otherwise(empty).alias("left"),
            F.when(F.col("l"), F.slice("body", F.size("body"), F.lit(1))).otherwise(empty).alias("right"),
            F.slice("body", F.when(F.col("f"), 2).otherwise(1), F.greatest(F.lit(0), F.size("body") - F.col("f").cast("int") - F.col("l").cast("int"))).alias("body"),
        )
        single = ~F.col("is_start") & (F.size("body") == 1) & ~F.try_element_at("body", F.lit(1))["var"]
        cut = cut.withColumn("single", F.coalesce(single, F.lit(False)))
        cut = settle(cut.select("nt", F.when(F.col("single"), F.concat("left", "body")).otherwise(F.col("left")).alias("left"), "right", F.when(F.col("single"), empty).otherwise(F.col("body")).alias("body"), "is_start", (F.size("left") + F.size("right")).alias("gone")))
        out = cut if out is None else settle(out.unionByName(cut))
    if out is None:
        return g, 0, 0
    times = items(g.rules).where("var").groupBy(F.col("sym").alias("nt")).agg(F.count("*").alias("m"))
    moved = int(out.join(times, "nt").agg(F.coalesce(F.sum(F.col("gone") * F.col("m")), F.lit(0))).first()[0])
    rules = settle(out.where((F.size("body") > 0) | F.col("is_start")).select("nt", "body"))
    return ChainGrammar(rules, g.starts, g.names), moved, occurrences


def compress_runs(g: ChainGrammar):
    """(grammar, new letters): after popping, every counted run of two and more is one letter."""
    fresh = lambda x: letter(F.lit("run"), x["sym"], x["n"])
    made = lambda x: ~x["var"] & (x["n"] > 1)
    keys = items(g.rules).where("not var and n > 1").select("sym", "n").distinct().select(letter(F.lit("run"), F.col("sym"), F.col("n")).alias("sym"), F.lit("run").alias("kind"), F.col("sym").alias("a"), F.col("n").alias("b"))
    body = F.transform("body", lambda x: F.struct(F.when(made(x), fresh(x)).otherwise(x["sym"]).alias("sym"), F.when(made(x), F.lit(1).cast("long")).otherwise(x["n"]).alias("n"), x["var"].alias("var")))
    return ChainGrammar(settle(g.rules.select("nt", body.alias("body"))), g.starts, g.names), settle(keys)


def edge_letters(g: ChainGrammar) -> DataFrame:
    """(nt, first, last): the letters at the two ends of what a nonterminal derives, found by doubling paths of first and of last items."""

    def resolve(at: int, name: str) -> DataFrame:
        have = settle(g.rules.where(F.size("body") > 0).select("nt", F.element_at("body", at).alias("x")).select("nt", "x.sym", "x.var"))
        while have.where("var").take(1):
            to = have.select(F.col("nt").alias("sym"), F.col("sym").alias("to"), F.col("var").alias("still"), F.lit(True).alias("var"))
            have = settle(have.join(to, ["sym", "var"], "left").select("nt", F.coalesce("to", "sym").alias("sym"), F.coalesce("still", "var").alias("var")))
        return have.select("nt", F.col("sym").alias(name))

    return resolve(1, "first").join(resolve(-1, "last"), "nt")


def neighbours(g: ChainGrammar) -> DataFrame:
    """(nt, a, b, crossing): for neighbouring items of a rule the last letter of the upper and the first of the lower."""
    edges = settle(edge_letters(g))
    two = g.rules.where(F.size("body") > 1).select("nt", F.explode(F.transform(F.sequence(F.lit(1), F.size("body") - 1), lambda i: F.struct(F.element_at("body", i.cast("int")).alias("x"), F.element_at("body", (i + 1).cast("int")).alias("y")))).alias("p")).select("nt", "p.x", "p.y")
    up = edges.select(F.col("nt").alias("ux"), "last")
    down = edges.select(F.col("nt").alias("dy"), "first")
    got = two.join(up, (F.col("x.sym") == F.col("ux")) & F.col("x.var"), "left").join(down, (F.col("y.sym") == F.col("dy")) & F.col("y.var"), "left")
    return got.select("nt", F.coalesce("last", "x.sym").alias("a"), F.coalesce("first", "y.sym").alias("b"), (F.col("x.var") | F.col("y.var")).alias("crossing"))


def pair_graph(g: ChainGrammar, counts: str = "tree") -> DataFrame:
    """(a, b, occ) of unequal neighbours: in the derived chains (counts "tree") or in the rules (counts "grammar")."""
    near = neighbours(g).where("a <> b")
    if counts == "tree":
        return near.join(multiplicities(g), "nt").groupBy("a", "b").agg(F.sum("times").cast("long").alias("occ"))
    return near.groupBy("a", "b").agg(F.count("*").alias("occ"))


def crossing_pairs(g: ChainGrammar, sides: DataFrame) -> DataFrame:
    """(a, b, occ): pairs of an upper and a lower letter that stand across a nonterminal's border; none after popping."""
    a, b = sides.select(F.col("sym").alias("a"), F.col("side").alias("sa")), sides.select(F.col("sym").alias("b"), F.col("side").alias("sb"))
    return neighbours(g).where("crossing and a <> b").join(a, "a").join(b, "b").where((F.col("sa") == P.UP) & (F.col("sb") == P.DOWN)).groupBy("a", "b").agg(F.count("*").alias("occ"))


def compress_pairs(g: ChainGrammar, sides: DataFrame):
    """(grammar, new letters): after popping, an upper letter right above a lower one merges with it."""
    one = g.rules.select("nt", F.posexplode_outer("body").alias("seq", "x"))
    held = one.withColumn("sym", F.col("x.sym")).join(sides, "sym", "left").withColumn("side", F.when(~F.col("x.var"), F.col("side"))).groupBy("nt").agg(F.array_sort(F.collect_list(F.struct("seq", "x", "side"))).alias("b"))
    at = lambda i: F.try_element_at("b", i.cast("int"))
    hit = lambda i: F.coalesce((at(i)["side"] == P.UP) & (at(i + 1)["side"] == P.DOWN), F.lit(False))
    low = lambda i: F.when(i > 1, F.coalesce((F.try_element_at("b", F.greatest(i - 1, F.lit(1)).cast("int"))["side"] == P.UP) & (at(i)["side"] == P.DOWN), F.lit(False))).otherwise(False)
    marked = held.select("nt", F.transform("b", lambda x, j: F.struct(x["x"].alias("x"), hit(j + 1).alias("hit"), low(j + 1).alias("low"), at(j + 2)["x"]["sym"].alias("below"))).alias("m"))
    marked = settle(marked)
    keys = marked.select(F.explode("m").alias("e")).where("e.hit").select(F.col("e.x.sym").alias("a"), F.col("e.below").alias("b")).distinct().select(letter(F.lit("pair"), F.col("a"), F.col("b")).alias("sym"), F.lit("pair").alias("kind"), "a", "b")
    body = F.transform(F.filter("m", lambda e: ~e["low"] & e["x"].isNotNull()), lambda e: F.struct(F.when(e["hit"], letter(F.lit("pair"), e["x"]["sym"], e["below"])).otherwise(e["x"]["sym"]).alias("sym"), e["x"]["n"].alias("n"), e["x"]["var"].alias("var")))
    return ChainGrammar(settle(marked.select("nt", body.alias("body"))), g.starts, g.names), settle(keys)


def recompress(g: ChainGrammar, partition: str = "auto", counts: str = "tree", max_phases: int = 200) -> Recompressed:
    """Phases of runs and pairs on the rules until every start is one letter.

    counts: the weights of the colouring, "tree", "grammar" or "alternate" (one phase each). With "tree" the letters are those
    of the tree engine. Each phase's stats hold the occurrences of nonterminals before popping and the letters moved, at most two for each.
    """
    keys, stats = [], []
    for phase in range(1, max_phases + 1):
        g, moved, occ = popped(g, "runs")
        g, runs = compress_runs(g)
        keys.append(runs)
        stat = {"phase": phase, "run_occurrences": occ, "run_moved": moved, "pair_occurrences": 0, "pair_moved": 0, "size": rules_size(g.rules)}
        stats.append(stat)
        weigh = counts if counts != "alternate" else ("tree", "grammar")[phase % 2 == 0]
        graph = settle(pair_graph(g, weigh))
        if not graph.take(1):
            break
        sides = settle(P.choose(graph, partition))
        g, stat["pair_moved"], stat["pair_occurrences"] = popped(g, "pairs", sides)
        g, pairs = compress_pairs(g, sides)
        keys.append(pairs)
        stat["size"] = rules_size(g.rules)
    ends = g.starts.join(g.rules, "nt").select("tree_id", F.try_element_at("body", F.lit(1))["sym"].alias("sym"))
    return Recompressed(settle(reduce(DataFrame.unionByName, keys).distinct()), settle(ends), stats)


def recompress_texts(texts: DataFrame, key: str, text: str, counts: str = "tree", max_phases: int = 200) -> tuple[Recompressed, DataFrame]:
    """The bisection grammar of texts, recompressed, and the names of its input letters: packs of texts at once, one write a phase.

    Letters and counts are those of recompress(bisection_grammar()), which takes texts too long for one task.
    """
    if (texts.agg(F.max(F.length(text))).first()[0] or 0) > chain_packs.LONGEST:
        g = bisection_grammar(texts, key, text)
        return recompress(g, "auto", counts, max_phases), g.names
    names = settle(texts.select(F.explode(F.array_distinct(S.string_parts(text, "char"))).alias("name")).distinct().select(unary(F.col("name")).alias("sym"), "name"))
    t, ends, stats = chain_packs.recompress(texts.sparkSession, S.letters_of(texts, key, text, "char"), counts, max_phases)
    rules = t.read(packed.RULE).select("label", "sym", "kind", "rhs")
    first, second = F.col("rhs")[0], F.try_element_at("rhs", F.lit(2))
    keys = rules.select("sym", "kind", first["sym"].alias("a"), F.when(F.col("kind") == "run", first["at"].cast("long")).otherwise(second["sym"]).alias("b"))
    return Recompressed(keys.distinct(), ends.select("tree_id", "sym"), stats, (rules, ends)), names


def unfold(r: Recompressed, names: DataFrame, max_rounds: int = 1000) -> DataFrame:
    """(tree_id, text): the chains that recompressed letters stand for. Each letter's text is built once, from the letters below it; of packs, a pack at a time."""
    if r.by_pack is not None:
        rules, starts = r.by_pack
        points = {x.sym: ord(x.name) for x in names.collect()}  # no more than there are characters
        empty = chain_packs.EMPTY
        return packed.texts_of(rules, starts.select("label", "tree_id", F.coalesce("sym", F.lit(empty)).alias("sym")), points | {empty: -1})
    known = settle(names.select("sym", "name"))
    left = r.keys
    for _ in range(max_rounds):
        a, b = known.select(F.col("sym").alias("a"), F.col("name").alias("na")), known.select(F.col("sym").alias("b"), F.col("name").alias("nb"))
        runs = left.where("kind = 'run'").join(a, "a").select("sym", F.expr("repeat(na, cast(b as int))").alias("name"))
        pairs = left.where("kind = 'pair'").join(a, "a").join(b, "b").select("sym", F.concat("na", "nb").alias("name"))
        new = settle(runs.unionByName(pairs))
        if not new.take(1):
            break
        known = settle(known.unionByName(new))
        left = settle(left.join(new, "sym", "left_anti"))
    return r.starts.join(known, "sym", "left").select("tree_id", F.coalesce("name", F.lit("")).alias("text"))
