"""Phases of runs, pairs and leaves until every tree is one letter, and the way back.

A node carries what its letter stands for: ``w``, the input nodes of its pattern, and for each parameter its number,
the pattern's nodes before it, and where the node that hangs there has its parent and its slot. So a new
letter's rule, weight and parameters come out of the rows that make it, without joining a dictionary, and
the way back needs nothing but rules: every part's place, parent and slot follow from numbers in them.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from canopy.model import Forest, Grammar, letter, settle, unsettle
from canopy.operators import leaves as L
from canopy.operators import packed
from canopy.operators import pairs as P
from canopy.operators import places
from canopy.operators import runs as R
from canopy.operators import scan

PARAMS = places.PARAMS
#: own: parameters of the rule's first part. weights: of the parts, in order (a run's base once).
RULE = f"sym long, phase int, kind string, rhs array<struct<sym:bigint,at:int>>, cost int, rank int, weight long, params {PARAMS}, own {PARAMS}, weights array<bigint>"
PART = "array<struct<sym:bigint,at:int>>"


@dataclass
class Config:
    """steps: which rewrites a phase makes. partition: auto, hashed, linear, random, greedy, exact. stop_size: trees of no more nodes are left as they are.

    scope: "forest" shares letters between trees, "tree" gives each tree its own, "joined" makes one tree of all under a balanced
    spine of binary letters. block: pre-order numbers of a block of a tree too large for one task; None finds out.
    """

    steps: tuple[str, ...] = ("runs", "pairs", "leaves")
    partition: str = "auto"
    ordered_leaves: bool = True
    stop_size: int = 1
    max_phases: int | None = None
    scope: str = "forest"
    block: int | None = None


def census(nodes: DataFrame, block: int | None = None) -> dict:
    """Nodes by rank and maximal unary chains."""
    row = chain_starts(nodes, block).agg(*counters()).first()
    return {k: int(v or 0) for k, v in row.asDict().items()}


def chain_starts(nodes: DataFrame, block: int | None) -> DataFrame:
    near = scan.beside(nodes, {"_br": F.col("rank")}, {}, block)
    return near.withColumn("first", (F.col("rank") == 1) & F.coalesce(F.col("_br") != 1, F.lit(True)))


def first_census(forest: Forest, block: int | None = None) -> DataFrame:
    """What the first phase of compress() counts, as one row, without making the phase."""
    block = block or block_for(forest.nodes.groupBy("tree_id").agg(F.count("*").alias("n")))
    counted = chain_starts(forest.nodes.where("not (parent is null and rank = 0)"), block).agg(*counters())
    return counted.select(*(F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in counted.columns))


def block_for(sizes: DataFrame) -> int | None:
    return scan.BLOCK if (sizes.agg(F.max("n")).first()[0] or 0) > scan.BLOCK else None


def counters() -> list[Column]:
    n = lambda c: F.sum(F.when(c, 1).otherwise(0))
    return [F.count(F.lit(1)).alias("nodes"), n(F.col("rank") == 0).alias("n0"), n(F.col("rank") == 1).alias("n1"), n(F.col("rank") > 1).alias("n2plus"), n(F.col("first")).alias("chains")]


def nothing(kind: str) -> Column:
    return F.lit(None).cast(kind)


def made_of(when: Column, kind: str, rhs: Column, cost: Column, params: Column, own: Column, weights: Column) -> Column:
    """What a rewritten row's new letter stands for, null for the others."""
    return F.when(when, F.struct(F.lit(kind).alias("kind"), rhs.cast(PART).alias("rhs"), cost.cast("int").alias("cost"), own.cast(PARAMS).alias("own"), weights.cast("array<bigint>").alias("weights"), params.cast(PARAMS).alias("params")))


def part(sym: Column, at: Column) -> Column:
    return F.struct(sym.alias("sym"), at.cast("int").alias("at"))


def param(id_: Column, off: Column, up: Column, at: Column) -> Column:
    return F.struct(id_.cast("int").alias("id"), off.cast("long").alias("off"), up.cast("long").alias("up"), at.cast("int").alias("at"))


NODE = ("tree_id", "pre", "parent", "slot", "sym", "rank", "w", "params")


def finished(out: DataFrame, made: Column, weight: Column) -> DataFrame:
    out = out.withColumn("_made", made).withColumn("_w", weight.cast("long"))
    hit = F.col("_made").isNotNull()
    return out.select(*NODE[:6], F.when(hit, F.col("_w")).otherwise(F.col("w")).alias("w"), F.when(hit, F.col("_made.params")).otherwise(F.col("params")).alias("params"), F.col("_made").dropFields("params").alias("made"))


def run_step(marked: DataFrame, block: int | None) -> DataFrame:
    """From rows marked by heads(), which can be counted on their way."""
    out = R.islands(marked, block)
    new = (F.col("rank") == 1) & (F.col("len") > 1)
    p, n = F.col("params")[0], F.col("len").cast("long")
    out = out.withColumn("base", F.col("sym")).withColumn("sym", F.when(new, letter(F.lit("run"), F.col("sym"), n)).otherwise(F.col("sym")))
    params = F.array(param(p["id"], n * p["off"], (n - 1) * p["off"] + p["up"], p["at"]))
    return finished(out, made_of(new, "run", F.array(part(F.col("base"), n)), n, params, F.col("params"), F.array("w")), n * F.col("w"))


def pair_step(nodes: DataFrame, up: Column, block: int | None) -> DataFrame:
    out = P.merge_pairs(nodes, up, block)
    p, q = F.col("params")[0], F.col("_l.params")[0]
    params = F.array(param(q["id"], p["off"] + q["off"], p["off"] + q["up"], q["at"]))
    rhs = F.array(part(F.col("_a"), F.lit(1)), part(F.col("low"), F.lit(2)))
    return finished(out, made_of(F.col("low").isNotNull(), "pair", rhs, F.lit(2), params, F.col("params"), F.array(F.col("w"), F.col("_l.w"))), F.col("w") + F.col("_l.w"))


def leaf_step(nodes: DataFrame, ordered: bool) -> DataFrame:
    """The leaves' weights move every later parameter, and every parent of a parameter that comes after them."""
    out = L.merge_leaves(nodes, ordered)
    hit = F.col("f").isNotNull()
    move = places.udfs().in_order if ordered else places.udfs().unordered
    params = move(F.when(hit, F.col("params")), F.when(hit, F.transform("leaves", lambda x: F.struct(x["slot"].alias("slot"), x["w"].alias("w")))))
    total = F.aggregate("leaves", F.lit(0).cast("long"), lambda s, x: s + x["w"])
    rhs = F.concat(F.array(part(F.col("f"), F.lit(0))), F.transform("leaves", lambda x: part(x["sym"], x["slot"])))
    weights = F.concat(F.array("w"), F.transform("leaves", lambda x: x["w"]))
    return finished(out.withColumn("_moved", params), made_of(hit, "leaf", rhs, F.size("leaves") + 1, F.col("_moved"), F.col("params"), weights), F.col("w") + total)


def rules_of(tables: list[DataFrame], phase: int) -> DataFrame:
    """One row for each new letter; ``clash`` is not zero where one id stands for different keys."""
    rows = reduce(DataFrame.unionByName, [t.where("made is not null").select("sym", "rank", "w", "params", "made") for t in tables])
    check = F.xxhash64(F.lit(77), "made.kind", "made.rhs")
    got = rows.withColumn("check", check).groupBy("sym").agg(F.first("made").alias("made"), F.first("rank").alias("rank"), F.first("w").alias("weight"), F.first("params").alias("params"), F.min("check").alias("c0"), F.max("check").alias("c1"))
    return got.select("sym", F.lit(phase).alias("phase"), "made.kind", "made.rhs", "made.cost", F.col("rank").cast("int").alias("rank"), "weight", "params", "made.own", "made.weights", (F.col("c0") != F.col("c1")).cast("int").alias("clash"))


def watched(df: DataFrame, *columns: Column) -> tuple[DataFrame, Observation]:
    """df that counts while it is written."""
    seen = Observation(f"canopy_{uuid.uuid4().hex}")
    return df.observe(seen, *columns), seen


def observed(seen: Observation, written: DataFrame) -> dict:
    """The counts, once the table is written; none if it is empty, for the plan of an empty table may count nothing."""
    return {k: int(v or 0) for k, v in seen.get.items()} if written.take(1) else {}


def joined_trees(forest: Forest) -> Forest:
    """One tree of all: their roots hang, by tree number, below a balanced spine of binary letters. A single tree stays as it is.

    Inner spine nodes are those of the balanced search tree over 1 .. m; node j has the trees' numbers in one range
    below it. Its pre-order number follows from the range and from the trees' sizes before it.
    """
    spark = forest.nodes.sparkSession
    sizes = [(int(r.tree_id), int(r.n)) for r in forest.nodes.groupBy("tree_id").agg(F.count("*").alias("n")).orderBy("tree_id").collect()]
    if len(sizes) < 2:
        return forest
    before = [0]
    for _, n in sizes:
        before.append(before[-1] + n)
    spine, hung = [], []
    todo = [(0, len(sizes), 0, None, None)]  # trees lo .. hi, spine nodes before, parent, slot
    while todo:
        lo, hi, above, parent, slot = todo.pop()
        pre = before[lo] + above
        if hi - lo == 1:
            hung.append((sizes[lo][0], pre, parent, slot))
            continue
        spine.append((0, pre, parent, slot))
        mid = (lo + hi) // 2
        todo += [(lo, mid, above + 1, pre, 1), (mid, hi, above + 1 + (mid - lo - 1), pre, 2)]
    cons = letter(F.lit("input"), F.lit("&"), F.lit(2))
    top = spark.createDataFrame(spine, "tree_id long, pre long, parent long, slot int").select("tree_id", "pre", "parent", "slot", cons.alias("sym"), F.lit(2).alias("rank"))
    where = spark.createDataFrame(hung, "tree_id long, base long, up long, hang int")
    moved = forest.nodes.join(where, "tree_id")
    moved = moved.select(F.lit(0).cast("long").alias("tree_id"), (F.col("pre") + F.col("base")).alias("pre"), F.when(F.col("parent").isNull(), F.col("up")).otherwise(F.col("parent") + F.col("base")).alias("parent"), F.coalesce("slot", "hang").alias("slot"), "sym", "rank")
    spine_letter = spark.range(1).select(cons.alias("sym"), F.lit("input").alias("kind"), F.lit(2).alias("rank"), F.lit("&").alias("name"))
    return Forest(top.unionByName(moved), forest.symbols.select("sym", "kind", "rank", "name").unionByName(spine_letter))


def per_tree(forest: Forest) -> Forest:
    """Letters of their own for every tree: no two trees share one."""
    own = lambda df: df.withColumn("sym", letter(F.lit("own"), F.col("tree_id"), F.col("sym")))
    used = forest.nodes.select("tree_id", "sym").distinct().join(forest.symbols.select("sym", "kind", "rank", "name"), "sym")
    return Forest(own(forest.nodes), own(used).drop("tree_id"))


def compress(forest: Forest, cfg: Config = Config()) -> Grammar:
    """The grammar of a forest.

    Empty forests have none; a single-node tree is its own start. The loop ends when all trees are single letters or no
    step removes a node (possible only without the leaf step). Trees of at most stop_size nodes leave the loop as residual.
    A phase is one write for each step and one for its rules; nodes are counted on the way. Where every tree fits a task and nothing
    unusual is asked for, the same phases run over packed trees, with one write a phase.
    """
    forest = {"forest": lambda f: f, "tree": per_tree, "joined": joined_trees}[cfg.scope](forest)
    spark = forest.nodes.sparkSession
    sizes = settle(forest.nodes.groupBy("tree_id").agg(F.count("*").alias("n")))
    block = cfg.block or block_for(sizes)
    if block is None and cfg.steps == Config.steps and cfg.partition in ("auto", "hashed") and cfg.ordered_leaves and cfg.stop_size == 1 and cfg.max_phases is None:
        packed.prepare(spark)
        count = sizes.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        return gathered(packed.phases(spark, packed.from_nodes(forest.nodes, int(count))), forest.symbols, sizes)
    first = F.when(F.col("rank") > 0, F.transform(F.sequence(F.lit(1), F.greatest(F.col("rank"), F.lit(1))), lambda i: param(i, F.lit(1), F.lit(0), i))).otherwise(F.array().cast(PARAMS))
    nodes = forest.nodes.withColumn("w", F.lit(1).cast("long")).withColumn("params", first).select(*NODE)
    rules, stats, starts, left, spent = [], [], [], [], []
    last, phase = -1, 0
    while True:
        phase += 1
        if cfg.max_phases is not None and phase > cfg.max_phases:
            left.append(nodes)
            break
        if cfg.stop_size > 1:
            nodes = settle(nodes)
            spent.append(nodes)
            done = nodes.groupBy("tree_id").agg(F.count("*").alias("m")).where(F.col("m") <= cfg.stop_size)
            left.append(nodes.join(done, "tree_id", "left_semi"))
            nodes = nodes.join(done, "tree_id", "left_anti")
        else:
            starts.append(nodes.where("parent is null and rank = 0").select("tree_id", "sym"))
            nodes = nodes.where("not (parent is null and rank = 0)")
        made, before = [], nodes
        if "runs" in cfg.steps:
            marked, seen = watched(R.heads(nodes, block), *counters())
            nodes = settle(run_step(marked, block))
            count = observed(seen, nodes)
            made.append(nodes)
        else:
            nodes = settle(nodes)
            count = census(nodes, block)
            spent.append(nodes)
        if not count.get("nodes") or count["nodes"] == last:
            left.append(before)
            break
        last = count["nodes"]
        if "pairs" in cfg.steps:
            plain = nodes.select(*NODE)
            graph = P.pair_graph(plain, block)
            if cfg.partition in ("auto", "hashed", "linear"):
                graph = settle(graph) if cfg.partition == "linear" else graph
                found = P.linear_colouring(graph) if cfg.partition == "linear" else P.hashed_colouring(graph)
                merged = pair_step(plain, found.up(F.col("sym")), block) if found else None
            else:
                graph = settle(graph)
                sides = P.choose(graph, cfg.partition) if graph.take(1) else None
                merged = pair_step(plain.join(sides, "sym", "left"), F.when(F.col("side") == P.UP, True).when(F.col("side") == P.DOWN, False), block) if sides is not None else None
            if merged is not None:
                nodes = settle(merged)
                made.append(nodes)
        if "leaves" in cfg.steps:
            nodes = settle(leaf_step(nodes.select(*NODE), cfg.ordered_leaves))
            made.append(nodes)
        fresh, seen = watched(rules_of(made, phase), F.count(F.lit(1)).alias("letters"), F.sum("clash").alias("clash"))
        fresh = settle(fresh)
        counted = observed(seen, fresh)
        if counted.get("clash"):
            raise ValueError("one letter id for two keys")
        rules.append(fresh.drop("clash"))
        for x in made[:-1]:
            unsettle(x)
        spent += made[-1:]
        stats.append({"phase": phase, **count, "letters": counted.get("letters", 0)})
        nodes = nodes.select(*NODE)
    every = rules_once(reduce(DataFrame.unionByName, rules) if rules else spark.createDataFrame([], RULE))
    residual = settle(reduce(DataFrame.unionByName, left).select(*NODE)) if left else spark.createDataFrame([], nodes.schema)
    roots = reduce(DataFrame.unionByName, starts) if starts else residual.limit(0).select("tree_id", "sym")
    started = settle(roots.join(sizes.hint("merge"), "tree_id").select("tree_id", "sym", "n"))
    for x in spent:
        unsettle(x)
    known = settle(forest.symbols.select("sym", "kind", F.col("rank").cast("int").alias("rank"), "name", F.lit(1).cast("long").alias("weight")).unionByName(every.select("sym", "kind", "rank", nothing("string").alias("name"), "weight")))
    runs = every.where("kind = 'run'").select("sym", F.col("rhs")[0]["sym"].alias("base"), F.col("rhs")[0]["at"].alias("len"))
    return Grammar(every, known, started, residual, runs, stats)


def measured(spark, forests: dict[str, Forest], runs: list[tuple[str, int]]) -> tuple[dict[tuple[str, int], dict], dict[str, DataFrame]]:
    """For each forest and stop size what compress() and grammar_size() would count, and the forests' nodes, written.

    Counts are nodes and rank of the forest, stats of the phases, the rules' highest rank and the grammar's size. All share one loop of
    phases over packs, each with letters and colourings of its own; a forest with a tree too large for one task is compressed by itself.
    """
    names = list(forests)
    every = settle(reduce(DataFrame.unionByName, [forests[w].nodes.withColumn("forest", F.lit(i)) for i, w in enumerate(names)]))
    nodes = {w: every.where(F.col("forest") == i).drop("forest") for i, w in enumerate(names)}
    trees = every.groupBy("forest", "tree_id").agg(F.count("*").alias("n"), F.max("rank").alias("r"))
    facts = {names[x.forest]: x for x in trees.groupBy("forest").agg(F.sum("n").alias("nodes"), F.max("n").alias("largest"), F.max("r").alias("rank")).collect()}
    out, begun = {}, []
    packed.prepare(spark)
    for i, (w, stop) in enumerate(runs):
        x = facts.get(w)
        held = out[w, stop] = {"nodes": int(x.nodes) if x else 0, "rank": int(x["rank"]) if x else 0, "stats": [], "most": 0, "size": 0}
        if x and x.largest > scan.BLOCK:
            g = compress(Forest(nodes[w], forests[w].symbols), Config(stop_size=stop))
            held |= {"stats": g.stats, "most": g.rules.agg(F.coalesce(F.max("rank"), F.lit(0))).first()[0], "size": grammar_size(g)}
        elif x:
            begun.append(packed.from_nodes(nodes[w], held["nodes"], packed.LEAN, i, stop))
    if begun:
        t = packed.phases(spark, reduce(DataFrame.unionByName, begun), packed.LEAN)
        check = F.xxhash64(F.lit(77), "kind", "rhs")
        once = t.read(packed.RULE).groupBy("label", "sym").agg(F.first("kind").alias("kind"), F.first(F.col("rhs")[0]).alias("part"), F.max("cost").alias("cost"), F.max("rank").alias("rank"), (F.min(check) != F.max(check)).alias("clash"))
        once = settle(once)
        lengths = once.where("kind = 'run'").select(F.struct("label", "part.sym").alias("base"), F.col("part.at").alias("len"))
        spelled = R.represent_runs(lengths).select(F.col("base.label").alias("label"), "cost")
        left = t.read(packed.START).where("weight is not null").select("label", F.col("weight").alias("cost"))
        for x in once.groupBy("label").agg(F.max("rank").alias("most"), F.max("clash").alias("clash")).collect():
            if x.clash:
                raise ValueError("one letter id for two keys")
            out[runs[x.label]]["most"] = x.most
        for x in once.where("kind <> 'run'").select("label", F.col("cost").cast("long").alias("cost")).unionByName(spelled.withColumn("cost", F.col("cost").cast("long"))).unionByName(left).groupBy("label").agg(F.sum("cost").alias("size")).collect():
            out[runs[x.label]]["size"] = int(x["size"])
        for i, stats in t.by_group.items():
            out[runs[i]]["stats"] = stats
    return out, nodes


def gathered(t: packed.Tables, symbols: DataFrame, sizes: DataFrame) -> Grammar:
    """The grammar that the packs' phases wrote, each letter's rule once."""
    spark = sizes.sparkSession
    raw = t.read(packed.RULE).withColumn("phase", F.when(F.col("kind") == "run", F.col("phase")).otherwise(F.col("phase") - 1))
    fresh = {r.phase: r.n for r in raw.select("phase", "sym").distinct().groupBy("phase").agg(F.count("*").alias("n")).collect()}
    check = F.xxhash64(F.lit(77), "kind", "rhs")
    once = raw.withColumn("check", check).groupBy("sym").agg(F.min("phase").alias("phase"), *(F.first(c).alias(c) for c in ("kind", "rhs", "cost", "rank", "weight", "params", "own", "weights")), (F.min("check") != F.max("check")).cast("int").alias("clash"))
    once, seen = watched(once, F.count(F.lit(1)).alias("letters"), F.sum("clash").alias("clash"))
    every = settle(once)
    if observed(seen, every).get("clash"):
        raise ValueError("one letter id for two keys")
    every = every.drop("clash")
    started = settle(t.read(packed.START).select("tree_id", "sym").join(sizes.hint("merge"), "tree_id").select("tree_id", "sym", "n"))
    residual = spark.createDataFrame([], f"tree_id long, pre long, parent long, slot int, sym long, rank int, w long, params {PARAMS}")
    known = settle(symbols.select("sym", "kind", F.col("rank").cast("int").alias("rank"), "name", F.lit(1).cast("long").alias("weight")).unionByName(every.select("sym", "kind", "rank", nothing("string").alias("name"), "weight")))
    runs = every.where("kind = 'run'").select("sym", F.col("rhs")[0]["sym"].alias("base"), F.col("rhs")[0]["at"].alias("len"))
    return Grammar(every, known, started, residual, runs, [s | {"letters": fresh.get(s["phase"], 0)} for s in t.stats])


def rules_once(rules: DataFrame) -> DataFrame:
    """A letter that two phases make is one rule."""
    return settle(rules.groupBy("sym").agg(*(F.first(c).alias(c) if c != "phase" else F.min(c).alias(c) for c in rules.columns if c != "sym")).select(*rules.columns))


def grammar_size(g: Grammar, scheme: str = "gap", accounting: str = "compact", count_params: bool = False) -> int:
    """Non-parameter nodes of all right-hand sides, runs spelled by scheme, with the residual trees; with count_params also the parameters."""
    cost = g.rules.where("kind <> 'run'").agg(F.coalesce(F.sum(F.col("cost") + (F.col("rank") if count_params else F.lit(0))), F.lit(0))).first()[0]
    spelled = R.represent_runs(g.run_letters, scheme, accounting).agg(F.coalesce(F.sum(F.col("cost") + (1 if count_params else 0)), F.lit(0))).first()[0]
    return int(cost) + int(spelled) + g.residual.count()


#: Parts and parameters of rules up to which the way back broadcasts them. Their files are far smaller than they are in memory, so Spark's own estimate says nothing.
BROADCAST_CELLS = 100_000
ITEM = "tree_id long, pre long, parent long, slot int, sym long, inside array<bigint>"


def residual_items(residual: DataFrame) -> DataFrame:
    """What is left of trees stopped early, with the sizes of what hangs at each node's parameters.

    A tree of the residual is no larger than the stop size (or all of the tree, where no leaf step ran) and is one task's work.
    """

    def run(table: pa.Table) -> pa.Table:
        rows = sorted(table.to_pylist(), key=lambda r: r["pre"])
        at, size, kids = {r["pre"]: r for r in rows}, {}, {}
        for r in rows:
            if r["parent"] is not None:
                kids.setdefault(r["parent"], []).append(r)
        for r in reversed(rows):
            size[r["pre"]] = r["w"] + sum(size[k["pre"]] for k in kids.get(r["pre"], ()))
        out = []
        for r in rows:
            below = sorted(kids.get(r["pre"], ()), key=lambda k: k["slot"])
            out.append({"tree_id": r["tree_id"], "pre": r["pre"], "parent": r["parent"], "slot": r["slot"], "sym": r["sym"], "inside": [size[k["pre"]] for k in below]})
        for r in out:  # where a node really hangs: below the parameter's parent in the letter above it
            if r["parent"] is not None:
                top = at[r["parent"]]
                p = next(i for i, x in enumerate(top["params"]) if x["id"] == r["slot"] or len(top["params"]) == 1)
                inside = [size[k["pre"]] for k in sorted(kids[top["pre"]], key=lambda k: k["slot"])]
                up = top["params"][p]["up"]
                r["parent"] = top["pre"] + up + sum(n for x, n in zip(top["params"], inside) if x["off"] <= up)
                r["slot"] = top["params"][p]["at"]
        return pa.Table.from_pylist(out, pa.schema([("tree_id", pa.int64()), ("pre", pa.int64()), ("parent", pa.int64()), ("slot", pa.int32()), ("sym", pa.int64()), ("inside", pa.list_(pa.int64()))]))

    return residual.groupBy("tree_id").applyInArrow(run, ITEM)


def unfolded(items: DataFrame, rules: DataFrame, keep=lambda items: items) -> Iterator[DataFrame]:
    """Composite letters replaced by their parts, a level a round; yields the input letters as they come out.

    An item says where its pattern begins, below what, and how many nodes hang at each of its parameters. ``keep`` may drop items
    that are not wanted, before they are opened.
    """
    rules = rules.select("sym", F.col("kind").alias("how"), "rhs", "own", "weights")
    cells = rules.agg(F.sum(F.size("rhs") + F.size("own"))).first()[0] or 0
    rules = F.broadcast(rules) if cells <= BROADCAST_CELLS else rules.hint("merge")
    items = settle(items.join(rules, "sym", "left"))
    item = lambda pre, parent, slot, sym, inside: F.struct(pre.cast("long").alias("pre"), parent.cast("long").alias("parent"), slot.cast("int").alias("slot"), sym.alias("sym"), inside.cast("array<bigint>").alias("inside"))
    while True:
        yield items.where("how is null").select("tree_id", "pre", "parent", "slot", "sym")
        work = items.where("how is not null")
        if not work.take(1):
            return
        pre, up, slot, h, own, w = F.col("pre"), F.col("parent"), F.col("slot"), F.col("inside")[0], F.col("own")[0], F.col("weights")
        n = F.col("rhs")[0]["at"].cast("long")
        run = F.transform(F.sequence(F.lit(0).cast("long"), F.when(F.col("how") == "run", n - 1).otherwise(0)), lambda k: item(pre + k * own["off"], F.when(k == 0, up).otherwise(pre + (k - 1) * own["off"] + own["up"]), F.when(k == 0, slot).otherwise(own["at"]), F.col("rhs")[0]["sym"], F.array(h + (n - 1 - k) * w[0])))
        pair = F.array(item(pre, up, slot, F.col("rhs")[0]["sym"], F.array(h + w[1])), item(pre + own["off"], pre + own["up"], own["at"], F.col("rhs")[1]["sym"], F.array(h)))
        leaf = places.udfs().opened(*(F.when(F.col("how") == "leaf", F.col(c)) for c in ("pre", "parent", "slot", "rhs", "own", "weights", "inside")))
        held = work.withColumn("_leaf", leaf)
        parts = held.select("tree_id", F.explode(F.when(F.col("how") == "run", run).when(F.col("how") == "pair", pair).otherwise(F.col("_leaf"))).alias("x")).select("tree_id", "x.*")
        items = settle(keep(parts).join(rules, "sym", "left"))


def expand(g: Grammar) -> DataFrame:
    """The nodes that the grammar derives, trees stopped early included."""
    start = g.starts.select("tree_id", F.lit(0).cast("long").alias("pre"), nothing("long").alias("parent"), nothing("int").alias("slot"), "sym", F.array().cast("array<bigint>").alias("inside"))
    if g.residual.take(1):
        start = start.unionByName(residual_items(g.residual))
    ranks = g.symbols.where("kind = 'input'").select("sym", "rank")
    return reduce(DataFrame.unionByName, unfolded(start, g.rules)).join(ranks, "sym").select("tree_id", "pre", "parent", "slot", "sym", "rank")


def expand_symbol(g: Grammar, sym: int) -> DataFrame:
    """The pattern of one letter: (pre, parent, slot, sym) of its nodes, its parameters as missing children."""
    rank = g.rules.where(F.col("sym") == sym).select("rank").first()
    inside = F.array_repeat(F.lit(0).cast("long"), rank[0] if rank else 0)
    start = g.rules.sparkSession.range(1).select(F.lit(0).cast("long").alias("tree_id"), F.lit(0).cast("long").alias("pre"), nothing("long").alias("parent"), nothing("int").alias("slot"), F.lit(sym).cast("long").alias("sym"), inside.alias("inside"))
    return reduce(DataFrame.unionByName, unfolded(start, g.rules)).select("pre", "parent", "slot", "sym")
