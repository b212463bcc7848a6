"""What a grammar tells without being expanded: heights, equal trees, single nodes, pattern counts; and its views, files and terms."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from canopy.model import Forest, Grammar, settle
from canopy.operators import packed, places
from canopy.operators.compressor import nothing, unfolded

DEEP = "array<struct<id:int,depth:bigint>>"


def heights(g: Grammar) -> DataFrame:
    """(sym, high, deep): the greatest depth in a letter's pattern and the depth at which each parameter hangs, phase by phase from the rules."""
    first = F.when(F.col("rank") > 0, F.transform(F.sequence(F.lit(1), F.greatest("rank", F.lit(1))), lambda i: F.struct(i.alias("id"), F.lit(1).cast("long").alias("depth")))).otherwise(F.array().cast(DEEP))
    known = settle(g.symbols.where("kind = 'input'").select("sym", F.lit(0).cast("long").alias("high"), first.alias("deep")))
    phases = sorted(r[0] for r in g.rules.select("phase").distinct().collect())
    for phase in phases:
        for kind in ("run", "pair", "leaf"):
            now = g.rules.where((F.col("phase") == phase) & (F.col("kind") == kind))
            parts = now.select("sym", F.posexplode("rhs").alias("i", "x")).select(F.col("sym").alias("top"), "i", F.col("x.sym").alias("sym"), F.col("x.at").alias("at")).join(known, "sym")
            rows = parts.groupBy("top").agg(F.array_sort(F.collect_list(F.struct("i", "at", "high", "deep"))).alias("p"))
            a, b, n = F.col("p")[0], F.col("p")[1], F.col("p")[0]["at"]
            da = a["deep"][0]["depth"]
            if kind == "run":
                new = rows.select(F.col("top").alias("sym"), ((n - 1) * da + a["high"]).cast("long").alias("high"), F.array(F.struct(a["deep"][0]["id"].alias("id"), (n * da).cast("long").alias("depth"))).alias("deep"))
            elif kind == "pair":
                db = F.try_element_at("p", F.lit(2))["deep"][0]
                new = rows.select(F.col("top").alias("sym"), F.greatest(a["high"], da + F.try_element_at("p", F.lit(2))["high"]).alias("high"), F.array(F.struct(db["id"].alias("id"), (da + db["depth"]).alias("depth"))).alias("deep"))
            else:
                rest = F.transform(F.slice("p", 2, F.size("p")), lambda x: F.struct(x["at"].alias("at"), x["high"].alias("high")))
                new = rows.select(F.col("top").alias("sym"), places.udfs().depths(a["high"], a["deep"], rest).alias("d")).select("sym", "d.high", "d.deep")
            known = known.unionByName(new)
        known = settle(known.dropDuplicates(["sym"]))
    return known


def tree_heights(g: Grammar) -> DataFrame:
    """(tree_id, height): edges on the longest way down."""
    return g.starts.join(heights(g).select("sym", "high"), "sym").select("tree_id", F.col("high").alias("height"))


def equal_trees(g: Grammar) -> DataFrame:
    """(tree_id, class): trees are equal just if their start letters are; a class is named by its least tree."""
    least = g.starts.groupBy("sym").agg(F.min("tree_id").alias("class"))
    return g.starts.join(least, "sym").select("tree_id", "class")


def node_at(g: Grammar, wanted: DataFrame) -> DataFrame:
    """The nodes (tree_id, pre) named in wanted, with letter name, parent and slot: only letters whose range holds a wanted place are opened."""
    want = wanted.select("tree_id", F.col("pre").alias("k")).distinct()
    weight = g.symbols.select("sym", "weight", "kind")
    start = g.starts.join(want.select("tree_id").distinct(), "tree_id", "left_semi").select("tree_id", F.lit(0).cast("long").alias("pre"), nothing("long").alias("parent"), nothing("int").alias("slot"), "sym", F.array().cast("array<bigint>").alias("inside"))

    def near(items: DataFrame) -> DataFrame:
        end = F.col("pre") + F.col("weight") + F.aggregate("inside", F.lit(0).cast("long"), lambda s, x: s + x)
        ranged = items.join(weight.select("sym", "weight"), "sym").withColumn("end", end)
        hit = ranged.join(want.withColumnRenamed("tree_id", "t"), (F.col("tree_id") == F.col("t")) & (F.col("k") >= F.col("pre")) & (F.col("k") < F.col("end")), "left_semi")
        return hit.select(items.columns)

    found = reduce(DataFrame.unionByName, unfolded(start, g.rules, near))
    names = g.symbols.where("kind = 'input'").select("sym", "name")
    return found.join(want.withColumnRenamed("k", "pre"), ["tree_id", "pre"], "left_semi").join(names, "sym").select("tree_id", "pre", "parent", "slot", "name")


def occurrences(g: Grammar) -> DataFrame:
    """(sym, times): how often each letter stands in the derived forest's derivation, pushed down from the starts."""
    use = settle(g.starts.groupBy("sym").agg(F.count("*").cast("decimal(38,0)").alias("times")))
    rules = g.rules.select("sym", "kind", F.explode("rhs").alias("x")).select("sym", F.col("x.sym").alias("part"), F.when(F.col("kind") == "run", F.col("x.at")).otherwise(1).alias("by"))
    rounds = [use]
    while True:
        use = settle(use.join(rules, "sym").groupBy(F.col("part").alias("sym")).agg(F.sum(F.col("times") * F.col("by")).cast("decimal(38,0)").alias("times")))
        if not use.take(1):
            return settle(reduce(DataFrame.unionByName, rounds).groupBy("sym").agg(F.sum("times").cast("decimal(38,0)").alias("times")))
        rounds.append(use)


def top_rules(g: Grammar, n: int = 10) -> DataFrame:
    """The rules that save most: occurrences times the nodes they spare, ties by letter."""
    saved = (F.col("times") * (F.col("cost") - 1) - F.col("cost")).cast("long")
    return g.rules.join(occurrences(g), "sym").select("sym", "kind", "cost", F.col("times").cast("long").alias("times"), saved.alias("saved")).orderBy(F.desc("saved"), "kind", "sym").limit(n)


def covered_share(spark: SparkSession, chains: DataFrame, end: int, by: str) -> DataFrame:
    """(by, nodes, cost, ratio): for each class of chains (tree_id, letters, by) the cost of the rules it needs over its nodes.

    A tree needs just the letters that the phases make in it, so they are noted by class as they are made.
    """
    packed.prepare(spark)
    label = F.xxhash64(F.lit("class"), by)
    nodes = chains.groupBy(by).agg(F.sum(F.size("letters") + 1).alias("nodes")).withColumn("label", label)
    made = packed.phases(spark, packed.from_chains(chains.select("tree_id", "letters", label.alias("label")), end, packed.NONE), packed.NONE)
    cost = packed.used(made, "cost").groupBy("label").agg(F.sum("cost").alias("cost"))
    return nodes.join(cost, "label", "left").select(by, "nodes", F.coalesce("cost", F.lit(0)).alias("cost"), (F.coalesce("cost", F.lit(0)) / F.col("nodes")).alias("ratio"))


TABLES = ("rules", "symbols", "starts", "residual", "run_letters")


def write_grammar(g: Grammar, path: str) -> None:
    """Parquet tables of a grammar, rules by phase, so undoing a phase reads one partition."""
    for name in TABLES:
        out = getattr(g, name).write.mode("error")
        (out.partitionBy("phase") if name == "rules" else out).parquet(f"{path}/{name}")


def read_grammar(spark: SparkSession, path: str) -> Grammar:
    return Grammar(*(spark.read.parquet(f"{path}/{name}") for name in TABLES))


def register_views(g: Grammar, forest: Forest | None = None, prefix: str = "canopy") -> list[str]:
    """Temporary views of a grammar's tables (and a forest's nodes) for SQL, and the table function binary_expansion(n)."""
    spark = g.rules.sparkSession
    made = []
    for name in ("rules", "symbols", "starts"):
        getattr(g, name).createOrReplaceTempView(f"{prefix}_{name}")
        made.append(f"{prefix}_{name}")
    columns = ("phase", "nodes", "n0", "n1", "n2plus", "chains", "letters")
    spark.createDataFrame([tuple(s[c] for c in columns) for s in g.stats], ", ".join(f"{c} {'int' if c == 'phase' else 'long'}" for c in columns)).createOrReplaceTempView(f"{prefix}_phases")
    made.append(f"{prefix}_phases")
    if forest is not None:
        forest.nodes.createOrReplaceTempView(f"{prefix}_nodes")
        made.append(f"{prefix}_nodes")
    spark.udtf.register("binary_expansion", binary_udtf())
    return made


def binary_udtf():
    from pyspark.sql.functions import udtf

    class Binary:
        def eval(self, n: int):
            for i in range(int(n).bit_length()):
                if n >> i & 1:
                    yield i, 1 << i

    return udtf(Binary, returnType="bit int, power long")


def written_rules(g: Grammar) -> DataFrame:
    """(sym, line): each rule as text, letters by name or number."""
    names = g.symbols.select("sym", F.coalesce("name", F.concat(F.lit("#"), F.hex("sym"))).alias("shown"))
    parts = g.rules.select("sym", "kind", F.posexplode("rhs").alias("i", "x")).select("sym", "kind", "i", F.col("x.at").alias("at"), F.col("x.sym").alias("part")).join(names.withColumnRenamed("sym", "part"), "part")
    one = F.when(F.col("kind") == "run", F.concat("shown", F.lit("^"), F.col("at").cast("string"))).when((F.col("kind") == "leaf") & (F.col("i") > 0), F.concat(F.col("at").cast("string"), F.lit(":"), "shown")).otherwise(F.col("shown"))
    lines = parts.withColumn("one", one).groupBy("sym").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("i", "one"))), lambda x: x["one"]), " ").alias("body"))
    return lines.join(names, "sym").select("sym", F.concat("shown", F.lit(" -> "), "body").alias("line"))


def dot_lines(g: Grammar) -> DataFrame:
    """Lines of a graph description: an arc from each letter to each of its parts."""
    arcs = g.rules.select("sym", F.explode("rhs").alias("x")).select("sym", F.col("x.sym").alias("part")).distinct()
    return arcs.select(F.format_string('  "%s" -> "%s";', F.hex("sym"), F.hex("part")).alias("line"))
