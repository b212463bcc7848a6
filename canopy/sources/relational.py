"""Forests of the given tables: (tree_id, pre, parent, slot, name, rank) rows, by windows and unions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from canopy.model import letter

END = "#"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def rows(df: DataFrame, tree, pre, parent, slot, name, rank) -> DataFrame:
    c = lambda x: x if not isinstance(x, (int, type(None))) else F.lit(x)
    return df.select(c(tree).cast("long").alias("tree_id"), c(pre).cast("long").alias("pre"), c(parent).cast("long").alias("parent"), c(slot).cast("int").alias("slot"), c(name).alias("name"), c(rank).cast("int").alias("rank"))


def order_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An order over its lines, a line as flag over status over a leaf of its quantity's ten."""
    line = table(spark, sf_dir, "lineitem")
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus")
    line = line.withColumn("k", F.row_number().over(w))
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus")
    many = line.groupBy("l_orderkey").agg(F.count("*").alias("m"))
    roots = orders.join(many, F.col("o_orderkey") == F.col("l_orderkey"), "left")
    kept = line.join(orders, F.col("o_orderkey") == F.col("l_orderkey"), "left_semi")
    at = 1 + 3 * (F.col("k") - 1)
    key = F.col("l_orderkey")
    return (
        rows(roots, F.col("o_orderkey"), 0, None, None, F.concat(F.lit("O:"), "o_orderstatus"), F.coalesce("m", F.lit(0)))
        .unionByName(rows(kept, key, at, 0, F.col("k"), F.concat(F.lit("RF:"), "l_returnflag"), 1))
        .unionByName(rows(kept, key, at + 1, at, 1, F.concat(F.lit("LS:"), "l_linestatus"), 1))
        .unionByName(rows(kept, key, at + 2, at + 1, 1, F.concat(F.lit("Q:"), F.floor(F.col("l_quantity") / 10).cast("string")), 0))
    )


def chain(df: DataFrame, tree: str, order: list, name) -> DataFrame:
    """One unary chain for each tree, with an end leaf."""
    w = Window.partitionBy(tree).orderBy(*order)
    body = df.withColumn("k", F.row_number().over(w) - 1)
    up = F.when(F.col("k") > 0, F.col("k") - 1)
    ends = df.groupBy(tree).agg(F.count("*").alias("m"))
    return rows(body, F.col(tree), F.col("k"), up, F.when(F.col("k") > 0, 1), name, 1).unionByName(rows(ends, F.col(tree), F.col("m"), F.col("m") - 1, 1, F.lit(END), 0))


def event_chains(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A user's events in time."""
    return chain(table(spark, sf_dir, "events"), "user_id", ["ts", "event_id"], F.col("event_type"))


def user_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A user over days, a day as its chain of events."""
    e = table(spark, sf_dir, "events").withColumn("day", F.to_date("ts"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = e.withColumn("i", F.row_number().over(w)).withColumn("d", F.dense_rank().over(Window.partitionBy("user_id").orderBy("day"))).withColumn("j", F.row_number().over(Window.partitionBy("user_id", "day").orderBy("ts", "event_id")))
    at = F.col("i") + F.col("d") - 1
    days = e.groupBy("user_id", "d").agg(F.max("i").alias("i"))
    users = days.groupBy("user_id").agg(F.max("d").alias("m"))
    return (
        rows(users, F.col("user_id"), 0, None, None, F.lit("U"), F.col("m"))
        .unionByName(rows(e, F.col("user_id"), at, F.when(F.col("j") == 1, 0).otherwise(at - 1), F.when(F.col("j") == 1, F.col("d")).otherwise(1), F.col("event_type"), 1))
        .unionByName(rows(days, F.col("user_id"), F.col("i") + F.col("d"), F.col("i") + F.col("d") - 1, 1, F.lit(END), 0))
    )


def string_parts(text: str, unit: str) -> Column:
    """A text's characters, words or lines; null and empty texts have none."""
    body = F.coalesce(F.col(text), F.lit(""))
    cut = {"char": F.split(body, ""), "word": F.split(F.trim(F.regexp_replace(body, r"\s+", " ")), " "), "line": F.split(body, "\n")}[unit]
    return F.filter(cut, lambda x: x != "") if unit != "line" else F.when(body == "", F.array().cast("array<string>")).otherwise(cut)


def strings(df: DataFrame, key: str, text: str, unit: str = "char") -> DataFrame:
    """A text as a chain of characters, words or lines; null and empty texts are the end leaf alone."""
    held = df.select(F.col(key).alias("key"), string_parts(text, unit).alias("parts"))
    one = held.select("key", F.posexplode("parts").alias("k", "x"))
    up = F.when(F.col("k") > 0, F.col("k") - 1)
    n = F.size("parts")
    return rows(one, F.col("key"), F.col("k"), up, F.when(F.col("k") > 0, 1), F.col("x"), 1).unionByName(rows(held, F.col("key"), n, F.when(n > 0, n - 1), F.when(n > 0, 1), F.lit(END), 0))


def letters_of(df: DataFrame, key: str, text: str, unit: str, *more: str) -> DataFrame:
    """(tree_id, letters, more): the chains of strings() with their letters' ids beside each other."""
    ids = F.transform(string_parts(text, unit), lambda x: letter(F.lit("input"), x, F.lit(1)))
    return df.select(F.col(key).cast("long").alias("tree_id"), ids.alias("letters"), *more)


def document_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return strings(table(spark, sf_dir, "documents"), "doc_id", "text", "line")


def event_props(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A JSON object over its key over its value."""
    e = table(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").alias("v"))
    i = F.col("event_id")
    return rows(e, i, 0, None, None, F.lit("{}"), 1).unionByName(rows(e, i, 1, 0, 1, F.lit("k"), 1)).unionByName(rows(e, i, 2, 1, 1, F.col("v"), 0))


def sign_chains(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A vector's signs, ended by its label."""
    e = table(spark, sf_dir, "embeddings")
    one = e.select("vec_id", F.posexplode("embedding").alias("k", "x"))
    up = F.when(F.col("k") > 0, F.col("k") - 1)
    return rows(one, F.col("vec_id"), F.col("k"), up, F.when(F.col("k") > 0, 1), F.when(F.col("x") < 0, "-").otherwise("+"), 1).unionByName(rows(e, F.col("vec_id"), F.size("embedding"), F.size("embedding") - 1, 1, F.concat(F.lit("L:"), F.col("label").cast("string")), 0))


def from_terms(spark: SparkSession, terms: dict[int, str]) -> DataFrame:
    """Forests written as terms, for worked examples: f(a(b),c)."""
    out = []
    for tree, term in terms.items():
        stack, name, made = [], "", []

        def node(name: str) -> None:
            parent = stack[-1] if stack else None
            if parent is not None:
                made[parent][5] += 1
            made.append([tree, len(made), parent, made[parent][5] if parent is not None else None, name, 0])

        for ch in term + ",":
            if ch in "(),":
                if name:
                    node(name)
                if ch == "(":
                    stack.append(len(made) - 1)
                elif ch == ")":
                    stack.pop()
                name = ""
            else:
                name += ch
        out += [tuple(x) for x in made]
    return spark.createDataFrame(out, "tree_id long, pre long, parent long, slot int, name string, rank int")


def family(spark: SparkSession, kind: str, k: int) -> DataFrame:
    """Synthetic trees from spark.range. power: a^k over a leaf; ab: (ab)^k over a leaf; fibonacci: the k-th Fibonacci word over a leaf; flat: k equal leaves; binary: perfect of height k; comb: k inner nodes; random: k nodes of rank at most 3."""
    one = F.lit(0)
    if kind == "fibonacci":
        a, b = "a", "ab"
        for _ in range(k - 2):
            a, b = b, b + a
        word = [(0, i, c) for i, c in enumerate(b)]
        n, i = len(word), F.col("i")
        body = spark.createDataFrame(word, "t long, i long, c string")
        return rows(body, one, i, F.when(i > 0, i - 1), F.when(i > 0, 1), F.col("c"), 1).unionByName(rows(spark.range(1), one, n, n - 1, 1, F.lit("c"), 0))
    if kind == "random":
        import random

        rng, made, open_ = random.Random(k), [], [(None, None)]
        while open_:
            parent, slot = open_.pop()
            rank = 0 if len(made) + len(open_) >= k else rng.choice([0, 1, 1, 2, 2, 3])
            rank = max(rank, 1) if not open_ and len(made) + 1 < k else rank
            made.append((0, len(made), parent, slot, f"{'cabf'[rank]}{rng.randrange(3)}", rank))
            open_ += [(len(made) - 1, j) for j in range(rank, 0, -1)]
        return spark.createDataFrame(made, "tree_id long, pre long, parent long, slot int, name string, rank int")
    if kind in ("power", "ab"):
        n = k if kind == "power" else 2 * k
        i = F.col("id")
        name = F.when(i == n, "c").when((i % 2 == 1) & F.lit(kind == "ab"), "b").otherwise("a")
        return rows(spark.range(n + 1), one, i, F.when(i > 0, i - 1), F.when(i > 0, 1), name, F.when(i == n, 0).otherwise(1))
    if kind == "flat":
        i = F.col("id")
        return rows(spark.range(k + 1), one, i, F.when(i > 0, 0), F.when(i > 0, i), F.when(i > 0, "c").otherwise("f"), F.when(i > 0, 0).otherwise(k))
    if kind == "comb":
        i = F.col("id")  # inner node j at 2j, its leaf at 2j+1; the last has a second leaf
        inner = (i % 2 == 0) & (i < 2 * k)
        parent = F.when(i == 0, None).when(i == 2 * k, i - 2).when(i % 2 == 0, i - 2).otherwise(i - 1)
        return rows(spark.range(2 * k + 1), one, i, parent, F.when(i == 0, None).when((i % 2 == 0) , 2).otherwise(1), F.when(inner, "f").otherwise("c"), F.when(inner, 2).otherwise(0))
    # perfect binary: node with heap path of depth d; pre-order number from the path's bits
    levels = spark.range(k + 1).select(F.col("id").alias("d")).withColumn("p", F.explode(F.sequence(F.lit(0), F.call_function("shiftleft", F.lit(1), F.col("d").cast("int")) - 1)))
    bits = F.when(F.col("d") > 0, F.transform(F.sequence(F.lit(1), F.col("d").cast("int")), lambda j: F.call_function("shiftright", F.col("p"), F.col("d").cast("int") - j) % 2)).otherwise(F.array().cast("array<int>"))
    pre = F.aggregate(F.transform(bits, lambda b, j: 1 + b * (F.call_function("shiftleft", F.lit(1), (k - j).cast("int") if not isinstance(k, int) else (F.lit(k) - j).cast("int")) - 1)), F.lit(0), lambda s, x: s + x)
    up = F.aggregate(F.transform(F.slice(bits, 1, F.greatest(F.col("d").cast("int") - 1, F.lit(0))), lambda b, j: 1 + b * (F.call_function("shiftleft", F.lit(1), (F.lit(k) - j).cast("int")) - 1)), F.lit(0), lambda s, x: s + x)
    return rows(levels, one, pre, F.when(F.col("d") > 0, up), F.when(F.col("d") > 0, F.col("p") % 2 + 1), F.when(F.col("d") == k, "c").otherwise("f"), F.when(F.col("d") == k, 0).otherwise(2))
