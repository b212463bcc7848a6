"""Trees of branching tables: geography, conversations, the catalogue and pages."""

from __future__ import annotations

from html.parser import HTMLParser

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from canopy.sources.relational import END, rows, table

SPACES = r"[\x20\x09-\x0D]+"
#: Elements without content, and those that an equal open one ends.
VOID = frozenset(("area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "source", "track", "wbr"))
SELF_ENDING = frozenset(("p", "li", "option", "tr", "td", "th", "dt", "dd"))


def words(text: str) -> "F.Column":
    return F.filter(F.split(F.coalesce(F.col(text), F.lit("")), SPACES), lambda x: x != "")


def before(value, *by, over) -> "F.Column":
    return F.coalesce(F.sum(value).over(Window.partitionBy(*over).orderBy(*by).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))


def geography(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One tree of regions, nations, suppliers before customers, and a customer's orders. Places come from prefix sums of subtree sizes, one level at a time."""
    order = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("ck"), "o_orderkey", "o_orderstatus")
    held = order.groupBy("ck").agg(F.count("*").alias("m"))
    cust = table(spark, sf_dir, "customer").join(held, F.col("c_custkey") == F.col("ck"), "left").select("c_custkey", F.col("c_nationkey").alias("nk"), "c_mktsegment", F.coalesce("m", F.lit(0)).alias("m"))
    cust = cust.withColumn("k", F.row_number().over(Window.partitionBy("nk").orderBy("c_custkey"))).withColumn("off", before(F.col("m") + 1, "c_custkey", over=["nk"]))
    supp = table(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("nk"), F.row_number().over(Window.partitionBy("s_nationkey").orderBy("s_suppkey")).alias("k"))
    ns, nc = supp.groupBy("nk").agg(F.count("*").alias("ns")), cust.groupBy("nk").agg(F.count("*").alias("nc"), F.sum(F.col("m") + 1).alias("wc"))
    zero = lambda c: F.coalesce(c, F.lit(0))
    nation = table(spark, sf_dir, "nation").withColumn("nk", F.col("n_nationkey")).join(ns, "nk", "left").join(nc, "nk", "left").select("nk", "n_name", F.col("n_regionkey").alias("rk"), zero("ns").alias("ns"), zero("nc").alias("nc"), (1 + zero("ns") + zero("wc")).alias("size"))
    nation = nation.withColumn("k", F.row_number().over(Window.partitionBy("rk").orderBy("nk"))).withColumn("off", before(F.col("size"), "nk", over=["rk"]))
    per = nation.groupBy("rk").agg(F.count("*").alias("m"), (1 + F.sum("size")).alias("size"))
    one = F.lit(0)
    region = table(spark, sf_dir, "region").join(per, F.col("r_regionkey") == F.col("rk"), "left").select(F.col("r_regionkey").alias("rk"), "r_name", zero("m").alias("m"), F.coalesce("size", F.lit(1)).alias("size")).withColumn("k", F.row_number().over(Window.partitionBy(one).orderBy("rk"))).withColumn("at", 1 + before(F.col("size"), "rk", over=[one]))
    nation = nation.join(region.select("rk", F.col("at").alias("up")), "rk").withColumn("at", F.col("up") + 1 + F.col("off"))
    places = nation.select("nk", F.col("at").alias("up"), "ns")
    cust = cust.join(places, "nk").withColumn("at", F.col("up") + 1 + F.col("ns") + F.col("off"))
    order = order.withColumn("k", F.row_number().over(Window.partitionBy("ck").orderBy("o_orderkey"))).join(cust.select(F.col("c_custkey").alias("ck"), F.col("at").alias("up")), "ck")
    root = region.agg(F.count("*").alias("m"))
    return (
        rows(root, one, 0, None, None, F.lit("W"), F.col("m"))
        .unionByName(rows(region, one, F.col("at"), 0, F.col("k"), F.concat(F.lit("R:"), "r_name"), F.col("m")))
        .unionByName(rows(nation, one, F.col("at"), F.col("up"), F.col("k"), F.concat(F.lit("N:"), "n_name"), F.col("ns") + F.col("nc")))
        .unionByName(rows(supp.join(places, "nk"), one, F.col("up") + F.col("k"), F.col("up"), F.col("k"), F.lit("S"), 0))
        .unionByName(rows(cust, one, F.col("at"), F.col("up"), F.col("ns") + F.col("k"), F.concat(F.lit("C:"), "c_mktsegment"), F.col("m")))
        .unionByName(rows(order, one, F.col("up") + F.col("k"), F.col("up"), F.col("k"), F.concat(F.lit("O:"), "o_orderstatus"), 0))
    )


def conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A conversation over its turns, a turn as its role over its words over an end leaf."""
    t = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", words("text").alias("w"))
    t = t.withColumn("k", F.row_number().over(Window.partitionBy("conv_id").orderBy("turn"))).withColumn("at", 1 + before(F.size("w") + 2, "turn", over=["conv_id"]))
    one = t.select("conv_id", "at", F.posexplode("w").alias("j", "x"))
    c, end = F.col("conv_id"), F.col("at") + F.size("w") + 1
    return (
        rows(t.groupBy("conv_id").agg(F.count("*").alias("m")), c, 0, None, None, F.lit("V"), F.col("m"))
        .unionByName(rows(t, c, F.col("at"), 0, F.col("k"), F.col("role"), 1))
        .unionByName(rows(one, c, F.col("at") + 1 + F.col("j"), F.col("at") + F.col("j"), 1, F.col("x"), 1))
        .unionByName(rows(t, c, end, end - 1, 1, F.lit(END), 0))
    )


def catalogue(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A part type over its brands over its parts; a part is its name's words over a leaf of its size's ten."""
    p = table(spark, sf_dir, "part").select("p_type", "p_brand", "p_partkey", words("p_name").alias("w"), F.concat(F.lit("S:"), F.floor(F.col("p_size") / 10).cast("string")).alias("leaf"))
    ids = p.select("p_type").distinct().withColumn("t", F.row_number().over(Window.orderBy("p_type")) - 1)
    p = p.join(F.broadcast(ids), "p_type").withColumn("k", F.row_number().over(Window.partitionBy("p_type", "p_brand").orderBy("p_partkey"))).withColumn("off", before(F.size("w") + 1, "p_partkey", over=["p_type", "p_brand"]))
    b = p.groupBy("t", "p_type", "p_brand").agg(F.count("*").alias("m"), (1 + F.sum(F.size("w") + 1)).alias("size"))
    b = b.withColumn("k", F.row_number().over(Window.partitionBy("t").orderBy("p_brand"))).withColumn("at", 1 + before(F.col("size"), "p_brand", over=["t"]))
    p = p.join(b.select("t", "p_brand", F.col("at").alias("up")), ["t", "p_brand"]).withColumn("at", F.col("up") + 1 + F.col("off"))
    one = p.select("t", "at", "up", "k", F.posexplode("w").alias("j", "x"))
    first, none = F.col("j") == 0, F.size("w") == 0
    end = F.col("at") + F.size("w")
    return (
        rows(b.groupBy("t", "p_type").agg(F.count("*").alias("m")), F.col("t"), 0, None, None, F.concat(F.lit("T:"), "p_type"), F.col("m"))
        .unionByName(rows(b, F.col("t"), F.col("at"), 0, F.col("k"), F.concat(F.lit("B:"), "p_brand"), F.col("m")))
        .unionByName(rows(one, F.col("t"), F.col("at") + F.col("j"), F.when(first, F.col("up")).otherwise(F.col("at") + F.col("j") - 1), F.when(first, F.col("k")).otherwise(1), F.col("x"), 1))
        .unionByName(rows(p, F.col("t"), end, F.when(none, F.col("up")).otherwise(end - 1), F.when(none, F.col("k")).otherwise(1), F.col("leaf"), 0))
    )


class _Dom(HTMLParser):
    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.made, self.stack = [[None, None, "#doc", 0]], [0]

    def add(self, name: str) -> int:
        up = self.stack[-1]
        self.made[up][3] += 1
        self.made.append([up, self.made[up][3], name, 0])
        return len(self.made) - 1

    def handle_starttag(self, tag, attrs):
        if tag in SELF_ENDING and self.made[self.stack[-1]][2] == tag:
            self.stack.pop()
        at = self.add(tag)
        if tag not in VOID:
            self.stack.append(at)

    def handle_startendtag(self, tag, attrs):
        self.add(tag)

    def handle_endtag(self, tag):
        for depth in range(len(self.stack) - 1, 0, -1):
            if self.made[self.stack[depth]][2] == tag:
                del self.stack[depth:]
                return

    def handle_data(self, data):
        if data.strip():
            self.add("#text")


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A page's elements and texts below #doc. An end tag closes to its element or is ignored; open elements end with the page; null and empty pages are #doc alone."""

    def run(batches):
        for batch in batches:
            out = []
            for key, html in zip(batch.column("page_id").to_pylist(), batch.column("html").to_pylist()):
                dom = _Dom()
                dom.feed(html or "")
                dom.close()
                out += [(key, pre, *x) for pre, x in enumerate(dom.made)]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate((pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.string(), pa.int32()))], ["tree_id", "pre", "parent", "slot", "name", "rank"])

    return table(spark, sf_dir, "pages").select(F.col("page_id").cast("long").alias("page_id"), "html").mapInArrow(run, "tree_id long, pre long, parent long, slot int, name string, rank int")


def binarise(nodes: DataFrame) -> DataFrame:
    """(tree_id, pre, name, child, sibling): first child and next sibling of every node, null where there is none."""
    sibling = F.lead("pre").over(Window.partitionBy("tree_id", "parent").orderBy("slot"))
    return nodes.select("tree_id", "pre", "name", F.when(F.col("rank") > 0, F.col("pre") + 1).alias("child"), F.when(F.col("parent").isNotNull(), sibling).alias("sibling"))
