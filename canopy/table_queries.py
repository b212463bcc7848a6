"""Queries of the branching workloads, chain grammars and the operators around them, with their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from canopy.model import settle
from canopy.operators import chains as C
from canopy.sources import hierarchies as H
from canopy.sources import relational as S

_recompressed: dict[tuple, tuple[C.Recompressed, DataFrame]] = {}
W3_TAG = "<([a-zA-Z][a-zA-Z0-9]*)"


def sign_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    signs = F.concat_ws("", F.transform("embedding", lambda x: F.when(x < 0, "-").otherwise("+")))
    return S.table(spark, sf_dir, "embeddings").select("vec_id", signs.alias("signs"))


def recompressed(spark: SparkSession, sf_dir: str, counts: str) -> tuple[C.Recompressed, DataFrame]:
    key = (spark.sparkContext.applicationId, sf_dir, counts)
    if key not in _recompressed:
        _recompressed[key] = C.recompress_texts(sign_texts(spark, sf_dir), "vec_id", "signs", counts)
    return _recompressed[key]


def w8_recompress(counts: str):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return C.unfold(*recompressed(spark, sf_dir, counts))

    return query


def w8_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Letters moved out of rules in each phase, beside the occurrences of nonterminals that allow two each."""
    got = recompressed(spark, sf_dir, "tree")[0].stats
    columns = ("phase", "run_occurrences", "run_moved", "pair_occurrences", "pair_moved", "size")
    held = [(*(s[c] for c in columns), s["run_moved"] <= 2 * s["run_occurrences"] and s["pair_moved"] <= 2 * s["pair_occurrences"]) for s in got]
    return spark.createDataFrame(held, "phase int, run_occurrences long, run_moved long, pair_occurrences long, pair_moved long, size long, within boolean")


def w3_tags(spark: SparkSession, sf_dir: str) -> DataFrame:
    return H.pages(spark, sf_dir).where("substr(name, 1, 1) <> '#'").groupBy("name").agg(F.count("*").alias("n"))


def w5_depth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nodes of each depth, a level a round: a tree's depth is small, its width isn't."""
    nodes = settle(H.geography(spark, sf_dir).select("pre", "parent"))
    level, out, d = settle(nodes.where("parent is null").select("pre")), [], 0
    while n := level.count():
        out.append((d, n))
        level, d = settle(nodes.join(level.withColumnRenamed("pre", "parent"), "parent").select("pre")), d + 1
    return spark.createDataFrame(out, "depth int, n long")


def scan_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.order_trees(spark, sf_dir).where("rank >= 2 and name = 'O:F'").select("tree_id", "rank")


def semi(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.table(spark, sf_dir, "orders").join(S.table(spark, sf_dir, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").select("o_orderkey")


def outer(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, o = S.table(spark, sf_dir, "customer"), S.table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count("*").alias("m"))
    return c.join(o, F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", F.coalesce("m", F.lit(0)).alias("n"))


def label_sets(kind: str):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        a = S.table(spark, sf_dir, "documents").select(F.explode(H.words("text")).alias("word"))
        b = S.table(spark, sf_dir, "benchmark").select(F.explode(H.words("text")).alias("word"))
        return {"union": lambda: a.union(b).distinct(), "intersect": lambda: a.intersect(b), "except": lambda: b.exceptAll(a).distinct()}[kind]()

    return query


def windows(kind: str):
    w = lambda: Window.partitionBy("user_id").orderBy("ts", "event_id")
    made = {
        "lag": lambda: F.lag("event_type").over(w()), "running": lambda: F.count("*").over(w().rowsBetween(Window.unboundedPreceding, 0)), "ntile": lambda: F.ntile(4).over(w()),
    }

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        return S.table(spark, sf_dir, "events").select("event_id", made[kind]().alias("got"))

    return query


def pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.table(spark, sf_dir, "events").groupBy("user_id").pivot("event_type").agg(F.count("event_id")).na.fill(0)


def days(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.table(spark, sf_dir, "events").groupBy("user_id").agg(F.count_distinct(F.to_date("ts")).alias("days"), F.count("*").alias("n"))


def props(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = S.table(spark, sf_dir, "events").select(F.explode(F.from_json("props", "map<string,string>")).alias("k", "v"))
    return e.groupBy("k", "v").agg(F.count("*").alias("n"))


def arrays(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An order's leaf labels in order."""
    leaves = S.order_trees(spark, sf_dir).where("rank = 0 and parent is not null")
    return leaves.groupBy("tree_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("pre", "name"))), lambda x: x["name"]), ",").alias("labels"))


def terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.table(spark, sf_dir, "events").select("event_id", F.format_string("{}(k(%s))", F.get_json_object("props", "$.k")).alias("term"))


QUERIES = {
    "w3_dom_nodes": lambda s, d: H.pages(s, d), "w3_tag_counts": w3_tags, "w5_nodes": lambda s, d: H.geography(s, d), "w5_binarise": lambda s, d: H.binarise(H.geography(s, d)), "op_recursive_depth": w5_depth,
    "w6_nodes": lambda s, d: H.conversations(s, d), "w9_nodes": lambda s, d: H.catalogue(s, d),
    "w8_recompress_tree_counts": w8_recompress("tree"), "w8_recompress_grammar_counts": w8_recompress("grammar"), "w8_recompress_alternate": w8_recompress("alternate"), "w8_recompress_ledger": w8_ledger,
    "op_scan_filter": scan_filter, "op_semi_absorbing": semi, "op_outer_children": outer, "op_union": label_sets("union"), "op_intersect": label_sets("intersect"), "op_except": label_sets("except"),
    "op_lag_letters": windows("lag"), "op_running_size": windows("running"), "op_ntile": windows("ntile"), "op_pivot_types": pivot, "op_date_days": days, "op_json_props": props, "op_array_rhs": arrays, "op_string_terms": terms,
}

WORDS = lambda t: f"SELECT unnest(list_filter(string_split_regex(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '')) AS word FROM {t}"
W5 = """o AS (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS k FROM orders),
c AS (SELECT c_custkey, c_nationkey AS nk, c_mktsegment, (SELECT count(*) FROM orders WHERE o_custkey = c_custkey) AS m FROM customer),
c2 AS (SELECT *, row_number() OVER (PARTITION BY nk ORDER BY c_custkey) AS k, coalesce(sum(m + 1) OVER (PARTITION BY nk ORDER BY c_custkey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS off FROM c),
n AS (SELECT n_nationkey AS nk, n_name, n_regionkey AS rk, (SELECT count(*) FROM supplier WHERE s_nationkey = n_nationkey) AS ns, (SELECT count(*) FROM c WHERE nk = n_nationkey) AS nc, (SELECT coalesce(sum(m + 1), 0) FROM c WHERE nk = n_nationkey) AS wc FROM nation),
n2 AS (SELECT *, row_number() OVER (PARTITION BY rk ORDER BY nk) AS k, coalesce(sum(1 + ns + wc) OVER (PARTITION BY rk ORDER BY nk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS off FROM n),
r AS (SELECT r_regionkey AS rk, r_name, (SELECT count(*) FROM n WHERE rk = r_regionkey) AS m, (SELECT coalesce(sum(1 + ns + wc), 0) FROM n WHERE rk = r_regionkey) AS w FROM region),
r2 AS (SELECT *, row_number() OVER (ORDER BY rk) AS k, 1 + coalesce(sum(1 + w) OVER (ORDER BY rk ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS pos FROM r),
n3 AS (SELECT n2.*, r2.pos AS up, r2.pos + 1 + n2.off AS pos FROM n2 JOIN r2 USING (rk)),
c3 AS (SELECT c2.*, n3.pos AS up, n3.ns, n3.pos + 1 + n3.ns + c2.off AS pos FROM c2 JOIN n3 USING (nk)),
w5 AS (SELECT 0::BIGINT AS tree_id, 0::BIGINT AS pre, NULL::BIGINT AS parent, NULL::INT AS slot, 'W' AS name, count(*)::INT AS rank FROM region
UNION ALL SELECT 0, pos::BIGINT, 0, k::INT, 'R:' || r_name, m::INT FROM r2
UNION ALL SELECT 0, pos::BIGINT, up::BIGINT, k::INT, 'N:' || n_name, (ns + nc)::INT FROM n3
UNION ALL SELECT 0, (pos + row_number() OVER (PARTITION BY s_nationkey ORDER BY s_suppkey))::BIGINT, pos::BIGINT, (row_number() OVER (PARTITION BY s_nationkey ORDER BY s_suppkey))::INT, 'S', 0 FROM supplier JOIN n3 ON nk = s_nationkey
UNION ALL SELECT 0, pos::BIGINT, up::BIGINT, (ns + k)::INT, 'C:' || c_mktsegment, m::INT FROM c3
UNION ALL SELECT 0, (pos + o.k)::BIGINT, pos::BIGINT, o.k::INT, 'O:' || o_orderstatus, 0 FROM o JOIN c3 ON c_custkey = o_custkey)"""
SIGNS = "SELECT vec_id AS tree_id, array_to_string(list_transform(embedding, lambda x: CASE WHEN x < 0 THEN '-' ELSE '+' END), '') AS text FROM embeddings"
EV = "OVER (PARTITION BY user_id ORDER BY ts, event_id{})"
SQL = {
    "w3_tag_counts": f"SELECT lower(t) AS name, count(*) AS n FROM (SELECT unnest(regexp_extract_all(html, '{W3_TAG}', 1)) AS t FROM pages) GROUP BY 1",
    "w5_nodes": f"WITH {W5} SELECT * FROM w5",
    "w5_binarise": f"WITH {W5} SELECT tree_id, pre, name, CASE WHEN rank > 0 THEN pre + 1 END AS child, CASE WHEN parent IS NOT NULL THEN lead(pre) OVER (PARTITION BY parent ORDER BY slot) END AS sibling FROM w5",
    "op_recursive_depth": f"WITH RECURSIVE {W5}, d AS (SELECT pre, 0 AS depth FROM w5 WHERE parent IS NULL UNION ALL SELECT w5.pre, depth + 1 FROM w5 JOIN d ON w5.parent = d.pre) SELECT depth, count(*) AS n FROM d GROUP BY 1",
    "w6_nodes": """WITH t AS (SELECT conv_id, turn, role, list_filter(string_split_regex(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS w FROM conversations),
u AS (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS k, 1 + coalesce(sum(len(w) + 2) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS pos FROM t)
SELECT conv_id AS tree_id, 0::BIGINT AS pre, NULL::BIGINT AS parent, NULL::INT AS slot, 'V' AS name, count(*)::INT AS rank FROM u GROUP BY 1
UNION ALL SELECT conv_id, pos, 0, k::INT, role, 1 FROM u
UNION ALL SELECT conv_id, pos + j, pos + j - 1, 1, x, 1 FROM (SELECT conv_id, pos, unnest(w) AS x, generate_subscripts(w, 1) AS j FROM u)
UNION ALL SELECT conv_id, pos + len(w) + 1, pos + len(w), 1, '#', 0 FROM u""",
    "w9_nodes": """WITH p AS (SELECT *, dense_rank() OVER (ORDER BY p_type) - 1 AS t, list_filter(string_split_regex(p_name, '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS w FROM part),
q AS (SELECT *, dense_rank() OVER (PARTITION BY t ORDER BY p_brand) AS b, row_number() OVER (PARTITION BY t, p_brand ORDER BY p_partkey) AS k, coalesce(sum(len(w) + 1) OVER (PARTITION BY t ORDER BY p_brand, p_partkey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS off FROM p),
r AS (SELECT *, 1 + b + off AS pos, min(b + off) OVER (PARTITION BY t, p_brand) AS up FROM q)
SELECT t AS tree_id, 0::BIGINT AS pre, NULL::BIGINT AS parent, NULL::INT AS slot, 'T:' || p_type AS name, count(DISTINCT p_brand)::INT AS rank FROM r GROUP BY t, p_type
UNION ALL SELECT t, up, 0, b::INT, 'B:' || p_brand, count(*)::INT FROM r GROUP BY t, up, b, p_brand
UNION ALL SELECT t, pos + j, CASE WHEN j = 0 THEN up ELSE pos + j - 1 END, CASE WHEN j = 0 THEN k ELSE 1 END, x, 1 FROM (SELECT t, pos, up, k, unnest(w) AS x, generate_subscripts(w, 1) - 1 AS j FROM r)
UNION ALL SELECT t, pos + len(w), CASE WHEN len(w) = 0 THEN up ELSE pos + len(w) - 1 END, CASE WHEN len(w) = 0 THEN k ELSE 1 END, 'S:' || floor(p_size / 10)::BIGINT, 0 FROM r""",
    "w8_recompress_tree_counts": SIGNS, "w8_recompress_grammar_counts": SIGNS, "w8_recompress_alternate": SIGNS,
    "op_scan_filter": "SELECT o_orderkey AS tree_id, count(*)::INT AS rank FROM orders JOIN lineitem ON l_orderkey = o_orderkey WHERE o_orderstatus = 'F' GROUP BY 1 HAVING count(*) > 1",
    "op_semi_absorbing": "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)",
    "op_outer_children": "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY 1",
    "op_union": f"{WORDS('documents')} UNION {WORDS('benchmark')}", "op_intersect": f"{WORDS('documents')} INTERSECT {WORDS('benchmark')}", "op_except": f"SELECT DISTINCT word FROM ({WORDS('benchmark')} EXCEPT ALL {WORDS('documents')})",
    "op_lag_letters": f"SELECT event_id, lag(event_type) {EV.format('')} AS got FROM events",
    "op_running_size": f"SELECT event_id, count(*) {EV.format(' ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW')} AS got FROM events",
    "op_ntile": f"SELECT event_id, ntile(4) {EV.format('')}::INT AS got FROM events",
    "op_pivot_types": "SELECT user_id, " + ", ".join(f"count(*) FILTER (event_type = '{t}') AS {t}" for t in ("click", "error", "purchase", "signup", "view")) + " FROM events GROUP BY 1",
    "op_date_days": "SELECT user_id, count(DISTINCT CAST(ts AS DATE)) AS days, count(*) AS n FROM events GROUP BY 1",
    "op_json_props": "SELECT 'k' AS k, json_extract_string(props, '$.k') AS v, count(*) AS n FROM events GROUP BY 2",
    "op_array_rhs": "SELECT l_orderkey AS tree_id, string_agg('Q:' || floor(l_quantity / 10)::BIGINT, ',' ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus) AS labels FROM lineitem WHERE l_orderkey IN (SELECT o_orderkey FROM orders) GROUP BY 1",
    "op_string_terms": "SELECT event_id, '{}(k(' || json_extract_string(props, '$.k') || '))' AS term FROM events",
}
