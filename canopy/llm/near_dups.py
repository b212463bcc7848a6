"""Near-duplicate groups by a multi-index Hamming join over b-bit minhash signatures.

A signature is PARTS x SIZE components of BITS bits. Two signatures that differ in at most FAR = 2 PARTS - 1
components agree, by pigeonhole, in all but one component of some part; so a key for every part and
every component left out of it brings together all pairs within FAR. That distance is the threshold of the join: all
pairs within it are candidates, none beyond it. Every candidate is confirmed on the full shingle sets.

No group is expanded into its pairs. Texts with equal sets are one representative; a bucket first links its
members to three centres; only members that are still in different components then meet, with size,
signature distance and the sets' least hashes tested in blocks, so that only possible links leave the bucket.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.llm import kernels as K
from canopy.llm.common import cut, drop_cut, ship, small_enough, temporary
from canopy.llm.graph import components

PARTS = 12
SIZE = 4
BITS = 16
ERRORS = 1
#: The greatest distance at which a pair is sure to share a key. At similarity 0.8 the distance is about 10 of 48, beyond 23 four times in 10**6.
FAR = (ERRORS + 1) * PARTS - 1
#: Least shingle hashes of a set that a join compares; a set of no more is whole there.
LOW = 512
#: Members of a bucket that a task compares at once.
BLOCK = 2048
PERCENT = 80

_seeds = np.random.default_rng(64).integers(0, 2**63, (2, PARTS * SIZE), dtype=np.int64).astype(K.U)
FACTORS, SHIFTS = _seeds[0] * K.U(2) + K.U(1), _seeds[1]


def signatures(sets: np.ndarray, at: np.ndarray) -> np.ndarray:
    """[documents with a shingle, PARTS * SIZE] components."""
    first = at[:-1][np.diff(at) > 0]
    out = np.empty((len(first), PARTS * SIZE), dtype=np.int16)
    with np.errstate(over="ignore"):
        for j in range(PARTS * SIZE):
            out[:, j] = (K.mix(np.minimum.reduceat(sets * FACTORS[j] + SHIFTS[j], first)) & K.U((1 << BITS) - 1)).astype(np.uint16).view(np.int16) if len(first) else 0
    return out


def sketch(docs: DataFrame, width: int) -> DataFrame:
    """doc_id, n (set size), two hashes of the set, and the signature (null without shingles)."""
    ship(docs.sparkSession)

    def run(batches):
        for batch in batches:
            for part in K.slices(batch, "text", 1 << 20):
                sets, at = K.shingle_sets(*K.text_buffer(part.column("text")), width)
                n = np.diff(at)
                total = [np.concatenate((np.zeros(1, K.U), np.cumsum(K.mix(sets ^ K.U(s)), dtype=K.U))) for s in (0, 0x5BD1E995)]
                with np.errstate(over="ignore"):
                    k1, k2 = (t[at[1:]] - t[at[:-1]] for t in total)
                sig = signatures(sets, at)
                offsets = np.concatenate(([0], np.cumsum((n > 0) * PARTS * SIZE))).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(sig.ravel()))
                yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), pa.array(n.astype(np.int64)), pa.array(k1.view(np.int64)), pa.array(k2.view(np.int64)), lists], ["doc_id", "n", "k1", "k2", "sig"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(K.tidy(run), "doc_id long, n long, k1 long, k2 long, sig array<smallint>")


def bucket_keys(sig):
    """The keys of one signature: part, left-out place and the other components of the part, packed without collisions."""
    keys = []
    for p in range(PARTS):
        for out in range(SIZE):
            key = F.lit(p * SIZE + out).cast("long")
            for j in range(SIZE):
                if j != out:
                    key = F.shiftleft(key, BITS).bitwiseOR(sig[p * SIZE + j].cast("long").bitwiseAND(F.lit((1 << BITS) - 1)))
            keys.append(key)
    return F.array(*keys)


def distance(a, b):
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x != y).cast("int")), F.lit(0), lambda s, x: s + x)


def size_fits(a, b, percent: int):
    return (100 * F.least(a, b) >= percent * F.greatest(a, b))


def chosen(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """id and text of the documents named in ids."""
    ids = F.broadcast(ids) if small_enough(ids) else ids
    return docs.select(F.col("doc_id").cast("long").alias("id"), "text").join(ids, "id", "left_semi")


def full_sets(docs: DataFrame, ids: DataFrame, width: int) -> DataFrame:
    """rep and the whole sorted shingle set of each document named in ids."""

    def run(batches):
        for batch in batches:
            for part in K.slices(batch, "text", 1 << 20):
                sets, at = K.shingle_sets(*K.text_buffer(part.column("text")), width)
                yield pa.RecordBatch.from_arrays([part.column("id"), pa.ListArray.from_arrays(pa.array(at.astype(np.int32)), pa.array(sets.view(np.int64)))], ["rep", "set"])

    return chosen(docs, ids).mapInArrow(K.tidy(run), "rep long, set array<long>").dropDuplicates(["rep"])


def least_hashes(sets: DataFrame) -> DataFrame:
    """rep and the LOW least shingle hashes, 32 bits of them."""
    return sets.select("rep", F.transform(F.slice("set", 1, LOW), lambda x: F.shiftright(x, 32).cast("int")).alias("low"))


def possible(low: list[np.ndarray], n: np.ndarray, i: int, js: np.ndarray, percent: int) -> np.ndarray:
    """Whether set i can be as similar as asked to the sets js.

    Up to the lesser of two sets' last known hashes all members are known. What is common there, and the lesser
    of the two rests, bounds what is common in all. Hash ties only raise the bound, so no link is lost.
    """
    x = low[i].view(np.uint32)
    flat, size = np.concatenate([low[j] for j in js]).view(np.uint32), np.array([len(low[j]) for j in js])
    first = np.cumsum(size) - size
    ends = np.where(n[js] > LOW, flat[first + size - 1], np.uint32(0xFFFFFFFF))
    limit = np.minimum(x[-1] if n[i] > LOW else np.uint32(0xFFFFFFFF), ends)
    inside = flat <= np.repeat(limit, size)
    same = np.add.reduceat(np.isin(flat, x) & inside, first, dtype=np.int64)
    mine = np.searchsorted(x, limit, side="right")
    theirs = np.add.reduceat(inside, first, dtype=np.int64)
    most = np.minimum(same + np.minimum(n[i] - mine, n[js] - theirs), np.minimum(n[i], n[js]))
    return 100 * most >= percent * (n[i] + n[js] - most)


def met(a: np.ndarray, b: np.ndarray, slot: int) -> np.ndarray:
    """[a, b] whether two signatures are within FAR and this bucket is the first that they share."""
    differ = np.stack([(a[:, None, p * SIZE : (p + 1) * SIZE] != b[None, :, p * SIZE : (p + 1) * SIZE]).sum(2, dtype=np.int8) for p in range(PARTS)], 2)
    part, out = divmod(slot, SIZE)
    first = ~(differ[:, :, :part] <= ERRORS).any(2) & ((differ[:, :, part] == ERRORS) | (out == 0))
    return first & (differ.sum(2) <= FAR)


def pairs_apart(rows: DataFrame, percent: int) -> DataFrame:
    """Possible links between members of a bucket that are in different components.

    rows: key, rep, component, n, sig, low. A bucket of more than BLOCK members is dealt over tasks by
    pairs of blocks, each member going to as many tasks as there are blocks.
    """
    size = rows.groupBy("key").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks"))
    dealt = rows.join(size, "key").withColumn("own", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).withColumn("bi", F.least("own", "other")).withColumn("bj", F.greatest("own", "other"))
    by = ("key", "bi", "bj")
    dealt = dealt.select(*by, "own", "rep", "component", "n", "sig", "low").repartition(*by).sortWithinPartitions(*by)

    def run(batches):
        for batch in K.whole_groups(batches, by, 2048):
            col = {c: batch.column(c).to_numpy(zero_copy_only=False) for c in ("key", "bi", "bj", "own", "rep", "component", "n")}
            sig = batch.column("sig").flatten().to_numpy(zero_copy_only=False).reshape(-1, PARTS * SIZE)
            low = [np.asarray(x) for x in batch.column("low").to_numpy(zero_copy_only=False)]
            edge = np.concatenate(([0], np.flatnonzero(K.borders(batch, by)) + 1, [batch.num_rows]))
            left, right = [], []
            for s, e in zip(edge[:-1].tolist(), edge[1:].tolist()):
                slot = int(col["key"][s]) >> (BITS * (SIZE - 1))
                for f in range(s, e, 128):
                    i = np.arange(f, min(f + 128, e))
                    ok = met(sig[i], sig[s:e], slot) & (col["component"][i][:, None] != col["component"][s:e]) & (col["rep"][i][:, None] < col["rep"][s:e])
                    ok &= 100 * np.minimum(col["n"][i][:, None], col["n"][s:e]) >= percent * np.maximum(col["n"][i][:, None], col["n"][s:e])
                    if col["bi"][s] != col["bj"][s]:
                        ok &= col["own"][i][:, None] != col["own"][s:e]
                    for k in np.flatnonzero(ok.any(1)):
                        js = s + np.flatnonzero(ok[k])
                        js = js[possible(low, col["n"], f + int(k), js, percent)]
                        left.append(np.full(len(js), col["rep"][f + k]))
                        right.append(col["rep"][js])
            if left:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(left)), pa.array(np.concatenate(right))], ["a", "b"])

    return dealt.mapInArrow(K.tidy(run), "a long, b long").distinct()


def confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose full sets are as similar as asked. One pair's two sets are in memory at a time."""
    one, two = sets.select(F.col("rep").alias("a"), F.col("set").alias("set_a")), sets.select(F.col("rep").alias("b"), F.col("set").alias("set_b"))
    both, total = F.size(F.array_intersect("set_a", "set_b")), F.size("set_a") + F.size("set_b")
    met = pairs.join(one, "a").join(two, "b").where(size_fits(F.size("set_a"), F.size("set_b"), percent)).withColumn("both", both)
    return met.where(100 * F.col("both") >= percent * (total - F.col("both"))).select("a", "b")


def near_duplicates(docs: DataFrame, width: int = 5, percent: int = PERCENT) -> DataFrame:
    """doc_id, n_shingles, component_id and kept for every row.

    Null and empty texts have no shingles and link with nothing. A null id belongs to no component and its
    row is kept. Rows that share an id are one document, linked where any of them is; all of its rows
    give the same component. An empty table gives no rows.
    """
    sketches = cut(sketch(docs, width), "sketch")
    live = sketches.where("n > 0 and doc_id is not null")
    reps = live.groupBy("k1", "k2", "n").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies"), F.first("sig").alias("sig"))
    reps = cut(reps, "reps")
    keyed = reps.select("rep", F.explode(bucket_keys(F.col("sig"))).alias("key"))
    centres = keyed.groupBy("key").agg(F.min("rep").alias("low"), F.max("rep").alias("high"), F.min_by("rep", F.xxhash64("rep", F.lit(3))).alias("some")).where("low < high")
    shared = cut(keyed.join(centres, "key"), "shared")
    info = reps.select("rep", "n", "sig")

    def plausible(pairs: DataFrame) -> DataFrame:
        a, b = info.select(F.col("rep").alias("a"), F.col("n").alias("na"), F.col("sig").alias("sa")), info.select(F.col("rep").alias("b"), F.col("n").alias("nb"), F.col("sig").alias("sb"))
        return pairs.join(a, "a").join(b, "b").where(size_fits(F.col("na"), F.col("nb"), percent) & (distance(F.col("sa"), F.col("sb")) <= FAR)).select("a", "b")

    spokes = shared.select(F.col("rep").alias("b"), F.explode(F.array_distinct(F.array("low", "high", "some"))).alias("a")).where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    tried = cut(plausible(spokes), "tried")
    sets = cut(full_sets(docs, tried.select(F.col("a").alias("id")).union(tried.select("b")).distinct(), width), "sets")
    links = cut(confirmed(tried, sets, percent), "links")
    drop_cut(sets)
    groups = components(links)
    # members of a bucket that are still apart
    placed = shared.select("key", "rep").join(groups.withColumnRenamed("node", "rep"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))
    mixed = placed.groupBy("key").agg(F.min("component").alias("c0"), F.max("component").alias("c1")).where("c0 < c1").select("key")
    apart = cut(placed.join(mixed, "key", "left_semi").join(info, "rep"), "apart")
    sets = cut(full_sets(docs, apart.select(F.col("rep").alias("id")).distinct(), width), "sets")
    more = cut(pairs_apart(apart.join(least_hashes(sets), "rep"), percent).join(tried, ["a", "b"], "left_anti"), "more")
    if more.take(1):
        extra = cut(confirmed(more, sets, percent), "links")
        groups = components(links.union(extra)) if extra.take(1) else groups
    drop_cut(shared)
    drop_cut(apart)
    drop_cut(sets)
    moved = reps.join(groups.withColumnRenamed("node", "rep"), "rep", "left").where("copies > 1 or component is not null").select("k1", "k2", "n", F.coalesce("component", "rep").alias("component"))
    out = sketches.select("doc_id", "n", "k1", "k2").join(moved, ["k1", "k2", "n"], "left").select("doc_id", F.col("n").alias("n_shingles"), F.when((F.col("n") > 0) & F.col("component").isNotNull(), F.least("component", "doc_id")).otherwise(F.col("doc_id")).alias("component_id"))
    return out.withColumn("component_id", F.when(F.col("doc_id").isNotNull(), F.col("component_id"))).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def drop_near_duplicates(docs: DataFrame, width: int = 5, percent: int = PERCENT) -> DataFrame:
    """docs with one document of each group: the one with the least id.

    Rows without an id, and empty texts, stay. Of rows that share an id and a text one stays; rows of a kept id
    whose texts differ all stay.
    """
    with temporary() as kept:
        judged = cut(near_duplicates(docs, width, percent), "judged")
        kept.append(judged)
    gone = judged.where("not kept").select(F.col("doc_id").alias("gone_id")).distinct()
    many = docs.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").limit(1).count()
    gone = F.broadcast(gone) if small_enough(gone) else gone
    out = docs.join(gone, docs["doc_id"].cast("long") == gone["gone_id"], "left_anti")
    return out.where("doc_id is null").unionByName(out.where("doc_id is not null").dropDuplicates(["doc_id", "text"])) if many else out
