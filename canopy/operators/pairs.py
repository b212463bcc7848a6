"""Unary parent/child pairs: the arc graph, two-colourings of the letters, and compression."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.model import letter, settle, unsettle
from canopy.operators.scan import beside

#: Hashed colourings tried at once, each both ways round.
TRIES = 32
UP, DOWN = "U", "D"


def pair_graph(nodes: DataFrame, block: int | None = None) -> DataFrame:
    """(a, b, occ): how often unary b stands right below unary a, a and b different."""
    unary = nodes.select("tree_id", "pre", F.col("sym").alias("a"), "rank")
    below = beside(unary, {}, {"b": F.col("a"), "rank_b": F.col("rank")}, block)
    return below.where("rank = 1 and rank_b = 1 and a <> b").groupBy("a", "b").agg(F.count("*").alias("occ"))


def neighbour_lists(pairs: DataFrame) -> DataFrame:
    """(sym, below, above): for each letter the letters right under it and right over it with their counts, as sorted arrays; a letter's lists are as long as it has different neighbours."""
    down = pairs.groupBy(F.col("a").alias("sym")).agg(F.array_sort(F.collect_list(F.struct(F.col("b").alias("sym"), "occ"))).alias("below"))
    up = pairs.groupBy(F.col("b").alias("sym")).agg(F.array_sort(F.collect_list(F.struct(F.col("a").alias("sym"), "occ"))).alias("above"))
    none = F.array().cast("array<struct<sym:bigint,occ:bigint>>")
    return down.join(up, "sym", "full").select("sym", F.coalesce("below", none).alias("below"), F.coalesce("above", none).alias("above"))


def turned(side: dict[int, str], arcs: list[tuple[int, int, int]]) -> dict[int, str]:
    """Sides swapped if more weight runs from down to up."""
    ud = sum(w for a, b, w in arcs if side[a] == UP and side[b] == DOWN)
    du = sum(w for a, b, w in arcs if side[a] == DOWN and side[b] == UP)
    return {k: (DOWN if v == UP else UP) for k, v in side.items()} if du > ud else side


def greedy(arcs: list[tuple[int, int, int]]) -> dict[int, str]:
    """Letters in order, each to the side that cuts more of the weight to letters placed before; ties go up."""
    weight: dict[int, dict[int, int]] = {}
    for a, b, w in arcs:
        for x, y in ((a, b), (b, a)):
            weight.setdefault(x, {})[y] = weight.setdefault(x, {}).get(y, 0) + w
    side: dict[int, str] = {}
    for x in sorted(weight):
        to = {UP: 0, DOWN: 0}
        for y, w in weight[x].items():
            if y in side:
                to[side[y]] += w
        side[x] = UP if to[DOWN] >= to[UP] else DOWN
    return turned(side, arcs)


def exhaustive(arcs: list[tuple[int, int, int]]) -> dict[int, str]:
    """The best directed cut, for at most 16 letters."""
    letters = sorted({x for a, b, _ in arcs for x in (a, b)})
    if len(letters) > 16:
        raise ValueError("too many letters to try all colourings")
    at = {x: i for i, x in enumerate(letters)}
    best = max(range(1 << len(letters)), key=lambda m: sum(w for a, b, w in arcs if m >> at[a] & 1 and not m >> at[b] & 1)) if letters else 0
    return {x: UP if best >> at[x] & 1 else DOWN for x in letters}


def letters_of(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.col("a").alias("sym")).union(pairs.select("b")).distinct()


def by_hash(pairs: DataFrame, seed: int) -> DataFrame:
    """Each letter's side from its id and a seed."""
    return letters_of(pairs).select("sym", F.when(F.pmod(F.xxhash64("sym", F.lit(seed)), F.lit(2)) == 0, UP).otherwise(DOWN).alias("side"))


def covered(pairs: DataFrame, sides: DataFrame) -> tuple[int, int, int]:
    """Weight of all arcs, of those from up to down, and of those from down to up."""
    a, b = sides.select(F.col("sym").alias("a"), F.col("side").alias("sa")), sides.select(F.col("sym").alias("b"), F.col("side").alias("sb"))
    w = lambda x, y: F.sum(F.when((F.col("sa") == x) & (F.col("sb") == y), F.col("occ")).otherwise(0))
    got = pairs.join(a, "a").join(b, "b").agg(F.sum("occ"), w(UP, DOWN), w(DOWN, UP)).first()
    return tuple(int(x or 0) for x in got)


def random_sides(pairs: DataFrame, seed: int = 0, tries: int = 4) -> DataFrame:
    best, found = -1, None
    for s in range(seed, seed + tries):
        sides = by_hash(pairs, s)
        _, ud, du = covered(pairs, sides)
        if max(ud, du) > best:
            best = max(ud, du)
            found = sides if ud >= du else sides.withColumn("side", F.when(F.col("side") == UP, DOWN).otherwise(UP))
    return found


def parity(sym, seed: int):
    """Parity of the bits of a letter's hash that the seed names."""
    return F.bit_count(short_hash(sym).bitwiseAND(F.lit(seed))) % 2


def short_hash(sym):
    return F.xxhash64(sym, F.lit(11)).bitwiseAND(F.lit((1 << 32) - 1))


@dataclass(frozen=True)
class Colouring:
    """A side for every letter by a rule: bit ``bit`` of its hash, or the parity of its hash under ``seed``; turned swaps the sides."""

    bit: int | None
    seed: int = 0
    turned: bool = False

    def up(self, sym):
        """Whether a letter is on the upper side."""
        is_up = (F.call_function("shiftrightunsigned", F.xxhash64(sym, F.lit(5)), F.lit(self.bit)).bitwiseAND(F.lit(1)) == 1) if self.bit is not None else (parity(sym, self.seed) == 0)
        return ~is_up if self.turned else is_up

    def sides(self, letters: DataFrame) -> DataFrame:
        return letters.select("sym", F.when(self.up(F.col("sym")), UP).otherwise(DOWN).alias("side"))


def hashed_colouring(pairs: DataFrame) -> Colouring | None:
    """The colouring that covers most of TRIES hashed ones, each both ways round; in one aggregate, whatever the number of letters.

    None without arcs. In the unlikely case that even the best covers less than a quarter, the linear one, which never does.
    """
    a, b = F.xxhash64("a", F.lit(5)), F.xxhash64("b", F.lit(5))
    near = pairs.select("occ", a.bitwiseAND(F.bitwise_not(b)).alias("ud"), b.bitwiseAND(F.bitwise_not(a)).alias("du"))
    share = lambda c, k: F.sum(F.col("occ") * F.call_function("shiftrightunsigned", F.col(c), F.lit(k)).bitwiseAND(F.lit(1)))
    got = near.agg(F.sum("occ"), *(share(c, k) for k in range(TRIES) for c in ("ud", "du"))).first()
    if not got[0]:
        return None
    best = max(range(2 * TRIES), key=lambda i: (got[1 + i], -i))
    return Colouring(best // 2, turned=best % 2 == 1) if 4 * got[1 + best] >= got[0] else linear_colouring(pairs)


def linear_colouring(pairs: DataFrame) -> Colouring:
    """Sides as parity of (seed and hashed id), the seed's bits fixed from low to high by what they cut.

    A pair is decided by the highest bit in which its hashed ids differ, so every pair is counted in
    one round; each round keeps at least half of its weight. 32 small aggregates, whatever the letters.
    """
    arcs = settle(pairs.select("occ", short_hash("a").bitwiseXOR(short_hash("b")).alias("x")).where("x <> 0").groupBy("x").agg(F.sum("occ").alias("occ")).withColumn("top", F.length(F.bin("x")) - 1))
    seed = 0
    for t in range(32):
        odd = F.bit_count(F.col("x").bitwiseAND(F.lit(seed))) % 2 == 1
        got = arcs.where(F.col("top") == t).agg(F.sum(F.when(odd, F.col("occ")).otherwise(0)), F.sum(F.when(~odd, F.col("occ")).otherwise(0))).first()
        if (got[1] or 0) > (got[0] or 0):
            seed |= 1 << t
    unsettle(arcs)
    flat = Colouring(None, seed)
    _, ud, du = covered(pairs, flat.sides(letters_of(pairs)))
    return Colouring(None, seed, turned=du > ud)


METHODS = ("auto", "hashed", "linear", "random", "greedy", "exact")


def choose(pairs: DataFrame, method: str = "auto") -> DataFrame:
    """(sym, side). auto is hashed at every size. greedy and exact take all arcs to the driver, and are meant for alphabets that fit there."""
    spark = pairs.sparkSession
    if method in ("auto", "hashed", "linear"):
        got = linear_colouring(pairs) if method == "linear" else hashed_colouring(pairs)
        return (got or Colouring(0)).sides(letters_of(pairs))
    if method == "random":
        return random_sides(pairs)
    arcs = [tuple(map(int, r)) for r in pairs.select("a", "b", "occ").collect()]
    side = exhaustive(arcs) if method == "exact" else greedy(arcs)
    return spark.createDataFrame(sorted(side.items()), "sym long, side string")


def merge_pairs(nodes: DataFrame, up, block: int | None = None) -> DataFrame:
    """Every up letter right above a down letter is one node with it. ``up``: a boolean column, null for letters of neither side.

    There ``low`` holds the lower letter and ``_l`` its other columns; else low is null.
    """
    unary = F.col("rank") == 1
    coloured = nodes.withColumn("_up", F.when(unary, up))
    rest = F.struct(*(F.col(c) for c in nodes.columns if c not in ("tree_id", "pre", "parent", "slot", "sym", "rank")), F.col("rank"))
    near = beside(coloured, {"_pu": F.col("_up")}, {"_nu": F.col("_up"), "_ns": F.col("sym"), "_nl": rest}, block)
    bottom = F.coalesce(~F.col("_up") & F.col("_pu"), F.lit(False))
    top = F.coalesce(F.col("_up") & ~F.col("_nu"), F.lit(False))
    marked = near.withColumn("_gone", bottom).withColumn("_a", F.when(top, F.col("sym"))).withColumn("low", F.when(top, F.col("_ns"))).withColumn("_l", F.when(top, F.col("_nl"))).drop("_up", "_pu", "_nu", "_ns", "_nl")
    kept = beside(marked, {"_bg": F.col("_gone"), "_bp": F.col("parent")}, {}, block).where("not _gone")
    out = kept.withColumn("parent", F.when(F.col("_bg"), F.col("_bp")).otherwise(F.col("parent"))).drop("_gone", "_bg", "_bp")
    return out.withColumn("sym", F.when(F.col("low").isNotNull(), letter(F.lit("pair"), F.col("sym"), F.col("low"))).otherwise(F.col("sym")))


def compress_pairs(nodes: DataFrame, sides: DataFrame | None = None, broadcast: bool = True, pair: tuple[int, int] | None = None, block: int | None = None):
    """(nodes, new letters (sym, a, b)): every up letter right above a down letter merges with it; with ``pair`` only that one pair of different letters."""
    if pair is not None:
        if pair[0] == pair[1]:
            raise ValueError("equal letters overlap: use runs")
        coloured, up = nodes, F.when(F.col("sym") == pair[0], True).when(F.col("sym") == pair[1], False)
    else:
        sides = F.broadcast(sides) if broadcast else sides
        coloured = nodes.join(sides, "sym", "left")
        up = F.when(F.col("side") == UP, True).when(F.col("side") == DOWN, False)
    out = merge_pairs(coloured, up, block)
    keys = out.where("low is not null").select("sym", F.col("_a").alias("a"), F.col("low").alias("b")).distinct()
    return out.select(*nodes.columns), keys
