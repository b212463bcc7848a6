"""Host-level quality rules: failures by host, shrunk by an empirical beta prior, joined back to documents."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.llm import kernels as K
from canopy.llm.common import cut, ship, small_enough, temporary

MIN_WORDS = 20
REPEAT_WINDOW = 8
REPEAT_PERCENT = 30
#: A host goes when its shrunk rate is so many standard deviations of the hosts' prior above the mean, and always above HOST_MOST.
HOST_DEVIATIONS = 3.0
HOST_MOST = 0.5
SALTS = 64
#: The characters that count as symbols.
SYMBOLS = b"#*$%&|<>"

IS_SYMBOL = np.zeros(256, dtype=bool)
IS_SYMBOL[list(SYMBOLS)] = True
MEASURES = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long"


def repeated(keys: np.ndarray) -> np.ndarray:
    """Whether each key stands twice or more."""
    _, back, count = np.unique(keys, return_inverse=True, return_counts=True)
    return count[back] > 1


def measure(raw: np.ndarray, offsets: np.ndarray) -> list[np.ndarray]:
    n = len(offsets) - 1
    sums = lambda flags: np.diff(np.concatenate(([0], np.cumsum(flags, dtype=np.int64)))[offsets])
    start, end, doc, code = K.words(raw, offsets)
    at = K.per_document(doc, n)
    chars = sums(~K.SPACE[raw] & ((raw & 0xC0) != 0x80))
    # lines with a word: those that hold a word's start
    breaks = np.unique(np.concatenate((offsets[:-1], np.flatnonzero(raw == 10) + 1)))
    breaks = breaks[breaks < len(raw)]
    line = np.unique(np.searchsorted(breaks, start, side="right") - 1)
    first = breaks[line]
    who = K.owner(offsets, first)
    stop = np.append(breaks, len(raw))[line + 1]
    stop = np.where((stop <= offsets[who + 1]) & (stop > first) & (raw[np.maximum(stop - 1, 0)] == 10), stop - 1, np.minimum(stop, offsets[who + 1]))
    salt = K.mix(np.arange(n).astype(K.U))
    lines = K.span_hash(K.prefix_hash(K.BYTE_CODE[raw]), first, stop) ^ salt[who]
    order = np.argsort(lines, kind="stable")
    again = np.zeros(len(lines), dtype=bool)
    again[order[1:]] = lines[order[1:]] == lines[order[:-1]]
    # windows of eight words
    where = np.arange(max(len(doc) - REPEAT_WINDOW + 1, 0))
    where = where[doc[where] == doc[where + REPEAT_WINDOW - 1]]
    hit = repeated(K.span_hash(K.prefix_hash(code), where, where + REPEAT_WINDOW) ^ salt[doc[where]]) if len(where) else np.zeros(0, bool)
    cover = np.zeros(len(doc) + 1, dtype=np.int64)
    np.add.at(cover, where[hit], 1)
    np.add.at(cover, where[hit] + REPEAT_WINDOW, -1)
    inside = np.concatenate(([0], np.cumsum(np.cumsum(cover[:-1]) > 0)))
    return [np.diff(at), chars, sums(IS_SYMBOL[raw]), np.bincount(who[again], minlength=n), inside[at[1:]] - inside[at[:-1]]]


def measures(docs: DataFrame) -> DataFrame:
    """doc_id, source and the five measures of every whole text. Null texts measure as empty."""
    ship(docs.sparkSession)

    def run(batches):
        for batch in batches:
            for part in K.slices(batch, "text"):
                got = measure(*K.text_buffer(part.column("text")))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("source"), *(pa.array(x.astype(np.int64)) for x in got)], ["doc_id", "source", *(c.split()[0] for c in MEASURES.split(", "))])

    return docs.select(F.col("doc_id").cast("long"), "source", "text").mapInArrow(run, f"doc_id long, source string, {MEASURES}")


@dataclass(frozen=True)
class Prior:
    """Beta(mean * weight, (1 - mean) * weight) over the failure rates of hosts."""

    mean: float
    weight: float

    @property
    def limit(self) -> float:
        return min(HOST_MOST, self.mean + HOST_DEVIATIONS * (self.mean * (1 - self.mean) / (self.weight + 1)) ** 0.5)


def host_prior(hosts: DataFrame) -> Prior:
    """The prior by moments: the mean over all documents, and the variance of the rates between hosts less what chance alone makes within them.

    weight = mean (1 - mean) / variance - 1, kept between 1 and 1,000; 1,000 where nothing is left of the variance.
    """
    n, f, squares, many = hosts.agg(F.sum("docs"), F.sum("fails"), F.sum(F.col("fails") * F.col("fails") / F.col("docs")), F.count("*")).first()
    if not n:
        return Prior(0.0, 1000.0)
    m = f / n
    v = squares / n - m * m - m * (1 - m) * many / n
    return Prior(m, min(1000.0, max(1.0, m * (1 - m) / v - 1)) if v > 1e-12 else 1000.0)


def host_key(c: str):
    """A null host is a host of its own, unlike any name."""
    return F.concat(F.when(F.col(c).isNull(), "-").otherwise("+"), F.coalesce(F.col(c), F.lit("")))


def host_rates(rows: DataFrame) -> DataFrame:
    """(key, docs, fails, host_rate, host_limit): each host's failure rate shrunk towards the prior, and the rate above which it goes."""
    hosts = rows.groupBy(host_key("source").alias("key")).agg(F.count("*").alias("docs"), F.sum(F.col("base_failed").cast("long")).alias("fails"))
    prior = host_prior(hosts)
    return hosts.withColumn("host_rate", (F.col("fails") + F.lit(prior.mean * prior.weight)) / (F.col("docs") + F.lit(prior.weight))).withColumn("host_limit", F.lit(prior.limit))


def judge(docs: DataFrame) -> DataFrame:
    """Each document's measures and verdict, with its host's shrunk failure rate and the limit for it.

    A document goes if its base rule fails or its host's rate exceeds the limit, which is drawn from the hosts' own
    distribution. A null host is a host of its own. Null texts measure as empty; repeated rows are judged alike and
    each counts for its host; an empty table gives no rows. Rates are broadcast while the hosts are few (counted), else joined on
    host and salt so that a host with a third of all rows is dealt over many tasks.
    """
    base = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > REPEAT_PERCENT * F.col("n_words"))
    with temporary() as kept:
        rows = cut(measures(docs).withColumn("base_failed", base), "rules")
        hosts = cut(host_rates(rows).select("key", "host_rate", "host_limit"), "hosts")
        kept += [rows, hosts]
    keyed = rows.withColumn("key", host_key("source"))
    if small_enough(hosts):
        joined = keyed.join(F.broadcast(hosts), "key")
    else:
        spread = hosts.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        joined = keyed.withColumn("salt", F.pmod(F.xxhash64("doc_id", "n_words", "word_chars"), F.lit(SALTS)).cast("int")).join(spread, ["key", "salt"])
    kept_if = ~F.col("base_failed") & (F.col("host_rate") <= F.col("host_limit"))
    return joined.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", kept_if.alias("kept"), "host_rate", "host_limit")
