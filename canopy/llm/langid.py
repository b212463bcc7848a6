"""Language identification by nearest centroid.

Texts become normalised TF-IDF vectors of hashed letter n-grams; each language has several centroids from
spherical k-means; the nearest centroid by cosine names the language, and a text much farther from it than
held-out labelled texts of that language and of its length are is rejected.
"""

from __future__ import annotations

import functools
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from canopy.llm import kernels as K
from canopy.llm.common import ship

UNKNOWN = "und"
LETTER = regex.compile(r"\p{L}")
#: Bounds of the labelled sample: rows of a language, rows in all (shared by the languages, two of each at least) and bytes of text.
FIT_PER_LANGUAGE = 400
FIT_ROWS = 6400
FIT_BYTES = 32 << 20
DIMS = 4096
ORDERS = (1, 2, 3)
CENTROIDS = 4
#: One labelled text of so many is held out to see how far from the centroids texts of a length are.
HOLD = 4
#: Letters at which a new class of lengths begins.
LENGTHS = (0, 48, 192, 768)
#: A text is rejected below this share of the low quantile of the held-out cosines of its language and length.
QUANTILE = 0.02
SLACK = 0.6


@dataclass
class Model:
    languages: list[str]
    idf: np.ndarray
    centroids: np.ndarray
    of: np.ndarray
    cuts: np.ndarray


@functools.cache
def letters() -> np.ndarray:
    """Whether each code point is a letter."""
    table = np.zeros(0x110000, dtype=bool)
    text = "".join(chr(c) for c in range(0x110000) if not 0xD800 <= c < 0xE000)
    codes = np.frombuffer(text.encode("utf-32-le"), np.uint32)
    for m in regex.finditer(r"\p{L}+", text):
        table[codes[m.start() : m.end()]] = True
    return table


def counts(texts: list[str]) -> np.ndarray:
    """n-gram counts by text. Runs of non-letters count as one blank, which also stands at both ends."""
    joined = "\x00".join(texts).lower()
    codes = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
    border = codes == 0
    if border.sum() != len(texts) - 1:  # a text holds NUL itself
        joined = "\x00".join(t.replace("\x00", " ") for t in texts).lower()
        codes = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
        border = codes == 0
    letter = letters()[codes]
    keep = letter | border
    keep[1:] |= letter[:-1]  # the first blank after a letter
    doc = np.cumsum(border)[keep]
    code = np.where(letter, codes, 32)[keep].astype(K.U)
    code = np.concatenate((np.full(1, 32, K.U), code, np.full(1, 32, K.U)))
    doc = np.concatenate((doc[:1], doc, doc[-1:])) if len(doc) else np.zeros(2, np.int64)
    out = np.zeros(len(texts) * DIMS)
    with np.errstate(over="ignore"):
        for n in ORDERS:
            if len(code) < n:
                continue
            gram = np.full(len(code) - n + 1, K.U(n))
            for k in range(n):
                gram = gram * K.U(1_000_003) + code[k : len(code) - n + 1 + k]
            at = (K.mix(gram) % K.U(DIMS)).astype(np.int64) + doc[n // 2 : n // 2 + len(gram)] * DIMS
            out += np.bincount(at, minlength=len(out))
    return out.reshape(len(texts), DIMS)


def unit(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)


def spherical_means(x: np.ndarray, k: int, rounds: int = 12) -> np.ndarray:
    """k-means by cosine; starts at rows far from those chosen before, so it is deterministic."""
    picked = [unit(x.mean(0, keepdims=True))[0]]
    for _ in range(min(k, len(x)) - 1):
        picked.append(x[np.argmin(np.max(x @ np.array(picked).T, axis=1))])
    centres = np.array(picked)
    for _ in range(rounds):
        near = np.argmax(x @ centres.T, axis=1)
        centres = np.array([unit(x[near == j].mean(0, keepdims=True))[0] if (near == j).any() else centres[j] for j in range(len(centres))])
    return centres


def sample(labelled: DataFrame, per_language: int) -> dict[str, list[str]]:
    """Texts with a letter by language: every labelled language has some, drawn by id hash, within the bounds of rows and bytes.

    Hashes and lengths are drawn first; only the chosen texts are collected.
    """
    spark = labelled.sparkSession
    rows = labelled.where(F.col("lang").isNotNull() & F.col("text").isNotNull()).where(F.col("text").rlike(r"\p{L}")).select("text", "lang", F.xxhash64("doc_id", F.lit(17)).alias("draw"), F.octet_length("text").alias("n"))
    tally = {r.lang: r["count"] for r in rows.groupBy("lang").count().collect()}
    if not tally:
        return {}
    most = min(per_language, max(2, FIT_ROWS // len(tally)))
    limits = []
    for lang, n in tally.items():  # a draw below the language's threshold; the margin makes a short sample unlikely
        p = min(1.0, 1.3 * most / n + 20 / n)
        limits.append((lang, int(-(2**63) + min(p * 2**64, 2**64 - 1))))
    near = rows.join(F.broadcast(spark.createDataFrame(limits, "lang string, top long")), "lang").where("draw <= top")
    budget = FIT_BYTES // len(tally)
    order = Window.partitionBy("lang").orderBy("draw", "n")
    # a text that alone is past the budget is left out, unless it is the language's shortest
    fit = near.withColumn("least", F.min("n").over(Window.partitionBy("lang"))).where((F.col("n") <= budget // 8) | (F.col("n") == F.col("least")))
    drawn = fit.withColumn("i", F.row_number().over(order)).withColumn("total", F.sum("n").over(order)).where((F.col("i") == 1) | ((F.col("i") <= most) & (F.col("total") <= budget)))
    out: dict[str, list[str]] = {}
    for r in sorted(drawn.select("lang", "draw", "text").collect()):
        out.setdefault(r.lang, []).append(r.text)
    return out


def length_class(n_letters: np.ndarray) -> np.ndarray:
    return np.searchsorted(np.array(LENGTHS), n_letters, side="right") - 1


def fit(labelled: DataFrame, per_language: int = FIT_PER_LANGUAGE) -> Model:
    """Fit on a bounded sample of labelled rows of every language.

    Centroids come from all of them. The cuts come from one text of HOLD, measured against centroids of the others; a
    class of lengths with fewer than five of those takes the cut of the next shorter class, the shortest no more than half of its least.
    """
    by = sample(labelled, per_language)
    if not by:
        return Model([], np.ones(DIMS), np.zeros((0, DIMS)), np.zeros(0, int), np.zeros((0, len(LENGTHS))))
    raw = {k: np.vstack([counts(v[i : i + 64]) for i in range(0, len(v), 64)]).astype(np.float32) for k, v in by.items()}
    n = sum(map(len, raw.values()))
    idf = np.log((1 + n) / (1 + sum((x > 0).sum(0) for x in raw.values()))) + 1
    centroids, of, cuts, languages = [], [], [], sorted(raw)
    for j, lang in enumerate(languages):
        x = unit(np.log1p(raw[lang]) * idf)
        c = spherical_means(x, CENTROIDS)
        centroids.append(c)
        of += [j] * len(c)
        held = np.arange(len(x)) % HOLD == HOLD - 1
        near = (x[held] @ spherical_means(x[~held], CENTROIDS).T).max(1) if held.any() else (x @ c.T).max(1)
        size = length_class(raw[lang][held if held.any() else slice(None)].sum(1) / len(ORDERS))
        row, last = [], 0.5 * float(near.min())
        for k in range(len(LENGTHS)):
            if (size == k).sum() >= 5:
                last = SLACK * float(np.quantile(near[size == k], QUANTILE))
            row.append(last)
        cuts.append(row)
    return Model(languages, idf, np.vstack(centroids), np.array(of), np.array(cuts))


def predict(texts: list[str | None], model: Model) -> tuple[list[str], list[float], list[bool]]:
    """Language, cosine and acceptance. Null texts and those without a letter are ``und``, 0 and rejected; of equally near centroids the first language by name wins."""
    langs, scores, taken = [UNKNOWN] * len(texts), [0.0] * len(texts), [False] * len(texts)
    rows = [i for i, t in enumerate(texts) if t is not None and LETTER.search(t)]
    for part in ([] if not model.languages else [rows[a : a + 64] for a in range(0, len(rows), 64)]):
        got = counts([texts[i] for i in part])
        size = length_class(got.sum(1) / len(ORDERS))
        near = unit(np.log1p(got) * model.idf) @ model.centroids.T
        for i, k, best, cosine in zip(part, size, near.argmax(1), near.max(1)):
            j = int(model.of[best])
            langs[i], scores[i], taken[i] = model.languages[j], float(min(1.0, max(0.0, cosine))), bool(cosine >= model.cuts[j][k])
    return langs, scores, taken


def classify(docs: DataFrame, model: Model, keep: list[str] = ()) -> DataFrame:
    """doc_id, lang_pred, score, accepted and the columns named in keep. Repeated rows are judged alike, by whole texts of any length; an empty table gives none."""
    ship(docs.sparkSession)
    kinds = {f.name: f.dataType.simpleString() for f in docs.schema.fields}
    extra = [c for c in keep if c not in ("doc_id", "text")]
    schema = f"doc_id {kinds['doc_id']}, lang_pred string, score double, accepted boolean" + "".join(f", `{c}` {kinds[c]}" for c in extra) + (f", text {kinds['text']}" if "text" in keep else "")
    names = ["doc_id", "lang_pred", "score", "accepted", *extra, *(["text"] if "text" in keep else [])]

    def run(batches):
        for batch in batches:
            for part in K.slices(batch, "text", 1 << 20):
                langs, scores, taken = predict(part.column("text").to_pylist(), model)
                cols = [part.column("doc_id"), pa.array(langs, pa.string()), pa.array(scores, pa.float64()), pa.array(taken, pa.bool_()), *(part.column(c) for c in extra)]
                yield pa.RecordBatch.from_arrays(cols + ([part.column("text")] if "text" in keep else []), names)

    return docs.select("doc_id", "text", *extra).mapInArrow(K.tidy(run), schema)
