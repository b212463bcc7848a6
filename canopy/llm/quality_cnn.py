"""Quality classifier: a byte-level convolutional network in numpy.

Filters over windows of bytes run along overlapping chunks that cover the whole document. A filter
holds one weight for each byte value at each place of its window, so its response is a sum of
look-ups. Each filter's greatest response in a chunk is kept; a document is described by the mean and the
greatest of its chunks' values, and one logistic unit makes a probability of them. A blank symbol
of weight zero follows every document, so a score depends on nothing but the text.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.llm import kernels as K
from canopy.llm.common import ship

FILTERS = 16
WIDTH = 4
CHUNK = 512
STRIDE = 448
#: The symbol after a document's end; its weights stay zero.
BLANK = 256
#: Labelled rows that a fit may use, and bytes of text of them.
FIT_ROWS = 2500
FIT_BYTES = 16 << 20
EPOCHS = 14
SEED = 5
#: Chunks whose responses are held at once.
BLOCK = 256


@dataclass
class Model:
    filters: np.ndarray
    weights: np.ndarray
    bias: float


def symbols(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The bytes with WIDTH - 1 blanks after each document, and offsets into them (a document's blanks count as its own)."""
    n = len(offsets) - 1
    size = np.diff(offsets)
    at = np.concatenate(([0], np.cumsum(size + WIDTH - 1)))
    out = np.full(at[-1] + WIDTH, BLANK, np.int16)
    out[np.arange(len(raw)) + np.repeat(np.arange(n) * (WIDTH - 1), size)] = raw
    return out, at


def chunks(size: np.ndarray, first: np.ndarray):
    """Start, end and document of the chunks; the last of a document ends at its end; empty documents have none."""
    many = np.where(size > 0, 1 + np.maximum(0, -((CHUNK - size) // STRIDE)), 0)
    doc = np.repeat(np.arange(len(size)), many)
    step = STRIDE * (np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many))
    return first[doc] + step, first[doc] + np.minimum(step + CHUNK, size[doc]), doc


def greatest(model: Model, code: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """[chunks, filters]: the greatest response in each chunk, at least zero."""
    top = np.zeros((len(start), FILTERS), np.float32)
    for f in range(0, len(start), BLOCK):
        a, b = start[f : f + BLOCK], end[f : f + BLOCK]
        lo, hi = int(a[0]), int(b[-1])
        got = model.filters[0][code[lo : hi + 1]]
        for j in range(1, WIDTH):
            got += model.filters[j][code[lo + j : hi + 1 + j]]
        top[f : f + BLOCK] = np.maximum.reduceat(got, np.stack([a, b], 1).ravel() - lo, axis=0)[::2]
    return np.maximum(top, 0)


def described(top: np.ndarray, doc: np.ndarray, n: int) -> np.ndarray:
    """[documents, 2 x filters]: mean and greatest of the chunks' values, zero without a chunk."""
    out = np.zeros((n, 2 * FILTERS), np.float32)
    if len(doc):
        first = np.flatnonzero(np.append(True, doc[1:] != doc[:-1]))
        out[doc[first], :FILTERS] = np.add.reduceat(top, first) / np.diff(np.append(first, len(doc)))[:, None]
        out[doc[first], FILTERS:] = np.maximum.reduceat(top, first)
    return out


def probability(model: Model, raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    code, at = symbols(raw, offsets)
    start, end, doc = chunks(np.diff(offsets), at[:-1])
    x = described(greatest(model, code, start, end), doc, len(offsets) - 1).astype(np.float64)
    z = (x * model.weights).sum(1) + model.bias  # row by row: a matrix product may round by the batch's shape
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def train(texts: list[str], labels: np.ndarray, epochs: int = EPOCHS, rate: float = 0.02) -> Model:
    """Adam on the cross entropy, with classes weighted to equal halves; the bias is refitted to the true share at the end."""
    rng = np.random.default_rng(SEED)
    model = Model(rng.normal(0, 0.3, (WIDTH, BLANK + 1, FILTERS)).astype(np.float32), rng.normal(0, 0.1, 2 * FILTERS).astype(np.float32), 0.0)
    model.filters[:, BLANK] = 0
    raws = [np.frombuffer(t.encode("utf-8", "surrogatepass"), np.uint8) for t in texts]
    share = float(np.clip(labels.mean(), 0.01, 0.99))
    cost = np.where(labels == 1, 0.5 / share, 0.5 / (1 - share))
    state = [np.zeros_like(model.filters), np.zeros_like(model.filters), np.zeros(2 * FILTERS + 1), np.zeros(2 * FILTERS + 1)]
    each = np.arange(FILTERS)
    step = 0
    for _ in range(epochs):
        order = rng.permutation(len(raws))
        for a in range(0, len(order), 32):
            pick = order[a : a + 32]
            size = np.array([len(raws[i]) for i in pick])
            code, at = symbols(np.concatenate([raws[i] for i in pick]), np.concatenate(([0], np.cumsum(size))))
            start, end, doc = chunks(size, at[:-1])
            top, where = np.zeros((len(start), FILTERS), np.float32), np.zeros((len(start), FILTERS), np.int64)
            for f in range(0, len(start), BLOCK):
                lo, hi = int(start[f]), int(end[min(f + BLOCK, len(end)) - 1])
                got = sum(model.filters[j][code[lo + j : hi + j]] for j in range(WIDTH))
                for k in range(f, min(f + BLOCK, len(start))):
                    part = got[start[k] - lo : end[k] - lo]
                    where[k] = part.argmax(0)
                    top[k] = part[where[k], each]
                    where[k] += start[k]
            top = np.maximum(top, 0)
            x = described(top, doc, len(pick))
            z = x @ model.weights + model.bias
            d = (cost[pick] * (1 / (1 + np.exp(-np.clip(z, -30, 30))) - labels[pick]) / len(pick)).astype(np.float32)
            grad = np.zeros_like(model.filters)
            if len(doc):
                count = np.bincount(doc, minlength=len(pick))[doc][:, None]
                best = top >= x[doc, FILTERS:]
                g = d[doc][:, None] * (model.weights[:FILTERS] / count + model.weights[FILTERS:] * best) * (top > 0)
                f = np.broadcast_to(each, where.shape)
                for j in range(WIDTH):
                    np.add.at(grad[j], (code[where + j], f), g)
                grad[:, BLANK] = 0
            flat = np.append(x.T @ d + 1e-4 * model.weights, d.sum())
            step += 1
            fix = np.sqrt(1 - 0.999**step) / (1 - 0.9**step)
            for k, gr in ((0, grad), (2, flat)):
                state[k] = 0.9 * state[k] + 0.1 * gr
                state[k + 1] = 0.999 * state[k + 1] + 0.001 * gr**2
            model.filters -= (rate * fix * state[0] / (np.sqrt(state[1]) + 1e-8)).astype(np.float32)
            move = rate * fix * state[2] / (np.sqrt(state[3]) + 1e-8)
            model.weights -= move[:-1].astype(np.float32)
            model.bias -= float(move[-1])
    model.bias += float(np.log(share / (1 - share)))
    return model


def sample(docs: DataFrame, labels: DataFrame | None = None) -> list[tuple[str, int]]:
    """(text, label) of at most FIT_ROWS rows, drawn by id hash, of at most FIT_BYTES of whole texts in all.

    Without labels (doc_id, label) docs has a label column itself. Ids and lengths are drawn first, and no text is shuffled; only the texts that
    fit are collected, one a doc_id. A text that doesn't fit is left out alone, and the shortest drawn text of each label comes first, so that both labels are there.
    """
    named = docs if labels is None else docs.select("doc_id", "text")
    sized = named.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.octet_length("text"), F.lit(0)).alias("n"), *(["label"] if labels is None else []))
    rows = (sized if labels is None else sized.join(labels.select(F.col("doc_id").cast("long").alias("doc_id"), "label"), "doc_id")).where("label is not null and doc_id is not null")
    rows = rows.select("doc_id", "n", F.col("label").cast("int").alias("label"), F.xxhash64("doc_id", F.lit(29)).alias("draw"))
    p = min(1.0, (1.3 * FIT_ROWS + 20) / max(rows.count(), 1))
    known = rows.where((F.col("draw") <= int(-(2**63) + min(p * 2**64, 2**64 - 1))) & (F.col("n") <= FIT_BYTES)).orderBy("draw", "n", "label").limit(2 * FIT_ROWS).collect()
    least = {}
    for r in known:
        if r.label not in least or r.n < least[r.label].n:
            least[r.label] = r
    chosen, total = {}, 0
    for r in [*least.values(), *known]:
        if r.doc_id not in chosen and len(chosen) < FIT_ROWS and total + r.n <= FIT_BYTES:
            chosen[r.doc_id] = r
            total += r.n
    if not chosen:
        return []
    wanted = docs.sparkSession.createDataFrame([(int(r.doc_id), int(r.n)) for r in chosen.values()], "doc_id long, n long")
    texts = named.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n"))
    got = texts.join(F.broadcast(wanted), ["doc_id", "n"]).groupBy("doc_id").agg(F.min("text").alias("text")).collect()
    return [(r.text or "", chosen[r.doc_id].label) for r in sorted(got, key=lambda r: chosen[r.doc_id].draw)]


def fit(docs: DataFrame, labels: DataFrame | None = None) -> Model:
    """Fit on a bounded sample of labelled rows: docs (doc_id, text) and labels (doc_id, label), or docs with a label column.

    Without rows of both labels every text scores the share of label 1 (one half without rows).
    """
    got = sample(docs, labels)
    y = np.array([label for _, label in got], dtype=np.float32)
    if len(set(y.tolist())) < 2:
        share = float(np.clip(y.mean(), 0.01, 0.99)) if len(y) else 0.5
        return Model(np.zeros((WIDTH, BLANK + 1, FILTERS), np.float32), np.zeros(2 * FILTERS, np.float32), float(np.log(share / (1 - share))))
    return train([t for t, _ in got], y)


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, score and predicted of every whole text.

    Null counts as empty; equal texts score equal wherever they stand, repeated rows too; other columns are
    ignored; an empty table gives no rows.
    """
    ship(docs.sparkSession)
    spread = docs.sparkSession.sparkContext.broadcast(model)  # about 66 kB whatever the input

    def run(batches):
        model = spread.value
        for batch in batches:
            for part in K.slices(batch, "text", 1 << 20):
                p = probability(model, *K.text_buffer(part.column("text")))
                yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), pa.array(p, pa.float64()), pa.array((p >= 0.5).astype(np.int32), pa.int32())], ["doc_id", "score", "predicted"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, score double, predicted int")
