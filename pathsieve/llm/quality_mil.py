"""Quality classifier: gated attention over a document's passages, learned from document labels."""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathsieve.llm import kernels as K
from pathsieve.llm.language_id import bounded_sample

PASSAGE_WORDS = 32
#: Bound of the labelled sample and shape of the network.
SAMPLE_PER_LABEL = 1500
HIDDEN, ATTENTION, EPOCHS, RATE, DECAY, THRESHOLD = 24, 16, 40, 0.01, 0.01, 0.3

# Classes of bytes: lower and upper case, digits, white space, non-ASCII, and some marks on their own.
_CLASS = np.full(256, 9, np.int64)
_CLASS[97:123] = 0
_CLASS[65:91] = 1
_CLASS[48:58] = 2
_CLASS[[32, 9]] = 3
_CLASS[[10, 11, 12, 13]] = 4
_CLASS[128:] = 5
_CLASS[[ord("."), ord(",")]] = 6
_CLASS[[ord("!"), ord("?")]] = 7
_CLASS[[ord("|"), ord("<"), ord(">")]] = 8
_CLASS[[ord("*"), ord("#"), ord("$"), ord("%"), ord("&"), ord("@"), ord("~")]] = 10
_CLASSES = 11
_BUCKETS = 64
WIDTH = _CLASSES**2 + _BUCKETS + 3


def passages(column: pa.Array):
    """For each chunk of rows: its range, a matrix of passage encodings, row offsets into it.

    A passage has PASSAGE_WORDS words, the last of a text what is left. Its encoding holds shares of pairs of neighbouring
    byte classes, shares of hashed words, mean word length, share of distinct words and fill.
    """
    data, offsets = K.flat(column)
    for i, j in K.chunks(offsets):
        b, at = data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        starts, ends, rows = K.words(b, at, K.NOT_SPACE)
        count = -(-np.diff(rows) // PASSAGE_WORDS)
        first = np.concatenate([[0], np.cumsum(count)])
        n = int(first[-1])
        out = np.zeros((n, WIDTH), np.float32)
        if n:
            place = np.arange(n) - np.repeat(first[:-1], count)
            head = np.repeat(rows[:-1], count) + place * PASSAGE_WORDS
            tail = np.minimum(head + PASSAGE_WORDS, np.repeat(rows[1:], count))
            of_word = np.repeat(np.arange(n), tail - head)
            row = np.repeat(np.arange(j - i), count)
            bounds = np.where(place == 0, at[row], starts[head])
            within = np.ones(len(b), bool)
            within[np.maximum(at[1:] - 1, 0)] = False
            within[: at[row[0]]] = False
            spot = np.flatnonzero(within)
            of_byte = np.searchsorted(bounds, spot, side="right") - 1
            whole = spot < at[row[of_byte] + 1]
            spot, of_byte = spot[whole], of_byte[whole]
            pairs = _CLASS[b[spot]] * _CLASSES + _CLASS[b[spot + 1]]
            out[:, : _CLASSES**2] = np.bincount(of_byte * _CLASSES**2 + pairs, minlength=n * _CLASSES**2)[: n * _CLASSES**2].reshape(n, -1)
            out[:, : _CLASSES**2] /= np.maximum(out[:, : _CLASSES**2].sum(axis=1, keepdims=True), 1)
            h = K.spans_hash(K.LOWER[b], starts, ends)
            size = tail - head
            word = (h % K.U64(_BUCKETS)).astype(np.int64)
            out[:, _CLASSES**2 : -3] = np.bincount(of_word * _BUCKETS + word, minlength=n * _BUCKETS).reshape(n, -1) / size[:, None]
            out[:, -3] = np.bincount(of_word, ends - starts, minlength=n) / size / 10
            fold = (h ^ (of_word.astype(K.U64) * K.U64(0x9E3779B97F4A7C15)))
            _, one = np.unique(fold, return_index=True)
            out[:, -2] = np.bincount(of_word[one], minlength=n) / size
            out[:, -1] = size / PASSAGE_WORDS
        yield i, j, out, first


class Model(NamedTuple):
    mean: np.ndarray
    scale: np.ndarray
    params: dict[str, np.ndarray]
    prior: float


def _sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def _forward(x, rows, p):
    """Encodings, gates, attention and score of each text; rows with no passage aren't allowed here."""
    h = np.tanh(x @ p["encode"] + p["shift"])
    t, s = np.tanh(h @ p["v"]), _sigmoid(h @ p["u"])
    e = (t * s) @ p["w"]
    size = np.diff(rows)
    a = np.exp(e - np.repeat(np.maximum.reduceat(e, rows[:-1]), size))
    a /= np.repeat(np.add.reduceat(a, rows[:-1]), size)
    z = np.add.reduceat(a[:, None] * h, rows[:-1], axis=0)
    return h, t, s, a, z, _sigmoid(z @ p["out"] + p["bias"])


def fit(x: np.ndarray, rows: np.ndarray, y: np.ndarray, seed: int = 5) -> Model:
    """Gradient descent with adaptive moments on the log loss of document labels; all texts have passages."""
    mean, scale = x.mean(axis=0), x.std(axis=0) + 0.02
    x = ((x - mean) / scale).clip(-8, 8)
    rng = np.random.default_rng(seed)
    draw = lambda a, b: rng.normal(0, 1 / np.sqrt(a), (a, b)).astype(np.float32)
    p = {"encode": draw(x.shape[1], HIDDEN), "shift": np.zeros(HIDDEN, np.float32), "v": draw(HIDDEN, ATTENTION), "u": draw(HIDDEN, ATTENTION), "w": draw(ATTENTION, 1)[:, 0], "out": draw(HIDDEN, 1)[:, 0], "bias": np.zeros(1, np.float32)}
    m, q = {k: np.zeros_like(v) for k, v in p.items()}, {k: np.zeros_like(v) for k, v in p.items()}
    step, n = 0, len(y)
    for _ in range(EPOCHS):
        order = rng.permutation(n)
        for lo in range(0, n, 64):
            docs = np.sort(order[lo : lo + 64])
            size = np.diff(rows)[docs]
            part, at = x[K.ragged(rows[docs], size)], np.concatenate([[0], np.cumsum(size)])
            h, t, s, a, z, out = _forward(part, at, p)
            d = ((out - y[docs]) / len(docs)).astype(np.float32)
            dz = np.repeat(d[:, None] * p["out"], size, axis=0)
            da = (dz * h).sum(axis=1)
            de = a * (da - np.repeat(np.add.reduceat(a * da, at[:-1]), size))
            dt, ds = de[:, None] * p["w"] * s * (1 - t * t), de[:, None] * p["w"] * t * s * (1 - s)
            dh = (a[:, None] * dz + dt @ p["v"].T + ds @ p["u"].T) * (1 - h * h)
            g = {"encode": part.T @ dh, "shift": dh.sum(axis=0), "v": h.T @ dt, "u": h.T @ ds, "w": (t * s).T @ de, "out": z.T @ d, "bias": d.sum(keepdims=True)}
            step += 1
            for k in p:
                m[k] += 0.1 * (g[k] - m[k])
                q[k] += 0.001 * (g[k] ** 2 - q[k])
                p[k] = (p[k] * (1 - RATE * DECAY) - RATE * (m[k] / (1 - 0.9**step)) / (np.sqrt(q[k] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
    return Model(mean, scale, p, float(y.mean()))


def score(x: np.ndarray, rows: np.ndarray, model: Model) -> np.ndarray:
    """Scores of texts; a text without passages gets the share of label 1 in the sample."""
    out = np.full(len(rows) - 1, model.prior)
    full = np.flatnonzero(np.diff(rows))
    if len(full) and model.params:
        x = ((x - model.mean) / model.scale).clip(-8, 8).astype(np.float32)
        out[full] = _forward(x, np.append(rows[:-1][full], rows[-1]), model.params)[-1]
    return out


def _encoded(batches):
    for batch in batches:
        for i, j, x, rows in passages(batch.column("text")):
            yield pa.RecordBatch.from_arrays([
                *(batch.column(c).slice(i, j - i) for c in ("place", "doc_id", "quality")),
                pa.array([x[s:e].tobytes() for s, e in zip(rows[:-1], rows[1:], strict=True)], pa.binary()),
            ], names=["place", "doc_id", "quality", "encoded"])


def train(docs: DataFrame, labels: DataFrame, usable: Column | None = None) -> Model:
    """Fit on a bounded sample of labelled rows that ``usable`` (of doc_id) allows.

    Tasks encode the whole text of each; the driver gets the passages' encodings, no text. Ids whose labels disagree are left out.
    """
    known = labels.where("doc_id IS NOT NULL AND quality IN (0, 1)").groupBy("doc_id").agg(F.min("quality").alias("quality"), F.max("quality").alias("other")).where("quality = other").drop("other")
    known = known.where(usable) if usable is not None else known
    chosen = bounded_sample(known, "quality", SAMPLE_PER_LABEL, 2).select("doc_id", "quality", "place")
    rows = docs.select("doc_id", "text").where("text IS NOT NULL").join(F.broadcast(chosen), "doc_id").select("place", "doc_id", F.col("quality").cast("int").alias("quality"), "text")
    encoded = rows.mapInArrow(_encoded, f"place long, doc_id {dict(rows.dtypes)['doc_id']}, quality int, encoded binary")
    got = encoded.orderBy("place", "doc_id", "encoded").select("quality", "encoded").collect()
    parts = [np.frombuffer(r["encoded"], np.float32).reshape(-1, WIDTH) for r in got]
    if not parts:
        return Model(np.zeros(0), np.ones(0), {}, 0.5)
    x, size = np.concatenate(parts), np.array([len(a) for a in parts])
    y = np.array([r["quality"] for r in got], np.float32)[size > 0]
    if len(set(y.tolist())) < 2:
        return Model(np.zeros(0), np.ones(0), {}, float(y.mean()) if len(y) else 0.5)
    return fit(x, np.concatenate([[0], np.cumsum(size[size > 0])]), y)


def _score(batches, model: Model):
    for batch in batches:
        for i, j, x, rows in passages(batch.column("text")):
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(i, j - i), pa.array(score(x, rows, model).astype(np.float64))], names=["doc_id", "score"])


def classify(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, score (0 to 1, of label 1) and predicted (score >= THRESHOLD) of every row's whole text.

    Null and wordless texts get the sample's share of label 1. Other columns are not read. One narrow pass; the model has a
    fixed size of some KB.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    id_type = dict(docs.dtypes)["doc_id"]
    scored = docs.select("doc_id", "text").mapInArrow(lambda it: _score(it, shared.value), f"doc_id {id_type}, score double")
    return scored.withColumn("predicted", (F.col("score") >= THRESHOLD).cast("int"))
