"""Language identification with presence kernels, Nyström landmarks and one-versus-rest ridge regression."""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathsieve.llm import kernels as K

LENGTHS, BITS = (1, 2, 3, 4), 16
#: Rows of a language that the classifier is fitted on; languages rarer than the first MOST_LANGUAGES give one row each.
SAMPLE_PER_LANGUAGE, MOST_LANGUAGES = 300, 200
LANDMARKS_PER_LANGUAGE, RIDGE, SHARPNESS = 40, 1e-3, 6.0

#: ASCII letters in lower case and bytes of other characters stay; the rest parts words.
_KEEP = np.full(256, 32, np.uint8)
_KEEP[65:91] = np.arange(97, 123)
_KEEP[97:123] = np.arange(97, 123)
_KEEP[128:] = np.arange(128, 256)


class Model(NamedTuple):
    languages: list[str]
    weights: np.ndarray  # (n-gram buckets, languages)


def grams(column: pa.Array):
    """For each chunk of rows: its range and a list of the buckets of n-grams present in each row's whole text."""
    data, offsets = K.flat(column)
    for i, j in K.chunks(offsets):
        b = _KEEP[data[offsets[i] : offsets[j]]]
        rows = offsets[i : j + 1] - offsets[i]
        edge = np.zeros(len(b) + 1, bool)
        edge[rows] = True
        gap = (b == 32) & ~edge[:-1]
        gap[1:] &= b[:-1] == 32
        gap[:1] = False
        kept = np.concatenate([[0], np.cumsum(~gap)])
        b, rows = b[~gap].astype(np.uint32), kept[rows]
        h, buckets = np.zeros(len(b), np.uint32), []
        for n in range(1, max(LENGTHS) + 1):
            if len(b) >= n:
                h = h[: len(b) - n + 1] * np.uint32(0x01000193) + b[n - 1 :] + np.uint32(1)
                x = h * np.uint32(0x9E3779B1) + np.uint32(n * 0x85EBCA6B & 0xFFFFFFFF)
                buckets.append((x >> np.uint32(32 - BITS)).astype(np.int64))
        flags = np.zeros(1 << BITS, bool)
        present = []
        for s, e in zip(rows[:-1].tolist(), rows[1:].tolist(), strict=True):
            for n, x in enumerate(buckets, 1):
                flags[x[s : max(s, e - n + 1)]] = True
            found = np.flatnonzero(flags)
            flags[found] = False
            present.append(found)
        yield i, j, present


def fit(present: list[np.ndarray], languages: list[str]) -> Model:
    """From the buckets present in each text: Nyström features on evenly spread landmarks, then ridge regression of each language against the rest.

    The kernel is the share of common n-grams, |a & b| / sqrt(|a| |b|) over the blended spectrum. It is linear in
    the presence vectors, so landmarks, whitening and regression weights multiply into one matrix.
    """
    names = sorted(set(languages))
    use = [x for x, p in enumerate(present) if len(p)]
    y = np.array([names.index(languages[x]) for x in use])
    marks = [x for c in range(len(names)) for x in np.flatnonzero(y == c)[:LANDMARKS_PER_LANGUAGE]]
    dense = np.zeros((len(marks), 1 << BITS), np.float32)
    for row, x in enumerate(marks):
        dense[row, present[use[x]]] = 1 / np.sqrt(len(present[use[x]]))
    kernel = np.stack([dense[:, present[x]].sum(axis=1) / np.sqrt(len(present[x])) for x in use]).astype(np.float64)
    values, vectors = np.linalg.eigh(kernel[marks])
    good = values > values.max() * 1e-6
    whiten = vectors[:, good] / np.sqrt(values[good])
    features = np.hstack([kernel @ whiten, np.ones((len(use), 1))])
    target = np.where(y[:, None] == np.arange(len(names)), 1.0, -1.0)
    weight = (len(y) / np.bincount(y, minlength=len(names)))[y]
    left = features.T @ (features * weight[:, None]) + RIDGE * weight.sum() * np.eye(features.shape[1])
    solved = np.linalg.solve(left, features.T @ (target * weight[:, None]))
    table = dense.T.astype(np.float64) @ (whiten @ solved[:-1])
    return Model(names, np.vstack([table, solved[-1:]]).astype(np.float32))


def scores(present: list[np.ndarray], model: Model) -> np.ndarray:
    """Regression values, rows by languages: one product of the batch's presence rows with the weights."""
    out = np.tile(model.weights[-1], (len(present), 1))
    size = np.array([len(p) for p in present])
    full = np.flatnonzero(size)
    if len(full):
        at = np.cumsum(size[full]) - size[full]
        sums = np.add.reduceat(model.weights[np.concatenate([present[x] for x in full])], at, axis=0)
        out[full] += sums / np.sqrt(size[full])[:, None]
    return out


def _predict(batches, model: Model):
    names = np.array(model.languages, dtype=object)
    for batch in batches:
        letters = batch.column("has_letter")
        for i, j, present in grams(batch.column("text")):
            if len(names):
                value = SHARPNESS * scores(present, model).astype(np.float64)
                share = np.exp(value - value.max(axis=1, keepdims=True))
                share /= share.sum(axis=1, keepdims=True)
                best, score = names[share.argmax(axis=1)], share.max(axis=1)
            else:
                best, score = np.full(j - i, "und", object), np.zeros(j - i)
            known = letters.slice(i, j - i).to_numpy(zero_copy_only=False).astype(bool)
            yield pa.RecordBatch.from_arrays([
                batch.column("doc_id").slice(i, j - i), pa.array(np.where(known, best, "und"), pa.string()), pa.array(np.where(known, score, 0.0)),
            ], names=["doc_id", "lang_pred", "score"])


def bounded_sample(rows: DataFrame, label: str, per_label: int, most_labels: int) -> DataFrame:
    """About ``per_label`` distinct rows of each label, chosen by a hash of all their other columns, and their place in hash order.

    A label's share of the hash range is ``per_label`` over its rows, so repeated rows can only make the sample smaller. Of labels rarer than the ``most_labels`` most frequent ones, the first row in that order.
    """
    found = rows.groupBy(label).count().orderBy(F.desc("count"), label).limit(most_labels + 1).collect()
    counts = {r[0]: r[1] for r in found[:most_labels]}
    place = F.pmod(F.xxhash64(*[c for c in rows.columns if c != label], F.lit(11)), F.lit(1 << 30))
    wanted = F.lit(False)
    for value, n in counts.items():
        wanted = wanted | ((F.col(label) == F.lit(value)) & (place < int((1 << 30) * min(1.0, per_label / n))))
    sample = rows.where(wanted).distinct().withColumn("place", place)
    if len(found) <= most_labels:
        return sample
    rare = rows.where(~F.col(label).isin(list(counts))).withColumn("place", place)
    return sample.unionByName(rare.groupBy(label).agg(F.min(F.struct("place", *rows.columns)).alias("row")).select("row.*"))


def _present(batches):
    for batch in batches:
        for i, j, present in grams(batch.column("text")):
            yield pa.RecordBatch.from_arrays([
                *(batch.column(c).slice(i, j - i) for c in ("place", "doc_id", "lang")),
                pa.array([p.astype("<u2").tobytes() for p in present], pa.binary()),
            ], names=["place", "doc_id", "lang", "present"])


def train(docs: DataFrame, usable: Column | None = None) -> Model:
    """Fit on a bounded sample of the rows with a language that ``usable`` allows.

    Tasks find the n-grams of the whole text of each; the driver gets two bytes for each bucket present, no text.
    """
    rows = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull())
    rows = rows.where(usable) if usable is not None else rows
    sample = bounded_sample(rows.select("doc_id", "lang", "text"), "lang", SAMPLE_PER_LANGUAGE, MOST_LANGUAGES)
    marked = sample.select("place", "doc_id", "lang", "text").mapInArrow(_present, f"place long, doc_id {dict(rows.dtypes)['doc_id']}, lang string, present binary")
    got = marked.orderBy("place", "doc_id", "present").select("lang", "present").collect()
    if not got:
        return Model([], np.zeros((1, 0), np.float32))
    return fit([np.frombuffer(r["present"], "<u2").astype(np.int64) for r in got], [r["lang"] for r in got])


def identify(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, lang_pred and score (0 to 1) of every row's whole text; ``und`` and 0 for null and letterless texts.

    Takes doc_id and text; other columns are not read. One narrow pass; the model, a table of 2**BITS rows, is broadcast.
    Without any labelled row, all texts are ``und``.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    id_type = dict(docs.dtypes)["doc_id"]
    rows = docs.select("doc_id", "text", F.coalesce(F.col("text").rlike(r"\p{L}"), F.lit(False)).alias("has_letter"))
    return rows.mapInArrow(lambda it: _predict(it, shared.value), f"doc_id {id_type}, lang_pred string, score double")
