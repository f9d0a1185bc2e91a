"""Benchmark decontamination by winnowing: guaranteed fingerprints, join, extension of hits."""

from __future__ import annotations

import hashlib
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathsieve.llm import kernels as K
from pathsieve.loop import cut

SPAN = 10
#: Bytes of benchmark text up to which its fingerprints are broadcast; beyond, they are joined.
BROADCAST_BYTES = 32 << 20


def tier_shape(span: int) -> tuple[int, int]:
    """Words in a gram and grams in a window, so that ``span`` shared words hold one window."""
    gram = (span + 1) // 2
    return gram, span - gram + 1


def winnow(h: np.ndarray, rows: np.ndarray, span: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Positions (first word, ascending), hashes and rows of the grams chosen by winnowing.

    In each window of consecutive grams the least hash is chosen, the rightmost of equal
    ones; any ``span`` words in a row hold a whole window, and so share its choice with
    every other place of the same words.
    """
    gram, window = tier_shape(span)
    grams, at = K.shingles(h, rows, gram, whole=False)
    n = len(grams) - window + 1
    if n <= 0:
        return np.zeros(0, np.int64), np.zeros(0, K.U64), np.zeros(0, np.int64)
    best, where = grams[:n].copy(), np.arange(n)
    for j in range(1, window):
        less = grams[j : n + j] <= best
        best[less] = grams[j : n + j][less]
        where[less] = np.flatnonzero(less) + j
    fits = np.zeros(n, np.int8)
    counts = np.diff(at) - window + 1
    whole = counts > 0
    fits[K.ragged(at[:-1][whole], counts[whole])] = 1
    chosen = np.unique(where[fits == 1])
    row = np.searchsorted(at, chosen, side="right") - 1
    return rows[row] + chosen - at[row], grams[chosen], row


class _Tier(NamedTuple):
    span: int
    hashes: np.ndarray  # sorted
    item: np.ndarray
    word: np.ndarray
    seen: np.ndarray  # by the lowest 16 bits


class Fingerprints(NamedTuple):
    """Words and winnowing fingerprints of benchmark items."""

    ids: list[str]
    h: np.ndarray
    rows: np.ndarray
    tiers: list[_Tier]


def fingerprints(ids: list[str], texts: list[str], span: int = SPAN) -> Fingerprints:
    """The items' fingerprints: a tier for ``span`` words and one for each shorter length that occurs."""
    data, offsets = K.flat(pa.array(texts, pa.string()))
    b = K.LOWER[data[: offsets[-1]]]
    starts, ends, rows = K.words(b, offsets, K.ALNUM)
    h = K.spans_hash(b, starts, ends)
    sizes, tiers = np.diff(rows), []
    for n in sorted({min(int(x), span) for x in sizes} - {0}):
        pos, hashes, row = winnow(h, rows, n)
        own = np.minimum(sizes[row], span) == n
        pos, hashes, row = pos[own], hashes[own], row[own]
        order = np.argsort(hashes, kind="stable")
        seen = np.zeros(1 << 16, bool)
        seen[(hashes & K.U64(0xFFFF)).astype(np.int64)] = True
        tiers.append(_Tier(n, hashes[order], row[order], pos[order] - rows[row[order]], seen))
    return Fingerprints(ids, h, rows, tiers)


def _same_run(a: np.ndarray, b: np.ndarray) -> int:
    """How many first elements are equal."""
    n = min(len(a), len(b))
    step, done = 16, 0
    while done < n:
        unequal = np.flatnonzero(a[done : done + step] != b[done : done + step][: n - done]) if done + step <= n else np.flatnonzero(a[done:n] != b[done:n])
        if len(unequal):
            return done + int(unequal[0])
        done, step = done + step, step * 4
    return n


def find(h: np.ndarray, rows: np.ndarray, marks: Fingerprints, span: int = SPAN) -> tuple[np.ndarray, list[set[int]]]:
    """Which words are hit, and the items found in each row."""
    hit = np.zeros(len(h), bool)
    items: list[set[int]] = [set() for _ in range(len(rows) - 1)]
    for tier in marks.tiers:
        pos, hashes, row = winnow(h, rows, tier.span)
        maybe = np.flatnonzero(tier.seen[(hashes & K.U64(0xFFFF)).astype(np.int64)])
        left = np.searchsorted(tier.hashes, hashes[maybe], side="left")
        right = np.searchsorted(tier.hashes, hashes[maybe], side="right")
        done: dict[tuple[int, int, int], int] = {}
        for m, lo, hi in zip(maybe[right > left], left[right > left], right[right > left], strict=True):
            p, r = int(pos[m]), int(row[m])
            start, end = int(rows[r]), int(rows[r + 1])
            for x in range(lo, hi):
                item, q = int(tier.item[x]), int(tier.word[x])
                line = (r, item, p - q)
                if done.get(line, -1) > p:
                    continue
                first, last = int(marks.rows[item]), int(marks.rows[item + 1])
                at = first + q
                back = _same_run(h[max(start, p - q) : p][::-1], marks.h[max(first, at - (p - start)) : at][::-1])
                on = _same_run(h[p:end], marks.h[at:last])
                done[line] = p + max(on, 1)
                if back + on >= min(span, last - first):
                    hit[p - back : p + on] = True
                    items[r].add(item)
    return hit, items


def _hashed(column: pa.Array):
    data, offsets = K.flat(column)
    for i, j in K.chunks(offsets):
        b = K.LOWER[data[offsets[i] : offsets[j]]]
        starts, ends, rows = K.words(b, offsets[i : j + 1] - offsets[i], K.ALNUM)
        yield i, j, K.spans_hash(b, starts, ends), rows


def _scan(batches, marks: Fingerprints, span: int):
    for batch in batches:
        for i, j, h, rows in _hashed(batch.column("text")):
            hit, items = find(h, rows, marks, span)
            found = [sorted({marks.ids[x] for x in s}) for s in items]
            yield pa.RecordBatch.from_arrays([
                batch.column("doc_id").slice(i, j - i), pa.array(np.diff(rows), pa.int64()),
                pa.array(K.row_sums(hit, rows), pa.int64()), pa.array(found, pa.list_(pa.string())),
            ], names=["doc_id", "n_words", "n_hit", "items"])


def _marks(batches, span: int, name: str, tiers: list[int]):
    """The winnowing fingerprints of ``tiers`` as rows, for the join, each once a row; items give those of their own tier."""
    for batch in batches:
        for i, j, h, rows in _hashed(batch.column("text")):
            keys = batch.column(name).slice(i, j - i)
            for n in tiers:
                _, hashes, row = winnow(h, rows, n)
                if name == "item_row":
                    own = np.minimum(np.diff(rows)[row], span) == n
                    hashes, row = hashes[own], row[own]
                order = np.lexsort((hashes, row))
                hashes, row = hashes[order], row[order]
                new = np.ones(len(row), bool)
                new[1:] = (hashes[1:] != hashes[:-1]) | (row[1:] != row[:-1])
                hashes, row = hashes[new], row[new]
                yield pa.RecordBatch.from_arrays([keys.take(pa.array(row)), pa.array(np.full(len(row), n, np.int32)), pa.array(hashes.view(np.int64))], names=[name, "tier", "mark"])


def _extend(batches, span: int):
    for batch in batches:
        starts, ends = [], []
        for text, item in zip(batch.column("text").to_pylist(), batch.column("item_text").to_pylist(), strict=True):
            (_, _, h, rows), = _hashed(pa.array([text], pa.string()))
            hit, _ = find(h, rows, fingerprints(["x"], [item], span), span)
            edge = np.flatnonzero(np.diff(np.concatenate([[0], hit.astype(np.int8), [0]])))
            starts.append(edge[::2].tolist())
            ends.append(edge[1::2].tolist())
        yield pa.RecordBatch.from_arrays([batch.column("row_key"), batch.column("item_id"), pa.array(starts, pa.list_(pa.int64())), pa.array(ends, pa.list_(pa.int64()))], names=["row_key", "item_id", "starts", "ends"])


def _counted(batches):
    for batch in batches:
        for i, j, _, rows in _hashed(batch.column("text")):
            yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(i, j - i), batch.column("row_key").slice(i, j - i), pa.array(np.diff(rows), pa.int64())], names=["doc_id", "row_key", "n_words"])


def _joined(docs: DataFrame, items: DataFrame, span: int) -> DataFrame:
    """The same result by a join on fingerprints, for a benchmark of any size.

    Documents give fingerprints of the lengths that occur among the items only, most often one; they meet the items'
    before anything else is shuffled.
    """
    id_type = dict(docs.dtypes)["doc_id"]
    keyed = docs.select("doc_id", "text", F.sha2(F.to_json(F.struct("doc_id", "text")), 256).alias("row_key"))
    texts = keyed.select("row_key", "text").where("text IS NOT NULL").dropDuplicates(["row_key"])
    items = items.select("item_id", F.col("text").alias("item_text"), F.monotonically_increasing_id().alias("item_row"))
    items = cut(items, "items")
    every = list(range(1, span + 1))
    at = cut(items.select("item_row", F.col("item_text").alias("text")).mapInArrow(lambda it: _marks(it, span, "item_row", every), "item_row long, tier int, mark long"), "marks")
    present = sorted(r[0] for r in at.select("tier").distinct().collect())
    spots = texts.mapInArrow(lambda it: _marks(it, span, "row_key", present), "row_key string, tier int, mark long")
    pairs = cut(spots.join(at, ["tier", "mark"]).select("row_key", "item_row").distinct(), "candidates")
    both = pairs.join(texts, "row_key").join(items, "item_row").select("row_key", "item_id", "text", "item_text")
    runs = cut(both.mapInArrow(lambda it: _extend(it, span), "row_key string, item_id string, starts array<long>, ends array<long>").where("size(starts) > 0"), "runs")
    spans = runs.select("row_key", F.explode(F.arrays_zip("starts", "ends")).alias("x")).select("row_key", F.explode(F.expr("sequence(x.starts, x.ends - 1)")).alias("word"))
    hits = spans.distinct().groupBy("row_key").agg(F.count("*").alias("n_hit"))
    found = runs.groupBy("row_key").agg(F.array_sort(F.collect_set("item_id")).alias("items"))
    base = keyed.mapInArrow(_counted, f"doc_id {id_type}, row_key string, n_words long")
    return base.join(hits, "row_key", "left").join(found, "row_key", "left").select("doc_id", "n_words", F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"), F.coalesce("items", F.array().cast("array<string>")).alias("items"))


def contamination(docs: DataFrame, benchmark: DataFrame, span: int = SPAN, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """Benchmark passages in each row of ``docs``.

    Words are runs of ASCII digits, letters (A-Z lower-cased) and non-ASCII characters. An item's
    windows are its runs of ``span`` words; an item of fewer words, but not none, is one
    window. Takes doc_id, text and item_id, text; other columns are not read. Returns doc_id,
    n_words, n_hit (words inside an occurrence of any window), items (sorted ids, as strings, of
    items with occurring windows), n_items, items_sha256, contaminated. Null and wordless
    texts have no hits. Items without text or item_id are left out; an id that several items
    share is listed once. Rows that repeat a doc_id each give a row.

    Both sides are winnowed; a shared window guarantees a shared fingerprint, and matches are
    extended both ways to whole runs. If the benchmark's text is within ``broadcast_bytes``,
    its fingerprints go to the tasks and one pass without a shuffle does all; a larger
    one is joined by fingerprint.
    """
    items = benchmark.select(F.col("item_id").cast("string").alias("item_id"), "text").where("item_id IS NOT NULL AND text IS NOT NULL")
    small = (items.agg(F.sum(F.octet_length("text"))).first()[0] or 0) <= broadcast_bytes
    if small:
        rows = items.collect()
        marks = docs.sparkSession.sparkContext.broadcast(fingerprints([r[0] for r in rows], [r[1] for r in rows], span))
        id_type = dict(docs.dtypes)["doc_id"]
        found = docs.select("doc_id", "text").mapInArrow(lambda it: _scan(it, marks.value, span), f"doc_id {id_type}, n_words long, n_hit long, items array<string>")
    else:
        found = _joined(docs, items, span)
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"), "items")


def brute_force(texts: list[str | None], items: dict, span: int = SPAN) -> list[tuple[int, int, int, str]]:
    """(n_words, n_hit, n_items, items_sha256) of each text by comparing all windows; for tests."""
    import re

    split = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    windows: dict[tuple, set] = {}
    for key, text in items.items():
        w = split(text)
        for i in range(max(1, len(w) - span + 1) if w else 0):
            windows.setdefault(tuple(w[i : i + span]), set()).add(str(key))
    out = []
    for text in texts:
        w, hit, found = split(text), set(), set()
        for n in {len(x) for x in windows}:
            for i in range(len(w) - n + 1):
                if x := windows.get(tuple(w[i : i + n])):
                    found |= x
                    hit |= set(range(i, i + n))
        out.append((len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest()))
    return out


def without_contaminated(docs: DataFrame, benchmark: DataFrame, span: int = SPAN) -> DataFrame:
    """The rows of ``docs`` in which no benchmark window occurs, with their columns."""
    carried = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("doc_id"), docs["text"].alias("text"))
    return contamination(carried, benchmark, span).where("NOT contaminated").select("doc_id.*")
