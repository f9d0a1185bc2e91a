"""Repeated passages of lines: winnowing over line hashes, join of positions, extension, deletion."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathsieve.llm import kernels as K
from pathsieve.loop import cut, scratch

GRAM_WORDS, WINDOW_WORDS = 25, 50
_BLOCK_RUNS = 1 << 14


def line_table(b: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of the lines with a word: hash of the line's words, words, number in the text; row offsets."""
    starts, ends, first = K.words(b, rows, K.NOT_SPACE)
    h = K.spans_hash(K.LOWER[b], starts, ends)
    breaks = np.flatnonzero(b == 10)
    line = np.searchsorted(breaks, starts)
    row = np.repeat(np.arange(len(rows) - 1), np.diff(first))
    new = np.ones(len(starts), bool)
    new[1:] = (line[1:] != line[:-1]) | (row[1:] != row[:-1])
    at = np.flatnonzero(new)
    edges = np.append(at, len(starts))
    place = np.arange(len(starts)) - np.repeat(at, np.diff(edges))
    mixed = K.mix64(h + place.astype(K.U64) * K.U64(0x9FB21C651E98DF25))
    hashes = np.add.reduceat(mixed, at) if len(at) else np.zeros(0, K.U64)
    number = line[at] - np.searchsorted(breaks, rows[:-1])[row[at]]
    return hashes, np.diff(edges), number, np.searchsorted(at, first)


def fingerprints(h: np.ndarray, n: np.ndarray, gram_words: int, window_words: int) -> list[tuple[int, int]]:
    """(first line, hash) of the winnowed grams of one text's lines.

    A gram is the shortest run of lines from a line on with ``gram_words`` words, a window the
    shortest run with ``window_words``. In each window the gram of least hash within it is chosen, the
    rightmost of equal ones. So two places that share a run of ``window_words`` words share a gram.
    """
    words = np.concatenate([[0], np.cumsum(n)])
    lines = np.arange(len(h))
    gram_end = np.searchsorted(words, words[:-1] + gram_words)
    window_end = np.searchsorted(words, words[:-1] + window_words)
    grams = lines[gram_end <= len(h)]
    if not len(grams):
        return []
    hashes = _run_hashes(h, grams, gram_end[grams])
    last = np.searchsorted(gram_end[grams], window_end, side="right")
    chosen = set()
    for i in np.flatnonzero(window_end <= len(h)).tolist():
        inside = hashes[i : last[i]]
        chosen.add(last[i] - 1 - int(np.argmin(inside[::-1])))
    return [(int(g), int(hashes[g].view(np.int64))) for g in sorted(chosen)]


def _run_hashes(h: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hashes of the runs h[start:end] of lines."""
    at = np.cumsum(ends - starts) - (ends - starts)
    index = K.ragged(starts, ends - starts)
    place = index - np.repeat(starts, ends - starts)
    mixed = K.mix64(h[index] + place.astype(K.U64) * K.U64(0xA0761D6478BD642F))
    return K.mix64(np.add.reduceat(mixed, at) + (ends - starts).astype(K.U64))


def whole_windows(n: np.ndarray, window_words: int) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the shortest runs with ``window_words`` words from each line on and up to each line.

    Both kinds together cover each run of so many words or more: a line whose words, counted from the start
    of the run, reach ``window_words`` ends a window in the run, any other is in the window that begins the run.
    """
    words = np.concatenate([[0], np.cumsum(n, dtype=np.int64)])
    onward = np.searchsorted(words, words[:-1] + window_words)
    first = np.flatnonzero(onward <= len(n))
    last = np.flatnonzero(words[1:] >= window_words)
    since = np.searchsorted(words, words[last + 1] - window_words, side="right") - 1
    runs = np.unique(np.concatenate([first * (len(n) + 1) + onward[first], since * (len(n) + 1) + last + 1]))
    return runs // (len(n) + 1), runs % (len(n) + 1)


def _lines(batches, gram_words: int, window_words: int):
    for batch in batches:
        data, offsets = K.flat(batch.column("text"))
        for i, j in K.chunks(offsets):
            h, n, number, rows = line_table(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i])
            marks = [fingerprints(h[s:e], n[s:e], gram_words, window_words) for s, e in zip(rows[:-1], rows[1:], strict=True)]
            at = np.concatenate([[0], np.cumsum([len(m) for m in marks])])
            flat = np.array([x for m in marks for x in m], np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([
                batch.column("row_key").slice(i, j - i), K.lists(h.view(np.int64), rows, pa.int64()), K.lists(n, rows, pa.int32()),
                K.lists(number, rows, pa.int32()), K.lists(flat[:, 0], at, pa.int32()), K.lists(flat[:, 1], at, pa.int64()),
            ], names=["row_key", "h", "n", "number", "place", "mark"])


def matched_lines(h: np.ndarray, n: np.ndarray, h0: np.ndarray, places: np.ndarray, shift: int, gram_words: int) -> np.ndarray:
    """Lines of the runs through ``places`` that equal the lines ``shift`` earlier in ``h0``."""
    low, high = max(0, shift), min(len(h), len(h0) + shift)
    breaks = np.concatenate([[low - 1], low + np.flatnonzero(h[low:high] != h0[low - shift : high - shift]), [high]])
    at = np.unique(np.searchsorted(breaks, places))
    words = np.concatenate([[0], np.cumsum(n)])
    starts, ends = breaks[at - 1] + 1, breaks[at]
    long = words[ends] - words[starts] >= gram_words
    return K.ragged(starts[long], ends[long] - starts[long])


def _extended(batches, gram_words: int):
    for batch in batches:
        part = {c: (batch.column(c).offsets.to_numpy(), batch.column(c).values.to_numpy(zero_copy_only=False)) for c in ("h", "n", "number", "h0", "places")}
        shifts = batch.column("shift").to_numpy(zero_copy_only=False).tolist()
        count, lines = np.zeros(len(shifts), np.int64), [np.zeros(0, np.int32)]
        for x, shift in enumerate(shifts):
            h, n, number, h0, places = (v[o[x] : o[x + 1]] for o, v in part.values())
            gone = matched_lines(h, n, h0, places, shift, gram_words)
            count[x] = len(gone)
            lines.append(number[gone])
        keys = batch.column("row_key").take(pa.array(np.repeat(np.arange(len(shifts)), count)))
        yield pa.RecordBatch.from_arrays([keys, pa.array(np.concatenate(lines), pa.int32())], names=["row_key", "line"])


def _windows(batches, window_words: int):
    """The whole windows of each text that hold the first line of a gram which stands at two places or more."""
    for batch in batches:
        part = {c: (batch.column(c).offsets.to_numpy(), batch.column(c).values.to_numpy(zero_copy_only=False)) for c in ("h", "n", "repeated")}
        for x in range(batch.num_rows):
            h, n, places = (v[o[x] : o[x + 1]] for o, v in part.values())
            starts, ends = whole_windows(n, window_words)
            marked = np.zeros(len(n) + 1, np.int64)
            marked[places + 1] = 1
            marked = np.cumsum(marked)
            again = marked[ends] > marked[starts]
            starts, ends = starts[again], ends[again]
            for i in range(0, len(starts), _BLOCK_RUNS):
                s, e = starts[i : i + _BLOCK_RUNS], ends[i : i + _BLOCK_RUNS]
                keys = batch.column("row_key").take(pa.array(np.full(len(s), x)))
                yield pa.RecordBatch.from_arrays([keys, pa.array(_run_hashes(h.view(K.U64), s, e).view(np.int64)), pa.array(s, pa.int32()), pa.array(e, pa.int32())], names=["row_key", "run", "start", "end"])


def _covered(batches):
    for batch in batches:
        part = {c: (batch.column(c).offsets.to_numpy(), batch.column(c).values.to_numpy(zero_copy_only=False)) for c in ("number", "starts", "ends")}
        count, lines = np.zeros(batch.num_rows, np.int64), [np.zeros(0, np.int32)]
        for x in range(batch.num_rows):
            number, starts, ends = (v[o[x] : o[x + 1]] for o, v in part.values())
            inside = np.bincount(starts, minlength=len(number) + 1) - np.bincount(ends, minlength=len(number) + 1)
            gone = np.flatnonzero(np.cumsum(inside)[:-1] > 0)
            count[x] = len(gone)
            lines.append(number[gone])
        keys = batch.column("row_key").take(pa.array(np.repeat(np.arange(batch.num_rows), count)))
        yield pa.RecordBatch.from_arrays([keys, pa.array(np.concatenate(lines), pa.int32())], names=["row_key", "line"])


def _keyed(docs: DataFrame) -> Column:
    """A key whose order is that of the documents: by doc_id, then a hash of the text; equal rows share it.

    Numbers: negative ones come first, in the order of their digits. Other kinds of ids are in the order of their text. Rows
    without an id come last.
    """
    text = F.xxhash64(docs["text"]).cast("string")
    if dict(docs.dtypes)["doc_id"] not in ("tinyint", "smallint", "int", "bigint"):
        return F.concat_ws(":", F.when(docs["doc_id"].isNull(), "1").otherwise("0"), docs["doc_id"].cast("string"), text)
    return F.concat_ws(":", F.when(docs["doc_id"] < 0, "0").otherwise("1"), F.lpad(docs["doc_id"].cast("string"), 20, "0"), text)


def repeated_lines(docs: DataFrame, gram_words: int = GRAM_WORDS, window_words: int = WINDOW_WORDS) -> DataFrame:
    """(row_key, lines): the numbers of the lines to delete from each text that has any."""
    with scratch(docs.sparkSession) as held:
        return held.keep(_found_lines(docs, gram_words, window_words))


def _found_lines(docs: DataFrame, gram_words: int, window_words: int) -> DataFrame:
    texts = docs.select(_keyed(docs).alias("row_key"), "text").where("text IS NOT NULL")
    kind = "row_key string, h array<long>, n array<int>, number array<int>, place array<int>, mark array<long>"
    table = cut(texts.mapInArrow(lambda it: _lines(it, gram_words, window_words), kind), "lines").dropDuplicates(["row_key"])
    marks = table.select("row_key", F.explode(F.arrays_zip("place", "mark")).alias("x")).select("row_key", "x.place", "x.mark")
    marks = cut(marks, "marks")
    keys = marks.groupBy("mark").agg(F.min("row_key").alias("key0"), F.count("*").alias("c")).where("c > 1").drop("c")
    place0 = marks.join(keys, "mark").where("row_key = key0").groupBy("mark").agg(F.min("place").alias("place0"), F.first("key0").alias("key0"))
    found = marks.join(cut(place0, "first"), "mark")
    runs = found.groupBy("row_key", "key0", (F.col("place") - F.col("place0")).alias("shift")).agg(F.collect_set("place").alias("places"))
    runs = cut(runs, "runs")
    repeated = runs.groupBy("row_key").agg(F.flatten(F.collect_list("places")).alias("repeated"))
    needed = cut(table.join(repeated, "row_key").select("row_key", "h", "n", "number", "repeated"), "needed")
    source = needed.select(F.col("row_key").alias("key0"), F.col("h").alias("h0"))
    pairs = runs.where("row_key <> key0 OR shift <> 0").join(source, "key0").join(needed, "row_key").select("row_key", "h", "n", "number", "h0", "places", "shift")
    gone = pairs.mapInArrow(lambda it: _extended(it, gram_words), "row_key string, line int")
    gone = gone.union(_repeated_windows(needed, window_words))
    return cut(gone.groupBy("row_key").agg(F.array_sort(F.collect_set("line")).alias("lines")), "gone")


def _repeated_windows(needed: DataFrame, window_words: int) -> DataFrame:
    """(row_key, line) of all lines of the windows that stood earlier as a whole, wherever their grams stood first."""
    whole = cut(needed.select("row_key", "h", "n", "repeated").mapInArrow(lambda it: _windows(it, window_words), "row_key string, run long, start int, end int"), "windows")
    first = whole.groupBy("run").agg(F.min(F.struct("row_key", "start")).alias("first"), F.count("*").alias("c")).where("c > 1").select("run", "first")
    later = whole.join(cut(first, "whole"), "run").where("row_key <> first.row_key OR start <> first.start")
    spans = later.groupBy("row_key").agg(F.collect_list("start").alias("starts"), F.collect_list("end").alias("ends"))
    return spans.join(needed.select("row_key", "number"), "row_key").select("number", "starts", "ends", "row_key").mapInArrow(_covered, "row_key string, line int")


def without_repeated_lines(docs: DataFrame, gram_words: int = GRAM_WORDS, window_words: int = WINDOW_WORDS, emptied: bool = True) -> DataFrame:
    """``docs`` with later repeats of passages of lines deleted from ``text``.

    A line is compared by its words, ASCII-lower-cased; lines without a word take no part and
    stay. The first place of a passage, by doc_id and within a text by position, keeps it. Any run of
    lines with ``window_words`` words that also stands earlier shares a fingerprint with an
    earlier place; matches are extended both ways and deleted if they have ``gram_words`` words
    or more. Shorter repeats (headers, signatures) stay. All columns stay; n_chars, where there is one, is set
    anew. Without ``emptied``, rows that lost a line and have no word left go. The gram may have stood first in another text than the rest of the run, so each whole window of a text
    with a repeated gram is also looked up by its own hash: every line of a run of ``window_words`` words or more
    that stands earlier goes. Null texts stay null; a text may become empty. Rows equal in doc_id and text are treated alike,
    as one place. The lines' hashes are kept whole for the texts with matches only; a hot passage is
    aggregated before the shuffle, and joins against its first place can be split.
    """
    gone = repeated_lines(docs, gram_words, window_words)
    names = docs.columns
    carried = docs.select(_keyed(docs).alias("row_key"), F.struct(*[docs[c] for c in names]).alias("row"))
    joined = carried.join(gone.hint("merge"), "row_key", "left")
    cutting = joined.select("row", F.col("lines").alias("gone"), F.when(F.col("lines").isNotNull(), F.split("row.text", "\n", -1)).alias("parts"))
    kept = cutting.select("row", "gone", F.expr("IF(gone IS NULL, row.text, array_join(transform(array_except(sequence(0, size(parts) - 1), gone), i -> parts[i]), '\n'))").alias("text_now"), F.size(F.coalesce("gone", F.array().cast("array<int>"))).alias("n_removed"))
    if not emptied:
        kept = kept.where(F.expr(r"gone IS NULL OR text_now RLIKE '[^ \\t-\\r]'"))
    out = {c: F.col(f"row.{c}") for c in names} | {"text": F.col("text_now")}
    if "n_chars" in names:
        out["n_chars"] = F.when(F.col("gone").isNull(), F.col("row.n_chars")).otherwise(F.length("text_now").cast(dict(docs.dtypes)["n_chars"]))
    return kept.select(*[out[c].alias(c) for c in names], *([] if "n_removed" in names else [F.col("n_removed").cast("long").alias("n_removed")]))
