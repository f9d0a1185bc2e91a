"""SentencePiece encoding by shared-prefix Viterbi search over a trie of distinct marked words, and decoding.

Distinct words, marked and sorted, are the paths of a trie that is walked depth-first; the forward states of a prefix are
computed once and reused by all words that share it. For a unigram model the state of a prefix is its best sum of piece scores and the
last piece of it. The public model at hand holds BPE pieces. Its encoding of a word is not the best sum of scores but the
result of ranked merges; still, the last piece of every prefix is unique, and a
segmentation is the encoding exactly if each two neighbours are the encoding of their own
concatenation. So there the state is the one piece that ends the prefix's encoding. The kind is read from the model file; kinds
other than these two, and normalizers that change characters, are refused.
"""

from __future__ import annotations

from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathsieve.llm import kernels as K
from pathsieve.llm.word_codes import WordCodes

MARK = "▁"
_models: dict[str, "PieceModel"] = {}


UNIGRAM, BPE = 1, 2
#: What an unknown character scores below the least piece.
UNKNOWN_PENALTY = 10.0


def _fields(data: bytes):
    """(number, value) of the fields of a protocol buffer message; values are numbers or bytes."""
    at = 0

    def number():
        nonlocal at
        value, shift = 0, 0
        while True:
            byte = data[at]
            at += 1
            value |= (byte & 127) << shift
            shift += 7
            if byte < 128:
                return value

    while at < len(data):
        tag = number()
        kind = tag & 7
        if kind == 0:
            yield tag >> 3, number()
        else:
            size = {1: 8, 5: 4}.get(kind) or number()
            yield tag >> 3, data[at : at + size]
            at += size


class PieceModel:
    """Pieces of a model file and the forward search."""

    def __init__(self, path: str) -> None:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        parts = dict(_fields(sp.serialized_model_proto()))
        trainer, normalizer = dict(_fields(parts.get(2, b""))), dict(_fields(parts.get(3, b"")))
        self.kind = trainer.get(3, UNIGRAM)
        if self.kind not in (UNIGRAM, BPE):
            raise ValueError("neither a unigram nor a BPE model")
        if normalizer.get(2) or not normalizer.get(3, 1) or normalizer.get(4, 1) or not normalizer.get(5, 1) or trainer.get(24):
            raise ValueError("the model changes texts before it encodes them")
        n = sp.get_piece_size()
        self.text = [sp.id_to_piece(i) for i in range(n)]
        plain = [i for i in range(n) if not (sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i))]
        self.vocab = {self.text[i]: i for i in plain}
        self.score = {self.text[i]: sp.get_score(i) for i in plain}
        if any(MARK in p.lstrip(MARK) for p in self.vocab):
            raise ValueError("pieces reach over words")
        falls_back = any(sp.is_byte(i) for i in range(n))
        self.bytes = [sp.piece_to_id(f"<0x{i:02X}>") for i in range(256)] if falls_back else None
        self.unknown, self.unknown_score = sp.unk_id(), min(self.score.values()) - UNKNOWN_PENALTY
        self.longest = max(map(len, self.vocab))
        self.by_last: dict[str, list[int]] = {}
        for p in self.vocab:
            self.by_last.setdefault(p[-1], []).append(len(p))
        self.by_last = {c: sorted(set(ls), reverse=True) for c, ls in self.by_last.items()}
        self.breaks = not any("\n" in p for p in self.vocab)
        self._pairs: dict[int, bool] = {}
        raw = [b"" if sp.is_control(i) else bytes([int(p[3:5], 16)]) if sp.is_byte(i) else p.replace(MARK, " ").encode() for i, p in enumerate(self.text)]
        self.raw_size = np.array([len(r) for r in raw], np.int64)
        self.raw_at = np.cumsum(self.raw_size) - self.raw_size
        self.raw = np.frombuffer(b"".join(raw), np.uint8)
        self.codes = WordCodes(self.encode_words if self.kind == BPE else self.best_words)

    def merged(self, word: str) -> list[str]:
        """Ranked merges of one word, leftmost first among equals."""
        parts = list(word)
        while True:
            best = max(((self.score[a + b], -i) for i, (a, b) in enumerate(pairwise(parts)) if a + b in self.score), default=None)
            if best is None:
                return parts
            i = -best[1]
            parts[i : i + 2] = [parts[i] + parts[i + 1]]

    def _neighbours(self, a: int, b: int) -> bool:
        key = a << 20 | b
        if (known := self._pairs.get(key)) is None:
            if len(self._pairs) > 2_000_000:
                self._pairs.clear()
            known = self._pairs[key] = self.merged(self.text[a] + self.text[b]) == [self.text[a], self.text[b]]
        return known

    def encode_words(self, words: list[bytes]) -> list[list[int]]:
        """Ids of marked words (spaces stand for marks), by depth-first descent in their sorted trie.

        ``last[i]`` is the id that ends the encoding of the first i characters, or -1 for a
        character that is no piece; states up to the depth shared with the word before stay.
        """
        marked = [w.decode().replace(" ", MARK) for w in words]
        order = sorted(range(len(marked)), key=marked.__getitem__)
        out: list[list[int]] = [[]] * len(words)
        last, size, before = [-1], [0], ""
        vocab, by_last, pairs, none = self.vocab, self.by_last, self._pairs, ()
        for x in order:
            word = marked[x]
            n, depth = len(word), 0
            most = min(n, len(before))
            while depth < most and word[depth] == before[depth]:
                depth += 1
            del last[depth + 1 :], size[depth + 1 :]
            for i in range(depth + 1, n + 1):
                found, width = -1, 1
                for width in by_last.get(word[i - 1], none):
                    if width > i:
                        continue
                    piece = vocab.get(word[i - width : i])
                    if piece is None:
                        continue
                    prior = last[i - width]
                    if width == i or prior < 0:
                        ok = self.merged(word[i - width : i]) == [word[i - width : i]] if (ok := pairs.get(~piece)) is None else ok
                        pairs[~piece] = ok
                    elif (ok := pairs.get(prior << 20 | piece)) is None:
                        ok = self._neighbours(prior, piece)
                    if ok:
                        found = piece
                        break
                else:
                    width = 1
                last.append(found)
                size.append(width)
            out[x] = self._read_back(word, last, size)
            before = word
        return out

    def _read_back(self, word: str, last: list[int], size: list[int]) -> list[int]:
        """Ids of a word from the last piece (-1 for none) and its width at each prefix."""
        i, ids = len(word), []
        while i:
            if last[i] >= 0:
                ids.append(last[i])
            elif self.bytes is not None:
                ids.extend(self.bytes[c] for c in reversed(word[i - 1].encode()))
            elif not ids or ids[-1] != self.unknown:
                ids.append(self.unknown)
            i -= size[i]
        ids.reverse()
        return ids

    def best_words(self, words: list[bytes]) -> list[list[int]]:
        """Ids of marked words by the best sum of piece scores, the longer last piece among equal sums.

        The same descent as :meth:`encode_words`; ``best[i]`` is the forward score of the first i characters.
        """
        marked = [w.decode().replace(" ", MARK) for w in words]
        order = sorted(range(len(marked)), key=marked.__getitem__)
        out: list[list[int]] = [[]] * len(words)
        best, last, size, before = [0.0], [-1], [0], ""
        vocab, score, by_last, none = self.vocab, self.score, self.by_last, ()
        for x in order:
            word = marked[x]
            depth, most = 0, min(len(word), len(before))
            while depth < most and word[depth] == before[depth]:
                depth += 1
            del best[depth + 1 :], last[depth + 1 :], size[depth + 1 :]
            for i in range(depth + 1, len(word) + 1):
                top, found, wide = -float("inf"), -1, 1
                for width in by_last.get(word[i - 1], none):
                    if width <= i and (piece := vocab.get(word[i - width : i])) is not None:
                        value = best[i - width] + score[self.text[piece]]
                        if value > top:
                            top, found, wide = value, piece, width
                if word[i - 1] not in vocab and best[i - 1] + self.unknown_score > top:
                    top, found, wide = best[i - 1] + self.unknown_score, -1, 1
                best.append(top)
                last.append(found)
                size.append(wide)
            out[x] = self._read_back(word, last, size)
            before = word
        return out

    def decode(self, ids: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Bytes of all rows and the row offsets into them; the mark put before a text is taken off."""
        size = self.raw_size[ids]
        data = self.raw[K.ragged(self.raw_at[ids], size)]
        at = np.concatenate([[0], np.cumsum(size)])[rows]
        full = np.diff(at) > 0
        keep = np.ones(len(data), bool)
        lead = at[:-1][full]
        keep[lead[data[lead] == 32]] = False
        ends = np.concatenate([[0], np.cumsum(keep)])
        return data[keep], ends[at]


def model(path: str) -> PieceModel:
    """This process's model for a file; its path must exist wherever tasks run."""
    if path not in _models:
        _models[path] = PieceModel(path)
    return _models[path]


def _marked_words(b: np.ndarray, rows: np.ndarray, breaks: bool):
    """The rows with a leading space each, cut before runs of spaces and around line ends."""
    full = np.flatnonzero(np.diff(rows))
    b = np.insert(b, rows[:-1][full], 32)
    lead = np.zeros(len(rows), np.int64)
    lead[full + 1] = 1
    rows = rows + np.cumsum(lead)
    cut = np.zeros(len(b) + 1, bool)
    space = b == 32
    cut[:-1] = space
    cut[1:-1] &= ~space[:-1]
    if breaks:
        end = b == 10
        cut[:-1] |= end
        cut[1:] |= end
    cut[rows] = True
    starts = np.flatnonzero(cut[:-1])
    return b, starts, np.append(starts[1:], len(b)), np.searchsorted(starts, rows)


def encode_rows(column: pa.Array, path: str):
    """For each chunk of rows: its range, all ids, row offsets into them, and whether decoding gives each text back."""
    m = model(path)
    data, offsets = K.flat(column)
    for i, j in K.chunks(offsets, 4 << 20):
        plain, at = data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i]
        if len(plain):
            ids, rows = m.codes.of(*_marked_words(plain, at, m.breaks))
        else:
            ids, rows = np.zeros(0, np.int32), np.zeros(len(at), np.int64)
        back, back_at = m.decode(ids, rows)
        if len(back) == len(plain) and np.array_equal(back_at, at):
            wrong = K.row_sums(back != plain, at) > 0
        else:
            wrong = np.array([back[back_at[k] : back_at[k + 1]].tobytes() != plain[at[k] : at[k + 1]].tobytes() for k in range(j - i)])
        yield i, j, ids, rows, ~wrong


def _encode(batches, path: str):
    for batch in batches:
        for i, j, ids, rows, back in encode_rows(batch.column("text"), path):
            yield pa.RecordBatch.from_arrays([
                batch.column("doc_id").slice(i, j - i), K.lists(ids, rows, pa.int32()), pa.array(np.diff(rows)), pa.array(back),
            ], names=["doc_id", "ids", "n_pieces", "round_trip"])


def encode(docs: DataFrame, path: str) -> DataFrame:
    """Piece ids of every row's whole text: doc_id, ids, n_pieces, round_trip (decoding gives the text back).

    Takes doc_id and text; other columns are not read. Ids equal the sentencepiece library's (of a unigram model, unless two sums of
    scores agree to seven digits). Null and empty texts have no
    ids. Characters that are no piece become byte pieces, or the unknown piece where the model has no byte pieces. One narrow pass: each task encodes the
    distinct words of a few MB at a time and keeps a bounded number of words' ids.
    """
    id_type = dict(docs.dtypes)["doc_id"]
    return docs.select("doc_id", "text").mapInArrow(lambda it: _encode(it, path), f"doc_id {id_type}, ids array<int>, n_pieces long, round_trip boolean")


def _decode(batches, path: str):
    m = model(path)
    for batch in batches:
        lists = batch.column("ids")
        for k in range(0, len(lists), 1000):
            part = lists.slice(k, 1000).fill_null([])
            rows = np.concatenate([[0], np.cumsum(part.value_lengths().to_numpy(zero_copy_only=False))]).astype(np.int64)
            data, at = m.decode(part.flatten().to_numpy(zero_copy_only=False), rows)
            text = data.tobytes()
            yield pa.RecordBatch.from_arrays([
                batch.column("doc_id").slice(k, 1000), pa.array([text[s:e].decode("utf-8", "replace") for s, e in pairwise(at.tolist())], pa.string()),
            ], names=["doc_id", "text"])


def decode(encoded: DataFrame, path: str) -> DataFrame:
    """Texts of rows of piece ids: doc_id, text. Null ids give an empty text; bytes that are no UTF-8 are replaced."""
    id_type = dict(encoded.dtypes)["doc_id"]
    return encoded.select("doc_id", F.col("ids").cast("array<int>").alias("ids")).mapInArrow(lambda it: _decode(it, path), f"doc_id {id_type}, text string")
