"""Encoding whole texts through their distinct words, for encoders in which words are independent."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

from pathsieve.llm import kernels as K


class WordCodes:
    """Ids of words, kept by word hash between batches, up to ``most`` words.

    ``encode`` gets a list of distinct words and returns their lists of ids.
    """

    def __init__(self, encode: Callable[[list[bytes]], list], most: int = 1_500_000) -> None:
        self.encode, self.most = encode, most
        self._clear()

    def _clear(self) -> None:
        self.keys, self.at, self.size, self.ids = np.zeros(0, K.U64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int32)

    def _add(self, keys: np.ndarray, words: list[bytes]) -> None:
        found = self.encode(words)
        size = np.fromiter(map(len, found), np.int64, len(found))
        flat = np.fromiter((x for f in found for x in f), np.int32, int(size.sum()))
        at = len(self.ids) + np.cumsum(size) - size
        keys, at, size = np.concatenate([self.keys, keys]), np.concatenate([self.at, at]), np.concatenate([self.size, size])
        order = np.argsort(keys, kind="stable")
        self.keys, self.at, self.size, self.ids = keys[order], at[order], size[order], np.concatenate([self.ids, flat])

    def _missing(self, keys: np.ndarray) -> np.ndarray:
        if not len(self.keys):
            return np.ones(len(keys), bool)
        return self.keys[np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)] != keys

    def of(self, b: np.ndarray, starts: np.ndarray, ends: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words in order, and the row offsets into them."""
        keys, first, inverse = np.unique(K.spans_hash(b, starts, ends), return_index=True, return_inverse=True)
        new = self._missing(keys)
        if len(self.keys) + new.sum() > self.most:
            self._clear()
            new[:] = True
        if new.any():
            text = b.tobytes()
            self._add(keys[new], [text[s:e] for s, e in zip(starts[first[new]].tolist(), ends[first[new]].tolist(), strict=True)])
        place = np.searchsorted(self.keys, keys)[inverse]
        size = self.size[place]
        at = np.concatenate([[0], np.cumsum(size)])
        return self.ids[K.ragged(self.at[place], size)], at[rows]
