"""Token ids of many texts by way of their distinct words, with a bounded memo that a Python worker keeps."""

from __future__ import annotations

from collections.abc import Callable
from itertools import repeat

import numpy as np


class WordMemo:
    """Ids of words. The first `most` words seen are kept for later batches; further ones are encoded anew each time."""

    def __init__(self, encode: Callable[[list[str]], tuple[np.ndarray, np.ndarray]], most: int = 500_000):
        self.encode, self.most = encode, most
        self.at: dict[str, int] = {}
        self.ids, self.lengths = np.empty(0, np.uint32), np.empty(0, np.int64)

    def __call__(self, words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(ids, first id of each word, its number of ids)."""
        at = self.at
        place = np.fromiter(map(at.get, words, repeat(-1)), np.int64, len(words))
        new = np.flatnonzero(place < 0)
        ids, lengths = self.ids, self.lengths
        if len(new):
            fresh_words = [words[i] for i in new]
            fresh, fresh_lengths = self.encode(fresh_words)
            place[new] = len(lengths) + np.arange(len(new))
            ids, lengths = np.concatenate((ids, fresh.astype(np.uint32))), np.concatenate((lengths, fresh_lengths))
            room = self.most - len(at)
            if room > 0:
                base = len(self.lengths)
                at.update(zip(fresh_words[:room], range(base, base + room), strict=False))
                upto = base + min(room, len(new))
                self.lengths = lengths[:upto].copy()
                self.ids = ids[: int(self.lengths.sum())].copy()
        starts = np.concatenate(([0], np.cumsum(lengths)[:-1])) if len(lengths) else lengths
        return ids, starts[place], lengths[place]


def spread(ids: np.ndarray, starts: np.ndarray, lengths: np.ndarray, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(ids of the words in `codes` one after another, the end of each word's ids)."""
    n = lengths[codes]
    ends = np.cumsum(n)
    total = int(ends[-1]) if len(ends) else 0
    where = np.repeat(starts[codes] - (ends - n), n) + np.arange(total)
    return ids[where], ends
