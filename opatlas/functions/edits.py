"""The nearest of many names by edit distance: one column of the distance table at a time, for all names of a length at once."""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np

#: Names whose words are held at once, so that they stay in a core's cache.
CHUNK = 16_384
WORD = 64


def _codes(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)


class Names:
    """Names in the order that breaks ties, by length and as numbers of their letters."""

    def __init__(self, names: Sequence[str]) -> None:
        codes = [_codes(n) for n in names]
        lengths = np.array([len(c) for c in codes], np.int64)
        self.letters = np.unique(np.concatenate(codes)) if codes else np.zeros(0, np.uint32)
        kind = np.uint16 if len(self.letters) < 1 << 16 else np.uint32
        self.groups: list[tuple[int, np.ndarray, np.ndarray]] = []
        for length in np.unique(lengths):
            places = np.flatnonzero(lengths == length)
            for at in range(0, len(places), CHUNK):
                some = places[at : at + CHUNK]
                rows = np.stack([codes[i] for i in some]) if length else np.zeros((len(some), 0), np.uint32)
                self.groups.append((int(length), some, np.ascontiguousarray(np.searchsorted(self.letters, rows).astype(kind).T)))

    def nearest(self, label: str) -> tuple[int, float]:
        """Place and similarity of the nearest name: one minus the edits over the longer length; the first of equals."""
        text = _codes(label)
        at = np.searchsorted(self.letters, text)
        known = at < len(self.letters)
        known[known] = self.letters[at[known]] == text[known]
        at[~known] = -1
        best = (-1.0, 0, 0.0)
        for length, places, columns in self.groups:
            longest = max(length, len(text))
            edits = (_by_words if len(text) <= WORD else _by_cells)(at, columns, len(self.letters))
            sims = 1 - edits / longest if longest else np.ones(len(places))
            i = int(edits.argmin())
            best = max(best, (round(float(sims[i]), 9), -int(places[i]), float(sims[i])))
        return -best[1], best[2]


def _by_words(label: np.ndarray, columns: np.ndarray, n_letters: int) -> np.ndarray:
    """Edits between a label of at most 64 letters and each name; differences down a column are the bits of two words."""
    m, n = len(label), columns.shape[1]
    edits = np.full(n, m, np.int64)
    if not m:
        return edits + len(columns)
    one, last = np.uint64(1), np.uint64(m - 1)
    where = np.zeros(n_letters, np.uint64)
    for i, c in enumerate(label):
        if c >= 0:
            where[c] |= one << np.uint64(i)
    up, down = np.full(n, ~np.uint64(0)), np.zeros(n, np.uint64)
    for column in columns:
        same = where[column]
        level = same | down
        carried = (((same & up) + up) ^ up) | same
        rise, fall = down | ~(carried | up), up & carried
        edits += ((rise >> last) & one).astype(np.int64)
        edits -= ((fall >> last) & one).astype(np.int64)
        rise = (rise << one) | one
        up, down = (fall << one) | ~(level | rise), rise & level
    return edits


def _by_cells(label: np.ndarray, columns: np.ndarray, n_letters: int) -> np.ndarray:
    """The same for a label of any length, cell by cell."""
    n = columns.shape[1]
    row = [np.full(n, j, np.int64) for j in range(len(columns) + 1)]
    for i, c in enumerate(label, 1):
        before, row = row, [np.full(n, i, np.int64)]
        for j, column in enumerate(columns, 1):
            row.append(np.minimum(np.minimum(before[j], row[-1]) + 1, before[j - 1] + (column != c if c >= 0 else 1)))
    return row[-1]
