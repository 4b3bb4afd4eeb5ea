"""Sampled segmentations over a SentencePiece vocabulary, and lossless decoding.

A piece's weight follows its rank (``-alpha * ln(rank + 2)``), so a segmentation's probability
is in proportion to the product of its pieces' weights. No piece holds a blank behind another
character (checked when the vocabulary is read), so a text's lattice falls into the lattices of
its units, a run of blanks with what follows it. For each different unit the forward sums over
its lattice give, at every place, the distribution of the piece that ends there; drawing from
the end back to the start samples whole segmentations exactly. New units of a slice of rows are
matched and summed together, and all its units are drawn together; the draws are hashes of the
row's key, the unit's place and the step, so a row gets the same pieces in any layout and on
any run.

A character that is no piece is written as its bytes' pieces; so is the sign that stands for a
blank in pieces, where a text holds it, and decoding gives back the very text. Characters that
occur in no longer piece are units of their own.

``encode_pieces`` gives the likeliest segmentation instead of a sampled one: the same lattices,
with the best way to each place in place of the sum over all ways (ties: the longer last piece).

Defined results: null and empty texts have no pieces; a null key is a key of its own; repeated
rows get equal pieces; very long texts are read whole, and a single unit of n characters (no
blank or other boundary in it) takes memory in proportion to n; an empty table gives no rows.
Kept columns pass through unread, whatever their names; one called like an output column gets
an underscore before its name.
"""

from __future__ import annotations

import math
import re
from functools import lru_cache, partial
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import beside, extended, free, map_batches, named

SEED = 7
ALPHA = 1.0
#: Edges of the lattices a task keeps, characters whose lattices are made at once, and characters of text in one slice: they bound its memory only.
CACHE = 1 << 21
LEARN = 1 << 18
SLICE = 1 << 17
BLANK = "▁"
_MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)
_SLOTS = 20


def text_hash(text: str) -> int:
    h = 0
    for c in text:
        h = (h + ord(c) + 1) * int(_MULTIPLIER) % (1 << 64)
    return h


class Pieces:
    """What sampling and decoding need of one SentencePiece file, picklable."""

    def __init__(self, path: str, alpha: float) -> None:
        from sentencepiece import SentencePieceProcessor

        model = SentencePieceProcessor(model_file=path)
        self.ids: dict[str, int] = {}
        self.byte_ids = [0] * 256
        self.texts: list[bytes] = []  # by id
        for i in range(model.get_piece_size()):
            piece = model.id_to_piece(i)
            if model.is_byte(i):
                self.byte_ids[int(piece[3:5], 16)] = i
                self.texts.append(bytes([int(piece[3:5], 16)]))
            elif model.is_control(i) or model.is_unknown(i) or model.is_unused(i):
                self.texts.append(b"")
            else:
                text = piece.replace(BLANK, " ")
                if " " in text.lstrip(" "):
                    raise ValueError(f"piece {i} holds a blank inside; units would not be apart")
                self.ids[text] = i
                self.texts.append(text.encode())
        if not all(self.byte_ids):
            raise ValueError("the vocabulary has no pieces for bytes")
        first = min(self.ids.values())
        self.weight = {t: -alpha * math.log(i - first + 2) for t, i in self.ids.items()}
        self.byte_weight = -alpha * math.log(len(self.texts) + 2)
        self.longest = max(map(len, self.ids))
        self.unit = self._unit_pattern()
        self._hash()

    def _unit_pattern(self) -> str:
        """Units by what stands side by side in some piece: a sign that follows no letter in any piece ends a unit of letters."""
        beside = {(a, b) for t in self.ids for a, b in zip(t, t[1:], strict=False) if a != " "}
        joined = {c for t in self.ids if len(t) > 1 for c in t} - {" "}
        letters = {c for c in joined if c.isalpha()}
        while more := {b for a, b in beside if a in letters and b not in letters}:
            letters |= more
        a, b = ("".join(map(re.escape, sorted(x))) for x in (letters, joined - letters))
        signs = f"[{b}]" if b else "(?!)"
        return f" *(?:{signs}*[{a}]+|{signs}+)| +|(?s:.)"

    def _hash(self) -> None:
        """A table by hash of all pieces and their beginnings, so that whole arrays of places are matched at once.

        Hashes have 64 bits; a stretch of text is mistaken for a piece with a chance of about 2e-15.
        """
        known = {t[:k]: -1 for t in self.ids for k in range(1, len(t))} | self.ids
        texts = list(known)
        hashes = np.array([text_hash(t) for t in texts], np.uint64)
        if len(np.unique(hashes)) != len(hashes):
            raise ValueError("two pieces share a hash")
        self.keys = np.zeros(1 << _SLOTS, np.uint64)
        self.values = np.full(1 << _SLOTS, -2, np.int64)
        self.weights = np.zeros(len(self.texts))
        for t, i in self.ids.items():
            self.weights[i] = self.weight[t]
        self.probes = 0
        for h, t in zip(hashes.tolist(), texts, strict=True):
            slot, n = h >> (64 - _SLOTS), 1
            while self.values[slot] != -2:
                slot, n = (slot + 1) & ((1 << _SLOTS) - 1), n + 1
            self.keys[slot], self.values[slot] = h, known[t]
            self.probes = max(self.probes, n)

    def find(self, hashes: np.ndarray) -> np.ndarray:
        """Ids by hash; -1: only a beginning of pieces, -2: neither."""
        slot = (hashes >> np.uint64(64 - _SLOTS)).astype(np.int64)
        out = np.full(len(hashes), -2, np.int64)
        open_ = np.arange(len(hashes))
        for _ in range(self.probes):
            hit = self.keys[slot[open_]] == hashes[open_]
            out[open_[hit]] = self.values[slot[open_[hit]]]
            open_ = open_[~hit & (self.values[slot[open_]] != -2)]
            if not len(open_):
                break
            slot[open_] = (slot[open_] + 1) & ((1 << _SLOTS) - 1)
        return out


@lru_cache(maxsize=4)
def pieces(path: str, alpha: float = ALPHA) -> Pieces:
    return Pieces(path, alpha)


def mix64(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser, for draws that depend on nothing but their key."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Index(dict):
    """Numbers its keys as they come."""

    def __missing__(self, key: str) -> int:
        self[key] = n = len(self)
        return n


class Sampler:
    """Samples slices of rows, or takes their likeliest segmentation (``best``); one per task."""

    def __init__(self, p: Pieces, best: bool = False) -> None:
        self.p, self.best = p, best
        self.split = re.compile(p.unit).findall
        self.raw: list[bytes] = []  # characters written as several bytes; id -k-1 stands for entry k
        self.raw_at: dict[str, int] = {}
        self._forget()

    def _forget(self) -> None:
        self.index = Index()
        #: By unit its length and first node; by node its first edge; by edge id, length and running probability.
        self.length, self.base, self.first = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(1, np.int64)
        self.ids, self.back, self.running = np.zeros(0, np.int32), np.zeros(0, np.uint8), np.zeros(0)

    def _character(self, c: str) -> tuple[int, float]:
        """How a character that is no piece is written, and its weight."""
        raw = c.encode()
        if len(raw) == 1:
            return self.p.byte_ids[raw[0]], self.p.byte_weight
        if c not in self.raw_at:
            self.raw_at[c] = len(self.raw)
            self.raw.append(raw)
        return -self.raw_at[c] - 1, self.p.byte_weight * len(raw)

    def _learn(self, units: list[str]) -> None:
        """Adds the lattices of new units."""
        p = self.p
        chars = np.frombuffer("".join(units).encode("utf-32-le"), np.uint32)
        n = len(chars)
        length = np.fromiter(map(len, units), np.int64, len(units))
        base = np.cumsum(length) - length
        left = np.repeat(base + length, length) - np.arange(n)
        most = int(min(p.longest, length.max()))
        found = np.full((n, most), -(1 << 30), np.int32)  # by end and length
        weight = np.full((n, most), -np.inf)
        at, h = np.arange(n), np.zeros(n, np.uint64)
        for size in range(1, most + 1):
            inside = left[at] >= size
            at, h = at[inside], h[inside]
            h = (h + chars[at + size - 1] + np.uint64(1)) * _MULTIPLIER
            ids = p.find(h)
            hit = ids >= 0
            found[at[hit] + size - 1, size - 1] = ids[hit]
            weight[at[hit] + size - 1, size - 1] = p.weights[ids[hit]]
            at, h = at[ids > -2], h[ids > -2]
        lone = np.flatnonzero(weight[:, 0] == -np.inf)
        if len(lone):
            kinds, which = np.unique(chars[lone], return_inverse=True)
            written = [self._character(chr(c)) for c in kinds]
            found[lone, 0] = np.array([i for i, _ in written])[which]
            weight[lone, 0] = np.array([w for _, w in written])[which]
        # forward sums, a place of all units at a time; each unit has a slot before its first character
        slot = np.arange(n) + np.repeat(np.arange(len(units)), length) + 1
        forward = np.zeros(n + len(units))
        sizes = np.arange(1, most + 1)
        longest_first = np.argsort(-length, kind="stable")
        sorted_base, sorted_length = base[longest_first], length[longest_first]
        for j in range(int(length.max())):
            end = sorted_base[: np.searchsorted(-sorted_length, -j, side="left")] + j
            k = min(j + 1, most)
            ways = weight[end, :k] + forward[slot[end][:, None] - sizes[:k]]
            top = ways.max(axis=1, keepdims=True)
            if self.best:
                forward[slot[end]] = top[:, 0]
                last = k - 1 - np.argmax(ways[:, ::-1] == top, axis=1)
                weight[end, :k] = np.where(np.arange(k) == last[:, None], 0.0, -np.inf)
                continue
            total = top[:, 0] + np.log(np.exp(ways - top).sum(axis=1))
            forward[slot[end]] = total
            weight[end, :k] = ways - total[:, None]
        # longer pieces first: they are likelier, and draws look at one after the other
        node, size = np.nonzero(weight[:, ::-1] > -np.inf)
        size = most - 1 - size
        counts = np.bincount(node, minlength=n)
        ends = np.cumsum(counts)
        running = np.cumsum(np.exp(weight[node, size]))
        running -= np.repeat(np.concatenate([[0.0], running[ends[:-1] - 1]]), counts)
        running[ends - 1] = 1.0
        nodes = len(self.first) - 1
        self.running = np.concatenate([self.running, running])
        self.ids = np.concatenate([self.ids, found[node, size]])
        self.back = np.concatenate([self.back, (size + 1).astype(np.uint8)])
        self.base = np.concatenate([self.base, base + nodes])
        self.length = np.concatenate([self.length, length])
        self.first = np.concatenate([self.first, ends + self.first[-1]])

    def __call__(self, texts: list[str], keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All ids of the slice in order, and where each row's begin (one more entry than rows)."""
        if len(self.ids) > CACHE:
            self._forget()
        index = self.index
        known = len(index)
        units: list[int] = []
        per_row = np.zeros(len(texts), np.int64)
        for r, text in enumerate(texts):
            found = self.split(" " + text) if text else []
            units.extend(map(index.__getitem__, found))
            per_row[r] = len(found)
        if not units:
            return np.zeros(0, np.int64), np.zeros(len(texts) + 1, np.int64)
        if len(index) > known:
            part, size = [], 0
            for unit in islice(index, known, None):
                if part and size + len(unit) > LEARN:
                    self._learn(part)
                    part, size = [], 0
                part.append(unit)
                size += len(unit)
            self._learn(part)
        which = np.array(units, np.int64)
        row = np.repeat(np.arange(len(texts)), per_row)
        place = np.arange(len(units)) - np.repeat(np.cumsum(per_row) - per_row, per_row)
        seed = mix64(keys.view(np.uint64)[row] + place.astype(np.uint64) * _MULTIPLIER)
        at, active, base = self.length[which], np.arange(len(units)), self.base[which]
        taken: list[tuple[np.ndarray, np.ndarray]] = []
        while len(active):
            step = np.uint64(len(taken) * 0xD1B54A32D192ED03 % (1 << 64))
            draws = (mix64(seed[active] + step) >> np.uint64(11)) * 2.0**-53
            edge = self.first[base[active] + at[active] - 1]
            behind = np.flatnonzero(draws >= self.running[edge])
            while len(behind):
                edge[behind] += 1
                behind = behind[draws[behind] >= self.running[edge[behind]]]
            taken.append((active, self.ids[edge]))
            at[active] -= self.back[edge]
            active = active[at[active] > 0]
        n_pieces = np.zeros(len(units), np.int64)
        for who, _ in taken:
            n_pieces[who] += 1
        ends = np.cumsum(n_pieces)
        out = np.empty(int(ends[-1]), np.int64)
        for k, (who, what) in enumerate(taken):  # drawn from the end
            out[ends[who] - 1 - k] = what
        bounds = np.concatenate([[0], ends])[np.concatenate([[0], np.cumsum(per_row)])]
        return self._bytes(out, bounds)

    def _bytes(self, out: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Writes the characters that take several byte pieces."""
        at = np.flatnonzero(out < 0)
        if not len(at):
            return out, bounds
        size = np.ones(len(out), np.int64)
        size[at] = [len(self.raw[-x - 1]) for x in out[at]]
        begin = np.concatenate([[0], np.cumsum(size)])
        wide = np.repeat(out, size)
        for k, x in zip(at, out[at], strict=True):
            wide[begin[k] : begin[k + 1]] = [self.p.byte_ids[b] for b in self.raw[-x - 1]]
        return wide, begin[bounds]


def encode(text: str, key: int, p: Pieces) -> list[int]:
    """The sampled pieces of one text."""
    return Sampler(p)([text], np.array([key], np.int64))[0].tolist()


def encode_best(text: str, p: Pieces) -> list[int]:
    """The likeliest pieces of one text."""
    return Sampler(p, best=True)([text], np.zeros(1, np.int64))[0].tolist()


def decode(ids: list[int], p: Pieces) -> str:
    """The text of a sequence of pieces; those of bytes stand together in whole characters."""
    return b"".join(map(p.texts.__getitem__, ids)).decode()[1:]


def _work(shared, best: bool):
    p: Pieces = shared.value
    sample = Sampler(p, best)

    def of(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts, keys = [t or "" for t in batch.column("text").to_pylist()], batch.column("key").to_numpy()
        parts, ends, same, first, size = [], [np.zeros(1, np.int64)], [], 0, 0
        for i, text in enumerate(texts):
            size += len(text)
            if size < SLICE and i + 1 < len(texts):
                continue
            ids, bounds = sample(texts[first : i + 1], keys[first : i + 1])
            flat, b = ids.tolist(), bounds.tolist()
            same += [decode(flat[b[k] : b[k + 1]], p) == t for k, t in enumerate(texts[first : i + 1])]
            ends.append(bounds[1:] + ends[-1][-1])
            parts.append(ids)
            first, size = i + 1, 0
        ids, bounds = np.concatenate([np.zeros(0, np.int64), *parts]), np.concatenate(ends)
        lists = pa.ListArray.from_arrays(pa.array(bounds, pa.int32()), pa.array(ids.astype(np.int32)))
        return pa.RecordBatch.from_arrays([batch.column("kept"), lists, pa.array(np.diff(bounds), pa.int64()), pa.array(same, pa.bool_())], ["kept", *_OUT])

    return of


_OUT = ("ids", "n_pieces", "lossless")


def _encoded(docs: DataFrame, path: str, keep: tuple[str, ...], alpha: float, seed: int, best: bool) -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(pieces(path, alpha))
    # the kept columns travel as one struct, so their names never meet those of others
    chosen = docs.select(*(named(docs, c) for c in keep)).columns
    kept = F.struct(*(named(docs, c).alias(n) for c, n in zip(keep, free(chosen, *_OUT), strict=True))) if keep else F.lit(None).cast("int")
    rows = docs.select(kept.alias("kept"), F.col("text").cast("string").alias("text"), F.xxhash64(F.lit(seed), F.col("doc_id").cast("long")).alias("key"))
    found = map_batches(rows, partial(_work, shared, best), extended(rows.select("kept"), "ids array<int>, n_pieces long, lossless boolean"), rows=256)
    return found.select(*(["kept.*"] if keep else []), *_OUT)


def sample_pieces(docs: DataFrame, path: str, keep: tuple[str, ...] = ("doc_id",), alpha: float = ALPHA, seed: int = SEED) -> DataFrame:
    """The columns in ``keep`` with ids, n_pieces, and lossless: whether the ids, decoded, are the text."""
    return _encoded(docs, path, keep, alpha, seed, best=False)


def encode_pieces(docs: DataFrame, path: str, keep: tuple[str, ...] = ("doc_id",), alpha: float = ALPHA) -> DataFrame:
    """The same for the likeliest segmentation, which needs no seed."""
    return _encoded(docs, path, keep, alpha, SEED, best=True)


def decode_pieces(pieces_: DataFrame, path: str, ids: str = "ids") -> DataFrame:
    """Adds ``decoded``, the text of each row's ids (null: null)."""
    shared = pieces_.sparkSession.sparkContext.broadcast(pieces(path))
    kept = F.struct(*beside(pieces_, "decoded")).alias("kept")

    def make():
        p = shared.value

        def of(batch: pa.RecordBatch) -> pa.RecordBatch:
            texts = [None if x is None else decode(x, p) for x in batch.column("ids").to_pylist()]
            return pa.RecordBatch.from_arrays([batch.column("kept"), pa.array(texts, pa.string())], ["kept", "decoded"])

        return of

    rows = pieces_.select(kept, named(pieces_, ids).alias("ids"))
    return map_batches(rows, make, extended(rows.select("kept"), "decoded string")).select("kept.*", "decoded")
