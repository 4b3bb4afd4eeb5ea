"""Token counts with a whole-token shortcut.

Once per vocabulary, on the driver, every vocabulary string is put through the merges; those
that come out as one token and that the splitting pattern leaves whole are proven. A text is
then split by the pattern, proven pre-tokens count one each without any merging, and only the
rest are merged, each different one once per task while it stays in a bounded cache.

Defined results: null and empty texts have no bytes and no tokens. A special string inside a
text is one token, as the library takes it by default. The proven table is bounded by the
vocabulary (about 50,000 short strings) and is sent as a broadcast variable. Very long texts
are counted whole; a single pre-token of n bytes is merged in n log n time. Repeated rows get
equal counts, an empty table gives no rows, and columns other than doc_id and text are not
read, whatever their names.
"""

from __future__ import annotations

import heapq
import json
from functools import lru_cache, partial

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches

LIMIT = 512
CACHE = 200_000
#: The byte-level splitting pattern, with white space spelt out as the Unicode property.
PATTERN = (
    r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+"
    r"|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+"
)


def byte_letters() -> dict[str, int]:
    """The printable letter that stands for each byte in byte-level vocabularies."""
    plain = [*range(ord("!"), ord("~") + 1), *range(ord("¡"), ord("¬") + 1), *range(ord("®"), ord("ÿ") + 1)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


def merged_count(data: bytes, ranks: dict[tuple[bytes, bytes], int]) -> int:
    """How many tokens the merges leave of one pre-token; lowest rank first, then leftmost.

    A heap over a linked list, so a pre-token of n bytes takes n log n steps.
    """
    parts: list[bytes] = [data[i : i + 1] for i in range(len(data))]
    n = len(parts)
    nxt, prv = list(range(1, n + 1)), list(range(-1, n - 1))
    heap = [(r, i, parts[i], parts[i + 1]) for i in range(n - 1) if (r := ranks.get((parts[i], parts[i + 1]))) is not None]
    heapq.heapify(heap)
    left = n
    while heap:
        _, i, a, b = heapq.heappop(heap)
        j = nxt[i]
        if parts[i] != a or j >= n or parts[j] != b:
            continue  # one side has been merged meanwhile
        parts[i], parts[j] = a + b, b""
        nxt[i] = k = nxt[j]
        left -= 1
        if k < n:
            prv[k] = i
            if (r := ranks.get((parts[i], parts[k]))) is not None:
                heapq.heappush(heap, (r, i, parts[i], parts[k]))
        if (h := prv[i]) >= 0 and (r := ranks.get((parts[h], parts[i]))) is not None:
            heapq.heappush(heap, (r, h, parts[h], parts[i]))
    return left


class Vocabulary:
    """What counting needs of one byte-level BPE file, picklable."""

    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        letters = byte_letters()
        raw = lambda s: bytes(letters[c] for c in s)
        merges = [m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"]]
        self.ranks = {(raw(a), raw(b)): i for i, (a, b) in enumerate(merges)}
        self.specials = tuple(t["content"] for t in spec["added_tokens"])
        whole = regex.compile(PATTERN)
        self.proven: set[str] = set()
        for token in spec["model"]["vocab"]:
            if token in self.specials or any(c not in letters for c in token):
                continue
            try:
                text = raw(token).decode()
            except UnicodeDecodeError:
                continue  # part of a character is never a pre-token
            if whole.fullmatch(text) and whole.match(text).end() == len(text) and merged_count(raw(token), self.ranks) == 1:
                self.proven.add(text)


@lru_cache(maxsize=4)
def vocabulary(path: str) -> Vocabulary:
    return Vocabulary(path)


class Counter:
    """Counts tokens of texts; one per task."""

    def __init__(self, v: Vocabulary) -> None:
        self.split, self.ranks = regex.compile(PATTERN).findall, v.ranks
        self.special = regex.compile("|".join(map(regex.escape, sorted(v.specials, key=len, reverse=True)))) if v.specials else None
        self.proven, self.rest = v.proven, {}

    def _plain(self, text: str) -> int:
        found = self.split(text)
        other = [t for t in found if t not in self.proven]
        n, rest = len(found) - len(other), self.rest
        for t in other:
            k = rest.get(t)
            if k is None:
                if len(rest) >= CACHE:
                    rest.clear()
                k = rest[t] = merged_count(t.encode(), self.ranks)
            n += k
        return n

    def __call__(self, text: str) -> int:
        if self.special is None:
            return self._plain(text)
        parts = self.special.split(text)
        return len(parts) - 1 + sum(map(self._plain, parts))


def _work(shared, limit: int):
    count = Counter(shared.value)

    def of(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts = [t or "" for t in batch.column("text").to_pylist()]
        tokens = [count(t) for t in texts]
        return pa.RecordBatch.from_arrays(
            [
                batch.column("doc_id"),
                pa.array([len(t.encode()) for t in texts], pa.int64()),
                pa.array(tokens, pa.int64()),
                pa.array([n > limit for n in tokens], pa.bool_()),
            ],
            ["doc_id", "n_bytes", "n_tokens", "over_limit"],
        )

    return of


def count_tokens(docs: DataFrame, path: str, limit: int = LIMIT) -> DataFrame:
    """doc_id, n_bytes, n_tokens and over_limit for every row of ``docs``."""
    shared = docs.sparkSession.sparkContext.broadcast(vocabulary(path))
    kept = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return map_batches(kept, partial(_work, shared, limit), "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
