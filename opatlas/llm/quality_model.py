"""Quality classifier: histogram gradient-boosted trees over document statistics.

Statistics are computed where the texts lie. The trees are fitted on the driver from the
statistics (not the texts) of a sample of labelled rows bounded by ``SAMPLE_ROWS``, and
flattened into three arrays, which tasks traverse for a whole slice of rows at a time.

Defined results: null and empty texts have all statistics zero and get the score of that
vector; labels that are null, or whose document is missing, are not learnt from; several
labels of one document count once, by their rounded mean; without labels of both kinds the
score is the share of label 1 (0.5 without any). Repeated rows get equal scores, and scores
tie only where all statistics do. Very long texts are read whole, in linear time and memory; an
empty table gives no rows. Columns other than doc_id and text are never read; ``keep`` gives
back the columns it was given, whatever their names.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass
from functools import partial
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import extended, map_batches, packed

SAMPLE_ROWS = 20_000
THRESHOLD = 0.3
FOLDS = 5
SYMBOLS = b"#*$%&|<>"
FEATURES = (
    "log_bytes", "log_words", "upper_share", "digit_share", "blank_share", "symbol_share", "bang_share", "bar_share", "comma_stop_share",
    "other_punct_share", "high_share", "word_bytes", "distinct_share", "same_as_last_share", "top_word_share", "upper_word_share",
    "line_words", "repeated_line_share", "stop_words_per_word", "control_share",
)


def statistics(text: str | None) -> list[float]:
    """The document statistics, in the order of ``FEATURES``; one pass over bytes, one over words."""
    data = (text or "").encode()
    if not data:
        return [0.0] * len(FEATURES)
    n = len(data)
    c = np.bincount(np.frombuffer(data, np.uint8), minlength=256)
    w = data.split()
    k = len(w)
    if not k:
        return [float(np.log1p(n)), *[0.0] * 3, 1.0, *[0.0] * (len(FEATURES) - 5)]
    lines = [x for x in data.split(b"\n") if x and not x.isspace()]
    symbols, bars = int(c[list(SYMBOLS)].sum()), int(c[ord("|")])
    letters = int(c[65:91].sum() + c[97:123].sum())
    stops = int(c[ord(".")] + c[ord(",")])
    punct = int(c[33:48].sum() + c[58:65].sum() + c[91:97].sum() + c[123:127].sum())
    return [
        float(np.log1p(n)), float(np.log1p(k)), float(c[65:91].sum()) / max(1, letters), float(c[48:58].sum()) / n,
        float(c[32] + c[9:14].sum()) / n, symbols / k, int(c[ord("!")]) / k, bars / k, stops / k, (punct - symbols - stops - int(c[ord("!")])) / k,
        float(c[128:].sum()) / n, (n - int(c[32] + c[9:14].sum())) / k, len(set(w)) / k, sum(map(eq, w, w[1:])) / k,
        Counter(w).most_common(1)[0][1] / k, sum(map(bytes.isupper, w)) / k, k / max(1, len(lines)), 1 - len(set(lines)) / max(1, len(lines)),
        int(c[ord(".")]) / k, float(c[:9].sum() + c[14:32].sum() + c[127]) / n,
    ]


@dataclass
class Trees:
    """Complete binary trees, node i's children at 2i+1 and 2i+2; a row goes right if above the threshold."""

    feature: np.ndarray  # (trees, 2^depth - 1)
    threshold: np.ndarray  # likewise
    leaf: np.ndarray  # (trees, 2^depth)
    start: float

    def score(self, x: np.ndarray) -> np.ndarray:
        total = np.full(len(x), self.start)
        rows, inner = np.arange(len(x)), self.feature.shape[1]
        depth = (inner + 1).bit_length() - 1
        for f, t, v in zip(self.feature, self.threshold, self.leaf, strict=True):
            at = np.zeros(len(x), np.int64)
            for _ in range(depth):
                at = 2 * at + 1 + (x[rows, f[at]] > t[at])
            total += v[at - inner]
        return 1 / (1 + np.exp(-total))


def fit(x: np.ndarray, y: np.ndarray, trees: int = 80, depth: int = 4, rate: float = 0.15, bins: int = 64, l2: float = 2.0, least: int = 10) -> Trees:
    """Second-order boosting of the logistic loss; splits are sought in histograms of binned features."""
    inner = (1 << depth) - 1
    share = float(y.mean()) if len(y) else 0.5
    if not len(y) or not 0 < share < 1:
        share = min(max(share, 1e-6), 1 - 1e-6)
        return Trees(np.zeros((0, inner), np.int64), np.zeros((0, inner)), np.zeros((0, inner + 1)), float(np.log(share / (1 - share))))
    cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) for j in range(x.shape[1])]
    binned = np.stack([np.searchsorted(c, x[:, j], side="left") for j, c in enumerate(cuts)], axis=1)
    d, start = x.shape[1], float(np.log(share / (1 - share)))
    feature, threshold, leaf = (np.zeros((trees, k), t) for k, t in ((inner, np.int64), (inner, float), (inner + 1, float)))
    threshold[:] = np.inf
    raw = np.full(len(y), start)
    offsets = np.arange(d) * bins
    for t in range(trees):
        p = 1 / (1 + np.exp(-raw))
        g, h = p - y, np.maximum(p * (1 - p), 1e-9)
        at = np.zeros(len(y), np.int64)
        for level in range(depth):
            first, width = (1 << level) - 1, 1 << level
            key = ((at - first)[:, None] * (d * bins) + offsets + binned).ravel()
            size = width * d * bins
            sums = [np.bincount(key, weights=np.repeat(v, d), minlength=size).reshape(width, d, bins).cumsum(axis=2) for v in (g, h, np.ones(len(y)))]
            (gl, hl, nl), (gt, ht, nt) = sums, (s[:, :, -1:] for s in sums)
            gain = gl**2 / (hl + l2) + (gt - gl) ** 2 / (ht - hl + l2) - gt**2 / (ht + l2)
            gain[(nl < least) | (nt - nl < least)] = 0
            for j, c in enumerate(cuts):
                gain[:, j, len(c) :] = 0
            best = gain.reshape(width, -1).argmax(axis=1)
            for i in range(width):
                j, b = divmod(int(best[i]), bins)
                if gain[i, j, b] > 1e-9:
                    feature[t, first + i], threshold[t, first + i] = j, cuts[j][b]
            at = 2 * at + 1 + (x[np.arange(len(y)), feature[t, at]] > threshold[t, at])
        node = at - inner
        value = -np.bincount(node, weights=g, minlength=inner + 1) / (np.bincount(node, weights=h, minlength=inner + 1) + l2)
        leaf[t] = rate * value
        raw += leaf[t, node]
    return Trees(feature, threshold, leaf, start)


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % FOLDS == 0, F.lit(False))


def _statistics_work():
    def of(batch: pa.RecordBatch) -> pa.RecordBatch:
        found = [statistics(t) for t in batch.column("text").to_pylist()]
        return pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("label"), pa.array(found, pa.list_(pa.float64()))], ["doc_id", "label", "x"])

    return of


def train(docs: DataFrame, labels: DataFrame, target: str = "quality", rows: int = SAMPLE_ROWS) -> Trees:
    """Trees from the labelled documents outside the held-out fold, at most about ``rows`` of them."""
    known = labels.where(F.col(target).isNotNull() & F.col("doc_id").isNotNull()).groupBy(F.col("doc_id").cast("long").alias("_l")).agg(F.round(F.avg(target)).alias("label"))
    known = known.where(~held_out(F.col("_l")))
    total = known.count()
    if total > rows:
        known = known.where(F.pmod(F.xxhash64("_l"), F.lit(1 << 30)) < int((1 << 30) * rows / total))
    joined = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(known), F.col("doc_id") == F.col("_l"))
    found = map_batches(joined.select("doc_id", "label", "text"), _statistics_work, "doc_id long, label double, x array<double>").toPandas()
    found = found.sort_values("doc_id", kind="stable")
    x = np.array(found["x"].tolist(), float).reshape(len(found), len(FEATURES))
    return fit(x, found["label"].to_numpy(float))


def _score_work(shared):
    model = shared.value

    def of(batch: pa.RecordBatch) -> pa.RecordBatch:
        x = np.array([statistics(t) for t in batch.column("text").to_pylist()], float).reshape(batch.num_rows, len(FEATURES))
        keep = [n for n in batch.schema.names if n != "text"]
        return pa.RecordBatch.from_arrays([*(batch.column(n) for n in keep), pa.array(model.score(x), pa.float64())], [*keep, "score"])

    return of


def score(docs: DataFrame, model: Trees) -> DataFrame:
    """doc_id and score of every row of ``docs``."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kept = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return map_batches(kept, partial(_score_work, shared), "doc_id long, score double")


def keep(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """The documents that score at least the threshold, with the columns they came with."""
    shared = docs.sparkSession.sparkContext.broadcast(train(docs, labels))
    rows = docs.select(packed(docs).alias("doc"), F.col("text").cast("string").alias("text"))
    scored = map_batches(rows, partial(_score_work, shared), extended(rows.drop("text"), "score double"))
    return scored.where(F.col("score") >= threshold).select("doc.*")


def digest(docs: DataFrame, labels: DataFrame) -> DataFrame:
    out = score(docs, train(docs, labels))
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
