"""SimHash near-duplicates through a segment-popcount grid.

A 64-bit fingerprint is embedded as the bit counts of 16 segments of four bits. Two
fingerprints with at most two differing bits lie within Manhattan distance two in that
embedding, and two lattice points that near always share a lattice point at distance one or
less from both. So each distinct fingerprint is entered under its own cell and the 32 cells
beside it, equal cells are joined, and pairs are verified on the bits.

A cell with more than ``CROWD`` fingerprints is not joined with itself: its fingerprints are
linked through the 65 words within one bit of each, which finds the same groups exactly and
puts at most 65 fingerprints under one word. Nothing is capped or left out.

Near copies by similarity (``near_groups``, ``dedup``) are texts whose sets of five-word shingles
have a Jaccard similarity of 0.8 or more. Fingerprints of such texts differ in up to a third of
their bits, and at that radius popcounts bound nothing: almost all cells are neighbours. So
candidates come from fingerprints of parts: shingles are sampled by their hash at a rate that
follows the text's length and dealt into ``GROUPS`` groups, and texts of like length that agree
in all of a group meet. At the least similarity two texts miss each other in all groups with a
chance of 0.3 % or less, and of far less above it. Candidates within ``NEAR_BITS`` bits of each
other, whose smallest shingles by ``BINS`` ranges of the hash differ in at most ``BIN_BITS`` bits (one
bit kept of each), are verified exactly on their whole sets. In each bucket all members are verified against
its ``HUBS`` most central ones, those that share most keys with most texts; then all pairs of a
bucket that are not yet connected are verified too. Where a bucket has more than ``CROWD`` members, they
are dealt into blocks, and a task compares all texts of two blocks on their whole sets, unsifted, and gives
back only links that connect what was not connected before them: rows follow the texts, while
the comparisons within tasks still follow the pairs. So a large group makes no pairs as rows, and a
bucket's size loses no pair; what can be missed is a pair that shares no key or, in a bucket that is not crowded, is sifted.

Defined results: null and empty texts have fingerprint zero and no shingles and link like any
other; equal fingerprints (texts) always link, so copies are reduced to one vertex first;
repeated rows share a component; very long texts are read whole, in time linear in their
length; an empty table gives no rows. Rows without a doc_id join what they link and get the
component of their fingerprint; in ``dedup`` they come after rows with one. Columns other than
doc_id and text are not read; ``dedup`` gives all of them back, whatever their names.
"""

from __future__ import annotations

import math
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from ..operators.components import components
from ..plans.planning import BROADCAST_ROWS
from ..session import cut
from .common import map_batches, packed

SEED = 42
SHINGLE = 3
MAX_BITS = 2
SEGMENTS = 16
CROWD = 48
#: Near copies: words of a shingle and least similarity.
NEAR_SHINGLE = 5
NEAR = 0.8
#: Groups of sampled shingles of a text, and how many shingles are sampled at least where there are more.
GROUPS = 16
SAMPLED = 24
#: Members of a bucket that all others are verified against.
HUBS = 4
#: Members of crowded buckets in a block, and about how many shingles they have at most.
BLOCK = 1024
BLOCK_SHINGLES = 1 << 20
#: A shingle that more pairs of two blocks share is counted by a matrix product; pairs of other shingles at once.
DENSE = 4096
_PAIRS = 1 << 22
#: Candidates differ in no more bits: 3.6 standard deviations above the mean of pairs at the least similarity.
NEAR_BITS = 20
#: Ranges of the hash whose smallest shingle leaves one bit, and in how many candidates differ at most. Each differs
#: with a chance of (1 - similarity) / 2, so 26 of 256 at the least similarity, and 3.6 standard deviations more.
BINS = 256
BIN_BITS = 43
_CHUNK = 1 << 15


def shingle_hashes(text: str | None, k: int):
    """XXH64 of the text's shingles in order, in bounded parts."""
    # bytes.lower() folds A-Z only and bytes.split() cuts at exactly the six blanks of the word rule
    w = (text or "").encode().lower().split()
    if w and len(w) < k:
        w, k = [b" ".join(w)], 1
    n = len(w) - k + 1 if w else 0
    for start in range(0, n, _CHUNK):
        part = w[start : min(start + _CHUNK, n) + k - 1]
        yield np.array([xxh64_intdigest(b" ".join(s), SEED) for s in zip(*(part[i:] for i in range(k)))], "<u8")


def _majority(parts) -> int:
    """The bits set in over half of all hashes."""
    ones, n = np.zeros(64, np.int64), 0
    for hashes in parts:
        ones += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        n += len(hashes)
    return int(np.packbits(2 * ones > n, bitorder="little").view("<u8")[0]) if n else 0


def fingerprint(text: str | None, k: int = SHINGLE) -> int:
    """The unsigned fingerprint of one text; shingles count as often as they occur."""
    return _majority(shingle_hashes(text, k))


def _work(k: int):
    def of(batch: pa.RecordBatch) -> pa.RecordBatch:
        found = np.array([fingerprint(t, k) for t in batch.column("text").to_pylist()], np.uint64).view(np.int64)
        return pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(found)], ["doc_id", "fp"])

    return of


def fingerprints(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """doc_id and ``fp``, the fingerprint as a signed long."""
    kept = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return map_batches(kept, partial(_work, shingle), "doc_id long, fp long")


def as_hex(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def _cells(fp: Column) -> Column:
    """The cell of a fingerprint and the 32 beside it; three bits hold each coordinate plus one."""
    width = 64 // SEGMENTS
    own = sum(
        (
            F.shiftleft((F.bit_count(F.shiftright(fp, width * s).bitwiseAND(F.lit((1 << width) - 1))) + 1).cast("long"), 3 * s)
            for s in range(SEGMENTS)
        ),
        F.lit(0).cast("long"),
    )
    steps = [0, *(sign << (3 * s) if sign > 0 else -(1 << (3 * s)) for s in range(SEGMENTS) for sign in (1, -1))]
    return F.transform(F.array(*(F.lit(x).cast("long") for x in steps)), lambda x: x + own)


def links(vertices: DataFrame) -> DataFrame:
    """Links between the distinct fingerprints in ``vertices`` (fp, id): lo < hi, both ids.

    Light cells give every linked pair, crowded ones enough links for the same components.
    """
    entered = vertices.select("fp", "id", F.explode(_cells(F.col("fp"))).alias("cell"))
    sizes = entered.groupBy("cell").agg(F.count("*").alias("n")).where("n > 1")
    placed = entered.join(sizes, "cell")
    a = placed.where(F.col("n") <= CROWD).select("cell", F.col("fp").alias("fa"), F.col("id").alias("a"))
    b = a.select("cell", F.col("fa").alias("fb"), F.col("a").alias("b"))
    near = F.bit_count(F.col("fa").bitwiseXOR(F.col("fb"))) <= MAX_BITS
    light = a.join(b, (a["cell"] == b["cell"]) & (F.col("fa") < F.col("fb")) & near).select("a", "b")

    crowd = placed.where(F.col("n") > CROWD).select("fp", "id").distinct()
    flips = F.array(F.lit(0).cast("long"), *(F.lit((1 << i) - (1 << 64 if i == 63 else 0)).cast("long") for i in range(64)))
    words = crowd.select("id", F.explode(F.transform(flips, lambda x: x.bitwiseXOR(F.col("fp")))).alias("word"))
    stars = words.join(words.groupBy("word").agg(F.min("id").alias("b"), F.count("*").alias("n")).where("n > 1"), "word")
    heavy = stars.where(F.col("id") != F.col("b")).select(F.col("id").alias("a"), "b")
    both = light.unionByName(heavy)
    return both.select(F.least("a", "b").alias("lo"), F.greatest("a", "b").alias("hi")).where("lo < hi").distinct()


def _spread(df: DataFrame, key: str) -> DataFrame:
    """``df`` over the session's shuffle partitions: checkpoints keep as few as adaptive execution left."""
    return df.repartition(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), key)


def resolve(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """doc_id, fp and component_id of every row of ``docs``."""
    prints = cut(fingerprints(docs, shingle))
    vertices = cut(_spread(prints.groupBy("fp").agg(F.min("doc_id").alias("id")), "fp"))
    # fingerprints are the nodes, so those of rows without an id link others too
    found = components(links(vertices.select("fp", F.col("fp").alias("id"))))
    rooted = vertices.join(found, vertices["fp"] == found["node"], "left").select(F.col("fp").alias("vfp"), F.coalesce("root", "fp").alias("root"), "id")
    least = rooted.groupBy(F.col("root").alias("r")).agg(F.min("id").alias("component_id"))
    named_ = rooted.join(least, F.col("root") == F.col("r")).select("vfp", "component_id")
    return prints.join(named_, prints["fp"] == named_["vfp"]).select("doc_id", "fp", "component_id")


def digest(docs: DataFrame) -> DataFrame:
    return resolve(docs).select("doc_id", as_hex(F.col("fp")).alias("fingerprint"), "component_id")


# --- near copies --------------------------------------------------------------------------


def shingle_set(text: str | None, k: int = NEAR_SHINGLE) -> np.ndarray:
    """The text's different shingles by hash, in order."""
    parts = list(shingle_hashes(text, k))
    return np.unique(np.concatenate(parts)) if parts else np.zeros(0, "<u8")


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def bucket_keys(shingles: np.ndarray, similarity: float = NEAR) -> np.ndarray:
    """A key for each group of the text's sampled shingles, in its band of lengths and the one below.

    Sets as similar as that differ by a band at most, so they share one, and with it the rate of
    the sample. A text without shingles has one key.
    """
    n = len(shingles)
    if not n:
        return np.zeros(1, np.uint64)
    step = -math.log(similarity)
    top, out = int(math.log(n) / step + 1e-9), []
    for band in {top, max(0, top - 1)}:
        rate = max(0, int(math.log2(math.exp(band * step) / SAMPLED + 1e-9)) if math.exp(band * step) >= SAMPLED else 0)
        sample = shingles[shingles & np.uint64((1 << rate) - 1) == 0]
        group = ((sample >> np.uint64(40)) * np.uint64(GROUPS) >> np.uint64(24)).astype(np.int64)
        # sums of mixed hashes, modulo 2 to the 64th, name a group's set in any order
        sums = np.zeros(GROUPS, np.uint64)
        np.add.at(sums, group, _mix(sample))
        used = np.unique(group)
        out.append(_mix(sums[used] + np.uint64(0x9E3779B97F4A7C15) * (used + GROUPS * (band + 1)).astype(np.uint64)))
    return np.concatenate(out)


def bin_bits(shingles: np.ndarray) -> np.ndarray:
    """One bit of the smallest shingle in each range of the hash (none: 0), as BINS / 64 longs; ``shingles`` are in order."""
    width = np.uint64(64 - int(math.log2(BINS)))
    used, first = np.unique(shingles >> width, return_index=True)
    bits = np.zeros(BINS, np.uint8)
    bits[used.astype(np.int64)] = _mix(shingles[first]) & np.uint64(1)
    return np.packbits(bits, bitorder="little").view("<i8")


def _near_work(k: int, similarity: float):
    def of(batch: pa.RecordBatch) -> pa.RecordBatch:
        fps, sizes, keys, bins = [], [], [], []
        for text in batch.column("text").to_pylist():
            s = shingle_set(text, k)
            fps.append(_majority([s]))
            sizes.append(len(s))
            keys.append(bucket_keys(s, similarity).view(np.int64))
            bins.append(bin_bits(s))
        lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum([len(x) for x in keys])]), pa.int32()), pa.array(np.concatenate([np.zeros(0, np.int64), *keys])))
        return pa.RecordBatch.from_arrays([batch.column("node"), batch.column("doc_id"), pa.array(np.array(fps, np.uint64).view(np.int64)), pa.array(sizes, pa.int64()), lists, pa.array(bins, pa.list_(pa.int64()))], ["node", "doc_id", "fp", "n", "keys", "bins"])

    return of


def _set_work(k: int):
    def of(batch: pa.RecordBatch) -> pa.RecordBatch:
        sets = [shingle_set(t, k).view(np.int64) for t in batch.column("text").to_pylist()]
        return pa.RecordBatch.from_arrays([batch.column("v"), pa.array(sets, pa.list_(pa.int64()))], ["v", "shingles"])

    return of


def _nodes(docs: DataFrame) -> DataFrame:
    """node (a digest of the text), doc_id and text of every row."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    return docs.select(F.md5(text).alias("node"), F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"))


def _sets(need: DataFrame, docs: DataFrame, k: int) -> DataFrame:
    """v and shingles of the texts in ``need`` (v, node); only those are read into sets."""
    # where they are few, by count, all other texts stay where they are; else both sides are exchanged
    need = cut(need)
    need = F.broadcast(need) if need.count() <= BROADCAST_ROWS else need
    # a text once, whatever its copies: those of its smallest id are few
    read = _nodes(docs).select("node", "text").join(need, "node").dropDuplicates(["v"])
    return map_batches(read.select("v", "text"), partial(_set_work, k), "v long, shingles array<long>")


def verified(pairs: DataFrame, texts: DataFrame, docs: DataFrame, k: int = NEAR_SHINGLE, similarity: float = NEAR) -> DataFrame:
    """Those of ``pairs`` (lo, hi: numbers in ``texts``) whose shingle sets are similar."""
    need = pairs.select(F.explode(F.array("lo", "hi")).alias("v")).distinct().join(texts.select("v", "node"), "v")
    sets = cut(_sets(need, docs, k))
    a, b = sets.select(F.col("v").alias("lo"), F.col("shingles").alias("sa")), sets.select(F.col("v").alias("hi"), F.col("shingles").alias("sb"))
    both = F.size(F.array_intersect("sa", "sb"))
    alike = (both >= F.lit(similarity) * (F.size("sa") + F.size("sb") - both) - 1e-9).alias("alike")
    return cut(pairs.join(a, "lo").join(b, "hi").select("lo", "hi", alike).where("alike").select("lo", "hi"))


def shared_counts(na: np.ndarray, sa: np.ndarray, nb: np.ndarray, sb: np.ndarray) -> np.ndarray:
    """How many shingles each set of one block shares with each of another: sizes, and the shingles of all sets in order."""
    common = np.intersect1d(sa, sb)
    out = np.zeros((len(na), len(nb)), np.float32)
    if not len(common):
        return out

    def postings(n: np.ndarray, s: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        at = np.minimum(np.searchsorted(common, s), len(common) - 1)
        held = common[at] == s
        at, rows = at[held], np.repeat(np.arange(len(n)), n)[held]
        by = np.argsort(at, kind="stable")
        count = np.bincount(at, minlength=len(common))
        return rows[by], count, np.cumsum(count) - count

    (ra, ca, fa), (rb, cb, fb) = postings(na, sa), postings(nb, sb)
    pairs = ca * cb
    dense = np.flatnonzero(pairs > DENSE)
    for start in range(0, len(dense), 1024):
        part = dense[start : start + 1024]
        x, y = np.zeros((len(na), len(part)), np.float32), np.zeros((len(nb), len(part)), np.float32)
        for m, rows, count, first in ((x, ra, ca, fa), (y, rb, cb, fb)):
            for col, t in enumerate(part):
                m[rows[first[t] : first[t] + count[t]], col] = 1
        out += x @ y.T
    rare = np.flatnonzero(pairs <= DENSE)
    ends = np.cumsum(pairs[rare])
    cuts = np.searchsorted(ends, np.arange(_PAIRS, (ends[-1] if len(ends) else 0) + _PAIRS, _PAIRS), side="right")
    for part in np.split(rare, np.unique(cuts)):
        if len(part):
            t = np.repeat(part, pairs[part])
            i = np.arange(len(t)) - np.repeat(np.cumsum(pairs[part]) - pairs[part], pairs[part])
            cell = ra[fa[t] + i // cb[t]] * len(nb) + rb[fb[t] + i % cb[t]]
            out += np.bincount(cell, minlength=out.size).reshape(out.shape)
    return out


def block_links(a: tuple, b: tuple, similarity: float = NEAR) -> list[tuple[int, int]]:
    """Pairs of similar texts of two blocks, each (numbers, roots, sizes, shingles): only those that connect roots not connected before."""
    (va, ra, na, sa), (vb, rb, nb, sb) = a, b
    both = shared_counts(na, sa, nb, sb)
    alike = both >= similarity * (na[:, None] + nb[None, :] - both) - 1e-9
    x, y = np.nonzero(alike & (ra[:, None] != rb[None, :]))
    # one pair for each two roots
    _, first = np.unique(np.stack([np.minimum(ra[x], rb[y]), np.maximum(ra[x], rb[y])]), axis=1, return_index=True)
    above: dict[int, int] = {}

    def top(r: int) -> int:
        while (up := above.get(r, r)) != r:
            above[r] = above.get(up, up)
            r = up
        return r

    out = []
    for p, q in zip(x[first].tolist(), y[first].tolist(), strict=True):
        r, s = top(int(ra[p])), top(int(rb[q]))
        if r != s:
            above[max(r, s)] = min(r, s)
            out.append((min(int(va[p]), int(vb[q])), max(int(va[p]), int(vb[q]))))
    return out


def _block_work(similarity: float):
    def members(column: pa.Array, row: int) -> tuple:
        held = column[row].values
        sets = held.field("shingles")
        return held.field("v").to_numpy(), held.field("root").to_numpy(), sets.value_lengths().to_numpy().astype(np.int64), sets.flatten().to_numpy()

    def of(batch: pa.RecordBatch) -> pa.RecordBatch:
        found = [e for row in range(batch.num_rows) for e in block_links(members(batch.column("a"), row), members(batch.column("b"), row), similarity)]
        return pa.RecordBatch.from_arrays([pa.array([e[i] for e in found], pa.int64()) for i in (0, 1)], ["lo", "hi"])

    return of


def crowd_links(crowds: DataFrame, texts: DataFrame, docs: DataFrame, k: int = NEAR_SHINGLE, similarity: float = NEAR) -> DataFrame:
    """Links (lo, hi) that connect all similar texts with a crowded bucket in common: ``crowds`` has key, c, v, n and root of the buckets' members.

    A text is dealt once, whatever its buckets, into a block of texts of its largest bucket; members of
    a root with ``BLOCK`` of them there have blocks of their own, which need not meet each other. Blocks
    that have a bucket in common meet in one task.
    """
    mine = crowds.groupBy("v").agg(F.min_by("key", F.struct(-F.col("c"), "key")).alias("main"), F.min("n").alias("n"), F.min("root").alias("root"))
    large = mine.groupBy("main", "root").agg(F.count("*").alias("m"))
    mine = mine.join(large, ["main", "root"]).withColumn("own", F.when(F.col("m") >= BLOCK, F.col("root")).otherwise(-1))
    parts = F.greatest(F.ceil(F.count("*") / BLOCK), F.ceil(F.sum("n") / BLOCK_SHINGLES))
    number = F.pmod(F.xxhash64("v"), F.col("parts"))
    # blocks whose names are alike by chance are one block
    dealt = mine.join(mine.groupBy("main", "own").agg(parts.alias("parts")), ["main", "own"]).select("v", "root", F.xxhash64("main", "own", number).alias("block"))
    dealt = cut(dealt)
    roots = dealt.groupBy("block").agg(F.min("root").alias("r0"), F.max("root").alias("r1"))
    at = cut(crowds.select("key", "v").join(dealt.select("v", "block"), "v").select("key", "block").distinct().join(roots, "block"))
    other = at.select("key", F.col("block").alias("j"), F.col("r0").alias("s0"), F.col("r1").alias("s1"))
    apart = F.least("r0", "s0") < F.greatest("r1", "s1")
    meet = at.withColumnRenamed("block", "i").join(other, "key").where((F.col("i") <= F.col("j")) & apart).select("i", "j").distinct()
    sets = _sets(dealt.join(texts.select("v", "node"), "v").select("v", "node"), docs, k)
    blocks = cut(sets.join(dealt, "v").groupBy("block").agg(F.collect_list(F.struct("v", "root", "shingles")).alias("members")))
    one = lambda i, a: blocks.select(F.col("block").alias(i), F.col("members").alias(a))
    both = meet.join(one("i", "a"), "i").join(one("j", "b"), "j").select("a", "b")
    return cut(map_batches(both, partial(_block_work, similarity), "lo long, hi long", rows=1))


def near_groups(docs: DataFrame, shingle: int = NEAR_SHINGLE, similarity: float = NEAR) -> DataFrame:
    """node, id (its smallest doc_id) and root of every different text: texts linked by near copies share a root."""
    prints = map_batches(_nodes(docs), partial(_near_work, shingle, similarity), "node string, doc_id long, fp long, n long, keys array<long>, bins array<long>")
    texts = prints.groupBy("node").agg(F.min("doc_id").alias("id"), F.min("fp").alias("fp"), F.min("n").alias("n"), F.min("keys").alias("keys"), F.min("bins").alias("bins"))
    # numbers are fixed by the checkpoint
    texts = cut(_spread(texts, "node").withColumn("v", F.monotonically_increasing_id()))
    size = F.count("*").over(Window.partitionBy("key"))
    # most keys are a text's own: what is compared follows only those that are not
    met = texts.select("v", F.explode("keys").alias("key")).withColumn("c", size).where("c > 1")
    shared = cut(met.join(texts.select("v", "fp", "n", "bins"), "v"))
    pair = [F.least("v", "w").alias("lo"), F.greatest("v", "w").alias("hi")]

    def near(a: str, b: str) -> Column:
        bits = F.bit_count(F.col("fp" + a).bitwiseXOR(F.col("fp" + b))) <= NEAR_BITS
        apart = F.aggregate(F.zip_with("bins" + a, "bins" + b, lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda x, y: x + y)
        return bits & (apart <= BIN_BITS) & (F.least("n" + a, "n" + b) >= F.lit(similarity) * F.greatest("n" + a, "n" + b) - 1e-9)

    central = shared.groupBy(F.col("v").alias("w")).agg(F.sum("c").alias("score"))
    members = shared.select("key", F.col("v").alias("w"), F.col("fp").alias("fpw"), F.col("n").alias("nw"), F.col("bins").alias("binsw")).join(central, "w")
    rank = F.row_number().over(Window.partitionBy("key").orderBy(F.desc("score"), "w"))
    hubs = members.withColumn("r", rank).where(F.col("r") <= HUBS).drop("score", "r")
    first = cut(shared.join(hubs, "key").where((F.col("v") != F.col("w")) & near("", "w")).select(*pair).distinct())
    edges = verified(first, texts, docs, shingle, similarity)
    found = components(edges)

    # what shares a bucket but no component yet
    placed = shared.join(found, F.col("v") == F.col("node"), "left").select("key", "c", "v", "fp", "n", "bins", F.coalesce("root", "v").alias("root"))
    small = placed.where(F.col("c") <= CROWD)
    other = small.select("key", *(F.col(c).alias(c + "w") for c in ("fp", "n", "bins", "root")), F.col("v").alias("w"))
    light = small.join(other, "key").where((F.col("v") < F.col("w")) & (F.col("root") != F.col("rootw")) & near("", "w")).select(*pair)
    cross = cut(light.distinct().join(first, ["lo", "hi"], "left_anti"))
    more = verified(cross, texts, docs, shingle, similarity)
    crowded = cut(placed.where(F.col("c") > CROWD).select("key", "c", "v", "n", "root"))
    # a bucket within one component has nothing to compare
    split = crowded.groupBy("key").agg(F.min("root").alias("r0"), F.max("root").alias("r1")).where("r0 < r1").select("key")
    tied = crowd_links(cut(crowded.join(split, "key")), texts, docs, shingle, similarity)
    found = components(found.select(F.col("root").alias("lo"), F.col("node").alias("hi")).unionByName(more).unionByName(tied))
    rooted = texts.select("node", "id", "v").join(found.withColumnRenamed("node", "_v"), F.col("v") == F.col("_v"), "left")
    return rooted.select("node", "id", F.coalesce("root", "v").alias("root"))


def dedup(docs: DataFrame, shingle: int = NEAR_SHINGLE, similarity: float = NEAR) -> DataFrame:
    """One row of each group of near copies, that of its smallest doc_id, with the columns of ``docs``.

    Of repeated rows of that id the one with the first text, then the first by all its columns, stays.
    """
    groups = near_groups(docs, shingle, similarity)
    # the join's keys are the window's, so the texts move once
    keys = lambda i: (F.coalesce(i, F.lit(0)).alias("k"), i.isNull().alias("z"))
    chosen = groups.groupBy("root").agg(F.min(F.struct(F.col("id").isNull().alias("no"), "id", "node")).alias("m")).select(F.col("m.node").alias("node"), *keys(F.col("m.id")))
    node = F.md5(F.coalesce(F.col("text").cast("string"), F.lit("")))
    rest = docs.drop("text")  # equal for equal nodes
    rows = docs.select(node.alias("node"), *keys(F.col("doc_id").cast("long")), F.to_json(packed(rest)).alias("_rest"), packed(docs).alias("_doc"))
    kept = rows.join(chosen, ["node", "k", "z"])
    one = kept.withColumn("_n", F.row_number().over(Window.partitionBy("node", "k", "z").orderBy("_rest"))).where("_n = 1")
    return one.select("_doc.*")
