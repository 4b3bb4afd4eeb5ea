"""Media columns: payloads stored as lossless WebP and read back as pixel arrays.

A payload is padded with zero bytes to a positive multiple of 64 and stored as the 8-bit green
samples of one or more images, rows of at least 64 samples. Images of every size have prefix
codes of their own and back-references where these save bits; differences to the left or upper
sample, and a palette of up to 16 different bytes, which packs two to eight samples into one,
are taken if they are smaller. An ``oLEN`` chunk, which WebP readers skip, holds the padded
length. Longer payloads than one image holds are stored as several files in a row.

Defined results: null and empty texts are stored as 64 zero bytes; equal texts give equal
files and features; repeated rows are stored each; texts beyond ``MAX_IMAGE`` bytes become
several files, decoded one at a time; an empty table gives no rows. ``store_texts`` reads no
columns but doc_id and text; ``pixel_arrays`` passes all columns through, and one called like
its own gets an underscore before its name.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import webp
from .common import beside, bounded, extended, map_batches, named

UNIT = 64
SIDE = 16_384
#: Bytes of payload in one image: bounds what a task holds of a decoded one.
MAX_IMAGE = 1 << 20


def pad(data: bytes) -> bytes:
    return data + b"\0" * (max(UNIT, -(-len(data) // UNIT) * UNIT) - len(data))


def store(payload: bytes) -> bytes:
    """The stored form of a padded payload."""
    files = []
    for start in range(0, len(payload), MAX_IMAGE):
        part = np.frombuffer(payload[start : start + MAX_IMAGE], np.uint8)
        width = UNIT * -(-len(part) // (UNIT * SIDE))
        rows = -(-len(part) // width)
        samples = np.zeros(rows * width, np.uint8)
        samples[: len(part)] = part
        data = webp.encode_samples(samples, width)
        files.append(webp.container(data, (b"oLEN", struct.pack("<Q", len(part)))))
    return b"".join(files)


def files(media: bytes) -> Iterator[bytes]:
    """The files of a stored form, in order."""
    at = 0
    while at < len(media):
        size = 8 + struct.unpack("<I", media[at + 4 : at + 8])[0]
        yield media[at : at + size]
        at += size


def load(media: bytes) -> bytes:
    """The padded payload of a stored form, through the decoder."""
    out = []
    for image in files(media):
        n = struct.unpack("<Q", image[-8:])[0]
        out.append(webp.decode(image)[..., 2].astype(np.uint8).tobytes()[:n])
    return b"".join(out)


def feature(payload: bytes) -> str:
    """Mean and entropy of the samples, and a hash of where the mean rises along 65 equal stretches."""
    samples = np.frombuffer(payload, np.uint8)
    p = np.bincount(samples, minlength=256) / len(samples)
    p = p[p > 0]
    edges = np.linspace(0, len(samples), 66).astype(np.int64)
    sums = np.concatenate([[0], np.cumsum(samples, dtype=np.int64)])
    means = (sums[edges[1:]] - sums[edges[:-1]]) / np.maximum(1, edges[1:] - edges[:-1])
    rises = int.from_bytes(np.packbits(np.diff(means) > 0).tobytes(), "big")
    return f"mean={samples.mean():.4f};entropy={max(0.0, float(-(p * np.log2(p)).sum())):.4f};rise={rises:016x}"


_SCHEMA = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def _columns(batch: pa.RecordBatch, keep_media: bool) -> pa.RecordBatch:
    rows = []
    for text in batch.column("text").to_pylist():
        data = (text or "").encode()
        media = store(pad(data))
        back = load(media)
        row = [len(data), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-UNIT:]), len(media), hashlib.sha256(media).hexdigest(), feature(back)]
        rows.append(row + [media] * keep_media)
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.binary()][: 7 + keep_media]
    names = [x.split()[0] for x in _SCHEMA.split(", ")] + ["media"] * keep_media
    cols = zip(*rows, strict=True) if rows else [[]] * len(kinds)
    return pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], names)


def _work_media():
    return lambda batch: _columns(batch, True)


def _work_digest():
    return lambda batch: _columns(batch, False)


def store_texts(docs: DataFrame, keep_media: bool = True) -> DataFrame:
    """Each text's stored form (``media``, if kept), checked by reading it back, and its features."""
    kept = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return map_batches(kept, _work_media if keep_media else _work_digest, _SCHEMA + ", media binary" * keep_media)


def pixel_arrays(media: DataFrame, column: str = "media") -> DataFrame:
    """Adds ``image``, ``height``, ``width`` and ``argb`` (four bytes a pixel, in rows): a row for each file of a stored form, numbered from 0.

    Null and empty media give one row with nulls. The files of a row leave one at a time.
    """
    # the columns travel as one struct, so their names never meet those of others
    rows = media.select(F.struct(*beside(media, *_PIXELS)).alias("kept"), named(media, column).alias("media"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, m in enumerate(batch.column("media").to_pylist()):
                row = batch.column("kept").slice(i, 1)
                for n, image in enumerate(files(m)) if m else [(None, None)]:
                    c = webp.decode(image) if m else None
                    shape = [pa.array([c.shape[k] if m else None], pa.int32()) for k in (0, 1)]
                    argb = pa.array([c.astype(np.uint8).tobytes() if m else None], pa.binary())
                    yield pa.RecordBatch.from_arrays([row, pa.array([n], pa.int32()), *shape, argb], ["kept", *_PIXELS])

    found = bounded(rows).mapInArrow(run, extended(rows.select("kept"), "image int, height int, width int, argb binary"))
    return found.select("kept.*", *_PIXELS)


_PIXELS = ("image", "height", "width", "argb")
