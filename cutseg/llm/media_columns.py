"""Media columns: store payloads as baseline JPEG, read them back as DC-only
luminance thumbnails, and keep dimensions and hashes of the thumbnails."""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from cutseg.llm import jpeg
from cutseg.llm.words import small_batches

#: Payload bytes that are coded and decoded together; bounds a worker's memory.
CHUNK = 1 << 20
_MEDIA = "doc_id long, n_bytes long, media binary"
_DIGESTS = ("doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string,"
            " feature string, width int, height int, images int")
_THUMBS = "id long, width int, height int, images int, thumbnail binary, thumb_columns int, thumb_hash string, error string"


def padded(text: bytes | None) -> np.ndarray:
    """The text's bytes, with 255 appended up to a positive multiple of 576."""
    raw = text or b""
    n = max(1, -(-len(raw) // jpeg.UNIT)) * jpeg.UNIT
    return np.frombuffer(raw.ljust(n, b"\xff"), np.uint8)


def average_hash(thumb: np.ndarray) -> str:
    """64 bits: which cells of an 8 x 8 grid are brighter than the mean cell."""
    rows = np.linspace(0, thumb.shape[0], 9).astype(int)
    columns = np.linspace(0, thumb.shape[1], 9).astype(int)
    total = np.pad(thumb.astype(np.int64).cumsum(0).cumsum(1), ((1, 0), (1, 0)))[rows][:, columns]
    cells = np.diff(np.diff(total, axis=0), axis=1) / np.maximum(1, np.outer(np.diff(rows), np.diff(columns)))
    return np.packbits(cells > cells.mean()).tobytes().hex()


def difference_hash(thumb: np.ndarray) -> str:
    """64 bits: in which of 8 x 9 sampled places brightness rises to the right."""
    rows = np.linspace(0, thumb.shape[0] - 1, 8).astype(int)
    columns = np.linspace(0, thumb.shape[1] - 1, 9).astype(int)
    sample = thumb[np.ix_(rows, columns)].astype(int)
    return np.packbits(np.diff(sample, axis=1) > 0).tobytes().hex()


def read_back(media: list[bytes]) -> list[tuple[np.ndarray, int, int, int]]:
    """For each run of images: thumbnail rows, width, total height, images."""
    parts, headers, counts = [], [], []
    for raw in media:
        found = jpeg.split_images(raw)
        parts += [raw] * len(found)
        headers += found
        counts.append(len(found))
    thumbs = iter(zip(jpeg.thumbnails(parts, headers), headers))
    out = []
    for n in counts:
        own = [next(thumbs) for _ in range(n)]
        rows = own[0][0] if n == 1 else np.concatenate([t for t, _ in own])
        out.append((rows, own[0][1].width, sum(h.height for _, h in own), n))
    return out


def _chunks(texts: list[bytes | None]) -> Iterator[tuple[int, list[np.ndarray]]]:
    start, size, group = 0, 0, []
    for i, t in enumerate(texts):
        p = padded(t)
        if group and size + len(p) > CHUNK:
            yield start, group
            start, size, group = i, 0, []
        group.append(p)
        size += len(p)
    if group:
        yield start, group


def _store(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = batch.column(1).cast(pa.binary()).to_pylist()
        for start, group in _chunks(texts):
            n = len(group)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).slice(start, n), pa.array([len(t or b"") for t in texts[start:start + n]], pa.int64()), pa.array(jpeg.encode_flat(group), pa.binary())],
                ["doc_id", "n_bytes", "media"])


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts, rows = batch.column(1).cast(pa.binary()).to_pylist(), []
        for _, group in _chunks(texts):
            media = jpeg.encode_flat(group)
            for raw, (thumb, width, height, n) in zip(media, read_back(media)):
                payload = thumb.tobytes()
                rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(raw), hashlib.sha256(raw).hexdigest(),
                             f"{width}x{height}:{average_hash(thumb)}:{difference_hash(thumb)}", width, height, n))
        columns = list(zip(*rows)) or [()] * 9
        kinds = (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int32(), pa.int32(), pa.int32())
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array([len(t or b"") for t in texts], pa.int64()), *(pa.array(c, k) for c, k in zip(columns, kinds))],
            ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "width", "height", "images"])


def store_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_bytes, media``: each text as a run of JPEG images.

    A null text is stored as an empty one: a unit of 255s.
    """
    small_batches(docs.sparkSession)
    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].cast("string").alias("text")).mapInArrow(_store, _MEDIA)


def _describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = []
        for raw in batch.column(1).to_pylist():
            try:
                thumb, width, height, n = read_back([raw])[0] if raw else (None, None, None, 0)
                rows.append((width, height, n, thumb.tobytes(), thumb.shape[1], average_hash(thumb), None) if n else (None, None, 0, None, None, None, "empty"))
            except (jpeg.JpegError, LookupError, ValueError, struct.error) as e:
                rows.append((None, None, None, None, None, None, str(e) or type(e).__name__))
        columns = list(zip(*rows)) or [()] * 7
        kinds = (pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.int32(), pa.string(), pa.string())
        yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(columns, kinds))],
                                         ["id", "width", "height", "images", "thumbnail", "thumb_columns", "thumb_hash", "error"])


def describe_images(media: DataFrame, id_col: str = "id", media_col: str = "media") -> DataFrame:
    """Dimensions, thumbnail and hash of any baseline JPEG column; what cannot
    be read gets null dimensions and says why in ``error``."""
    small_batches(media.sparkSession)
    return media.select(media[id_col].cast("long").alias("id"), media[media_col].cast("binary").alias("media")).mapInArrow(_describe, _THUMBS)


def digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Store each text, read the stored bytes back, and describe both.

    One row per input row; equal texts have equal values, a null text those of
    an empty one.
    """
    small_batches(docs.sparkSession)
    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].cast("string").alias("text")).mapInArrow(_digest, _DIGESTS)


def op6_media_jpeg(spark, sf_dir: str) -> DataFrame:
    return digests(spark.read.parquet(f"{sf_dir}/documents.parquet"))
