"""Media columns: documents as lossless images, stored, read back and described.

A text's UTF-8 bytes, filled with spaces to a multiple of a row, are the red, green and blue samples of an
image 64 pixels wide; a text of more than 3 MB takes several files, one after the other. Files are compressed
with the format's own tools (palette or predictor, references, colour cache, fitted prefix codes), stored in a
table of the shared folder and read from there; decoding and features use the stored bytes only. Rows are taken a
few megabytes at a time, and their files are encoded and decoded together.

Defined results: null text is empty text, and an empty text is one row of spaces; equal texts, and so ties and
repeated rows, give equal values, a row for each; null ids and other columns do no harm; an empty table gives an
empty result; a very long text is one cell of several files, and memory is a few times its size.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterable, Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relseq.llm import store, webp, webp_reader, webp_writer

WIDTH = 64
ROW = 3 * WIDTH
FILL = 32
CHUNK_BYTES, CHUNK_ROWS = 4 << 20, 2048


def to_media(raws: list[bytes]) -> list[bytes]:
    """The files of each text."""
    pictures, counts = [], []
    for raw in raws:
        payload = raw + bytes([FILL]) * (-len(raw) % ROW if raw else ROW)
        rows = np.frombuffer(payload, np.uint8).reshape(-1, WIDTH, 3)
        pictures += [rows[at : at + webp.SIDE] for at in range(0, len(rows), webp.SIDE)]
        counts.append(-(-len(rows) // webp.SIDE))
    files = iter(webp_writer.encode_many(pictures))
    return [b"".join(islice(files, n)) for n in counts]


def from_media(cells: list[bytes]) -> list[np.ndarray]:
    """For each cell, height x width x 4 samples of all its files."""
    parts = [list(webp.files(cell)) for cell in cells]
    pixels = iter(webp_reader.decode_many([f for files in parts for f in files]))
    return [next(pixels) if len(files) == 1 else np.concatenate(list(islice(pixels, len(files)))) for files in parts]


def together(rows: Iterable[tuple], weight) -> Iterator[list[tuple]]:
    """Rows in lists of up to ``CHUNK_BYTES`` or ``CHUNK_ROWS``; a larger row is alone."""
    held, size = [], 0
    for row in rows:
        n = weight(row)
        if held and (size + n > CHUNK_BYTES or len(held) == CHUNK_ROWS):
            yield held
            held, size = [], 0
        held.append(row)
        size += n
    if held:
        yield held


def samples_of(pixels: np.ndarray) -> np.ndarray:
    """Red, green and blue; copied by channel, which takes a fraction of the time."""
    out = np.empty((*pixels.shape[:2], 3), np.uint8)
    for c in range(3):
        out[..., c] = pixels[..., c]
    return out


def describe(pixels: np.ndarray) -> str:
    """Size, sums by channel, and an eight-band histogram of green."""
    sums = pixels[..., :3].sum(axis=(0, 1), dtype=np.int64)
    bands = np.bincount(pixels[..., 1].ravel() >> 5, minlength=8)
    return f"{pixels.shape[1]}x{pixels.shape[0]};" + ",".join(map(str, sums)) + ";" + ",".join(map(str, bands))


def encode_media(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_bytes, media binary)."""

    def texts(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, bytes]]:
        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                yield doc, text.as_buffer().to_pybytes() if text.is_valid else b""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in together(texts(batches), lambda row: len(row[1])):
            ids, raws = zip(*rows)
            columns = [pa.array(ids, pa.int64()), pa.array(map(len, raws), pa.int64()), pa.array(to_media(raws), pa.binary())]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n_bytes", "media"])

    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(run, "doc_id long, n_bytes long, media binary")


def media_features(stored: DataFrame) -> DataFrame:
    """Decodes ``media`` and describes what it holds."""
    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
    types = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]

    def cells(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, int, bytes]]:
        for batch in batches:
            for doc, n, cell in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)):
                yield doc, n, cell.as_buffer().to_pybytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in together(cells(batches), lambda row: row[1]):
            out = []
            for (doc, n, media), pixels in zip(rows, from_media([media for _, _, media in rows])):
                payload = samples_of(pixels).tobytes()
                out.append((doc, n, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(media), hashlib.sha256(media).hexdigest(), describe(pixels)))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), types)], names)

    return stored.select("doc_id", "n_bytes", "media").mapInArrow(run, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")


def op2_media_lossless_webp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_features(store.materialise(encode_media(store.table(spark, sf_dir, "documents")), "media"))
