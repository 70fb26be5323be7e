"""Media columns: bytes stored as 8-bit WAV, read back by the wave module, and fingerprinted.

A short-time Fourier transform gives the strongest bins of each frame; pairs of peaks in nearby frames become
landmarks (anchor bin, target bin, frame distance), kept with the anchor's frame as time codes.

Defined results: null is the empty text; any text, however long, is one clip; padding makes the payload a
positive multiple of 64 bytes; equal texts give equal values. Only the named columns are read.
"""

from __future__ import annotations

import hashlib
import io
import wave
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

RATE = 8000
SCHEMA = "id long, n_bytes long, media binary, payload_bytes long, payload_sha256 string, tail_crc32 long, frames array<int>, marks array<int>"


def to_wav(raw: bytes, block: int = 64) -> bytes:
    """A mono 8-bit WAV file whose samples are the bytes and their zero padding."""
    raw += bytes(-len(raw) % block or (block if not raw else 0))
    out = io.BytesIO()
    with wave.open(out, "wb") as w:
        w.setnchannels(1)
        w.setsampwidth(1)
        w.setframerate(RATE)
        w.writeframes(raw)
    return out.getvalue()


def from_wav(media: bytes) -> bytes:
    with wave.open(io.BytesIO(media), "rb") as w:
        return w.readframes(w.getnframes())


def landmarks(samples: bytes, frame: int = 256, hop: int = 128, peaks: int = 2, fan: int = 2) -> tuple[np.ndarray, np.ndarray]:
    """Frames of the anchors, and landmarks as bin << 20 | bin << 8 | distance. Frames overlap; half a frame of silence before the clip and padding behind it give every sample full weight in sum."""
    x = np.frombuffer(samples, dtype=np.uint8).astype(np.float32) - 128
    lead = frame - hop
    x = np.pad(x, (lead, lead + -(len(x) + lead) % hop))
    view = np.lib.stride_tricks.sliding_window_view(x, frame)[::hop]
    window, found = np.hanning(frame).astype(np.float32), []
    for at in range(0, len(view), 2048):
        power = np.abs(np.fft.rfft(view[at : at + 2048] * window, axis=1))[:, 1:].round(3)
        found.append(np.argsort(-power, axis=1, kind="stable")[:, :peaks] + 1)
    top = np.concatenate(found)
    times, marks = [], []
    for d in range(1, min(fan, len(top) - 1) + 1):
        for p in range(peaks):
            times.append(np.arange(len(top) - d))
            marks.append(top[:-d, p] << 20 | top[d:, 0] << 8 | d)
    if not times:
        times, marks = [np.zeros(peaks, dtype=np.int64)], [top[0] << 20]
    times, marks = np.concatenate(times), np.concatenate(marks)
    order = np.lexsort((marks, times))
    return times[order].astype(np.int32), marks[order].astype(np.int32)


def media_column(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_bytes, media, payload_bytes, payload_sha256, tail_crc32, frames, marks): a clip for each row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 256):
                rows = []
                for i, t in zip(b.column(0).slice(at, 256).to_pylist(), b.column(1).slice(at, 256).cast(pa.binary()).to_pylist()):
                    t = t or b""
                    media = to_wav(t)
                    back = from_wav(media)
                    times, marks = landmarks(back)
                    rows.append((i, len(t), media, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), times, marks))
                kinds = (pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.string(), pa.int64(), pa.list_(pa.int32()), pa.list_(pa.int32()))
                names = [f.split()[0] for f in SCHEMA.split(", ")]
                yield pa.RecordBatch.from_arrays([pa.array(c, type=k) for c, k in zip(zip(*rows), kinds)], names=names)

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("t")).mapInArrow(run, SCHEMA)


def op10(docs: DataFrame) -> DataFrame:
    """feature: the first 8 bytes of the landmarks' SHA-256, the number of landmarks and the last time code; frames and marks are the time-coded landmarks."""
    m = media_column(docs)
    coded = F.array_join(F.zip_with("frames", "marks", lambda t, k: F.concat_ws(":", t, k)), ",")
    feature = F.concat_ws("-", F.substring(F.sha2(coded, 256), 1, 16), F.size("marks"), F.element_at("frames", -1))
    return m.select(
        F.col("id").alias("doc_id"), "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32",
        F.octet_length("media").cast("long").alias("media_bytes"), F.sha2("media", 256).alias("media_sha256"), feature.alias("feature"), "frames", "marks",
    )
