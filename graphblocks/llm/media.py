"""Media columns: WAV payloads, short-time Fourier transforms, spectral-peak fingerprints."""

from __future__ import annotations

import hashlib
import io
import wave
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from . import kernels as K
from .common import text_column

#: Fixed value: payloads are filled to a positive multiple of this many bytes.
BLOCK = 576
SAMPLE_RATE = 8000
FILL = 255
#: Frames overlap by half, with half a frame of silence before and after, so that each byte counts and a block alone has pairs; bins are those of BLOCK samples.
FRAME, HOP = 144, 72
PEAKS_PER_FRAME, REACH = 3, 3
#: Frames that are transformed at a time.
FRAMES_AT_ONCE = 1024


def to_wav(payload: bytes, rate: int = SAMPLE_RATE) -> bytes:
    """One channel of unsigned 8-bit samples, a byte each."""
    out = io.BytesIO()
    with wave.open(out, "wb") as w:
        w.setnchannels(1)
        w.setsampwidth(1)
        w.setframerate(rate)
        w.writeframes(payload)
    return out.getvalue()


def from_wav(content: bytes) -> bytes:
    """The samples as bytes."""
    with wave.open(io.BytesIO(content), "rb") as r:
        if r.getnchannels() != 1 or r.getsampwidth() != 1:
            raise ValueError("one channel of 8-bit samples is expected")
        return r.readframes(r.getnframes())


def text_payload(text: bytes) -> bytes:
    """The bytes, filled up to a positive multiple of BLOCK."""
    size = max(BLOCK, -(-len(text) // BLOCK) * BLOCK)
    return text + bytes([FILL]) * (size - len(text))


_window = np.hanning(FRAME).astype(np.float32)


def spectral_peaks(samples: np.ndarray) -> np.ndarray:
    """(frames, PEAKS_PER_FRAME) frequency bins of the largest magnitudes, the strongest first; ties go to the lower bin."""
    frames = np.lib.stride_tricks.sliding_window_view(np.pad(samples, HOP, constant_values=128), FRAME)[::HOP]
    out = np.empty((len(frames), PEAKS_PER_FRAME), np.int16)
    for i in range(0, len(frames), FRAMES_AT_ONCE):
        x = (frames[i : i + FRAMES_AT_ONCE].astype(np.float32) - 128) * _window
        power = np.abs(np.fft.rfft(x, BLOCK, axis=1))
        power = np.round(power[:, 2:] * 16).astype(np.int64)
        inner = np.zeros_like(power)
        inner[:, 1:-1] = power[:, 1:-1] * ((power[:, 1:-1] >= power[:, :-2]) & (power[:, 1:-1] > power[:, 2:]))
        key = inner * 512 + (511 - np.arange(inner.shape[1]))
        top = np.argpartition(-key, PEAKS_PER_FRAME, axis=1)[:, :PEAKS_PER_FRAME]
        order = np.argsort(-np.take_along_axis(key, top, 1), axis=1)
        out[i : i + len(x)] = np.take_along_axis(top, order, 1) + 2
    return out


def fingerprint(peaks: np.ndarray) -> np.ndarray:
    """Time-coded pairs: frame << 21 | distance << 18 | anchor bin << 9 | target bin, by time.

    Each frame's strongest peak is paired with the peaks of the next REACH frames.
    """
    found = []
    for step in range(1, REACH + 1):
        if len(peaks) > step:
            anchor, target = peaks[:-step, :1].astype(np.int64), peaks[step:].astype(np.int64)
            time = np.arange(len(anchor), dtype=np.int64)[:, None]
            found.append((time << 21 | step << 18 | anchor << 9 | target).ravel())
    return np.sort(np.concatenate(found)) if found else np.zeros(0, np.int64)


_MEDIA = "media binary, n_bytes long, peaks array<int>, fingerprint array<long>"
_DIGEST = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def _texts(column: pa.Array) -> Iterator[bytes]:
    for _, _, data, offsets in K.byte_chunks(column):
        raw, cut = data.tobytes(), offsets.tolist()
        for a, b in zip(cut, cut[1:]):
            yield raw[a:b]


def media_columns(docs: DataFrame) -> DataFrame:
    """doc_id with the stored WAV, the peaks of its frames and the fingerprint array.

    A null text is stored as an empty one.  One pass without a shuffle; repeated
    rows and null ids come out as they go in; no rows give no rows.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, size = [], 0
            first = 0
            for text in _texts(batch.column(1)):
                media = to_wav(text_payload(text))
                peaks = spectral_peaks(np.frombuffer(from_wav(media), np.uint8))
                rows.append((media, len(text), peaks.ravel().astype(np.int32), fingerprint(peaks)))
                size += len(media)
                if size > 8 * K.CHUNK_BYTES:
                    yield _media_batch(batch.column(0).slice(first, len(rows)), rows)
                    first, rows, size = first + len(rows), [], 0
            if rows:
                yield _media_batch(batch.column(0).slice(first, len(rows)), rows)

    return docs.select(docs["doc_id"].cast("long"), text_column(docs)).mapInArrow(run, "doc_id long, " + _MEDIA)


def _media_batch(ids: pa.Array, rows: list[tuple]) -> pa.RecordBatch:
    media, n, peaks, prints = zip(*rows)
    return pa.RecordBatch.from_arrays(
        [ids, pa.array(media, pa.binary()), pa.array(n, pa.int64()), pa.array(list(peaks), pa.list_(pa.int32())), pa.array(list(prints), pa.list_(pa.int64()))],
        ["doc_id", "media", "n_bytes", "peaks", "fingerprint"],
    )


def media_digest(docs: DataFrame) -> DataFrame:
    """The contract's columns, computed from the stored form as it is read back."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cols: list[list] = [[] for _ in range(7)]
            for text in _texts(batch.column(1)):
                media = to_wav(text_payload(text))
                payload = from_wav(media)
                prints = fingerprint(spectral_peaks(np.frombuffer(payload, np.uint8)))
                feature = f"{len(prints)}:{hashlib.sha256(prints.astype('<i8').data).hexdigest()[:32]}"
                for c, x in zip(cols, (len(text), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(media), hashlib.sha256(media).hexdigest(), feature)):
                    c.append(x)
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(cols, kinds))], names)

    return docs.select(docs["doc_id"].cast("long"), text_column(docs)).mapInArrow(run, _DIGEST)
