"""Media columns: lossless 8-bit WAV payloads, short-time Fourier transforms, spectral-peak pair fingerprints.

A payload is stored as the samples of a mono WAV, read back through the wave module and analysed from the
stored samples. Landmarks are the strongest bins of each frequency band in each frame; each landmark is
paired with the FAN next ones of later frames within REACH frames. A pair's hash (band bin, other bin, frame distance) is
stored time-coded: frame << 32 | hash.

Defined cases: null text is empty; the payload is zero-padded to a positive multiple of 64 bytes, so an empty
text is 64 zero bytes with an empty fingerprint; texts of any length are analysed in blocks of frames, so beside
the stored bytes only the landmarks grow with a text; equal texts give equal values; other columns are not read.
"""

from __future__ import annotations

import hashlib
import io
import wave
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches, utf8

#: Fixed values of the analysis.
RATE, FRAME, HOP, BLOCK, FAN, REACH = 8000, 256, 128, 2048, 4, 16
#: Frequency bands as bin limits (octaves); each gives at most one landmark a frame.
BANDS = (1, 4, 8, 16, 32, 64, 129)
WINDOW = np.hanning(FRAME).astype(np.float32)


def pad(data: bytes) -> bytes:
    return data + bytes(-len(data) % 64 if data else 64)


def to_wav(payload: bytes) -> bytes:
    out = io.BytesIO()
    with wave.open(out, "wb") as w:
        w.setnchannels(1)
        w.setsampwidth(1)
        w.setframerate(RATE)
        w.writeframes(payload)
    return out.getvalue()


def from_wav(media: bytes) -> bytes:
    with wave.open(io.BytesIO(media), "rb") as w:
        if (w.getnchannels(), w.getsampwidth()) != (1, 1):
            raise ValueError("not an 8-bit mono payload")
        return w.readframes(w.getnframes())


def landmarks(samples: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(frame, bin) of the spectral peaks, in time order then frequency order; samples are centred floats or stored bytes."""
    n = 1 + max(0, -(-(len(samples) - FRAME) // HOP))
    centre = 128 if samples.dtype == np.uint8 else 0
    times, bins = [], []
    for at in range(0, n, BLOCK):
        m = min(BLOCK, n - at)
        piece = samples[at * HOP : (at + m - 1) * HOP + FRAME]
        x = np.zeros((m - 1) * HOP + FRAME, np.float32)
        x[: len(piece)] = piece
        x[: len(piece)] -= centre
        part = np.lib.stride_tricks.sliding_window_view(x, FRAME)[::HOP]
        part = (part - part.mean(axis=1, keepdims=True)) * WINDOW
        power = np.abs(np.fft.rfft(part, axis=1)).astype(np.float32)
        floor = power.mean(axis=1)
        top = np.stack([lo + power[:, lo:hi].argmax(axis=1) for lo, hi in zip(BANDS, BANDS[1:])], axis=1)
        strong = np.take_along_axis(power, top, 1) > np.maximum(2 * floor, 1e-3)[:, None]
        t, band = np.nonzero(strong)
        times.append(t + at)
        bins.append(top[t, band])
    return np.concatenate(times), np.concatenate(bins)


def fingerprint(samples: np.ndarray) -> np.ndarray:
    """Time-coded landmark pair hashes, ascending."""
    t, f = landmarks(samples)
    found = []
    later = np.searchsorted(t, t, "right")  # the first landmark of a later frame
    for k in range(FAN):
        a = np.nonzero(later + k < len(t))[0]
        b = later[a] + k
        near = t[b] - t[a] <= REACH
        a, b = a[near], b[near]
        found.append((t[a] << 32) | (f[a] << 16) | (f[b] << 8) | (t[b] - t[a]))
    return np.sort(np.concatenate(found).astype(np.int64)) if found else np.empty(0, np.int64)


def store_media(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """(id, n_bytes, media): each text's payload as a WAV."""

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            raw = utf8(batch.column(1))
            return pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array([len(x) for x in raw], pa.int64()), pa.array([to_wav(pad(x)) for x in raw], pa.binary())], ["doc_id", "n_bytes", "media"])

        return step

    return map_batches(docs.select(id_column, text_column), make, "doc_id long, n_bytes long, media binary", text_column)


def read_media(stored: DataFrame) -> DataFrame:
    """Payload, fingerprint array and payload checks of stored media (column media, binary)."""

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            media = batch.column("media").to_pylist()
            payloads = [from_wav(m) for m in media]
            prints = [fingerprint(np.frombuffer(p, np.uint8)) if any(p) else np.empty(0, np.int64) for p in payloads]
            return pa.RecordBatch.from_arrays(
                [
                    batch.column("doc_id"),
                    batch.column("n_bytes"),
                    batch.column("media"),
                    pa.array(payloads, pa.binary()),
                    pa.array([zlib.crc32(p[-64:]) for p in payloads], pa.int64()),
                    pa.array(prints, pa.list_(pa.int64())),
                ],
                ["doc_id", "n_bytes", "media", "payload", "tail_crc32", "fingerprint"],
            )

        return step

    return map_batches(stored, make, "doc_id long, n_bytes long, media binary, payload binary, tail_crc32 long, fingerprint array<bigint>", "media")


def media_digest(docs: DataFrame) -> DataFrame:
    """The digest query: summaries of what read_media gives for the stored column."""

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            hashes = ["%d:%s" % (len(p), hashlib.sha256(np.asarray(p, "<i8").tobytes()).hexdigest()[:32]) for p in (x.values.to_numpy(zero_copy_only=False) for x in batch.column("fingerprint"))]
            columns = [batch.column(k) for k in ("doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256")]
            return pa.RecordBatch.from_arrays([*columns, pa.array(hashes, pa.string())], NAMES)

        return step

    media, payload = F.col("media"), F.col("payload")
    sizes = [F.length(payload).cast("long").alias("payload_bytes"), F.sha2(payload, 256).alias("payload_sha256"), "tail_crc32", F.length(media).cast("long").alias("media_bytes"), F.sha2(media, 256).alias("media_sha256")]
    return map_batches(read_media(store_media(docs)).select("doc_id", "n_bytes", *sizes, "fingerprint"), make, SCHEMA, "payload_sha256")


SCHEMA = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
NAMES = [x.split()[0] for x in SCHEMA.split(", ")]


def matching_prints(media: DataFrame, min_shared: int = 5) -> DataFrame:
    """Searches one recording set in another's prints by shared pair hash at a constant time offset.

    media has doc_id, fingerprint and role ('query' or 'track'); returns query_id, doc_id, offset, shared.
    Both sides are pre-aggregated by (hash, frame) before they meet.
    """
    coded = media.select("doc_id", "role", F.explode("fingerprint").alias("c")).select("doc_id", "role", F.shiftright("c", 32).alias("t"), F.col("c").bitwiseAND(F.lit((1 << 32) - 1)).alias("h"))
    q = coded.filter("role = 'query'").select(F.col("doc_id").alias("query_id"), "h", F.col("t").alias("qt"))
    d = coded.filter("role = 'track'").select("doc_id", "h", "t")
    return q.join(d, "h").groupBy("query_id", "doc_id", (F.col("t") - F.col("qt")).alias("offset")).agg(F.count(F.lit(1)).alias("shared")).filter(F.col("shared") >= min_shared)
