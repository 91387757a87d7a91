"""Media columns: WAV samples, short-time spectra and time-coded peak-pair fingerprints.

A text's UTF-8 bytes, padded with spaces to a positive multiple of 192, become the 8-bit
samples of a mono WAV. The ``wave`` module reads them back; frames of 192 samples that overlap
by half get a short-time Fourier transform. The strongest bin of each of four bands is a peak
if it is no weaker than that band's strongest of the frame before and of the frame after; each
peak is paired with those of the next frames. A pair is one integer that carries its time.

Null and empty texts are one frame of silence-like padding. Long texts are transformed in
blocks, so memory does not follow their length but for the result's own. Repeated rows give repeated results; an
empty table gives an empty table; other columns of the input are not read.
"""

from __future__ import annotations

import hashlib
import io
import wave
import zlib

import numpy as np
from pyspark.sql import DataFrame

from .common import map_batches

FRAME, HOP, BLOCK_FRAMES = 192, 96, 4096
#: Bands of spectral bins in which the strongest one is a peak.
BANDS = ((1, 12), (12, 28), (28, 56), (56, 97))
#: A peak is paired with the peaks of so many next frames, in the same and the next band.
AHEAD = 3
WINDOW = np.hanning(FRAME).astype(np.float32)


def to_wav(payload: bytes, rate: int = 8000) -> bytes:
    store = io.BytesIO()
    with wave.open(store, "wb") as w:
        w.setnchannels(1)
        w.setsampwidth(1)
        w.setframerate(rate)
        w.writeframes(payload)
    return store.getvalue()


def from_wav(stored: bytes) -> bytes:
    with wave.open(io.BytesIO(stored), "rb") as w:
        return w.readframes(w.getnframes())


def padded(text: str | None) -> tuple[int, bytes]:
    raw = (text or "").encode("utf-8", "surrogatepass")
    return len(raw), raw + b" " * (-len(raw) % FRAME if raw else FRAME)


def spectra(samples: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Strongest bin and its magnitude for each frame and band."""
    frames = np.lib.stride_tricks.sliding_window_view(samples, FRAME)[::HOP]
    bins = np.empty((len(frames), len(BANDS)), dtype=np.int64)
    loud = np.empty((len(frames), len(BANDS)), dtype=np.float32)
    for at in range(0, len(frames), BLOCK_FRAMES):
        block = (frames[at : at + BLOCK_FRAMES].astype(np.float32) - 128.0) * WINDOW
        spectrum = np.abs(np.fft.rfft(block, axis=1)).astype(np.float32)
        for b, (low, high) in enumerate(BANDS):
            best = spectrum[:, low:high].argmax(axis=1)
            bins[at : at + len(block), b] = best + low
            loud[at : at + len(block), b] = spectrum[np.arange(len(block)), best + low]
    return bins, loud


def peaks(loud: np.ndarray) -> np.ndarray:
    """Which frames and bands hold a peak: no weaker than the frames beside them."""
    out = np.ones(loud.shape, dtype=bool)
    out[1:] &= loud[1:] >= loud[:-1]
    out[:-1] &= loud[:-1] >= loud[1:]
    return out


def pair_codes(bins: np.ndarray, peak: np.ndarray) -> np.ndarray:
    """time << 24 | first bin << 16 | second bin << 8 | frames between, for every peak and the peaks of the next AHEAD
    frames in its band and in the one above; in order."""
    n, bands = bins.shape
    time = np.arange(n, dtype=np.int64)
    out = []
    for gap in range(1, AHEAD + 1):
        if n > gap:
            for b in range(bands):
                for other in (b, b + 1):
                    if other < bands:
                        both = np.flatnonzero(peak[:-gap, b] & peak[gap:, other])
                        out.append(time[both] << 24 | bins[both, b] << 16 | bins[both + gap, other] << 8 | gap)
    return np.sort(np.concatenate(out)) if out else np.empty(0, dtype=np.int64)


def media_columns(
    docs: DataFrame, text: str = "text", key: str = "doc_id", keep_media: bool = False, keep_pairs: bool = True
) -> DataFrame:
    """One row per row of docs: sizes and digests of payload and stored form, the fingerprint's digest and its array
    of time-coded pairs, and on request the stored WAV."""
    kind = docs.schema[key].dataType.simpleString()
    ddl = f"{key} {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_frames long, n_pairs long"
    ddl += ", media binary" * keep_media + ", pairs array<long>" * keep_pairs

    def work():
        def step(keys, texts):
            out = {c.split()[0]: [] for c in ddl.split(", ")}
            for k, t in zip(keys, texts):
                n, payload = padded(t)
                stored = to_wav(payload)
                read = from_wav(stored)
                bins, loud = spectra(np.frombuffer(read, dtype=np.uint8))
                codes = pair_codes(bins, peaks(loud))
                row = {
                    key: k,
                    "n_bytes": n,
                    "payload_bytes": len(read),
                    "payload_sha256": hashlib.sha256(read).hexdigest(),
                    "tail_crc32": zlib.crc32(read[-16:]),
                    "media_bytes": len(stored),
                    "media_sha256": hashlib.sha256(stored).hexdigest(),
                    "feature": f"{len(bins)}:{len(codes)}:{hashlib.sha256(codes.tobytes()).hexdigest()}",
                    "n_frames": len(bins),
                    "n_pairs": len(codes),
                    "media": stored,
                    "pairs": codes,
                }
                for c in out:
                    out[c].append(row[c])
            return out

        return step

    return map_batches(docs.select(key, text), ddl, work)
