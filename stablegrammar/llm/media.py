"""Media columns: texts stored as WAV audio, read back, and described by spectral-peak pair fingerprints."""

from __future__ import annotations

import hashlib
import io
import wave
import zlib
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stablegrammar.llm.common import map_texts, texts

BLOCK = 192


def to_wav(payload: bytes, rate: int = 8000) -> bytes:
    """One channel of unsigned 8-bit samples; the header is a function of the length alone."""
    out = io.BytesIO()
    with wave.open(out, "wb") as w:
        w.setnchannels(1)
        w.setsampwidth(1)
        w.setframerate(rate)
        w.writeframes(payload)
    return out.getvalue()


def from_wav(media: bytes) -> bytes:
    with wave.open(io.BytesIO(media), "rb") as r:
        return r.readframes(r.getnframes())


def spectral_peaks(payload: bytes, frame: int = BLOCK, hop: int = BLOCK // 2, per_frame: int = 2) -> tuple[np.ndarray, np.ndarray]:
    """Times and frequency bins of the strongest local maxima of each frame of the short-time Fourier transform.

    Frames overlap by half, so that the window, which fades at a frame's ends, leaves no sample out of account.
    """
    x = np.frombuffer(payload, np.uint8).astype(np.float32) - 128.0
    frames = np.lib.stride_tricks.sliding_window_view(x, frame)[::hop]
    window = np.hanning(frame).astype(np.float32)
    times, bins = [], []
    for a in range(0, len(frames), 4096):
        power = np.abs(np.fft.rfft(frames[a : a + 4096] * window, axis=1))[:, 1:-1]
        power = np.round(np.log1p(power) * 64).astype(np.int32)  # coarse steps, so that equal samples give equal peaks everywhere
        inner = np.where((power[:, 1:-1] > power[:, :-2]) & (power[:, 1:-1] >= power[:, 2:]), power[:, 1:-1], 0)
        top = np.argsort(-inner, axis=1, kind="stable")[:, :per_frame]
        hit = np.take_along_axis(inner, top, 1) > 0
        times.append((np.broadcast_to(np.arange(a, a + len(top))[:, None], top.shape))[hit])
        bins.append(top[hit] + 2)
    return np.concatenate(times), np.concatenate(bins)


def peak_pairs(times: np.ndarray, bins: np.ndarray, fan_out: int = 3) -> np.ndarray:
    """Time-coded fingerprints: (time << 32) | (first bin << 20) | (second bin << 8) | time step, for each peak and its next few."""
    codes = []
    for step in range(1, fan_out + 1):
        dt = times[step:] - times[:-step]
        ok = dt < 256
        codes.append((times[:-step][ok] << 32) | (bins[:-step][ok] << 20) | (bins[step:][ok] << 8) | dt[ok])
    return np.sort(np.concatenate(codes).astype(np.int64))


def media_columns(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", keep_media: bool = True) -> DataFrame:
    """Store every text as WAV and describe what is read back.

    Columns: doc_id, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, fingerprints (array of time-coded
    longs), and media (the stored bytes) if `keep_media`. The payload is the text's UTF-8 bytes, then spaces up to a positive multiple
    of 192; one byte is one sample. Null and empty texts become 192 spaces. Texts of any length
    are stored whole, their frames transformed in blocks of 4096. One narrow pass; a row's result depends on its text only,
    so repeated texts agree; null ids stay null, other columns are ignored, an empty table gives an empty result.
    """
    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, fingerprints array<long>" + ", media binary" * keep_media

    def kernel(lists: Iterator) -> Iterator[dict]:
        for ids, held in lists:
            out: dict[str, list] = {k.split()[0]: [] for k in schema.split(", ")}
            for i, t in zip(ids, held, strict=True):
                raw = t.encode()
                media = to_wav(raw + b" " * (-len(raw) % BLOCK or (BLOCK if not raw else 0)))
                payload = from_wav(media)
                row = (i, len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(media), hashlib.sha256(media).hexdigest(), peak_pairs(*spectral_peaks(payload)), media)
                for column, v in zip(out.values(), row, strict=False):
                    column.append(v)
            yield out

    return map_texts(texts(docs, id_col, text_col), kernel, schema)


def feature(fingerprints: str = "fingerprints"):
    """A digest of the fingerprint array, led by its length."""
    return F.concat_ws(":", F.size(fingerprints).cast("string"), F.md5(F.array_join(F.transform(fingerprints, lambda x: x.cast("string")), ",")))
