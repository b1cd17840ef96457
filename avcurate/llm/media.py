"""Media columns: texts stored as lossless WebP, read back as pixel arrays, and their features.

Edge cases: a null or empty text is padding alone; a text of any length goes on in further images;
repeated rows give repeated results; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from avcurate.llm import webp
from avcurate.llm.common import map_values, spread, stage

UNIT, PAD = 192, b" "


def payload_of(text: str | None) -> tuple[bytes, int]:
    raw = (text or "").encode("utf-8")
    return raw + PAD * (max(UNIT, -(-len(raw) // UNIT) * UNIT) - len(raw)), len(raw)


def feature(samples: bytes) -> str:
    """Mean, deviation, distinct values and a histogram of 16 bins of the 8-bit samples."""
    counts = np.bincount(np.frombuffer(samples, np.uint8), minlength=256)
    n, v = int(counts.sum()), np.arange(256)
    mean = int(counts @ v) / n
    var = max(0.0, int(counts @ (v * v)) / n - mean * mean)
    bins = ",".join(map(str, counts.reshape(16, 16).sum(axis=1).tolist()))
    return f"mean={mean:.4f};dev={var**0.5:.4f};distinct={int((counts > 0).sum())};bins={bins}"


def store_texts(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, media: one media value for each document, staged in the shared folder."""

    def make():
        def some(texts: list[str | None]) -> list[list]:
            made = [payload_of(t) for t in texts]
            return [[n for _, n in made], webp.encode_payloads([p for p, _ in made])]

        return some

    return stage(map_values(spread(docs.select(F.col("doc_id").cast("long"), "text")), "text", make, "n_bytes long, media binary", 2 << 20), "media")


def read_media(stored: DataFrame, samples: bool = False) -> DataFrame:
    """What the stored bytes hold; samples adds the pixel arrays as bytes."""
    added = "payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string" + ", samples binary" * samples
    sha = hashlib.sha256

    def make():
        def some(media: list[bytes]) -> list[list]:
            found = webp.decode_payloads(media)
            rows = [(len(p), sha(p).hexdigest(), zlib.crc32(p[-16:]), len(m), sha(m).hexdigest(), feature(p)) + ((p,) if samples else ()) for m, p in zip(media, found)]
            return list(zip(*rows))

        return some

    return map_values(stored.select("doc_id", "n_bytes", "media"), "media", make, added, 2 << 20)
