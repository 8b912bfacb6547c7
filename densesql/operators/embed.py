"""The fixed trace encoder: signed feature hashing of words and word pairs to unit vectors."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

_WORD = re.compile(r"[a-z0-9_]+")


def encode_text(text: str | None, dims: int = 256, ngrams: tuple[int, ...] = (1, 2)) -> np.ndarray:
    """A unit vector, or zeros for a text without words."""
    words = _WORD.findall((text or "").lower())
    grams = [" ".join(words[k : k + n]) for n in ngrams for k in range(len(words) - n + 1)]
    out = np.zeros(dims)
    if grams:
        hashes = np.fromiter(map(xxh64_intdigest, grams), dtype=np.uint64, count=len(grams))
        signs = np.where((hashes >> np.uint64(63)).astype(bool), -1.0, 1.0)
        out = np.bincount((hashes % np.uint64(dims)).astype(np.int64), weights=signs, minlength=dims)
    size = np.linalg.norm(out)
    return out / size if size else out


def encode(df: DataFrame, key: str, text: str, dims: int = 256, ngrams: tuple[int, ...] = (1, 2), keep: tuple[str, ...] = ()) -> DataFrame:
    """(key, keep..., embedding): every distinct text is encoded once and joined back by a 128-bit digest."""
    digest = F.md5(F.coalesce(F.col(text), F.lit("")).cast("binary"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            vectors = [encode_text(t, dims, ngrams).astype(np.float32) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(vectors, pa.list_(pa.float32()))], names=["digest", "embedding"])

    keyed = df.select(*dict.fromkeys((key, *keep)), F.col(text).alias("_text"), digest.alias("digest"))
    distinct = keyed.groupBy("digest").agg(F.first("_text").alias("_text")).mapInArrow(run, "digest string, embedding array<float>")
    return keyed.drop("_text").join(distinct, "digest").drop("digest")
