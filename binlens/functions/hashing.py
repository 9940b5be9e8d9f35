"""Deterministic randomness: draws, ranks and signs from MD5, the same bits in Spark and in any SQL engine with MD5."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

try:
    from _md5 import md5  # the same digest at half the cost for a short word
except ImportError:
    from hashlib import md5


def u32(*parts) -> Column:
    """First 32 bits of the MD5 of the parts, joined by a bar."""
    cols = [p if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    return F.conv(F.substring(F.md5(F.concat_ws("|", *[c.cast("string") for c in cols])), 1, 8), 16, 10).cast("long")


def sign(bits: Column, i: int) -> Column:
    """+1 or -1 from bit ``i``."""
    return F.shiftright(bits, i).bitwiseAND(1) * 2 - 1


def flat_words(column: pa.ListArray) -> tuple[pa.Array, np.ndarray]:
    """The words of all rows one after another, and where each row's begin (rows + 1); a null row has none."""
    sizes = column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
    return column.flatten(), np.concatenate([[0], np.cumsum(sizes, dtype=np.int64)])


def coded(words: pa.Array) -> tuple[np.ndarray, list[bytes]]:
    """Each word's number in the list of different words, and that list."""
    known = words.cast(pa.large_binary()).dictionary_encode()
    return known.indices.to_numpy(zero_copy_only=False), known.dictionary.to_pylist()


def u32_each(words: list[bytes], *parts: str) -> np.ndarray:
    """``u32`` of the parts and each word: a batch's different words are hashed once each."""
    head = "".join(f"{p}|" for p in parts).encode()
    return np.frombuffer(b"".join([md5(head + w).digest() for w in words]), ">u4")[::4].astype(np.int64)
