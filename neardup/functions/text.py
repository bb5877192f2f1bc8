"""Words, shingles and the stand-in embedding of texts."""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Letters and digits of a word, the same class in Spark, Python and SQL.
WORD_CLASS = "[0-9a-zß-öø-ÿ]+"
_WORDS = re.compile(WORD_CLASS)


def words(text: str | Column = "text") -> Column:
    """The lower-case words of a text in order; none for null."""
    return F.coalesce(F.regexp_extract_all(F.lower(text), F.lit(WORD_CLASS), 0), F.array().cast("array<string>"))


def shingles(tokens: str | Column, size: int = 3) -> Column:
    """Distinct runs of ``size`` words; all words as one run where there are fewer."""
    tokens = F.col(tokens) if isinstance(tokens, str) else tokens
    last = F.size(tokens) - size + 1
    runs = F.transform(F.sequence(F.lit(1), last), lambda i: F.array_join(F.slice(tokens, i, size), " "))
    return F.array_distinct(F.when(last >= 1, runs).otherwise(F.array(F.array_join(tokens, " "))))


def signature_of(text: str | None, dims: int = 256, size: int = 3) -> np.ndarray:
    """Signed sums: over the distinct shingles, +1 where the hash has the bit, else -1."""
    found = _WORDS.findall((text or "").lower())
    runs = {" ".join(found[i : i + size]) for i in range(max(1, len(found) - size + 1))}
    rounds = -(-dims // 128)
    raw = b"".join(hashlib.md5(f"{r}|{s}".encode()).digest() for s in runs for r in range(rounds))
    # Words are big-endian groups of eight hex digits; bit b of a word is (word >> b) & 1.
    w = np.frombuffer(raw, ">u4").reshape(len(runs), rounds * 4)[:, : dims // 32]
    bits = np.unpackbits(w.astype("<u4").view(np.uint8).reshape(len(runs), -1), axis=1, bitorder="little")
    return 2 * bits.sum(0, dtype=np.int64) - len(runs)


def embedding_udf(dims: int = 256, size: int = 3):
    """Arrow function from texts to signed sums."""

    @F.pandas_udf("array<int>")
    def embed(texts: pd.Series) -> pd.Series:
        return pd.Series([signature_of(t, dims, size).astype(np.int32) for t in texts])

    return embed


def signature_udf(dims: int = 256, size: int = 3):
    """Arrow function from texts to the packed bits of their sums (a bit is set if its sum is over 0)."""

    @F.pandas_udf("array<long>")
    def sign(texts: pd.Series) -> pd.Series:
        def packed(t):
            flags = signature_of(t, dims, size) > 0
            return np.packbits(flags, bitorder="little").view("<u4").astype(np.int64)

        return pd.Series([packed(t) for t in texts])

    return sign
