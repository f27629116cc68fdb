"""Arrow kernels over whole texts, without a Python loop over words where possible."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: White space between words, [\x20\x09-\x0D]; bytes.split() uses the same set.
IS_SPACE = np.zeros(256, bool)
IS_SPACE[[0x20, *range(0x09, 0x0E)]] = True


def spans(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string or binary array as one vector, and its offsets; nulls are empty."""
    texts = texts.cast(pa.large_binary()).fill_null(b"")
    _, offsets, data = texts.buffers()
    at = np.frombuffer(offsets, np.int64)[texts.offset : texts.offset + len(texts) + 1]
    return np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8), at


def word_counts(texts: pa.Array) -> np.ndarray:
    """Number of ``[^\\x20\\x09-\\x0D]+`` in each text."""
    data, at = spans(texts)
    if not len(at) or at[-1] == at[0]:
        return np.zeros(len(texts), np.int64)
    data = data[at[0] : at[-1]]
    at = at - at[0]
    word = ~IS_SPACE[data]
    begins = word.copy()
    begins[1:] &= ~word[:-1]
    first = at[:-1][at[:-1] < at[1:]]  # a text begins a word even where the one before it ends with a word
    begins[first] = word[first]
    places = np.searchsorted(np.flatnonzero(begins), at)
    return places[1:] - places[:-1]


def word_count(text: Column) -> Column:
    """Words of a text column as a long; null counts as empty."""

    @F.arrow_udf(T.LongType())
    def count(texts: pa.Array) -> pa.Array:
        return pa.array(word_counts(texts), pa.int64())

    return count(text.cast("binary"))


def leading_words(text: Column, words: Column) -> Column:
    """The text up to the end of its word number ``words``; null where the text is null.

    Built-in functions, so that inside ``when`` only the rows that are cut are read."""
    parts = F.regexp_extract_all(text, F.lit(r"[\x20\x09-\x0D]*[^\x20\x09-\x0D]+"), F.lit(0))
    return F.array_join(F.slice(parts, 1, words.cast("int")), "")
