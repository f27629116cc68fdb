"""Labelled training samples and the logistic fits shared by the classifiers."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def held_out(id_column: Column) -> Column:
    """True for the rows kept from training: crc32 of the id as text leaves 2 modulo 4; null ids are held out."""
    return F.coalesce(F.crc32(id_column.cast("string").cast("binary")) % 4 == 2, F.lit(True))


#: Windows that a long training text is read through.
EXCERPTS = 4


def excerpt(text: Column, most_chars: int) -> Column:
    """A text of at most ``most_chars`` code points whole; of a longer one, ``EXCERPTS`` windows spread over all of it."""
    size = max(1, most_chars // EXCERPTS)
    starts = [((F.length(text) - size) * i / (EXCERPTS - 1)).cast("int") + 1 for i in range(EXCERPTS)]
    return F.when(F.length(text) <= most_chars, text).otherwise(F.concat_ws("\n", *(text.substr(at, F.lit(size)) for at in starts)))


def training_sample(docs: DataFrame, labels: DataFrame, label: str, rows: int, most_chars: int, id_col: str = "doc_id", text_col: str = "text") -> list[tuple[str, int]]:
    """(text, label) of at most ``rows`` labelled rows of each class, in the order of a hash of their id.

    Rows that are held out never enter; null texts are empty; of a text of more than ``most_chars`` code points,
    windows spread over it are read. The bound is on the fit alone; scores are computed for all rows and whole texts."""
    known = labels.where(F.col(label).isin(0, 1) & ~held_out(F.col(id_col))).select(F.col(id_col).alias("_id"), F.col(label).cast("int").alias("_y"))
    picked = None
    for y in (0, 1):
        some = known.where(F.col("_y") == y).orderBy(F.xxhash64("_id"), "_id").limit(rows)
        picked = some if picked is None else picked.unionByName(some)
    usable = docs.select(F.col(id_col).alias("_id"), excerpt(F.coalesce(F.col(text_col), F.lit("")), most_chars).alias("_text"))
    found = usable.join(F.broadcast(picked), "_id").collect()
    return sorted({(r._id, r._text): (r._text, r._y) for r in found}.values())


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, steps: int = 50) -> np.ndarray:
    """Weights of a logistic model by Newton steps; a column of ones is up to the caller."""
    w = np.zeros(x.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        slope = x.T @ (p - y) + ridge * w
        change = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w)), slope)
        w -= change
        if np.abs(change).max() < 1e-8:
            break
    return w


def logit(p: float) -> float:
    return float(np.log(p / (1 - p)))


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))
