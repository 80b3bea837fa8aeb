"""Labelled training rows and calibration shared by the two classifiers."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gradvb.llm.common import labelled_crc


def training_rows(docs: DataFrame, labels: DataFrame, label: str, folds: int, held_out: int, bound: int) -> tuple[list[bytes], np.ndarray]:
    """At most ``bound`` labelled texts outside the held-out fold, in the order of a hash of their ids.

    The bound is a parameter of the training, not of the scoring; fewer labels give fewer rows.
    Rows with a null id, text or label are no examples; of rows that share an id the least text is one.
    """
    chosen = (
        labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("y"))
        .where(F.col("y").isin(0, 1) & (labelled_crc(F.col("doc_id")) % folds != held_out))
        .dropDuplicates(["doc_id"])
        .orderBy(F.xxhash64("doc_id", F.lit(17)), "doc_id")
        .limit(bound)
    )
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text")).where("text is not null")
    got = texts.join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "y").agg(F.min("text").alias("text")).toPandas()
    got["text"] = got["text"].map(bytes)
    got = got.sort_values(["doc_id", "text"], kind="stable").drop_duplicates("text")
    return got["text"].tolist(), got["y"].to_numpy(np.int64)


def halves(texts: list[bytes]) -> np.ndarray:
    """A split of the training texts for calibration."""
    import zlib

    return np.array([zlib.crc32(t) >> 7 & 1 for t in texts], np.int64)


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, steps: int = 50) -> np.ndarray:
    """Ridge logistic regression by Newton steps, the last weight an intercept."""
    x = np.column_stack([x, np.ones(len(y))])
    w = np.zeros(x.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        hess = (x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(len(w))
        step = np.linalg.solve(hess, x.T @ (y - p) - ridge * w)
        w += np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-8:
            break
    return w


def logistic(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(np.column_stack([x, np.ones(len(x))]) @ w, -30, 30)))
