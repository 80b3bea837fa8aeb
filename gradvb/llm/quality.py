"""Quality by naive Bayes support vectors over n-gram indicators."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradvb.llm.common import IS_SPACE, labelled_crc, mix, prefix_hash, runs, slices, small_batches, span_hash, table
from gradvb.llm.labelled import fit_logistic, halves, logistic, training_rows

BUCKETS = 1 << 18
KEY = np.uint64((1 << 40) - 1)

#: A byte's class in a shape: small letters (and all that lies beyond ASCII) 1, capitals 2, digits 3, others themselves.
SHAPE = np.arange(256, dtype=np.uint8)
SHAPE[97:123] = SHAPE[128:] = 1
SHAPE[65:91] = 2
SHAPE[48:58] = 3


def token_shapes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hash of each token's sequence of byte classes, repeats collapsed."""
    kind = SHAPE[data]
    change = np.ones(len(data), bool)
    change[1:] = kind[1:] != kind[:-1]
    change[starts] = True
    place = np.concatenate([[0], np.cumsum(change)])
    return mix(span_hash(prefix_hash(kind[change]), place[starts], place[ends]))


def share_level(part: np.ndarray, whole: np.ndarray) -> np.ndarray:
    """Halvings from the whole down to the part: 0 from three quarters up, at most 7."""
    return np.clip(np.round(-np.log2(np.maximum(part, 1e-9) / np.maximum(whole, 1))), 0, 7).astype(np.uint64)


def indicators(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(text, bucket) of every n-gram indicator of a slice of texts.

    The n-grams are words, and one to three neighbouring token shapes. A shape n-gram also tells
    how large a share of the text's tokens it has. Further indicators tell the number of
    tokens and the shares of tokens and lines that repeat (the token before, any earlier line).
    """
    n = len(offsets) - 1
    starts, ends, text = runs(~IS_SPACE[data], offsets)
    total = np.bincount(text, minlength=n)
    word = mix(span_hash(prefix_hash(data), starts, ends)) if len(starts) else np.zeros(0, np.uint64)
    shape = token_shapes(data, starts, ends) if len(starts) else np.zeros(0, np.uint64)
    owner = text.astype(np.uint64) << np.uint64(40)
    out_text, out_key = [], []
    keys = [owner | shape & KEY]
    with np.errstate(over="ignore"):
        two = np.flatnonzero(text[1:] == text[:-1])
        pair = mix(shape[two] * np.uint64(31) + shape[two + 1])
        keys.append(owner[two] | pair & KEY)
        three = two[:-1][two[1:] == two[:-1] + 1]
        keys.append(owner[three] | mix(mix(shape[three] * np.uint64(31) + shape[three + 1]) * np.uint64(31) + shape[three + 2]) & KEY)
    found, count = np.unique(np.concatenate(keys), return_counts=True)
    of = (found >> np.uint64(40)).astype(np.int64)
    level = share_level(count, total[of])
    for extra in (np.uint64(99), level):
        out_text.append(of)
        out_key.append(mix((found & KEY) ^ (extra << np.uint64(56))))
    seen = np.unique(owner | word & KEY)
    out_text.append((seen >> np.uint64(40)).astype(np.int64))
    out_key.append(mix(seen & KEY ^ np.uint64(0xA5 << 48)))
    again = (word[1:] == word[:-1]) & (text[1:] == text[:-1])
    repeated = np.bincount(text[1:][again], minlength=n) if len(text) else np.zeros(n)
    line_starts, line_ends, line_text = runs(data != 10, offsets)
    lines = np.bincount(line_text, minlength=n)
    line = mix(span_hash(prefix_hash(data), line_starts, line_ends)) if len(line_starts) else np.zeros(0, np.uint64)
    different = np.unique(line_text.astype(np.uint64) << np.uint64(40) | line & KEY)
    copies = lines - np.bincount((different >> np.uint64(40)).astype(np.int64), minlength=n)
    for tag, value in ((1, np.round(2 * np.log2(1 + total)).astype(np.uint64)), (2, share_level(repeated, total)), (3, share_level(copies, lines))):
        out_text.append(np.arange(n))
        out_key.append(mix(value + np.uint64(tag << 52)))
    return np.concatenate(out_text), (np.concatenate(out_key) & np.uint64(BUCKETS - 1)).astype(np.int64)


def dual_descent(rows: list[np.ndarray], values: np.ndarray, y: np.ndarray, cost: np.ndarray, epochs: int = 12, seed: int = 7) -> np.ndarray:
    """Hinge-loss linear weights by dual coordinate descent; example k has ``values`` at ``rows[k]``."""
    rng = np.random.default_rng(seed)
    w, alpha = np.zeros(len(values)), np.zeros(len(rows))
    norm = np.array([(values[r] ** 2).sum() for r in rows])
    for _ in range(epochs):
        most = 0.0
        for k in rng.permutation(len(rows)):
            r = rows[k]
            x = values[r]
            slope = y[k] * (w[r] @ x) - 1
            moved = min(max(alpha[k] - slope / max(norm[k], 1e-12), 0.0), cost[k])
            if moved != alpha[k]:
                w[r] += (moved - alpha[k]) * y[k] * x
                most = max(most, abs(moved - alpha[k]) / cost[k])
                alpha[k] = moved
        if most < 1e-3:
            break
    return w


@dataclass
class QualityModel:
    """``weight``: per bucket, its log-count ratio times its hinge weight; ``fit``: calibration of the margin."""

    weight: np.ndarray
    fit: np.ndarray

    def margin(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        text, bucket = indicators(data, offsets)
        n = len(offsets) - 1
        return np.bincount(text, weights=self.weight[bucket], minlength=n) / np.sqrt(np.maximum(np.bincount(text, minlength=n), 1))

    def score(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        return logistic(np.clip(self.margin(data, offsets), -50, 50)[:, None], self.fit)


def joined(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(b"".join(texts), np.uint8), np.concatenate([[0], np.cumsum([len(t) for t in texts])]).astype(np.int64)


def fit_weights(rows: list[np.ndarray], y: np.ndarray, smooth: float = 1.0, cost: float = 1.0) -> np.ndarray:
    """Per bucket, the log ratio of its counts in both classes times its hinge weight on indicators so scaled."""
    count = [np.bincount(np.concatenate([r for r, own in zip(rows, y, strict=True) if own == k]), minlength=BUCKETS) for k in (0, 1)]
    ratio = np.log(((count[1] + smooth) / (y == 1).sum()) / ((count[0] + smooth) / (y == 0).sum()))
    ratio[count[0] + count[1] < 2] = 0
    share = np.where(y == 1, (y == 1).mean(), (y == 0).mean())
    scale = np.sqrt([max(1, len(r)) for r in rows])
    return ratio * dual_descent(rows, ratio, np.where(y == 1, 1.0, -1.0), cost * 0.5 / share / scale)


def fit_quality(texts: list[bytes], y: np.ndarray) -> QualityModel:
    """Fit on all texts, calibrated on halves that the weights of the other half have not seen.

    Without examples of both labels the model says the share of label 1 (one half without any) for all.
    """
    if len(set(y.tolist())) < 2:
        share = np.clip(float(y.mean()) if len(y) else 0.5, 1e-6, 1 - 1e-6)
        return QualityModel(np.zeros(BUCKETS), np.array([0, np.log(share / (1 - share))]))
    rows: list[np.ndarray] = []
    for _, data, offsets in slices(pa.array(texts, pa.large_binary()), 500_000):
        text, bucket = indicators(data, offsets)
        order = np.argsort(text, kind="stable")
        cuts = np.searchsorted(text[order], np.arange(1, len(offsets) - 1))
        rows += [np.unique(r).astype(np.int32) for r in np.split(bucket[order], cuts)]
    half, margin = halves(texts), np.zeros(len(texts))
    for k in (0, 1):
        learn = np.flatnonzero(half != k)
        if len(set(y[learn].tolist())) < 2:
            learn = np.arange(len(texts))
        weight = fit_weights([rows[i] for i in learn], y[learn])
        for i in np.flatnonzero(half == k):
            margin[i] = weight[rows[i]].sum() / np.sqrt(max(1, len(rows[i])))
    return QualityModel(fit_weights(rows, y), fit_logistic(np.clip(margin, -50, 50)[:, None], y))


def score_quality(docs: DataFrame, model: QualityModel, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.3) -> DataFrame:
    """(doc_id, score, predicted) for every row; texts are read whole.

    Null and empty texts are scored as texts without tokens. Repeated rows are scored as often
    as they come, an empty table gives no rows, other columns are not read.
    """
    shipped = small_batches(docs).sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            parts = [shipped.value.score(data, offsets) for _, data, offsets in slices(batch.column(1), 500_000)]
            score = np.concatenate(parts) if parts else np.zeros(0)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(score), pa.array((score >= threshold).astype(np.int32))], names=["doc_id", "score", "predicted"])

    chosen = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return chosen.mapInArrow(run, "doc_id long, score double, predicted int")


def train_quality(docs: DataFrame, labels: DataFrame, bound: int = 2500) -> QualityModel:
    """Fit on at most ``bound`` labelled texts outside the held-out fifth."""
    return fit_quality(*training_rows(docs, labels, "quality", 5, 0, bound))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = score_quality(docs, train_quality(docs, table(spark, sf_dir, "labels")))
    held_out = F.coalesce(labelled_crc(F.col("doc_id")) % 5 == 0, F.lit(False))
    return scored.select("doc_id", held_out.alias("held_out"), "score", "predicted")
