"""Toxicity by subword bags: character n-gram vectors averaged into a linear softmax."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradvb.llm.common import IS_WORD, LOWER, give_back, labelled_crc, mix, prefix_hash, lean, slices, small_batches, span_hash, table
from gradvb.llm.labelled import fit_logistic, halves, logistic, training_rows

BUCKETS = 1 << 17
SIZES = (3, 4, 5)
#: Bytes of text that the kernels take at a time.
SLICE = 500_000
#: Distinct words whose subwords are looked up at a time while training.
WORDS = 20_000


@dataclass
class Words:
    """Words of a slice of texts, with their subwords as (position of the stream, bucket)."""

    stream: np.ndarray
    starts: np.ndarray
    ends: np.ndarray
    text: np.ndarray


def lay_out(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Lower-cased bytes with what is no word blanked, a blank before and after every text; and where texts begin."""
    n = len(offsets) - 1
    stream = np.full(len(data) + n + 8, 32, np.uint8)
    place = np.arange(len(data)) + np.repeat(np.arange(1, n + 1), np.diff(offsets))
    stream[place] = np.where(IS_WORD[data], LOWER[data], 32)
    return stream, offsets + np.arange(n + 1)


def find_words(data: np.ndarray, offsets: np.ndarray) -> Words:
    stream, begins = lay_out(data, offsets)
    inside = stream != 32
    edges = np.flatnonzero(inside[1:] != inside[:-1]) + 1
    starts, ends = edges[::2], edges[1::2]
    return Words(stream, starts, ends, np.searchsorted(begins, starts, side="right") - 1)


def subwords(words: Words) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """For each n-gram size: where one begins whose inner bytes lie in a word, and every position's bucket."""
    stream = words.stream.astype(np.uint64)
    inside = words.stream != 32
    n = len(stream)
    gram = stream[: n - 2] | stream[1 : n - 1] << np.uint64(8) | stream[2:] << np.uint64(16)
    valid = inside[1 : n - 1].copy()
    for size in SIZES:
        if size > 3:
            keep = n - size + 1
            gram = gram[:keep] | stream[size - 1 :] << np.uint64(8 * (size - 1))
            valid = valid[:keep] & inside[size - 2 : n - 1]
        yield valid, (mix(gram ^ np.uint64(size << 60)) & np.uint64(BUCKETS - 1)).astype(np.int64)


def spelled_subwords(spelled: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """The subwords of a list of words as (place of the word, bucket), sorted by place."""
    words = find_words(*joined([b" ".join(spelled)]))
    mark = np.zeros(len(words.stream), np.int32)
    mark[words.starts] = 1
    owner = np.cumsum(mark, dtype=np.int32) - 1
    rows, cols = [], []
    for valid, bucket in subwords(words):
        at = np.flatnonzero(valid)
        rows.append(owner[at + 1])
        cols.append(bucket[at].astype(np.int32))
    rows, cols = np.concatenate(rows), np.concatenate(cols)
    order = np.argsort(rows, kind="stable")
    return rows[order], cols[order]


def word_logits(words: Words, weight: np.ndarray) -> np.ndarray:
    """Each word's mean over its subwords of their scalar part in the softmax."""
    n = len(words.stream)
    total, count = np.zeros(n + 1), np.zeros(n + 1)
    for valid, bucket in subwords(words):
        total[1 : len(valid) + 1] += np.where(valid, weight[bucket], 0)
        count[1 : len(valid) + 1] += valid
    np.cumsum(total, out=total)
    np.cumsum(count, out=count)
    lo, hi = words.starts - 1, words.ends - 1
    return (total[hi] - total[lo]) / np.maximum(count[hi] - count[lo], 1)


@dataclass
class ToxicityModel:
    """``weight``: per bucket, its vector times the softmax's two columns' difference; ``bias`` theirs; ``fit``: calibration."""

    weight: np.ndarray
    bias: float
    fit: np.ndarray

    def features(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Per text: the largest and second largest word logit, the log of the expected number of toxic words, that of all words."""
        words = find_words(data, offsets)
        n = len(offsets) - 1
        z = word_logits(words, self.weight) + self.bias
        count = np.bincount(words.text, minlength=n)
        best, second = np.full(n, -20.0), np.full(n, -20.0)
        if len(z):
            order = np.lexsort((z, words.text))
            last = np.cumsum(count) - 1
            has, two = count > 0, count > 1
            best[has] = z[order[last[has]]]
            second[two] = z[order[last[two] - 1]]
        toxic = np.bincount(words.text, weights=1 / (1 + np.exp(-np.clip(z, -20, 20))), minlength=n)
        return np.column_stack([np.clip(best, -20, 20), np.clip(second, -20, 20), np.log1p(toxic), np.log1p(count)])

    def features_of(self, texts: list[bytes]) -> np.ndarray:
        """As ``features``, slice by slice: the kernels take about a hundred bytes a byte of text."""
        parts = [self.features(data, offsets) for _, data, offsets in slices(pa.array(texts, pa.large_binary()), SLICE)]
        return np.concatenate(parts) if parts else np.zeros((0, 4))

    def score(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        return logistic(self.features(data, offsets), self.fit)


def fit_vectors(texts: list[bytes], y: np.ndarray, dim: int = 8, rounds: int = 3, epochs: int = 3, rate: float = 0.3, decay: float = 1e-3, seed: int = 11) -> ToxicityModel:
    """Train bucket vectors and the softmax together by stochastic gradient steps over distinct words.

    A word counts against toxicity once per clean text that has it. For it, it counts in toxic
    texts: wholly in the first round, later by the chance, as the last round has it, that this
    word is toxic given that some word of the text is.
    """
    rng = np.random.default_rng(seed)
    names, spelled, pairs = [], [], []
    for first_text, data, offsets in slices(pa.array(texts, pa.large_binary()), SLICE):
        part = find_words(data, offsets)
        name = mix(span_hash(prefix_hash(part.stream), part.starts, part.ends))
        own, sample = np.unique(name, return_index=True)
        names.append(own)
        spelled += [part.stream[s:e].tobytes() for s, e in zip(part.starts[sample].tolist(), part.ends[sample].tolist(), strict=True)]
        pairs.append(np.unique(np.stack([part.text + first_text, np.searchsorted(own, name)]), axis=1) + np.array([[0], [sum(map(len, names[:-1]))]]))
    if not spelled:
        return ToxicityModel(np.zeros(BUCKETS), 0.0, np.zeros(5))
    _, sample, kind_of = np.unique(np.concatenate(names), return_index=True, return_inverse=True)
    doc, kind = np.concatenate(pairs, axis=1)
    kind = kind_of[kind]
    spelled = [spelled[i] for i in sample.tolist()]
    del names, pairs, kind_of
    size, cols = [], []
    for lo in range(0, len(spelled), WORDS):
        part = spelled[lo : lo + WORDS]
        row, col = spelled_subwords(part)
        size.append(np.bincount(row, minlength=len(part)))
        cols.append(col)
    del spelled, part, row, col
    size, cols = np.concatenate(size), np.concatenate(cols)
    first = np.concatenate([[0], np.cumsum(size)])
    give_back()
    toxic = y[doc] == 1
    against = np.bincount(kind[~toxic], minlength=len(sample)).astype(float)
    blame = np.ones(int(toxic.sum()))
    vectors = rng.normal(0, 0.1, (BUCKETS, dim)).astype(np.float32)
    soft = rng.normal(0, 0.5, (dim, 2)).astype(np.float32)
    bias = np.zeros(2, np.float32)
    heat_v, heat_s = np.full(BUCKETS, 1e-4, np.float32), np.full((dim, 2), 1e-4, np.float32)
    used = np.flatnonzero(size > 0)
    for _ in range(rounds):
        pro = np.bincount(kind[toxic], weights=blame, minlength=len(sample))
        con = against + np.bincount(kind[toxic], weights=1 - blame, minlength=len(sample))
        for _ in range(epochs):
            for batch in np.array_split(rng.permutation(used), max(1, len(used) // 2048)):
                n = size[batch]
                flat = np.repeat(first[batch] - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
                ids, cut = cols[flat], np.concatenate([[0], np.cumsum(n)[:-1]])
                h = np.add.reduceat(vectors[ids], cut) / n[:, None]
                z = h @ soft + bias
                p = np.exp(z - z.max(axis=1, keepdims=True))
                p /= p.sum(axis=1, keepdims=True)
                weight = np.log1p(pro[batch] + con[batch])
                goal = np.column_stack([con[batch], pro[batch]]) / (pro[batch] + con[batch] + 1e-9)[:, None]
                miss = ((p - goal) * weight[:, None]).astype(np.float32)
                g_soft, g_h = h.T @ miss / len(batch), miss @ soft.T
                g_ids = np.repeat(g_h / n[:, None], n, axis=0)
                uniq, back = np.unique(ids, return_inverse=True)
                g_v = np.column_stack([np.bincount(back, weights=g, minlength=len(uniq)) for g in g_ids.T]).astype(np.float32)
                g_v += decay * vectors[uniq]
                heat_v[uniq] += (g_v**2).mean(axis=1)
                heat_s += g_soft**2
                vectors[uniq] -= rate * g_v / np.sqrt(heat_v[uniq])[:, None]
                soft -= 0.1 * g_soft / np.sqrt(heat_s)
                bias -= 0.05 * miss.mean(axis=0)
        scalar = (vectors @ (soft[:, 1] - soft[:, 0])).astype(np.float64)
        shift = float(bias[1] - bias[0])
        z = np.where(size > 0, np.add.reduceat(np.append(scalar[cols], 0.0), first[:-1]) / np.maximum(size, 1), -20) + shift
        likely = 1 / (1 + np.exp(-np.clip(z[kind[toxic]], -15, 15)))
        none = np.bincount(doc[toxic], weights=np.log1p(-np.minimum(likely, 1 - 1e-9)), minlength=len(texts))
        blame = np.minimum(1, likely / -np.expm1(none[doc[toxic]]))
    return ToxicityModel(scalar, shift, np.zeros(5))


def joined(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(b"".join(texts), np.uint8), np.concatenate([[0], np.cumsum([len(t) for t in texts])]).astype(np.int64)


def fit_toxicity(texts: list[bytes], y: np.ndarray) -> ToxicityModel:
    """Vectors from all texts, calibrated on halves that the vectors of the other half have not seen.

    Without examples of both labels the model says the share of toxic texts (0 without any) for all.
    """
    if len(set(y.tolist())) < 2:
        share = np.clip(float(y.mean()) if len(y) else 0.0, 1e-6, 1 - 1e-6)
        return ToxicityModel(np.zeros(BUCKETS), 0.0, np.array([0, 0, 0, 0, np.log(share / (1 - share))]))
    half = halves(texts)
    found = np.zeros((len(texts), 4))
    for k in (0, 1):
        learn, judge = np.flatnonzero(half != k), np.flatnonzero(half == k)
        if len(set(y[learn].tolist())) < 2 or not len(judge):
            learn = judge = np.arange(len(texts))
        part = fit_vectors([texts[i] for i in learn], y[learn])
        found[judge] = part.features_of([texts[i] for i in judge])
    model = fit_vectors(texts, y)
    model.fit = fit_logistic(found, y)
    return model


def scores(model: ToxicityModel, column: pa.Array) -> np.ndarray:
    parts = [model.score(data, offsets) for _, data, offsets in slices(column, SLICE)]
    return np.concatenate(parts) if parts else np.zeros(0)


def score_toxicity(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.7) -> DataFrame:
    """(doc_id, score, predicted) for every row.

    A text is as toxic as its most toxic words; texts of any length are read whole. Null and
    empty texts are scored as texts without words. Repeated rows are scored as often as they
    come, an empty table gives no rows, other columns are not read.
    """
    shipped = small_batches(docs).sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            score = scores(shipped.value, batch.column(1))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(score), pa.array((score >= threshold).astype(np.int32))], names=["doc_id", "score", "predicted"])

    chosen = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    return chosen.mapInArrow(lean(run), "doc_id long, score double, predicted int")


def drop_toxic(docs: DataFrame, model: ToxicityModel, text_col: str = "text", threshold: float = 0.7) -> DataFrame:
    """The rows of ``docs`` that score below the threshold, with all their columns, whatever these are called.

    Null and empty texts are scored as texts without words; equal texts go or stay together; an empty table gives no rows.
    """
    shipped = small_batches(docs).sparkSession.sparkContext.broadcast(model)
    place = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(scores(shipped.value, batch.column(place)) < threshold))

    return docs.mapInArrow(lean(run), docs.schema)


def train_toxicity(docs: DataFrame, labels: DataFrame, bound: int = 2500) -> ToxicityModel:
    """Fit on at most ``bound`` labelled texts outside the held-out third."""
    model = fit_toxicity(*training_rows(docs, labels, "toxic", 3, 1, bound))
    give_back()
    return model


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = score_toxicity(docs, train_toxicity(docs, table(spark, sf_dir, "labels")))
    held_out = F.coalesce(labelled_crc(F.col("doc_id")) % 3 == 1, F.lit(False))
    return scored.select("doc_id", held_out.alias("held_out"), "score", "predicted")
