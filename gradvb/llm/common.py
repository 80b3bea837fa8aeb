"""Helpers shared by the training-data operators."""

from __future__ import annotations

import ctypes
import re
import sys
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Texts are handed to the vector kernels in slices of about this many bytes.
SLICE_BYTES = 2_000_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Bytes of an Arrow batch that goes to a worker.
BATCH_BYTES = 4 << 20


def small_batches(df: DataFrame) -> DataFrame:
    """``df``, after asking its session for Arrow batches of 4 MB at most: texts are long, and workers hold several copies of a batch."""
    conf, name = df.sparkSession.conf, "spark.sql.execution.arrow.maxBytesPerBatch"
    found = re.match(r"(-?\d+)", conf.get(name))
    if found is None or not 0 < int(found[1]) <= BATCH_BYTES:
        conf.set(name, str(BATCH_BYTES))
    return df


#: Rows of a side that is broadcast; longer ones are joined by a shuffle.
BROADCAST_ROWS = 100_000


def is_short(side: DataFrame) -> bool:
    return side.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS


def checked(side: DataFrame) -> DataFrame:
    """``side``, to be broadcast if it is short. It is counted for that, so it should be written already."""
    return F.broadcast(side) if is_short(side) else side


def lean(run):
    """``run`` for mapInArrow, giving what it freed back to the system when a partition ends: workers live on and hold it otherwise."""

    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        give_back()

    return wrapped


def give_back() -> None:
    """Give what this process freed back to the system."""
    pa.default_memory_pool().release_unused()
    if sys.platform == "linux":
        ctypes.CDLL(None).malloc_trim(0)


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z only, which leaves every other letter as it is."""
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


#: Fixed pattern: words are runs of ASCII letters, digits and all that lies beyond ASCII.
WORD_PATTERN = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def words(text: Column) -> Column:
    """The word array of a text (null: no words), split at what no word holds."""
    parts = F.split(ascii_lower(F.coalesce(text, F.lit(""))), r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    return F.filter(parts, lambda w: w != "")


def as_binary(column: pa.Array) -> pa.Array:
    return column.cast(pa.large_binary())


def slices(column: pa.Array, limit: int = SLICE_BYTES) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """Cut a text column into (first row, bytes, offsets); null counts as empty.

    Each slice holds whole texts of ``limit`` bytes together, or one text that is longer.
    """
    column = as_binary(column)
    if column.null_count:
        column = column.fill_null(b"")
    if len(column) == 0:
        return
    buffers = column.buffers()
    offsets = np.frombuffer(buffers[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(buffers[2], np.uint8) if buffers[2] is not None else np.zeros(0, np.uint8)
    first, n = 0, len(column)
    while first < n:
        end = int(np.searchsorted(offsets, offsets[first] + limit, side="right")) - 1
        end = min(max(end, first + 1), n)
        own = offsets[first : end + 1]
        yield first, data[own[0] : own[-1]], own - own[0]
        first = end


#: Odd multiplier of the polynomial hashes modulo 2^64, and its inverse.
BASE = np.uint64(0x9E3779B97F4A7C15)
BASE_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 2**64))


class Powers:
    """Powers of the hash base, grown on demand and kept by the worker."""

    def __init__(self) -> None:
        self.up = self.down = np.ones(1, np.uint64)

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = max(n, 2 * len(self.up))
            with np.errstate(over="ignore"):
                for name, base in (("up", BASE), ("down", BASE_INVERSE)):
                    grown = np.full(size, base, np.uint64)
                    grown[0] = 1
                    setattr(self, name, np.multiply.accumulate(grown))
        return self.up[:n], self.down[:n]


POWERS = Powers()


def mix(x: np.ndarray) -> np.ndarray:
    """Finish a 64-bit hash so that all its bits depend on all of the input's."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def prefix_hash(values: np.ndarray) -> np.ndarray:
    """Prefix sums of value times base^position modulo 2^64, one longer than the input."""
    up, _ = POWERS.get(len(values) + 1)
    out = np.zeros(len(values) + 1, np.uint64)
    with np.errstate(over="ignore"):
        np.cumsum((values.astype(np.uint64) + np.uint64(1)) * up[: len(values)], out=out[1:])
    return out


def span_hash(prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hashes of [start, end): equal spans have equal hashes wherever they stand."""
    _, down = POWERS.get(len(prefix))
    with np.errstate(over="ignore"):
        return (prefix[end] - prefix[start]) * down[start]


#: Byte tables: A-Z lowered, and which bytes belong to words of letters, digits and non-ASCII.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
IS_WORD = np.zeros(256, bool)
IS_WORD[48:58] = IS_WORD[65:91] = IS_WORD[97:123] = True
IS_WORD[128:] = True
IS_SPACE = np.zeros(256, bool)
IS_SPACE[[9, 10, 11, 12, 13, 32]] = True


def runs(mask: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Maximal runs of true bytes that stay within a text: starts, ends and each one's text."""
    if not len(mask):
        return (np.zeros(0, np.int64),) * 3
    edge = np.zeros(len(mask) + 1, bool)
    edge[0] = edge[-1] = True
    edge[1:-1] = mask[1:] != mask[:-1]
    edge[offsets] = True
    cuts = np.flatnonzero(edge)
    starts, ends = cuts[:-1], cuts[1:]
    keep = mask[starts]
    starts, ends = starts[keep], ends[keep]
    return starts, ends, np.searchsorted(offsets, starts, side="right") - 1


def labelled_crc(doc_id: Column) -> Column:
    """crc32 of the id written as text."""
    return F.crc32(doc_id.cast("string").cast("binary"))
