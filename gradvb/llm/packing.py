"""Packing documents into token sequences by best fit, longest first."""

from __future__ import annotations

import base64
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyspark
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradvb.llm.common import lean, small_batches, table

SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
ARROW = pa.schema([(name, pa.int64()) for name in ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")])
_ENCODERS: dict = {}


#: Fixed value: the vocabulary's special string, which tokenizers reads as one id wherever it stands in a text.
SPECIAL = {"<|endoftext|>": 50256}


def encoder(vocabulary: str):
    """The byte-level BPE whose ranks the file lists, with its special string; the worker keeps it."""
    import public_tokenizers
    import tiktoken

    if vocabulary not in _ENCODERS:
        with open(vocabulary, "rb") as lines:
            ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}
        _ENCODERS[vocabulary] = tiktoken.Encoding("bpe", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=SPECIAL)
    return _ENCODERS[vocabulary]


def default_vocabulary() -> str:
    """Ranks of the vocabulary that ``byte_bpe_50k.json`` holds; they give the same ids several times faster."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


class OpenSequences:
    """Open sequences by their room left, under a segment tree that finds the tightest one that fits."""

    def __init__(self, window: int) -> None:
        self.leaves = 1 << window.bit_length()
        self.count = [0] * (2 * self.leaves)
        self.stacks: list[list[int]] = [[] for _ in range(window + 1)]

    def add(self, room: int, sequence: int) -> None:
        self.stacks[room].append(sequence)
        node = room + self.leaves
        while node:
            self.count[node] += 1
            node >>= 1

    def take(self, size: int) -> tuple[int, int] | None:
        """Remove the open sequence with the least room of at least ``size``: (room, sequence)."""
        count, node = self.count, size + self.leaves
        if not count[node]:
            while node > 1 and (node & 1 or not count[node + 1]):
                node >>= 1
            if node <= 1:
                return None
            node += 1
            while node < self.leaves:
                node <<= 1
                if not count[node]:
                    node += 1
        room = node - self.leaves
        while node:
            count[node] -= 1
            node >>= 1
        return room, self.stacks[room].pop()


def best_fit_decreasing(lengths: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray, int]:
    """Sequence and offset of each piece, and the number of sequences; ties go by the given order."""
    sequence, offset, used = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64), 0
    space = OpenSequences(window)
    for k in np.argsort(-lengths, kind="stable").tolist():
        size = int(lengths[k])
        found = space.take(size)
        if found is None:
            room, where, used = window, used, used + 1
        else:
            room, where = found
        sequence[k], offset[k] = where, window - room
        if room > size:
            space.add(room - size, where)
    return sequence, offset, used


def unpadded(total: int, window: int) -> list[int]:
    """Sizes of sequences that hold ``total`` ids without padding: full windows, then powers of two, largest first."""
    sizes, rest = [window] * (total // window), total % window
    return sizes + [1 << k for k in range(rest.bit_length() - 1, -1, -1) if rest >> k & 1]


def place_rests(rests: list[tuple[int, int, bytes, int]], window: int, least_fill: float) -> tuple[list[tuple], int]:
    """Pieces (doc, start, length, crc, document's ids, sequence, offset) of (doc, start, raw ids, document's ids), and the number of sequences.

    Sequences that best fit fills to less than ``least_fill`` of the window, and not to a power of two, are laid end to end and cut anew, so that they need no padding.
    """
    lengths = np.array([len(r[2]) // 4 for r in rests], np.int64)
    sequence, offset, used = best_fit_decreasing(lengths, window)
    load = np.bincount(sequence, weights=lengths, minlength=used).astype(np.int64)
    loose = (load < least_fill * window) & (load & (load - 1) != 0)
    number = np.cumsum(~loose) - 1
    own = loose[sequence]
    out = [(d, at, n, zlib.crc32(raw), total, s, o) for (d, at, raw, total), n, s, o, cut in zip(rests, lengths.tolist(), number[sequence].tolist(), offset.tolist(), own.tolist(), strict=True) if not cut]
    sizes = unpadded(int(load[loose].sum()), window)
    k, filled, first = -1, 0, int((~loose).sum())
    for i in np.lexsort((offset, sequence)).tolist():
        if not own[i]:
            continue
        doc, at, raw, total = rests[i]
        while raw:
            if k < 0 or filled == sizes[k]:
                k, filled = k + 1, 0
            piece = raw[: 4 * (sizes[k] - filled)]
            out.append((doc, at, len(piece) // 4, zlib.crc32(piece), total, first + k, filled))
            at, filled, raw = at + len(piece) // 4, filled + len(piece) // 4, raw[len(piece) :]
    return out, first + len(sizes)


def pack(
    docs: DataFrame,
    window: int = 2048,
    vocabulary: str | None = None,
    end_id: int = 1,
    group: int = 8_000_000,
    least_fill: float = 0.98,
    id_col: str = "doc_id",
    text_col: str = "text",
) -> DataFrame:
    """Pack every document into sequences of at most ``window`` tokens, one row per piece.

    A document's ids are its text's and ``end_id``. Documents longer than a window are cut into
    full windows, each a sequence of its own; the rests are packed best fit, longest first,
    within a scan partition (about ``group`` ids at a time, which bounds memory). Sequences that this leaves
    less than ``least_fill`` full are cut anew into full windows and, at the end, sequences of a power of two, so that padding does
    not depend on how the table is dealt out. No row is
    shuffled: a sequence belongs to one partition and its id starts with that partition's number.

    Null and empty texts are the end id alone. Special strings of the vocabulary are one id each. Repeated rows are packed as often as they come,
    ties by their order in the file. An empty table gives no rows. Columns other than the id and
    the text are not read.
    """
    vocabulary = vocabulary or default_vocabulary()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = encoder(vocabulary)
        base = pyspark.TaskContext.get().partitionId() << 33
        used, rest, held = 0, [], 0

        def rows(found: list[tuple]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*found, strict=True)], schema=ARROW)

        def close() -> pa.RecordBatch:
            nonlocal used, rest, held
            found, more = place_rests(rest, window, least_fill)
            found = [(*r[:5], base + used + r[5], r[6]) for r in found]
            used, rest, held = used + more, [], 0
            return rows(found)

        for batch in batches:
            full = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                ids = np.append(bpe.encode_to_numpy(text or "", allowed_special="all"), end_id).astype("<u4")
                raw, n = ids.tobytes(), len(ids)
                cut = n - n % window
                for start in range(0, cut, window):
                    full.append((doc, start, window, zlib.crc32(raw[4 * start : 4 * (start + window)]), n, base + used, 0))
                    used += 1
                if cut < n:
                    rest.append((doc, cut, raw[4 * cut :], n))
                    held += n - cut
            if full:
                yield rows(full)
            if held >= group:
                yield close()
        if rest:
            yield close()

    return small_batches(docs).select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(lean(run), SCHEMA)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))
