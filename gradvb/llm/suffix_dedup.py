"""Exact repeats of long byte strings by a sparse suffix sort that compares prefix hashes.

A string of ``length`` bytes that stands in two places has, in both, the same least gram hash
among its grams, so it is enough to sort the suffixes at such grams (anchors) and to look at most ``length``
bytes either way.

1. Each task finds the anchors of its texts, with a 128-bit digest of their surroundings. Anchors whose whole
   surroundings recur in the task are settled at once, and one of each kind goes on.
2. Anchors meet by gram hash, those of common grams by gram and surroundings. Equal surroundings settle
   each other; where surroundings of one gram differ, one of each kind has its bytes fetched.
3. Suffixes at a gram, to the right and reversed to the left, are sorted by a mergesort whose comparisons
   find the common extension by binary search on prefix hashes; neighbours' extensions
   are then verified byte by byte. Grams with more kinds than a task sorts are first divided by the bytes
   that any two matching members must share.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from functools import reduce
from hashlib import blake2b, sha256

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from gradvb.llm.common import POWERS, as_binary, checked, lean, mix, slices, small_batches, table
from gradvb.session import cut_lineage, ensure_checkpoint_dir

#: Bytes of anchors' texts that a task holds to settle repeats within itself.
CHUNK_BYTES = 16_000_000
#: Surroundings of one group that a task sorts; larger groups are divided.
GROUP_LIMIT = 300
#: Surroundings sorted at a time, and rows with surroundings that a task gives at a time.
BATCH = 2_000
#: Texts that tell which grams are common, in how many surroundings one is, and how many are kept; they deal out work, which never moves the result.
SAMPLE, COMMON, MOST_COMMON = 10_000, 8, 100_000


def sliding(values: np.ndarray, width: int, best) -> np.ndarray:
    """The least (or largest) of each ``width`` neighbouring values, by doubling."""
    out, have = values, 1
    while have < width:
        step = min(have, width - have)
        out = best(out[:-step], out[step:])
        have += step
    return out


def prefix(values: np.ndarray) -> np.ndarray:
    up, _ = POWERS.get(len(values) + 1)
    out = np.zeros(len(values) + 1, np.uint64)
    with np.errstate(over="ignore"):
        np.cumsum(values * up[: len(values)], out=out[1:])
    return out


def spans(pre: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    _, down = POWERS.get(len(pre))
    with np.errstate(over="ignore"):
        return (pre[hi] - pre[lo]) * down[lo]


def anchors(data: np.ndarray, offsets: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, ...]:
    """(text, place in the text, gram hash, both halves of the surroundings' digest) of a slice's anchors."""
    n, width = len(data), length - gram + 1
    if n < length:
        return (np.zeros(0, np.int64),) * 2 + (np.zeros(0, np.uint64),) * 3
    first = prefix(data.astype(np.uint64) + np.uint64(1))
    place = np.arange(n - gram + 1)
    h = mix(spans(first, place, place + gram)) | np.uint64(1)
    text_end = np.repeat(offsets[1:], np.diff(offsets))
    low = sliding(h, width, np.minimum)
    whole = np.arange(len(low)) + length <= text_end[: len(low)]
    low = np.where(whole, low, np.uint64(0))
    pad = np.zeros(width - 1, np.uint64)
    top = sliding(np.concatenate([pad, low, pad]), width, np.maximum)
    at = np.flatnonzero(top[: len(h)] == h)
    text = np.searchsorted(offsets, at, side="right") - 1
    lo, hi = np.maximum(at - (length - gram), offsets[text]), np.minimum(at + length, offsets[text + 1])
    raw = data.tobytes()
    digests = b"".join([blake2b(raw[x:y], digest_size=16).digest() for x, y in zip(lo.tolist(), hi.tolist(), strict=True)])
    c = np.frombuffer(digests, "<u8").reshape(-1, 2)
    with np.errstate(over="ignore"):  # the same bytes around a gram that stands elsewhere in them are another kind
        return text, at - offsets[text], h[at], c[:, 0].copy(), c[:, 1] + (at - lo).astype(np.uint64) * POWERS.get(2)[0][1]


def merged(row: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Union of the intervals of each row."""
    order = np.lexsort((lo, row))
    row, lo, hi = row[order], lo[order], hi[order]
    if not len(row):
        return row, lo, hi
    group = np.cumsum(np.concatenate([[0], row[1:] != row[:-1]]))
    reach = np.maximum.accumulate(hi + group * (1 << 40)) - group * (1 << 40)
    new = np.concatenate([[True], (row[1:] != row[:-1]) | (lo[1:] > reach[:-1])])
    start = np.flatnonzero(new)
    return row[start], lo[start], np.maximum.reduceat(hi, start)


def keyed(docs: DataFrame, id_col: str, text_col: str, *more: Column) -> DataFrame:
    """(doc, key, *more, text): a row is known by its id and a hash of its text, so only rows of one id could ever be taken for each other."""
    text = F.col(text_col)
    return docs.select(F.col(id_col).cast("long").alias("doc"), F.xxhash64(F.coalesce(text.cast("binary"), F.lit(b""))).alias("key"), *more, text.alias("text"))


def same_row(a: DataFrame, b: DataFrame) -> Column:
    return a["key"].eqNullSafe(b["own_key"]) & a["doc"].eqNullSafe(b["own_doc"])


def find_anchors(texts: DataFrame, length: int, gram: int, common: np.ndarray) -> DataFrame:
    """Anchors (``copies`` of their surroundings in the task) and, with 0 copies, intervals that are settled.

    ``deal`` says where rows go next: by gram, and those of ``common`` grams by gram and surroundings.
    """
    back = length - gram

    def settle(doc, key, text, place, f, c1, c2) -> pa.RecordBatch:
        order = np.lexsort((place, text, c2, c1, f))
        text, place, f, c1, c2 = text[order], place[order], f[order], c1[order], c2[order]
        start = np.flatnonzero(np.concatenate([[True], (f[1:] != f[:-1]) | (c1[1:] != c1[:-1]) | (c2[1:] != c2[:-1])])[: len(f)])
        copies = np.diff(np.append(start, len(f)))
        settled = np.repeat(copies > 1, copies)
        row, lo, hi = merged(text[settled], np.maximum(place[settled] - back, 0), place[settled] + length)
        zero, f, c1, c2 = np.zeros(len(row), np.uint64), f[start], c1[start], c2[start]
        at = np.concatenate([text[start], row])
        columns = [
            doc.take(pa.array(at)), pa.array(key[at]), *(pa.array(np.concatenate([x, y]).astype(np.int32)) for x, y in ((place[start], lo), (place[start], hi))),
            *(pa.array(np.concatenate([x, zero]).view(np.int64)) for x in (f, c1, c2)), pa.array(np.concatenate([copies, np.zeros(len(row), np.int64)]).astype(np.int32)),
            pa.array(np.concatenate([np.where(np.isin(f, common), mix(f ^ c1), f), mix(key[row].view(np.uint64))]).view(np.int64)),
        ]
        return pa.RecordBatch.from_arrays(columns, names=["doc", "key", "place", "upto", "f", "c1", "c2", "copies", "deal"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, docs, keys, size, n = [], [], [], 0, 0

        def close() -> pa.RecordBatch:
            return settle(pa.concat_arrays(docs), np.concatenate(keys), *(np.concatenate(x) for x in zip(*held, strict=True)))

        for batch in batches:
            docs.append(batch.column(0))
            keys.append(batch.column(1).to_numpy(zero_copy_only=False))
            for first_row, data, offsets in slices(batch.column(2), 200_000):
                text, *rest = anchors(data, offsets, length, gram)
                held.append((n + first_row + text, *rest))
                size += len(data)
            n += batch.num_rows
            if size >= CHUNK_BYTES:
                yield close()
                held, docs, keys, size, n = [], [], [], 0, 0
        if held:
            yield close()

    return texts.select("doc", "key", "text").mapInArrow(lean(run), "doc long, key long, place int, upto int, f long, c1 long, c2 long, copies int, deal long")


def common_grams(texts: DataFrame, length: int, gram: int) -> np.ndarray:
    """Grams with many kinds of surroundings in a sample of the texts, sorted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, data, offsets in slices(batch.column(0), 200_000):
                _, _, f, c, _ = anchors(data, offsets, length, gram)
                yield pa.RecordBatch.from_arrays([pa.array(f.view(np.int64)), pa.array(c.view(np.int64))], names=["f", "c"])

    share = min(1.0, SAMPLE / max(1, texts.count()))
    sample = texts.where(F.pmod("key", F.lit(1 << 20)) < int(share * (1 << 20))).select("text")
    counted = sample.mapInArrow(lean(run), "f long, c long").distinct().groupBy("f").agg(F.count("*").alias("n")).where(F.col("n") >= COMMON)
    return np.sort(np.array([r.f for r in counted.orderBy(F.desc("n"), "f").limit(MOST_COMMON).collect()], np.int64).view(np.uint64))


class Surroundings:
    """Bytes around anchors, aligned at the gram, with prefix hashes of each row."""

    def __init__(self, around: list[bytes], back: np.ndarray, length: int, gram: int) -> None:
        self.length, self.centre = length, length - gram
        size = np.array([len(a) for a in around])
        self.left, self.right = back, size - back
        self.bytes = np.zeros((len(around), self.centre + length), np.uint8)
        at = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size) + np.repeat(self.centre - back, size)
        self.bytes[np.repeat(np.arange(len(around)), size), at] = np.frombuffer(b"".join(around), np.uint8)
        up, _ = POWERS.get(self.bytes.shape[1] + 1)
        self.hash = np.zeros((len(around), self.bytes.shape[1] + 1), np.uint64)
        with np.errstate(over="ignore"):
            np.cumsum((self.bytes.astype(np.uint64) + np.uint64(1)) * up[:-1], axis=1, out=self.hash[:, 1:])

    def common(self, i: np.ndarray, j: np.ndarray, forward: bool) -> np.ndarray:
        """Common extension from the gram on (or back from it), by binary search on prefix hashes."""
        size = self.right if forward else self.left
        lo, hi = np.zeros(len(i), np.int64), np.minimum(size[i], size[j])
        base = self.hash[i, self.centre] - self.hash[j, self.centre]
        while (lo < hi).any():
            mid = (lo + hi + 1) // 2
            at = self.centre + (mid if forward else -mid)
            same = self.hash[i, at] - self.hash[j, at] == base
            lo, hi = np.where(same, mid, lo), np.where(same, hi, mid - 1)
        return lo

    def less(self, i: np.ndarray, j: np.ndarray, forward: bool) -> np.ndarray:
        """Whether suffix i sorts before suffix j; equal ones go by their numbers."""
        size = self.right if forward else self.left
        lcp = self.common(i, j, forward)
        inside = lcp < np.minimum(size[i], size[j])
        at = np.clip(self.centre + (lcp if forward else -1 - lcp), 0, self.bytes.shape[1] - 1)
        a, b = self.bytes[i, at].astype(np.int64), self.bytes[j, at].astype(np.int64)
        a, b = np.where(inside, a, size[i]), np.where(inside, b, size[j])
        return (a < b) | (a == b) & (i < j)

    def order(self, group: np.ndarray, forward: bool) -> np.ndarray:
        """Mergesort within groups (which stand together), all groups' merges of a width at once."""
        n = len(group)
        cuts = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1], [True]]))
        size = np.diff(cuts)
        first, end = np.repeat(cuts[:-1], size), np.repeat(cuts[1:], size)
        item, rank, width = np.arange(n), np.arange(n) - first, 1
        while width < size.max(initial=1):
            block = rank // width
            other = block ^ 1
            lo = np.minimum(first + other * width, end)
            start, hi = lo.copy(), np.minimum(lo + width, end)
            while True:
                live = np.flatnonzero(lo < hi)
                if not len(live):
                    break
                mid = (lo[live] + hi[live]) // 2
                before = self.less(item[mid], item[live], forward)
                lo[live] = np.where(before, mid + 1, lo[live])
                hi[live] = np.where(before, hi[live], mid)
            moved = first + np.minimum(block, other) * width + rank % width + lo - start
            out = np.empty(n, np.int64)
            out[moved] = item
            item = out
            width *= 2
        return item

    def neighbours(self, order: np.ndarray, group: np.ndarray, forward: bool) -> np.ndarray:
        """Verified common extension of each suffix with the one before it in the order, -1 where a group begins."""
        i, j = order[:-1], order[1:]
        size = self.right if forward else self.left
        part = self.bytes[:, self.centre :] if forward else self.bytes[:, self.centre - 1 :: -1] if self.centre else self.bytes[:, :0]
        differ = part[i] != part[j]
        lcp = np.where(differ.any(axis=1), differ.argmax(axis=1), differ.shape[1])
        lcp = np.minimum(lcp, np.minimum(size[i], size[j]))
        return np.concatenate([[-1], np.where(group[i] == group[j], lcp, -1)])

    def matched(self, group: np.ndarray, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Largest and least offset, from ``low`` to ``high``, of the gram in a window of ``length`` bytes that another member has too; -1 if none."""
        n = len(group)
        sides = []
        for forward in (True, False):
            order = self.order(group, forward)
            lcp = self.neighbours(order, group, forward)
            claimed = self.common(order[:-1], order[1:], forward) if n > 1 else np.zeros(0, np.int64)
            inner = lcp[1:] >= 0
            if (claimed[inner] != lcp[1:][inner]).any():  # a hash collision: sort the bytes themselves
                part = self.bytes[:, self.centre :] if forward else self.bytes[:, : self.centre][:, ::-1]
                size = self.right if forward else self.left
                order = np.array(sorted(range(n), key=lambda k: (group[k], part[k, : size[k]].tobytes(), k)))
                lcp = self.neighbours(order, group, forward)
            sides.append((order, lcp))
        largest, least = np.full(n, -1), np.full(n, -1)
        label = np.empty((2, n), np.int64)
        for offset in range(int(low.min(initial=0)), int(high.max(initial=-1)) + 1):
            for k, need in ((0, self.length - offset), (1, offset)):
                order, lcp = sides[k]
                label[k, order] = np.cumsum(lcp < need)
            fits = (self.left >= offset) & (self.right >= self.length - offset) & (low <= offset) & (offset <= high)
            at = np.flatnonzero(fits)
            if len(at) < 2:
                continue
            _, back, count = np.unique(label[0, at] * (n + 1) + label[1, at], return_inverse=True, return_counts=True)
            own = at[count[back] > 1]
            largest[own] = offset
            least[own] = np.where(least[own] < 0, offset, least[own])
        return largest, least


#: A member of a group: the group, the offsets that its windows may have, the row and place, whether it is the only one of its kind, its bytes; in divided groups a hull.
MEMBERS = "g binary, low int, high int, doc long, key long, place int, once boolean, around binary, hull binary"
ARROW = pa.schema([("g", pa.binary()), ("low", pa.int32()), ("high", pa.int32()), ("doc", pa.int64()), ("key", pa.int64()), ("place", pa.int32()), ("once", pa.bool_()), ("around", pa.binary()), ("hull", pa.binary())])


def match_groups(batches: Iterator[pa.RecordBatch], length: int, gram: int) -> Iterator[pa.RecordBatch]:
    """Intervals of the members whose surroundings are the only ones of their kind; input sorted by group."""
    held: list[tuple] = []

    def close(rows: list[tuple]) -> pa.RecordBatch:
        names: dict[bytes, int] = {}
        g = np.array([names.setdefault(r[0], len(names)) for r in rows])
        low, high, place, once = (np.array([r[k] for r in rows]) for k in (1, 2, 5, 6))
        largest, least = Surroundings([r[7] for r in rows], np.minimum(place, length - gram), length, gram).matched(g, low, high)
        own = np.flatnonzero((largest >= 0) & once)
        columns = [pa.array([rows[i][k] for i in own], pa.int64()) for k in (3, 4)] + [pa.array((place - largest)[own], pa.int32()), pa.array((place - least)[own] + length, pa.int32())]
        return pa.RecordBatch.from_arrays(columns, names=["doc", "key", "lo", "hi"])

    for batch in batches:
        for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if len(held) >= BATCH and row[0] != held[-1][0]:
                yield close(held)
                held = []
            held.append(row)
    if held:
        yield close(held)


def halves(row: tuple, length: int, gram: int) -> Iterator[tuple]:
    """A member in two groups, one for each half of its offsets, with a ``hull`` beside its other fields.

    Windows of the offsets low to high all hold the gram, ``low`` bytes before it and ``length - high`` from its
    start on, so members that share a window share these bytes, which name the group. ``hull`` names all that
    these windows cover: members of one hull share all their windows.
    """
    _, low, high, doc, key, place, once, around = row
    back = min(place, length - gram)
    middle = (low + high) // 2
    for x, y in ((low, middle), (middle + 1, high)):
        if x <= y and back >= x and len(around) - back >= length - y and max(x, length - len(around) + back) <= min(y, back):
            core = blake2b(around[back - x : back + length - y], digest_size=16, person=b"%d,%d" % (x, y)).digest()
            lo, hi = max(0, back - y), min(len(around), back + length - x)
            yield core, x, y, doc, key, place, once, around, blake2b(around[lo:hi], digest_size=16, person=b"%d" % (back - lo)).digest()


def as_batch(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], f.type) for k, f in enumerate(ARROW)], schema=ARROW)


def matches(members: DataFrame, folder: str, length: int, gram: int) -> DataFrame:
    """(doc, key, lo, hi) of members that share a window with another one of their group.

    Groups without hulls are sorted, one task each. Those with hulls are sorted if one task can, else divided by halves of their
    offsets until it can; members that share all that a half covers are settled on the way, and one of
    each kind stays as a partner of the others.
    """
    spark, level = members.sparkSession, 0
    names = [c for c in ARROW.names if c != "hull"]
    fit, settled, parts = [members.where("hull is null").select(names)], [], members.where("hull is not null")

    def divided(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, BATCH):
                columns = (c.to_pylist() for c in batch.slice(lo, BATCH).columns)
                yield as_batch([half for row in zip(*columns, strict=True) for half in halves(row, length, gram)])

    while True:
        over = cut_lineage(parts.groupBy("g").agg(F.count("*").alias("n")).where(F.col("n") > GROUP_LIMIT).select("g"))
        if over.isEmpty():
            fit.append(parts.select(names))
            break
        over = checked(over)
        fit.append(parts.join(over, "g", "left_anti").select(names))
        parts.join(over, "g", "left_semi").write.parquet(f"{folder}/large{level}")
        rest = spark.read.parquet(f"{folder}/large{level}")
        hulls = rest.groupBy("g", "hull").agg(F.count("*").alias("n"), F.min(F.struct("doc", "key", "place")).alias("one"))
        shared = cut_lineage(hulls.where("n > 1"))
        hit = checked(shared.select("g", "hull"))
        back = F.least("place", F.lit(length - gram))
        lo, hi = F.col("place") - F.least("high", back), F.col("place") - F.greatest("low", length - (F.length("around") - back)) + length
        settled.append(rest.join(hit, ["g", "hull"], "left_semi").where("once").select("doc", "key", lo.cast("int").alias("lo"), hi.cast("int").alias("hi")))
        ones = shared.select(F.col("g").alias("own_g"), F.col("hull").alias("own_hull"), *(F.col(f"one.{c}").alias(f"own_{c}") for c in ("doc", "key", "place")))
        stays = (rest["g"] == ones["own_g"]) & (rest["hull"] == ones["own_hull"]) & (rest["place"] == ones["own_place"]) & same_row(rest, ones)
        partners = rest.join(ones, stays, "left_semi").withColumn("once", F.lit(False)).select(names)
        large = rest.join(hit, ["g", "hull"], "left_anti").select(names).union(partners).where("low < high")
        large.mapInArrow(lean(divided), MEMBERS).write.parquet(f"{folder}/parts{level}")
        parts, level = spark.read.parquet(f"{folder}/parts{level}"), level + 1
    fit = reduce(DataFrame.union, fit).repartition("g").sortWithinPartitions("g")
    return reduce(DataFrame.union, [fit.mapInArrow(lean(lambda b: match_groups(b, length, gram)), "doc long, key long, lo int, hi int"), *settled])


def packed_texts(texts: DataFrame) -> DataFrame:
    """(doc, key, z): texts compressed before they are shuffled."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press = zstandard.ZstdCompressor(level=3)
        for batch in batches:
            z = [press.compress(x or b"") for x in as_binary(batch.column(2)).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(z, pa.binary())], names=["doc", "key", "z"])

    return texts.mapInArrow(lean(run), "doc long, key long, z binary")


def repeated_spans(docs: DataFrame, length: int = 200, gram: int = 64, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(own_doc, own_key, spans): for rows (see ``keyed``) with repeated strings, the byte intervals (lo, hi) that cover them; ends may lie beyond the text's."""
    spark = small_batches(docs).sparkSession
    texts = keyed(docs, id_col, text_col)
    folder = f"{ensure_checkpoint_dir(spark)}/suffixes-{uuid.uuid4().hex}"
    kinds, grams = W.partitionBy("deal", "f", "c1", "c2"), W.partitionBy("deal", "f")
    met = find_anchors(texts, length, gram, common_grams(texts, length, gram)).repartition("deal")
    met = met.withColumn("total", F.sum("copies").over(kinds)).withColumn("row", F.row_number().over(kinds.orderBy("doc", "key", "place")))
    met = met.withColumn("kinds", F.sum((F.col("row") == 1).cast("long")).over(grams)).withColumn("rarest", F.min("total").over(grams))
    spread = F.col("deal") != F.col("f")
    fetch = (F.col("copies") > 0) & (F.col("row") == 1) & (spread | (F.col("kinds") > 1) & (F.col("rarest") == 1))
    met = met.select("doc", "key", "place", "upto", "f", "copies", "total", "kinds", spread.alias("spread"), fetch.alias("fetch"))
    met.where("copies = 0 or copies = 1 and total > 1 or fetch").write.parquet(f"{folder}/met")
    met = spark.read.parquet(f"{folder}/met")
    back = length - gram
    settled = met.where("copies = 0").select("doc", "key", F.col("place").alias("lo"), F.col("upto").alias("hi"))
    settled = settled.union(met.where("copies = 1 and total > 1").select("doc", "key", F.greatest(F.col("place") - back, F.lit(0)), F.col("place") + length))

    # common grams, no more than MOST_COMMON of them, were dealt out by surroundings: count their kinds here
    spread = met.where("fetch and spread").groupBy("f").agg(F.count("*").alias("n"), F.min("total").alias("least")).where("n > 1 and least = 1").select("f", "n")
    wanted = met.where("fetch").join(F.broadcast(spread), "f", "left").where("not spread or n is not null")
    wanted = wanted.groupBy("doc", "key").agg(F.collect_list(F.struct("f", "place", "total", F.coalesce("n", "kinds").alias("kinds"))).alias("wanted"))
    wanted = wanted.toDF("own_doc", "own_key", "wanted")
    zipped = packed_texts(texts)
    bytes_of = zipped.join(wanted, same_row(zipped, wanted)).select("doc", "key", "z", "wanted")

    limit = GROUP_LIMIT

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The bytes around anchors; those of grams with more kinds than a task sorts, divided already."""
        open_ = zstandard.ZstdDecompressor()
        for batch in batches:
            out: list[tuple] = []
            for doc, key, z, want in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                text = open_.decompress(z)
                for w in want:
                    place = w["place"]
                    row = (w["f"].to_bytes(8, "little", signed=True), 0, back, doc, key, place, w["total"] == 1, text[max(0, place - back) : place + length])
                    out.extend(halves(row, length, gram) if w["kinds"] > limit else [(*row, None)])
                    if len(out) >= BATCH:
                        yield as_batch(out)
                        out = []
            yield as_batch(out)

    bytes_of.mapInArrow(lean(cut), MEMBERS).write.parquet(f"{folder}/around")
    every = settled.union(matches(spark.read.parquet(f"{folder}/around"), folder, length, gram))
    out = cut_lineage(every.groupBy("doc", "key").agg(F.collect_set(F.struct("lo", "hi")).alias("spans")).toDF("own_doc", "own_key", "spans"))
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
    return out


def kept_parts(text: bytes, found: list[dict] | None) -> tuple[list[bytes], int, int]:
    """The bytes left, how many went, and in how many maximal runs."""
    parts, removed, runs, at, end = [], 0, 0, 0, -1
    for s in sorted((x["lo"], x["hi"]) for x in found or ()):
        lo, hi = s[0], min(s[1], len(text))
        if lo > end:
            runs += 1
            parts.append(text[at:lo])
        new = max(hi, end)
        removed += new - max(lo, end) if lo <= end else hi - lo
        at = end = new
    parts.append(text[at:])
    return parts, removed, runs


def remove_repeats(docs: DataFrame, length: int = 200, gram: int = 64, id_col: str = "doc_id", text_col: str = "text", keep_text: bool = False) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256), and with ``keep_text`` the remaining text as ``kept``.

    A byte goes if a string of ``length`` bytes that starts anywhere else in the table, the same
    text included, covers it. ``kept`` drops the bytes of characters that a cut divides. Null texts count as
    empty; texts shorter than ``length`` stay whole. Repeated rows are repeats of each other. An
    empty table gives no rows; other columns are not read.
    """
    found = repeated_spans(docs, length, gram, id_col, text_col)
    rows = packed_texts(keyed(docs, id_col, text_col))
    joined = rows.join(found, same_row(rows, found), "left").select(F.col("doc").alias("doc_id"), "z", "spans")
    names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"] + ["kept"] * keep_text

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        open_ = zstandard.ZstdDecompressor()
        for batch in batches:
            out: list[list] = [[] for _ in range(5)]
            for z, spans_ in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                text = open_.decompress(z)
                parts, removed, runs = kept_parts(text, spans_)
                left = b"".join(parts)
                for column, value in zip(out, (len(text), removed, runs, sha256(left).hexdigest(), b"".join(p.decode("utf-8", "ignore").encode() for p in parts).decode() if keep_text else None), strict=True):
                    column.append(value)
            arrays = [batch.column(0), *(pa.array(c, pa.int64()) for c in out[:3]), pa.array(out[3], pa.string())]
            yield pa.RecordBatch.from_arrays(arrays + [pa.array(out[4], pa.string())] * keep_text, names=names)

    return joined.mapInArrow(lean(run), "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept string" * keep_text)


def strip_repeats(docs: DataFrame, length: int = 200, gram: int = 64, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` without their repeated strings; rows of which nothing but white space is left go.

    Whole characters stay whole: the bytes of a character that a cut divides go with it. A column
    ``n_chars`` is counted anew. Texts without repeats, null texts among them, stay as they are.
    """
    found = repeated_spans(docs, length, gram, id_col, text_col)
    others = [c for c in docs.columns if c != text_col]
    shaped = keyed(docs, id_col, text_col, F.struct(*others).alias("rest"))
    rest = shaped.schema["rest"].dataType.simpleString()

    def press(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = zstandard.ZstdCompressor(level=3)
        for batch in batches:
            z = [None if x is None else own.compress(x) for x in as_binary(batch.column(3)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(z, pa.binary())], names=["doc", "key", "rest", "z"])

    def restore(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = zstandard.ZstdDecompressor()
        for batch in batches:
            texts, stays = [], []
            for z, spans_ in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                text = None if z is None else own.decompress(z)
                if spans_:
                    parts, _, _ = kept_parts(text, spans_)
                    text = b"".join(p.decode("utf-8", "ignore").encode() for p in parts)
                stays.append(not spans_ or bool(text.strip()))
                texts.append(text)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.binary()).cast(pa.string()), pa.array(stays)], names=["rest", "text", "stays"])

    packed = shaped.mapInArrow(lean(press), f"doc long, key long, rest {rest}, z binary")
    joined = packed.join(found, same_row(packed, found), "left").select("rest", "z", "spans")
    out = joined.mapInArrow(lean(restore), f"rest {rest}, text string, stays boolean").where("stays")
    columns = [F.col("text").alias(c) if c == text_col else F.length("text").cast(docs.schema[c].dataType).alias(c) if c == "n_chars" else F.col("rest")[c].alias(c) for c in docs.columns]
    return out.select(*columns)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents"))


#: The same rows from all windows of 200 bytes. Windows are cut from blocks of 1000, as SQL finds a place in a string by walking there.
ORACLE = """
WITH docs AS (SELECT row_number() OVER () AS r, doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
blocks AS (SELECT r, j, substr(h, 2000 * j + 1, 2398) AS p FROM (SELECT r, h, unnest(range(0, length(h) // 2000 + 1)) AS j FROM docs)),
windows AS (SELECT r, 1000 * j + o AS i, md5(substr(p, 2 * o + 1, 400)) AS m FROM (SELECT r, j, p, unnest(range(0, least(1000, length(p) // 2 - 199))) AS o FROM blocks WHERE length(p) >= 400)),
twice AS (SELECT m FROM windows GROUP BY m HAVING count(*) > 1),
hit AS (SELECT r, i FROM windows WHERE m IN (SELECT m FROM twice)),
steps AS (SELECT r, i, CASE WHEN i - lag(i) OVER (PARTITION BY r ORDER BY i) <= 200 THEN 0 ELSE 1 END AS fresh FROM hit),
runs AS (SELECT r, min(i) AS lo, max(i) + 200 AS hi FROM (SELECT r, i, sum(fresh) OVER (PARTITION BY r ORDER BY i) AS run FROM steps) GROUP BY r, run),
ends AS (SELECT r, lo AS upto, coalesce(lag(hi) OVER (PARTITION BY r ORDER BY lo), 0) AS since FROM runs
  UNION ALL SELECT docs.r, length(any_value(h)) // 2, coalesce(max(hi), 0) FROM docs LEFT JOIN runs ON runs.r = docs.r GROUP BY docs.r),
kept AS (SELECT r, coalesce(string_agg(substr(h, 2 * since + 1, 2 * (upto - since)), '' ORDER BY since, upto), '') AS k FROM ends JOIN docs USING (r) GROUP BY r),
sums AS (SELECT r, sum(hi - lo)::BIGINT AS n_removed, count(*) AS n_spans FROM runs GROUP BY r)
SELECT doc_id, length(h) // 2 AS n_bytes, coalesce(n_removed, 0) AS n_removed, coalesce(n_spans, 0) AS n_spans, sha256(unhex(k)) AS kept_sha256
FROM docs JOIN kept USING (r) LEFT JOIN sums USING (r)
"""
