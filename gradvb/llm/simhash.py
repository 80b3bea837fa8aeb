"""SimHash near-duplicates by deletion-variant signatures."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradvb.llm.common import IS_SPACE, LOWER, POWERS, as_binary, checked, is_short, lean, mix, prefix_hash, runs, slices, small_batches, span_hash, table
from gradvb.llm.components import components
from gradvb.session import cut_lineage

#: A text of more than this share (one in so many) of the rows is named without a shuffle of its copies.
HOT = 10_000
#: Buckets up to this size are compared pair by pair at once, larger ones by a search that keeps a forest.
SMALL = 24


def fingerprint(text: bytes, shingle: int, seed: int) -> int:
    """The 64 majority bits of the hashes of a text's word shingles; no words give zero."""
    from xxhash import xxh64_digest

    found = text.lower().split()
    if not found:
        return 0
    joined = b" ".join(found)
    n = max(1, len(found) - shingle + 1)
    if n == 1:
        digests = xxh64_digest(joined, seed)
    else:
        ends = np.cumsum([len(w) + 1 for w in found])
        starts = np.concatenate([[0], ends[: n - 1]]).tolist()
        digests = b"".join([xxh64_digest(joined[s:e], seed) for s, e in zip(starts, (ends[shingle - 1 :] - 1).tolist(), strict=True)])
    bits = np.unpackbits(np.frombuffer(digests, np.uint8).reshape(n, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * bits > n).tobytes(), "big", signed=True)


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, seed: int = 42) -> DataFrame:
    """(id, fp): words are runs without ASCII white space, A-Z lowered; fewer words than a shingle make one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fp = [fingerprint(x or b"", shingle, seed) for x in as_binary(batch.column(1)).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fp, pa.int64())], names=["id", "fp"])

    return small_batches(docs).select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")).mapInArrow(lean(run), "id long, fp long")


def signatures(prints: DataFrame) -> DataFrame:
    """64 rows a fingerprint: each 32-bit half with one bit wiped out, tagged by half and bit.

    Two fingerprints that differ in at most three bits differ in at most one bit of some half,
    so they share the signature that wipes out this bit.
    """
    tag = F.explode(F.sequence(F.lit(0), F.lit(63))).alias("tag")
    half = F.when(F.col("tag") < 32, F.shiftrightunsigned("fp", 32)).otherwise(F.col("fp").bitwiseAND(F.lit(0xFFFFFFFF)))
    wiped = half.bitwiseAND(F.expr("~shiftleft(1L, tag % 32)"))
    return prints.select("fp", tag).select(F.shiftleft(F.col("tag").cast("long"), 32).bitwiseOR(wiped).alias("sig"), "fp")


def linked(x: np.ndarray, y: np.ndarray, tag: np.ndarray, bits: int) -> np.ndarray:
    """Whether pairs differ in at most ``bits`` bits, and ``tag`` is the first signature that the pair shares."""
    diff = x ^ y
    top, low = diff >> np.uint64(32), diff & np.uint64(0xFFFFFFFF)
    n_top, n_low = np.bitwise_count(top), np.bitwise_count(low)
    use_low = n_top > 1
    own = np.where(use_low, low, top)
    first = np.where(own > 0, np.bitwise_count(own - np.uint64(1) * (own > 0)), 0) + 32 * use_low
    return (n_top + n_low <= bits) & (x != y) & (np.where(use_low, n_low, n_top) <= 1) & (first == tag)


def links_in(sig: np.ndarray, fp: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Links within runs of equal signatures; a large run yields a spanning forest of its links."""
    cuts = np.flatnonzero(np.concatenate([[True], sig[1:] != sig[:-1], [True]]))
    size = np.diff(cuts)
    tag = sig >> np.uint64(32)
    run_size = np.repeat(size, size)
    left, right = [], []
    for step in range(1, min(SMALL, int(size.max(initial=0)))):
        i = np.flatnonzero((sig[step:] == sig[:-step]) & (run_size[step:] <= SMALL))
        i = i[linked(fp[i], fp[i + step], tag[i], bits)]
        left.append(fp[i])
        right.append(fp[i + step])
    for k in np.flatnonzero(size > SMALL):
        rest = np.unique(fp[cuts[k] : cuts[k + 1]])
        mark = tag[cuts[k]]
        frontier: list[np.uint64] = []
        while len(rest) or frontier:
            if not frontier:
                frontier, rest = [rest[-1]], rest[:-1]
            node = frontier.pop()
            near = linked(rest, node, mark, bits)
            found = rest[near]
            left.append(np.full(len(found), node))
            right.append(found)
            frontier.extend(found)
            rest = rest[~near]
    empty = np.zeros(0, np.uint64)
    return np.concatenate(left or [empty]), np.concatenate(right or [empty])


def near_links(prints: DataFrame, bits: int = 3) -> DataFrame:
    """Links (a, b) that connect all distinct fingerprints within ``bits`` (at most 3) of each other.

    Signatures meet by an equality shuffle. The task then walks its sorted signatures run by run
    and verifies each pair's bits.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []

        def close(sig: np.ndarray, fp: np.ndarray) -> Iterator[pa.RecordBatch]:
            a, b = links_in(sig, fp, bits)
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

        for batch in batches:
            sig = batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
            fp = batch.column(1).to_numpy(zero_copy_only=False).view(np.uint64)
            if not len(sig):
                continue
            last = int(np.searchsorted(sig, sig[-1], side="left"))
            if held and (last > 0 or held[0][0][0] != sig[0]):
                held.append((sig[:last], fp[:last]))
                yield from close(np.concatenate([h[0] for h in held]), np.concatenate([h[1] for h in held]))
                held = []
            elif last > 0:
                yield from close(sig[:last], fp[:last])
            held.append((sig[last:], fp[last:]))
        if held:
            yield from close(np.concatenate([h[0] for h in held]), np.concatenate([h[1] for h in held]))

    return signatures(prints).repartition("sig").sortWithinPartitions("sig").mapInArrow(lean(run), "a long, b long")


def simhash_groups(
    docs: DataFrame, shingle: int = 3, bits: int = 3, seed: int = 42, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """(doc_id, fingerprint, component_id) for every row of ``docs``.

    The component is the smallest doc_id among all rows reachable by links of at most ``bits``
    differing bits. Equal texts meet as one fingerprint before anything is compared. Null and
    empty texts have fingerprint zero and link like any other; rows with a null id take part and
    never name a component unless all of it has null ids; repeated rows come back as often as
    they came; an empty table gives no rows; other columns are not read.
    """
    if not 0 <= bits <= 3:
        raise ValueError("two halves find at most three differing bits")
    each = cut_lineage(fingerprints(docs, id_col, text_col, shingle, seed))
    prints = cut_lineage(each.groupBy("fp").agg(F.min("id").alias("first_id"), F.count("*").alias("n")))
    groups = components(near_links(prints.select("fp"), bits))
    known = prints.join(groups, prints["fp"] == groups["node"], "left").select("fp", "first_id", "n", F.coalesce("component", "fp").alias("group"))
    known = cut_lineage(known)
    least = known.groupBy("group").agg(F.min("first_id").alias("component_id"))
    names = cut_lineage(known.join(least, "group").select("fp", "n", "component_id"))
    # fingerprints of more than a HOT-th of the rows, HOT of them at most, are named where their rows lie
    many = F.col("n") * HOT > (names.agg(F.sum("n")).first()[0] or 0)
    hot = names.where(many).select(F.col("fp").alias("hot_fp"), F.col("component_id").alias("hot_id"))
    tagged = each.join(F.broadcast(hot), each["fp"] == hot["hot_fp"], "left")
    rest = tagged.where("hot_fp is null").select("id", "fp").join(names.where(~many), "fp").select("id", "fp", "component_id")
    found = tagged.where("hot_fp is not null").select("id", "fp", F.col("hot_id").alias("component_id")).union(rest)
    return found.select(F.col("id").alias("doc_id"), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_groups(table(spark, sf_dir, "documents"))


#: Texts that tell which shingles are common, in how many of them one is, and how many common ones are kept; they order shingles, which moves the cost and never the result.
SAMPLE, COMMON, MOST_COMMON = 10_000, 8, 100_000
#: Texts of a bucket of shingles that a task compares at a time, rows of a bucket that a task holds, and keys of texts that it knows as seen.
BLOCK, RUN, SEEN = 4000, 500_000, 500_000

Common = tuple[np.ndarray, np.ndarray]


def shingle_hashes(column: pa.Array, size: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Slices of a text column as (first row, rows, row of each shingle, hash): each text's set of ``shingle_set``, as 64-bit hashes."""
    for first_row, data, offsets in slices(column, 1_000_000):
        n = len(offsets) - 1
        starts, ends, text = runs(~IS_SPACE[data], offsets)
        word = mix(span_hash(prefix_hash(LOWER[data]), starts, ends)) if len(starts) else np.zeros(0, np.uint64)
        count = np.bincount(text, minlength=n)
        first = np.cumsum(count) - count
        up, _ = POWERS.get(size + 1)
        whole = np.flatnonzero(text[size - 1 :] == text[: max(0, len(text) - size + 1)])
        short = np.flatnonzero(count < size)
        full, part = np.zeros(len(whole), np.uint64), count[short].astype(np.uint64)
        with np.errstate(over="ignore"):
            for k in range(size):
                full += word[whole + k] * up[k + 1]
                more = count[short] > k
                part[more] += word[first[short[more]] + k] * up[k + 1]
        owner, hashed = np.concatenate([text[whole], short]), np.concatenate([mix(full), mix(part)])
        order = np.lexsort((hashed, owner))
        owner, hashed = owner[order], hashed[order]
        new = np.ones(len(owner), bool)
        new[1:] = (owner[1:] != owner[:-1]) | (hashed[1:] != hashed[:-1])
        yield first_row, n, owner[new], hashed[new]


def prefixes(column: pa.Array, size: int, least: float, common: Common) -> tuple[pa.Array, pa.Array]:
    """Each text's number of shingles, and as many of its first ones as two texts of a similarity of ``least`` must share one of.

    All texts order shingles alike: those not known as common by hash, then the common ones, rarest first.
    """
    known, place = common
    sizes, kept, lengths = [], [], []
    for _, n, owner, hashed in shingle_hashes(column, size):
        rank = np.zeros(len(hashed), np.int64)
        if len(known):
            at = np.minimum(np.searchsorted(known, hashed), len(known) - 1)
            rank = np.where(known[at] == hashed, place[at], 0)
        order = np.lexsort((hashed, rank, owner))
        count = np.bincount(owner, minlength=n)
        take = count - np.ceil(least * count - 1e-9).astype(np.int64) + 1
        position = np.arange(len(owner)) - (np.cumsum(count) - count)[owner]
        sizes.append(count)
        lengths.append(np.minimum(take, count))
        kept.append(hashed[order][position < take[owner]])
    empty = [np.zeros(0, np.int64)]
    ends = np.concatenate([[0], np.cumsum(np.concatenate(lengths or empty))])
    values = np.concatenate(kept or [np.zeros(0, np.uint64)]).view(np.int64)
    return pa.array(np.concatenate(sizes or empty), pa.int64()), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(values))


def common_shingles(rows: DataFrame, share: float, size: int) -> Common:
    """Hashes, sorted, and places of the shingles that many texts of a sample by key hold, the rarest first."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys = batch.column(0).to_numpy(zero_copy_only=False)
            for first, _, owner, hashed in shingle_hashes(batch.column(1), size):
                yield pa.RecordBatch.from_arrays([pa.array(keys[first + owner]), pa.array(hashed.view(np.int64))], names=["key", "h"])

    sample = rows.where(F.pmod(F.xxhash64("key"), F.lit(1 << 20)) < int(share * (1 << 20))).select("key", "text")
    counted = sample.mapInArrow(lean(run), "key long, h long").distinct().groupBy("h").agg(F.count("*").alias("n")).where(F.col("n") >= COMMON)
    found = counted.orderBy(F.desc("n"), "h").limit(MOST_COMMON).collect()
    hashes = np.array([r.h for r in found], np.int64).view(np.uint64)
    order = np.argsort(hashes)
    return hashes[order], (len(found) - np.arange(len(found)))[order]


def whole_runs(batches: Iterator[pa.RecordBatch], limit: int) -> Iterator[tuple[list[np.ndarray], bool, bool]]:
    """The columns of sorted batches, cut where the first column changes, or within a run of more than ``limit`` rows.

    With them comes whether the first run began in the piece before, whose last row is then repeated, and whether the last run goes on.
    """
    held: list[list[np.ndarray]] = []
    began = False

    def joined() -> list[np.ndarray]:
        return [np.concatenate(c) for c in zip(*held, strict=True)]

    for batch in batches:
        if not batch.num_rows:
            continue
        columns = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
        last = int(np.searchsorted(columns[0], columns[0][-1], side="left"))
        if held and (last > 0 or held[0][0][0] != columns[0][0]):
            held.append([c[:last] for c in columns])
            yield joined(), began, False
            held, began = [], False
        elif last > 0:
            yield [c[:last] for c in columns], False, False
        held.append([c[last:] for c in columns])
        if sum(len(h[0]) for h in held) > limit:
            piece = joined()
            yield piece, began, True
            held, began = [[c[-1:] for c in piece]], True
    if held:
        yield joined(), began, False


def may_be_near(n: np.ndarray, pos: np.ndarray, i, j, least: float) -> np.ndarray:
    """Whether enough shingles are left from the first shared one on. Pairs that are near pass in the bucket of the first they share."""
    return np.minimum(n[i] - pos[i], n[j] - pos[j]) >= np.ceil(least / (1 + least) * (n[i] + n[j]) - 1e-9)


def first_pairs(least: float):
    """From (h, key, n, pos) sorted by h and key: all pairs of small buckets as (a, b); of large ones a chain and a star, and each row as (a, null, h, n, pos)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for columns, began, goes_on in whole_runs(batches, RUN):
            h, key = columns[:2]
            new = np.ones(len(h), bool)
            new[1:] = (h[1:] != h[:-1]) | (key[1:] != key[:-1])
            h, key, n, pos = (c[new] for c in columns)
            size = np.diff(np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1], [True]])))
            in_run, start = np.repeat(size, size), np.repeat(np.cumsum(size) - size, size)
            if began:
                in_run[: size[0]] = SMALL + 1
            if goes_on:
                in_run[len(h) - size[-1] :] = SMALL + 1
            left, right = [], []
            for step in range(1, min(SMALL, int(size.max()))):
                i = np.flatnonzero((h[step:] == h[:-step]) & ((in_run[step:] <= SMALL) | (step == 1)))
                i = i[may_be_near(n, pos, i, i + step, least)]
                left.append(i)
                right.append(i + step)
            big = np.flatnonzero(in_run > SMALL)
            star = big[(start[big] != big) & may_be_near(n, pos, big, start[big], least)]
            i, j = np.concatenate([*left, star]), np.concatenate([*right, start[star]])
            if len(i):
                none = pa.nulls(len(i), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(key[i], key[j])), pa.array(np.maximum(key[i], key[j])), none, none, none], names=["a", "b", "h", "n", "pos"])
            big = big[began:] if len(big) and big[0] == 0 else big
            if len(big):
                yield pa.RecordBatch.from_arrays([pa.array(key[big]), pa.nulls(len(big), pa.int64()), pa.array(h[big]), pa.array(n[big]), pa.array(pos[big])], names=["a", "b", "h", "n", "pos"])

    return run


def met_before(member: np.ndarray, shingle: np.ndarray, size: int) -> np.ndarray:
    """Rows of 0 and 1 whose product tells how many of the given shingles two members share."""
    names, code, count = np.unique(shingle, return_inverse=True, return_counts=True)
    shared = count > 1
    place = np.cumsum(shared) - 1
    out = np.zeros((size, int(shared.sum())), np.float32)
    own = shared[code]
    out[member[own], place[code[own]]] = 1
    return out


def bitmaps(column: pa.Array, size: int) -> pa.Array:
    """Each text's set of shingles as a bitmap of at least four bits a shingle, by the first bits of their hashes."""
    out = []
    for _, n, owner, hashed in shingle_hashes(column, size):
        ends = np.searchsorted(owner, np.arange(n + 1))
        for lo, hi in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True):
            power = max(6, int(4 * (hi - lo) - 1).bit_length())
            bits = np.zeros(1 << power, bool)
            bits[(hashed[lo:hi] >> np.uint64(64 - power)).astype(np.int64)] = True
            out.append(np.packbits(bits, bitorder="little").tobytes())
    return pa.array(out, pa.binary())


def halved(maps: np.ndarray) -> np.ndarray:
    """Bitmaps (rows of bytes) of half the width: each two neighbouring bits as one."""
    bits = np.unpackbits(maps, axis=1, bitorder="little")
    return np.packbits(bits[:, ::2] | bits[:, 1::2], axis=1, bitorder="little")


class Maps:
    """Bitmaps of a group's texts by width, which a text shares with those of up to twice its shingles."""

    def __init__(self, maps: list[bytes]) -> None:
        self.width = np.array([len(m) for m in maps])
        self.row = np.zeros(len(maps), np.int64)
        self.own: dict[int, np.ndarray] = {}
        for w in np.unique(self.width).tolist():
            at = np.flatnonzero(self.width == w)
            self.row[at] = np.arange(len(at))
            self.own[w] = np.frombuffer(b"".join(maps[k] for k in at), np.uint8).reshape(len(at), w)
        self.folded = {w // 2: halved(m) for w, m in self.own.items() if w > 8}

    def most_shared(self, n: np.ndarray, i: int, j: np.ndarray) -> np.ndarray:
        """Upper bounds of the shingles that text i shares with each of j, of no smaller size: a bit that the other lacks stands for one that it lacks at least."""
        w = int(self.width[i])
        mine = self.own[w][self.row[i]].view(np.uint64)
        out = np.minimum(n[i], n[j])
        for kind, maps in ((w, self.own.get(w)), (2 * w, self.folded.get(w))):
            at = np.flatnonzero(self.width[j] == kind)
            if len(at):
                theirs = maps[self.row[j[at]]].view(np.uint64)
                both = np.bitwise_count(theirs & mine).sum(axis=1, dtype=np.int64)
                lost = int(np.bitwise_count(mine).sum()) - both, np.bitwise_count(theirs).sum(axis=1, dtype=np.int64) - both
                out[at] = np.minimum(n[i] - lost[0], n[j[at]] - lost[1])
        return out


def open_pairs(least: float):
    """From (g, key, n, pos, label, block, same, before, bits) sorted by g and n: the pairs (x, y) of a bucket that have different labels and may be near.

    ``same`` pairs a block with itself; ``before`` lists the large buckets of a row that come before this one in the order of shingles, so
    a pair comes out of the first large bucket that it shares, and of no other. Bitmaps bound what a pair shares, so those that come out are near or nearly so.
    """

    def close(columns: list, before: pa.ListArray, bits: list[bytes]) -> Iterator[pa.RecordBatch]:
        key, n, pos, label, block, same = columns
        if (label == label[0]).all():
            return
        sizes = before.value_lengths().to_numpy(zero_copy_only=False)
        met = met_before(np.repeat(np.arange(len(sizes)), sizes), before.flatten().to_numpy(zero_copy_only=False), len(key))
        maps = Maps(bits)
        left, right = [], []
        for i in range(len(key) - 1):
            end = int(np.searchsorted(n, n[i] / least + 1e-6, side="right"))
            j = np.arange(i + 1, end)
            j = j[(label[j] != label[i]) & (bool(same[0]) | (block[j] != block[i]))]
            j = j[may_be_near(n, pos, i, j, least)]
            if met.shape[1] and len(j):
                j = j[met[j] @ met[i] == 0]
            if len(j):
                j = j[maps.most_shared(n, i, j) >= np.ceil(least / (1 + least) * (n[i] + n[j]) - 1e-9)]
                left.append(np.full(len(j), key[i]))
                right.append(key[j])
        if left:
            x, y = np.concatenate(left), np.concatenate(right)
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y))], names=["x", "y"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def flush() -> Iterator[pa.RecordBatch]:
            whole = pa.Table.from_batches(held).combine_chunks()
            yield from close([whole.column(k).to_numpy() for k in range(1, 7)], whole.column(7).combine_chunks(), whole.column(8).to_pylist())

        for batch in batches:
            g = batch.column(0).to_numpy(zero_copy_only=False)
            cuts = np.flatnonzero(np.concatenate([[True], g[1:] != g[:-1], [True]])) if len(g) else np.zeros(0, np.int64)
            for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                if held and held[0].column(0)[0].as_py() != g[lo]:
                    yield from flush()
                    held = []
                held.append(batch.slice(lo, hi - lo))
        if held:
            yield from flush()

    return run


def still_open(members: DataFrame, links: DataFrame, texts: DataFrame, shingle: int, least: float) -> DataFrame:
    """Pairs (x, y) of the large buckets ``members`` that ``links`` leave apart and that may be near. Buckets are dealt out by pairs of blocks; those whose texts are one group already are left out."""
    groups = components(links)
    held = members.groupBy("key").agg(F.collect_list(F.struct("pos", "h")).alias("own"))
    rows = members.join(held, "key").join(groups, F.col("key") == groups["node"], "left")
    rows = cut_lineage(rows.select("h", "key", "n", "pos", F.coalesce("component", "key").alias("label"), F.transform(F.filter("own", lambda o: o["pos"] < F.col("pos")), lambda o: o["h"]).alias("before")))
    apart = rows.groupBy("h").agg(F.ceil(F.count("*") / BLOCK).alias("blocks"), F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo < hi").select("h", "blocks")
    rows = rows.join(checked(cut_lineage(apart)), "h")
    keys = cut_lineage(rows.select(F.col("key").alias("own_key")).distinct())

    def mapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), bitmaps(batch.column(1), shingle)], names=["own_key", "bits"])

    chosen = texts.join(checked(keys), texts["key"] == keys["own_key"], "left_semi").select("key", "text")
    chosen = chosen.mapInArrow(lean(mapped), "own_key long, bits binary").groupBy("own_key").agg(F.first("bits").alias("bits"))
    rows = rows.withColumn("block", F.pmod(F.xxhash64("key"), F.col("blocks"))).join(chosen, F.col("key") == F.col("own_key"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    group = F.xxhash64("h", F.least("block", "other"), F.greatest("block", "other"))
    # a block meets itself as (k, k) and every other block as (k, other)
    rows = rows.select(group.alias("g"), "key", "n", "pos", "label", "block", (F.col("block") == F.col("other")).cast("long").alias("same"), "before", "bits")
    return rows.repartition("g").sortWithinPartitions("g", "n").mapInArrow(lean(open_pairs(least)), "x long, y long").distinct()


def shingle_set(text: bytes, size: int) -> set[bytes]:
    found = text.lower().split()
    return {b" ".join(found[k : k + size]) for k in range(max(1, len(found) - size + 1))}


def similarity(a: set, b: set) -> float:
    return len(a & b) / len(a | b)


def fingerprint_pairs(texts: DataFrame, bits: int = 3) -> DataFrame:
    """Pairs (x, y) of keys of ``texts`` (key, text) that SimHash links: the least key of a fingerprint with every other key of it, and with those of fingerprints within ``bits`` of it.

    Links of large signature runs are a spanning forest, as ``near_links`` gives them.
    """
    each = cut_lineage(fingerprints(texts, "key", "text").groupBy("id", "fp").agg(F.lit(1).alias("one")).select("id", "fp"))
    leads = cut_lineage(each.groupBy("fp").agg(F.min("id").alias("lead"), F.count("*").alias("n")))
    shared = checked(cut_lineage(leads.where("n > 1").select("fp", F.col("lead").alias("x"))))
    same = each.join(shared, "fp").where("id != x").select("x", F.col("id").alias("y"))
    ends = leads.select("fp", "lead")
    near = near_links(leads.select("fp"), bits).join(ends.toDF("a", "la"), "a").join(ends.toDF("b", "lb"), "b")
    return same.union(near.select(F.least("la", "lb"), F.greatest("la", "lb")))


def rows_that_stay(docs: DataFrame, shingle: int = 5, least: float = 0.8, bits: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text_key) of the rows that stay: one of each group of equal or near-equal texts, that of the smallest id.

    Texts are near if their sets of ``shingle`` words have a similarity of ``least``. SimHash pairs texts whose fingerprints are at most ``bits`` apart. An exact
    search gives the pairs that fingerprints miss: two near texts share one of the first shingles of each, in an order common to all texts, and meet there. Each pair is
    verified on the texts. Small buckets give all their pairs. Large ones first give a chain and a star, then every pair that the links
    verified so far, SimHash's among them, leave apart and that bitmaps of both texts' shingles do not rule out, so no pair that could join two groups is left out.
    """
    import zstandard

    rows = small_batches(docs).select(F.col(id_col).cast("long").alias("id"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("key"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    firsts = cut_lineage(rows.groupBy("key").agg(F.min("id").alias("first_id")))
    common = common_shingles(rows, min(1.0, SAMPLE / max(1, firsts.count())), shingle)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()  # copies that a task meets again add nothing; those of other tasks are told apart in their buckets
        for batch in batches:
            fresh = []
            for k in batch.column(0).to_pylist():
                fresh.append(k not in seen)
                seen.add(k)
            if len(seen) > SEEN:
                seen.clear()
            batch = batch.filter(pa.array(fresh, pa.bool_()))
            yield pa.RecordBatch.from_arrays([batch.column(0), *prefixes(batch.column(1), shingle, least, common)], names=["key", "n", "prefix"])

    texts = rows.select("key", "text").mapInArrow(lean(cut), "key long, n long, prefix array<long>")
    buckets = texts.select("key", "n", F.posexplode("prefix").alias("pos", "h")).select("h", "key", "n", F.col("pos").cast("long").alias("pos"))
    met = buckets.repartition("h").sortWithinPartitions("h", "key").mapInArrow(lean(first_pairs(least)), "a long, b long, h long, n long, pos long")
    met = cut_lineage(met)
    found = met.where("b is not null").select(F.col("a").alias("x"), F.col("b").alias("y")).union(fingerprint_pairs(rows.select("key", "text"), bits))
    found = cut_lineage(found.distinct())
    members = met.where("b is null").select("h", F.col("a").alias("key"), "n", "pos")

    def zipped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press = zstandard.ZstdCompressor(level=3)
        for batch in batches:
            z = [press.compress(x) for x in as_binary(batch.column(2)).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(z, pa.binary())], names=["id", "key", "z"])

    def verified(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        open_, kept, last = zstandard.ZstdDecompressor(), set(), None
        for batch in batches:
            out = []
            for x, y, zx, zy in zip(*(batch.column(k).to_pylist() for k in range(4)), strict=True):
                if x != last:
                    kept, last = shingle_set(open_.decompress(zx), shingle), x
                if similarity(kept, shingle_set(open_.decompress(zy), shingle)) >= least:
                    out.append((x, y))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], names=["a", "b"])

    def verify(found: DataFrame) -> DataFrame:
        ends = found.select(F.col("x").alias("own")).union(found.select("y")).distinct()
        ends = cut_lineage(ends.join(firsts, ends["own"] == firsts["key"]).select("own", "first_id"))
        chosen = (F.col("key") == F.col("own")) & F.col("id").eqNullSafe(F.col("first_id"))
        if is_short(ends):
            bodies = rows.join(F.broadcast(ends), chosen).select("id", "key", "text").mapInArrow(lean(zipped), "id long, key long, z binary")
        else:
            bodies = rows.mapInArrow(lean(zipped), "id long, key long, z binary").join(ends, chosen)
        bodies = cut_lineage(bodies.groupBy("key").agg(F.first("z").alias("z")))
        pairs = found.join(bodies.toDF("x", "zx"), "x").join(bodies.toDF("y", "zy"), "y").select("x", "y", "zx", "zy")
        return cut_lineage(pairs.mapInArrow(lean(verified), "a long, b long"))

    links = verify(found)
    if not members.isEmpty():
        rest = cut_lineage(still_open(members, links, rows.select("key", "text"), shingle, least).join(found, ["x", "y"], "left_anti"))
        if not rest.isEmpty():
            links = links.union(verify(rest))
    groups = components(links)
    named = firsts.join(groups, firsts["key"] == groups["node"], "left").select("key", "first_id", F.coalesce("component", "key").alias("group"))
    best = named.groupBy("group").agg(F.min(F.struct(F.col("first_id").isNull(), "first_id", "key")).alias("best"))
    return best.select(F.col("best.first_id").alias("doc_id"), F.col("best.key").alias("text_key"))


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of ``docs`` that ``rows_that_stay`` leaves, each once, with all their columns."""
    stay = cut_lineage(rows_that_stay(docs, id_col=id_col, text_col=text_col, **options)).toDF("stay_id", "stay_key")
    key = F.xxhash64(F.coalesce(docs[text_col], F.lit("")))
    kept = docs.join(stay, docs[id_col].cast("long").eqNullSafe(stay["stay_id"]) & (key == stay["stay_key"]), "left_semi")
    ids = docs.select(docs[id_col].cast("long").alias("id"), key.alias("key")).groupBy("id", "key").agg(F.count("*").alias("n"))
    if ids.where("n > 1").isEmpty():
        return kept
    return kept.dropDuplicates([id_col, text_col])
