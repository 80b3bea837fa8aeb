"""Row samplers: what an iteration reads, and the weight that makes its sums unbiased."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from gradvb.functions.scalars import hash_uniform
from gradvb.session import ensure_checkpoint_dir

#: Index lists of at most this many rows are broadcast; longer ones are joined by a shuffle.
BROADCAST_INDEX = 2_000_000


def index_frame(spark: SparkSession, index) -> DataFrame:
    """A pandas index list as a table, by Arrow whatever the session says: row objects would take a hundred times its memory."""
    return spark.createDataFrame(pa.Table.from_pandas(index, preserve_index=False))


def build_store(obs: DataFrame, tiles: int = 16, key: str = "obs_key", salt: str = "tile") -> DataFrame:
    """Adds ``tile`` (hashed at random) and ``row_idx`` (0.. within its tile): one shuffle, done once, that deals tiles out evenly (hashed, some tasks had several and others none)."""
    tile = F.least(F.floor(hash_uniform(salt, F.col(key)) * tiles), F.lit(tiles - 1)).cast("int")
    parts = min(tiles, max(LEAST_TILES, int(obs.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    rows = obs.withColumn("tile", tile).repartitionById(parts, F.col("tile"))
    return rows.withColumn("row_idx", (F.row_number().over(W.partitionBy("tile").orderBy(F.md5(F.col(key).cast("binary")), key)) - 1).cast("bigint"))


#: Rows of a tile, and rows up to which a store is cached; a larger one is written, with a folder for each tile and its rows in order.
TILE_ROWS, CACHED_ROWS, LEAST_TILES = 2_000_000, 20_000_000, 16


def lay_out(obs: DataFrame, tiles: int = 0, key: str = "obs_key", cached_rows: int = CACHED_ROWS) -> DataFrame:
    """The store that fits sample from; with no number of ``tiles``, tiles of about ``TILE_ROWS`` rows.

    A written store lies in the shared checkpoint folder. Its rows are sorted within tiles, so a range of
    ``row_idx`` reads the row groups that hold it, and a list of tiles reads their folders.
    """
    n = obs.count()
    store = build_store(obs, tiles or max(LEAST_TILES, -(-n // TILE_ROWS)), key)
    if n <= cached_rows:
        return store.cache()
    folder = f"{ensure_checkpoint_dir(obs.sparkSession)}/store-{uuid.uuid4().hex}"
    store.sortWithinPartitions("tile", "row_idx").write.partitionBy("tile").option("parquet.block.size", 8 << 20).parquet(folder)
    return obs.sparkSession.read.parquet(folder)


def tile_counts(store: DataFrame) -> dict[int, int]:
    return {r["tile"]: r["count"] for r in store.groupBy("tile").count().collect()}


def assign_chunks(obs: DataFrame, chunks: int, key: str = "obs_key", salt: str = "chunk") -> DataFrame:
    """Random chunks by a second hash of the key."""
    return obs.withColumn("chunk_id", F.least(F.floor(hash_uniform(salt, F.col(key)) * chunks), F.lit(chunks - 1)).cast("int"))


def sample_source(key) -> np.random.Generator:
    return np.random.Generator(np.random.Philox(key=int(np.random.SeedSequence(list(key)).generate_state(1, np.uint64)[0])))


def skip(rng: np.random.Generator, numbers: int) -> None:
    """Goes on as if so many uniform numbers had been drawn; the generator makes four at a time, so whole fours are jumped over."""
    rest = min(numbers, 4 - rng.bit_generator.state["buffer_pos"])
    rng.random(rest)
    if numbers > rest:  # the last four are used up
        rng.bit_generator.advance((numbers - rest) // 4)
        rng.random((numbers - rest) % 4)


def draw_indices(counts: dict[int, int], m: int, *key: int, part: range | None = None) -> tuple[np.ndarray, np.ndarray]:
    """``m`` uniform draws with replacement as (tile, row_idx), or a ``part`` of them: multinomial over tiles, uniform within each."""
    tiles = np.array(sorted(counts), np.int64)
    sizes = np.array([counts[t] for t in tiles], np.int64)
    rng, part = sample_source(key), part or range(m)
    share = rng.multinomial(m, sizes / sizes.sum())
    if part.start:
        skip(rng, part.start)
    at = np.repeat(np.arange(len(tiles)), np.diff(np.clip(np.cumsum(share), part.start, part.stop), prepend=part.start))
    return tiles[at], (rng.random(len(part)) * sizes[at]).astype(np.int64)


def spread_indices(store: DataFrame, counts: dict[int, int], m: int, seed: int, iteration: int = 0, draws: int | None = None) -> DataFrame:
    """(draw_id, tile, row_idx, w): the sample of ``draw_indices``, of which executors draw ``TILE_ROWS`` rows at a time."""
    parts = [(s, lo, min(lo + TILE_ROWS, m)) for s in range(draws or 1) for lo in range(0, m, TILE_ROWS)]
    spark = store.sparkSession
    shares = spark.createDataFrame(pa.table(dict(zip(("draw_id", "lo", "hi"), map(list, zip(*parts, strict=True)), strict=True))))
    shipped = spark.sparkContext.broadcast(counts)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for s, lo, hi in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                tile, row = draw_indices(shipped.value, m, seed, iteration, s, part=range(lo, hi))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(tile), s, np.int32)), pa.array(tile.astype(np.int32)), pa.array(row)], names=["draw_id", "tile", "row_idx"])

    drawn = shares.repartition(min(len(parts), 4 * spark.sparkContext.defaultParallelism), "draw_id", "lo").mapInArrow(run, "draw_id int, tile int, row_idx long")
    return drawn.groupBy("draw_id", "tile", "row_idx").agg(F.count("*").cast("double").alias("w"))


def with_replacement(store: DataFrame, counts: dict[int, int], m: int, seed: int, iteration: int = 0, draws: int | None = None) -> tuple[DataFrame, float]:
    """The simple random sample: rows with multiplicity ``w``, or with ``draws`` one sample for each draw_id.

    Lists of up to ``BROADCAST_INDEX`` rows are drawn here and broadcast; longer ones, the same rows, are drawn by executors and joined by a shuffle.
    """
    import pandas as pd

    spark = store.sparkSession
    if m * (draws or 1) > BROADCAST_INDEX:
        index = spread_indices(store, counts, m, seed, iteration, draws)
        return store.join(index if draws else index.drop("draw_id"), ["tile", "row_idx"]), sum(counts.values()) / m
    lists = []
    for s in range(draws or 1):
        tile, row = draw_indices(counts, m, seed, iteration, s)
        lists.append(pd.DataFrame({"draw_id": s, "tile": tile.astype(np.int32), "row_idx": row}))
    index = pd.concat(lists)
    keys = ["tile", "row_idx"] if draws is None else ["draw_id", "tile", "row_idx"]
    index = index.groupby(keys, as_index=False).size().rename(columns={"size": "w"})
    index["w"] = index["w"].astype(float)
    frame = index_frame(spark, index)
    frame = frame.withColumn("tile", F.col("tile").cast("int"))
    return store.join(F.broadcast(frame), ["tile", "row_idx"]), sum(counts.values()) / m


def slice_ranges(counts: dict[int, int], m: int, *key: int) -> list[tuple[int, int, int]]:
    """(tile, first row, end): ``m`` rows that follow each other in the store's random order, from a row drawn uniformly; the end joins the beginning."""
    tiles = sorted(counts)
    ends = np.cumsum([counts[t] for t in tiles])
    rng = sample_source(key)
    at, left, out = int(rng.integers(ends[-1])), m, []
    while left:
        k = int(np.searchsorted(ends, at, side="right"))
        first = at - (int(ends[k]) - counts[tiles[k]])
        take_rows = min(left, counts[tiles[k]] - first)
        out.append((tiles[k], first, first + take_rows))
        left -= take_rows
        at = (at + take_rows) % int(ends[-1])
    return out


def slice_sample(store: DataFrame, counts: dict[int, int], m: int, seed: int, iterations: range) -> tuple[DataFrame, float]:
    """The rows of each iteration's slice, with ``iteration``: a literal filter by tile and row, which prunes folders and row groups.

    Rows lie in a hashed order, so a slice is a simple random sample without replacement that reads ``m`` rows and not the table.
    """
    which, any_ = [], F.lit(False)
    for t in iterations:
        for tile, lo, hi in slice_ranges(counts, m, seed, t):
            inside = (F.col("tile") == tile) & (F.col("row_idx") >= lo) & (F.col("row_idx") < hi)
            which.append(F.when(inside, F.lit(t)))
            any_ = any_ | inside
    rows = store.where(any_).withColumn("iteration", F.explode(F.array_compact(F.array(*which))))
    return rows.withColumn("w", F.lit(1.0)), sum(counts.values()) / m


def take(obs: DataFrame, scheme: str, rate: float, seed: int, key: str = "obs_key", m: int | None = None) -> tuple[DataFrame, float | None]:
    """A sample by another scheme, and its weight (None where rows carry it in ``w``).

    ``poisson`` and ``bernoulli`` draw rows at a rate as the scan goes; ``hash`` keeps keys below a
    hashed threshold; ``hash_rank`` keeps the ``m`` least hashes.
    """
    if scheme == "poisson":
        return obs.sample(True, rate, seed), 1 / rate
    if scheme == "bernoulli":
        return obs.sample(False, rate, seed), 1 / rate
    if scheme == "hash":
        return obs.where(hash_uniform(f"s{seed}", F.col(key)) < rate), 1 / rate
    if scheme == "hash_rank":
        n = obs.count()
        if m > n:
            raise ValueError(f"a sample of {m} from {n} rows")
        return obs.orderBy(hash_uniform(f"s{seed}", F.col(key)), key).limit(m), n / m
    raise ValueError(f"unknown scheme {scheme}")


def stratified(obs: DataFrame, fraction: float, seed: int, chunk_col: str = "chunk_id", key: str = "obs_key") -> DataFrame:
    """In each chunk the m_k = ceil(fraction n_k) rows of least hash, with weight w = n_k / m_k."""
    by_chunk = W.partitionBy(chunk_col)
    ranked = obs.withColumn("n_k", F.count("*").over(by_chunk)).withColumn("rank", F.row_number().over(by_chunk.orderBy(hash_uniform(f"s{seed}", F.col(key)), key)))
    m_k = F.ceil(F.col("n_k") * fraction)
    return ranked.where(F.col("rank") <= m_k).withColumn("w", F.col("n_k") / m_k).drop("rank", "n_k")


def tile_sample(store: DataFrame, tiles: int, take_tiles: int, seed: int, iteration: int = 0) -> tuple[DataFrame, float]:
    """``take_tiles`` of the tiles, whole; the literal list prunes the store's folders."""
    rng = sample_source([seed, iteration])
    chosen = sorted(rng.permutation(tiles)[:take_tiles].tolist())
    return store.where(F.col("tile").isin(chosen)), tiles / take_tiles
