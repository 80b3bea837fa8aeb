"""Embedding near-duplicates by a forest of random-projection trees with spill."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradvb.llm.common import table
from gradvb.llm.components import components, forest
from gradvb.session import cut_lineage

#: A vector of more than this share (one in so many) of the rows is named without a shuffle of its copies.
HOT = 1_000
#: Leaves of more vectors are compared chunk against chunk, so that no task holds more than two chunks.
CHUNK = 4096


def unit(x: np.ndarray) -> np.ndarray:
    """Rows of length one in double precision; scaled first, so that no square overflows."""
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


@dataclass
class Tree:
    """One random direction a level; a node's threshold is the median of the fitted sample's projections there."""

    directions: np.ndarray
    thresholds: list[np.ndarray]
    spill: float
    shrink: float

    def leaves(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, leaf): rows near a threshold go to both sides. What is near shrinks from level to level, so copies stay few in trees of any depth."""
        row, code = np.arange(len(x)), np.zeros(len(x), np.int64)
        for level, direction in enumerate(self.directions):
            cut = self.thresholds[level]
            gap = (x @ direction)[row] - cut[code if len(cut) > 1 else np.zeros(len(code), np.int64)]
            near = self.spill * self.shrink**level
            left, right = gap <= near, gap > -near
            row, code = np.concatenate([row[left], row[right]]), np.concatenate([2 * code[left], 2 * code[right] + 1])
        return row, code


def fit_tree(sample: np.ndarray, dim: int, depth: int, spill: float, rng: np.random.Generator, least: int = 16, shrink: float = 0.91) -> Tree:
    """Medians by node while nodes hold ``least`` of the sample on average; below that, one median a level."""
    directions = rng.normal(size=(depth, dim))
    directions /= np.linalg.norm(directions, axis=1, keepdims=True)
    code, thresholds = np.zeros(len(sample), np.int64), []
    for level in range(depth):
        gap = sample @ directions[level]
        overall = float(np.median(gap)) if len(gap) else 0.0
        nodes = 1 << level
        if len(sample) < least * nodes:
            cut = np.array([overall])
            code = 2 * code + (gap > overall) if nodes < 1 << 62 else code
        else:
            cut = np.full(nodes, overall)
            order = np.argsort(code, kind="stable")
            edges = np.searchsorted(code[order], np.arange(nodes + 1))
            for k in range(nodes):
                own = gap[order[edges[k] : edges[k + 1]]]
                if len(own):
                    cut[k] = np.median(own)
            code = 2 * code + (gap > cut[code])
        thresholds.append(cut)
    return Tree(directions, thresholds, spill, shrink)


def vectors_of(column: pa.Array, dim: int) -> np.ndarray:
    """A list column as a matrix of doubles, short rows padded with zeros."""
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    sizes = column.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    out = np.zeros((len(sizes), dim))
    at = np.arange(len(flat)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    out[np.repeat(np.arange(len(sizes)), sizes), at] = flat
    return out


def compare(batches: Iterator[pa.RecordBatch], least: float) -> Iterator[pa.RecordBatch]:
    """From (group, part, node, copies, before, vector) sorted by group: links (a, b) that connect what a group's pairs of a cosine of at least ``least`` connect, and (a, null, more).

    ``more`` counts, for each node, the vectors it is linked with by pairs that met in no leaf before this one (``before`` lists a
    node's leaves in order up to it), so every pair counts in one group alone. What comes out grows with the nodes, not with their pairs.
    """
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("more", pa.int64())])
    held: list[pa.RecordBatch] = []

    def close() -> Iterator[pa.RecordBatch]:
        whole = pa.Table.from_batches(held).combine_chunks()
        part, node, copies = (whole.column(c).to_numpy() for c in ("part", "node", "copies"))
        before, vector = (whole.column(c).combine_chunks() for c in ("before", "vector"))
        if len(node) < 2:
            return
        sizes = before.value_lengths().to_numpy(zero_copy_only=False)
        met = shared_flags(np.repeat(np.arange(len(node)), sizes), before.flatten().to_numpy(zero_copy_only=False), len(node))
        x = unit(vectors_of(vector, int(vector.value_lengths().to_numpy(zero_copy_only=False).max())))
        mixed = part.min() != part.max()
        more, links = np.zeros(len(node), np.int64), []
        for lo in range(0, len(node), 512):
            near = x[lo : lo + 512] @ x.T >= least
            rows = np.arange(lo, lo + len(near))
            near[rows - lo, rows] = False
            if mixed:
                near &= part[rows][:, None] != part[None, :]
            a, b = np.nonzero(near)
            if len(a):
                links.append(forest(rows[a], b))
            if met.shape[1]:
                near &= met[rows] @ met.T == 0
            more[rows] += near @ copies
        if links:
            child, root = forest(*(np.concatenate([l[k] for l in links]) for k in (0, 1)))
            yield pa.RecordBatch.from_arrays([pa.array(node[child]), pa.array(node[root]), pa.nulls(len(child), pa.int64())], schema=schema)
        some = np.flatnonzero(more)
        if len(some):
            yield pa.RecordBatch.from_arrays([pa.array(node[some]), pa.nulls(len(some), pa.int64()), pa.array(more[some])], schema=schema)

    for batch in batches:
        code = batch.column(0).to_pylist()
        cuts = [k for k in range(len(code)) if k == 0 or code[k] != code[k - 1]] + [len(code)]
        for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
            if held and held[0].column(0)[0].as_py() != code[lo]:
                yield from close()
                held = []
            held.append(batch.slice(lo, hi - lo))
    if held:
        yield from close()


def shared_flags(member: np.ndarray, mark: np.ndarray, size: int) -> np.ndarray:
    """Rows of 0 and 1 whose product tells how many marks two members share."""
    _, code, count = np.unique(mark, return_inverse=True, return_counts=True)
    shared = count > 1
    place = np.cumsum(shared) - 1
    out = np.zeros((size, int(shared.sum())), np.float32)
    own = shared[code]
    out[member[own], place[code[own]]] = 1
    return out


def near_vectors(
    vectors: DataFrame,
    least: float = 0.93,
    trees: int = 8,
    leaf: int = 256,
    spill: float = 0.02,
    sample: int = 20_000,
    seed: int = 5,
    id_col: str = "vec_id",
    vector_col: str = "embedding",
    label_col: str = "label",
) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row of ``vectors``.

    Trees are fitted on at most ``sample`` distinct vectors; every distinct vector is then put
    into its leaves, and vectors of equal label and length that share a leaf are compared
    in double precision; a pair counts in the first leaf that it shares. Equal vectors of a label meet before that and count as linked. Rows
    whose label or vector is null, zero, empty, or holds a null or non-finite component
    link with nothing. Rows with a null id count as links of others, name no component, and are not kept.
    Repeated rows count as often as they come; an empty table gives no rows; other columns are not read.
    """
    spark = vectors.sparkSession
    fine = (
        F.col("label").isNotNull()
        & F.coalesce(F.forall("vector", lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))), F.lit(False))
        & F.coalesce(F.exists("vector", lambda v: v != 0), F.lit(False))
    )
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).alias("vector"), F.col(label_col).alias("label"))
    rows = rows.withColumn("fine", fine)
    alike = rows.where("fine").groupBy("label", "vector").agg(F.min("vec_id").alias("first_id"), F.count("*").alias("copies"))
    reps = cut_lineage(alike.withColumn("node", F.monotonically_increasing_id()))
    facts = reps.groupBy("label").agg(F.count("*").alias("n"), F.max(F.size("vector")).alias("dim")).agg(F.max("n").alias("n"), F.max("dim").alias("dim")).first()
    if not facts.n:
        return rows.select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.col("vec_id").isNotNull().alias("kept"))
    picked = reps.select("vector").orderBy(F.xxhash64("vector", F.lit(seed))).limit(sample).collect()
    known = np.zeros((len(picked), facts.dim))
    for k, r in enumerate(picked):
        known[k, : len(r.vector)] = r.vector
    depth = max(0, int(np.ceil(np.log2(facts.n / leaf))))
    rng = np.random.default_rng(seed)
    forest_ = spark.sparkContext.broadcast([fit_tree(unit(known), facts.dim, depth, spill, rng) for _ in range(trees)])

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A row for each leaf of each vector, with the leaves (tree and code in one number) that come before it."""
        for batch in batches:
            if not batch.num_rows:
                continue
            x = unit(vectors_of(batch.column(1), facts.dim))
            found = [tree.leaves(x) for tree in forest_.value]
            row = np.concatenate([r for r, _ in found])
            leaf_code = np.concatenate([np.int64(t) << np.int64(56) | c for t, (_, c) in enumerate(found)])
            order = np.lexsort((leaf_code, row))
            row, leaf_code = row[order], leaf_code[order]
            count = np.bincount(row, minlength=len(x))
            nth = np.arange(len(row)) - (np.cumsum(count) - count)[row]
            start = np.arange(len(row)) - nth
            flat = np.repeat(start - np.concatenate([[0], np.cumsum(nth)[:-1]]), nth) + np.arange(nth.sum())
            before = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(nth)]), pa.int32()), pa.array(leaf_code[flat]))
            at = pa.array(row)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(at), batch.column(2).take(at), pa.array(leaf_code), before], names=["node", "label_key", "leaf", "before"])

    keyed = reps.select("node", "vector", F.to_json(F.struct("label", F.size("vector").alias("size"))).alias("label_key"))
    placed = keyed.mapInArrow(assign, "node long, label_key string, leaf long, before array<long>")
    placed = cut_lineage(placed.select("node", F.struct("label_key", "leaf").alias("place"), "before"))
    large = placed.groupBy("place").agg(F.count("*").alias("n")).where(F.col("n") > CHUNK)
    large = large.select("place", F.ceil(F.col("n") / CHUNK).cast("int").alias("chunks"))
    placed = placed.join(large, "place", "left")
    own = F.pmod(F.xxhash64("node"), F.coalesce("chunks", F.lit(1))).cast("int")
    spread = placed.select("node", "place", "before", own.alias("own"), F.explode(F.sequence(F.lit(0), F.coalesce("chunks", F.lit(1)) - 1)).alias("other"))
    spread = spread.select("node", "before", F.to_json(F.struct("place", F.least("own", "other").alias("x"), F.greatest("own", "other").alias("y"))).alias("group"), F.col("own").alias("part"))
    met = spread.join(reps.select("node", "copies", "vector"), "node").select("group", "part", "node", "copies", "before", "vector")
    found = cut_lineage(met.repartition("group").sortWithinPartitions("group").mapInArrow(lambda b: compare(b, least), "a long, b long, more long"))
    linked = found.where("b is null").groupBy(F.col("a").alias("node")).agg(F.sum("more").alias("more"))
    pairs = found.where("b is not null").select("a", "b")
    groups = components(pairs).toDF("node", "group")
    known_reps = reps.join(linked, "node", "left").join(groups, "node", "left")
    known_reps = cut_lineage(known_reps.select("label", "vector", "copies", "first_id", (F.col("copies") - 1 + F.coalesce("more", F.lit(0))).alias("n_links"), F.coalesce("group", "node").alias("group")))
    least_ids = known_reps.groupBy("group").agg(F.min("first_id").alias("component_id"))
    named = cut_lineage(known_reps.join(least_ids, "group").select("label", "vector", "copies", "n_links", "component_id"))
    # vectors of more than a HOT-th of the rows, HOT of them at most, are named where their rows lie
    many = F.col("copies") * HOT > (named.agg(F.sum("copies")).first()[0] or 0)
    hot = F.broadcast(named.where(many).select("label", "vector", "n_links", "component_id"))
    own_rows = rows.where("fine")
    plain = own_rows.join(hot, ["label", "vector"], "left_anti").join(named.where(~many), ["label", "vector"])
    found = own_rows.join(hot, ["label", "vector"]).select("vec_id", "n_links", "component_id").union(plain.select("vec_id", "n_links", "component_id"))
    rest = rows.where("not fine").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return found.union(rest).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(False)))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_vectors(table(spark, sf_dir, "embeddings"))


#: The same rows from all pairs of a label.
ORACLE = """
WITH RECURSIVE rows_ AS (SELECT row_number() OVER () AS r, vec_id, label, embedding::DOUBLE[] AS e FROM embeddings),
fine AS (SELECT * FROM rows_ WHERE label IS NOT NULL AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(e, lambda x: x <> 0)) > 0),
links AS (SELECT a.r AS a, b.r AS b FROM fine a JOIN fine b ON a.label = b.label AND a.r <> b.r AND len(a.e) = len(b.e) AND list_cosine_similarity(a.e, b.e) >= 0.93),
reach AS (SELECT r, r AS c FROM fine UNION SELECT links.b, reach.c FROM reach JOIN links ON links.a = reach.r),
groups AS (SELECT reach.r, min(rows_.vec_id) AS component_id FROM reach JOIN rows_ ON rows_.r = reach.c GROUP BY reach.r),
counts AS (SELECT a AS r, count(*) AS n FROM links GROUP BY a),
named AS (SELECT vec_id, coalesce(n, 0) AS n_links, CASE WHEN groups.r IS NULL THEN vec_id ELSE component_id END AS component_id FROM rows_ LEFT JOIN groups USING (r) LEFT JOIN counts USING (r))
SELECT vec_id, n_links, component_id, coalesce(vec_id = component_id, false) AS kept FROM named
"""
