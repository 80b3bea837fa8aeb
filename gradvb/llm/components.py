"""Connected components of a link table, without collecting links anywhere."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gradvb.session import cut_lineage

#: Links that a task contracts at a time; it bounds the task's memory.
BLOCK = 1_000_000


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Stars (child, least node of its group) that connect what the links connect."""
    nodes, flat = np.unique(np.concatenate([a, b]), return_inverse=True)
    label = np.arange(len(nodes))
    x, y = flat[: len(a)], flat[len(a) :]
    while True:
        low = np.minimum(label[x], label[y])
        before = label.copy()
        np.minimum.at(label, label[x], low)
        np.minimum.at(label, label[y], low)
        while True:
            jumped = label[label]
            if np.array_equal(jumped, label):
                break
            label = jumped
        if np.array_equal(before, label):
            break
    child = np.flatnonzero(label != np.arange(len(nodes)))
    return nodes[child], nodes[label[child]]


def contract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Replace a partition's links by stars, a block of links at a time."""
    held, size = [], 0

    def close() -> pa.RecordBatch:
        a, b = (np.concatenate([h[k] for h in held]) for k in (0, 1))
        child, root = forest(a, b)
        return pa.RecordBatch.from_arrays([pa.array(child), pa.array(root)], names=["child", "root"])

    for batch in batches:
        held.append((batch.column(0).to_numpy(zero_copy_only=False), batch.column(1).to_numpy(zero_copy_only=False)))
        size += batch.num_rows
        if size >= BLOCK:
            yield close()
            held, size = [], 0
    if size:
        yield close()


def components(links: DataFrame) -> DataFrame:
    """(node, component) for every node of ``links`` (its first two columns, longs).

    The component is the least node reachable. Links of a node with itself and links with a null
    end count for nothing; repeated links count once; no links give no rows. Each task first
    contracts its own links to stars; rounds of star contraction (neighbours of a node move to
    the least of them, larger ones first, then smaller ones) follow until only stars are left,
    every round written to the shared checkpoint folder.
    """
    a, b = links.columns[:2]
    stars = (
        links.select(F.least(a, b).alias("root"), F.greatest(a, b).alias("child"))
        .where("root < child")
        .select("child", "root")
        .mapInArrow(contract, "child long, root long")
    )
    stars = cut_lineage(stars.groupBy("child", "root").agg(F.lit(1).alias("one")).select("child", "root"))
    while not stars.isEmpty():
        both = stars.select(F.col("child").alias("u"), F.col("root").alias("v")).union(stars.select("root", "child"))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("child"), F.col("m").alias("root")).where("child > root")
        large = cut_lineage(large.groupBy("child", "root").agg(F.lit(1).alias("one")).select("child", "root"))
        low = large.groupBy("child").agg(F.min("root").alias("m"))
        moved = large.join(low, "child")
        small = moved.select("child", F.col("m").alias("root")).union(moved.select(F.col("root").alias("child"), F.col("m").alias("root")))
        stars = cut_lineage(small.where("child > root").groupBy("child", "root").agg(F.lit(1).alias("one")).select("child", "root"))
        parents = stars.groupBy("child").agg(F.count("*").alias("n"), F.max("root").alias("root"))
        chained = parents.join(parents.select(F.col("child").alias("root")), "root", "left_semi").select("root")
        if chained.union(parents.where("n > 1").select("root")).isEmpty():
            break
    roots = stars.select(F.col("root").alias("node")).groupBy("node").agg(F.first("node").alias("component"))
    return stars.select(F.col("child").alias("node"), F.col("root").alias("component")).union(roots)
