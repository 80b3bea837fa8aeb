"""Sharding by a k-d tree over document metadata, split at distributed weighted medians."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from gradvb.llm.common import table
from gradvb.session import cut_lineage

#: Bins of a histogram pass; the driver sees at most this many sums for each node of the level.
BINS = 512
#: Coordinates are (value, tie break), 31 and 32 bits; the first 10 of the tie break are the text's.
VALUE_BITS, TIE_BITS, TEXT_BITS = 31, 32, 10


@dataclass
class Node:
    """A cell of the tree: how many shards it becomes, and once split, the dimension, the cut and both sides."""

    shards: int
    number: int = 0
    dim: int = 0
    cut: int | None = None
    left: Node | None = None
    right: Node | None = None

    def leaves(self) -> list[Node]:
        return [self] if self.cut is None else self.left.leaves() + self.right.leaves()


def place(node: Node, coords: list[Column], value) -> Column:
    """The tree as one expression over the coordinates; ``value`` gives a leaf's result."""
    if node.cut is None:
        return value(node)
    return F.when(coords[node.dim] <= F.lit(node.cut), place(node.left, coords, value)).otherwise(place(node.right, coords, value))


def metadata(docs: DataFrame, dims: dict[str, Column], id_col: str, text_col: str) -> DataFrame:
    """Narrow rows: id, size, checksum and a coordinate per dimension, whose ties go by text, then by the row's number in the scan, scattered.

    The number tells even rows of equal id and text apart. It holds as long as these rows are written before they are used.
    """
    text = F.coalesce(F.col(text_col), F.lit("")).cast("binary")
    base = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        (F.octet_length(text) + 16).cast("long").alias("size"),
        F.crc32(text).alias("text_crc32"),
        *(F.coalesce(c.cast("long"), F.lit(0)).alias(f"v{k}") for k, c in enumerate(dims.values())),
    )
    base = base.withColumn("row", F.monotonically_increasing_id())
    by_text = F.shiftleft(F.shiftright("text_crc32", 32 - TEXT_BITS), TIE_BITS - TEXT_BITS)
    by_row = F.xxhash64("row").bitwiseAND(F.lit((1 << (TIE_BITS - TEXT_BITS)) - 1))
    return base.select(
        "doc_id", "size", "text_crc32", "row", *(F.shiftleft(F.col(f"v{k}"), TIE_BITS).bitwiseOR(by_text).bitwiseOR(by_row).alias(f"c{k}") for k in range(len(dims)))
    )


def default_dims(docs: DataFrame, text_col: str = "text") -> dict[str, Column]:
    """Length on a log scale, and source and language where the table has them, as 31-bit numbers."""
    length = F.floor(F.log2(F.octet_length(F.coalesce(F.col(text_col), F.lit("")).cast("binary")) + F.lit(16.0)) * F.lit(float(1 << 25)))
    dims = {"length": length}
    for name in ("source", "lang"):
        if name in docs.columns:
            dims[name] = F.shiftright(F.crc32(F.col(name).cast("string").cast("binary")), 1)
    return dims


def grow(meta: DataFrame, shards: int, dims: int) -> Node:
    """Split until each cell is one shard: along the widest dimension, where the bytes divide as the shards do."""
    coords = [F.col(f"c{k}") for k in range(dims)]
    root = Node(shards)
    spans = None
    while any(leaf.shards > 1 for leaf in root.leaves()):
        leaves = root.leaves()
        for number, leaf in enumerate(leaves):
            leaf.number = number
        facts = meta.groupBy(place(root, coords, lambda n: F.lit(n.number)).alias("node")).agg(
            F.sum("size").alias("bytes"), *(f(c).alias(f"{name}{k}") for k, c in enumerate(coords) for name, f in (("lo", F.min), ("hi", F.max)))
        )
        known = {r["node"]: r for r in facts.collect()}
        if spans is None:
            spans = [max(1, (known[0][f"hi{k}"] >> TIE_BITS) - (known[0][f"lo{k}"] >> TIE_BITS)) if known else 1 for k in range(dims)]
        search: dict[int, dict] = {}
        for leaf in leaves:
            if leaf.shards == 1:
                continue
            left = leaf.shards // 2
            row = known.get(leaf.number)
            if row is None:
                search[leaf.number] = {"done": True, "dim": 0, "cut": 0, "left": left}
                continue
            width = [((row[f"hi{k}"] >> TIE_BITS) - (row[f"lo{k}"] >> TIE_BITS)) / spans[k] for k in range(dims)]
            dim = max(range(dims), key=lambda k: (width[k], -k))
            lo, hi = row[f"lo{dim}"], row[f"hi{dim}"]
            search[leaf.number] = {"done": lo == hi, "dim": dim, "cut": lo, "left": left, "lo": lo, "hi": hi, "below": 0, "goal": row["bytes"] * left / leaf.shards, "slack": row["bytes"] / leaf.shards * 5e-4}
        while not all(s["done"] for s in search.values()):

            def bin_of(leaf: Node) -> Column:
                s = search.get(leaf.number)
                if s is None or s["done"]:
                    return F.lit(None).cast("long")
                step = -(-(s["hi"] - s["lo"] + 1) // BINS)
                s["step"] = step
                c = coords[s["dim"]]
                return F.when((c >= s["lo"]) & (c <= s["hi"]), F.lit(leaf.number * BINS) + F.expr(f"(c{s['dim']} - {s['lo']}L) div {step}L"))

            sums = meta.groupBy(place(root, coords, bin_of).alias("bin")).agg(F.sum("size").alias("bytes")).where("bin is not null").collect()
            by_node: dict[int, dict[int, int]] = {}
            for r in sums:
                by_node.setdefault(r["bin"] // BINS, {})[r["bin"] % BINS] = r["bytes"]
            for number, s in search.items():
                if s["done"]:
                    continue
                below = s["below"]
                found = by_node[number]
                for b in sorted(found):
                    if below + found[b] >= s["goal"] or b == max(found):
                        start, end = s["lo"] + b * s["step"], min(s["hi"], s["lo"] + (b + 1) * s["step"] - 1)
                        over, under = below + found[b] - s["goal"], s["goal"] - below
                        s["cut"] = end if over <= under else start - 1
                        if s["step"] == 1 or min(over, under) <= s["slack"]:
                            s["done"] = True
                        else:
                            s.update(lo=start, hi=end, below=below)
                        break
                    below += found[b]
        for leaf in leaves:
            if leaf.number in search:
                s = search[leaf.number]
                leaf.dim, leaf.cut = s["dim"], s["cut"]
                leaf.left, leaf.right = Node(s["left"]), Node(leaf.shards - s["left"])
    for number, leaf in enumerate(root.leaves()):
        leaf.number = number
    return root


def kd_shards(
    docs: DataFrame, shards: int = 40, dims: dict[str, Column] | None = None, slot_rows: int = 250_000, id_col: str = "doc_id", text_col: str = "text", target_bytes: int | None = None
) -> DataFrame:
    """Put every document into one of ``shards`` shards of nearly equal bytes (law ``bytes``); with ``target_bytes``, into as many as make them that large at most on average.

    Each cell of the tree is split along the dimension in which it is widest, relative to the whole
    table, at the weighted median found by passes of byte histograms over all rows; a cell that
    becomes an odd number of shards is split in proportion. Within equal values ties go by the
    text's checksum, then by the row's number in the scan, so a group of equal texts, of equal rows or of a hot source is split where
    balance needs it. Slots count from 0 in each shard: rows are numbered within hashed
    sub-groups of about ``slot_rows`` and shifted by the sizes of the sub-groups before.

    Null texts count 16 bytes and the checksum of an empty text. Null ids and null dimensions are
    values like any other. Repeated rows are split like other ties and get a slot each. An empty table gives no rows. Extra
    columns are not read.
    """
    dims = dims or default_dims(docs, text_col)
    meta = cut_lineage(metadata(docs, dims, id_col, text_col))
    if target_bytes:
        shards = max(1, -(-(meta.agg(F.sum("size")).first()[0] or 0) // target_bytes))
    root = grow(meta, shards, len(dims))
    coords = [F.col(f"c{k}") for k in range(len(dims))]
    placed = meta.select("doc_id", "size", "text_crc32", "row", place(root, coords, lambda n: F.lit(n.number)).alias("shard"))
    total = meta.count()
    subs = max(4, min(4096, -(-total // (shards * slot_rows))))
    placed = placed.withColumn("sub", F.pmod(F.xxhash64("row", F.lit(1)), F.lit(subs)).cast("int"))
    sizes = placed.groupBy("shard", "sub").agg(F.count("*").alias("n"))
    before = W.partitionBy("shard").orderBy("sub").rowsBetween(W.unboundedPreceding, -1)
    shifts = sizes.select("shard", "sub", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("shift"))
    order = W.partitionBy("shard", "sub").orderBy("doc_id", "text_crc32", "row")
    numbered = placed.withColumn("number", F.row_number().over(order))
    return numbered.join(F.broadcast(shifts), ["shard", "sub"]).select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("shift") + F.col("number") - 1).alias("slot"), F.lit(None).cast("int").alias("grown_shard")
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return kd_shards(table(spark, sf_dir, "documents"))
