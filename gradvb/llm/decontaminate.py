"""Benchmark decontamination by winnowed fingerprints, joined and extended."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from gradvb.llm.common import ascii_lower, table

#: Benchmarks whose fingerprints are at most this many rows, of some 200 bytes each, are broadcast; larger ones are joined by a shuffle.
BROADCAST_ROWS = 100_000


def split_words(df: DataFrame, keep: list[str], text_col: str) -> DataFrame:
    """``keep``, the pieces of a text, how many of them stand before its first word, and its number of words."""
    parts = F.split(ascii_lower(F.coalesce(F.col(text_col), F.lit(""))), r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    first = F.when(F.get("parts", F.lit(0)) == "", 1).otherwise(0)
    last = F.when((F.size("parts") > 1) & (F.get("parts", F.size("parts") - 1) == ""), 1).otherwise(0)
    return df.select(*keep, parts.alias("parts")).select(*keep, "parts", first.alias("skip"), F.greatest(F.size("parts") - first - last, F.lit(0)).alias("n"))


def hashed_words(df: DataFrame, keep: list[str], text_col: str) -> DataFrame:
    """``keep`` and the array ``h`` of word hashes (null and wordless texts: empty)."""
    cut = split_words(df, keep, text_col).select(*keep, F.transform("parts", lambda w: F.xxhash64(w)).alias("all_h"), "skip", "n")
    return cut.select(*keep, F.slice("all_h", F.col("skip") + 1, F.col("n")).alias("h"))


def grams(h: str, size: int) -> Column:
    """Hashes of all runs of ``size`` neighbouring words."""
    run = F.transform(F.sequence(F.lit(0), F.size(h) - size), lambda i: F.xxhash64(*(F.get(F.col(h), i + k if k else i) for k in range(size))))
    return F.when(F.size(h) >= size, run).otherwise(F.array().cast("array<bigint>"))


def winnowed(hashed: DataFrame, keep: list[str], window: int, gram: int) -> DataFrame:
    """One row per selected gram: ``keep``, its hash ``f``, place ``p``, and the words around it.

    A gram is selected if its hash is the least of some ``window - gram + 1`` neighbouring ones (fewer where
    the text ends), so two texts that share ``window`` words share a selected gram there. As no least hash
    exceeds the hashes it is taken of, a gram is selected when the largest least hash around it is its own.
    ``near`` has the hashes of the words from ``window - gram`` before it to as many after its end, null
    beyond the text.
    """
    span, reach = window - gram + 1, window - gram
    have = hashed.where(F.size("h") >= window).select(*keep, "h", grams("h", gram).alias("g"))
    low = F.transform("g", lambda x, i: F.least(x, *(F.get(F.col("g"), i + k) for k in range(1, span))))
    have = have.select(*keep, "h", "g", low.alias("low"))

    def pick(x: Column, p: Column) -> Column:
        top = F.greatest(F.get(F.col("low"), p), *(F.get(F.col("low"), p - k) for k in range(1, span)))
        near = F.array(*(F.get(F.col("h"), p + k) for k in range(-reach, gram + reach)))
        return F.when(top == x, F.struct(x.alias("f"), p.alias("p"), near.alias("near")))

    picked = F.filter(F.transform("g", pick), lambda v: v.isNotNull())
    return have.select(*keep, F.explode(picked).alias("x")).select(*keep, "x.f", "x.p", "x.near")


def extended(matches: DataFrame, window: int, gram: int) -> tuple[Column, Column]:
    """First word and end of the equal stretch around a matching gram, looked at ``window - gram`` words either way."""
    reach = window - gram
    same = [F.coalesce(F.get("near", F.lit(k)) == F.get("item_near", F.lit(k)), F.lit(False)) for k in range(gram + 2 * reach)]
    left_run = F.lit(reach)
    for step in range(reach, 0, -1):
        left_run = F.when(~same[reach - step], F.lit(step - 1)).otherwise(left_run)
    right_run = F.lit(reach)
    for step in range(reach, 0, -1):
        right_run = F.when(~same[reach + gram + step - 1], F.lit(step - 1)).otherwise(right_run)
    whole = same[reach]
    for k in range(1, gram):
        whole = whole & same[reach + k]
    start, end = F.col("p") - left_run, F.col("p") + gram + right_run
    return F.when(whole, start), F.when(whole, end)


def spans_of(
    docs: DataFrame,
    benchmark: DataFrame,
    window: int = 10,
    gram: int = 5,
    id_col: str = "doc_id",
    text_col: str = "text",
    item_col: str = "item_id",
    item_text_col: str = "text",
) -> DataFrame:
    """(doc_id, text_key, item, s, e): stretches of words that hold occurring windows of an item."""
    texts = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    texts = texts.select("doc_id", F.xxhash64("text").alias("text_key"), "text")
    items = hashed_words(benchmark.select(F.col(item_col).cast("string").alias("item"), F.col(item_text_col).alias("item_text")), ["item"], "item_text")
    words = hashed_words(texts, ["doc_id", "text_key"], "text")
    lengths = [r.n for r in items.select(F.size("h").alias("n")).where(f"n between 1 and {window - 1}").distinct().collect()]

    marks = winnowed(items, ["item"], window, gram).select("f", "item", F.col("near").alias("item_near"))
    if marks.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS:
        marks = F.broadcast(marks)
    met = winnowed(words, ["doc_id", "text_key"], window, gram).join(marks, "f")
    start, end = extended(met, window, gram)
    spans = met.select("doc_id", "text_key", "item", start.alias("s"), end.alias("e")).where(F.col("e") - F.col("s") >= window)
    for n in sorted(lengths):
        short = items.where(F.size("h") == n).select("item", F.element_at(grams("h", n), 1).alias("f"))
        if short.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS:
            short = F.broadcast(short)
        runs = words.select("doc_id", "text_key", F.posexplode(grams("h", n)).alias("p", "f"))
        spans = spans.union(runs.join(short, "f").select("doc_id", "text_key", "item", F.col("p").alias("s"), (F.col("p") + n).alias("e")))
    return spans


def contamination(
    docs: DataFrame,
    benchmark: DataFrame,
    window: int = 10,
    gram: int = 5,
    id_col: str = "doc_id",
    text_col: str = "text",
    item_col: str = "item_id",
    item_text_col: str = "text",
) -> DataFrame:
    """(doc_id, n_words, n_hit, n_items, items_sha256, contaminated) for every document.

    A document word is hit if it lies in any occurrence of ``window`` consecutive words of an item,
    or of a whole item that has fewer words. Both sides are winnowed to the least hash of each
    ``window - gram + 1`` neighbouring grams, selected grams meet by an equality join, and each
    meeting is extended word by word; stretches of ``window`` words or more count. Items
    shorter than a window meet all runs of their length.

    Null and wordless texts have no words and no hits; wordless items occur nowhere; items with a
    null id hit words and are not counted. Equal rows give equal results. An empty table gives no
    rows, an empty benchmark no hits. Extra columns are not read.
    """
    spans = spans_of(docs, benchmark, window, gram, id_col, text_col, item_col, item_text_col)
    texts = docs.select(F.col(id_col).alias("doc_id"), F.xxhash64(text_col).alias("text_key"), F.col(text_col).alias("text"))
    covered = F.aggregate(
        F.array_sort("spans"),
        F.struct(F.lit(0).alias("end"), F.lit(0).cast("long").alias("n")),
        lambda a, x: F.struct(F.greatest(a["end"], x["e"]).alias("end"), (a["n"] + F.greatest(F.lit(0), x["e"] - F.greatest(a["end"], x["s"]))).cast("long").alias("n")),
        lambda a: a["n"],
    )
    hits = spans.groupBy("doc_id", "text_key").agg(F.collect_set(F.struct("s", "e")).alias("spans"), F.collect_set("item").alias("items"))
    hits = hits.select(F.col("doc_id").alias("hit_id"), F.col("text_key").alias("hit_key"), covered.alias("n_hit"), F.array_sort("items").alias("items"))
    base = split_words(texts, ["doc_id", "text_key"], "text").select("doc_id", "text_key", F.col("n").cast("long").alias("n_words"))
    joined = base.join(hits, F.col("doc_id").eqNullSafe(F.col("hit_id")) & (F.col("text_key") == F.col("hit_key")), "left")
    items_of = F.coalesce("items", F.array().cast("array<string>"))
    n_hit = F.coalesce("n_hit", F.lit(0).cast("long"))
    return joined.select(
        "doc_id",
        "n_words",
        n_hit.alias("n_hit"),
        F.size(items_of).cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", items_of).cast("binary"), 256).alias("items_sha256"),
        (n_hit > 0).alias("contaminated"),
    )


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of ``docs`` in which no word is hit, with all their columns."""
    found = spans_of(docs, benchmark, id_col=id_col, text_col=text_col, **options)
    hit = found.groupBy("doc_id", "text_key").agg(F.count("*").alias("n")).select(F.col("doc_id").alias("hit_id"), F.col("text_key").alias("hit_key"))
    return docs.join(hit, docs[id_col].eqNullSafe(hit["hit_id"]) & (F.xxhash64(docs[text_col]) == hit["hit_key"]), "left_anti")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


#: The same by plain comparison of all windows.
ORACLE = r"""
WITH item_words AS (
  SELECT item_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w
  FROM benchmark
), item_windows AS (
  SELECT DISTINCT item_id, least(len(w), 10) AS n, list_aggregate(w[i : i + least(len(w), 10) - 1], 'string_agg', ' ') AS win
  FROM item_words, LATERAL (SELECT unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS i)
  WHERE len(w) > 0
), sizes AS (SELECT DISTINCT n FROM item_windows),
doc_words AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w
  FROM documents
), doc_windows AS (
  SELECT doc_id, i, n, list_aggregate(w[i : i + n - 1], 'string_agg', ' ') AS win
  FROM doc_words, sizes, LATERAL (SELECT unnest(range(1, len(w) - n + 2)) AS i)
  WHERE len(w) >= n
), hits AS (
  SELECT doc_id, i, d.n, item_id FROM doc_windows d JOIN item_windows USING (win) WHERE d.n = item_windows.n
), hit_words AS (
  SELECT doc_id, count(DISTINCT p) AS n_hit FROM hits, LATERAL (SELECT unnest(range(i, i + n)) AS p) GROUP BY doc_id
), hit_items AS (
  SELECT doc_id, count(DISTINCT item_id) AS n_items, string_agg(DISTINCT item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS items FROM hits GROUP BY doc_id
)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM doc_words LEFT JOIN hit_words USING (doc_id) LEFT JOIN hit_items USING (doc_id)
"""
