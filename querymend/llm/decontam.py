"""Benchmark decontamination: test items inside documents by containment.

An item is contained when at least ``threshold`` of its distinct five-word
shingles occur in the document. Items are partitioned by size (powers of two);
a partition keeps of each item the least hashes of its shingles (a bottom-k
MinHash), k growing with the partition's size: with k > (1 - threshold) * size,
an item that is contained shares at least one kept hash with the document, so
the search misses none, however long the document is. Documents are searched
only for partitions whose items can be contained in so few shingles. Pairs
found are then verified by their exact shingles, in a second pass over the
documents that have any.

An item of one to four words is one shingle of that many words and is searched
among the documents' shingles of that width.

DataFrame and SQL functions only. The items' hashes are broadcast up to
``broadcast_rows`` rows and joined by a shuffle beyond it. Words are runs of
letters and digits in lower case; null texts and texts without words have no
shingles. Rows that share an id are one
document. Other columns are left behind.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize, workspace

WIDTH = 5


def words(text: Column) -> Column:
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda w: w != "")


def shingle_hashes(word_list: Column, width: int | Column = WIDTH) -> Column:
    """Hashes of all shingles in order; empty for fewer words than ``width``."""
    width = F.lit(width) if isinstance(width, int) else width
    starts = F.sequence(F.lit(1), F.greatest(F.size(word_list) - width + 1, F.lit(1)))
    return F.when(F.size(word_list) >= width, F.transform(starts, lambda i: F.xxhash64(F.slice(word_list, i, width)))).otherwise(F.expr("cast(array() as array<bigint>)"))


def _exploded(df: DataFrame, key: str, text: str, width: int) -> DataFrame:
    """(doc, n, h) of every shingle. The outer explode keeps the optimizer from
    pushing a filter on the list's size below, where it would put the splitting
    of the text inside the function that runs for every shingle."""
    listed = df.select(F.col(key).alias("doc"), words(F.col(text)).alias("w")).select("doc", (F.size("w") - width + 1).alias("n"), shingle_hashes(F.col("w"), width).alias("s"))
    return listed.select("doc", "n", F.explode_outer("s").alias("h")).where("h is not null")


def contained_items(docs: DataFrame, items: DataFrame, threshold: float = 0.8, width: int = WIDTH, key: str = "doc_id", item: str = "item_id", text: str = "text", broadcast_rows: int = 2_000_000) -> DataFrame:
    """(key, item, n_item, n_shared, containment) of every contained pair."""
    folder = workspace(docs.sparkSession)
    listed = items.select(F.col(item).alias("item"), words(F.col(text)).alias("w")).withColumn("width", F.least(F.size("w"), F.lit(width)))
    grams = listed.where("width > 0").select("item", "width", F.explode_outer(F.array_distinct(shingle_hashes(F.col("w"), F.col("width")))).alias("h")).where("h is not null").distinct()
    # an id that repeats with texts of several widths is an item for each
    sizes = grams.groupBy("item", "width").agg(F.count("*").alias("n_item"), F.array_sort(F.collect_list("h")).alias("hs"))
    percent = round(100 * threshold)
    # size partition: 2^band <= n_item < 2^(band + 1)
    sizes = sizes.withColumn("band", F.floor(F.log2("n_item")).cast("int"))
    top = F.pow(F.lit(2), F.col("band") + 1) - 1
    sizes = materialize(sizes.withColumn("k", F.least(F.col("n_item"), F.floor(F.lit(100 - percent) * top / 100) + 1).cast("int")), folder, "items")
    widths = sorted((r[0] for r in sizes.select("width").distinct().collect()), reverse=True)
    small = (sizes.agg(F.sum("n_item")).first()[0] or 0) <= broadcast_rows
    parts = [_contained(docs, sizes.where(F.col("width") == w), percent, w, key, text, small, broadcast_rows, f"{folder}/width{w}") for w in widths or [width]]
    return reduce(DataFrame.unionAll, parts).select(F.col("doc").alias(key), F.col("item").alias(item), "n_item", "n_shared", F.round(F.col("n_shared") / F.col("n_item"), 6).alias("containment"))


def _contained(docs: DataFrame, sizes: DataFrame, percent: int, width: int, key: str, text: str, small: bool, broadcast_rows: int, folder: str) -> DataFrame:
    """(doc, item, n_item, n_shared) for the items of one shingle width, which
    is at most the five of the search: as many passes as widths occur."""
    fit = (lambda df: F.broadcast(df)) if small else (lambda df: df.hint("merge"))
    sketch = sizes.select("item", F.ceil(F.lit(percent) * F.pow(F.lit(2), F.col("band")) / 100).alias("least"), F.explode(F.slice("hs", 1, F.col("k"))).alias("h"))
    every = sizes.select("item", "n_item", F.explode("hs").alias("h"))
    found = _exploded(docs, key, text, width).join(fit(sketch), "h").where("n >= least").select("doc", "item").distinct()
    found = materialize(found, folder, "candidates")
    ids = materialize(found.select("doc").distinct(), folder, "ids")
    few = ids.count() <= broadcast_rows
    again = docs.select(F.col(key).alias("doc"), F.col(text).alias("text")).join(F.broadcast(ids) if few else ids.hint("merge"), "doc", "left_semi")
    shared = _exploded(again, "doc", "text", width).select("doc", "h").join(fit(every), "h").select("doc", "item", "n_item", "h").distinct()
    shared = shared.groupBy("doc", "item", "n_item").agg(F.count("*").alias("n_shared")).where(F.col("n_shared") * 100 >= F.col("n_item") * percent)
    return shared.join(found, ["doc", "item"], "left_semi")


def keep_clean(docs: DataFrame, items: DataFrame, text: str = "text", broadcast_rows: int = 2_000_000, **options) -> DataFrame:
    """The rows of ``docs``, all columns, that contain no item. Each row is
    judged by its own text, under a 64-bit hash of it; ids, which may be null or
    carry several texts, do not matter."""
    rows = docs.withColumn("_row", F.xxhash64(text))
    hit = materialize(contained_items(rows, items, key="_row", text=text, **options).select(F.col("_row").alias("_hit")).distinct(), workspace(docs.sparkSession), "hit")
    hit = F.broadcast(hit) if hit.count() <= broadcast_rows else hit.hint("merge")
    return rows.join(hit, F.col("_row") == F.col("_hit"), "left_anti").select(*docs.columns)
