"""Benchmark decontamination: size-partitioned MinHash containment search, verified exactly.

Items are put into size classes (powers of two of their number of shingles). A class's sketch is the
k smallest MinHash values of an item, with k one more than the shingles that an item of the class's
largest size may miss: a document that holds the asked share of an item holds one of its sketch's
values at least, however long the document is. So candidates are complete, and containment is then
counted on all of the item's shingles. DataFrame functions only.
"""

from __future__ import annotations

from functools import partial

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import let, written

#: Item shingles up to which their table (16 bytes a row and overhead) is broadcast; beyond, the join is shuffled.
BROADCAST_ROWS = 500_000


def tokens(text: Column) -> Column:
    """Lower-cased runs of letters and digits."""
    t = F.trim(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+", " "))
    return F.when(t == "", F.array().cast("array<string>")).otherwise(F.split(t, " "))


def _shingles(w: Column, *, width: int) -> Column:
    made = F.transform(w, lambda x, i: F.xxhash64(F.lit(width), x, *[F.get(w, i + k) for k in range(1, width)]))
    return F.slice(made, F.lit(1), F.greatest(F.size(w) - (width - 1), F.lit(0)))


def item_shingles(items: DataFrame, width: int, share: float) -> DataFrame:
    """items(item_id, text) -> item_id, h, n_shingles, in_sketch, n_words (the width of its shingles).

    An item of fewer than `width` words is one shingle of all its words; one without words has none.
    """
    split = items.select("item_id", tokens(F.col("text")).alias("w"))
    made = F.when(F.size("w") >= width, let(F.col("w"), lambda w: _shingles(w, width=width)))
    for k in range(1, width):
        made = made.when(F.size("w") == k, let(F.col("w"), partial(_shingles, width=k)))
    rows = (
        split.filter(F.size("w") > 0)
        .groupBy("item_id", "w").agg(F.lit(1))
        .select("item_id", F.least(F.size("w"), F.lit(width)).alias("n_words"), F.explode(F.array_distinct(made)).alias("h"))
        .distinct()
    )
    by_item = W.partitionBy("item_id")
    counted = rows.withColumn("n_shingles", F.count("*").over(by_item)).withColumn(
        "_rank", F.row_number().over(by_item.orderBy(F.xxhash64(F.lit(7), "h"), "h"))
    )
    largest = F.pow(F.lit(2.0), F.ceil(F.log2("n_shingles")))
    allowed = F.floor(largest * (1 - share) + 1e-9) + 1
    return counted.select("item_id", "h", "n_words", "n_shingles", (F.col("_rank") <= allowed).alias("in_sketch"))


def _doc_shingles(docs: DataFrame, widths: list[int]) -> DataFrame:
    made = docs.select("doc_id", tokens(F.col("text")).alias("w"))
    return made.select("doc_id", F.explode(let(F.col("w"), lambda w: F.concat(*[_shingles(w, width=k) for k in widths]))).alias("h"))


def candidates(docs: DataFrame, sketches: DataFrame, widths: list[int]) -> DataFrame:
    """Pairs (doc_id, item_id) of a document that holds a value at least of an item's sketch(h, item_id)."""
    return _doc_shingles(docs, widths).join(sketches, "h").select("doc_id", "item_id").distinct()


def contained_items(docs: DataFrame, items: DataFrame, width: int = 5, share: float = 0.8, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """Pairs (doc_id, item_id, n_shingles, n_found, containment) with containment >= share.

    docs(doc_id, text, ...), items(item_id, text, ...). Texts are taken whole. Null and empty texts hold nothing and
    are held by nothing; repeated rows of either table count once; rows of one id (null too) unite their shingles. Empty tables
    give no pairs. Extra columns are ignored.
    """
    known = written(item_shingles(items, width, share), "items")
    widths = sorted(r[0] for r in known.select("n_words").distinct().collect())  # `width` values at most
    if not widths:
        widths = [width]
    sketches = known.filter("in_sketch").select("h", "item_id")
    if known.count() <= broadcast_rows:
        known, sketches = F.broadcast(known), F.broadcast(sketches)
    found = written(candidates(docs, sketches, widths), "candidates")
    # Only documents with a candidate are cut again, and only their candidates' shingles are looked up.
    pairs = found.select(F.col("doc_id").alias("_doc"), F.col("item_id").alias("_item"))
    same_doc, same_item = F.col("doc_id").eqNullSafe(F.col("_doc")), F.col("item_id").eqNullSafe(F.col("_item"))
    rows = _doc_shingles(docs.select("doc_id", "text").join(pairs.select("_doc").distinct(), same_doc, "left_semi"), widths)
    hits = (
        rows.join(known, "h").join(pairs, same_doc & same_item, "left_semi")
        .groupBy("doc_id", "item_id", "n_shingles").agg(F.count_distinct("h").alias("n_found"))
    )
    needed = F.ceil(F.col("n_shingles") * F.lit(share) - 1e-9)
    return hits.filter(F.col("n_found") >= needed).select(
        "doc_id", "item_id", "n_shingles", "n_found", (F.col("n_found") / F.col("n_shingles")).alias("containment")
    )
