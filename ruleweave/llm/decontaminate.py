"""Benchmark decontamination by size-partitioned MinHash containment search (op3), in DataFrame functions only.

Items are short, documents long, so their Jaccard similarity says little; what counts is containment, the share
of an item's distinct shingles that the document holds. Items fall into classes by size, powers of two. A class
fixes the number k of MinHash values kept for an item: its k shingles with the smallest hashes, with k so large that
an item of the class can't miss all of them and still reach the threshold. Such sketches are the smallest hashes, so a document's signature
against all classes is the part of its shingles with hashes up to the largest that any sketch keeps (its bottom MinHash values, as many as
that share of the hash space holds). Documents probe the sketches with their signatures; (document, item) pairs with enough hits are
candidates, and no pair that reaches the threshold is lost. Candidates are verified by exact containment of shingles, compared as text.
(Banded signatures of a fixed length for whole documents would lose pairs: 30 shingles of 5,000 have a Jaccard similarity of 0.006.)

Words are maximal runs of letters and digits, in lower case; a shingle is five words. Items with fewer words have no
shingles and are never found; null and empty texts hold nothing. Rows with equal doc_id count as parts of one document, rows with
equal item_id as parts of one item. An item without an id is one by its text and is reported with a null item_id.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WORDS = 5
THRESHOLD = 0.8
BROADCAST_ROWS = 500_000
NO_ID = -(1 << 63)  # stands for a null doc_id inside


def shingles(text: Column, words: int = WORDS, hashed: bool = True) -> Column:
    """Array of a text's shingles in order, as 64-bit hashes or as text; null if it has fewer words."""
    w = F.regexp_extract_all(F.lower(text), F.lit(r"[\p{L}\p{N}]+"), F.lit(0))
    if hashed:
        one = lambda i, w: F.xxhash64(*[F.get(w, i + k) for k in range(words)])
    else:
        one = lambda i, w: F.concat_ws(" ", *[F.get(w, i + k) for k in range(words)])
    # the words are named once, as the only element of an array, so that they are not found anew for each shingle
    named = F.transform(F.array(w), lambda v: F.when(F.size(v) >= words, F.transform(F.sequence(F.lit(0), F.size(v) - words), lambda i: one(i, v))))
    return F.get(named, 0)


def sketches(items: DataFrame, threshold: float = THRESHOLD, words: int = WORDS) -> DataFrame:
    """item_id, n_item (distinct shingles), needed (hits that a pair above the threshold has at least) and h, a row for each kept MinHash value."""
    sized = items.select("item_id", shingles(F.col("text"), words).alias("hs")).filter("hs is not null")
    sized = sized.groupBy("item_id").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("hs")))).alias("hs"))
    n = F.size("hs")
    most = F.pow(F.lit(2.0), F.floor(F.log2(n.cast("double"))) + 1) - 1  # the largest size of the item's class
    k = F.least(n, (F.floor((1 - threshold) * most + 1e-9) + 1).cast("int"))
    sized = sized.select("item_id", n.alias("n_item"), "hs", k.alias("k"))
    missable = F.floor((1 - threshold) * F.col("n_item") + 1e-9).cast("int")
    return sized.select("item_id", "n_item", (F.col("k") - missable).alias("needed"), F.explode(F.slice("hs", 1, F.col("k"))).alias("h"))


def leaks(docs: DataFrame, items: DataFrame, threshold: float = THRESHOLD, words: int = WORDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, item_id, n_item, n_shared, containment of every pair with a containment of at least the threshold."""
    texts = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID)).alias("doc_id"), F.col(text_col).alias("rw_text"))
    kind = dict(items.dtypes)["item_id"]
    # inside, an item is named by its id, or by its text if it has none
    own_name = F.concat(F.lit("t"), F.sha2(F.coalesce("text", F.lit("")), 256))
    items = items.select(F.coalesce(F.concat(F.lit("i"), F.col("item_id").cast("string")), own_name).alias("item_id"), "text")
    sketch = sketches(items, threshold, words)
    cut = sketch.agg(F.max("h")).first()[0]  # one number
    if cut is None:
        cut = NO_ID
    own = items.select("item_id", F.explode(F.array_distinct(shingles(F.col("text"), words, hashed=False))).alias("shingle")).distinct()
    small = own.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS  # benchmarks are small; a huge one is joined by a shuffle
    held = F.broadcast if small else (lambda df: df)
    probes = texts.select("doc_id", F.explode(F.array_distinct(F.filter(shingles(F.col("rw_text"), words), lambda h: h <= cut))).alias("h"))
    candidates = probes.join(held(sketch), "h").groupBy("doc_id", "item_id", "n_item", "needed").agg(F.count_distinct("h").alias("hits")).filter("hits >= needed").select("doc_id", "item_id", "n_item")
    suspects = candidates.groupBy("doc_id").agg(F.map_from_entries(F.collect_set(F.struct("item_id", "n_item"))).alias("rw_items"))  # a document has at most all items
    shared = texts.join(suspects, "doc_id").select("doc_id", "rw_items", F.explode(F.array_distinct(shingles(F.col("rw_text"), words, hashed=False))).alias("shingle"))
    shared = shared.join(held(own), "shingle").filter(F.map_contains_key("rw_items", F.col("item_id")))
    counted = shared.select("doc_id", "item_id", F.col("rw_items")[F.col("item_id")].alias("n_item"), "shingle").groupBy("doc_id", "item_id", "n_item").agg(F.count_distinct("shingle").alias("n_shared"))
    return counted.filter(F.col("n_shared") >= threshold * F.col("n_item") - 1e-9).select(F.nullif("doc_id", F.lit(NO_ID)).alias("doc_id"), F.when(F.col("item_id").startswith("i"), F.expr("substring(item_id, 2)")).cast(kind).alias("item_id"), F.col("n_item").cast("long").alias("n_item"), "n_shared", (F.col("n_shared") / F.col("n_item")).alias("containment"))
