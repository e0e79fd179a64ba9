"""Near-duplicate classes by order MinHash (op10).

A text is its sequence of shingles (five words), each labelled with how often it occurred before, so that every
label stands once. A sketch keeps, for one hash function, the few labels with the smallest hashes, in the order
in which they stand in the text; texts with a small edit distance often agree in a sketch, reordered ones do not.
Texts that agree in one of many sketches are candidates. A banded alignment of the two label sequences verifies
them: with L labels aligned in order, the similarity is L / (n1 + n2 - L). Labels stand once, so the longest common
subsequence is a longest increasing run of positions; labels further apart than the band allows cannot be part of
an alignment that reaches the threshold.

Short texts (4 to 8 labels) have besides the keys of all their labels and of all but one, so that no pair with 7 labels or fewer on one
side is left to chance.

Equal texts are one node. In a bucket (texts with a common sketch) every text is compared with the one that shares most sketches, a
star; links join components. A bucket that still holds several components is decided in full, block by block, by products of
label matrices, and gives only the links that join components. No bucket is cut, none is expanded into its pairs, and no group of
copies is expanded at all.

Texts with fewer than five words have one label, all their words. Null texts count as empty; texts without words are copies of each
other. A node is a text, numbered by a hash of its words, never a doc_id, so rows that share a doc_id or have none are documents of
their own. The class id is the smallest doc_id of the class that is not null; a class of null doc_ids only has a negative number of its own.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ruleweave.llm.common import checkpointed, lean, small_batches, staged
from ruleweave.llm.textnum import U, Words, encoded, mix
from ruleweave.operators.state import discard

WORDS, THRESHOLD = 5, 0.8
SKETCHES, KEPT = 24, 4
SHORT = 8  # labels; texts with fewer reach the threshold only with texts that have one label more
BLOCK, COLUMNS = 256, 4096
SALTS = 8
LOCAL_EDGES = 1_000_000  # 16 MB, and some 100 MB of a task while they are joined
NO_ID = -(1 << 63)
_SEEDS = mix(np.arange(1, 4096, dtype=U)) | U(1)


def labels(words: Words, hashes: np.ndarray, k: int, n: int = WORDS) -> np.ndarray:
    """The labelled shingles of text k in order."""
    w = hashes[words.first[k] : words.first[k + 1]]
    size = min(n, len(w))
    if not size:
        return np.empty(0, U)
    h = w[: len(w) - size + 1].copy()
    for j in range(1, size):
        h *= U(0x9E3779B97F4A7C15)
        h += w[j : len(w) - size + 1 + j]
    h = mix(h + U(size))
    order = np.argsort(h, kind="stable")
    s = h[order]
    at = np.arange(len(s))
    first = np.zeros(len(s), np.int64)
    new = np.flatnonzero(s[1:] != s[:-1]) + 1
    first[new] = new
    times = np.empty(len(s), U)
    times[order] = (at - np.maximum.accumulate(first)).astype(U)
    return mix(h + times * U(0xA24BAED4963EE407))


def sketch(marks: np.ndarray, sketches: int = SKETCHES, kept: int = KEPT) -> np.ndarray:
    """One 64-bit value a hash function: its `kept` smallest labels in text order."""
    if not len(marks):
        return np.zeros(sketches, U)
    kept = min(kept, len(marks))
    out = np.empty(sketches, U)
    step = max(1, (1 << 18) // len(marks))
    for a in range(0, sketches, step):
        y = marks * _SEEDS[a : min(a + step, sketches), None]
        at = np.argpartition(y, kept - 1, axis=1)[:, :kept] if kept < len(marks) else np.broadcast_to(np.arange(kept), y.shape).copy()
        at.sort(axis=1)
        value = np.zeros(len(y), U)
        for j in range(kept):
            value = mix(value * U(0x9E3779B97F4A7C15) + marks[at[:, j]])
        out[a : a + len(y)] = value
    return out


def short_keys(marks: np.ndarray) -> np.ndarray:
    """Keys of a short text: all its labels, and all but one. Of texts at 0.8 with up to 7 labels in one, one text has all the labels but one of the other."""
    if not 4 <= len(marks) <= SHORT:
        return np.empty(0, U)
    return np.concatenate([marks.sum(dtype=U)[None], marks.sum(dtype=U) - marks])


def aligned(a: np.ndarray, b: np.ndarray, threshold: float = THRESHOLD) -> float:
    """Similarity of two label sequences by banded alignment; 0 if it cannot reach the threshold."""
    n, m = len(a), len(b)
    if not n or not m:
        return float(n == m)
    least = threshold * (n + m) / (1 + threshold)  # labels that must be aligned
    if min(n, m) < least - 1e-9:
        return 0.0
    _, i, j = np.intersect1d(a, b, assume_unique=True, return_indices=True)
    band = (n + m) * (1 - threshold) / (1 + threshold) + 1e-9
    near = np.abs(i - j) <= band
    i, j = i[near], j[near]
    if len(i) < least - 1e-9:
        return 0.0
    j = j[np.argsort(i)]
    if (j[1:] > j[:-1]).all():
        common = len(j)
    else:
        tails: list[int] = []
        for x in j.tolist():
            at = bisect_left(tails, x)
            tails[at : at + 1] = [x]
        common = len(tails)
    return common / (n + m - common)


def sketched(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", sketches: int = SKETCHES, kept: int = KEPT) -> DataFrame:
    """id, exact (a hash of the text), copy (a hash of the text's words), n (labels) and sketches of every row."""

    def run(batches):
        for batch in batches:
            raw = encoded(batch["rw_text"].to_pylist())
            at = 0
            while at < len(raw):  # about a megabyte at a time
                end, size = at, 0
                while end < len(raw) and (end == at or size + len(raw[end]) <= 1 << 20):
                    size += len(raw[end])
                    end += 1
                part = raw[at:end]
                words = Words(part)
                h, h2 = words.hashes(), words.hashes(seed=1)
                rows = []
                for k in range(len(part)):
                    marks = labels(words, h, k)
                    w = h2[words.first[k] : words.first[k + 1]]
                    whole = int((mix(w + np.arange(len(w), dtype=U) * U(0xA24BAED4963EE407))).sum(dtype=U)) if len(w) else 0
                    s = np.concatenate([sketch(marks, sketches, kept), short_keys(marks)])
                    first = int(mix(np.array([len(w)], U) + marks.sum(dtype=U))[0]) if len(marks) else 0
                    rows.append((f"{first:016x}{whole:016x}", len(marks), s.view(np.int64)))
                yield pa.RecordBatch.from_arrays([batch["id"].slice(at, end - at), batch["exact"].slice(at, end - at), pa.array([r[0] for r in rows]), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.list_(pa.int64()))], ["id", "exact", "copy", "n", "sketches"])
                at = end

    small_batches(docs.sparkSession)
    narrow = docs.select(*row_key(docs, id_col, text_col), F.col(text_col).alias("rw_text"))
    return narrow.mapInArrow(lean(run), "id long, exact long, copy string, n int, sketches array<long>")


def row_key(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> list[Column]:
    """id (of a null doc_id NO_ID) and exact: a row up to repetition."""
    return [F.coalesce(docs[id_col].cast("long"), F.lit(NO_ID)).alias("id"), F.xxhash64(F.coalesce(docs[text_col], F.lit(""))).alias("exact")]


def verified(pairs: DataFrame, texts: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """The pairs (a, b) whose texts' alignment reaches the threshold."""

    def run(batches):
        last, marks_a = None, None
        for batch in batches:
            out_a, out_b = [], []
            for a, b, ta, tb in zip(*(batch[c].to_pylist() for c in ("a", "b", "text_a", "text_b")), strict=True):
                pair = encoded([tb] if a == last else [tb, ta])
                words = Words(pair)
                h = words.hashes()
                if a != last:
                    last, marks_a = a, labels(words, h, 1)
                if aligned(marks_a, labels(words, h, 0), threshold) >= threshold - 1e-9:
                    out_a.append(a)
                    out_b.append(b)
            yield pa.RecordBatch.from_arrays([pa.array(out_a, pa.int64()), pa.array(out_b, pa.int64())], ["a", "b"])

    held = texts.select(F.col("id").alias("a"), F.col("text").alias("text_a"))
    other = texts.select(F.col("id").alias("b"), F.col("text").alias("text_b"))
    return pairs.select("a", "b").join(other, "b").join(held, "a").mapInArrow(lean(run), "a long, b long")


def components(edges: DataFrame, local: int = LOCAL_EDGES) -> DataFrame:
    """id, component (its smallest id) of every node of an undirected graph (a, b): up to `local` edges in one task, more by large-star and small-star steps."""
    spark_edges = checkpointed(edges.filter("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    if spark_edges.count() <= local:  # a step has six exchanges, whose files are many however few the edges are
        return spark_edges.coalesce(1).mapInArrow(lean(_smallest), "id long, component long")
    seal = None
    while True:
        both = spark_edges.unionByName(spark_edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select("u", F.col("m").alias("v")))
        before, spark_edges = spark_edges, checkpointed(small.filter("u <> v").distinct())
        discard(before)
        now = spark_edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == seal:
            break
        seal = now
    heads = spark_edges.groupBy("u").agg(F.min("v").alias("component"))
    return heads.select(F.col("u").alias("id"), "component").unionByName(heads.select("component").distinct().select(F.col("component").alias("id"), "component"))


def _smallest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The nodes of all edges (u, v) with the smallest of their component: roots are hung below smaller neighbours, which leaves at most half of them a turn."""
    ends = [(batch["u"].to_numpy(), batch["v"].to_numpy()) for batch in batches]
    ids, at = np.unique(np.concatenate([np.empty(0, np.int64), *(x for pair in ends for x in pair)]), return_inverse=True)
    sizes = np.repeat([len(u) for u, _ in ends], 2)
    sides = np.split(at, np.cumsum(sizes)[:-1]) if ends else [at, at]
    u, v = np.concatenate(sides[::2]), np.concatenate(sides[1::2])
    root = np.arange(len(ids))
    while (root[u] != root[v]).any():
        a, b = root[u], root[v]
        np.minimum.at(root, np.maximum(a, b), np.minimum(a, b))
        while (root[root] != root).any():
            root = root[root]
    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(ids[root])], ["id", "component"])


def links(nodes: DataFrame, texts: DataFrame, threshold: float = THRESHOLD, block: int = BLOCK, repeated: bool = True) -> DataFrame:
    """Verified links (a, b) between different texts that connect every class: nodes has id, doc, exact, n, sketches; texts has doc, exact, text, once or more for each node."""
    keyed = nodes.select("id", "n", F.posexplode("sketches").alias("at", "s")).select("id", "n", F.xxhash64(F.least("at", F.lit(SKETCHES)), "s").alias("key"))  # short keys have no place
    shared = keyed.groupBy("key").agg(F.count("*").alias("size")).filter("size > 1")
    members = checkpointed(keyed.join(shared, "key"))
    wanted = nodes.select("id", "doc", "exact").join(members.select("id").distinct(), "id", "left_semi")
    texts = texts.join(wanted, ["doc", "exact"]).select("id", "text")
    texts = staged(texts.dropDuplicates(["id"]) if repeated else texts)  # those that stand in a bucket at all
    # the centre of a star is the text that shares most sketches: what others were copied from, and the same in most of its buckets
    wide = members.join(members.groupBy("id").agg(F.sum("size").alias("weight")), "id")
    centres = wide.groupBy("key").agg(F.max(F.struct("weight", F.bitwise_not("id").alias("rest"))).alias("top")).select("key", F.bitwise_not("top.rest").alias("a"))  # of equal weights the smallest id
    star = members.join(centres, "key").filter("id <> a").select(F.least("a", "id").alias("a"), F.greatest("a", "id").alias("b")).distinct()
    stars = checkpointed(verified(star, texts, threshold))
    parts = checkpointed(components(stars))
    # buckets of three or more that still hold several components
    apart = members.filter("size > 2").join(parts, "id", "left").withColumn("component", F.coalesce("component", "id"))
    mixed = apart.groupBy("key").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).filter("lo <> hi").select("key")
    apart = checkpointed(apart.join(mixed, "key").select("key", "id", "component", "size"))
    return stars.unionByName(solved(apart, texts, threshold, block))


def solved(apart: DataFrame, texts: DataFrame, threshold: float = THRESHOLD, block: int = BLOCK) -> DataFrame:
    """Links across components inside buckets (key, id, component, size): every pair of a bucket is decided, none is emitted unless it joins.

    A bucket falls into blocks of about `block` texts, and a task has one pair of blocks. The number of common labels of all
    its pairs comes from products of label matrices; pairs that have enough of them, most first, are aligned unless they are
    joined already.
    """

    def mark(batches):
        for batch in batches:
            raw = encoded(batch["text"].to_pylist())
            out = []
            for text in raw:
                words = Words([text])
                out.append(labels(words, words.hashes(), 0).tobytes())
            yield pa.RecordBatch.from_arrays([batch["id"], pa.array(out, pa.binary())], ["id", "labels"])

    def solve(key: tuple[pa.Scalar, ...], group: pa.Table) -> pa.Table:
        left, right = key[1].as_py(), key[2].as_py()
        ids, component, side = (group[c].to_pylist() for c in ("id", "component", "own"))
        marks = [np.frombuffer(x, U) for x in group["labels"].to_pylist()]
        pairs = joining(ids, component, marks, None if left == right else np.array(side) == left, threshold)
        return pa.table({"a": pa.array([a for a, _ in pairs], pa.int64()), "b": pa.array([b for _, b in pairs], pa.int64())})

    wanted = texts.join(apart.select("id").distinct(), "id", "left_semi").select("id", "text").mapInArrow(lean(mark), "id long, labels binary")
    n_blocks = F.ceil(F.col("size") / block)
    own = F.pmod(F.xxhash64("id"), n_blocks)
    pairs_of = F.transform(F.sequence(F.lit(0).cast("long"), n_blocks - 1), lambda x: F.struct(F.least(x, F.col("own")).alias("i"), F.greatest(x, F.col("own")).alias("j")))
    spread = apart.withColumn("own", own).withColumn("pair", F.explode(pairs_of)).select("key", "id", "component", "own", F.col("pair.i").alias("i"), F.col("pair.j").alias("j"))
    return spread.join(wanted, "id").groupBy("key", "i", "j").applyInArrow(solve, "a long, b long")


def joining(ids: list[int], component: list[int], marks: list[np.ndarray], left: np.ndarray | None, threshold: float = THRESHOLD) -> list[tuple[int, int]]:
    """Pairs of texts of different components that reach the threshold, as many as it takes to join what they join. left: the texts of the left block; pairs inside a block are another task's."""
    sizes = np.array([len(m) for m in marks])
    _, columns = np.unique(np.concatenate(marks) if marks else np.empty(0, U), return_inverse=True)
    rows = np.repeat(np.arange(len(marks)), sizes)
    times = np.bincount(columns)
    often = times[columns] > 1
    rows, columns = rows[often], columns[often]
    order = np.argsort(columns, kind="stable")
    rows, columns = rows[order], columns[order]
    common = np.zeros((len(marks), len(marks)), np.float32)
    at = 0
    while at < len(columns):
        end = int(np.searchsorted(columns, columns[at] + COLUMNS))
        part = np.zeros((len(marks), COLUMNS), np.float32)
        part[rows[at:end], columns[at:end] - columns[at]] = 1
        common += part @ part.T
        at = end
    enough = np.triu(common >= threshold * (sizes[:, None] + sizes) / (1 + threshold) - 1e-6, 1)
    kinds = np.array(component)
    enough &= kinds[:, None] != kinds
    if left is not None:
        enough &= left[:, None] != left
    i, j = np.nonzero(enough)
    parent = {c: c for c in component}

    def root(c):
        while parent[c] != c:
            parent[c] = parent[parent[c]]
            c = parent[c]
        return c

    out = []
    for k in np.argsort(-common[i, j] / (sizes[i] + sizes[j]), kind="stable"):
        a, b = int(i[k]), int(j[k])
        ra, rb = root(component[a]), root(component[b])
        if ra != rb and aligned(marks[a], marks[b], threshold) >= threshold - 1e-9:
            parent[ra] = rb
            out.append((ids[a], ids[b]))
    return out


def grouped(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """id, exact (see row_key), copy_of, class_id and first of every row. first: the row, repeated or not, that stands for its class."""
    rows = staged(sketched(docs, id_col, text_col))
    least = F.struct((F.col("id") == NO_ID).alias("none"), "id", "exact")
    copies = staged(rows.groupBy("copy").agg(F.min(least).alias("least")).withColumn("node", F.xxhash64("copy")))
    nodes = rows.join(copies.select("least.id", "least.exact", "node"), ["id", "exact"]).select(F.col("node").alias("id"), F.col("id").alias("doc"), "exact", "n", "sketches")
    nodes = staged(nodes.dropDuplicates(["id"]))
    repeated = not rows.groupBy("id", "exact").count().filter("count > 1").isEmpty()
    key = row_key(docs, id_col, text_col)
    texts = docs.select(key[0].alias("doc"), key[1], F.coalesce(text_col, F.lit("")).alias("text"))
    parts = components(links(nodes, texts, threshold, repeated=repeated)).select(F.col("id").alias("node"), "component")
    placed = checkpointed(copies.join(parts, "node", "left").select("copy", "least", F.coalesce("component", "node").alias("component")))
    heads = placed.groupBy("component").agg(F.min("least").alias("head"))
    class_id = F.when(F.col("head.none"), F.col("component").bitwiseOR(F.lit(NO_ID))).otherwise(F.col("head.id")).alias("class_id")
    named = placed.join(heads, "component").select("copy", F.col("least.id").alias("copy_of"), class_id, "head")
    named = named.withColumn("rw_salt", F.explode(F.array(*[F.lit(k) for k in range(SALTS)])))
    salted = rows.select("id", "exact", "copy", F.pmod(F.xxhash64("id", "exact"), F.lit(SALTS)).cast("int").alias("rw_salt"))
    first = (F.col("id") == F.col("head.id")) & (F.col("exact") == F.col("head.exact"))
    return salted.join(named, ["copy", "rw_salt"]).select("id", "exact", "copy_of", "class_id", first.alias("first"))


def classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, copy_of (smallest doc_id with the same words, null if there is none) and class_id (smallest doc_id of the class) of every row."""
    found = grouped(docs, id_col, text_col, threshold)
    return found.select(F.nullif("id", F.lit(NO_ID)).alias("doc_id"), F.nullif("copy_of", F.lit(NO_ID)).alias("copy_of"), "class_id")
