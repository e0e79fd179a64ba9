"""Approximate nearest neighbours by a hash-prefix forest (op2).

A vector has one long hash string (64 bits, signs of random projections) in each of many trees; a tree is the sorted
array of its strings, its inner nodes are prefixes. A query descends each tree to its longest prefix match, a
stretch of the array, and then all trees ascend together, one bit at a time: stretches grow and bring more
candidates. The ascent ends where the k-th best score found so far, s, leaves little chance of a better one unseen: a vector with
a score of s or more shares x bits of a tree with probability p(s)^x, and misses all trees with (1 - p(s)^x)^trees <= miss.
Easy queries stop far down, hard ones climb, to the root (all vectors) if need be. So recall is set by `miss`, at any size.

Vectors are dealt to shards by a hash of their id, queries to blocks; a task has one shard and one block, builds the shard's forest and answers
the block's queries, and the answers of all shards are merged. What a task holds is bounded by the two sizes, whatever the table. Equal vectors are one entry with its smallest ids (k + 1 of them, all that can be in an answer). Nearness is the inner product
in double precision. If lengths differ, an added coordinate makes them equal for hashing (never for scoring).

Vectors that are null, zero, of another dimension than most, or with null or non-finite components take no part, neither as query nor as
candidate. A vec_id stands for all its different vectors: the score of two ids is the best of theirs, a row that is there twice changes
nothing, an answer names an id once, and a query never finds its own id.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

TREES, MISS, BITS = 32, 0.05, 64
SHARD_ROWS, QUERY_ROWS, QUERY_BLOCK, MOST_TASKS = 100_000, 1024, 1024, 20_000
RESULT = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64())])


def _rows(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    ids = table["vec_id"].to_numpy()
    flat = table["v"].combine_chunks()
    if isinstance(flat, pa.ChunkedArray):
        flat = flat.chunk(0) if flat.num_chunks else pa.array([], pa.list_(pa.float64()))
    return ids, flat.flatten().to_numpy().reshape(len(ids), -1) if len(ids) else np.zeros((0, 0))


class Forest:
    """The forest of one shard: distinct vectors with their smallest ids, and a sorted array of hash strings for each tree."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, k: int, longest: float, trees: int = TREES, seed: int = 7):
        keys = np.ascontiguousarray(vectors).view(np.dtype((np.void, vectors.dtype.itemsize * vectors.shape[1]))).ravel()
        _, first, inverse = np.unique(keys, return_index=True, return_inverse=True)
        order = np.lexsort((ids, inverse))
        again = np.flatnonzero((inverse[order][1:] == inverse[order][:-1]) & (ids[order][1:] == ids[order][:-1])) + 1
        order = np.delete(order, again)  # a row that is there twice
        sizes = np.bincount(inverse[order])
        self.single_vectors = len(np.unique(ids[order])) == len(order)  # no id has several vectors
        starts = np.cumsum(sizes) - sizes
        self.members, self.starts, self.sizes = ids[order], starts, np.minimum(sizes, k + 1)
        self.vectors, self.k, self.trees, self.longest = vectors[first], k, trees, longest
        self.single = self.vectors.astype(np.float32)
        rng = np.random.default_rng(seed)
        self.planes = rng.standard_normal((trees, vectors.shape[1] + 1, BITS))
        rest = np.sqrt(np.maximum(0, 1 - (self.vectors**2).sum(axis=1) / longest**2))
        self.spread = np.column_stack([self.vectors / longest, rest])
        self.hashes, self.order = [], []
        for t in range(trees):
            h = self._strings(self.spread, t)
            at = np.argsort(h, kind="stable")
            self.hashes.append(h[at])
            self.order.append(at)

    def _strings(self, spread: np.ndarray, tree: int) -> np.ndarray:
        bits = np.packbits(spread @ self.planes[tree] > 0, axis=1)
        return bits.view(">u8").ravel().astype(np.uint64)

    def search(self, queries: np.ndarray, miss: float = MISS):
        """For each query, positions of distinct vectors that hold the answer (at least k + 1 ids of them) with their scores."""
        lengths = np.sqrt((queries**2).sum(axis=1))
        spread = np.column_stack([queries / lengths[:, None], np.zeros(len(queries))])
        lo, hi = self._stretches(np.array([self._strings(spread, t) for t in range(self.trees)]))
        for q in range(len(queries)):
            yield self._climb(queries[q], lo[:, :, q], hi[:, :, q], lengths[q], miss)

    def _stretches(self, strings: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where, at each prefix length (first axis, from 0) and in each tree, the query's prefix begins and ends in the sorted array."""
        levels = min(BITS, int(np.log2(len(self.vectors) + 1)) + 12) + 1
        lo = np.zeros((levels, *strings.shape), np.int64)
        hi = np.full((levels, *strings.shape), len(self.vectors), np.int64)
        for x in range(1, levels):
            low = strings >> np.uint64(BITS - x) << np.uint64(BITS - x)
            high = low | np.uint64((1 << (BITS - x)) - 1)
            for t in range(self.trees):
                lo[x, t], hi[x, t] = self.hashes[t].searchsorted(low[t]), self.hashes[t].searchsorted(high[t], "right")
        return lo, hi

    def _climb(self, query, lows, highs, length, miss):
        n = len(self.vectors)
        lo, hi = np.zeros(self.trees, np.int64), np.zeros(self.trees, np.int64)
        seen = np.zeros(n, bool)
        at, scores = np.empty(0, np.int64), np.empty(0, np.float32)
        # while climbing, scores are single precision; the slack covers their rounding, and answers() scores anew in double precision
        single, slack = query.astype(np.float32), 1e-4 * length * self.longest
        enough = np.flatnonzero((highs - lows).sum(axis=1) > self.k)  # longer prefixes alone can't hold an answer
        for x in range(int(enough[-1]) if len(enough) else 0, -1, -1):
            fresh = []
            for t in np.flatnonzero((lows[x] != lo) | (highs[x] != hi)) if x else (0,):
                a, b = lows[x, t], highs[x, t]
                if hi[t] <= lo[t]:
                    fresh.append(self.order[t][a:b])
                else:
                    fresh += [self.order[t][a : lo[t]], self.order[t][hi[t] : b]]
            lo, hi = lows[x], highs[x]
            mark = np.zeros(n, bool)
            for part in fresh:
                mark[part] = True
            mark &= ~seen
            new = np.flatnonzero(mark)
            if len(new):
                seen |= mark
                # a large part of the shard is scored in one sweep over memory rather than row by row
                more = (self.single @ single)[new] if len(new) > n // 8 else self.single[new] @ single
                at, scores = np.concatenate([at, new]), np.concatenate([scores, more])
            best = self._best(scores, at)
            if best is not None:
                stay = scores >= best - slack  # what can still be in the answer
                at, scores = at[stay], scores[stay]
                s = min(1.0, max(-1.0, best / (length * self.longest)))
                p = 1 - np.arccos(s) / np.pi
                if (1 - p**x) ** self.trees <= miss:
                    break
        return at

    def _best(self, scores, at):
        """Score of the (k + 1)-th best different id, None while there are fewer: k of them are not the query's own."""
        if self.sizes[at].sum() < self.k + 1:
            return None
        if not self.single_vectors:
            order = np.argsort(-scores, kind="stable")
            _, first = np.unique(self._ids(at[order]), return_index=True)
            if len(first) < self.k + 1:
                return None
            place = np.partition(first, self.k)[self.k]
            return scores[order[np.searchsorted(np.cumsum(self.sizes[at[order]]), place, "right")]]
        top = np.argpartition(-scores, min(self.k + 1, len(scores)) - 1)[: self.k + 1] if len(scores) > self.k + 1 else np.arange(len(scores))
        top = top[np.argsort(-scores[top], kind="stable")]
        return scores[top[np.searchsorted(np.cumsum(self.sizes[at[top]]), self.k + 1)]]

    def _ids(self, at):
        """The ids of entries, one entry after the other."""
        sizes = self.sizes[at]
        return self.members[np.repeat(self.starts[at] - np.cumsum(sizes) + sizes, sizes) + np.arange(sizes.sum())]

    def answers(self, query_ids: np.ndarray, queries: np.ndarray, miss: float = MISS) -> pa.Table:
        """The k nearest ids of each query in this shard, without its own id; a few more if scores tie."""
        out_q, out_v, out_s = [], [], []
        distinct, inverse = np.unique(queries, axis=0, return_inverse=True)
        inverse = inverse.ravel()
        for d, at in enumerate(self.search(distinct, miss)):
            exact = (self.vectors[at] * distinct[d]).sum(axis=1)  # one order of summation whatever stands beside it
            ids = self._ids(at)
            scores = np.repeat(exact, self.sizes[at])
            best = np.lexsort((ids, -scores))
            ids, scores = ids[best], scores[best]
            if not self.single_vectors:
                once = np.sort(np.unique(ids, return_index=True)[1])
                ids, scores = ids[once], scores[once]
            for q in query_ids[inverse == d]:
                other = ids != q
                mine = ids[other][: self.k]
                out_q.append(np.full(len(mine), q))
                out_v.append(mine)
                out_s.append(scores[other][: self.k])
        join = lambda parts, kind: np.concatenate(parts) if parts else np.empty(0, kind)
        return pa.Table.from_arrays([pa.array(join(out_q, np.int64), pa.int64()), pa.array(join(out_v, np.int64), pa.int64()), pa.array(join(out_s, float), pa.float64())], schema=RESULT)


def usable(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """vec_id and v (array<double>) of the rows that take part: the most frequent dimension, finite, not zero."""
    v = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).cast("array<double>").alias("v")).filter("vec_id is not null and v is not null")
    sound = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0)
    v = v.filter(sound)
    common = v.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").first()
    return v.filter(F.size("v") == (common.d if common else 0))


def neighbours(vectors: DataFrame, queries_at: int = 20, k: int = 20, trees: int = TREES, miss: float = MISS, shard_rows: int = SHARD_ROWS, query_rows: int = QUERY_ROWS) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest found of every row whose vec_id is divisible by queries_at."""
    v = usable(vectors)
    facts = v.agg(F.count("*").alias("n"), F.count_if(F.col("vec_id") % queries_at == 0).alias("asked"), F.max(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x)).alias("most")).first()
    shards = max(1, -(-facts.n // shard_rows))
    longest = float(np.sqrt(facts.most or 1.0)) * (1 + 1e-12)
    asked = v.filter(F.col("vec_id") % queries_at == 0).distinct()
    blocks = max(1, -(-facts.asked // query_rows))
    # every query meets every shard: a shard stands once for each block, a block once for each shard
    every = lambda n, name: F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long"))).alias(name)
    held = v.select("vec_id", "v", F.pmod(F.xxhash64("vec_id"), F.lit(shards)).alias("rw_shard"), every(blocks, "rw_block"))
    asked = asked.select("vec_id", "v", F.pmod(F.xxhash64("vec_id", "v"), F.lit(blocks)).alias("rw_block"), every(shards, "rw_shard"))
    tasks = min(4 * shards * blocks, MOST_TASKS)  # a stated number, so that small pairs of long work are not put into one task
    held, asked = (df.withColumn("rw_pair", F.col("rw_shard") * blocks + F.col("rw_block")).repartition(tasks, "rw_pair") for df in (held, asked))

    def run(key: tuple[pa.Scalar, ...], index: pa.Table, queries: pa.Table) -> pa.Table:
        if not index.num_rows or not queries.num_rows:
            return RESULT.empty_table()
        forest = Forest(*_rows(index), k, longest, trees)
        q_ids, q = _rows(queries)
        return pa.concat_tables([forest.answers(q_ids[a : a + QUERY_BLOCK], q[a : a + QUERY_BLOCK], miss) for a in range(0, len(q_ids), QUERY_BLOCK)])

    found = held.groupBy("rw_pair").cogroup(asked.groupBy("rw_pair")).applyInArrow(run, "query_id long, vec_id long, score double")
    found = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))  # over the vectors of a query
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
