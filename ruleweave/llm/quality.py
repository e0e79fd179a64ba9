"""Quality classifier (op5): random-indexing word vectors, pooled by document, then a two-layer network with calibrated probabilities.

Tokens are maximal runs of letters, of digits or of other signs; next to each stands its shape (kind, case, length) and, where
it applies, a mark that it repeats what stood before. Tokens are hashed to a fixed number of buckets. Each bucket has
a sparse random index vector of a few +1 and -1; its word vector is its own index vector plus the direction of the
sum of its neighbours' index vectors over the whole corpus. The sums are integers, so their order does not matter,
and their size is fixed by two parameters (buckets, dimensions), whatever the corpus.

A document is the mean vector of its tokens, and that of its shapes and marks. A two-layer numpy network, fitted on at most
`max_labelled` labelled rows (those with the smallest hash of their id), scores it; a temperature, fitted on rows that
training left out, calibrates the probability.

Null texts count as empty; empty texts have zero vectors and still get a score. Rows that repeat an id are scored each; a label stands for the text
of its id with the smallest hash. Labels that are null are not used; without both labels
every score is the share of label 1 (0.5 without any).
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ruleweave.llm.common import lean, small_batches
from ruleweave.llm.textnum import U, Words, encoded, mix

BUCKETS, DIMENSIONS, NONZERO = 1 << 14, 64, 4
MAX_LABELLED = 12_000
SHAPES = 1 << 10
HELD_OUT = 2
BLOCK_ROWS = 512
BLOCK_CELLS = BLOCK_ROWS * DIMENSIONS
FAN_IN, FAN_LEVELS = 128, 2
CHUNK_BYTES = 4 << 20
_KIND = np.full(256, 3, np.uint8)
_KIND[[9, 10, 11, 12, 13, 32]] = 0
_KIND[[*range(65, 91), *range(97, 123), *range(128, 256)]] = 1
_KIND[48:58] = 2
_UPPER = np.zeros(256, np.int64)
_UPPER[65:91] = 1


class Tokens(Words):
    """Runs of letters, digits and other signs of a list of texts, with buckets for each run and for its shape and marks."""

    def __init__(self, texts: list[bytes]):
        self.buf = np.frombuffer(b"\n".join(texts) + b"\n", np.uint8)
        offsets = np.concatenate([[0], np.cumsum(np.fromiter((len(t) + 1 for t in texts), np.int64, len(texts)))])
        kind = _KIND[self.buf]
        turn = np.flatnonzero(kind[1:] != kind[:-1]) + 1
        starts = np.concatenate([[0], turn]).astype(np.int64)
        ends = np.concatenate([turn, [len(kind)]]).astype(np.int64)
        solid = kind[starts] > 0
        self.starts, self.ends = starts[solid], ends[solid]
        self.first = np.searchsorted(self.starts, offsets)
        self.counts = np.diff(self.first)
        self.text_of = np.repeat(np.arange(len(texts)), self.counts)
        upper = np.concatenate([[0], np.cumsum(_UPPER[self.buf])])
        n_upper, size = upper[self.ends] - upper[self.starts], self.ends - self.starts
        case = (n_upper > 0).astype(np.int64) + (n_upper > 1) + ((n_upper > 1) & (n_upper == size))
        h = self.hashes()
        self.bucket = (h % U(BUCKETS)).astype(np.int64)
        shape = (kind[self.starts].astype(np.int64) * 4 + case) * 16 + np.minimum(15, size)
        again = np.zeros(len(h), np.int64)
        same = self.text_of[1:] == self.text_of[:-1]
        again[1:] += same & (h[1:] == h[:-1])
        at, three = self.windows(h, 3)
        seen = mix(three + self.text_of[at].astype(U) * U(0xA24BAED4963EE407))
        order = np.argsort(seen, kind="stable")
        repeated = np.zeros(len(seen), bool)
        repeated[order[1:]] = seen[order[1:]] == seen[order[:-1]]
        again[at[repeated]] += 2
        self.shape = shape * 4 + again  # below SHAPES


def shape_buckets() -> np.ndarray:
    """The bucket of each shape."""
    return (mix(np.arange(SHAPES, dtype=U) + U(1 << 32)) % U(BUCKETS)).astype(np.int64)


def dense_index_vectors() -> np.ndarray:
    places, signs = index_vectors()
    out = np.zeros((BUCKETS, DIMENSIONS))
    np.put_along_axis(out, places, signs, axis=1)
    return out


def index_vectors(buckets: int = BUCKETS, dimensions: int = DIMENSIONS, nonzero: int = NONZERO) -> tuple[np.ndarray, np.ndarray]:
    """Places and signs of each bucket's nonzero components."""
    h = mix(np.arange(buckets * nonzero, dtype=U).reshape(buckets, nonzero) + U(0x51ED270B))
    part = dimensions // nonzero
    return (h % U(part)).astype(np.int64) + np.arange(nonzero) * part, np.where(h >> U(63), 1, -1)


def _texts(column: pa.Array):
    """The column's texts as UTF-8, some megabytes at a time."""
    for at in range(0, len(column), 512):
        texts = encoded(column.slice(at, 512).to_pylist())
        for a, b in _chunks(texts):
            yield texts[a:b]


def _chunks(texts: list[bytes]):
    at = 0
    while at < len(texts):
        end, size = at, 0
        while end < len(texts) and (end == at or size + len(texts[end]) <= CHUNK_BYTES):
            size += len(texts[end])
            end += 1
        yield at, end
        at = end


def _packed(sums: np.ndarray) -> bytes:
    """Whole numbers, the sign as lowest bit, byte plane by byte plane, compressed: the upper planes of small numbers are empty."""
    sums = sums.astype("<i8")
    planes = np.ascontiguousarray((sums << 1 ^ sums >> 63).view(np.uint8).reshape(-1, 8).T)
    return pa.compress(planes.tobytes(), codec="zstd", asbytes=True)


def _unpacked(raw: bytes) -> np.ndarray:
    planes = np.frombuffer(pa.decompress(raw, 8 * BLOCK_CELLS, codec="zstd", asbytes=True), np.uint8)
    folded = np.ascontiguousarray(planes.reshape(8, -1).T).view("<u8").ravel()
    return (folded >> U(1)).astype(np.int64) ^ -(folded & U(1)).astype(np.int64)


def context_sums(docs: DataFrame, text_col: str = "text", reach: int = 2) -> np.ndarray:
    """For each bucket, the sum of the index vectors of its neighbours over all texts (buckets x dimensions integers, a fixed size)."""
    small_batches(docs.sparkSession)
    cells = BUCKETS * DIMENSIONS

    def count(batches):
        places, signs = index_vectors()
        total, shapes = np.zeros(cells), np.zeros(SHAPES * SHAPES)
        for batch in batches:
            for texts in _texts(batch[0]):
                tokens = Tokens(texts)
                for gap in range(1, reach + 1):
                    same = tokens.text_of[gap:] == tokens.text_of[:-gap]
                    left, right = tokens.bucket[:-gap][same], tokens.bucket[gap:][same]
                    for here, there in ((left, right), (right, left)):
                        cell = (here[:, None] * DIMENSIONS + places[there]).ravel()
                        total += np.bincount(cell, signs[there].ravel(), cells)  # whole numbers, so exact
                    shapes += np.bincount(tokens.shape[:-gap][same] * SHAPES + tokens.shape[gap:][same], minlength=SHAPES * SHAPES)
        beside = shapes.reshape(SHAPES, SHAPES)
        np.add.at(total.reshape(BUCKETS, DIMENSIONS), shape_buckets(), (beside + beside.T) @ dense_index_vectors()[shape_buckets()])
        blocks = total.astype("<i8").reshape(-1, BLOCK_CELLS)
        task = [TaskContext.get().partitionId()] * len(blocks)
        yield pa.RecordBatch.from_arrays([pa.array(range(len(blocks)), pa.int32()), pa.array(task, pa.int64()), pa.array([_packed(x) for x in blocks], pa.binary())], ["block", "part", "sums"])

    def add(key: tuple[pa.Scalar, ...], parts: pa.Table) -> pa.Table:
        total = np.zeros(BLOCK_CELLS, np.int64)
        for raw in parts["sums"]:
            total += _unpacked(raw.as_py())
        return pa.table({"block": pa.array([key[0].as_py()], pa.int32()), "part": pa.array([key[1].as_py()], pa.int64()), "sums": pa.array([_packed(total)], pa.binary())})

    schema = "block int, part long, sums binary"
    rows = docs.select(F.col(text_col).alias("rw_text")).mapInArrow(lean(count), schema)
    for _ in range(FAN_LEVELS):  # a tree: a group adds up at most FAN_IN rows of 256 KB
        rows = rows.withColumn("part", F.floor(F.col("part") / FAN_IN)).groupBy("block", "part").applyInArrow(add, schema)
    rows = rows.collect()  # buckets x dimensions numbers, once for every FAN_IN ** FAN_LEVELS tasks
    out = np.zeros((BUCKETS // BLOCK_ROWS, BLOCK_CELLS), np.int64)
    for r in rows:
        out[r.block] += _unpacked(bytes(r.sums))
    return out.reshape(BUCKETS, DIMENSIONS)


def word_vectors(sums: np.ndarray) -> np.ndarray:
    own = dense_index_vectors() / np.sqrt(NONZERO)
    length = np.sqrt((sums.astype(float) ** 2).sum(axis=1, keepdims=True))
    return (own + sums / np.maximum(1, length)).astype(np.float32)


def pooled(texts: list[bytes], vectors: np.ndarray) -> np.ndarray:
    """Mean vector of the tokens, of the shapes and marks, and the logarithm of the number of tokens, for each text."""
    out = np.zeros((len(texts), 2 * DIMENSIONS + 1), np.float32)
    for a, b in _chunks(texts):
        tokens = Tokens(texts[a:b])
        some = np.flatnonzero(tokens.counts)
        out[a:b, -1] = np.log1p(tokens.counts)
        if not len(some):
            continue
        n = tokens.counts[some][:, None]
        step, sums = 1 << 16, np.zeros((b - a, DIMENSIONS))
        for k in range(0, len(tokens.bucket), step):  # a bounded number of rows of word vectors at once
            here = tokens.text_of[k : k + step]
            edge = np.flatnonzero(np.diff(here, prepend=-1))
            sums[here[edge]] += np.add.reduceat(vectors[tokens.bucket[k : k + step]], edge, axis=0)
        out[a + some, :DIMENSIONS] = sums[some] / n
        for k in range(0, b - a, 256):  # there are few shapes, so they are counted first
            lo, hi = tokens.first[k], tokens.first[min(k + 256, b - a)]
            counts = np.bincount((tokens.text_of[lo:hi] - k) * SHAPES + tokens.shape[lo:hi], minlength=min(256, b - a - k) * SHAPES).reshape(-1, SHAPES)
            out[a + k : a + k + len(counts), DIMENSIONS:-1] = (counts @ vectors[shape_buckets()].astype(float)) / np.maximum(1, tokens.counts[k : k + len(counts)])[:, None]
    return out


@dataclass
class Network:
    """Two layers over standardised inputs; a temperature divides the logit."""

    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float = 1.0

    def logit(self, x: np.ndarray) -> np.ndarray:
        return np.maximum(0, ((x - self.mean) / self.scale) @ self.w1 + self.b1) @ self.w2 + self.b2

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logit(x) / self.temperature, -30, 30)))


def fit(x: np.ndarray, y: np.ndarray, hidden: int = 32, epochs: int = 60, rate: float = 3e-3, decay: float = 1e-3, seed: int = 5) -> Network:
    """Adam on the cross-entropy of four fifths of the rows, temperature on the last fifth."""
    x, y = x.astype(float), y.astype(float)
    rng = np.random.default_rng(seed)
    net = Network(x.mean(axis=0) if len(x) else np.zeros(x.shape[1]), x.std(axis=0) + 1e-3 if len(x) else np.ones(x.shape[1]), np.zeros((x.shape[1], hidden)), np.zeros(hidden), np.zeros(hidden), 0.0)
    if len(set(y.tolist())) < 2:
        share = min(max(y.mean() if len(y) else 0.5, 1e-6), 1 - 1e-6)
        net.b2 = float(np.log(share / (1 - share)))
        return net
    order = rng.permutation(len(x))
    kept, out = order[: max(1, len(x) * 4 // 5)], order[max(1, len(x) * 4 // 5) :]
    z = (x - net.mean) / net.scale
    weights = [rng.standard_normal((x.shape[1], hidden)) * np.sqrt(2 / x.shape[1]), np.zeros(hidden), rng.standard_normal(hidden) / np.sqrt(hidden), np.zeros(1)]
    m, v, t = [np.zeros_like(w) for w in weights], [np.zeros_like(w) for w in weights], 0
    for _ in range(epochs):
        for batch in np.array_split(rng.permutation(kept), max(1, len(kept) // 128)):
            a = z[batch] @ weights[0] + weights[1]
            h = np.maximum(0, a)
            p = 1 / (1 + np.exp(-np.clip(h @ weights[2] + weights[3], -30, 30)))
            d = (p - y[batch]) / len(batch)
            back = np.outer(d, weights[2]) * (a > 0)
            t += 1
            for k, g in enumerate((z[batch].T @ back + decay * weights[0], back.sum(axis=0), h.T @ d + decay * weights[2], np.array([d.sum()]))):
                m[k] = 0.9 * m[k] + 0.1 * g
                v[k] = 0.999 * v[k] + 0.001 * g * g
                weights[k] -= rate * (m[k] / (1 - 0.9**t)) / (np.sqrt(v[k] / (1 - 0.999**t)) + 1e-8)
    net.w1, net.b1, net.w2, net.b2 = weights[0], weights[1], weights[2], float(weights[3][0])
    if len(out):
        logit, truth = net.logit(x[out]), y[out]
        losses = [(np.logaddexp(0, np.where(truth > 0, -logit, logit) / s).mean(), s) for s in np.geomspace(0.25, 8, 61)]
        net.temperature = float(min(losses)[1])
    return net


@dataclass
class Model:
    vectors: np.ndarray
    network: Network

    def score(self, texts: list[bytes]) -> np.ndarray:
        return self.network.score(pooled(texts, self.vectors))


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("long").cast("string")), F.lit(4)) == HELD_OUT, F.lit(False))


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", max_labelled: int = MAX_LABELLED) -> Model:
    """Word vectors from all texts, the network from at most max_labelled labelled rows that are not held out."""
    spark = docs.sparkSession
    vectors = word_vectors(context_sums(docs, text_col))
    shared = spark.sparkContext.broadcast(vectors)
    usable = labels.select(F.col("doc_id").cast("long").alias("id"), F.col("quality").cast("int").alias("y")).filter("id is not null and y in (0, 1)").filter(~held_out(F.col("id")))
    chosen = usable.dropDuplicates(["id"]).orderBy(F.xxhash64("id"), "id").limit(max_labelled)
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("rw_text")).join(F.broadcast(chosen), "id")
    rows = rows.groupBy("id", "y").agg(F.min_by("rw_text", F.xxhash64("rw_text")).alias("rw_text"))  # one text an id: at most max_labelled rows

    def features(batches):
        for batch in batches:
            x = pooled(encoded(batch["rw_text"].to_pylist()), shared.value)
            yield pa.RecordBatch.from_arrays([batch["id"], batch["y"], pa.array([r.tobytes() for r in x], pa.binary())], ["id", "y", "x"])

    got = sorted(rows.mapInArrow(lean(features), "id long, y int, x binary").collect(), key=lambda r: (r.id, bytes(r.x)))
    x = np.frombuffer(b"".join(bytes(r.x) for r in got), np.float32).reshape(len(got), 2 * DIMENSIONS + 1)
    return Model(vectors, fit(x, np.array([r.y for r in got], float)))


def scores(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out and score of every row."""
    small_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)  # buckets x dimensions numbers and a small network

    def run(batches):
        for batch in batches:
            s = np.concatenate([shared.value.score(texts) for texts in _texts(batch["rw_text"])] or [np.empty(0)])
            yield pa.RecordBatch.from_arrays([batch["doc_id"], batch["held_out"], pa.array(s, pa.float64())], ["doc_id", "held_out", "score"])

    narrow = docs.select(F.col(id_col).cast("long").alias("doc_id"), held_out(F.col(id_col)).alias("held_out"), F.col(text_col).alias("rw_text"))
    return narrow.mapInArrow(lean(run), "doc_id long, held_out boolean, score double")


def scored(docs: DataFrame, model: Model, text_col: str = "text", out: str = "rw_score") -> DataFrame:
    """docs with a score column; all other columns stay as they are."""
    small_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.arrow_udf("double")
    def score(texts: pa.Array) -> pa.Array:
        return pa.array(np.concatenate([shared.value.score(part) for part in _texts(texts)] or [np.empty(0)]), pa.float64())

    return docs.withColumn(out, score(F.coalesce(F.col(text_col), F.lit(""))))
