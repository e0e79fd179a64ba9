"""How recursion keeps its state: materialised frames in the shared checkpoint folder, never executor-local ones.

Known rows stand in a few levels (`Levels`), hashed by the same columns into the same number of partitions and sorted, so that a round
compares its candidates with them without moving or sorting any. A level is merged with those after it once these hold as many rows: a row
is rewritten a logarithmic number of times, and the files of superseded frames are deleted.
"""

from __future__ import annotations

import contextlib
import tempfile
import uuid
from collections.abc import Iterable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field
from weakref import WeakKeyDictionary

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

MOST_LEVELS = 10
HASH = "_rw_hash"
_ROWS: WeakKeyDictionary[DataFrame, int] = WeakKeyDictionary()
# Runtime settings while rounds run. Adaptive plans hide how checkpoints are partitioned; a hash of some columns also serves
# joins on more; checkpoints keep constraints whose columns the optimizer has renamed; an anti join stays above the exchange it
# was written above; a removed alias would leave a checkpoint with a partitioning by a column that it does not have.
_FIXED = {
    "spark.sql.adaptive.enabled": "false",
    "spark.sql.requireAllClusterKeysForCoPartition": "false",
    "spark.sql.constraintPropagation.enabled": "false",
    "spark.sql.optimizer.excludedRules": "org.apache.spark.sql.catalyst.optimizer.PushDownLeftSemiAntiJoin,org.apache.spark.sql.catalyst.optimizer.PushLeftSemiLeftAntiThroughJoin,org.apache.spark.sql.catalyst.optimizer.RemoveRedundantAliases",
}


@dataclass
class FixpointResult:
    """The relation, how many rounds it took (the last one finds nothing), rows new in each round, seconds of each job, locals that came along, and whether rows are left out that nobody reads."""

    total: DataFrame
    rounds: int
    delta_sizes: list[int] = field(default_factory=list)
    seconds: list[float] = field(default_factory=list)
    locals: dict[str, DataFrame] = field(default_factory=dict)
    partial: bool = False


@contextlib.contextmanager
def fixed_plans(spark: SparkSession) -> Iterator[None]:
    """Plans that keep partitioning and order through checkpoints; the session's settings come back afterwards."""
    before = {k: spark.conf.get(k, None) for k in _FIXED}
    for k, v in _FIXED.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or the context's; only a local session without either gets one here."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        root = f"{tempfile.gettempdir()}/checkpoints"
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


def stored(df: DataFrame) -> DataFrame:
    """The rows as a Parquet table in the shared folder."""
    path = f"{shared_folder(df.sparkSession)}/ruleweave-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def _checkpoint(df: DataFrame) -> DataFrame:
    spark = df.sparkSession
    shared_folder(spark)
    key = "spark.sql.constraintPropagation.enabled"
    before = spark.conf.get(key, "true")
    spark.conf.set(key, "false")
    try:
        return df.checkpoint()
    finally:
        spark.conf.set(key, before)


def counted(df: DataFrame, **measures) -> tuple[DataFrame, dict[str, int]]:
    """checkpoint() in spark.checkpoint.dir, and what was counted on the way: rows, and any further aggregates, without a job of their own."""
    seen = Observation()
    frame = _checkpoint(df.observe(seen, F.count(F.lit(1)).alias("rows"), *[m.alias(n) for n, m in measures.items()]))
    found = {n: v or 0 for n, v in seen.get.items()} or dict.fromkeys(("rows", *measures), 0)
    _ROWS[frame] = found["rows"]
    return frame, found


def materialised(df: DataFrame) -> DataFrame:
    """checkpoint() in spark.checkpoint.dir; only a local session without one (as in tests) gets a folder here."""
    return counted(df)[0]


def all_materialised(frames: Iterable[DataFrame]) -> list[DataFrame]:
    """Independent frames, evaluated at the same time."""
    frames = list(frames)
    if len(frames) < 2:
        return [materialised(f) for f in frames]
    with ThreadPoolExecutor(min(8, len(frames))) as pool:
        return list(pool.map(materialised, frames))


def rows_of(frame: DataFrame) -> int | None:
    """Rows of a materialised frame, None for any other."""
    return _ROWS.get(frame)


def discard(frame: DataFrame) -> None:
    """Deletes the files of a superseded materialised frame."""
    with contextlib.suppress(Exception):  # a frame that is no checkpoint has none; what stays is only disk space
        rdd = frame._jdf.queryExecution().analyzed().rdd()
        path = rdd.getCheckpointFile()
        if path.isDefined():
            jvm = frame.sparkSession.sparkContext._jvm
            at = jvm.org.apache.hadoop.fs.Path(path.get())
            at.getFileSystem(frame.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def union_all(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def same_row(columns: list[str], prefix: str):
    """Equality with columns of that prefix, NULL being equal to NULL."""
    same = F.lit(True)
    for c in columns:
        same = same & F.col(f"`{c}`").eqNullSafe(F.col(f"`{prefix}{c}`"))
    return same


def minus(new: DataFrame, known: DataFrame, padded: bool = False) -> DataFrame:
    """Rows of new that known does not have. With padding, NULL equals NULL; without, plain keys keep the partitioning usable."""
    if not padded:
        return new.join(known, new.columns, "left_anti")
    other = known.select([F.col(f"`{c}`").alias(f"_k_{c}") for c in new.columns])
    return new.join(other, same_row(new.columns, "_k_"), "left_anti")


class Levels:
    """Known rows of one relation. Padded rows are placed by a hash of all columns, which then stands beside them."""

    def __init__(self, columns: list[str], key: list[str], partitions: int, padded: bool = False):
        self.columns, self.padded, self.partitions = columns, padded, partitions
        self.key = [HASH] if padded else key
        self.frames: list[DataFrame] = []
        self.rows: list[int] = []
        self._stale: list[DataFrame] = []

    def placed(self, df: DataFrame) -> DataFrame:
        if self.padded:
            df = df.withColumn(HASH, F.xxhash64(*[F.col(f"`{c}`") for c in self.columns]))
        return df.repartition(self.partitions, *[F.col(f"`{c}`") for c in self.key])

    def ordered(self, df: DataFrame) -> DataFrame:
        return df.sortWithinPartitions(*[F.col(f"`{c}`") for c in ([HASH] if self.padded else self.columns)])

    def unknown(self, new: DataFrame) -> DataFrame:
        """Rows of placed candidates that no level has: one merge a level, of sorted partitions that stay where they are."""
        for f in self.frames:
            if self.padded:
                other = f.select([F.col(f"`{c}`").alias(f"_k_{c}") for c in (HASH, *self.columns)])
                new = new.join(other.hint("merge"), (F.col(HASH) == F.col(f"_k_{HASH}")) & same_row(self.columns, "_k_"), "left_anti")
            else:
                new = new.join(f.hint("merge"), self.columns, "left_anti")
        return new

    def add(self, frame: DataFrame, rows: int) -> None:
        """A further level of rows that no other holds."""
        for old in self._stale:
            discard(old)
        self._stale = []
        if not rows:
            return
        self.frames.append(frame)
        self.rows.append(rows)
        if len(self.frames) > MOST_LEVELS:
            at = len(self.frames) - 2
            while at and self.rows[at - 1] <= sum(self.rows[at:]):
                at -= 1
            merged = materialised(self.ordered(union_all(self.frames[at:])))
            self._stale, self.frames = self.frames[at:], [*self.frames[:at], merged]  # the last of them may still be a round's delta
            self.rows = [*self.rows[:at], sum(self.rows[at:])]

    def total(self, empty: DataFrame) -> DataFrame:
        """All known rows."""
        return union_all(self.frames or [empty]).select([F.col(f"`{c}`") for c in self.columns])
