"""Insert-only maintenance of monotone recursive relations, and windowed counts of streams.

`Maintained` holds the relations of one linear program and continues its fixpoint from each batch of new facts: what new facts derive
with the total so far seeds the delta, and the rounds go on from there, over the same levels. Strata under negation have to be recomputed and
are refused. Windowed counts run in update mode into an idempotent sink, sessions in append mode, so that the watermark bounds their state.
"""

from __future__ import annotations

import uuid
from collections.abc import Mapping

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ruleweave.ir.nodes import Conjunction, Definition
from ruleweave.lang.ast import Atom
from ruleweave.operators.state import Levels, counted, fixed_plans, materialised, minus, shared_folder, union_all
from ruleweave.plans.conjunction import apply, conjunction
from ruleweave.plans.program import compile_program
from ruleweave.sources.facts import query
from ruleweave.workloads import programs


class Maintained:
    """One recursive definition kept up to date while facts are only added."""

    def __init__(self, defn: Definition, empty: Mapping[str, DataFrame]):
        if defn.locals or any(a.negated for c in defn.body for a in c.atoms):
            raise ValueError("only definitions without locals and negation are maintained")
        self.defn, self.facts, self.total = defn, dict(empty), None
        self.levels, self.spark = None, next(iter(empty.values())).sparkSession

    def add(self, new: Mapping[str, DataFrame]) -> DataFrame:
        """Adds facts; gives the rows that became derivable."""
        fresh = {n: materialised(minus(df.distinct(), self.facts[n])) for n, df in new.items()}
        for n, df in fresh.items():
            self.facts[n] = materialised(self.facts[n].unionByName(df))
        seeds = []
        frames = dict(self.facts) | ({self.defn.head: self.total} if self.total is not None else {})
        for c in self.defn.body:
            for k, a in enumerate(c.atoms):
                if a.pred in fresh and all(x.pred in frames for x in c.atoms):
                    marked = Conjunction(c.atoms[:k] + (Atom("_new", a.args),) + c.atoms[k + 1 :], c.compares)
                    seeds.append(conjunction(marked, self.defn.columns, frames | {"_new": fresh[a.pred]}, self.defn.types, "_new"))
        if not seeds:
            return self.total.limit(0)
        added = []
        with fixed_plans(self.spark):
            if self.levels is None:
                n = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
                self.levels = Levels(list(self.defn.columns), list(self.defn.columns), n)
            step = union_all(seeds)
            while step is not None:
                delta, found = counted(self.levels.unknown(self.levels.placed(step).distinct()))
                if not found["rows"]:
                    break
                added.append(delta)
                self.levels.add(delta, found["rows"])
                step = apply(self.defn, self.facts, delta, False)
            self.total = self.levels.total(delta)
        return union_all(added) if added else self.total.limit(0)


def _folder(spark: SparkSession) -> str:
    return f"{shared_folder(spark)}/ruleweave-stream-{uuid.uuid4().hex}"


def _event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    # a stream reads folders: the table's own if it is one, else the file by its name
    source = spark.readStream.schema(schema)
    source = source.parquet(path) if _is_folder(spark, path) else source.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return source.withColumn("ts", F.col("ts").cast("timestamp"))


def upserted(rows: DataFrame, keys: list[str], value: str) -> tuple[DataFrame, int]:
    """Runs a streaming aggregate in update mode to its end: a trigger writes the groups that it changed into a folder of its own (again, if it is
    repeated), and the last value of a group counts. The watermark lets go of state; also returned: rows that came too late for it."""
    folder = _folder(rows.sparkSession)
    write = lambda df, k: df.withColumn("batch", F.lit(k)).write.mode("overwrite").parquet(f"{folder}/out/part{k}")
    run = rows.writeStream.outputMode("update").option("checkpointLocation", f"{folder}/state").foreachBatch(write).trigger(availableNow=True).start()
    run.awaitTermination()
    kept = rows.sparkSession.read.parquet(f"{folder}/out/*").groupBy(*keys).agg(F.max_by(value, "batch").alias(value))
    return kept, late_rows(run)


def late_rows(run) -> int:
    """Rows that a finished streaming query dropped because its watermark had passed them."""
    return sum(op.numRowsDroppedByWatermark for p in run.recentProgress for op in p.stateOperators)


def event_windows(spark: SparkSession, sf_dir: str, length: str = "1 day", step: str | None = None) -> DataFrame:
    """Events by type and window as a stream; with step, windows slide."""
    counted = _event_stream(spark, sf_dir).withWatermark("ts", "1 day").groupBy(F.window("ts", length, step), "event_type").agg(F.count("*").alias("n"))
    rows = counted.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "event_type", "n")
    return upserted(rows, ["day", "event_type"], "n")[0]


def event_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Windows of two days that begin every day."""
    return event_windows(spark, sf_dir, "2 days", "1 day")


def event_sessions(spark: SparkSession, sf_dir: str, gap: str = "2 hours") -> DataFrame:
    """Sessions of each user: events less than `gap` apart. Sessions end once, so they are appended when the watermark has passed them; those
    that are still open at the end of the input are not there."""
    folder = _folder(spark)
    grouped = _event_stream(spark, sf_dir).withWatermark("ts", "0 seconds").groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    rows = grouped.select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("begins"), "n")
    run = rows.writeStream.outputMode("append").option("checkpointLocation", f"{folder}/state").format("parquet").option("path", f"{folder}/out").trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.schema(rows.schema).parquet(f"{folder}/out")


EVENT_WINDOWS_SQL = "select strftime(ts, '%Y-%m-%d') as day, event_type, count(*) as n from events group by all"
EVENT_SLIDING_SQL = "select strftime(date_trunc('day', ts) - to_days(cast(k as integer)), '%Y-%m-%d') as day, event_type, count(*) as n from events, range(2) t(k) group by all"
EVENT_SESSIONS_SQL = """with e as (select user_id, ts, case when ts - lag(ts) over w < interval 2 hour then 0 else 1 end as fresh from events window w as (partition by user_id order by ts)),
s as (select user_id, ts, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as k from e)
select user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') as begins, count(*) as n from s group by user_id, k having max(ts) + interval 2 hour <= (select max(ts) from events)"""


def _is_folder(spark: SparkSession, path: str) -> bool:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def turn_reach(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Reachability from chain heads while edges arrive in two batches."""
    edge = query(spark, sf_dir, "select * from turn_edge", ["turn_edge"])
    head = query(spark, sf_dir, programs.CHAINS["turns"][1], ["turn_edge"])
    kept = Maintained(compile_program(programs.FROM_HEADS).definitions[0], {"edge": edge.limit(0), "head": head.limit(0)})
    kept.add({"edge": edge.filter("src % 2 = 0"), "head": head})
    kept.add({"edge": edge.filter("src % 2 = 1")})
    return kept.total
