"""Steps along a static relation that falls apart into chains, as intervals of positions instead of rounds.

Each node gets its chain and its position by doubling pointers, in a number of joins that is logarithmic in the longest chain. What a
tuple reaches is then the stretch from its node to the next node where another tuple starts, a negated literal bars the way, or the chain ends:
one window over base tuples and bars, and an explode. No row is derived twice and none is compared with known ones.
"""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Mapping

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ruleweave.operators.keys import is_key
from ruleweave.operators.state import FixpointResult, counted, discard, materialised, union_all
from ruleweave.plans.ahead import Hop

MOST_NODES = 1_000_000  # of one chain, which is a row while stretches are expanded


def moving(hop: Hop) -> str | None:
    """The one column that the step changes, from one column of a static relation of two to the other; None if the step is of another kind."""
    own = [a.name for a in hop.own.args]
    static = [a.name for a in hop.static.args]
    changed = [c for c, v in zip(hop.columns, own, strict=True) if v != c]
    if len(changed) != 1 or len(static) != 2 or hop.compares or hop.binds:
        return None
    at = own[hop.columns.index(changed[0])]
    if sorted(static) != sorted((at, changed[0])) or at in hop.columns:
        return None
    barred = all(sorted(v.name for v in a.args) == sorted(hop.columns) for a in hop.negated)
    return changed[0] if barred and len(hop.columns) > 1 else None


def positions(edge: DataFrame) -> DataFrame | None:
    """chain, nodes (all, in order) of a relation (src, dst); None if it is not made of chains or a chain is too long."""
    edge = edge.toDF("src", "dst")
    if not is_key(edge, ("src",)) or not is_key(edge, ("dst",)):
        return None
    known, found = counted(edge.select(F.col("dst").alias("node"), F.col("src").alias("up"), F.lit(1).cast("bigint").alias("pos"), F.lit(True).alias("open")))
    most = max(1, math.ceil(math.log2(found["rows"] + 1))) + 1
    n = int(edge.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    for _ in range(most + 1):
        above = known.select(F.col("node").alias("up"), F.col("up").alias("up2"), F.col("pos").alias("pos2"))
        further = known.filter("open").join(above, "up", "left").select("node", F.coalesce("up2", "up").alias("up"), (F.col("pos") + F.coalesce("pos2", F.lit(0))).alias("pos"), F.col("up2").isNotNull().alias("open"))
        before = known
        known, found = counted(union_all([before.filter("not open"), further]).coalesce(n), going=F.count_if("open"))
        discard(before)
        if not found["going"]:
            break
    else:  # a cycle has no first node
        return None
    nodes = known.groupBy(F.col("up").alias("chain")).agg(F.sort_array(F.collect_list(F.struct("pos", "node"))).alias("n"))
    chains, found = counted(nodes.select("chain", F.concat(F.array("chain"), F.col("n.node")).alias("nodes")), longest=F.max(F.size("nodes")))
    discard(known)
    return chains if found["longest"] <= MOST_NODES else None


def stretches(hop: Hop, env: Mapping[str, DataFrame], seed: DataFrame) -> tuple[DataFrame, DataFrame, Callable[[DataFrame], DataFrame]] | None:
    """Base tuples outside of chains; those in chains with their position, the most nodes that they can reach before the next one and the chain's end; what makes rows of such stretches."""
    column = moving(hop)
    fixed = [c for c in hop.columns if c != column]
    edge = env[hop.static.pred]
    order = [c for c, a in zip(edge.columns, hop.static.args, strict=True) if a.name != column]
    chains = positions(edge.select(*order, *[c for c in edge.columns if c not in order]))
    if chains is None:
        return None
    place = chains.select(F.posexplode("nodes").alias("_rw_pos", column), F.col("chain").alias("_rw_chain"), F.size("nodes").alias("_rw_end"))
    points = [seed.select(*hop.columns, F.lit(True).alias("_rw_seed"))]
    for a in hop.negated:
        bars = env[a.pred].toDF(*[v.name for v in a.args])
        points.append(bars.select(*hop.columns, F.lit(False).alias("_rw_seed")))
    keys = [*fixed, "_rw_chain"]
    placed = union_all(points).join(place, column, "left")
    # a node that no edge has is a chain of its own
    alone = F.col("_rw_chain").isNull()
    first = placed.filter(alone & F.col("_rw_seed")).select(*hop.columns).distinct()
    marks = placed.filter(~alone).groupBy(*keys, "_rw_pos", "_rw_end").agg(F.max("_rw_seed").alias("_rw_seed"))
    following = F.lead("_rw_pos").over(Window.partitionBy(*keys).orderBy("_rw_pos"))
    spans = marks.withColumn("_rw_n", F.coalesce(following, F.col("_rw_end")) - F.col("_rw_pos")).filter("_rw_seed").select(*keys, "_rw_pos", "_rw_n", "_rw_end")

    def reached(some: DataFrame) -> DataFrame:
        nodes = F.explode(F.slice("nodes", F.col("_rw_pos") + 1, F.col("_rw_n"))).alias(column)
        return some.join(chains.withColumnRenamed("chain", "_rw_chain"), "_rw_chain").select(*fixed, nodes).select(*hop.columns)

    return materialised(first), materialised(spans), reached


def along(hop: Hop, env: Mapping[str, DataFrame], seed: DataFrame) -> FixpointResult | None:
    """The fixpoint of a step for which moving() names a column; None if the static relation is not made of chains."""
    started = time.perf_counter()
    found = stretches(hop, env, seed)
    if found is None:
        return None
    first, spans, reached = found
    lengths = {r[0]: r[1] for r in spans.groupBy("_rw_n").count().collect()}
    sizes, left = [], sum(lengths.values())
    for k in range(max(lengths, default=0)):
        sizes.append(left)
        left -= lengths.get(k + 1, 0)
    sizes = sizes or [0]
    sizes[0] += first.count()
    return FixpointResult(union_all([reached(spans), first]), len(sizes) + bool(sizes[-1]), sizes + [0] * bool(sizes[-1]), [time.perf_counter() - started])


def naive_along(hop: Hop, env: Mapping[str, DataFrame], seed: DataFrame, most: int) -> FixpointResult | None:
    """The same by naive rounds: each derives every stretch anew from the whole relation before, a node longer where it can be, until the number of rows stays."""
    found = stretches(hop, env, seed)
    if found is None:
        return None
    first, spans, reached = found
    alone = first.count()
    now, seen = counted(spans.withColumn("_rw_most", F.col("_rw_n")).withColumn("_rw_n", F.lit(1)), held=F.sum("_rw_n"))
    sizes, seconds = [seen["held"] + alone], [0.0]
    while len(sizes) <= most:
        started = time.perf_counter()
        before = now
        now, seen = counted(before.withColumn("_rw_n", F.least("_rw_most", F.col("_rw_n") + 1)), held=F.sum("_rw_n"))
        discard(before)
        sizes.append(seen["held"] + alone)
        seconds.append(time.perf_counter() - started)
        if sizes[-1] == sizes[-2]:
            break
    return FixpointResult(union_all([reached(now), first]), len(sizes), sizes, seconds)
