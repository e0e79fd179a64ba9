"""All rounds inside one partition: facts are grouped by the component of the graph they belong to, one shuffle in all.

For data that falls apart into many parts (users, customers, conversations) depth stops mattering: each group runs the whole
program with the local evaluator. Facts travel packed, one row a group and relation. Groups above `most_rows` facts don't fit this
way; they are taken out and run as ordinary rounds, and the results are united.
"""

from __future__ import annotations

from collections.abc import Mapping

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleweave.ir.lower import to_ir
from ruleweave.ir.primary import normal
from ruleweave.lang.ast import Program
from ruleweave.operators import fixpoint, local
from ruleweave.operators.state import materialised

MOST_ROWS = 1_000_000


def partition_local(program: Program, env: Mapping[str, DataFrame], parts: DataFrame, keys: Mapping[str, str | None], output: str, most_rows: int = MOST_ROWS) -> DataFrame:
    """The relation `output` of a canonical program over BIGINT facts.

    parts maps node to part; keys names, for each input relation, the column that holds a node (None: the relation is
    small and every group gets all of it).
    """
    split = {p: k for p, k in keys.items() if k is not None}
    shared = {p: [tuple(r) for r in env[p].collect()] for p, k in keys.items() if k is None}  # relations stated to be small
    node, part = parts.columns[:2]
    located = {}
    for p, k in split.items():
        located[p] = env[p].join(parts.select(F.col(node).alias(k), F.col(part).alias("rw_part")), k).select("rw_part", *[F.col(c).cast("bigint").alias(c) for c in env[p].columns])
    rows = None
    for p, df in located.items():
        one = df.select("rw_part", F.lit(p).alias("rw_pred"), F.array(*[F.col(c) for c in env[p].columns]).alias("rw_args"))
        rows = one if rows is None else rows.unionByName(one)
    sizes = rows.groupBy("rw_part").count().filter(F.col("count") > most_rows).select("rw_part")
    large = materialised(sizes)
    columns = next(d for d in normal(to_ir(program)) if d.head == output).columns
    schema = pa.schema([(c, pa.int64()) for c in columns])

    def run(key: tuple[pa.Scalar, ...], group: pa.Table) -> pa.Table:
        facts: dict[str, set] = {p: set(r) for p, r in shared.items()} | {p: set() for p in split}
        for pred, args in zip(group["rw_pred"].to_pylist(), group["rw_args"].to_pylist(), strict=True):
            facts[pred].add(tuple(args))
        found = local.evaluate(program, facts)[output]
        flat = np.array(sorted(found), np.int64).reshape(len(found), len(columns))
        return pa.Table.from_arrays([pa.array(flat[:, k]) for k in range(len(columns))], schema=schema)

    some_large = not large.isEmpty()
    small = rows.join(large, "rw_part", "left_anti") if some_large else rows
    out = small.groupBy("rw_part").applyInArrow(run, ", ".join(f"{c} bigint" for c in columns))
    if some_large:
        rest = dict(env) | {p: df.join(large, "rw_part", "left_semi").drop("rw_part") for p, df in located.items()}
        for d in normal(to_ir(program)):
            rest[d.head] = fixpoint.seminaive(d, rest).total
        out = out.unionByName(rest[output])
    return out
