"""Runs a workload: inputs from the tables of a folder, a program, a form, a strategy."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ruleweave.lang.normalize import canonical
from ruleweave.lang.parser import parse
from ruleweave.operators import fixpoint, keys
from ruleweave.operators.partition_local import partition_local
from ruleweave.operators.state import FixpointResult, materialised, union_all
from ruleweave.plans.program import Compiled, Evaluation, compile_program, evaluate, prepared
from ruleweave.sources.facts import facts, query
from ruleweave.workloads import programs


def inputs(spark: SparkSession, sf_dir: str, name: str) -> dict[str, DataFrame]:
    return facts(spark, sf_dir, programs.INPUTS[name])


def evaluated(spark: SparkSession, sf_dir: str, name: str, form: str = "lifted", strategy: Callable[..., FixpointResult] = fixpoint.seminaive, outputs: list[str] | None = None) -> tuple[Compiled, Evaluation]:
    """A workload's relations; with outputs, only what they need is computed."""
    program = parse(programs.PROGRAMS[name])
    if outputs:
        program.outputs = outputs
    compiled = compile_program(program, form)
    return compiled, evaluate(compiled, inputs(spark, sf_dir, name), strategy)


def picked_keys(compiled: Compiled, env: dict[str, DataFrame]) -> dict[str, tuple[str, ...]]:
    """For each input relation that recursion reads, the key that discovery and choice give it; relations without one are left out."""
    used = keys.recursive_columns(compiled.definitions, {n: tuple(f.columns) for n, f in env.items()})
    found = {n: keys.pick_key(keys.keys(env[n]), cols) for n, cols in sorted(used.items()) if n in env}
    return {n: k for n, k in found.items() if k}


def flow_reach_keyed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Deep reachability with the keys that discovery finds: rounds join the edges by their key and leave out the deduplication."""
    env, compiled = inputs(spark, sf_dir, "flow_reach"), compile_program(programs.FLOW_REACH)
    env["flow_edge"] = materialised(env["flow_edge"])
    known = {"flow_edge": keys.keys(env["flow_edge"])}
    return evaluate(compiled, env, partial(fixpoint.seminaive, keys=known)).relations["reach"]


def users_of_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return query(spark, sf_dir, "select event_id as node, user_id as part from events", [])


def customers_of_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return query(spark, sf_dir, "select o_orderkey as node, o_custkey as part from orders", [])


def flow_reach_local(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Deep reachability with all rounds inside each user's events: one shuffle in all."""
    return partition_local(canonical(parse(programs.FLOW_REACH)), inputs(spark, sf_dir, "flow_reach"), users_of_events(spark, sf_dir), {"flow_null": "src", "flow_edge": "src"}, "reach")


def heap_local(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The heap closure inside each customer's orders."""
    env = {"edge": facts(spark, sf_dir, ["order_next"])["order_next"]}
    return partition_local(canonical(parse(programs.CLOSURE)), env, customers_of_orders(spark, sf_dir), {"edge": "src"}, "path")


def chain(spark: SparkSession, sf_dir: str, kind: str) -> dict[str, DataFrame]:
    """Edges and heads of the natural chains of a table."""
    edge, head = programs.CHAINS[kind]
    return {"edge": facts(spark, sf_dir, [edge])[edge], "head": query(spark, sf_dir, head, [edge])}


def generated_chains(spark: SparkSession, width: int, length: int) -> dict[str, DataFrame]:
    """`width` chains of `length` edges: node = chain * (length + 1) + position."""
    step = length + 1
    edge = spark.range(width * length).select(((F.floor(F.col("id") / length)) * step + F.col("id") % length).cast("bigint").alias("src")).select("src", (F.col("src") + 1).alias("dst"))
    return {"edge": edge, "head": spark.range(width).select((F.col("id") * step).alias("node"))}


def from_heads(env: dict[str, DataFrame], strategy: Callable[..., FixpointResult] = fixpoint.seminaive) -> FixpointResult:
    definition = compile_program(programs.FROM_HEADS).definitions[0]
    return strategy(definition, prepared(definition, dict(env), env))


def closure(env: dict[str, DataFrame], strategy: Callable[..., FixpointResult] = fixpoint.seminaive) -> FixpointResult:
    definition = compile_program(programs.CLOSURE).definitions[0]
    return strategy(definition, prepared(definition, dict(env), env))


def ring_relations(env: dict[str, DataFrame], m: int, form: str) -> DataFrame:
    """rel, n, total (count and sum of nodes) of each relation of the ring."""
    found = evaluate(compile_program(programs.ring(m), form), env).relations
    parts = [found[f"r{k}"].agg(F.count("*").alias("n"), F.sum("node").alias("total")).select(F.lit(f"r{k}").alias("rel"), "n", F.col("total")) for k in range(1, m + 1)]
    return union_all(parts).filter("n > 0")
