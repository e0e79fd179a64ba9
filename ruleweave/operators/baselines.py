"""The ways to evaluate recursion that the compiled fixpoint is compared with, each on Spark.

`native_bounded`: one recursive query, for acyclic or depth-bounded data. `external_loop`: SQL text sent each round, over the whole
relation. `round_batches`: candidate, difference and merge as separate statements a round, each materialised. `arranged`: static relations laid out
by join key once, deltas shuffled to them. `local_oracle`: Python sets on the driver, for small inputs. Over many rows in chains, the first two
keep the relation as stretches (operators.chains); each round still is statements over the whole of it.
"""

from __future__ import annotations

import contextlib
import time
from collections.abc import Callable, Mapping
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleweave.ir.inline import inline_locals
from ruleweave.ir.nodes import Conjunction, Definition
from ruleweave.ir.rewrite import first_stage
from ruleweave.lang.ast import Atom, Program, Var
from ruleweave.operators import chains, fixpoint, local
from ruleweave.operators.state import FixpointResult, all_materialised, counted, discard, fixed_plans, materialised, minus, rows_of, union_all
from ruleweave.plans.ahead import single_hop
from ruleweave.plans.conjunction import apply
from ruleweave.plans.layout import many_rows, meeting, small
from ruleweave.sqltext.emit import DIALECTS, Dialect, Emitter, statement

MOST_LOCAL_FACTS = 100_000
STRETCHES = 200_000  # of a partition: a round's statement over fewer takes longer to start than to run


def native_bounded(definitions: list[Definition], output: str, env: Mapping[str, DataFrame], levels: int = 100) -> DataFrame:
    """Spark's own recursive common table. Wrong use (a cycle) ends in Spark's level or row limit, not in a wrong result."""
    d = DIALECTS["spark_bounded"]
    text = statement(definitions, output, Dialect(d.name, d.quote, "inlined", True, levels, True), {n: tuple(f.columns) for n, f in env.items()})
    return _sql(env, text)


def _sql(env: Mapping[str, DataFrame], text: str) -> DataFrame:
    """Runs text over the relations of env, bound as parameters."""
    spark = next(iter(env.values())).sparkSession
    used = {n: f for n, f in env.items() if f" {n} t" in text or f" {n} n" in text}
    for n in used:
        for kind in "tn":
            text = text.replace(f" {n} {kind}", f" {{{n}}} {kind}")
    return spark.sql(text, **used)


def _step_text(defn: Definition, env: Mapping[str, DataFrame]) -> tuple[Definition, list[str], list[str]]:
    flat = inline_locals(defn)
    e = Emitter(Dialect("spark_bounded", quote="`", form="inlined"), {n: tuple(f.columns) for n, f in env.items()} | {flat.head: flat.columns})
    base, step = flat.split()
    select = _staged if many_rows(flat, env) else Emitter.select
    return flat, [select(e, c, flat, False) for c in base], [select(e, c, flat, False) for c in step]


def _statement(parts: list[str], flat: Definition, placed: int) -> str:
    """The parts' rows, each once; with placed, in that many partitions by the columns that meet static relations."""
    hint = f"/*+ REPARTITION({placed}, {', '.join(f'`{c}`' for c in meeting(flat))}) */ " if placed else ""
    return f"SELECT DISTINCT * FROM (SELECT {hint}* FROM ({' UNION ALL '.join(f'({p})' for p in parts)}) a) b"


@contextlib.contextmanager
def _placed(flat: Definition, env: Mapping[str, DataFrame]):
    """The relations with what a round's constant part reads evaluated once, and how many partitions rounds keep (0: as each statement's plan has it)."""
    read = [p for p in dict.fromkeys(a.pred for c in flat.split()[0] for a in c.atoms) if p in env and rows_of(env[p]) is None]
    env = dict(env) | dict(zip(read, all_materialised(env[p] for p in read), strict=True))
    spark = next(iter(env.values())).sparkSession
    if not many_rows(flat, env):
        yield env, 0
        return
    with fixed_plans(spark):
        yield env, int(spark.conf.get("spark.sql.shuffle.partitions"))


def _staged(e: Emitter, conj: Conjunction, defn: Definition, distinct: bool) -> str:
    """The conjunction as SQL in which what some literals leave of their variables is made distinct before the others can multiply it."""
    inner: dict[str, str] = {}
    while cut := first_stage(conj, defn.columns, [defn.head, *inner]):
        name = f"rw_stage{len(inner) + 1}"
        columns, before, after = cut
        text = _nested(e.select(before, Definition(name, columns, (before,)), True), inner)
        inner[name], e.columns_of[name] = text, columns
        conj = Conjunction((Atom(name, tuple(map(Var, columns))), *after))
    return _nested(e.select(conj, defn, distinct), inner)


def _nested(text: str, inner: Mapping[str, str]) -> str:
    for name, part in inner.items():
        text = text.replace(f" {name} t", f" ({part}) t")
    return text


@dataclass(frozen=True)
class Stretches:
    """A relation whose step follows chains: base tuples outside of chains, statements over stretches of the others, what makes rows of them."""

    alone: DataFrame
    first: DataFrame
    held: tuple[str, ...]  # what names a stretch: unchanging columns, chain, position
    rows: Callable[[DataFrame], DataFrame]
    parts: int

    def statement(self, source: str, length: str, where: str = "true") -> str:
        held = ", ".join(f"`{c}`" for c in self.held)
        return f"SELECT {held}, {length} AS _rw_n, _rw_most, _rw_end FROM {source} t WHERE {where}"

    def total(self, now: DataFrame) -> DataFrame:
        return union_all([self.rows(now), self.alone])


def _stretches(flat: Definition, env: Mapping[str, DataFrame], seed: DataFrame) -> Stretches | None:
    """The stretches of one node that base tuples are; None if facts are few or the step follows no chains."""
    line = single_hop(flat) if flat.recursive and many_rows(flat, env) else None
    found = chains.stretches(line, env, seed) if line and chains.moving(line) else None
    if found is None:
        return None
    alone, spans, rows = found
    first = spans.withColumn("_rw_most", F.col("_rw_n")).withColumn("_rw_n", F.lit(1))
    held = tuple(c for c in spans.columns if c not in ("_rw_n", "_rw_end"))
    parts = -(-(rows_of(spans) + 1) // STRETCHES)
    return Stretches(alone, first.select(*held, "_rw_n", "_rw_most", "_rw_end").coalesce(parts), held, rows, parts)


def _external_stretches(s: Stretches, most: int) -> FixpointResult:
    """The whole relation anew in every round: each stretch from its base tuple on, a node longer than before where it can be."""
    alone, text = rows_of(s.alone), s.statement("rw_total", "least(_rw_most, _rw_n + 1)")
    now, seen = counted(s.first, held=F.sum("_rw_n"))
    sizes, seconds = [seen["held"] + alone], [0.0]
    while len(sizes) <= most:
        started, before = time.perf_counter(), now
        now, seen = counted(_sql({"rw_total": before}, text), held=F.sum("_rw_n"))
        discard(before)
        sizes.append(seen["held"] + alone)
        seconds.append(time.perf_counter() - started)
        if sizes[-1] == sizes[-2]:
            return FixpointResult(s.total(now), len(sizes), sizes, seconds)
    raise fixpoint.RoundLimit(f"more than {most} rounds")


def _batched_stretches(s: Stretches, most: int) -> FixpointResult:
    """Candidates are the next nodes of the stretches that grew last; those that are base tuples or barred are known; the others' stretches replace their shorter forms."""
    delta = materialised(s.first)
    sizes, seconds = [rows_of(delta) + rows_of(s.alone)], [0.0]

    def merged(before: DataFrame, new: DataFrame, last: DataFrame, rounds: int) -> DataFrame:
        # the stretches that grew are those as long as there were rounds, with room for a node
        kept = _sql({"rw_total": before}, s.statement("rw_total", "_rw_n", f"_rw_n < {rounds} OR _rw_n = _rw_most"))
        total = materialised(kept.unionByName(new).coalesce(s.parts))
        for old in {id(f): f for f in (before, last)}.values():
            discard(old)
        return total

    with ThreadPoolExecutor(1) as pool:  # the merge runs beside the next round's candidates, which don't read it
        total = pool.submit(lambda first=delta: first)
        while sizes[-1]:
            if len(sizes) > most:
                raise fixpoint.RoundLimit(f"more than {most} rounds")
            started, last = time.perf_counter(), delta
            candidates = materialised(_sql({"rw_delta": delta}, s.statement("rw_delta", "_rw_n + 1", "_rw_pos + _rw_n < _rw_end")))
            delta = materialised(_sql({"rw_candidates": candidates}, s.statement("rw_candidates", "_rw_n", "_rw_n <= _rw_most")))
            discard(candidates)
            total = pool.submit(merged, total.result(), delta, last, len(sizes))
            sizes.append(rows_of(delta))
            seconds.append(time.perf_counter() - started)
        return FixpointResult(s.total(total.result()), len(sizes), sizes, seconds)


def external_loop(defn: Definition, env: Mapping[str, DataFrame], most: int = fixpoint.MOST_ROUNDS) -> FixpointResult:
    """A driver loop that plans and runs one statement a round over the whole relation, until it stops growing."""
    flat, base, step = _step_text(defn, env)
    with _placed(flat, env) as (env, placed):
        total = materialised(_sql(env, _statement(base, flat, placed)))
        lines = _stretches(flat, env, total)
        if lines:
            return _external_stretches(lines, most)
        text = _statement([*base, *step], flat, placed)
        sizes, seconds = [rows_of(total)], [0.0]
        while len(sizes) <= most:
            started = time.perf_counter()
            before = total
            total = materialised(_sql(env | {flat.head: before}, text))
            discard(before)
            sizes.append(rows_of(total))
            seconds.append(time.perf_counter() - started)
            if sizes[-1] == sizes[-2]:
                return FixpointResult(total, len(sizes), sizes, seconds)
    raise fixpoint.RoundLimit(f"more than {most} rounds")


def round_batches(defn: Definition, env: Mapping[str, DataFrame], most: int = fixpoint.MOST_ROUNDS) -> FixpointResult:
    """Three materialised statements a round: candidates from the last delta, their difference, the merged relation."""
    flat, base, step = _step_text(defn, env)
    with _placed(flat, env) as (env, placed):
        total = delta = materialised(_sql(env, _statement(base, flat, placed)))
        lines = _stretches(flat, env, total)
        if lines:
            return _batched_stretches(lines, most)
        text = _statement(step, flat, placed)
        sizes, seconds = [rows_of(delta)], [0.0]
        while sizes[-1]:
            if len(sizes) > most:
                raise fixpoint.RoundLimit(f"more than {most} rounds")
            started = time.perf_counter()
            candidates = materialised(_sql(env | {flat.head: delta}, text))
            before, last = total, delta
            # few candidates are sent to where known rows are, which neither move nor are sorted
            few = placed and not defn.padded and small(candidates)
            delta = materialised(minus(candidates, before.join(F.broadcast(candidates), before.columns, "left_semi") if few else before, defn.padded))
            merged = before.unionByName(delta)
            total = materialised(merged.coalesce(placed) if placed else merged)
            for old in {id(f): f for f in (candidates, before, last)}.values():
                discard(old)
            sizes.append(rows_of(delta))
            seconds.append(time.perf_counter() - started)
    return FixpointResult(total, len(sizes), sizes, seconds)


def arranged(defn: Definition, env: Mapping[str, DataFrame], most: int = fixpoint.MOST_ROUNDS) -> FixpointResult:
    """Semi-naive rounds over static relations that are hashed and sorted by their join columns once."""
    flat = inline_locals(defn)
    laid: dict[str, DataFrame] = dict(env)
    for c in flat.split()[1]:
        own = {v.name for a in c.uses([flat.head]) for v in a.args}
        for a in c.positive:
            if a.pred != flat.head and a.pred in env and laid[a.pred] is env[a.pred]:
                by = [col for col, v in zip(env[a.pred].columns, a.args, strict=True) if v.name in own]
                if by:
                    laid[a.pred] = env[a.pred].repartition(*by).sortWithinPartitions(*by).persist()
    try:
        return fixpoint.seminaive(flat, laid, most)
    finally:
        for n, f in laid.items():
            if f is not env[n]:
                f.unpersist()


def local_oracle(program: Program, env: Mapping[str, DataFrame], most: int = MOST_LOCAL_FACTS) -> dict[str, set[tuple]]:
    """The model as Python sets; refuses inputs of more than `most` facts."""
    n = sum(env[p].count() for p in program.edb)
    if n > most:
        raise ValueError(f"{n} facts are too many for the driver")
    return local.evaluate(program, {p: {tuple(r) for r in env[p].collect()} for p in program.edb})


def naive(defn: Definition, env: Mapping[str, DataFrame]) -> FixpointResult:
    return fixpoint.naive(defn, env)


def constant_part(defn: Definition, env: Mapping[str, DataFrame]) -> DataFrame | None:
    """What a definition derives before its first round."""
    return apply(defn, env, None, True)
