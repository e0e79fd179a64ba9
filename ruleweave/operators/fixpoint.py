"""Fixpoints of definitions on DataFrames.

A round is a job: the delta joins the static relations, candidates are made distinct, known rows go by anti joins. State and static
relations are laid out once (plans.layout), so that a round moves its candidates once, or nothing at all where every static relation
is broadcast. Where deltas are small and don't grow, a job runs several rounds (plans.ahead). `pivoted` demands a column that the recursion
never changes. `naive` recomputes everything and is a control. `general` takes non-linear components, one delta for each own literal.
`lattice` keeps one best value a key.
"""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Mapping
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleweave.ir.inline import pivot_columns
from ruleweave.ir.nodes import Conjunction, Definition
from ruleweave.lang.ast import Atom, Var
from ruleweave.operators import bitsets, chains
from ruleweave.operators.state import FixpointResult, Levels, counted, discard, fixed_plans, materialised, rows_of, stored, union_all
from ruleweave.plans.ahead import ROUND, Hop, single_hop
from ruleweave.plans.conjunction import apply, conjunction
from ruleweave.plans.keyed import distinct_needed
from ruleweave.plans.layout import Layout, layout, many_rows

MOST_ROUNDS = 100_000
# One job runs several rounds while deltas grow by at most AHEAD_GROWTH. A tuple passes all later hops of its job, so k rounds handle about
# k * k / 2 times the delta's rows; k is such that these are at most AHEAD_ROWS.
MOST_AHEAD, AHEAD_ROWS, AHEAD_GROWTH = 16, 4_000_000, 1.1


class RoundLimit(RuntimeError):
    """A fixpoint did not end within the allowed rounds."""


def seminaive(defn: Definition, env: Mapping[str, DataFrame], most: int = MOST_ROUNDS, pivot: str | None = None, partitions: int | None = None, keys: Mapping[str, list[tuple[str, ...]]] | None = None, ahead: int = MOST_AHEAD, wanted: bitsets.Wanted | None = None) -> FixpointResult:
    """Set-semantics fixpoint of a definition with at most one own literal a conjunction.

    keys: known keys of input relations; a round leaves out the deduplication that they make needless. ahead: most rounds a job.
    wanted: the rows that anyone reads (of the relation and its locals), where others may be left out.
    """
    seed = apply(defn, env, None, True)
    if not defn.recursive:
        return FixpointResult(seed.distinct(), 1)
    spark = seed.sparkSession
    with fixed_plans(spark):
        halves = bitsets.cut(defn) if many_rows(defn, env) and ahead > 1 and not keys and not pivot else None
        found = (bitsets.rounds(halves, env) if wanted is None else bitsets.rounds(halves, env, wanted)) if halves else None
        if found is not None:
            return _within(found, most)
        n = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
        plan = layout(defn, env, n, pivot, keys)
        levels = Levels(list(defn.columns), list(plan.key), n, defn.padded)
        line = single_hop(defn) if plan.early and not plan.broadcast and ahead > 1 and not keys else None
        if line and chains.moving(line):  # rounds would move and compare rows for as many rounds as the longest chain has nodes
            found = chains.along(line, env, seed)
            if found is not None:
                return _within(found, most)
        hop = single_hop(defn) if plan.broadcast and plan.stays and ahead > 1 else None
        if hop:  # scans of files are known to be equal, so that all hops of a job share one broadcast
            plan = replace(plan, env=plan.env | {p: F.broadcast(stored(plan.env[p])) for p in hop.reads})
        repeats = distinct_needed(defn, {p: tuple(f.columns) for p, f in env.items()}, keys or {})
        return _rounds(defn, plan, levels, seed, hop, repeats, most, ahead)


def sizes_only(defn: Definition, env: Mapping[str, DataFrame]) -> FixpointResult:
    """The rounds and rows of seminaive(); over many rows the result may hold no rows."""
    if defn.recursive and many_rows(defn, env):
        halves = bitsets.cut(defn)
        with fixed_plans(next(iter(env.values())).sparkSession):
            found = bitsets.counts(halves, env) if halves else None
        if found is not None:
            return _within(found, MOST_ROUNDS)
    return seminaive(defn, env)


def _within(found: FixpointResult, most: int) -> FixpointResult:
    if found.rounds - 1 > most:
        raise RoundLimit(f"more than {most} rounds")
    return found


def candidates(defn: Definition, plan: Layout, levels: Levels, delta: DataFrame, repeats: bool = True) -> DataFrame | None:
    """What one round derives from a delta, each row once, where the state is."""
    found = apply(defn, plan.env, delta.select([F.col(f"`{c}`") for c in defn.columns]), False, plan.early)
    if found is None:
        return None
    if not plan.stays or defn.padded or plan.early and _chained(defn):
        found = levels.placed(found)
    return found.distinct() if repeats else found


def _rounds(defn: Definition, plan: Layout, levels: Levels, seed: DataFrame, hop: Hop | None, repeats: bool, most: int, ahead: int) -> FixpointResult:
    sizes, seconds = [], []
    started = time.perf_counter()
    if _same_value_twice(defn):  # the optimizer merges such columns, and the checkpoint would not know by which of them it is hashed
        seed = materialised(seed.distinct())
    first, found = counted(levels.ordered(levels.placed(seed).distinct()))
    delta, sizes = first, [found["rows"]]
    levels.add(first, sizes[0])
    seconds.append(time.perf_counter() - started)
    k = 1
    while sizes[-1]:
        if len(sizes) > most:
            raise RoundLimit(f"more than {most} rounds")
        started = time.perf_counter()
        if k > 1:
            many = hop.ahead(delta, plan.env, k, plan.key[0]).groupBy(*defn.columns).agg(F.min(ROUND).alias(ROUND)).filter(F.col(ROUND) > 0)
            frame, found = counted(levels.unknown(many), **{f"r{j}": F.count_if(F.col(ROUND) == j) for j in range(1, k + 1)})
            new = [found[f"r{j}"] for j in range(1, k + 1)]
            sizes += new[: new.index(0) + 1] if 0 in new else new
            delta = frame.filter(F.col(ROUND) == k).drop(ROUND)
            levels.add(frame.drop(ROUND), found["rows"])
        else:
            step = candidates(defn, plan, levels, delta, repeats)
            if step is None:
                break
            delta, found = counted(levels.unknown(step))
            sizes.append(found["rows"])
            levels.add(delta, found["rows"])
        seconds.append(time.perf_counter() - started)
        steady = hop and len(sizes) > 1 and sizes[-1] <= AHEAD_GROWTH * sizes[-2]
        k = max(1, min(2 * k, ahead, most + 1 - len(sizes), math.isqrt(2 * AHEAD_ROWS // max(1, sizes[-1])))) if steady else 1
    return FixpointResult(levels.total(first), len(sizes), sizes, seconds)


def _chained(defn: Definition) -> bool:
    """Whether some step joins several relations, so that distinct steps in between may move its rows."""
    return any(len(c.positive) > 2 for d in (defn, *defn.locals) for c in d.body)


def _same_value_twice(defn: Definition) -> bool:
    """Whether a base conjunction gives one variable to several head columns."""
    return any(c.op == "=" and isinstance(c.left, Var) and isinstance(c.right, Var) for b in defn.split()[0] for c in b.compares)


def pivoted(defn: Definition, env: Mapping[str, DataFrame], pivot: str | None = None, partitions: int | None = None, most: int = MOST_ROUNDS) -> FixpointResult:
    """Semi-naive rounds over state hashed by a column that no step changes, also where static relations have to be met by a shuffle.

    Where the pivot cannot be had, this is seminaive().
    """
    pivots = pivot_columns(defn)
    return seminaive(defn, env, most, pivot or (pivots[0] if pivots else None), partitions)


def naive(defn: Definition, env: Mapping[str, DataFrame], most: int = MOST_ROUNDS) -> FixpointResult:
    """Recomputes the whole relation from the whole previous one until its size stays; over many rows in chains, the relation is kept as stretches."""
    seed = apply(defn, env, None, True)
    early = many_rows(defn, env)
    line = single_hop(defn) if early and defn.recursive else None
    if line and chains.moving(line):
        with fixed_plans(seed.sparkSession):
            found = chains.naive_along(line, env, seed, most)
        if found is not None:
            if found.rounds > most:
                raise RoundLimit(f"more than {most} rounds")
            return found
    total = materialised(seed.distinct())
    sizes, seconds = [rows_of(total)], [0.0]
    while len(sizes) <= most:
        started = time.perf_counter()
        before = total
        total = materialised(apply(defn, env, before, True, early).distinct())
        discard(before)
        sizes.append(rows_of(total))
        seconds.append(time.perf_counter() - started)
        if sizes[-1] == sizes[-2]:
            return FixpointResult(total, len(sizes), sizes, seconds)
    raise RoundLimit(f"more than {most} rounds")


def general(definitions: list[Definition], env: Mapping[str, DataFrame], most: int = MOST_ROUNDS) -> dict[str, FixpointResult]:
    """Semi-naive evaluation of a component whose rules may have several own literals: each takes the delta in turn, the others the total."""
    names = [d.head for d in definitions]
    by = {d.head: d for d in definitions}
    frames = dict(env)
    spark = next(iter(env.values())).sparkSession
    with fixed_plans(spark):
        n = int(spark.conf.get("spark.sql.shuffle.partitions"))
        levels = {d.head: Levels(list(d.columns), list(d.columns), n, d.padded) for d in definitions}
        first: dict[str, DataFrame] = {}
        delta: dict[str, DataFrame] = {}
        sizes: dict[str, list[int]] = {name: [] for name in names}

        def take(name: str, new: DataFrame) -> None:
            frame, found = counted(levels[name].unknown(levels[name].placed(new).distinct()))
            first.setdefault(name, frame)
            sizes[name].append(found["rows"])
            levels[name].add(frame, found["rows"])
            delta[name] = frame.select([F.col(f"`{c}`") for c in by[name].columns])

        for d in definitions:
            base = [conjunction(c, d.columns, frames, d.types) for c in d.body if not c.uses(names)]
            if base:
                take(d.head, union_all(base))
        for _ in range(most):
            now = {name: f for name, f in delta.items() if sizes[name] and sizes[name][-1]}
            if not now:
                return {name: FixpointResult(levels[name].total(first[name]), len(sizes[name]), sizes[name]) for name in first}
            total = {name: levels[name].total(first[name]) for name in first}
            found: dict[str, DataFrame] = {}
            for d in definitions:
                parts = []
                for c in d.body:
                    own = c.uses(names)
                    for k, a in enumerate(own):
                        others = [x.pred for j, x in enumerate(own) if j != k]
                        if a.pred in now and all(o in total for o in others):
                            parts.append(conjunction(_marked(c, a), d.columns, frames | total | {f"_delta_{a.pred}": now[a.pred]}, d.types, f"_delta_{a.pred}"))
                if parts:
                    found[d.head] = union_all(parts)
            delta = {}
            for name in names:
                if name in found:
                    take(name, found[name])
                elif sizes[name]:
                    sizes[name].append(0)
    raise RoundLimit(f"more than {most} rounds")


def _marked(c: Conjunction, own: Atom) -> Conjunction:
    """The conjunction with one own literal reading the delta."""
    at = next(k for k, a in enumerate(c.atoms) if a is own)
    return Conjunction(c.atoms[:at] + (Atom(f"_delta_{own.pred}", own.args),) + c.atoms[at + 1 :], c.compares)


def lattice(seed: DataFrame, step: Callable[[DataFrame], DataFrame], keys: list[str], value: str, best: str = "min", most: int = MOST_ROUNDS) -> FixpointResult:
    """One best value a key: a round derives candidates from the rows that improved and keeps those that improve again."""
    choose = {"min": F.min, "max": F.max}[best]
    aggregated = lambda df: df.groupBy(*keys).agg(choose(value).alias(value))
    total = delta = materialised(aggregated(seed))
    sizes = [rows_of(delta)]
    while sizes[-1]:
        if len(sizes) > most:
            raise RoundLimit(f"more than {most} rounds")
        old = total.select(*keys, F.col(value).alias("_old"))
        new = aggregated(step(delta)).join(old, keys, "left")
        better = F.col(value) < F.col("_old") if best == "min" else F.col(value) > F.col("_old")
        delta = materialised(new.filter(F.col("_old").isNull() | better).select(*keys, value))
        sizes.append(rows_of(delta))
        if sizes[-1]:
            before = total
            total = materialised(aggregated(before.unionByName(delta)))
            discard(before)
    return FixpointResult(total, len(sizes), sizes)
