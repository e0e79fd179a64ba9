"""Where rows stand while a definition's rounds run: by which columns its state is hashed and how the relations that it reads are laid out.

A static relation is hashed and sorted by the columns that a round probes, once. Is it small (its counted rows fit BROADCAST_BYTES), it is
broadcast instead. If all are, state is hashed by a column that no step changes, and a round moves nothing. Otherwise state is hashed by the
columns that meet the static relations, and a round moves its candidates once.
"""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleweave.ir.inline import pivot_columns
from ruleweave.ir.nodes import Conjunction, Definition
from ruleweave.lang.ast import Var, variables
from ruleweave.operators.state import materialised, rows_of

BROADCAST_BYTES = 64 << 20
EARLY_ROWS = 200_000  # from so many static rows on, a round makes what it joins distinct between joins


def _probes(c: Conjunction, scope: list[str]) -> dict[str, tuple[int, ...]]:
    """For each static literal of a step, the places of the arguments that are bound when it is joined, the delta leading."""
    own = c.uses(scope)
    bound = {v for a in own for v in variables(a)}
    rest = [a for a in c.positive if a not in own]
    out: dict[str, tuple[int, ...]] = {}
    while rest:
        pick = max(rest, key=lambda a: len(set(variables(a)) & bound))
        rest.remove(pick)
        out.setdefault(pick.pred, tuple(k for k, v in enumerate(pick.args) if isinstance(v, Var) and v.name in bound))
        bound |= set(variables(pick))
    for a in c.atoms:
        if a.negated:
            out.setdefault(a.pred, tuple(k for k, v in enumerate(a.args) if isinstance(v, Var) and v.name in bound))
    return out


def probes(defn: Definition) -> dict[str, tuple[int, ...]]:
    """Static relations that the definition's rounds read, with the places of the columns they are probed by."""
    out: dict[str, tuple[int, ...]] = {}
    for d in (defn, *defn.locals):
        for c in d.body:
            if c.uses(defn.scope):
                for pred, at in _probes(c, defn.scope).items():
                    out.setdefault(pred, at)
    return {p: at for p, at in out.items() if p not in defn.scope}


def by_probe(df: DataFrame, at: tuple[int, ...], partitions: int) -> DataFrame:
    """The relation hashed and sorted by the columns at these places (all, where a round probes by none)."""
    columns = [F.col(f"`{df.columns[k]}`") for k in at] or [F.col(f"`{c}`") for c in df.columns]
    return df.repartition(partitions, *columns).sortWithinPartitions(*columns)


def small(df: DataFrame) -> bool:
    """Is a materialised relation small enough to be on every executor."""
    rows = rows_of(df)
    width = sum(8 if t in ("bigint", "int", "double", "date", "timestamp", "boolean") else 64 for _, t in df.dtypes) + 16
    return rows is not None and rows * width <= BROADCAST_BYTES


def many_rows(defn: Definition, env: Mapping[str, DataFrame]) -> bool:
    """Do the materialised relations that the definition reads hold so many rows that distinct steps between joins pay."""
    read = {a.pred for d in (defn, *defn.locals) for c in d.body for a in c.atoms}
    return sum(rows_of(env[p]) or 0 for p in read if p in env) > EARLY_ROWS


@dataclass(frozen=True)
class Layout:
    """The relations as rounds read them, whether all of them are broadcast, and the columns by which state is hashed."""

    env: dict[str, DataFrame]
    broadcast: bool
    key: tuple[str, ...]
    stays: bool  # candidates come out where their state is
    early: bool = False  # distinct steps between joins


def layout(defn: Definition, env: Mapping[str, DataFrame], partitions: int, pivot: str | None = None, keyed: Mapping[str, list[tuple[str, ...]]] | None = None) -> Layout:
    read = probes(defn)
    laid = dict(env)
    for pred, at in read.items():
        if pred in env and rows_of(env[pred]) is None:
            laid[pred] = materialised(by_probe(env[pred], at, partitions))
    little = {p for p in read if p in laid and small(laid[p])}
    early = many_rows(defn, laid)
    everywhere = all(p in little for p in read if p in laid)
    for pred, at in read.items():
        if pred in little:
            laid[pred] = F.broadcast(laid[pred])
        elif pred in laid:
            # by a key each probe meets one row, so a hash table of that side is as small as it can be
            unique = any(set(k) <= {env[pred].columns[i] for i in at} for k in (keyed or {}).get(pred, ()))
            laid[pred] = laid[pred].hint("shuffle_hash" if unique else "merge")
    pivots = pivot_columns(defn)
    if pivot is not None and pivot not in pivots:
        raise ValueError(f"{pivot} changes from round to round; unchanged are {pivots}")
    if pivot or pivots and everywhere:
        return Layout(laid, everywhere, (pivot or pivots[0],), everywhere, early)
    return Layout(laid, everywhere, meeting(defn), False, early)


def meeting(defn: Definition) -> tuple[str, ...]:
    """Own columns that every step uses to meet a static relation; all columns if there are none."""
    common = None
    for d in (defn, *defn.locals):
        for c in d.body:
            for own in c.uses([defn.head]):
                others = {v for a in c.positive if a.pred not in defn.scope for v in variables(a)}
                here = {col for col, v in zip(defn.columns, own.args, strict=True) if isinstance(v, Var) and v.name in others}
                common = here if common is None else common & here
    return tuple(c for c in defn.columns if c in (common or ())) or defn.columns
