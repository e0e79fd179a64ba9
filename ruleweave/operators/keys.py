"""Functional dependencies and keys of input relations, exact for the data, and their use.

Sets of columns are taken level by level; supersets of a key are not asked. A set is looked at with a sketch first and left out only if
the sketch's count is below the rows by more than five times its standard error; what remains is proven or refuted by a grouped
pass that ends at the first repeated value. Dependencies compare exact counts: a set determines a column if adding it makes no more.
"""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleweave.ir.nodes import Definition


ERROR, SKETCHES, TOGETHER = 0.02, 48, 4


@dataclass(frozen=True)
class FD:
    left: tuple[str, ...]
    right: str


class KeyViolation(ValueError):
    """Rows that repeat a key."""


def _distinct_counts(df: DataFrame, sets: list[tuple[str, ...]]) -> dict[tuple[str, ...], int]:
    """Exact numbers of different values, one grouped pass a set, side by side: nothing is expanded."""
    return dict(zip(sets, _together(lambda s: df.select(*s).distinct().count(), sets), strict=True))


def _together(run, sets: list[tuple[str, ...]]) -> list:
    with ThreadPoolExecutor(TOGETHER) as pool:
        return list(pool.map(run, sets))


def keys(df: DataFrame, most: int | None = None) -> list[tuple[str, ...]]:
    """Minimal sets of columns whose values are all different, smallest first; most: the largest size asked, all sizes by default."""
    n = df.count()
    found: list[tuple[str, ...]] = []
    for size in range(1, (most or len(df.columns)) + 1):
        sets = [s for s in combinations(df.columns, size) if not any(set(k) <= set(s) for k in found)]
        likely = []
        for a in range(0, len(sets), SKETCHES):
            part = sets[a : a + SKETCHES]
            rough = df.agg(*[F.approx_count_distinct(F.struct(*[F.col(c) for c in s]), ERROR).alias(f"n{k}") for k, s in enumerate(part)]).first()
            likely += [s for k, s in enumerate(part) if rough[k] >= n * (1 - 5 * ERROR)]
        found += [s for s, unique in zip(likely, _together(lambda s: is_key(df, s), likely), strict=True) if unique]
        if not sets:
            break
    return found


def is_key(df: DataFrame, columns: tuple[str, ...]) -> bool:
    """Whether no value of the columns is there twice; ends at the first that is."""
    return df.groupBy(*columns).count().filter("count > 1").limit(1).isEmpty()


def discover(df: DataFrame, most: int | None = None) -> list[FD]:
    """Minimal non-trivial functional dependencies with at most `most` columns on the left."""
    columns = df.columns
    most = min(most or len(columns) - 1, len(columns) - 1)
    counts: dict[tuple[str, ...], int] = {}
    found: list[FD] = []
    counts.update(_distinct_counts(df, [(c,) for c in columns]))
    for size in range(1, most + 1):
        counts.update(_distinct_counts(df, [s for s in combinations(columns, size + 1) if s not in counts]))
        for left in combinations(columns, size):
            for right in columns:
                if right in left or any(f.right == right and set(f.left) <= set(left) for f in found):
                    continue
                if counts[left] == counts[tuple(c for c in columns if c in (*left, right))]:
                    found.append(FD(left, right))
    return found


def recursive_columns(definitions: list[Definition], schema: dict[str, tuple[str, ...]]) -> dict[str, set[str]]:
    """For each input relation, its columns that a recursive definition refers to."""
    out: dict[str, set[str]] = {}
    for d in definitions:
        if not d.recursive:
            continue
        for x in (d, *d.locals):
            for c in x.body:
                for a in c.atoms:
                    if a.pred in schema:
                        out.setdefault(a.pred, set()).update(col for col, v in zip(schema[a.pred], a.args, strict=True) if not v.name.startswith("_w"))
    return out


def pick_key(found: list[tuple[str, ...]], used: set[str]) -> tuple[str, ...] | None:
    """The smallest key whose columns recursion uses; the first found of equal size."""
    fit = [k for k in found if set(k) <= used]
    return min(fit, key=len) if fit else None


def load_checked(df: DataFrame, key: tuple[str, ...]) -> DataFrame:
    """The relation, laid out by its key; KeyViolation if rows repeat it."""
    twice = df.groupBy(*key).count().filter("count > 1").limit(1).collect()
    if twice:
        raise KeyViolation(f"{dict(zip(key, twice[0], strict=False))} occurs {twice[0]['count']} times")
    return load_assumed(df, key)


def load_assumed(df: DataFrame, key: tuple[str, ...]) -> DataFrame:
    """The relation, laid out by its key, unchecked: hashed and sorted once, so that rounds don't move it again."""
    return df.repartition(*key).sortWithinPartitions(*key).persist()
