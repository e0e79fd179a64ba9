"""Relations without recursion whose rows are so many that making them distinct costs more than deriving them.

Each conjunction is cut in two at a head column: the literals that hold the column, and the rest, both projected to what the other side or
the head needs and made distinct. A value of the column that stands in one row of the first sides only gives no row twice. Rows of the other
values are made distinct as usual.
"""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleweave.ir.nodes import Conjunction, Definition
from ruleweave.lang.ast import Atom, Var, variables
from ruleweave.operators.state import all_materialised, materialised, rows_of, union_all
from ruleweave.plans.conjunction import apply, conjunction
from ruleweave.plans.layout import many_rows, small

Side = tuple[list[Atom], tuple[str, ...]]


def sides(conj: Conjunction, column: str, columns: tuple[str, ...]) -> tuple[Side, Side] | None:
    """The literals with the column and those that only test them, and the connected rest, with the variables that each side keeps."""
    if conj.compares or len(conj.positive) < len(conj.atoms) or not all(isinstance(v, Var) for a in conj.atoms for v in a.args):
        return None
    left = [a for a in conj.atoms if column in variables(a)]
    bound = {v for a in left for v in variables(a)}
    rest = []
    for a in (a for a in conj.atoms if a not in left):
        loose = set(variables(a)) - bound
        alone = not loose & ({v for x in conj.atoms if x is not a for v in variables(x)} | set(columns))
        (left if alone and set(variables(a)) & bound else rest).append(a)
    if not left:
        return None
    met = {v for a in rest for v in variables(a)}
    linked, todo = set(variables(rest[0])) if rest else set(), rest[1:]
    while todo:
        near = [a for a in todo if set(variables(a)) & linked]
        if not near:
            return None
        linked |= {v for a in near for v in variables(a)}
        todo = [a for a in todo if a not in near]
    if rest and not bound & met:
        return None
    on = bound & met
    keep = lambda own: tuple(sorted(on | set(columns) & own))
    return (left, keep(bound)), (rest, keep(met))


def distinct_rows(defn: Definition, env: Mapping[str, DataFrame]) -> DataFrame:
    """What a definition without recursion derives, each row once."""
    many = many_rows(defn, env)
    if many:  # few values may meet many rows: where one side is small, no join is dealt out by them
        env = {p: F.broadcast(f) if small(f) else f for p, f in env.items()}
    if many and not defn.padded and not defn.locals:
        for column in defn.columns:
            cut = [sides(c, column, defn.columns) for c in defn.body]
            if all(cut) and any(rest for _, (rest, _) in cut):
                found = _by_column(defn, env, column, cut)
                if found is not None:
                    return found
    return apply(defn, env, None, True, many).distinct()


def _by_column(defn: Definition, env: Mapping[str, DataFrame], column: str, cut: list[tuple[Side, Side]]) -> DataFrame | None:
    """None if fewer than half of the first sides' rows stand alone with their value."""
    side = lambda s: conjunction(Conjunction(tuple(s[0])), s[1], env, early=True).distinct()
    lefts = all_materialised(side(left) for left, _ in cut)
    held = materialised(union_all([f.select(column) for f in lefts]).groupBy(column).count())
    alone = held.filter((F.col("count") == 1) & F.col(column).isNotNull()).count()
    if 2 * alone < sum(rows_of(f) for f in lefts):
        return None
    repeated = held.filter("count > 1").select(column, F.lit(True).alias("_rw_many"))
    n = int(held.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    once, several = [], []
    for f, (_, rest) in zip(lefts, cut, strict=True):
        marked = f.join(repeated, column, "left").withColumn("_rw_many", F.col("_rw_many").isNotNull() | F.col(column).isNull())
        other = materialised(side(rest)) if rest[0] else None
        for single, into in ((True, once), (False, several)):
            rows = marked.filter(~F.col("_rw_many") if single else F.col("_rw_many")).drop("_rw_many")
            if other is not None:
                on = [c for c in f.columns if c in other.columns]
                # a given number of partitions: by its input alone a join that multiplies rows would be coalesced to too few
                rows = rows.repartition(n, *on).join(F.broadcast(other) if small(other) else other.repartition(n, *on), on)
            into.append(rows.select(*defn.columns))
    return union_all([*once, union_all(several).distinct()])
