"""A conjunction as one DataFrame: joins by shared variables, filters, bindings and anti joins; Catalyst does the rest."""

from __future__ import annotations

import warnings
from collections.abc import Callable, Mapping
from dataclasses import replace
from functools import cache

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ruleweave.ir.nodes import Conjunction, Definition
from ruleweave.lang.ast import Arith, Atom, Compare, Const, Term, Var, variables

# Column types of the surface language.
TYPES = {"number": "bigint", "unsigned": "decimal(20,0)", "float": "double", "symbol": "string", "decimal": "decimal(18,4)", "timestamp": "timestamp", "date": "date"}


def spark_type(kind: str) -> str:
    return TYPES.get(kind, "bigint")


def expression(term: Term, inner: Callable[[Term], Column] | None = None) -> Column:
    """A term as a column; inner gives the columns of its parts, by default those named like its variables."""
    inner = inner or expression
    if isinstance(term, Var):
        return F.col(f"`{term.name}`")
    if isinstance(term, Const):
        return F.lit(term.value).cast("bigint") if isinstance(term.value, int) else F.lit(term.value)
    left, right = inner(term.left), inner(term.right)
    if term.op == "/":
        return F.try_divide(left - left % right, right).cast("bigint")
    return {"+": left.__add__, "-": left.__sub__, "*": left.__mul__, "%": left.__mod__}[term.op](right)


def condition(c: Compare, value: Callable[[Term], Column] = expression) -> Column:
    left, right = value(c.left), value(c.right)
    return {"=": left == right, "!=": left != right, "<": left < right, "<=": left <= right, ">": left > right, ">=": left >= right}[c.op]


def _read(atom: Atom, env: Mapping[str, DataFrame], wanted: set[str]) -> DataFrame:
    """An atom's relation with its columns named by variables, those nobody wants dropped."""
    df = env[atom.pred]
    return df.select([F.col(f"`{c}`").alias(a.name) for c, a in zip(df.columns, atom.args, strict=True) if isinstance(a, Var) and a.name in wanted])


def conjunction(conj: Conjunction, columns: tuple[str, ...], env: Mapping[str, DataFrame], types: tuple[str, ...] = (), first: str | None = None, early: bool = False) -> DataFrame:
    """The conjunction's tuples over the given columns, possibly repeated (set semantics is up to the caller).

    The atom of `first` (the delta) leads; then comes whichever atom shares most variables. An atom that only tests becomes a semi
    join. Variables are dropped as soon as nothing needs them; with early, what is left is made distinct before a further atom can multiply it.
    """
    kinds = dict(zip(columns, types or ("number",) * len(columns), strict=True))
    atoms, compares, negated = list(conj.positive), list(conj.compares), [a for a in conj.atoms if a.negated]
    bound: set[str] = set()
    acc: DataFrame | None = None

    def needed() -> set[str]:
        return set(columns) | {v for x in (*atoms, *compares, *negated) for v in variables(x)}

    def settle() -> None:
        """Applies the comparisons whose variables are bound and binds what an equality determines."""
        nonlocal acc
        again = True
        while again:
            again = False
            for c in list(compares):
                loose = set(variables(c)) - bound
                if not loose and acc is not None:
                    acc = acc.filter(condition(c))
                elif c.op == "=" and len(loose) == 1 and acc is not None and any(isinstance(a, Var) and {a.name} == loose and not set(variables(b)) & loose for a, b in ((c.left, c.right), (c.right, c.left))):
                    name = next(iter(loose))
                    source = c.right if isinstance(c.left, Var) and c.left.name == name else c.left
                    value = expression(source)
                    if isinstance(source, Const) and source.value is None:
                        value = F.lit(None).cast(spark_type(kinds.get(name, "number")))
                    acc = acc.withColumn(name, value)
                    bound.add(name)
                else:
                    continue
                compares.remove(c)
                again = True

    while atoms:
        if acc is None:
            pick = next((a for a in atoms if a.pred == first), atoms[0])
        else:
            pick = max(atoms, key=lambda a: len(set(variables(a)) & bound))
        atoms.remove(pick)
        own = set(variables(pick))
        wanted = {v for v in own if v in needed() or v in bound}
        right = _read(pick, env, wanted)
        if acc is None:
            acc, bound = right if right.columns else right.select(F.lit(1).alias("_one")), set(right.columns)
        else:
            shared = sorted(own & bound)
            if not shared:
                if right.columns:
                    warnings.warn(f"{pick.pred} shares no variable with the literals before it: a cross product", stacklevel=2)
                acc = acc.crossJoin(right) if right.columns else acc
            elif wanted <= bound:
                acc = acc.join(right, shared, "left_semi")
            else:
                acc = acc.join(right, shared)
            bound |= wanted
        settle()
        rest = needed()
        spare = [c for c in acc.columns if c not in rest and c != "_one"]
        if spare and len(spare) < len(acc.columns):
            acc = acc.drop(*spare)
            bound -= set(spare)
            if early and any(set(variables(a)) & rest - bound for a in atoms):
                acc = acc.distinct()
    if acc is None:  # a stated fact: one row of constants
        acc = SparkSession.active().range(1).select(F.lit(1).alias("_one"))
    settle()
    for a in negated:
        shared = sorted(set(variables(a)) & bound)
        right = _read(a, env, set(shared))
        acc = acc.join(right, shared, "left_anti") if shared else acc.join(right.select(F.lit(1).alias("_x")).limit(1), F.lit(True), "left_anti")
    return acc.select([F.col(f"`{c}`") for c in columns])


@cache
def pruned(defn: Definition) -> Definition:
    """The definition with its locals cut down to the columns that somebody reads."""
    readers, kept = [(defn.body, set(defn.columns))], {}
    for d in reversed(defn.locals):
        want: set[str] = set()
        for body, heads in readers:
            for c in body:
                for a in c.uses([d.head]):
                    others = heads | {v for x in (*c.atoms, *c.compares) if x is not a for v in variables(x)}
                    names = [v for t in a.args for v in variables(t)]
                    want |= {col for col, v in zip(d.columns, a.args, strict=True) if not isinstance(v, Var) or v.name in others or names.count(v.name) > 1}
        kept[d.head] = [k for k, c in enumerate(d.columns) if c in want] or [0]
        readers.append((d.body, {d.columns[k] for k in kept[d.head]}))

    def cut(body: tuple[Conjunction, ...]) -> tuple[Conjunction, ...]:
        return tuple(Conjunction(tuple(replace(a, args=tuple(a.args[k] for k in kept[a.pred])) if a.pred in kept else a for a in c.atoms), c.compares) for c in body)

    pick = lambda values, d: tuple(values[k] for k in kept[d.head]) if values else values
    return replace(defn, body=cut(defn.body), locals=tuple(replace(d, columns=pick(d.columns, d), types=pick(d.types, d), body=cut(d.body)) for d in defn.locals))


def apply(defn: Definition, env: Mapping[str, DataFrame], own: DataFrame | None, constant: bool, early: bool = False) -> DataFrame | None:
    """What a definition derives from `own` tuples of itself, through its locals; with constant, also what needs none.

    Linear definitions make this additive: apply(own1 + own2) = apply(own1) + apply(own2). None stands for nothing.
    """
    defn = pruned(defn)
    frames: dict[str, DataFrame] = dict(env)
    scope = defn.scope
    for name in scope:
        frames.pop(name, None)
    if own is not None:
        frames[defn.head] = own
    out = None
    for d in (*defn.locals, defn):
        parts = []
        for c in d.body:
            used = c.uses(scope)
            if not used and constant or used and used[0].pred in frames:
                parts.append(conjunction(c, d.columns, frames, d.types, used[0].pred if used else None, early))
        whole = None
        for p in parts:
            whole = p if whole is None else whole.unionByName(p)
        if d is defn:
            out = whole
        elif whole is not None:
            frames[d.head] = whole
    return out
