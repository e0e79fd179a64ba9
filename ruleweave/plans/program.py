"""A program as a sequence of evaluated definitions: text in, DataFrames out."""

from __future__ import annotations

import time
from collections.abc import Callable, Mapping
from dataclasses import dataclass, field

from pyspark.sql import DataFrame

from ruleweave.ir.lower import to_ir
from ruleweave.ir.nodes import Definition, Group, check_normal, check_scopes
from ruleweave.ir.primary import normal
from ruleweave.lang import checks
from ruleweave.lang.ast import Const, Program, Var, variables
from ruleweave.lang.normalize import canonical
from ruleweave.lang.parser import parse
from ruleweave.operators import fixpoint
from ruleweave.operators.state import FixpointResult, all_materialised, fixed_plans, materialised
from ruleweave.plans.conjunction import apply, pruned
from ruleweave.plans.layout import EARLY_ROWS, by_probe, probes
from ruleweave.plans.single import distinct_rows


@dataclass
class Compiled:
    """A checked program in normal form, with the route of each component."""

    program: Program
    rules: list[Definition | Group]
    definitions: list[Definition]
    routes: dict[tuple[str, ...], str]
    seconds: float


def compile_program(text: str | Program, form: str = "lifted") -> Compiled:
    """Parses, normalizes, checks and lowers; form is 'lifted' or 'tagged' (see ir.primary.normal)."""
    started = time.perf_counter()
    program = canonical(parse(text) if isinstance(text, str) else text)
    checks.arities(program)
    checks.safe(program)
    checks.stratified(program)
    routes = checks.routes(program)
    rules = to_ir(program)
    definitions: list[Definition] = []
    for r in rules:
        names = [b.head for b in r.branches] if isinstance(r, Group) else [r.head]
        if any(routes.get(c) == "general" for c in routes if set(c) == set(names)):
            definitions += list(r.branches) if isinstance(r, Group) else [r]
        else:
            ready = normal([r], form)
            check_normal(ready)
            definitions += ready
    check_scopes([d for d in definitions])
    return Compiled(program, rules, definitions, routes, time.perf_counter() - started)


@dataclass
class Evaluation:
    """Relations by name, and the fixpoint result of each recursive definition."""

    relations: dict[str, DataFrame]
    fixpoints: dict[str, FixpointResult] = field(default_factory=dict)


def evaluate(compiled: Compiled, facts: Mapping[str, DataFrame], strategy: Callable[..., FixpointResult] = fixpoint.seminaive) -> Evaluation:
    """All relations of a program over input relations."""
    out = Evaluation(dict(facts))
    general = [c for c, route in compiled.routes.items() if route == "general"]
    done: set[str] = set()
    beside: dict[Definition, DataFrame] = {}
    hidden: list[str] = []  # relations of which only the rows are known that others read
    for d in compiled.definitions:
        if d.head in done:
            continue
        component = next((c for c in general if d.head in c), None)
        if component:
            found = fixpoint.general([x for x in compiled.definitions if x.head in component], out.relations)
            out.relations.update({n: r.total for n, r in found.items()})
            out.fixpoints.update(found)
            done |= set(component)
        elif d.recursive:
            wanted = _read_of(compiled, d) if strategy is fixpoint.seminaive else None
            result = strategy(d, prepared(d, out.relations, facts), **({} if wanted is None else {"wanted": wanted}))
            out.relations[d.head] = result.total
            out.fixpoints[d.head] = result
            hidden += [d.head] if result.partial else []
            beside.update({x: result.locals[x.head] for x in pruned(d).locals if x.head in result.locals})
        elif d in beside:
            out.relations[d.head] = beside[d]
        elif _part_of_set(d, out.fixpoints):
            out.relations[d.head] = apply(d, out.relations, None, True)
        else:
            if any(sum(out.fixpoints[a.pred].delta_sizes) > EARLY_ROWS for c in d.body for a in c.atoms if a.pred in out.fixpoints):
                # inputs of a known size can be broadcast, so that the large relation stays where it is
                fresh = [p for p in dict.fromkeys(a.pred for c in d.body for a in c.atoms) if p in facts and out.relations[p] is facts[p]]
                out.relations.update(zip(fresh, all_materialised(facts[p] for p in fresh), strict=True))
            found = distinct_rows(d, out.relations)
            out.relations[d.head] = materialised(found) if _used_later(compiled, d) else found
    for name in hidden:
        del out.relations[name]
    return out


def _read_of(compiled: Compiled, d: Definition) -> list[tuple[str, dict[str, int]]] | None:
    """Which rows of a recursive relation and its locals the program's other definitions read; None if it is an output itself or whole rows of it are read."""
    if not compiled.program.outputs or d.head in compiled.program.outputs:
        return None
    along = [] if d.padded else [x for x in pruned(d).locals if all(c.uses(d.scope) for c in x.body)]  # come out of the rounds
    read: list[tuple[str, dict[str, int]]] = []
    for x in compiled.definitions:
        if x in along:
            read.append((x.head, {}))
        elif x.head != d.head:
            for c in (c for y in (x, *x.locals) for c in y.body):
                for a in c.uses([d.head]):
                    fixed = {v.left.name: v.right.value for v in c.compares if v.op == "=" and isinstance(v.left, Var) and isinstance(v.right, Const)}
                    values = {col: fixed[v.name] for col, v in zip(d.columns, a.args, strict=True) if isinstance(v, Var) and v.name in fixed}
                    if not values:
                        return None
                    read.append((d.head, values))
    return read


def prepared(d: Definition, relations: dict[str, DataFrame], facts: Mapping[str, DataFrame]) -> dict[str, DataFrame]:
    """The relations, with the inputs that the definition's rounds read evaluated once, hashed by the columns that rounds probe."""
    fresh = {p: at for p, at in probes(d).items() if p in facts and relations.get(p) is facts[p]}
    if fresh:
        spark = next(iter(facts.values())).sparkSession
        n = int(spark.conf.get("spark.sql.shuffle.partitions"))
        with fixed_plans(spark):
            relations.update(zip(fresh, all_materialised(by_probe(facts[p], at, n) for p, at in fresh.items()), strict=True))
    return relations


def _part_of_set(d: Definition, fixpoints: Mapping[str, FixpointResult]) -> bool:
    """Whether the definition is some rows of a recursive relation, of which it drops constant columns only: its rows are distinct."""
    if len(d.body) != 1 or len(d.body[0].atoms) != 1 or d.locals or d.padded:
        return False
    a, fixed = d.body[0].atoms[0], {c.left.name for c in d.body[0].compares if c.op == "=" and isinstance(c.left, Var) and isinstance(c.right, Const)}
    return a.pred in fixpoints and not a.negated and set(variables(a)) <= set(d.columns) | fixed


def _used_later(compiled: Compiled, d: Definition) -> bool:
    """A stratum that others read is evaluated once; a local of the same name in another definition is not this one."""
    return any(c.uses([d.head]) for x in compiled.definitions if d.head not in x.scope for y in (x, *x.locals) for c in y.body)
