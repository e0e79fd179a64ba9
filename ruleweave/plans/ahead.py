"""Several rounds in one job, for definitions whose step extends a tuple along one static relation.

Each hop is an outer join that keeps a tuple beside its successors, so nothing is computed twice, and marks in which round a tuple came up.
That pays where rounds are many and small: a job then costs its start, not its rows.
"""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleweave.ir.inline import inline_locals
from ruleweave.ir.nodes import Conjunction, Definition
from ruleweave.lang.ast import Atom, Const, Var, variables

ROUND = "_rw_round"


class Hop:
    """The one step of a definition: own literal, static literal, negated literals and comparisons."""

    def __init__(self, defn: Definition, step: Conjunction, own: Atom, static: Atom):
        self.columns, self.head = defn.columns, defn.head
        self.own, self.static = own, static
        self.negated = [a for a in step.atoms if a.negated]
        bound = {*variables(own), *variables(static)}
        self.binds = {c.left.name: c.right for c in step.compares if c.op == "=" and isinstance(c.left, Var) and c.left.name not in bound}
        self.compares = [c for c in step.compares if not (isinstance(c.left, Var) and c.left.name in self.binds)]
        self.reads = {static.pred, *(a.pred for a in self.negated)}
        known = bound | set(self.binds)
        self.fits = set(defn.columns) <= known and all(set(variables(x)) <= bound for x in (*self.compares, *self.binds.values()))
        self.fits &= not any(isinstance(x, Const) and x.value is None for x in self.binds.values())

    def ahead(self, delta: DataFrame, env: Mapping[str, DataFrame], rounds: int, pivot: str) -> DataFrame:
        """The tuples of delta as round 0 and what the next `rounds` rounds derive from them, with repetitions; where they are hashed by
        the pivot, they stay so.

        The hops are one SQL text: a plan that is analysed once, where a chain of DataFrame calls would be analysed at every call.
        """
        kinds = [t for _, t in delta.select(*[F.col(f"`{c}`") for c in self.columns]).dtypes]
        text = f"select {', '.join(f'`{c}` c{i}' for i, c in enumerate(self.columns))}, 0 rnd from {{rw_delta}}"
        bound = {"rw_delta": delta, f"rw_{self.static.pred}": env[self.static.pred]}
        for k in range(rounds):
            text = self._hop(text, env, kinds, k, self.columns.index(pivot))
        for a in self.negated:
            bound[f"rw_{a.pred}"] = env[a.pred]
        names = ", ".join(f"c{i} `{c}`" for i, c in enumerate(self.columns))
        return delta.sparkSession.sql(f"select {names}, rnd {ROUND} from ({text})", **bound)

    def _hop(self, text: str, env: Mapping[str, DataFrame], kinds: list[str], k: int, pivot: int) -> str:
        static = dict(zip(env[self.static.pred].columns, (a.name for a in self.static.args), strict=True))
        values = {a.name: f"o.c{i}" for i, a in enumerate(self.own.args)}
        on = [f"o.rnd = {k}", *(f"s.`{c}` = {values[v]}" for c, v in static.items() if v in values)]
        met = f"s.`{next(iter(static))}` is not null"
        for c, v in static.items():
            values.setdefault(v, f"s.`{c}`")
        holds = [met, *(f"{self._text(c.left, values)} {'<>' if c.op == '!=' else c.op} {self._text(c.right, values)}" for c in self.compares)]
        values |= {v: self._text(term, values) for v, term in self.binds.items()}
        joins = f"left join {{rw_{self.static.pred}}} s on {' and '.join(on)}"
        for j, a in enumerate(self.negated):
            columns = env[a.pred].columns
            shared = [(c, v.name) for c, v in zip(columns, a.args, strict=True) if isinstance(v, Var) and v.name in values]
            few = "distinct " if len(shared) < len(columns) else ""
            joins += f" left join (select {few}{', '.join(f'`{c}`' for c, _ in shared)}, true there from {{rw_{a.pred}}}) n{j} on {met}" + "".join(f" and n{j}.`{c}` = {values[v]}" for c, v in shared)
            holds.append(f"n{j}.there is null")
        moving = [i for i in range(len(self.columns)) if i != pivot]
        packed = lambda values, rnd: f"named_struct({', '.join([f"'c{i}', {values[i]}" for i in moving] + [f"'rnd', {rnd}"])})"
        stay = packed({i: f"o.c{i}" for i in moving}, "o.rnd")
        go = packed({i: f"cast({values[self.columns[i]]} as {kinds[i]})" for i in moving}, k + 1)
        both = f"explode(array({stay}, case when {' and '.join(holds)} then {go} end)) t"
        return f"select c{pivot}, t.* from (select o.c{pivot}, {both} from ({text}) o {joins}) where t is not null"

    @staticmethod
    def _text(term, values: Mapping[str, str]) -> str:
        """A term of whole numbers as SQL; division drops the remainder."""
        if isinstance(term, Var):
            return values[term.name]
        if isinstance(term, Const):
            return f"cast({term.value} as bigint)" if isinstance(term.value, int) else "'" + str(term.value).replace("\\", "\\\\").replace("'", "\\'") + "'"
        left, right = Hop._text(term.left, values), Hop._text(term.right, values)
        return f"try_divide({left} - {left} % {right}, {right})" if term.op == "/" else f"({left} {term.op} {right})"


def single_hop(defn: Definition) -> Hop | None:
    """The definition's step as a hop, None if it is of another kind."""
    flat = inline_locals(defn)
    _, step = flat.split()
    if defn.padded or len(step) != 1:
        return None
    own = step[0].uses([flat.head])
    static = [a for a in step[0].positive if a.pred != flat.head]
    if len(own) != 1 or own[0].negated or len(static) != 1 or not all(isinstance(v, Var) for a in step[0].atoms for v in a.args):
        return None
    hop = Hop(flat, step[0], own[0], static[0])
    return hop if hop.fits and len({v.name for v in own[0].args}) == len(own[0].args) else None
