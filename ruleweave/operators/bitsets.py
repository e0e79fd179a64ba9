"""Rounds over sets of places, for definitions whose steps move an object's places far more often than the object.

One column is the object, the others together are its place. Each step is cut in two: static literals that hold an object, and static literals
over places, with at most one variable between the two. Objects that steps link stand in chains; chains of like objects share a block, in
which a row of bits a place tells which objects stand there. A round is the same semi-naive round as elsewhere, for 64 objects an operation; the
relations come out as arrays of places, the part that many objects of a block share being kept once. Where only rounds and rows are asked for,
places that steps from locals don't tell apart are one.
"""

from __future__ import annotations

import hashlib
import time
from collections.abc import Iterable, Iterator, Mapping
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleweave.ir.inline import inline_locals
from ruleweave.ir.nodes import Conjunction, Definition
from ruleweave.lang.ast import Const, Var, variables
from ruleweave.operators import chains
from ruleweave.operators.state import FixpointResult, all_materialised, counted, materialised, rows_of, stored, union_all
from ruleweave.plans.conjunction import apply, conjunction, pruned

MOST_EDGES, MOST_PLACES, MOST_PREFIXES = 8_000_000, 2_000_000, 64
BLOCK = 1024  # objects; a chain is never cut
BLOCK_BYTES = 64 << 20  # of one matrix of bits
SHARED = 16  # objects with more places may share a part


@dataclass(frozen=True)
class Half:
    """A step in two halves: object literals over (from, to, label) and place literals over (places, label, new places)."""

    source: str
    target: str
    stays: bool
    objects: Conjunction
    object_columns: tuple[str, ...]  # from and, if the object changes, to
    label: str | None
    places: Conjunction
    before: tuple[str, ...]
    after: tuple[str, ...]


@dataclass(frozen=True)
class Cut:
    """A definition with all its steps cut at one column, which stands at carriers[relation] in each relation of its scope."""

    defn: Definition
    carriers: dict[str, int]
    halves: list[Half]

    def columns(self, relation: str) -> tuple[str, ...]:
        d = next(d for d in (*self.defn.locals, self.defn) if d.head == relation)
        return tuple(c for k, c in enumerate(d.columns) if k != self.carriers[relation])


def cut(defn: Definition) -> Cut | None:
    """The cut of a definition of several steps, some of which change places alone; None if no column allows one."""
    flat = pruned(inline_locals(defn) if defn.padded else defn)
    if len(flat.columns) < 2 or len(flat.split()[1]) < 2:
        return None
    for at in range(len(flat.columns)):
        found = _cut_at(flat, at)
        if found is not None and any(h.stays and not h.objects.atoms for h in found.halves):
            return found
    return None


def _cut_at(flat: Definition, at: int) -> Cut | None:
    carriers, halves = {flat.head: at}, []
    for d in (*flat.locals, flat):
        for c in d.body:
            used = c.uses(flat.scope)
            if not used:
                continue
            if d is not flat and d.head not in carriers:  # a local keeps the object
                names = [v.name if isinstance(v, Var) else None for v in used[0].args]
                held = names[carriers[used[0].pred]] if used[0].pred in carriers else None
                if held not in d.columns or len(d.columns) < 2:
                    return None
                carriers[d.head] = d.columns.index(held)
            half = _half(d, c, carriers, flat.scope)
            if half is None:
                return None
            halves.append(half)
    return Cut(flat, carriers, halves)


def _half(d: Definition, c: Conjunction, carriers: Mapping[str, int], scope: list[str]) -> Half | None:
    own = c.uses(scope)
    if len(own) != 1 or own[0].pred not in carriers or any(a.negated or not all(isinstance(v, Var) for v in a.args) for a in c.atoms):
        return None
    names = [v.name for v in own[0].args]
    if len(set(names)) < len(names):
        return None
    at = carriers[own[0].pred]
    one, other = names[at], d.columns[carriers[d.head]]
    before, after = tuple(n for k, n in enumerate(names) if k != at), tuple(x for x in d.columns if x != other)
    rest = [a for a in c.atoms if a is not own[0]]
    near = [a for a in rest if {one, other} & set(variables(a))]
    far = [a for a in rest if a not in near]
    held, known = {v for a in near for v in variables(a)}, {v for x in (*far, *c.compares) for v in variables(x)}
    fits = all(x.op == "=" and isinstance(x.left, Var) and isinstance(x.right, Const) and isinstance(x.right.value, int) and x.left.name not in (one, other) for x in c.compares)
    fits &= not held & {*before, *after} and {*before, *after} <= known and bool(far)
    labels = (held - {one, other}) & known
    if not fits or len(labels) > 1 or (one != other and not {one, other} <= held):
        return None
    columns = (one,) if one == other else (one, other)
    return Half(own[0].pred, d.head, one == other, Conjunction(tuple(near)), columns, next(iter(labels), None), Conjunction(tuple(far), c.compares), before, after)


def _numbers(df: DataFrame) -> bool:
    return all(t in ("bigint", "int", "smallint", "tinyint") for _, t in df.dtypes)


def _table(df: DataFrame) -> np.ndarray | None:
    """A frame of whole numbers as a matrix; None if it holds NULL."""
    found = df.toArrow()
    if any(c.null_count for c in found.columns):
        return None
    return np.column_stack([c.to_numpy().astype(np.int64) for c in found.columns]) if found.num_columns else np.zeros((found.num_rows, 0), np.int64)


def _codes(nodes: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Places as their numbers in the sorted table of nodes."""
    if nodes.shape[1] == 1:
        return np.searchsorted(nodes[:, 0], rows[:, 0])
    both, inverse = np.unique(np.concatenate([nodes, rows]), axis=0, return_inverse=True)
    assert len(both) == len(nodes)
    return inverse.reshape(-1)[len(nodes) :]


Wanted = list[tuple[str, dict[str, int]]]  # relations, and values that some of their columns must have


def _inputs(found: Cut, env: Mapping[str, DataFrame]) -> tuple | None:
    """Base tuples, the object literals of each step, those of steps that change the object, and places and edges in order."""
    defn = found.defn
    carrier = defn.columns[found.carriers[defn.head]]
    seed = apply(defn, env, None, True)
    if seed is None:
        return None
    seed = materialised(seed.distinct())
    near, far = [], []
    for h in found.halves:
        label = (h.label,) if h.label else ()
        e = conjunction(h.places, tuple(dict.fromkeys((*h.before, *label, *h.after))), env, early=True)
        names = [F.col(f"`{c}`").alias(f"p{k}") for k, c in enumerate((*h.before, *label, *h.after))]
        far.append(e.select(names).distinct())
        if h.objects.atoms:
            o = conjunction(h.objects, (*h.object_columns, *label), env, early=True).toDF(*(["a"] if h.stays else ["a", "b"]), *(["l"] if label else []))
            near.append(o.select("a", *([] if h.stays else ["b"]), (F.col("l") if label else F.lit(0).cast("bigint")).alias("l")).distinct())
        else:
            near.append(None)
    if not all(_numbers(f) for f in (seed, *far, *(o for o in near if o is not None))):
        return None
    ready = iter(all_materialised([*far, *(o.filter("a is not null and l is not null") for o in near if o is not None)]))
    far = [next(ready) for _ in far]
    near = [None if o is None else next(ready) for o in near]
    if sum(rows_of(f) for f in far) > MOST_EDGES:
        return None
    spots = [F.col(f"`{c}`") for c in found.columns(defn.head)]
    tables, starts = [_table(f) for f in far], materialised(seed.select(spots).distinct())
    if rows_of(starts) > MOST_PLACES:
        return None
    starts = _table(starts)
    moves = [o for h, o in zip(found.halves, near, strict=True) if not h.stays]
    if starts is None or any(t is None for t in tables) or not seed.filter(F.col(f"`{carrier}`").isNull()).isEmpty():
        return None
    if any(not o.filter("b is null").isEmpty() for o in moves):
        return None
    nodes, edges = _domain(found, tables, starts)
    if sum(map(len, nodes.values())) > MOST_PLACES or any(len(np.unique(n[:, :-1], axis=0)) > MOST_PREFIXES for n in nodes.values()):
        return None
    return seed, near, moves, nodes, edges


def rounds(found: Cut, env: Mapping[str, DataFrame], wanted: Wanted | None = None) -> FixpointResult | None:
    """The fixpoint; None if the relations are not of the kind that this takes. With wanted, relations hold the wanted rows only, and rounds leave out places that lead to none."""
    started, defn = time.perf_counter(), found.defn
    read = _inputs(found, env)
    if read is None:
        return None
    seed, near, moves, nodes, edges = read
    if wanted is not None:
        wanted = [(r, {c: v for c, v in fixed.items() if c in found.columns(r)}) for r, fixed in wanted]
        nodes, edges = _leading(found, nodes, edges, wanted)
    objects = _objects(found, seed, near, moves, nodes[defn.head])
    if objects is None:
        return None
    out = stored(objects.mapInArrow(_Block(found, nodes, edges, wanted).run, "relation string, obj bigint, prefix int, core string, places array<bigint>"))
    sizes = {r[0]: r[1] for r in out.filter("relation = ''").groupBy("obj").agg(F.sum(F.col("places")[0])).collect()}
    sizes = [sizes.get(k, 0) for k in range(max(sizes, default=0) + 1)]
    whole = {d.head: _relation(out, found, d, nodes[d.head]) for d in (*defn.locals, defn) if d is defn or not any(not c.uses(defn.scope) for c in d.body)}
    total = whole.pop(defn.head)
    return FixpointResult(total, len(sizes), sizes, [time.perf_counter() - started], whole, wanted is not None)


def counts(found: Cut, env: Mapping[str, DataFrame]) -> FixpointResult | None:
    """Rounds and rows of the fixpoint without the rows themselves (total has none); None as for rounds(), or if nothing is shared.

    What an object derives before it meets a local is kept apart, row by row. What comes through a local is the same for all places with the
    same steps into them, which are one place there, with a weight.
    """
    started, defn = time.perf_counter(), found.defn
    read = _inputs(found, env) if any(h.source != defn.head for h in found.halves) else None
    if read is None:
        return None
    seed, near, moves, nodes, edges = read
    objects = _objects(found, seed, near, moves, nodes[defn.head])
    if objects is None:
        return None
    out = objects.mapInArrow(_Counts(found, nodes, edges).run, "relation string, obj bigint, prefix int, core string, places array<bigint>")
    sizes = {r[0]: r[1] for r in out.groupBy("obj").agg(F.sum(F.col("places")[0])).collect()}
    sizes = [sizes.get(k, 0) for k in range(max(sizes, default=0) + 1)]
    return FixpointResult(seed.limit(0), len(sizes), sizes, [time.perf_counter() - started], {}, True)


def _rows_once(rows: np.ndarray) -> np.ndarray:
    return np.unique(rows[:, 0]).reshape(-1, 1) if rows.shape[1] == 1 else np.unique(rows, axis=0)


def _domain(found: Cut, tables: list[np.ndarray], starts: np.ndarray) -> tuple[dict[str, np.ndarray], list[dict[int, tuple[np.ndarray, np.ndarray]]]]:
    """For each relation its places in order; for each step and label its edges between numbers of places, ordered by the second."""
    held: dict[str, list[np.ndarray]] = {found.defn.head: [starts]}
    for h, t in zip(found.halves, tables, strict=True):
        held.setdefault(h.source, []).append(t[:, : len(h.before)])
        held.setdefault(h.target, []).append(t[:, t.shape[1] - len(h.after) :])
    nodes = {r: _rows_once(np.concatenate(parts)) for r, parts in held.items()}
    edges = []
    for h, t in zip(found.halves, tables, strict=True):
        a, b = _codes(nodes[h.source], t[:, : len(h.before)]), _codes(nodes[h.target], t[:, t.shape[1] - len(h.after) :])
        label = t[:, len(h.before)] if h.label else np.zeros(len(t), np.int64)
        order = np.lexsort((a, b, label))
        a, b, label = a[order], b[order], label[order]
        edges.append({int(v): (a[label == v], b[label == v]) for v in np.unique(label)})
    return nodes, edges


def _rows_of(found: Cut, relation: str, rows: np.ndarray, wanted: Wanted | None) -> np.ndarray:
    """Which of these places of a relation are wanted."""
    if wanted is None:
        return np.ones(len(rows), bool)
    names, hit = found.columns(relation), np.zeros(len(rows), bool)
    for _, fixed in (w for w in wanted if w[0] == relation):
        hit |= np.all([rows[:, names.index(c)] == v for c, v in fixed.items()], axis=0) if fixed else True
    return hit


def _leading(found: Cut, nodes: dict[str, np.ndarray], edges: list[dict[int, tuple[np.ndarray, np.ndarray]]], wanted: Wanted) -> tuple[dict[str, np.ndarray], list[dict[int, tuple[np.ndarray, np.ndarray]]]]:
    """The places from which steps lead to wanted ones, and the edges between them."""
    kept = {r: _rows_of(found, r, n, wanted) for r, n in nodes.items()}
    before = -1
    while before < (now := sum(int(k.sum()) for k in kept.values())):
        before = now
        for h, by_label in zip(found.halves, edges, strict=True):
            for a, b in by_label.values():
                kept[h.source][a[kept[h.target][b]]] = True
    number = {r: np.cumsum(k) - 1 for r, k in kept.items()}
    left = [{v: (number[h.source][a[kept[h.target][b]]], number[h.target][b[kept[h.target][b]]]) for v, (a, b) in e.items()} for h, e in zip(found.halves, edges, strict=True)]
    return {r: n[kept[r]] for r, n in nodes.items()}, left


def _objects(found: Cut, seed: DataFrame, near: list[DataFrame | None], moves: list[DataFrame], nodes: np.ndarray) -> DataFrame | None:
    """One row an object, with its chain, seeds, labels and moves; like chains stand together. None if moves don't make chains."""
    spark, defn = seed.sparkSession, found.defn
    carrier, spots = defn.columns[found.carriers[defn.head]], list(found.columns(defn.head))
    numbers = spark.createDataFrame(pa.Table.from_arrays([*(pa.array(nodes[:, k]) for k in range(nodes.shape[1])), pa.array(np.arange(len(nodes)))], names=[*spots, "rw_node"]))
    own = seed.join(F.broadcast(numbers), spots).groupBy(F.col(f"`{carrier}`").cast("bigint").alias("obj")).agg(F.collect_list(F.col("rw_node").cast("int")).alias("seeds"))
    if moves:
        link = union_all([o.select("a", "b") for o in moves]).filter("a <> b").distinct()
        lines = chains.positions(link)
        if lines is None or lines.filter(F.size("nodes") > 64 * BLOCK).limit(1).count():
            return None
        frame = lines.select("chain", F.explode("nodes").alias("obj")).join(own, "obj", "full_outer").withColumn("chain", F.coalesce("chain", "obj"))
    else:
        frame = own.withColumn("chain", F.col("obj"))
    for k, (h, o) in enumerate(zip(found.halves, near, strict=True)):
        if o is None:
            continue
        held = o.groupBy(F.col("a").alias("obj")).agg(F.collect_list("l").alias(f"l{k}"), *([] if h.stays else [F.collect_list("b").alias(f"b{k}")]))
        frame = frame.join(held, "obj", "left")
    # like objects are those with the same label in a step that keeps them
    kinds = [F.array_min(f"l{k}").cast("bigint") for k, h in enumerate(found.halves) if h.stays and h.label]
    frame, seen = counted(frame.withColumn("class", F.coalesce(*kinds[:1], F.lit(0).cast("bigint"))))
    first = frame.groupBy("chain").agg(F.min("class").alias("chain_class"), F.max(F.col("seeds").isNotNull()).alias("some")).filter("some").drop("some")
    n = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-seen["rows"] // (8 * BLOCK)))
    return frame.join(first, "chain").repartitionByRange(n, "chain_class", "chain").sortWithinPartitions("chain_class", "chain", "obj")


def _relation(out: DataFrame, found: Cut, d: Definition, nodes: np.ndarray) -> DataFrame:
    """A relation from its arrays: the shared part and what an object has beside it."""
    carrier, spots = d.columns[found.carriers[d.head]], found.columns(d.head)
    prefixes = np.unique(nodes[:, :-1], axis=0)
    own = out.filter(F.col("relation") == d.head)
    shared = out.filter(F.col("relation") == f"{d.head} core").select("core", F.col("places").alias("rw_shared")).dropDuplicates(["core"])
    rows = own.join(F.broadcast(shared), "core", "left")
    parts = []
    for k, values in enumerate(prefixes):
        all_places = F.concat(F.coalesce("rw_shared", F.array().cast("array<bigint>")), "places")
        one = rows.filter(F.col("prefix") == k).select(F.col("obj").alias(carrier), F.explode(all_places).alias(spots[-1]))
        parts.append(one.select(*[F.lit(int(values[spots.index(c)])).cast("bigint").alias(c) if c in spots[:-1] else F.col(f"`{c}`") for c in d.columns]))
    return union_all(parts) if parts else own.select(*[F.lit(0).cast("bigint").alias(c) for c in d.columns]).limit(0)


class _Block:
    """What a task does: whole chains are packed into blocks, each evaluated to its end."""

    def __init__(self, found: Cut, nodes: Mapping[str, np.ndarray], edges: list[dict[int, tuple[np.ndarray, np.ndarray]]], wanted: Wanted | None = None):
        self.head = found.defn.head
        self.steps = [(h.source, h.target, h.stays, bool(h.objects.atoms), e) for h, e in zip(found.halves, edges, strict=True)]
        self.nodes = nodes
        self.width = int(max(64, min(BLOCK, BLOCK_BYTES * 8 // max(1, len(nodes[self.head])) // 64 * 64)))
        # for each relation the stretches of places that differ in their last column only
        self.stretches = {}
        for r, n in nodes.items():
            _, at = np.unique(n[:, :-1], axis=0, return_index=True)
            self.stretches[r] = list(zip(at.tolist(), [*at[1:].tolist(), len(n)], strict=True)) if len(n) else []
        self.wanted = {r: _rows_of(found, r, n, wanted) for r, n in nodes.items()}

    def run(self, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: list[pa.Table] = []
        held = 0
        for batch in batches:
            kept.append(pa.Table.from_batches([batch]))
            held += batch.num_rows
            if held >= 8 * self.width:
                table = pa.concat_tables(kept).combine_chunks()
                last = self._ends(table)[-2] if len(self._ends(table)) > 1 else 0
                yield from self._blocks(table.slice(0, last))
                kept = [table.slice(last)]
                held = table.num_rows - last
        if held:
            yield from self._blocks(pa.concat_tables(kept).combine_chunks())

    @staticmethod
    def _ends(table: pa.Table) -> list[int]:
        chain = table["chain"].to_numpy()
        return [0, *(np.flatnonzero(chain[1:] != chain[:-1]) + 1).tolist(), len(chain)]

    def _blocks(self, table: pa.Table) -> Iterator[pa.RecordBatch]:
        if not table.num_rows:
            return
        start, ends = 0, self._ends(table)
        for before, end in zip(ends[:-1], ends[1:], strict=True):
            if end - start > self.width and before > start:
                yield from self._block(table.slice(start, before - start))
                start = before
        yield from self._block(table.slice(start))

    @staticmethod
    def _lists(table: pa.Table, name: str) -> tuple[np.ndarray, np.ndarray]:
        """The row number and the value of each element of a column of arrays."""
        column = table[name].combine_chunks()
        column = column.chunk(0) if isinstance(column, pa.ChunkedArray) else column
        sizes = column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
        return np.repeat(np.arange(len(sizes)), sizes), column.flatten().to_numpy(zero_copy_only=False)

    def _block(self, table: pa.Table) -> Iterator[pa.RecordBatch]:
        obj = table["obj"].to_numpy()
        words = -(-len(obj) // 64)
        order = np.argsort(obj, kind="stable")
        steps = []
        for k, (source, target, stays, some, edges) in enumerate(self.steps):
            if not some:
                steps += [(source, target, e, None, None) for e in edges.values()]
                continue
            row, label = self._lists(table, f"l{k}")
            to = row
            if not stays:
                _, b = self._lists(table, f"b{k}")
                to = order[np.searchsorted(obj[order], b)]
            for v in np.unique(label):
                if int(v) in edges:
                    a, b = row[label == v], to[label == v]
                    steps.append((source, target, edges[int(v)], _mask(a, words), None if stays else (a, b)))
        row, seeds = self._lists(table, "seeds")
        total, sizes = self._rounds(steps, row, seeds, words)
        out = [("", k, 0, None, np.array([s], np.int64)) for k, s in enumerate(sizes)]
        kinds = table["class"].to_numpy()
        for relation, bits in total.items():
            for prefix, (a, b) in enumerate(self.stretches[relation]):
                if not self.wanted[relation][a:b].any():
                    continue
                for kind in np.unique(kinds):
                    out += self._arrays(relation, prefix, bits[a:b], self.nodes[relation][a:b, -1], obj, np.flatnonzero(kinds == kind))
        for k in range(0, len(out), 4096):
            yield _batch(out[k : k + 4096])

    def _rounds(self, steps: list, row: np.ndarray, seeds: np.ndarray, words: int) -> tuple[dict[str, np.ndarray], list[int]]:
        """The bits of each relation and how many new ones of the head each round found."""
        fresh = lambda: {r: np.zeros((len(n), words), np.uint64) for r, n in self.nodes.items()}
        total, new = fresh(), fresh()
        delta = np.zeros_like(total[self.head])
        np.bitwise_or.at(delta, (seeds, row // 64), np.uint64(1) << (row % 64).astype(np.uint64))
        active = {r: np.zeros(len(n), bool) for r, n in self.nodes.items()}
        active[self.head][seeds] = True
        total[self.head] |= delta
        sizes = [int(np.bitwise_count(delta).sum())]
        while sizes[-1]:
            touched = {r: np.zeros(len(n), bool) for r, n in self.nodes.items()}
            for source, target, (a, b), mask, moved in steps:
                at = active[self.head] if source == self.head else touched[source]
                hit = at[a]
                if hit.any():
                    _pass(delta if source == self.head else new[source], a[hit], b[hit], mask, moved, new[target], touched[target])
            for r, hit in touched.items():
                at = np.flatnonzero(hit)
                found = new[r][at] & ~total[r][at]
                new[r][at] = 0
                if r != self.head:
                    total[r][at] |= found
                    continue
                delta[active[r]] = 0
                some = found.any(axis=1)
                at, found = at[some], found[some]
                total[r][at] |= found
                delta[at] = found
                active[r][:] = False
                active[r][at] = True
                sizes.append(int(np.bitwise_count(found).sum()))
        return total, sizes

    def _arrays(self, relation: str, prefix: int, bits: np.ndarray, values: np.ndarray, obj: np.ndarray, members: np.ndarray) -> list[tuple]:
        """A row an object that has places: the name of the shared part, if it has that, and its other places."""
        words, out, core = bits.shape[1], [], None
        n = np.zeros(words * 64, np.int64)
        for k in range(0, len(bits), 8192):
            n += np.unpackbits(bits[k : k + 8192].view(np.uint8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        n = n[members]
        big = members[(2 * n >= n.max()) & (n > SHARED)]
        bits = bits & _mask(members, words)
        if len(big) > 1:
            mask = _mask(big, words)
            at = ((bits & mask) == mask).all(axis=1)
            shared = values[at]
            core = hashlib.sha256(shared.tobytes()).hexdigest() + f" {prefix}"
            out.append((f"{relation} core", 0, prefix, core, shared))
            bits[at] &= ~mask
        some = np.flatnonzero(bits.any(axis=1))
        places = [np.zeros(0, np.int64)]
        owners = [np.zeros(0, np.int64)]
        for k in range(0, len(some), 8192):
            i, o = np.nonzero(np.unpackbits(bits[some[k : k + 8192]].view(np.uint8), axis=1, bitorder="little"))
            places.append(values[some[k : k + 8192]][i])
            owners.append(o)
        place, owner = np.concatenate(places), np.concatenate(owners)
        order = np.argsort(owner, kind="stable")
        place, ends = place[order], np.cumsum(np.bincount(owner, minlength=words * 64))
        having = set(big.tolist()) if core else set()
        for m in members[n > 0].tolist():
            out.append((relation, int(obj[m]), prefix, core if m in having else None, place[ends[m - 1] if m else 0 : ends[m]]))
        return out


class _Counts(_Block):
    """The same blocks, for how many rows are new in each round."""

    def __init__(self, found: Cut, nodes: Mapping[str, np.ndarray], edges: list[dict[int, tuple[np.ndarray, np.ndarray]]]):
        super().__init__(found, nodes, edges)
        kinds = _alike(self.head, len(nodes[self.head]), self.steps)
        self.places, self.kinds, self.weights = len(kinds), kinds, np.bincount(kinds[kinds >= 0], minlength=1)
        # edges from places, ordered by them, with where each place's begin; edges of kinds, ordered by the second
        self.own, apart = [], []
        for source, target, stays, some, by_label in self.steps:
            kept, ends = {}, {}
            for v, (a, b) in by_label.items():
                if source == self.head:
                    order = np.argsort(a, kind="stable")
                    kept[v] = (a[order].astype(np.int32), b[order].astype(np.int32))
                one, other = (kinds[a] if source == self.head else a), (kinds[b] if target == self.head else b)
                pairs = np.unique(np.column_stack([other, one])[(one >= 0) & (other >= 0)], axis=0)
                if len(pairs):
                    ends[v] = (pairs[:, 1].copy(), pairs[:, 0].copy())
            self.own.append(kept)
            apart.append((source, target, stays, some, ends))
        self.steps = apart
        self.rows = {r: len(n) for r, n in nodes.items()} | {self.head: len(self.weights)}
        self.width = int(max(64, min(8 * BLOCK, BLOCK_BYTES * 8 // max(1, len(self.weights)) // 64 * 64)))  # few kinds: a block is a partition
        self.nodes, self.stretches, self.wanted = {}, {}, {}

    def _block(self, table: pa.Table) -> Iterator[pa.RecordBatch]:
        obj = table["obj"].to_numpy()
        words, order = -(-len(obj) // 64), np.argsort(obj, kind="stable")
        shared, own = [], []
        for k, ((source, target, stays, some, ends), kept) in enumerate(zip(self.steps, self.own, strict=True)):
            row = to = label = None
            if some:
                row, label = self._lists(table, f"l{k}")
                to = row
                if not stays:
                    _, b = self._lists(table, f"b{k}")
                    to = order[np.searchsorted(obj[order], b)]
            for v in kept.keys() | ends.keys():
                a, b = (row[label == v], to[label == v]) if some else (None, None)
                if some and not len(a):
                    continue
                if v in ends:
                    shared.append((k, source, target, ends[v], _mask(a, words) if some else None, None if stays else (a, b)))
                if v in kept:
                    own.append((target, kept[v], _where(len(obj), a, b)))
        row, seeds = self._lists(table, "seeds")
        # all steps of one relation stand before those that read it
        shared = [step[1:] for step in sorted(shared, key=lambda step: step[0])]
        yield _batch([("", k, 0, None, np.array([n], np.int64)) for k, n in enumerate(self._sizes(shared, own, row.astype(np.int64), seeds.astype(np.int64), words))])

    def _sizes(self, shared: list, own: list, row: np.ndarray, seeds: np.ndarray, words: int) -> list[int]:
        fresh = lambda: {r: np.zeros((n, words), np.uint64) for r, n in self.rows.items()}
        total, new = fresh(), fresh()
        delta, active = np.zeros_like(total[self.head]), np.zeros(self.rows[self.head], bool)
        known = last = np.unique(row * self.places + seeds)
        sizes, pending = [len(last)], last[self.kinds[last % self.places] >= 0]  # rows found apart that may come through a local later
        while sizes[-1]:
            touched = {r: np.zeros(n, bool) for r, n in self.rows.items()}
            at, place = last // self.places, last % self.places
            found = [np.zeros(0, np.int64)]
            for target, (a, b), where in own:
                i, there = _along(a, b, place)
                for o in (at[i],) if where is None else (w[at[i]] for w in where):
                    some = o >= 0
                    if target == self.head:
                        found.append(o[some] * self.places + there[some])
                    elif some.any():
                        _set(new[target], there[some], o[some])
                        touched[target][there[some]] = True
            last = np.setdiff1d(np.concatenate(found), known)
            known = np.union1d(known, last)
            for source, target, (a, b), mask, moved in shared:
                hit = (active if source == self.head else touched[source])[a]
                if hit.any():
                    _pass(delta if source == self.head else new[source], a[hit], b[hit], mask, moved, new[target], touched[target])
            count = 0
            for r, hit in touched.items():
                where = np.flatnonzero(hit)
                bits = new[r][where] & ~total[r][where]
                new[r][where] = 0
                if r != self.head:
                    total[r][where] |= bits
                    continue
                delta[active] = 0
                some = bits.any(axis=1)
                where, bits = where[some], bits[some]
                total[r][where] |= bits
                delta[where] = bits
                active[:] = False
                active[where] = True
                count = int(np.bitwise_count(bits).sum(axis=1, dtype=np.int64) @ self.weights[where])
            count -= int(self._held(delta, pending).sum())
            alone = last[~self._held(total[self.head], last)]
            pending = np.concatenate([pending[~self._held(delta, pending)], alone[self.kinds[alone % self.places] >= 0]])
            sizes.append(count + len(alone))
        return sizes

    def _held(self, bits: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """Whether the kind of each row's place has the row's object."""
        o, kind = rows // self.places, self.kinds[rows % self.places]
        return (kind >= 0) & ((bits[kind, o // 64] >> (o % 64).astype(np.uint64)) & np.uint64(1)).astype(bool)


def _alike(head: str, n: int, steps: list) -> np.ndarray:
    """For each place of the head the number of its kind: places of a kind have steps from the same kinds and locals into them. -1: none leads there from a local."""
    into = [(k, v, source == head, a, b) for k, (source, target, _, _, e) in enumerate(steps) if target == head for v, (a, b) in e.items()]
    there, before = np.zeros(n, bool), -1
    while before < (now := int(there.sum())):
        before = now
        for _, _, own, a, b in into:
            there[b[there[a]] if own else b] = True
    sources, targets, own = [], [], []
    for j, (k, _, inner, a, b) in enumerate(into):
        some = there[a] if inner else np.ones(len(a), bool)
        a, b = a[some].astype(np.int64), b[some]
        # a local's places keep their numbers; those of a step and label are told apart by its number
        own.append(np.full(len(a), inner))
        sources.append(np.column_stack([np.full(len(a), j), a]))
        targets.append(b)
    sources, targets, own = np.concatenate(sources), np.concatenate(targets), np.concatenate(own)
    kinds, count = np.where(there, 0, -1), 1
    while len(targets):
        value = np.where(own, kinds[np.where(own, sources[:, 1], 0)], sources[:, 1])
        order = np.lexsort((value, sources[:, 0], targets))
        rows = np.column_stack([targets, sources[:, 0], value])[order]
        rows = rows[np.concatenate([[True], (rows[1:] != rows[:-1]).any(axis=1)])]
        first = np.flatnonzero(np.concatenate([[True], rows[1:, 0] != rows[:-1, 0]]))
        # numbers of 64 bits stand for what leads into a place; two of them, so that different places don't meet
        held = [kinds[rows[first, 0]]]
        for seed in (0x9E3779B97F4A7C15, 0xD1B54A32D192ED03):
            held.append(np.add.reduceat(_mixed(rows[:, 1].astype(np.uint64) * np.uint64(seed) ^ _mixed(rows[:, 2].astype(np.uint64) + np.uint64(seed))), first))
        order = np.lexsort(held)
        other = np.zeros(len(order), np.int64)
        for h in held:
            other[1:] |= h[order][1:] != h[order][:-1]
        kinds[rows[first[order], 0]] = np.cumsum(other)
        if kinds.max() + 1 == count:
            break
        count = int(kinds.max()) + 1
    return kinds


def _mixed(x: np.ndarray) -> np.ndarray:
    for shift, by in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(by)
    return x ^ (x >> np.uint64(31))


def _where(n: int, a: np.ndarray | None, b: np.ndarray | None) -> list[np.ndarray] | None:
    """To which object each object's places go, -1: none; an object goes to one other and to itself. None: all to themselves."""
    if a is None:
        return None
    found = []
    for some in (a == b, a != b):
        if some.any():
            to = np.full(n, -1, np.int64)
            to[a[some]] = b[some]
            found.append(to)
    return found


def _along(a: np.ndarray, b: np.ndarray, places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each edge (a ordered) from one of the places: which place, and where to."""
    low, high = np.searchsorted(a, places, "left"), np.searchsorted(a, places, "right")
    sizes = high - low
    i = np.repeat(np.arange(len(places)), sizes)
    return i, b[np.arange(len(i)) - np.repeat(np.cumsum(sizes) - sizes, sizes) + low[i]].astype(np.int64)


def _set(bits: np.ndarray, rows: np.ndarray, objects: np.ndarray) -> None:
    np.bitwise_or.at(bits, (rows, objects // 64), np.uint64(1) << (objects % 64).astype(np.uint64))


def _mask(bits: np.ndarray, words: int) -> np.ndarray:
    held = np.zeros(words * 64, np.uint8)
    held[bits] = 1
    return np.packbits(held, bitorder="little").view(np.uint64)


def _pass(rows: np.ndarray, a: np.ndarray, b: np.ndarray, mask: np.ndarray | None, moved: tuple[np.ndarray, np.ndarray] | None, into: np.ndarray, touched: np.ndarray) -> None:
    """Bits of the rows a go to the rows b (ordered); with moved, from object to object."""
    first = np.flatnonzero(np.concatenate([[True], b[1:] != b[:-1]]))
    found, at = np.bitwise_or.reduceat(rows[a], first, axis=0), b[first]
    if mask is not None:
        found &= mask
    if moved is not None:
        some = found.any(axis=1)
        found, at = found[some], at[some]
        if not len(at):
            return
        one, other = moved
        bits = np.unpackbits(found.view(np.uint8), axis=1, bitorder="little")
        there = np.zeros_like(bits)
        same = one == other
        there[:, other[~same]] = bits[:, one[~same]]  # an object is reached from one other only, and from itself
        there[:, one[same]] |= bits[:, one[same]]
        found = np.packbits(there, axis=1, bitorder="little").view(np.uint64)
    into[at] |= found
    touched[at] = True


def _batch(rows: Iterable[tuple]) -> pa.RecordBatch:
    relation, obj, prefix, core, places = zip(*rows, strict=True)
    ends = np.concatenate([[0], np.cumsum([len(p) for p in places])]).astype(np.int32)
    lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(places)))
    return pa.RecordBatch.from_arrays([pa.array(relation), pa.array(obj, pa.int64()), pa.array(prefix, pa.int32()), pa.array(core, pa.string()), lists], names=["relation", "obj", "prefix", "core", "places"])
