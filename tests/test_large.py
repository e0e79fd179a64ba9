"""Plans that large inputs take, forced here on small ones."""

from __future__ import annotations

import random

import duckdb
import pytest

from ruleweave import queries
from ruleweave.lang import normalize
from ruleweave.lang.parser import parse
from ruleweave.operators import baselines, bitsets, chains, fixpoint, local
from ruleweave.plans import layout
from ruleweave.plans.program import compile_program, evaluate
from ruleweave.sources import facts as fact_views
from ruleweave.workloads import programs, reference

FACTS = {
    "entry_unit": {(1,), (9,)},
    # site 10 stands in two rows and site 12 in both relations, so their callees can repeat
    "dyn_site": {(10, 1, 100, 1, 1), (10, 2, 3, 1, 1), (11, 2, 100, 1, 1), (12, 3, 3, 1, 2), (13, 7, 100, 1, 1)},
    "subkind": {(3, 100), (4, 100), (3, 3)},
    "unit_impl": {(3, 1, 1, 2), (4, 1, 1, 2), (4, 1, 1, 3), (3, 1, 2, 4), (3, 1, 1, 5)},
    "fix_site": {(12, 3, 4), (20, 4, 6), (21, 8, 7), (30, 2, 2), (31, 1, 3), (32, 1, 2), (33, 3, 5)},
}
COLUMNS = {"entry_unit": "unit long", "dyn_site": "site long, caller long, decl long, nm long, sig long", "subkind": "sub long, sup long", "unit_impl": "kind long, nm long, sig long, callee long", "fix_site": "site long, caller long, callee long"}


def frames(spark):
    return {n: spark.createDataFrame(sorted(FACTS[n]), c) for n, c in COLUMNS.items()}


def rows(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.mark.parametrize("form", ["lifted", "tagged"])
@pytest.mark.parametrize("strategy", [fixpoint.seminaive, fixpoint.naive, baselines.external_loop, baselines.round_batches, baselines.arranged])
def test_dispatch_with_distinct_steps(spark, monkeypatch, form, strategy):
    if form == "tagged" and strategy is not fixpoint.seminaive:
        pytest.skip("one strategy for the tagged form")
    monkeypatch.setattr(layout, "EARLY_ROWS", 0)
    want = local.evaluate(normalize.canonical(parse(programs.DISPATCH_CALLS)), FACTS)
    found = evaluate(compile_program(programs.DISPATCH_CALLS, form), frames(spark), strategy).relations
    assert rows(found["live"]) == sorted(want["live"]) and rows(found["calls"]) == sorted(want["calls"])


def test_most_rows_are_not_made_distinct(spark, monkeypatch):
    """Only the callees of sites that stand in several rows are aggregated behind the last join; the relation is no checkpoint."""
    monkeypatch.setattr(layout, "EARLY_ROWS", 0)
    found = evaluate(compile_program(programs.DISPATCH_CALLS), frames(spark)).relations["calls"]
    plan = found._jdf.queryExecution().optimizedPlan().toString()
    assert plan.lstrip().startswith("Union") and plan.count("Aggregate [site") == 1


def test_the_tagged_form_keeps_only_what_recursion_reads():
    whole, *behind = compile_program(programs.DISPATCH_CALLS, "tagged").definitions
    assert len(whole.columns) == 2 and [d.head for d in behind] == ["live", "calls"] and not behind[1].recursive

EDGE = {(k, k + 1) for a in (0, 10, 20) for k in range(a, a + 7)} | {(40, 41)}


@pytest.mark.parametrize("edge", [EDGE, EDGE | {(50, 51), (51, 50)}, EDGE | {(3, 23)}, {(2, 5), (5, 1), (1, 9)}])
def test_chains_as_intervals(spark, monkeypatch, edge):
    """Where nothing is broadcast, steps along chains are intervals; cycles and forks still go by rounds. Rounds are counted alike."""
    text = "r(x, y) :- e0(x, y). r(x, y) :- r(x, z), edge(z, y), !bar(x, y).\n.output r"
    facts = {"edge": edge, "e0": {(1, 0), (1, 3), (2, 10), (2, 12), (3, 99), (4, 5), (4, 50)}, "bar": {(1, 5), (2, 12), (3, 100), (4, 6)}}
    env = {n: spark.createDataFrame(sorted(f), "src long, dst long" if n == "edge" else "x long, y long") for n, f in facts.items()}
    compiled = compile_program(text)
    rounds = evaluate(compiled, env).fixpoints["r"]
    monkeypatch.setattr(layout, "BROADCAST_BYTES", 0)
    monkeypatch.setattr(layout, "EARLY_ROWS", 0)
    used = []
    along = chains.along
    monkeypatch.setattr(chains, "along", lambda *a: used.append(along(*a)) or used[-1])
    found = evaluate(compiled, env).fixpoints["r"]
    assert rows(found.total) == sorted(local.evaluate(compiled.program, facts)["r"])
    assert (found.rounds, found.delta_sizes) == (rounds.rounds, rounds.delta_sizes)
    assert (used[0] is not None) == (edge == EDGE or len(edge) == 3)


@pytest.mark.parametrize("edge", [EDGE, EDGE | {(50, 51), (51, 50)}])
def test_naive_rounds_over_stretches(spark, monkeypatch, edge):
    """Where facts are many, naive rounds keep chains as stretches, with the rows of each round; cycles go by rows."""
    text = "r(x, y) :- e0(x, y). r(x, y) :- r(x, z), edge(z, y).\n.output r"
    facts = {"edge": edge, "e0": {(1, 0), (1, 3), (2, 10), (2, 12), (3, 99), (4, 5), (4, 50)}}
    env = {n: spark.createDataFrame(sorted(f), "src long, dst long" if n == "edge" else "x long, y long") for n, f in facts.items()}
    compiled = compile_program(text)
    by_rows = evaluate(compiled, env, fixpoint.naive).fixpoints["r"]
    monkeypatch.setattr(layout, "EARLY_ROWS", 0)
    used, along = [], chains.naive_along
    monkeypatch.setattr(chains, "naive_along", lambda *a: used.append(along(*a)) or used[-1])
    found = evaluate(compiled, env, fixpoint.naive).fixpoints["r"]
    assert rows(found.total) == sorted(local.evaluate(compiled.program, facts)["r"])
    assert (found.rounds, found.delta_sizes) == (by_rows.rounds, by_rows.delta_sizes) and (used[0] is not None) == (edge == EDGE)


def test_local_oracle_beyond_the_driver(spark, data, monkeypatch):
    """More facts than the driver takes are evaluated with Python sets in the tasks; turns that run into the next conversation's stay linked."""
    want = rows(queries.queries()["turns_local_oracle"](spark, data))
    monkeypatch.setattr(baselines, "MOST_LOCAL_FACTS", 0)
    assert rows(queries.queries()["turns_local_oracle"](spark, data)) == want
    monkeypatch.setattr(queries.run, "chain", lambda *_: {"edge": spark.createDataFrame([(1998, 1999), (1999, 2000), (2000, 2001)], "src long, dst long"), "head": spark.createDataFrame([(1998,)], "node long")})
    assert rows(queries.queries()["turns_local_oracle"](spark, data)) == [(1998, n) for n in (1998, 1999, 2000, 2001)]


def test_keys_of_events_name_the_columns_of_the_sql(spark, data, tmp_path):
    """Two users with the same events: a key of two columns, named in the order of the reference SQL."""
    events = spark.read.parquet(f"{data}/events.parquet").limit(50)
    events.union(events.withColumns({"event_id": events.event_id + 10**6, "user_id": events.user_id + 10**6})).coalesce(1).write.parquet(str(tmp_path / "events.parquet"))
    con = duckdb.connect()
    con.execute(f"create view events as select * from '{tmp_path}/events.parquet/*.parquet'")
    want = con.execute(queries.oracle_sql()["fd_keys_events"]).fetchall()
    assert ("user_id,ts",) in want and rows(queries.queries()["fd_keys_events"](spark, str(tmp_path))) == sorted(want)


@pytest.mark.parametrize("name", ["w10_trace", "summary_programs"])
def test_trace_and_summary_read_the_tables(spark, data, name):
    con = duckdb.connect()
    for t in ("nation", "customer", "supplier", "part", "orders", "lineitem", "events"):
        con.execute(f"create view {t} as select * from '{data}/{t}.parquet'")
    want = con.execute(queries.oracle_sql()[name])
    columns = [c[0] for c in want.description]
    found = queries.queries()[name](spark, data)
    assert found.inputFiles() or name == "w10_trace"
    assert rows(found.select(columns)) == sorted(want.fetchall()) and found.count() > 4


def _heap_facts(seed, orders=60, names=12):
    """Random facts of the heap program: objects in chains, likewise objects that meet themselves, labels of several kinds."""
    r = random.Random(seed)
    pairs = lambda n: {(r.randrange(names), r.randrange(names)) for _ in range(n)}
    content = [(o, o + 1) for o in range(orders) if o % 7] + [(o, o) for o in range(0, orders, 9)]
    return {
        "alloc": {(o, r.randrange(names), r.randrange(4)) for o in range(0, orders, 3)} | {(1000 + o, o, 1) for o in range(3)},
        "live_unit": {(0,), (1,), (2,)}, "assign": pairs(3), "cast_assign": pairs(2), "arg_assign": pairs(2), "ret_assign": pairs(1),
        "static_store": {(v, r.randrange(3), r.randrange(4)) for v in range(0, names, 3)}, "static_load": {(r.randrange(3), v, r.randrange(4)) for v in range(1, names, 4)},
        "field_load": {(b, b % 2, v) for b, v in pairs(6)}, "field_content": {(h, r.randrange(2), o) for h, o in content if h % 2}, "array_load": pairs(5),
        "array_content": {p for p in content if not p[0] % 2}, "recv_call": pairs(4), "obj_kind": {(o, r.randrange(3)) for o in range(orders + 1)} | {(4, 0), (4, 1)}, "self_of": {(k, s, r.randrange(names)) for k in range(3) for s in range(0, names, 2)},
    }


@pytest.mark.parametrize("form", ["lifted", "tagged"])
@pytest.mark.parametrize("seed", [1, 2])
def test_heap_flow_as_bit_sets(spark, monkeypatch, form, seed):
    """Relations and rounds are those of rounds over rows, also where blocks are many and shared parts are kept once."""
    facts = _heap_facts(seed)
    env = {n: spark.createDataFrame(sorted(f), ", ".join(f"{c} long" for c in reference.COLUMNS[n].split())) for n, f in facts.items()}
    compiled = compile_program(programs.HEAP_FLOW, form)
    by_rows = next(iter(evaluate(compiled, env).fixpoints.values()))
    monkeypatch.setattr(layout, "EARLY_ROWS", 0)
    monkeypatch.setattr(bitsets, "BLOCK", 64)
    monkeypatch.setattr(bitsets, "SHARED", 2)
    used, rounds = [], bitsets.rounds
    monkeypatch.setattr(bitsets, "rounds", lambda *a: used.append(rounds(*a)) or used[-1])
    found = evaluate(compiled, env)
    want = local.evaluate(compiled.program, facts)
    assert rows(found.relations["points"]) == sorted(want["points"]) and rows(found.relations["fpoints"]) == sorted(want["fpoints"])
    by_bits = next(iter(found.fixpoints.values()))
    assert used[0] is by_bits and (by_bits.rounds, by_bits.delta_sizes) == (by_rows.rounds, by_rows.delta_sizes)


def test_objects_that_fork_go_by_rows(spark, monkeypatch):
    facts = _heap_facts(3)
    facts["array_content"] |= {(2, 40), (2, 50)}
    env = {n: spark.createDataFrame(sorted(f), ", ".join(f"{c} long" for c in reference.COLUMNS[n].split())) for n, f in facts.items()}
    monkeypatch.setattr(layout, "EARLY_ROWS", 0)
    compiled = compile_program(programs.HEAP_FLOW)
    assert rows(evaluate(compiled, env).relations["points"]) == sorted(local.evaluate(compiled.program, facts)["points"])


def test_heap_flow_of_the_tables_as_bit_sets(spark, data, monkeypatch):
    """Shared parts, labels and moves of the tables: equal to the reference SQL."""
    monkeypatch.setattr(layout, "EARLY_ROWS", 0)
    con = duckdb.connect()
    for t in ("nation", "customer", "supplier", "part", "orders", "lineitem"):
        con.execute(f"create view {t} as select * from '{data}/{t}.parquet'")
    for name in ("w3_points_lifted", "w3_fields_tagged"):
        assert rows(queries.queries()[name](spark, data)) == sorted(con.execute(queries.oracle_sql()[name]).fetchall())


@pytest.mark.parametrize("form", ["lifted", "tagged"])
@pytest.mark.parametrize("seed", [1, 2])
def test_places_that_lead_to_no_output_are_left_out(spark, monkeypatch, form, seed):
    """Where only the fields are asked for, rounds keep no place from which none is reached; the fields are all there."""
    facts = _heap_facts(seed)
    env = {n: spark.createDataFrame(sorted(f), ", ".join(f"{c} long" for c in reference.COLUMNS[n].split())) for n, f in facts.items()}
    program = parse(programs.HEAP_FLOW)
    program.outputs = ["fpoints"]
    compiled = compile_program(program, form)
    monkeypatch.setattr(layout, "EARLY_ROWS", 0)
    found, want = evaluate(compiled, env), local.evaluate(compiled.program, facts)
    assert rows(found.relations["fpoints"]) == sorted(want["fpoints"])
    ((name, result),) = found.fixpoints.items()
    assert result.partial and name not in found.relations and sum(result.delta_sizes) < len(want["points"])


def test_windows_are_shared_by_views(spark, data):
    """A window over a table that several views read is evaluated once, and gives each the same rows."""
    found = fact_views.facts(spark, data, ["assign", "arg_assign", "array_content", "field_content"])
    for name, f in found.items():
        assert "Window" not in f._jdf.queryExecution().optimizedPlan().toString()
        assert rows(f) == rows(fact_views.query(spark, data, f"select * from {name}", [name]))


@pytest.mark.parametrize("strategy", [baselines.external_loop, baselines.round_batches])
def test_statements_of_baselines_read_evaluated_relations(spark, data, monkeypatch, strategy):
    """A round's statement reads evaluated relations, not the views behind them."""
    monkeypatch.setattr(layout, "EARLY_ROWS", 0)
    plans, sql = [], baselines._sql
    monkeypatch.setattr(baselines, "_sql", lambda *a: plans.append(sql(*a)) or plans[-1])
    texts = []
    materialised = baselines.materialised
    monkeypatch.setattr(baselines, "materialised", lambda df: texts.append(df._jdf.queryExecution().executedPlan().toString() if df is plans[-1] else "") or materialised(df))
    compiled = compile_program(programs.FLOW_REACH)
    edge = {(k, k + 1) for k in range(12)} | {(20, 21), (21, 20)}
    env = {"flow_edge": spark.createDataFrame(sorted(edge), "src long, dst long"), "flow_null": spark.range(9).selectExpr("id % 3 src", "id dst").union(spark.range(1).selectExpr("7", "20L"))}
    found = evaluate(compiled, env, strategy).relations["reach"]
    want = local.evaluate(compiled.program, {"flow_edge": edge, "flow_null": {(k % 3, k) for k in range(9)} | {(7, 20)}})["reach"]
    assert rows(found) == sorted(want)
    assert len(texts) > 5 and not any("Range" in t for t in texts[1:])


@pytest.mark.parametrize("edge", [EDGE, EDGE | {(50, 51), (51, 50)}])
@pytest.mark.parametrize("strategy", [baselines.external_loop, baselines.round_batches])
def test_statements_of_baselines_over_stretches(spark, monkeypatch, strategy, edge):
    """Where facts are many, the statements of baselines keep chains as stretches, also with bars and base tuples in the way; the rows of each round are those of rounds by rows."""
    text = "r(x, y) :- e0(x, y). r(x, y) :- r(x, z), edge(z, y), !bar(x, y).\n.output r"
    facts = {"edge": edge, "e0": {(1, 0), (1, 3), (2, 10), (2, 12), (3, 99), (4, 5), (4, 50)}, "bar": {(1, 5), (2, 12), (3, 100), (4, 6)}}
    env = {n: spark.createDataFrame(sorted(f), "src long, dst long" if n == "edge" else "x long, y long") for n, f in facts.items()}
    compiled = compile_program(text)
    by_rows = evaluate(compiled, env, strategy).fixpoints["r"]
    monkeypatch.setattr(layout, "EARLY_ROWS", 0)
    used, stretches = [], baselines._stretches
    monkeypatch.setattr(baselines, "_stretches", lambda *a: used.append(stretches(*a)) or used[-1])
    found = evaluate(compiled, env, strategy).fixpoints["r"]
    assert rows(found.total) == sorted(local.evaluate(compiled.program, facts)["r"])
    assert (found.rounds, found.delta_sizes) == (by_rows.rounds, by_rows.delta_sizes) and (used[0] is not None) == (edge == EDGE)


@pytest.mark.parametrize("seed", range(1, 5))
def test_rounds_and_rows_without_the_rows(spark, monkeypatch, seed):
    """Counted over kinds of places, the rows of each round are those of rounds over rows; fewer kinds than places are kept."""
    facts = _heap_facts(seed, names=12 + 8 * seed)
    env = {n: spark.createDataFrame(sorted(f), ", ".join(f"{c} long" for c in reference.COLUMNS[n].split())) for n, f in facts.items()}
    compiled = compile_program(programs.HEAP_FLOW)
    by_rows = next(iter(evaluate(compiled, env).fixpoints.values()))
    monkeypatch.setattr(layout, "EARLY_ROWS", 0)
    monkeypatch.setattr(bitsets, "BLOCK", 64)
    monkeypatch.setattr(bitsets, "rounds", None)
    kinds, alike = [], bitsets._alike
    monkeypatch.setattr(bitsets, "_alike", lambda *a: kinds.append(alike(*a)) or kinds[-1])
    found = next(iter(evaluate(compiled, env, fixpoint.sizes_only).fixpoints.values()))
    assert (found.rounds, found.delta_sizes) == (by_rows.rounds, by_rows.delta_sizes)
    assert kinds and kinds[0].max() + 1 < len(kinds[0])
