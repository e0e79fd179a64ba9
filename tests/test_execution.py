from __future__ import annotations

import sqlite3

import duckdb
import pytest

from ruleweave.ir.inline import inline_locals
from ruleweave.lang import normalize
from ruleweave.lang.parser import parse
from ruleweave.operators import baselines, fixpoint, keys, local
from ruleweave.operators.partition_local import partition_local
from ruleweave.plans.program import compile_program, evaluate
from ruleweave.sqltext.emit import acceptance, schema_script, statement
from ruleweave.workloads import programs, run


def rows(df):
    return {tuple(r) for r in df.collect()}


def edges(spark, pairs):
    return {"edge": spark.createDataFrame(pairs or [(0, 0)], "src long, dst long").limit(len(pairs))}


CYCLE = [(1, 2), (2, 3), (3, 1), (3, 4), (5, 5)]


@pytest.mark.parametrize("strategy", [fixpoint.seminaive, fixpoint.pivoted, fixpoint.naive, baselines.external_loop, baselines.round_batches, baselines.arranged])
def test_every_strategy_ends_on_cycles(spark, strategy):
    d = compile_program(programs.CLOSURE)
    want = local.evaluate(d.program, {"edge": set(CYCLE)})["path"]
    assert rows(strategy(d.definitions[0], edges(spark, CYCLE)).total) == want


def test_empty_inputs(spark):
    result = fixpoint.seminaive(compile_program(programs.CLOSURE).definitions[0], edges(spark, []))
    assert result.rounds == 1 and result.total.count() == 0


def test_chain_counts(spark):
    env = run.generated_chains(spark, 7, 9)
    heads = run.from_heads(env)
    assert heads.total.count() == 7 * 10 and heads.rounds == 11
    assert run.closure({"edge": env["edge"]}).total.count() == 7 * 9 * 10 // 2


@pytest.mark.parametrize("m", [2, 3])
def test_ring_forms_agree(spark, m):
    env = run.generated_chains(spark, 3, 7)
    assert rows(run.ring_relations(env, m, "lifted")) == rows(run.ring_relations(env, m, "tagged"))


def test_knot_takes_the_tagged_form(spark):
    env = {"start": spark.createDataFrame([(1,)], "x long"), "y_edge": spark.createDataFrame([(1, 2)], "x long, y long"), "z_edge": spark.createDataFrame([(2, 9)], "x long, y long")}
    compiled = compile_program(programs.KNOT)
    assert any(d.padded for d in compiled.definitions)
    want = local.evaluate(compiled.program, {n: rows(f) for n, f in env.items()})
    found = evaluate(compiled, env).relations
    assert {n: rows(found[n]) for n in "abc"} == {n: want[n] for n in "abc"}


def test_padding_with_mixed_types_ends(spark):
    text = '.decl a(x: number, s: symbol) .decl b(s: symbol) .output a, b\na(x, s) :- e(x, s). a(x, s) :- b(s), e(x, _). b(s) :- a(_, s).'
    env = {"e": spark.createDataFrame([(1, "p"), (2, "q")], "x long, s string")}
    want = local.evaluate(normalize.canonical(parse(text)), {"e": rows(env["e"])})
    for form in ("tagged", "lifted"):
        found = evaluate(compile_program(text, form), env).relations
        assert rows(found["a"]) == want["a"] and rows(found["b"]) == want["b"]


def test_negation_and_comparisons(spark):
    text = "r(x, y) :- e(x, y), !e(y, x), x * 2 < y + 10, y >= 2. s(y) :- r(_, y), !none(y)."
    env = {"e": spark.createDataFrame(CYCLE, "x long, y long"), "none": spark.createDataFrame([], "y long")}
    want = local.evaluate(normalize.canonical(parse(text)), {"e": set(CYCLE), "none": set()})
    found = evaluate(compile_program(text), env).relations
    assert rows(found["r"]) == want["r"] and rows(found["s"]) == want["s"]


def test_partition_local_with_a_large_group(spark):
    env = edges(spark, CYCLE)
    parts = spark.createDataFrame([(k, 0 if k < 5 else 1) for k in range(1, 6)], "node long, part long")
    want = local.evaluate(normalize.canonical(parse(programs.CLOSURE)), {"edge": set(CYCLE)})["path"]
    for most in (100, 2):
        assert rows(partition_local(normalize.canonical(parse(programs.CLOSURE)), env, parts, {"edge": "src"}, "path", most)) == want


def test_pivoted_rounds_do_not_shuffle_state(spark):
    d = compile_program(programs.FROM_HEADS).definitions[0]
    with pytest.raises(ValueError):
        fixpoint.pivoted(d, run.generated_chains(spark, 2, 2), pivot="node")


def test_generated_sql_runs_on_two_engines(spark):
    facts = {"edge": CYCLE}
    want = local.evaluate(normalize.canonical(parse(programs.CLOSURE)), {"edge": set(CYCLE)})["path"]
    d = compile_program(programs.CLOSURE).definitions
    con, lite = duckdb.connect(), sqlite3.connect(":memory:")
    for c in (con, lite):
        c.execute("create table edge(src bigint, dst bigint)")
        c.executemany("insert into edge values (?, ?)", facts["edge"])
    columns = {"edge": ("src", "dst")}
    assert set(con.execute(statement(d, "path", "duckdb", columns)).fetchall()) == want
    assert set(lite.execute(statement(d, "path", "sqlite", columns)).fetchall()) == want
    matrix = acceptance({"closure": (d, "path", columns)}, {"duckdb": con.execute, "sqlite": lite.execute})
    assert ("closure", "duckdb", "nested", True) in matrix and ("closure", "sqlite", "inlined", True) in matrix


@pytest.mark.parametrize("form", ["lifted", "tagged"])
def test_generated_sql_of_a_group(spark, data, form):
    compiled = compile_program(programs.DISPATCH_CALLS, form)
    env = run.inputs(spark, data, "dispatch_calls")
    con = duckdb.connect()
    for n, f in env.items():
        con.register(f"v_{n}", f.toPandas())
        con.execute(f"create table {n} as select * from v_{n}")
    columns = {n: tuple(f.columns) for n, f in env.items()}
    found = evaluate(compiled, env).relations
    for out in ("live", "calls"):
        for dialect in ("duckdb", "inlined"):
            assert set(con.execute(statement(compiled.definitions, out, dialect, columns)).fetchall()) == rows(found[out])


def test_dialect_text():
    d = compile_program(programs.DISPATCH_CALLS).definitions
    columns = {"entry_unit": ("unit",), "dyn_site": ("site", "caller", "decl", "nm", "sig"), "subkind": ("sub", "sup"), "unit_impl": ("kind", "nm", "sig", "callee"), "fix_site": ("site", "caller", "callee")}
    assert statement(d, "live", "postgres", columns).count("SELECT * FROM live)") == 1  # one self-reference
    assert "live_now" in statement(d, "live", "postgres", columns)
    assert "MAX RECURSION LEVEL 100" in statement(d, "live", "spark_bounded", columns)
    assert "PRIMARY KEY (a)" in schema_script({"t": [("a", "number")]}, {"t": ("a",)})
    assert "CLUSTERED BY" in schema_script({"t": [("a", "number")]}, {"t": ("a",)}, "spark_bounded")


def test_keys(spark):
    df = spark.createDataFrame([(1, 1, 5), (1, 2, 5), (2, 1, 6)], "a long, b long, c long")
    assert keys.keys(df) == [("a", "b"), ("b", "c")]
    assert keys.FD(("a",), "c") in keys.discover(df) and keys.FD(("c",), "a") in keys.discover(df)
    assert keys.pick_key(keys.keys(df), {"b", "c"}) == ("b", "c")
    with pytest.raises(keys.KeyViolation):
        keys.load_checked(df, ("a",))
    assert keys.load_checked(df, ("a", "b")).count() == 3


def test_lattice_and_general(spark):
    env = edges(spark, CYCLE)
    compiled = compile_program(programs.NON_LINEAR_CLOSURE)
    want = local.evaluate(compiled.program, {"edge": set(CYCLE)})["path"]
    assert rows(evaluate(compiled, env).relations["path"]) == want


def test_inlined_equals_lifted(spark, data):
    env = run.inputs(spark, data, "dispatch_calls")
    d = compile_program(programs.DISPATCH_CALLS).definitions[0]
    assert rows(fixpoint.seminaive(d, env).total) == rows(fixpoint.seminaive(inline_locals(d), env).total)
