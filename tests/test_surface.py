from __future__ import annotations

import subprocess
import sys
import time
from pathlib import Path

import duckdb
import pytest

from ruleweave import metrics, queries
from ruleweave.functions import table_function
from ruleweave.lang.parser import parse
from ruleweave.operators import fixpoint, state
from ruleweave.plans.keyed import distinct_needed, multiplies
from ruleweave.plans.layout import layout
from ruleweave.plans.program import compile_program, evaluate
from ruleweave.sources import files
from ruleweave.workloads import programs, run


def test_text_and_parquet_files(spark, tmp_path):
    program = parse(".decl edge(src: number, dst: number)\n.input edge\n" + programs.CLOSURE)
    (tmp_path / "edge.facts").write_text("1\t2\n2\t3\n")
    env = files.read_text(spark, program, str(tmp_path))
    found = evaluate(compile_program(program), env).relations
    paths = files.write_outputs(found, program.outputs, str(tmp_path / "out"))
    assert spark.read.parquet(paths[0]).count() == 3
    env["edge"].write.parquet(str(tmp_path / "edge.parquet"))
    assert files.read_parquet(spark, program, str(tmp_path))["edge"].count() == 2


def test_table_function(spark):
    table_function.register(spark)
    spark.createDataFrame([(1, 2), (2, 3)], "src long, dst long").createOrReplaceTempView("rw_edges")
    text = "path(x, y) :- edge(x, y). path(x, y) :- path(x, z), edge(z, y)."
    rows = spark.sql(f"select * from rule_program(table(rw_edges) with single partition, '{text}', 'edge', 'path')").collect()
    assert {tuple(r) for r in rows} == {(1, 2), (2, 3), (1, 3)}


def test_keys_in_plans():
    d = compile_program(programs.FLOW_REACH).definitions[0]
    columns = {"flow_edge": ("src", "dst"), "flow_null": ("src", "dst")}
    step = d.split()[1][0]
    assert multiplies(step, "reach", columns, {}) and not multiplies(step, "reach", columns, {"flow_edge": [("src",)]})
    assert distinct_needed(d, columns, {}) and distinct_needed(d, columns, {"flow_edge": [("src",)]})
    assert not distinct_needed(d, columns, {"flow_edge": [("src",), ("dst",)]})


def test_a_known_key_drops_the_deduplication(spark):
    d = compile_program(programs.CLOSURE).definitions[0]
    env = run.generated_chains(spark, 3, 5)
    for keys, aggregates in ((None, True), ({"edge": [("src",), ("dst",)]}, False)):
        with state.fixed_plans(spark):
            plan = layout(d, {"edge": env["edge"]}, 4, None, keys)
            levels = state.Levels(list(d.columns), list(plan.key), 4)
            delta = state.materialised(levels.ordered(levels.placed(env["edge"])))
            needed = distinct_needed(d, {"edge": ("src", "dst")}, keys or {})
            text = fixpoint.candidates(d, plan, levels, delta, needed)._jdf.queryExecution().executedPlan().toString()
        assert ("HashAggregate" in text) == aggregates
        assert fixpoint.seminaive(d, {"edge": env["edge"]}, keys=keys).total.count() == 3 * 15


@pytest.mark.parametrize(("name", "exchanges"), [("flow_reach", 0), ("dispatch_calls", 1), ("orders", 0), ("orders, nothing broadcast", 1)])
def test_rounds_move_neither_state_nor_static_relations(spark, data, name, exchanges, monkeypatch):
    """A round's plan has at most one exchange, that of the candidates, and none where state is split by an unchanging column and the rest broadcast."""
    if "nothing" in name:
        monkeypatch.setattr("ruleweave.plans.layout.BROADCAST_BYTES", 0)
    plans = []
    plain = state._checkpoint

    def seen(df):
        plans.append(df._jdf.queryExecution().executedPlan().toString())
        return plain(df)

    monkeypatch.setattr(state, "_checkpoint", seen)
    if "orders" in name:
        found = {"x": run.from_heads(run.chain(spark, data, "orders"))}
    else:
        found = run.evaluated(spark, data, name)[1].fixpoints
    rounds = [p for p in plans if "LeftAnti" in p and "Window" not in p]  # without the inputs
    assert rounds and max(f.rounds for f in found.values()) > 2
    assert all(p.count("Exchange hashpartitioning") <= exchanges for p in rounds)


def test_levels_rewrite_rows_seldom(spark):
    with state.fixed_plans(spark):
        levels = state.Levels(["x"], ["x"], 4)
        written = []
        for k in range(60):
            frame, found = state.counted(levels.ordered(levels.placed(spark.range(10 * k, 10 * k + 10).toDF("x"))))
            before = levels.rows
            levels.add(frame, found["rows"])
            written.append(sum(r for r in levels.rows if r not in before))
        assert len(levels.frames) <= state.MOST_LEVELS and levels.total(frame).count() == 600
        assert levels.unknown(levels.placed(spark.range(595, 605).toDF("x"))).count() == 5
    assert sum(written) < 6 * 600


def test_measures():
    t = metrics.timed(lambda: None, 3)
    assert len(t.seconds) == 3 and metrics.geomean([1, 4]) == pytest.approx(2)
    with pytest.raises(ZeroDivisionError):
        metrics.run_with_timeout(lambda: 1 / 0)
    assert metrics.run_with_timeout(lambda: time.sleep(2), 0.2).dnf
    assert metrics.growth([1, 2, 4], [1.0, None, 3.0]) == [(1.0, 1.0), (4.0, 3.0)]


@pytest.mark.parametrize("name", ["w2_edges_lifted", "w8_knot", "w9_closure_partition", "turns_external_loop", "native_cte_turns", "norm_split_disjunction", "op_range_join", "stream_turn_reach", "stream_event_sessions", "fd_keys_nation", "key_pick_w2"])
def test_queries_match_reference_sql(spark, data, name):
    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "conversations"):
        con.execute(f"create view {t} as select * from '{data}/{t}.parquet'")
    result = con.execute(queries.oracle_sql()[name])
    columns = [c[0] for c in result.description]
    want = sorted(map(str, result.fetchall()))
    found = queries.queries()[name](spark, data)
    assert sorted(str(tuple(r)) for r in found.select(columns).collect()) == want


def test_names_need_no_session():
    code = "import __spark_entry__ as e; print(len(e.queries()), len(e.oracle_sql()))"
    out = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, cwd=Path(__file__).resolve().parent.parent, check=True)
    assert min(map(int, out.stdout.split()[-2:])) > 80


def test_every_query_with_sql_exists():
    assert set(queries.oracle_sql()) <= set(queries.queries())
