"""The experiments: python -m ruleweave.workloads.studies STUDY [folder]. Each prints rows of measures as JSON lines.

end_to_end (every workload, compiled against the external loop and the local evaluator), tagged (tagged against lifted, on dispatch and on rings of
growing size), keys (with and without key layout), threads (local[1] against more, in fresh processes), portability (which engine takes
which form), size and depth (chains), components (rounds and seconds by stratum of move checking).
"""

from __future__ import annotations

import json
import os
import sqlite3
import subprocess
import sys
import time
from functools import partial

from pyspark.sql import SparkSession

from ruleweave import metrics
from ruleweave.operators import baselines, fixpoint, keys
from ruleweave.plans.program import compile_program, evaluate
from ruleweave.sqltext.emit import acceptance
from ruleweave.workloads import programs, run

LIMIT = 900


def session(threads: int = 8) -> SparkSession:
    builder = SparkSession.builder.master(f"local[{threads}]").config("spark.sql.shuffle.partitions", str(threads)).config("spark.driver.memory", "12g")
    return builder.config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()


def show(**row) -> None:
    print(json.dumps(row), flush=True)


def _warm(spark: SparkSession) -> None:
    """A small run before the first cell, so that no way pays for the session's start."""
    run.from_heads(run.generated_chains(spark, 100, 5)).total.count()


def _count(relations, outputs) -> dict[str, int]:
    return {o: relations[o].count() for o in outputs}


def end_to_end(spark: SparkSession, folder: str, repeats: int = 1) -> None:
    """Every program by each way, late ones as DNF; rows of all outputs are held against the compiled way's, speedups end in a geometric mean."""
    _warm(spark)
    gains: dict[str, list[float]] = {}
    for name, text in programs.PROGRAMS.items():
        env = {n: f.persist() for n, f in run.inputs(spark, folder, name).items()}
        _count(env, env)
        compiled = compile_program(text)
        ways = {"compiled": fixpoint.seminaive, "external_loop": baselines.external_loop, "round_batches": baselines.round_batches, "arranged": baselines.arranged}
        times, rows = {}, {}
        for way, strategy in ways.items():

            def cell(way=way, strategy=strategy):
                rows[way] = _count(evaluate(compiled, env, strategy).relations, compiled.program.outputs)

            times[way] = metrics.run_with_timeout(cell, LIMIT, repeats, spark)
        base = times["external_loop"]
        for way, t in times.items():
            gain = None if t.dnf or base.dnf else metrics.speedup(base, t)
            if gain is not None:
                gains.setdefault(way, []).append(gain)
            show(study="end_to_end", program=name, way=way, seconds=t.median, deviation=t.deviation, dnf=t.dnf, speedup=gain, rows=None if t.dnf else rows[way], same_rows=None if t.dnf or times["compiled"].dnf else rows[way] == rows["compiled"], compile_seconds=compiled.seconds)
        for f in env.values():
            f.unpersist()
    for way, found in gains.items():
        show(study="end_to_end", way=way, programs=len(found), geomean=metrics.geomean(found))


def tagged(spark: SparkSession, folder: str, width: int = 1000, length: int = 12, repeats: int = 1) -> None:
    env = {n: f.persist() for n, f in run.inputs(spark, folder, "dispatch_calls").items()}
    cases = {"dispatch_calls": (programs.DISPATCH_CALLS, env)} | {f"ring_{m}": (programs.ring(m), run.generated_chains(spark, width, length)) for m in range(2, 7)}
    for name, (text, facts) in cases.items():
        t = {form: metrics.timed(lambda f=form: _count(evaluate(compile_program(text, f), facts).relations, compile_program(text).program.outputs), repeats) for form in ("tagged", "lifted")}
        show(study="tagged", program=name, tagged=t["tagged"].median, lifted=t["lifted"].median, ratio=metrics.ratio(t["tagged"], t["lifted"]))


def with_keys(spark: SparkSession, folder: str, repeats: int = 1) -> None:
    """Every program without keys and with the picked ones: laid out by them, checked, and known to the rounds. Loading and discovery are not timed."""
    _warm(spark)
    gains = []
    for name, text in programs.PROGRAMS.items():
        compiled, plain = compile_program(text), {n: f.persist() for n, f in run.inputs(spark, folder, name).items()}
        _count(plain, plain)
        picked = run.picked_keys(compiled, plain)
        laid = plain | {n: keys.load_checked(plain[n], k) for n, k in picked.items()}
        _count(laid, picked)
        ways = {"without": (plain, fixpoint.seminaive), "with": (laid, partial(fixpoint.seminaive, keys={n: [k] for n, k in picked.items()}))}
        t, rows = {}, {}
        for way, (env, strategy) in ways.items():

            def cell(way=way, env=env, strategy=strategy):
                rows[way] = _count(evaluate(compiled, env, strategy).relations, compiled.program.outputs)

            t[way] = metrics.run_with_timeout(cell, LIMIT, repeats, spark)
        done = not any(x.dnf for x in t.values())
        gains += [metrics.speedup(t["without"], t["with"])] if done and picked else []
        show(study="keys", program=name, keys=picked, seconds_with=t["with"].median, seconds_without=t["without"].median, speedup=metrics.speedup(t["without"], t["with"]) if done else None, same_rows=rows["with"] == rows["without"] if done else None)
        for f in {id(f): f for f in (*plain.values(), *laid.values())}.values():
            f.unpersist()
    show(study="keys", geomean=metrics.geomean(gains) if gains else None)


def threads(folder: str, most: int = 8) -> None:
    for n in (1, most):
        code = f"from ruleweave.workloads import studies, run; import time; s = studies.session({n}); e = run.chain(s, {folder!r}, 'lines'); t = time.perf_counter(); run.from_heads(e).total.count(); print(time.perf_counter() - t)"
        out = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, timeout=LIMIT, check=True)
        show(study="threads", threads=n, seconds=float(out.stdout.split()[-1]))


def portability(spark: SparkSession, folder: str) -> None:
    import duckdb

    cases = {}
    for name, text in programs.PROGRAMS.items():
        compiled = compile_program(text)
        cases[name] = (compiled.definitions, compiled.program.outputs[-1], {n: tuple(f.columns) for n, f in run.inputs(spark, folder, name).items()})
    con, lite = duckdb.connect(), sqlite3.connect(":memory:")
    for _, _, columns in cases.values():
        for n, cols in columns.items():
            for c in (con, lite):
                c.execute(f"create table if not exists {n} ({', '.join(f'{x} bigint' for x in cols)})")
    for program, engine, form, accepted in acceptance(cases, {"duckdb": con.execute, "sqlite": lite.execute}):
        show(study="portability", program=program, engine=engine, form=form, accepted=accepted)


def size(spark: SparkSession, length: int = 10, widths: tuple[int, ...] = (1_000, 10_000, 100_000)) -> None:
    cells = []
    for w in widths:
        started = time.perf_counter()
        n = run.from_heads(run.generated_chains(spark, w, length)).total.count()
        cells.append(time.perf_counter() - started)
        show(study="size", edges=w * length, rows=n, correct=n == w * (length + 1), seconds=cells[-1])
    show(study="size", growth=metrics.growth([w * length for w in widths], cells))


def depth(spark: SparkSession, edges: int = 20_000, lengths: tuple[int, ...] = (5, 10, 20)) -> None:
    cells = []
    for n in lengths:
        started = time.perf_counter()
        result = run.from_heads(run.generated_chains(spark, edges // n, n))
        rows = result.total.count()
        cells.append(time.perf_counter() - started)
        show(study="depth", length=n, rounds=result.rounds, correct=rows == edges // n * (n + 1), seconds=cells[-1])
    show(study="depth", growth=metrics.growth(list(lengths), cells))


def components(spark: SparkSession, folder: str) -> None:
    compiled, found = run.evaluated(spark, folder, "move_check")
    for name, (rounds, widest, seconds) in metrics.per_component(found).items():
        show(study="components", relation=name, rounds=rounds, widest=widest, seconds=seconds)


def main() -> None:
    study, folder = sys.argv[1], sys.argv[2] if len(sys.argv) > 2 else os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.001")
    if study == "threads":
        threads(folder)
        return
    spark = session()
    spark.sparkContext.setLogLevel("ERROR")
    by_folder = {"end_to_end": end_to_end, "tagged": tagged, "keys": with_keys, "portability": portability, "components": components}
    if study in by_folder:
        by_folder[study](spark, folder)
    else:
        {"size": size, "depth": depth}[study](spark)


if __name__ == "__main__":
    main()
