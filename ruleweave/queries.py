"""The library's queries by name, with reference SQL: workloads by strategy and form, baselines, rewrites, keys and operators."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial
from itertools import combinations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ruleweave import metrics
from ruleweave.functions import relational
from ruleweave.ir.inline import inline_locals
from ruleweave.ir.rewrite import demand, linearize_closure
from ruleweave.lang import normalize
from ruleweave.lang.parser import parse
from ruleweave.operators import baselines, fixpoint, keys
from ruleweave.operators.state import all_materialised, rows_of, union_all
from ruleweave.plans.program import compile_program, evaluate
from ruleweave.sources.facts import facts, query
from ruleweave.streaming import incremental
from ruleweave.workloads import programs, reference, run

Query = Callable[[SparkSession, str], DataFrame]


def _relation(name: str, relation: str, form: str = "lifted", strategy=fixpoint.seminaive) -> Query:
    return lambda spark, sf_dir: run.evaluated(spark, sf_dir, name, form, strategy, [relation])[1].relations[relation]


def _inlined(defn, env):
    return fixpoint.seminaive(inline_locals(defn), env)


def _turns(strategy) -> Query:
    return lambda spark, sf_dir: run.from_heads(run.chain(spark, sf_dir, "turns"), strategy).total


def _turns_native(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.native_bounded(compile_program(programs.FROM_HEADS).definitions, "seen", run.chain(spark, sf_dir, "turns"))


def _turns_local(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Python sets on the driver; where the facts are too many for it, Python sets for each group of conversations."""
    program, env = compile_program(programs.FROM_HEADS).program, run.chain(spark, sf_dir, "turns")
    env = dict(zip(env, all_materialised(env.values()), strict=True))
    if sum(rows_of(f) for f in env.values()) > baselines.MOST_LOCAL_FACTS:
        nodes = env["edge"].select(F.col("src").alias("node")).union(env["edge"].select("dst")).union(env["head"].select("node")).distinct()
        # a node is a conversation's number times 1,000 and a turn; if an edge leads out of its thousand, all nodes are one group
        thousand = lambda c: F.floor(F.col(c) / 1000)
        apart = env["edge"].filter(thousand("src") != thousand("dst")).limit(1).isEmpty()
        parts = nodes.select("node", (thousand("node") if apart else F.lit(0)).cast("bigint").alias("part"))
        return run.partition_local(program, env, parts, {"edge": "src", "head": "node"}, "seen")
    found = baselines.local_oracle(program, env)
    return spark.createDataFrame(sorted(found["seen"]), "root long, node long")


def _turns_lattice(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Least number of steps from a head to each node: min inside the recursion."""
    env = run.chain(spark, sf_dir, "turns")
    step = lambda d: d.join(env["edge"], d.node == env["edge"].src).select(F.col("dst").alias("node"), (F.col("steps") + 1).alias("steps"))
    return fixpoint.lattice(env["head"].select("node", F.lit(0).cast("bigint").alias("steps")), step, ["node"], "steps").total


def _turns_general(spark: SparkSession, sf_dir: str) -> DataFrame:
    edge = {"edge": run.chain(spark, sf_dir, "turns")["edge"]}
    return evaluate(compile_program(programs.NON_LINEAR_CLOSURE), edge).relations["path"]


def _turns_linearized(spark: SparkSession, sf_dir: str) -> DataFrame:
    program = linearize_closure(normalize.canonical(parse(programs.NON_LINEAR_CLOSURE)))
    return evaluate(compile_program(program), {"edge": run.chain(spark, sf_dir, "turns")["edge"]}).relations["path"]


def _demand(spark: SparkSession, sf_dir: str) -> DataFrame:
    program = demand(normalize.canonical(parse(programs.CLOSURE)), "path", 0, 1000)
    return evaluate(compile_program(program), {"edge": run.chain(spark, sf_dir, "turns")["edge"]}).relations["path"]


def _knot(spark: SparkSession, sf_dir: str) -> DataFrame:
    env = {n: query(spark, sf_dir, q, []) for n, q in reference.KNOT_VIEWS.items()}
    found = evaluate(compile_program(programs.KNOT), env).relations
    return found["a"].select(F.lit("a").alias("rel"), "x").unionByName(found["b"].select(F.lit("b").alias("rel"), "x")).unionByName(found["c"].select(F.lit("c").alias("rel"), "x"))


def _trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    env = {n: query(spark, sf_dir, q, ["flow_edge"] if "flow_edge" in q else []) for n, q in reference.TRACE_VIEWS.items()}
    return evaluate(compile_program(programs.TRACE_RULES), env).relations["points"]


def _summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The measures of each program's text and the rows of its input relations in the tables."""
    rows = [(n, *metrics.program_summary(compile_program(t))) for n, t in sorted(programs.PROGRAMS.items())]
    texts = spark.createDataFrame(rows, "program string, n_edb int, n_idb int, n_scc int, n_rules int")
    views = facts(spark, sf_dir, sorted({v for names in programs.INPUTS.values() for v in names}))
    counts = union_all([f.agg(F.count(F.lit(1)).alias("n")).select(F.lit(v).alias("relation"), "n") for v, f in views.items()])
    uses = spark.createDataFrame([(n, v) for n, names in programs.INPUTS.items() for v in names], "program string, relation string")
    return texts.join(uses.join(counts, "relation").groupBy("program").agg(F.sum("n").alias("n_facts")), "program")


def _key_rows(table: str) -> Query:
    def go(spark, sf_dir):
        df = spark.read.parquet(f"{sf_dir}/{table}.parquet").select(KEY_TABLES[table].split())
        return spark.createDataFrame([(",".join(k),) for k in keys.keys(df)], "key_columns string")

    return go


def _fd_rows(table: str) -> Query:
    def go(spark, sf_dir):
        df = spark.read.parquet(f"{sf_dir}/{table}.parquet")
        return spark.createDataFrame([(",".join(f.left), f.right) for f in keys.discover(df)], "determinant string, determined string")

    return go


def _pick(name: str) -> Query:
    """The key of each input relation that recursion reads, over all its columns; an empty text where there is none."""

    def go(spark, sf_dir):
        compiled = compile_program(programs.PROGRAMS[name])
        env = dict(zip(programs.INPUTS[name], all_materialised(run.inputs(spark, sf_dir, name).values()), strict=True))
        picked = run.picked_keys(compiled, env)
        used = keys.recursive_columns(compiled.definitions, {n: tuple(f.columns) for n, f in env.items()})
        return spark.createDataFrame([(n, ",".join(picked.get(n, ()))) for n in sorted(used)], "relation string, key_columns string")

    return go


def _program_rounds(name: str) -> Query:
    """Rounds (the last one finds nothing) and rows of every recursive definition of a program."""

    def go(spark, sf_dir):
        found = run.evaluated(spark, sf_dir, name, strategy=fixpoint.sizes_only)[1].fixpoints
        return spark.createDataFrame([(n, r.rounds, sum(r.delta_sizes)) for n, r in sorted(found.items())], "relation string, rounds int, n_rows long")

    return go


def _rounds(kind: str) -> Query:
    def go(spark, sf_dir):
        result = run.from_heads(run.chain(spark, sf_dir, kind))
        return spark.createDataFrame([(kind, result.rounds - 2, sum(result.delta_sizes))], "chains string, longest long, n_rows long")

    return go


# Programs that need one rewrite each: text, the relation asked for, and the same in SQL.
REWRITE_CASES = {
    "split_heads": ("p(x), q(x) :- flow_null(x, _).\nr(x) :- p(x), q(x).\n.output r", "r", "select distinct src as x from flow_null"),
    "split_disjunction": ("r(x) :- (flow_null(x, _); flow_null(_, x)), x > 100; flow_null(x, x).\n.output r", "r", "select src as x from flow_null where src > 100 union select dst from flow_null where dst > 100 union select src from flow_null where src = dst"),
    "distinct_head": ("r(x, x, 7) :- flow_null(x, _).\n.decl r(a: number, b: number, c: number)\n.output r", "r", "select distinct src as a, src as b, cast(7 as bigint) as c from flow_null"),
    "lift_terms": ("r(x) :- flow_null(x, y), flow_edge(y, y + 2); flow_null(x, 40).\n.output r", "r", "select n.src as x from flow_null n join flow_edge e on e.src = n.dst and e.dst = n.dst + 2 union select src from flow_null where dst = 40"),
    "name_wildcards": ("r(x) :- flow_null(x, _), flow_edge(_, x).\n.output r", "r", "select distinct n.src as x from flow_null n join flow_edge e on e.dst = n.src"),
    "drop_dead": ("dead(x) :- flow_edge(x, _).\nr(x) :- flow_null(_, x).\n.output r", "r", "select distinct dst as x from flow_null"),
}


def _rewrite(case: str) -> Query:
    text, relation, _ = REWRITE_CASES[case]
    return lambda spark, sf_dir: evaluate(compile_program(text), facts(spark, sf_dir, ["flow_null", "flow_edge"])).relations[relation]


def _comparison(op: str) -> Query:
    text = f"r(x, y) :- flow_null(x, y), x % 10 {op} y % 10.\n.output r"
    return lambda spark, sf_dir: evaluate(compile_program(text), facts(spark, sf_dir, ["flow_null"])).relations["r"]


# The columns of each table in the order that names of sets follow (events without its value): keys of every size, dependencies of every size.
KEY_TABLES = {
    "region": "r_regionkey r_name", "nation": "n_nationkey n_name n_regionkey", "supplier": "s_suppkey s_name s_nationkey s_acctbal",
    "customer": "c_custkey c_name c_nationkey c_acctbal c_mktsegment", "orders": "o_orderkey o_custkey o_orderstatus o_totalprice o_orderdate o_orderpriority",
    "part": "p_partkey p_name p_brand p_type p_size p_retailprice", "events": "event_id user_id ts event_type props", "conversations": "conv_id turn role text",
}
FD_TABLES = ("region", "nation", "supplier", "customer")
WORKLOADS = {"w1": "flow_reach", "w2": "dispatch_calls", "w3": "heap_flow", "w4": "escape_scope", "w5": "move_check"}


def _sets(columns: list[str]) -> list[tuple[str, ...]]:
    return [s for n in range(1, len(columns) + 1) for s in combinations(columns, n)]


def _key_sql(table: str) -> str:
    """Brute force: every set is counted; those without a smaller key inside remain."""
    rows = " union all ".join(f"select [{', '.join(repr(c) for c in s)}] k from {table} having count(distinct ({', '.join(s)},)) = count(*)" for s in _sets(KEY_TABLES[table].split()))
    return f"with c as ({rows}) select array_to_string(k, ',') key_columns from c where not exists (select 1 from c d where d.k <> c.k and len(list_intersect(d.k, c.k)) = len(d.k))"


def _fd_sql(table: str) -> str:
    """Brute force: every set and column; those without a smaller set inside remain."""
    columns = KEY_TABLES[table].split()
    rows = " union all ".join(
        f"select [{', '.join(repr(c) for c in s)}] l, '{r}' r from {table} having count(distinct ({', '.join(s)},)) = count(distinct ({', '.join((*s, r))}))" for s in _sets(columns) for r in columns if r not in s
    )
    return f"with c as ({rows}) select array_to_string(l, ',') determinant, r determined from c where not exists (select 1 from c d where d.r = c.r and d.l <> c.l and len(list_intersect(d.l, c.l)) = len(d.l))"


def _pick_sql(name: str) -> str:
    """Brute force: for each relation of the recursion the first of the smallest keys among the columns that recursion uses."""
    compiled = compile_program(programs.PROGRAMS[name])
    columns = {n: reference.COLUMNS[n].split() for n in programs.INPUTS[name]}
    used = keys.recursive_columns(compiled.definitions, {n: tuple(c) for n, c in columns.items()})
    rows = []
    for n in sorted(used):
        sets = [s for s in _sets(columns[n]) if set(s) <= used[n]]
        rows += [f"select '{n}' relation, '{','.join(s)}' key_columns, {k} o from {n} having count(distinct ({', '.join(s)},)) = count(*)" for k, s in enumerate(sets)]
        rows.append(f"select '{n}', '', {len(sets)}")
    return reference.with_views(sorted(used), f"c as ({' union all '.join(rows)})", "select relation, arg_min(key_columns, o) key_columns from c group by relation")


def queries() -> dict[str, Query]:
    q: dict[str, Query] = {
        "w1_flow_reach": _relation("flow_reach", "reach"),
        "w1_flow_reach_pivot": _relation("flow_reach", "reach", strategy=fixpoint.pivoted),
        "w1_flow_reach_partition": run.flow_reach_local,
        "w1_flow_reach_keyed": run.flow_reach_keyed,
        "w8_knot": _knot,
        "w9_closure": lambda spark, sf_dir: run.closure({"edge": facts(spark, sf_dir, ["order_next"])["order_next"]}).total,
        "w9_closure_partition": run.heap_local,
        "w10_trace": _trace,
        "native_cte_turns": _turns_native,
        "turns_seminaive": _turns(fixpoint.seminaive),
        "turns_pivot": _turns(fixpoint.pivoted),
        "turns_naive": _turns(fixpoint.naive),
        "turns_external_loop": _turns(baselines.external_loop),
        "turns_round_batches": _turns(baselines.round_batches),
        "turns_arranged": _turns(baselines.arranged),
        "turns_local_oracle": _turns_local,
        "turns_lattice_min": _turns_lattice,
        "turns_non_linear": _turns_general,
        "turns_linearized": _turns_linearized,
        "turns_demand": _demand,
        "summary_programs": _summary,
        "rounds_turns": _rounds("turns"),
        "rounds_lines": _rounds("lines"),
        "stream_event_windows": incremental.event_windows,
        "stream_event_sliding": incremental.event_sliding,
        "stream_event_sessions": incremental.event_sessions,
        "stream_turn_reach": incremental.turn_reach,
    }
    for short, name in WORKLOADS.items():
        q[f"key_pick_{short}"] = _pick(name)
        q[f"rounds_{short}"] = _program_rounds(name)
    for way, strategy in (("naive", fixpoint.naive), ("external", baselines.external_loop), ("batches", baselines.round_batches), ("arranged", baselines.arranged)):
        q[f"w1_flow_reach_{way}"] = _relation("flow_reach", "reach", strategy=strategy)
        q[f"w2_edges_{way}"] = _relation("dispatch_calls", "calls", strategy=strategy)
    for form in ("lifted", "tagged", "inlined"):
        strategy = _inlined if form == "inlined" else fixpoint.seminaive
        kind = "tagged" if form == "tagged" else "lifted"
        q[f"w2_units_{form}"] = _relation("dispatch_calls", "live", kind, strategy)
        q[f"w2_edges_{form}"] = _relation("dispatch_calls", "calls", kind, strategy)
    for form in ("lifted", "tagged"):
        q[f"w3_points_{form}"] = _relation("heap_flow", "points", form)
        q[f"w3_fields_{form}"] = _relation("heap_flow", "fpoints", form)
        for m in range(2, 7):
            q[f"w7_ring_m{m}_{form}"] = partial(_ring, m, form)
    for short, relation in (("heap", "heap"), ("global", "global"), ("live", "live_alloc"), ("escapes", "escapes"), ("captured", "captured")):
        q[f"w4_{short}"] = _relation("escape_scope", relation)
    for relation in ("ancestor", "moved", "assigned", "uninit", "errors"):
        q[f"w5_{relation}"] = _relation("move_check", relation)
    for kind in programs.CHAINS:
        q[f"w6_{kind}_heads"] = partial(_chains, kind, "heads")
        q[f"w6_{kind}_closure"] = partial(_chains, kind, "closure")
    for what in ("heads", "closure"):
        q[f"w6_events_{what}_partition"] = partial(_events_local, what)
    for case in REWRITE_CASES:
        q[f"norm_{case}"] = _rewrite(case)
    for word, op in relational.COMPARISONS.items():
        q[f"op_compare_{word}"] = _comparison(op)
    for table in KEY_TABLES:
        q[f"fd_keys_{table}"] = _key_rows(table)
    for table in FD_TABLES:
        q[f"fd_deps_{table}"] = _fd_rows(table)
    q |= {f"op_{n}": f for n, f in relational.queries().items()}
    return q


def _ring(m: int, form: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return run.ring_relations(run.chain(spark, sf_dir, "turns"), m, form)


def _chains(kind: str, what: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    env = run.chain(spark, sf_dir, kind)
    return run.from_heads(env).total if what == "heads" else run.closure({"edge": env["edge"]}).total


def _events_local(what: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """The deep chains with all rounds inside each user's events."""
    env = run.chain(spark, sf_dir, "events")
    text, out = (programs.FROM_HEADS, "seen") if what == "heads" else (programs.CLOSURE, "path")
    if what == "closure":
        env.pop("head")
    return run.partition_local(compile_program(text).program, env, run.users_of_events(spark, sf_dir), {"edge": "src"} | ({"head": "node"} if what == "heads" else {}), out)


def oracle_sql() -> dict[str, str]:
    r = reference
    o = dict(r.W)
    for way in ("pivot", "partition", "keyed", "naive", "external", "batches", "arranged"):
        o[f"w1_flow_reach_{way}"] = o["w1_flow_reach"]
    for way in ("naive", "external", "batches", "arranged"):
        o[f"w2_edges_{way}"] = r.W["w2_edges"]
    for form in ("lifted", "tagged", "inlined"):
        o[f"w2_units_{form}"], o[f"w2_edges_{form}"] = r.W["w2_units"], r.W["w2_edges"]
    for form in ("lifted", "tagged"):
        o[f"w3_points_{form}"], o[f"w3_fields_{form}"] = r.W["w3_points"], r.W["w3_fields"]
        for m in range(2, 7):
            o[f"w7_ring_m{m}_{form}"] = r.ring_of("turns", m)
    for n in ("w2_units", "w2_edges", "w3_points", "w3_fields"):
        del o[n]
    for kind in programs.CHAINS:
        o[f"w6_{kind}_heads"], o[f"w6_{kind}_closure"] = r.heads(kind), r.closure(kind)
    o["w6_events_heads_partition"], o["w6_events_closure_partition"] = r.heads("events"), r.closure("events")
    for n in ("native_cte_turns", "turns_seminaive", "turns_pivot", "turns_naive", "turns_external_loop", "turns_round_batches", "turns_arranged", "turns_local_oracle", "stream_turn_reach"):
        o[n] = r.heads("turns")
    o["turns_non_linear"] = o["turns_linearized"] = r.closure("turns")
    o["turns_demand"] = f"select * from ({r.closure('turns')}) where src = 1000"
    o["turns_lattice_min"] = f"select node, cast(node - root as bigint) steps from ({r.heads('turns')})"
    o["w9_closure"] = o["w9_closure_partition"] = r.closure("orders")
    o["w8_knot"], o["w10_trace"], o["summary_programs"] = r.KNOT_SQL, r.TRACE_SQL, r.SUMMARY_SQL
    o["rounds_turns"] = f"select 'turns' chains, max(node - root) longest, count(*) n_rows from ({r.heads('turns')})"
    o["rounds_lines"] = f"select 'lines' chains, max(node - root) longest, count(*) n_rows from ({r.heads('lines')})"
    for short, name in WORKLOADS.items():
        o[f"key_pick_{short}"] = _pick_sql(name)
    for table in FD_TABLES:
        o[f"fd_deps_{table}"] = _fd_sql(table)
    for case, (_, _, sql) in REWRITE_CASES.items():
        o[f"norm_{case}"] = r.with_views(["flow_null", "flow_edge"], "one as (select 1)", sql)
    for word, op in relational.COMPARISONS.items():
        o[f"op_compare_{word}"] = r.with_views(["flow_null"], "one as (select 1)", f"select distinct src as x, dst as y from flow_null where src % 10 {'<>' if op == '!=' else op} dst % 10")
    for table in KEY_TABLES:
        o[f"fd_keys_{table}"] = _key_sql(table)
    o["stream_event_windows"], o["stream_event_sliding"], o["stream_event_sessions"] = incremental.EVENT_WINDOWS_SQL, incremental.EVENT_SLIDING_SQL, incremental.EVENT_SESSIONS_SQL
    o |= {f"op_{n}": s for n, s in relational.oracle_sql().items()}
    return o
