"""Fact views: one deterministic SELECT for each input relation, valid in Spark SQL and in DuckDB.

Ids are BIGINT, rows are distinct and free of NULL, window orders are total. A view may use views above it.
"""

from __future__ import annotations

import re
from collections.abc import Collection

from pyspark.sql import DataFrame, SparkSession

from ruleweave.operators.state import stored

BASE_TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "conversations")

# The definitions of the fact views.
VIEWS = {
    "flow_edge": """select src,dst from (select event_id as src, lead(event_id) over (partition by user_id order by ts,event_id) as dst from events) q where dst is not null""",
    "flow_null": """select e.src,e.dst from flow_edge e join events v on v.event_id=e.src where v.event_type='error'""",
    "entry_unit": """select s_suppkey as unit from supplier where s_acctbal<1000""",
    "subkind": """select cast(n_nationkey as bigint) as sub, cast(n_nationkey as bigint) as sup from nation union select cast(n_nationkey as bigint), cast(100+n_regionkey as bigint) from nation union select cast(n_nationkey as bigint), cast(200 as bigint) from nation""",
    "unit_impl": """select distinct cast(s_nationkey as bigint) as kind, cast(substr(p_brand,7) as bigint) as nm, cast(p_size%5 as bigint) as sig, s_suppkey as callee from lineitem join supplier on s_suppkey=l_suppkey join part on p_partkey=l_partkey where l_returnflag='A' and l_quantity<=5""",
    "dyn_site": """select distinct l_orderkey*8+l_linenumber as site, l_suppkey as caller, cast(case when l_linenumber%3=2 then 100+n_regionkey else n_nationkey end as bigint) as decl, cast(substr(p_brand,7) as bigint) as nm, cast(p_size%5 as bigint) as sig from lineitem join orders on o_orderkey=l_orderkey join customer on c_custkey=o_custkey join nation on n_nationkey=c_nationkey join part on p_partkey=l_partkey where l_returnflag='R' and l_quantity<=10""",
    "fix_site": """select distinct l_orderkey*8+l_linenumber as site, l_suppkey as caller, (l_suppkey*7+l_partkey)%(select count(*) from supplier) as callee from lineitem where l_returnflag='N' and l_quantity<=2""",
    "order_next": """select src,dst from (select o_orderkey as src, lead(o_orderkey) over (partition by o_custkey order by o_orderdate,o_orderkey) as dst from orders) q where dst is not null""",
    "alloc": """select l_orderkey as obj, min(l_partkey) as var, min(l_suppkey) as unit from lineitem join orders on o_orderkey=l_orderkey where o_orderpriority='1-URGENT' group by l_orderkey""",
    "live_unit": """select s_suppkey as unit from supplier where s_nationkey<>9""",
    "part_next": """select distinct src,dst,rf,ln from (select l_partkey as src, lead(l_partkey) over (partition by l_orderkey order by l_linenumber,l_partkey,l_suppkey) as dst, l_returnflag as rf, l_linenumber%4 as ln, l_quantity as qty from lineitem) q where dst is not null and qty<=2""",
    "assign": """select distinct src,dst from part_next where rf='N' and ln=0""",
    "cast_assign": """select distinct n.src,n.dst from part_next n join part a on a.p_partkey=n.src join part b on b.p_partkey=n.dst where n.rf='N' and n.ln=1 and a.p_type=b.p_type""",
    "arg_assign": """select distinct src,dst from part_next where rf='N' and ln=2""",
    "ret_assign": """select distinct src,dst from part_next where rf='N' and ln=3""",
    "static_store": """select distinct l_partkey as var, cast(substr(p_brand,7) as bigint) as fld, l_suppkey as unit from lineitem join part on p_partkey=l_partkey where l_returnflag='A' and l_quantity<=1""",
    "static_load": """select distinct cast(substr(p_brand,7) as bigint) as fld, l_partkey as var, l_suppkey as unit from lineitem join part on p_partkey=l_partkey where l_returnflag='R' and l_quantity<=1""",
    "field_load": """select distinct src as base, cast(src%5 as bigint) as fld, dst from part_next where rf='R' and ln=0""",
    "field_content": """select src as obj, cast(dst%5 as bigint) as fld, dst as val from order_next join orders on o_orderkey=src where o_orderstatus='F'""",
    "array_load": """select distinct src as base, dst from part_next where rf='R' and ln=1""",
    "array_content": """select src as obj, dst as val from order_next join orders on o_orderkey=src where o_orderstatus='O'""",
    "recv_call": """select distinct src as base, cast(src%5 as bigint) as sel from part_next where rf='A' and ln=0""",
    "obj_kind": """select o_orderkey as obj, cast(c_nationkey as bigint) as kind from orders join customer on c_custkey=o_custkey""",
    "self_of": """select distinct cast(s_nationkey as bigint) as kind, cast(l_partkey%5 as bigint) as sel, min(l_partkey) as self from lineitem join supplier on s_suppkey=l_suppkey group by s_nationkey,l_partkey%5""",
    "points": """select distinct l_orderkey as obj, l_partkey as var from lineitem""",
    "alloc_in": """select l_orderkey as obj, min(l_suppkey) as unit from lineitem group by l_orderkey""",
    "global_root": """select o_orderkey as obj from orders where o_orderpriority='1-URGENT'""",
    "ret_var": """select distinct l_partkey as var, l_suppkey as unit from lineitem where l_returnflag='R' and l_quantity<=3""",
    "arg_var": """select distinct l_partkey as var, l_suppkey as unit from lineitem where l_returnflag='A' and l_quantity<=3""",
    "recv_var": """select distinct l_partkey as var, l_suppkey as unit from lineitem where l_linestatus='F' and l_quantity<=3""",
    "point": """select event_id as pt, event_type as act, cast(regexp_extract(props,'([0-9]+)',1) as bigint) as leaf from events""",
    "child_path": """select distinct leaf as child, cast(1000+floor(leaf/10) as bigint) as parent from point union select distinct cast(1000+floor(leaf/10) as bigint), cast(2000 as bigint) from point""",
    "moved_base": """select distinct cast(1000+floor(leaf/10) as bigint) as path, pt from point where act='purchase'""",
    "assigned_base": """select distinct cast(1000+floor(leaf/10) as bigint) as path, pt from point where act='signup'""",
    "accessed_base": """select leaf as path, pt from point where act='view'""",
    "line_edge": """select src,dst from (select l_orderkey*64+row_number() over (partition by l_orderkey order by l_linenumber,l_partkey,l_suppkey) as src, 1+l_orderkey*64+row_number() over (partition by l_orderkey order by l_linenumber,l_partkey,l_suppkey) as dst, lead(l_partkey) over (partition by l_orderkey order by l_linenumber,l_partkey,l_suppkey) as nx from lineitem) q where nx is not null""",
    "turn_edge": """select src,dst from (select conv_id*1000+turn as src, lead(conv_id*1000+turn) over (partition by conv_id order by turn) as dst from conversations) q where dst is not null""",
}


def needed(names: list[str], given: Collection[str] = ()) -> list[str]:
    """The named views and those they use, in order of definition, without those given and what only these use."""
    want = set()
    work = list(names)
    while work:
        n = work.pop()
        if n in VIEWS and n not in want and n not in given:
            want.add(n)
            work += [v for v in VIEWS if v != n and f" {v} " in f"{VIEWS[n]} "]
    return [v for v in VIEWS if v in want]


def shared(names: list[str]) -> list[str]:
    """Windows over whole tables that several of the named views read and that are not named themselves."""
    views = needed(names)
    return [v for v in views if v not in names and " over (" in VIEWS[v] and sum(f" {v} " in f"{VIEWS[w]} " for w in views if w != v) > 1]


def common_tables(names: list[str], given: Collection[str] = ()) -> str:
    """The views as entries of a WITH clause, for plain SQL over the base tables."""
    return ", ".join(f"{v} as ({VIEWS[v]})" for v in needed(names, given))


def facts(spark: SparkSession, sf_dir: str, names: list[str]) -> dict[str, DataFrame]:
    """The named views as DataFrames; each base table that they use is opened once, each window that several of them read is evaluated once."""
    opened: dict[str, DataFrame] = {}
    for v in shared(names):
        opened[v] = stored(query(spark, sf_dir, f"select * from {v}", [v], opened))
    return {n: query(spark, sf_dir, f"select * from {n}", [n], opened) for n in names}


def query(spark: SparkSession, sf_dir: str, body: str, names: list[str], opened: dict[str, DataFrame] | None = None) -> DataFrame:
    """A SELECT over fact views and base tables of one folder; the tables are bound as parameters, no session view is made."""
    opened = {} if opened is None else opened
    given = [v for v in VIEWS if v in opened]
    views = common_tables(names, given)
    text = (f"with {views} " if views else "") + body
    used = [t for t in (*BASE_TABLES, *given) if re.search(rf"\b(from|join) {t}\b", text)]
    for t in used:
        if t not in opened:
            opened[t] = spark.read.parquet(f"{sf_dir}/{t}.parquet")
        text = re.sub(rf"\b(from|join) {t}\b", rf"\1 {{{t}}}", text)  # table names after FROM and JOIN become parameters
    return spark.sql(text, **{t: opened[t] for t in used})
