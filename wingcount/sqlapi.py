"""Edges and instances as SQL: temporary views and functions for Spark, and the same relations spelled for DuckDB."""

from __future__ import annotations

from pyspark.sql import SparkSession

from wingcount.functions.order_types import TYPES, classify_sql
from wingcount.functions.order_types import register as register_types
from wingcount.sources.edges import VIEWS, view, view_sql


def register(spark: SparkSession, sf_dir: str, views: tuple[str, ...] = VIEWS) -> None:
    """A temporary view edges_<name> for each graph, and the functions butterfly_type and u01."""
    for name in views:
        view(spark, sf_dir, name).createOrReplaceTempView(f"edges_{name}")
    register_types(spark)


def instances_sql(edges: str, tau: int, ties: str = "strict", starts: str | None = None) -> str:
    """CTEs e (edges) and inst (instances) for DuckDB. `edges` is a query of eid, u, l, t; `starts` a condition on e1."""
    o = (lambda k: f"e{k}.t") if ties == "strict" else (lambda k: f"row(e{k}.t, e{k}.eid)")
    window = lambda k: f"{o(k)} > {o(1)} and e{k}.t <= e1.t + {tau}"
    return f"""with e as materialized ({edges}), inst as (
      select e1.eid as e1, e2.eid as e2, e3.eid as e3, e4.eid as e4, e1.u as ux, e2.u as uy, e1.l as lx, e3.l as ly, e1.t as t1, e2.t as t2, e3.t as t3, e4.t as t4,
        {classify_sql(o(2), o(3), o(4))} as type, greatest(e2.t, e3.t, e4.t) - e1.t as duration
      from e e1
      join e e2 on e2.l = e1.l and e2.u <> e1.u and {window(2)}
      join e e3 on e3.u = e1.u and e3.l <> e1.l and {window(3)}
      join e e4 on e4.u = e2.u and e4.l = e3.l and {window(4)}
      where ({classify_sql(o(2), o(3), o(4))}) is not null {"and " + starts if starts else ""})"""


def six_sql(source: str = "inst", value: str = "count(*)", name: str = "count", kind: str = "bigint", zero: str = "0") -> str:
    """(type, name) for all types from instances."""
    kinds = ", ".join(f"({k})" for k in TYPES)
    return f"select k.type::int as type, coalesce(x.v, {zero})::{kind} as {name} from (values {kinds}) k(type) left join (select type, {value} as v from {source} group by type) x on x.type = k.type"
