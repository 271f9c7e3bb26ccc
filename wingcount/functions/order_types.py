"""The six orders in which the edges after the first one can come.

With the first edge (ux, lx), the others are a = (uy, lx), b = (ux, ly) and c = (uy, ly). The table is the one place that numbers the orders.
"""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

#: The order of a, b and c by type.
ORDERS = {1: "abc", 2: "acb", 3: "bac", 4: "cab", 5: "bca", 6: "cba"}
TYPES = tuple(ORDERS)
#: What a type becomes when the two layers change roles.
TRANSPOSED = {1: 3, 3: 1, 2: 5, 5: 2, 4: 6, 6: 4}


def classify(a: Column, b: Column, c: Column) -> Column:
    """The type of an instance by when a, b and c come (numbers, or structs in which an id breaks ties); null where two are equal."""
    at = {"a": a, "b": b, "c": c}
    out = F.lit(None).cast("int")
    for kind, order in ORDERS.items():
        out = F.when((at[order[0]] < at[order[1]]) & (at[order[1]] < at[order[2]]), kind).otherwise(out)
    return out


def classify_sql(a: str, b: str, c: str) -> str:
    at = {"a": a, "b": b, "c": c}
    return "case " + " ".join(f"when {at[o[0]]} < {at[o[1]]} and {at[o[1]]} < {at[o[2]]} then {k}" for k, o in ORDERS.items()) + " end"


def transposed(kind: Column) -> Column:
    return F.element_at(F.create_map(*(F.lit(x) for pair in TRANSPOSED.items() for x in pair)), kind)


def register(spark: SparkSession) -> None:
    """SQL functions for the classifier and the sampling hash; Spark inlines them."""
    spark.sql(f"create or replace temporary function butterfly_type(a bigint, b bigint, c bigint) returns int return {classify_sql('a', 'b', 'c')}")
    spark.sql("create or replace temporary function u01(seed int, id bigint) returns double return cast(conv(substring(md5(concat_ws(':', seed, id)), 1, 8), 16, 10) as double) / 4294967296d")
