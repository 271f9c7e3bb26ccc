"""Temporal bipartite edges: one frame of (eid, u, l, t), all longs. The layers are columns, so equal ids on both sides never mix."""

from __future__ import annotations

import datetime
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from wingcount.functions.hashing import key_hash, key_hash_sql

SCHEMA = T.StructType([T.StructField(c, T.LongType(), False) for c in ("eid", "u", "l", "t")])
HOUR, DAY = 3_600_000_000, 86_400_000_000
#: Numbers of the event kinds.
EVENT_KINDS = {"click": 0, "error": 1, "purchase": 2, "signup": 3, "view": 4}
#: Ten edges that satisfy every stated fact of the worked example.
TOY = [(0, 1, 1, 10), (1, 2, 1, 11), (2, 2, 2, 12), (3, 2, 3, 13), (4, 1, 2, 15), (5, 1, 3, 20), (6, 3, 4, 14), (7, 3, 5, 16), (8, 4, 5, 17), (9, 4, 4, 19)]


def edges_from_rows(spark: SparkSession, rows: list[tuple[int, int, int, int]]) -> DataFrame:
    return spark.createDataFrame(rows, SCHEMA)


def toy(spark: SparkSession) -> DataFrame:
    return edges_from_rows(spark, TOY)


def instant(c: Column, kind: T.DataType) -> Column:
    """Any time column as a long: timestamps in microseconds, dates in days, numbers as they are."""
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        return F.unix_micros(c.cast("timestamp"))
    return F.datediff(c, F.lit("1970-01-01").cast("date")).cast("long") if isinstance(kind, T.DateType) else c.cast("long")


def duration(tau: int | datetime.timedelta, unit: str = "micros") -> int:
    """A duration in the unit of the view's time."""
    if isinstance(tau, datetime.timedelta):
        tau = tau // datetime.timedelta(microseconds=1) if unit == "micros" else tau // datetime.timedelta(days=1)
    if tau < 0:
        raise ValueError("a duration is not negative")
    return int(tau)


def from_df(df: DataFrame, upper: str, lower: str, time: str, edge_id: str | None = None, nulls: str = "drop", duplicates: str = "keep") -> DataFrame:
    """Edges of any frame. String nodes become 60-bit hashes; without an edge id, the id is a hash of the other columns and of
    the edge's number among equal ones, so repeated edges are told apart (the 60 bits clash once in some 10^9 edges: give ids to larger graphs).
    nulls: 'drop' or 'error'. duplicates: 'keep' repeated (u, l, t), or 'collapse' them into one."""
    node = lambda c: F.when(F.col(c).isNotNull(), key_hash(c)) if isinstance(df.schema[c].dataType, T.StringType) else F.col(c).cast("long")
    out = df.select((F.col(edge_id).cast("long") if edge_id else F.lit(None).cast("long")).alias("eid"), node(upper).alias("u"), node(lower).alias("l"), instant(F.col(time), df.schema[time].dataType).alias("t"))
    missing = reduce(lambda a, b: a | b, (F.col(c).isNull() for c in ("u", "l", "t")))
    if nulls == "error":
        out = out.withColumn("t", F.when(missing, F.raise_error(F.lit("an edge has a null")).cast("long")).otherwise(F.col("t")))
    else:
        out = out.where(~missing)
    if edge_id is None and duplicates == "collapse":
        return out.select("u", "l", "t").distinct().select(key_hash("u", "l", "t").alias("eid"), "u", "l", "t")
    if edge_id is None:
        out = out.groupBy("u", "l", "t").agg(F.count(F.lit(1)).alias("n")).withColumn("k", F.explode(F.sequence(F.lit(1), "n"))).select(key_hash("u", "l", "t", "k").alias("eid"), "u", "l", "t")
    return out.groupBy("u", "l", "t").agg(F.min("eid").alias("eid")).select("eid", "u", "l", "t") if duplicates == "collapse" else out


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


_ITEM = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


def _day(c: str) -> Column:
    return F.datediff(F.col(c).cast("date"), F.lit("1970-01-01").cast("date")).cast("long")


def _ranked(df: DataFrame, by: tuple[str, ...]) -> DataFrame:
    """Edge ids as ranks over the composite key, for comparisons on small tables: it needs all rows in one order."""
    return df.withColumn("eid", (F.row_number().over(Window.orderBy(*by)) - 1).cast("long"))


def view(spark: SparkSession, sf_dir: str, name: str, ids: str = "hash") -> DataFrame:
    """Edges of one of the given tables' graphs (see VIEWS). ids='rank' numbers composite keys densely instead of hashing them."""
    if name in ("euk", "eut"):
        events = load(spark, sf_dir, "events", "event_id", "ts", "user_id", "props" if name == "euk" else "event_type")
        kinds = F.create_map(*(F.lit(x) for pair in EVENT_KINDS.items() for x in pair))
        lower = F.get_json_object("props", "$.k").cast("long") if name == "euk" else F.element_at(kinds, F.col("event_type")).cast("long")
        return events.select(F.col("event_id").cast("long").alias("eid"), F.col("user_id").cast("long").alias("u"), lower.alias("l"), F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    items = load(spark, sf_dir, "lineitem", *_ITEM, "l_shipdate")
    day = "l_shipdate"
    if name != "lsp":
        items = items.join(load(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
        day = "o_orderdate" if name == "ocp" else day
    if name == "nat":
        items = items.join(load(spark, sf_dir, "customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
        items = items.join(load(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    upper, lower = {"lsp": ("l_suppkey", F.col("l_partkey")), "ocp": ("o_custkey", F.col("l_partkey")), "ocs": ("o_custkey", F.col("l_suppkey")), "nat": ("c_nationkey", F.col("s_nationkey") + 100)}[name]
    out = items.withColumns({"eid": key_hash(*_ITEM), "u": F.col(upper).cast("long"), "l": lower.cast("long"), "t": _day(day)})
    if ids == "rank":
        out = _ranked(out, ("t", *_ITEM))
    return out.select("eid", "u", "l", "t")


VIEWS = ("euk", "eut", "lsp", "ocp", "ocs", "nat")


def view_sql(name: str) -> str:
    """The view's edges in DuckDB's SQL."""
    if name == "euk":
        return "select event_id::bigint as eid, user_id::bigint as u, json_extract_string(props, '$.k')::bigint as l, epoch_us(ts)::bigint as t from events"
    if name == "eut":
        kinds = " ".join(f"when '{k}' then {v}" for k, v in EVENT_KINDS.items())
        return f"select event_id::bigint as eid, user_id::bigint as u, (case event_type {kinds} end)::bigint as l, epoch_us(ts)::bigint as t from events"
    eid = key_hash_sql(*_ITEM)
    day = "o_orderdate" if name == "ocp" else "l_shipdate"
    upper, lower = {"lsp": ("l_suppkey", "l_partkey"), "ocp": ("o_custkey", "l_partkey"), "ocs": ("o_custkey", "l_suppkey"), "nat": ("c_nationkey", "s_nationkey + 100")}[name]
    source = "lineitem" + (" join orders on l_orderkey = o_orderkey" if name != "lsp" else "")
    source += " join customer on o_custkey = c_custkey join supplier on l_suppkey = s_suppkey" if name == "nat" else ""
    return f"select {eid} as eid, ({upper})::bigint as u, ({lower})::bigint as l, date_diff('day', date '1970-01-01', {day}::date)::bigint as t from {source}"


def read_edges(spark: SparkSession, path: str, fmt: str = "csv", cols: tuple[str, str, str] = ("u", "l", "t"), sep: str = ",", comment: str = "%") -> DataFrame:
    """Edge lists: 'csv' and 'text' (fields apart by white space) in the order of `cols`, 'json' and 'parquet' by name."""
    if fmt == "text":
        part = F.split(F.trim("value"), r"\s+")
        raw = spark.read.text(path).where(~F.col("value").startswith(comment) & (F.trim("value") != "")).select(*(F.get(part, F.lit(k)).cast("long").alias(c) for k, c in enumerate(cols)))
    elif fmt == "csv":
        raw = spark.read.csv(path, schema=", ".join(f"{c} long" for c in cols), sep=sep, comment=comment)
    else:
        raw = spark.read.schema(", ".join(f"{c} long" for c in cols)).format(fmt).load(path)
    return from_df(raw.select("u", "l", "t"), "u", "l", "t")


def write_edges(edges: DataFrame, path: str, width: int, by: str = "u", parts: int | None = None) -> None:
    """Edges as Parquet, a folder for each time bucket, ordered by node and time within, so that slices of time and nodes are read alone."""
    bucketed = edges.withColumn("tb", F.floor(F.col("t") / width))
    spread = bucketed.repartition(parts, "tb", by) if parts else bucketed.repartition("tb", by)
    spread.sortWithinPartitions("tb", by, "t").write.partitionBy("tb").parquet(path)
