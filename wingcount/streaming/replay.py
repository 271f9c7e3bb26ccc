"""Streams of edges: the event table replayed from files, window counts, wedges by a stream-stream join, and the six counts kept up to date."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wingcount.functions.hashing import u01
from wingcount.operators.counting import COUNTS, added, long_form
from wingcount.operators.joins import BLOCK, lazily
from wingcount.operators.ranked import ranked
from wingcount.shared import new_path, settled, ship
from wingcount.sources.edges import HOUR, view, view_sql
from wingcount.sqlapi import instances_sql, six_sql

EDGE = "eid long, u long, l long, t long, ts timestamp"
#: Cells of time that tau is cut into for a join of streams, and the most edges that a task holds to make blocks of them.
CELLS, HELD = 6, 1 << 20


def slices(edges: DataFrame, width: int, name: str = "replay") -> str:
    """Edges written in files that follow each other in time; a folder's modification times keep that order."""
    path = new_path(edges.sparkSession, name)
    edges = settled(edges)
    low, high = edges.agg(F.min("t"), F.max("t")).first()
    if low is None:
        edges.withColumn("ts", F.timestamp_micros("t")).write.mode("append").parquet(path)
        return path
    for at in range(low, high + 1, width):
        own = edges.where(F.col("t").between(at, at + width - 1)).withColumn("ts", F.timestamp_micros("t"))
        own.coalesce(1).write.mode("append").parquet(path)
    return path


def source(spark: SparkSession, path: str, delay: str | None = None, files: int = 4) -> DataFrame:
    df = spark.readStream.schema(EDGE).option("maxFilesPerTrigger", files).parquet(path)
    return df.withWatermark("ts", delay) if delay else df


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """All that a stream emits once its source is used up, as files of the shared folder: a folder a batch, so that one that is run again replaces its own. In mode
    'complete' the last batch holds everything."""
    spark, path, seen = stream.sparkSession, new_path(stream.sparkSession, "drained"), []

    def keep(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite").option("compression", "zstd").parquet(f"{path}/{n}")
        seen.append(f"{path}/{n}")

    q = stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", new_path(spark, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    if not seen:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*(dict.fromkeys(seen) if mode == "append" else seen[-1:]))


def tumbling(stream: DataFrame, length: str, slide: str | None = None) -> DataFrame:
    w = F.window("ts", length, slide)
    return stream.groupBy(w).agg(F.count(F.lit(1)).alias("n")).select(F.unix_micros("window.start").alias("begin"), "n")


def sessions(stream: DataFrame, gap: str) -> DataFrame:
    return stream.groupBy("u", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select("u", F.unix_micros("w.start").alias("begin"), "n")


def blocks(stream: DataFrame, cut: int) -> DataFrame:
    """(l, cell, low, high, edges): a task's edges of one lower node and one cell of time, BLOCK at most to a row and in the order of time, each batch of a stream on its own."""

    def packed(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        rows = pa.Table.from_batches(held).combine_chunks()
        node, t = rows["l"].to_numpy(), rows["t"].to_numpy()
        cell = t // cut
        by = np.lexsort((t, cell, node))
        node, cell, t = node[by], cell[by], t[by]
        new = np.concatenate([[True], (node[1:] != node[:-1]) | (cell[1:] != cell[:-1])])
        place = np.arange(len(by))
        place -= place[new][np.cumsum(new) - 1]
        first = np.flatnonzero(place % BLOCK == 0)
        last = np.append(first[1:], len(by)) - 1
        own = rows.take(pa.array(by)).select(["eid", "u", "t"]).combine_chunks().to_struct_array()
        own = own.combine_chunks() if isinstance(own, pa.ChunkedArray) else own
        lists = pa.ListArray.from_arrays(pa.array(np.append(first, len(by)), pa.int32()), own)
        return pa.RecordBatch.from_arrays([*(pa.array(x) for x in (node[first], cell[first], t[first], t[last])), lists], ["l", "cell", "low", "high", "edges"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for batch in batches:
            held, n = [*held, batch], n + batch.num_rows
            if n >= HELD:
                yield packed(held)
                held, n = [], 0
        if n:
            yield packed(held)

    ship(stream.sparkSession)
    rows = stream.where("u is not null and l is not null and t is not null").select("eid", "u", "l", "t")
    return rows.mapInArrow(run, "l long, cell long, low long, high long, edges array<struct<eid: long, u: long, t: long>>")


def stream_wedges(spark: SparkSession, path: str, tau: int, delay: str, p: float = 1.0, seed: int = 0, packed: bool = False) -> DataFrame:
    """Wedges as they close: both sides carry a watermark and the second edge comes within tau of the first, so state goes once it can match no more.
    With p below 1 only sampled first edges are kept as state; every edge still probes them.
    What is joined and kept as state are blocks of edges with one lower node and near times, under that node and a stretch of time of tau at least, so an edge meets edges of its own and the
    next stretch only. A block's time is that of its last edge, so an edge that is too late may still come along with later ones of its block. With `packed` the stream gives the pairs of
    blocks that close, for `listed` to make wedges of: their files then have no row for each wedge."""
    cut = max(1, -(-tau // CELLS))

    def side(edges: DataFrame, k: int) -> DataFrame:
        own = blocks(edges, cut).withColumn("ts", F.timestamp_micros("high")).withWatermark("ts", delay)
        return own.select(*(F.col(c).alias(f"{c}{k}") for c in own.columns), F.floor(F.col("cell") / CELLS).alias(f"stretch{k}"))

    edges = source(spark, path)
    first = side(edges.where(u01(seed, "eid") < p) if p < 1 else edges, 1).withColumn("stretch1", F.explode(F.array("stretch1", F.col("stretch1") + 1)))
    second = side(source(spark, path), 2)
    # times of blocks for the state, which must go by the watermark's column, and the edges' own
    late = (F.col("ts2") > F.col("ts1") - F.expr(f"interval {cut} microseconds")) & (F.col("ts2") <= F.col("ts1") + F.expr(f"interval {tau + cut} microseconds"))
    near = (F.col("high2") > F.col("low1")) & (F.col("low2") <= F.col("high1") + tau)
    joined = first.join(second, (F.col("l1") == F.col("l2")) & (F.col("stretch1") == F.col("stretch2")) & late & near)
    pairs = joined.select(F.col("l1").alias("center"), "edges1", "edges2")
    return pairs if packed else listed(pairs, tau)


def listed(pairs: DataFrame, tau: int) -> DataFrame:
    """The wedges in pairs of blocks, a first edge with a block's second edges, then the next one with the same."""
    one = pairs.select("center", "edges2", F.inline(lazily("edges1")).alias("e1", "ua", "t1"))
    two = one.select("center", "e1", "ua", "t1", F.inline("edges2").alias("e2", "ub", "t2"))
    within = (F.col("t2") > F.col("t1")) & (F.col("t2") <= F.col("t1") + tau)
    return two.where(within & (F.col("ua") != F.col("ub"))).select("e1", "e2", "ua", "ub", "center", "t1", "t2")


def stream_counts(spark: SparkSession, path: str, tau: int, delay: int, files: int = 4) -> DataFrame:
    """(type, count) kept up by batches: a batch counts the start edges whose window has closed since the last one, over the edges of the last tau and what may
    still come late; older edges are let go. State is a table in the shared folder, a version a batch."""
    state = {"edges": None, "closed": None, "counts": []}

    def step(batch: DataFrame, _: int) -> None:
        own = batch.sparkSession
        edges = batch.select("eid", "u", "l", "t")
        if state["closed"] is not None:
            edges = edges.where(F.col("t") > state["closed"])  # later than the delay allows: dropped, as a watermark would
        known = edges if state["edges"] is None else edges.union(own.read.parquet(state["edges"]))
        path_ = new_path(own, "window")
        known.write.parquet(path_)
        known = own.read.parquet(path_)
        latest = known.agg(F.max("t")).first()[0]
        if latest is None:
            return
        flush(known, latest - delay - tau)
        kept = new_path(own, "window")
        known.where(F.col("t") > state["closed"]).write.parquet(kept)
        state["edges"] = kept

    def flush(known: DataFrame, upto: int) -> None:
        low = state["closed"]
        starts = known.where((F.col("t") <= upto) & (F.lit(True) if low is None else F.col("t") > low))
        state["counts"].append(tuple(added(ranked(known, starts, tau, totals=True)).first()))
        state["closed"] = upto if low is None else max(low, upto)

    q = source(spark, path, files=files).writeStream.foreachBatch(step).option("checkpointLocation", new_path(spark, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    if state["edges"] is not None:
        known = spark.read.parquet(state["edges"])
        flush(known, (known.agg(F.max("t")).first()[0] or state["closed"]) + 1)
    return long_form(spark.createDataFrame(state["counts"] or [(0,) * 6], ", ".join(f"{c} long" for c in COUNTS)).agg(*(F.sum(c).alias(c) for c in COUNTS)))


def _replayed(spark: SparkSession, d: str, delay: str | None = "1 hour") -> DataFrame:
    return source(spark, slices(view(spark, d, "euk"), 240 * HOUR), delay)


def _late(spark: SparkSession, d: str) -> DataFrame:
    """The last quarter of the time comes first, then the quarter before it, then the first half. A batch drops what is behind the watermark of the batch before the last one, so
    the quarter before the last still counts, and the first half is dropped. The rows that are left, and all rows."""
    edges = view(spark, d, "euk").withColumn("ts", F.timestamp_micros("t"))
    path = new_path(spark, "late")
    mid, late = (int(x) for x in edges.agg(((F.min("t") + F.max("t")) / 2).cast("long"), ((F.min("t") + 3 * F.max("t")) / 4).cast("long")).first())
    for own in (F.col("t") > late, (F.col("t") > mid) & (F.col("t") <= late), F.col("t") <= mid):
        edges.where(own).coalesce(1).write.mode("append").parquet(path)
    got = drained(tumbling(source(spark, path, "1 hour", files=1), "1 day"), "append")
    kept = got.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("kept"))
    return kept.crossJoin(edges.agg(F.count(F.lit(1)).alias("rows")))  # single rows


def _dedup(spark: SparkSession, d: str) -> DataFrame:
    edges = view(spark, d, "euk")
    twice = slices(edges.union(edges.where("eid % 3 = 0")), 240 * HOUR)
    return drained(source(spark, twice, "1 hour").dropDuplicatesWithinWatermark(["eid"]).select("eid"))


_DAY = 24 * HOUR
_E = view_sql("euk")
_TAU = 6 * HOUR
QUERIES = {
    "stream_tumbling": (lambda s, d: drained(tumbling(_replayed(s, d), "1 day"), "complete"), f"select t // {_DAY} * {_DAY} as begin, count(*) as n from ({_E}) group by 1"),
    "stream_sliding": (lambda s, d: drained(tumbling(_replayed(s, d), "2 days", "1 day"), "complete"), f"select (t // {_DAY} - k) * {_DAY} as begin, count(*) as n from ({_E}), range(0, 2) r(k) group by 1"),
    "stream_session": (
        lambda s, d: drained(sessions(_replayed(s, d), "12 hours"), "complete"),
        f"with x as (select *, case when t - lag(t) over (partition by u order by t) < {12 * HOUR} then 0 else 1 end as new from ({_E})), y as (select u, t, sum(new) over (partition by u order by t) as k from x) select u, min(t) as begin, count(*) as n from y group by u, k",
    ),
    "stream_wedges": (
        lambda s, d: listed(drained(stream_wedges(s, slices(view(s, d, "euk"), 240 * HOUR), _TAU, "1 hour", packed=True)), _TAU),
        f"with e as ({_E}) select a.eid as e1, b.eid as e2, a.u as ua, b.u as ub, a.l as center, a.t as t1, b.t as t2 from e a join e b on a.l = b.l and a.u <> b.u and b.t > a.t and b.t <= a.t + {_TAU}",
    ),
    "stream_counts": (lambda s, d: stream_counts(s, slices(view(s, d, "euk"), 240 * HOUR), 24 * HOUR, HOUR, files=2), f"{instances_sql(_E, 24 * HOUR)} {six_sql()}"),
    "stream_late": (
        _late,
        # days that the watermark has closed by the end, without what came after the later half
        f"with e as ({_E}), x as (select trunc((min(t) + max(t)) / 2)::bigint as mid, max(t) - {HOUR} as mark from e) select count(*) filter (t > mid and (t // {_DAY} + 1) * {_DAY} <= mark) as kept, count(*) as rows from e, x",
    ),
    "stream_dedup": (_dedup, f"select eid from ({_E})"),
}
