"""SimHash near-duplicates with pigeonring candidate filtering.

A fingerprint has 64 bits, cut into a ring of four 16-bit segments. If two fingerprints differ in at most 3 bits, then from some segment on, the
chain of that segment and those after it differs by at most floor(l * 3/4) bits over its first l segments: 0, 1, 2, 3 bits. So a pair can be found by an
exact first segment together with two of the four octets of the next two segments: at most one octet of the second segment and at most
two of the four may differ. That makes 20 keys of 32 bits a fingerprint. The chain of budgets is checked before the full distance.

Only distinct fingerprints are compared, so copies cost nothing. Within a bucket each fingerprint is first held against the bucket's
smallest and largest one; after the components of those links only fingerprints outside their bucket's main component are
compared with the rest. No bucket is cut off, and links between fingerprints already known to be connected are not listed.

Texts without a word (and nulls) have fingerprint zero and link like any other. doc_id null: such rows link, but never name a component
unless all of its ids are null. Repeated rows share a component. Empty tables give empty results; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from wingcount.llm.components import components
from wingcount.llm.text_arrays import LOWER, chunks, take_slices, text_bytes, words
from wingcount.shared import written

SEGMENTS, MOST = 4, 3
#: Pairs of the octets 0-3 (0 and 1: second segment of a chain; 2 and 3: third) of which one is exact whenever the budgets hold.
OCTET_PAIRS = ((0, 1), (0, 2), (0, 3), (1, 2), (1, 3))


def fingerprint_array(column: pa.Array, width: int = 3, seed: int = 42) -> np.ndarray:
    """uint64 fingerprints of whole texts from all their word shingles, repeats included."""
    data, at = text_bytes(column)
    data = LOWER[data]
    starts, ends, bounds = words(data, at)
    spaced, word_at = take_slices(np.append(data, np.uint8(32)), starts, ends - starts + 1)
    spaced[word_at[1:] - 1] = 32
    n_words = np.diff(bounds)
    n = np.where(n_words >= width, n_words - width + 1, np.minimum(n_words, 1))
    first, total = np.repeat(bounds[:-1] - (np.cumsum(n) - n), n), int(n.sum())
    index = np.arange(total) + first
    last = np.minimum(index + width, np.repeat(bounds[1:], n))
    raw, digest = spaced.tobytes(), xxhash.xxh64_intdigest
    h = np.fromiter((digest(raw[a:b], seed) for a, b in zip(word_at[index].tolist(), (word_at[last] - 1).tolist(), strict=True)), np.uint64, total)
    out = np.zeros(len(n), np.uint64)
    own = np.flatnonzero(n)
    if len(own):
        bits = np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        set_ = np.add.reduceat(bits, (np.cumsum(n) - n)[own], axis=0, dtype=np.int32)
        out[own] = np.packbits(set_ * 2 > n[own, None], axis=1, bitorder="little").view(np.uint64).ravel()
    return out


def fingerprints(docs: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",), width: int = 3) -> DataFrame:
    """`keep` columns and fp, the fingerprint's 64 bits as a long."""
    rows = docs.select(*keep, F.col(text).alias("_text"))
    schema = T.StructType([rows.schema[c] for c in keep] + [T.StructField("fp", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in chunks(batch, "_text"):
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in keep), pa.array(fingerprint_array(part.column("_text"), width).view(np.int64))], [*keep, "fp"])

    return rows.mapInArrow(run, schema)


def _turned(fp: Column, k: int) -> Column:
    """The ring read from segment k on, that segment in the highest bits."""
    return F.shiftleft(fp, 16 * k).bitwiseOR(F.shiftrightunsigned(fp, 64 - 16 * k)) if k else fp


def chain_keys(fp: Column) -> Column:
    keys = []
    for k in range(SEGMENTS):
        turned = _turned(fp, k)
        octets = [F.shiftrightunsigned(turned, 40 - 8 * j).bitwiseAND(F.lit(255)) for j in range(4)]
        head = F.shiftleft(F.shiftrightunsigned(turned, 48), 16)
        for p, (i, j) in enumerate(OCTET_PAIRS):
            keys.append(F.lit((k * len(OCTET_PAIRS) + p) << 32).bitwiseOR(head).bitwiseOR(F.shiftleft(octets[i], 8)).bitwiseOR(octets[j]))
    return F.array(*keys)


def within_budgets(a: Column, b: Column, key: Column) -> Column:
    """Whether the chain that starts at the key's segment keeps its budgets at every length, the whole ring included."""
    differ = a.bitwiseXOR(b)
    start = F.shiftrightunsigned(key, 32).cast("int")
    out = F.lit(False)
    for k in range(SEGMENTS):
        turned = _turned(differ, k)
        kept = F.lit(True)
        for length in range(1, SEGMENTS + 1):
            kept = kept & (F.bit_count(F.shiftrightunsigned(turned, 64 - 16 * length)) <= length * MOST // SEGMENTS)
        out = F.when(F.floor(start / len(OCTET_PAIRS)) == k, kept).otherwise(out)
    return out


def links(distinct: DataFrame) -> DataFrame:
    """(fp, component) for the fingerprints that link to another one. `distinct` has each fp once."""
    keyed = distinct.select("fp", F.explode(chain_keys(F.col("fp"))).alias("key"))
    shared = keyed.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min("fp").alias("low"), F.max("fp").alias("high")).where("n > 1")
    members = written(keyed.join(shared, "key").select("key", "fp", "low", "high"), "buckets")
    near = members.select("key", "fp", F.explode(F.array("low", "high")).alias("pivot")).where("fp <> pivot").where(within_budgets(F.col("fp"), F.col("pivot"), F.col("key")))
    first = written(components(near.select(F.col("fp").alias("a"), F.col("pivot").alias("b"))), "components")
    labelled = members.select("key", "fp").join(first.select(F.col("node").alias("fp"), "component"), "fp", "left").select("key", "fp", F.coalesce("component", "fp").alias("label"))
    by_label = labelled.groupBy("key", "label").agg(F.count(F.lit(1)).alias("n"))
    main = by_label.groupBy("key").agg(F.max_by("label", F.struct("n", "label")).alias("main"), F.count(F.lit(1)).alias("labels")).where("labels > 1").select("key", "main")
    open_ = written(labelled.join(main, "key"), "open")
    x, y = open_.where("label <> main").alias("x"), open_.alias("y")
    across = x.join(y, (F.col("x.key") == F.col("y.key")) & (F.col("x.label") != F.col("y.label")) & within_budgets(F.col("x.fp"), F.col("y.fp"), F.col("x.key")))
    rest = across.select(F.col("x.label").alias("a"), F.col("y.label").alias("b"))
    return components(rest.union(first.select(F.col("node").alias("a"), F.col("component").alias("b")))).select(F.col("node").alias("fp"), "component")


def _grouped(docs: DataFrame, text: str, keep: tuple[str, ...], width: int) -> tuple[DataFrame, DataFrame]:
    """The documents' `keep` columns and fp; and each fp with its smallest doc_id and its component."""
    own = written(fingerprints(docs, text, keep, width), "fingerprints")
    distinct = written(own.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct")
    return own, distinct.join(links(distinct.select("fp")), "fp", "left").select("fp", "least", F.coalesce("component", "fp").alias("component"))


def near_duplicates(docs: DataFrame, text: str = "text", width: int = 3) -> DataFrame:
    """doc_id, fp and component_id: the smallest doc_id among all documents reached over links of at most 3 differing bits."""
    own, linked = _grouped(docs, text, ("doc_id",), width)
    ids = linked.groupBy("component").agg(F.min("least").alias("component_id"))
    named = linked.join(ids, "component").select("fp", "component_id")
    return own.join(named, "fp").select("doc_id", "fp", "component_id")


def deduplicated(docs: DataFrame, text: str = "text") -> DataFrame:
    """One document of each component: the one with the smallest doc_id (null ids last), then fingerprint and hashes of the text. Texts of other components
    stay, whatever their ids. Texts are dealt once, by id and hashes, for the join and for what repeats in full."""
    name = F.concat_ws(":", F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.xxhash64(text).cast("string"), F.xxhash64(F.lit(1), text).cast("string"))
    marked = docs.withColumn("_name", name)
    own, linked = _grouped(marked, text, ("doc_id", "_name"), 3)
    first = F.min(F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "fp", "_name")).alias("first")
    kept = own.join(linked.select("fp", "component"), "fp").groupBy("component").agg(first).select(F.col("first._name").alias("_name"))
    return marked.join(kept, "_name", "left_semi").dropDuplicates(["_name"]).drop("_name")
