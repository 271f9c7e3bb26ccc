"""The pipeline's stages keep the columns, pass odd tables, and take the decisions of their operators."""

import re
from collections import Counter

import pytest
import xxhash
from pyspark.sql import functions as F

from wingcount.llm import decontaminate, perplexity, simhash
from wingcount.llm.registry import vocabulary
from wingcount.shared import written

pipeline = pytest.importorskip("corpus_pipeline")
SF = "/root/testdata/sf0.001"


def known_by_sets(rows, least_share=0.4, least_learned=50_000):
    """All ids, and those whose text has enough n-grams of one language of the other half, by plain counts."""
    half = lambda t: xxhash.xxh64_intdigest((t or "").encode(), 42) & 1 if t is not None else 0

    def grams(t):
        raw = b"".join(bytes([x]) if x >= 128 or 97 <= x <= 122 else b"\0" for x in t.lower().encode())
        padded = b"\0\0" + raw + b"\0\0"
        return [g for g in (padded[i : i + 4] for i in range(len(raw) + 1)) if g[2:] != b"\0\0" and g[:3] != b"\0\0\0"]

    n = {0: {}, 1: {}}
    for r in rows:
        if r["text"] is not None and r["lang"] is not None:
            n[half(r["text"])].setdefault(r["lang"], Counter()).update(grams(r["text"]))
    kept = set()
    for r in rows:
        if not re.search(r"[^\W\d_]", r["text"] or ""):
            continue
        other = n[1 - half(r["text"])]
        total = {x: sum(c.values()) for x, c in other.items()}
        taught = [x for x in other if total[x] >= least_learned]
        share = lambda x, g: other[x][g] / total[x]
        own = grams(r["text"])
        has = Counter()
        for g in own:
            best = max((share(x, g) for x in other), default=0)
            has.update(x for x in other if best and share(x, g) >= 0.25 * best)
        if not taught or max(has.values(), default=0) / max(1, len(own)) >= least_share or (r["lang"] is not None and r["lang"] not in taught):
            kept.add(r["doc_id"])
    return {r["doc_id"] for r in rows}, kept


def test_language_stage_rejects_foreign_and_junk_texts(spark):
    """Planted texts of a language that nothing teaches, and letters without sense, go; they do not vouch for their copies."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    junk = ["Det var en gång en liten flicka som bodde i skogen med sin mormor och många vänliga djur", "zxqj kwpf vbnm qwrt plkj hgfd zxcv mnbv qqqq wwww " * 40]
    planted = spark.createDataFrame([(10**6 + k, t, lang, "s", len(t)) for k, (t, lang) in enumerate((t, lang) for t in junk for lang in (None, "en", "en"))], docs.schema)
    out = pipeline.language_id(spark, docs.union(planted), SF)
    kept = {r[0] for r in out.select("doc_id").collect()}
    lettered = {r[0] for r in docs.where(F.col("text").rlike(r"\p{L}")).select("doc_id").collect()}
    assert not [x for x in kept if x >= 10**6] and len(lettered - kept) <= 2
    unnamed = docs.withColumn("lang", F.lit(None).cast("string"))
    assert pipeline.language_id(spark, unnamed, SF).count() == len(lettered)


def test_stages_against_operators(spark, docs):
    now = docs
    for name, stage in pipeline.STAGES[:-1]:
        out = written(stage(spark, now, SF), "stage")
        assert out.schema.fieldNames() == docs.schema.fieldNames()
        ids = {r[0] for r in out.select("doc_id").collect()}
        if name == "quality_rules":
            want = perplexity.judged(now).where("kept")
        elif name == "language_id":
            ids_of, kept_of = known_by_sets(now.collect())
            assert ids == kept_of and ids <= ids_of
            want = out
        elif name == "near_dedup":
            want = simhash.near_duplicates(now).where("doc_id = component_id")
        else:
            hit = decontaminate.leaks(now, spark.read.parquet(f"{SF}/benchmark.parquet")).select("doc_id").distinct()
            want = now.join(hit, "doc_id", "left_anti")
        assert ids == {r[0] for r in want.select("doc_id").collect()}, name
        assert out.count() == len(ids) > 0
        now = out
    final = pipeline.STAGES[-1][1](spark, now, SF)
    assert final.count() == now.count()
    whole = pipeline.run(spark, SF)
    assert sorted(whole.collect()) == sorted(final.collect())
    assert vocabulary("byte_bpe_50k.json")


def test_odd_and_empty_tables(spark, odd, empty):
    for table in (odd, empty):
        now = table
        for _, stage in pipeline.STAGES:
            now = written(stage(spark, now, SF), "stage")
        assert "ids_sha256" in now.columns
    assert written(pipeline.quality_rules(spark, odd, SF), "stage").where(F.col("text").isNull()).count() == 0
