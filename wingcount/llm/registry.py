"""The corpus operators' queries, by name, and their SQL."""

from __future__ import annotations

from functools import wraps

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wingcount.shared import ship

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def remainder(of: int):
    """crc32 of doc_id as text, modulo `of`."""
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % of


def query(f):
    @wraps(f)
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return f(spark, sf_dir)

    QUERIES[f.__name__] = run
    return run


@query
def op1_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wingcount.llm.language import fit_filters, predict

    docs = table(spark, sf_dir, "documents")
    filters = fit_filters(docs.where(remainder(3) != 1))
    return predict(docs, filters).select("doc_id", (remainder(3) == 1).alias("held_out"), "lang_pred", "score")


@query
def op2_perplexity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wingcount.llm.perplexity import judged

    out = judged(table(spark, sf_dir, "documents"), every_byte=True)
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "cross_entropy", "n_scored")


@query
def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wingcount.llm.simhash import near_duplicates

    out = near_duplicates(table(spark, sf_dir, "documents"))
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


@query
def op4_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wingcount.llm.byte_pairs import encode_decode

    return encode_decode(table(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"))


@query
def op6_backoff(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wingcount.llm.backoff import score

    out = score(table(spark, sf_dir, "documents"), remainder(7) != 2)
    gain = ((F.col("score") - F.col("base_score")) / F.col("n_tokens")).alias("gain")
    return out.select("doc_id", (remainder(7) == 2).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score", gain)


@query
def op5_repair(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wingcount.llm.repair import read_ids, write_ids
    from wingcount.shared import new_path

    path = new_path(spark, "token-ids")
    write_ids(table(spark, sf_dir, "documents"), path, vocabulary("word_bpe_49k.json"))
    return read_ids(spark, path)


@query
def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wingcount.llm.warc import read_warc, write_warc
    from wingcount.shared import new_path

    path = new_path(spark, "warc")
    write_warc(table(spark, sf_dir, "pages"), path)
    return read_warc(spark, path).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


ORACLES["op9_warc"] = """
with h as (
  select page_id, octet_length(encode(coalesce(html, ''))) as payload_bytes, upper(sha1(coalesce(html, ''))) as hex from pages
), bits as (
  select page_id, payload_bytes, hex,
    (select string_agg(substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', ((('0x' || substr(hex, 5 * (i // 4) + 1, 5))::bigint >> (5 * (3 - i % 4))) & 31)::int + 1, 1), '' order by i)
     from range(0, 32) r(i)) as payload_digest
  from h
), first as (select hex, max(page_id) as first_id from h group by hex)
select page_id, payload_bytes::bigint as payload_bytes, payload_digest,
  case when page_id = first_id then 'response' else 'revisit' end as record_type,
  case when page_id <> first_id then first_id end as refers_to
from bits join first using (hex)
"""


@query
def op8_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wingcount.llm.decontaminate import leaks

    return leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


@query
def op3_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wingcount.llm.licenses import scan

    return scan(table(spark, sf_dir, "documents"))


def _license_sql() -> str:
    from wingcount.llm.licenses import oracle

    return oracle()


ORACLES["op3_licenses"] = _license_sql()


@query
def op7_line_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wingcount.llm.line_quality import fit, score

    docs = table(spark, sf_dir, "documents")
    chain = fit(docs, table(spark, sf_dir, "labels"), remainder(5) != 0)
    return score(docs, chain).select("doc_id", (remainder(5) == 0).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))
