"""The queries of this subpackage and their SQL, as ``__spark_entry__`` registers them."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import ship
from . import decontaminate, fingerprint, html_extract, license_scan, mixing, ngram_join, span_dedup, token_output, toxicity, url_filter
from .common import table

TOKENIZER = "word_bpe_49k.json"


def op1_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return html_extract.extract(table(spark, sf_dir, "pages"), ["page_id", "url"])


def op2_url_verdict(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return url_filter.judge(table(spark, sf_dir, "pages"), "page_id")


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    docs = table(spark, sf_dir, "documents")
    scored = toxicity.score(docs, toxicity.learn(docs, table(spark, sf_dir, "labels")), ["doc_id"])
    held_out = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, F.lit(False))
    return scored.select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op4_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.fingerprints(table(spark, sf_dir, "documents"))


def op5_span_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return span_dedup.deduplicate(table(spark, sf_dir, "documents"))


def op6_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return decontaminate.matches(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op7_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return ngram_join.counted(table(spark, sf_dir, "documents"))


def op8_token_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return token_output.read(token_output.write(table(spark, sf_dir, "documents"), public_tokenizers.path(TOKENIZER)))


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return mixing.mix(table(spark, sf_dir, "documents"))


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return license_scan.scan(table(spark, sf_dir, "documents"))


def url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the second query takes from rules alone."""
    return op2_url_verdict(spark, sf_dir).select("page_id", "host", "path", "rule")


def text_digests(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the fourth query tells of the texts themselves."""
    return op4_fingerprint(spark, sf_dir).select("doc_id", "n_chars", "edited_sha256")


def license_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The base part of the tenth query."""
    return op10_license_scan(spark, sf_dir).select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels")


QUERIES = {
    "op1_main_text": op1_main_text, "op2_url_verdict": op2_url_verdict, "op3_toxicity": op3_toxicity, "op4_fingerprint": op4_fingerprint, "op5_span_dedup": op5_span_dedup,
    "op6_decontaminate": op6_decontaminate, "op7_ngram_join": op7_ngram_join, "op8_token_blocks": op8_token_blocks, "op9_mixing": op9_mixing, "op10_license_scan": op10_license_scan,
}
#: Parts of the queries above that SQL can express, so that it can be held against them.
QUERIES |= {"url_rules": url_rules, "text_digests": text_digests, "license_base": license_base}
_RULES = [("net/", "net", "/"), ("example.net/en/", "example.net", "/en/"), ("example.com/de/", "example.com", "/de/"), ("org/fr/", "org", "/fr/")]
_PHRASES = {"cc-by": ["cc", "by"], "gpl": ["general", "public", "license"], "reserved": ["all", "rights", "reserved"]}
_FOUND = {label: f"list_filter(range(1, len(w) + 1), lambda i: {' and '.join(f"w[i + {j}] = '{x}'" for j, x in enumerate(words))})" for label, words in _PHRASES.items()}
ORACLE_SQL: dict[str, str] = {
    "url_rules": f"""with u as (select page_id, case when contains(url, '://') then substr(url, strpos(url, '://') + 3) else '' end as rest from pages),
    h as (select page_id, rest, regexp_extract(rest, '^[^/?#]*') as raw from u), p as (select page_id, translate(raw, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host, regexp_extract(substr(rest, length(raw) + 1), '^[^?#]*') as path from h),
    r as (select * from (values {', '.join(f"('{a}', '{b}', '{c}')" for a, b, c in _RULES)}) t(rule, rule_host, rule_path))
    select page_id, host, path, (select arg_max(rule, length(rule)) from r where (host = rule_host or ends_with(host, '.' || rule_host)) and starts_with(path, rule_path)) as rule from p""",
    "text_digests": """with d as (select doc_id, coalesce(text, '') as text from documents), n as (select *, coalesce(lead(text) over (order by doc_id desc), first_value(text) over (order by doc_id desc)) as next, length(text) as n, length(text) // 3 as k from d)
    select doc_id, cast(n as bigint) as n_chars, sha256(substr(text, 1, n - k) || substr(next, 1, k)) as edited_sha256 from n""",
    "license_base": f"""with d as (select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') as w from documents),
    f as (select doc_id, len(w) as n, {', '.join(f'{x} as "{label}"' for label, x in _FOUND.items())} from d), a as (select *, list_sort(list_concat({', '.join(f'"{label}"' for label in _FOUND)})) as places from f)
    select doc_id, cast(n as bigint) as n_words, cast(len(places) as bigint) as n_base, cast(places[1] - 1 as bigint) as first_word, cast(places[len(places)] - 1 as bigint) as last_word,
    array_to_string(list_filter([{', '.join(f"case when len(\"{label}\") > 0 then '{label}' end" for label in sorted(_FOUND))}], lambda x: x is not null), ',') as base_labels from a""",
}
