"""Thin queries of the corpus operators over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, fingerprints, html_extract, langid, mixing, ngram_join, quality, secrets, substring_dedup, token_output
from .common import scratch_path, table


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.repeated_passages(table(spark, sf_dir, "documents"))


def op2_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.extract(table(spark, sf_dir, "pages"))


def op3_secret_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    ledger = secrets.update_ledger(docs, scratch_path(spark, "ledger"))
    return secrets.digest(secrets.findings(docs, ledger))


def op4_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    mix = mixing.mix_documents(table(spark, sf_dir, "documents"))
    return mix.select("doc_id", "size", "source_size", "target", "taken", "source")


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text").withColumn("held_out", langid.held_out("doc_id", 4, 2))
    model = quality.fit(docs.filter("not held_out"), table(spark, sf_dir, "labels"))
    return quality.classify(docs, model).drop("text")


def op6_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.similar_documents(table(spark, sf_dir, "documents"))


def op7_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op8_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.compare_edited(table(spark, sf_dir, "documents"))


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang").withColumn("held_out", langid.held_out("doc_id", 5, 0))
    trees = langid.fit(docs.filter("not held_out"))
    got = langid.identify(docs.select("doc_id", "text", "held_out"), trees)
    return got.select("doc_id", "held_out", "lang_pred", F.col("lang_score").alias("score"), "lang_bits")


def op10_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_output.encode_documents(table(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_substring_dedup, op2_html_text, op3_secret_ledger, op4_source_mix, op5_quality, op6_ngram_join, op7_decontaminate, op8_fingerprints, op9_language_id, op10_token_output)}


def _secret_sql() -> str:
    def one(order: int, rule: secrets.Rule) -> str:
        p = rule.pattern.replace("'", "''")
        return f"select doc_id, '{rule.kind}' as kind, {order} as ord, {rule.least} as least, regexp_extract_all(text, '{p}', 0) as hit, regexp_extract_all(text, '{p}', {rule.group}) as val, regexp_split_to_array(text, '{p}') as gap from t"

    rules = " union all ".join(one(i, r) for i, r in enumerate(secrets.RULES))
    size = lambda xs: f"coalesce(list_sum(list_transform({xs}, lambda x: length(x))), 0)"
    counts = ", ".join(f"cast(count(*) filter (kind = '{r.kind}') as bigint) as n_{r.kind}" for r in secrets.BASE_RULES)
    base = len(secrets.BASE_RULES)
    return f"""with t as (select doc_id, coalesce(text, '') as text from documents), m as ({rules}),
 s as (select doc_id, kind, ord, least, val[i] as v, length(hit[i]) as n, {size('gap[1:i]')} + {size('hit[1:i-1]')} as st from m, unnest(range(1, len(hit) + 1)) r(i)),
 f as (select *, kind || ':' || cast(st as bigint) || ':' || cast(st + n as bigint) as span from s where length(v) >= least)
 select t.doc_id, {counts}, sha256(coalesce(string_agg(span, ',' order by st, ord) filter (ord < {base}), '')) as base_sha256, coalesce(string_agg(span, ',' order by st, ord), '') as spans
 from t left join f using (doc_id) group by t.doc_id"""


JACCARD_SQL = r"""with recursive w as (select doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') as ws from documents),
 sh as (select distinct doc_id, array_to_string(ws[i:i+4], ' ') as s from w, unnest(range(1, greatest(len(ws) - 4, 1) + 1)) r(i) where len(ws) > 0),
 n as (select doc_id, count(*) as n from sh group by 1),
 common as (select a.doc_id as a, b.doc_id as b, count(*) as k from sh a join sh b on a.s = b.s and a.doc_id <> b.doc_id group by 1, 2),
 link as (select a, b from common join n x on x.doc_id = a join n y on y.doc_id = b where k >= 0.8 * (x.n + y.n - k) - 1e-6),
 reach as (select a, b from link union select r.a, l.b from reach r join link l on r.b = l.a)
 select d.doc_id, least(d.doc_id, coalesce(c.least_id, d.doc_id)) as class_id, coalesce(l.n_links, 0) as n_links from documents d
 left join (select a, min(b) as least_id from reach group by 1) c on c.a = d.doc_id left join (select a, cast(count(*) as bigint) as n_links from link group by 1) l on l.a = d.doc_id"""

#: The other operators are not SQL: tests hold them against brute force.
ORACLES: dict[str, str] = {"op3_secret_ledger": _secret_sql(), "op6_ngram_join": JACCARD_SQL}
