"""Queries of the training-data operators, with production parameters, over whole tables; SQL where SQL can express one."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from binlens.llm import decontaminate, html_text, jaccard_join, license_scan, maxscore, merkle, packing, repair, role_repair, toxicity


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer(name: str) -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


def op1(spark, sf_dir):
    docs = _table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.fit(docs, _table(spark, sf_dir, "labels")))


def op2(spark, sf_dir):
    pages = _table(spark, sf_dir, "pages")
    found = merkle.audit(merkle.records(pages), merkle.records(merkle.rotten(pages)))
    return found.select(F.col("key").alias("page_id"), F.col("start").alias("byte_start"), F.col("size").alias("byte_size"), "our_hash", "their_hash")


def op3(spark, sf_dir):
    return role_repair.repair(_table(spark, sf_dir, "conversations"))


def op4(spark, sf_dir):
    return license_scan.scan(_table(spark, sf_dir, "documents"))


def op5(spark, sf_dir):
    return repair.round_trip(_table(spark, sf_dir, "documents"), tokenizer("byte_bpe_50k.json"))


def op6(spark, sf_dir):
    return packing.pack(_table(spark, sf_dir, "documents"), tokenizer("word_bpe_49k.json"))


def op7(spark, sf_dir):
    return decontaminate.contaminated(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op8(spark, sf_dir):
    return jaccard_join.jaccard_components(_table(spark, sf_dir, "documents"))


def op9(spark, sf_dir):
    vectors = _table(spark, sf_dir, "embeddings")
    return maxscore.top_k(vectors, vectors.where("vec_id % 50 = 0"))


def op10(spark, sf_dir):
    return html_text.extract(_table(spark, sf_dir, "pages"))


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_toxicity": op1, "op2_merkle_audit": op2, "op3_role_repair": op3, "op4_license_scan": op4, "op5_repair_grammar": op5, "op6_pow2_packing": op6,
        "op7_template_decontamination": op7, "op8_jaccard_join": op8, "op9_maxscore": op9, "op10_html_text": op10, "pipeline": pipeline,
    }


_RECORD = (
    "'WARC/1.1' || chr(10) || 'WARC-Type: response' || coalesce(chr(10) || 'WARC-Target-URI: ' || url, '') || case when {0} is null then chr(10) || "
        "'WARC-Truncated: unspecified' else '' end "
    "|| chr(10) || 'Content-Length: ' || cast(strlen(coalesce({0}, '')) as varchar) || chr(10) || chr(10) || coalesce({0}, '') || chr(10) || chr(10)"
)

_OP2 = f"""
with pages_ as (select page_id, url, html as good, case when md5(html) like '0a%' then substr(html, 2) else html end as bad from pages),
recs as (select page_id, {_RECORD.format("good")} as good, {_RECORD.format("bad")} as bad from pages_),
sized as (select page_id, good, bad, strlen(good) as byte_size, sum(strlen(good)) over (order by page_id) - strlen(good) as byte_start from recs)
select page_id, cast(byte_start as bigint) as byte_start, cast(byte_size as bigint) as byte_size, sha256(good) as our_hash, sha256(bad) as their_hash
from sized where good <> bad
"""

_OP9 = """
with v as (select vec_id, list_transform(embedding, lambda x: cast(floor(256 * cast(x as double)) as bigint)) as v from embeddings
    where embedding is not null and not list_bool_or(list_transform(embedding, lambda x: x is null or not isfinite(x)))),
s as (select q.vec_id as query_id, c.vec_id as vec_id, cast(list_sum(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2])) as bigint) as score
    from v q join v c on q.vec_id % 50 = 0 and q.vec_id <> c.vec_id),
r as (select *, cast(row_number() over (partition by query_id order by score desc, vec_id) as integer) as rank from s)
select query_id, rank, vec_id, score from r where rank <= 5
"""

_OP8 = r"""
with recursive w as (select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as w from documents),
s as (select doc_id, list_distinct(case when len(w) = 0 then [] when len(w) < 5 then [array_to_string(w, ' ')]
    else list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i+4], ' ')) end) as s from w),
e as (select doc_id, len(s) as n, unnest(s) as t from s),
o as (select a.doc_id as a, b.doc_id as b, a.n + b.n - count(*) as u, count(*) as k from e a join e b on a.t = b.t and a.doc_id <> b.doc_id
    and 100 * least(a.n, b.n) >= 75 * greatest(a.n, b.n) group by a.doc_id, b.doc_id, a.n, b.n),
l as (select a, b from o where 100 * k >= 75 * u),
r as (select doc_id, doc_id as c from documents union select l.b, r.c from r join l on l.a = r.doc_id where r.c < l.b)
select d.doc_id, cast(len(s.s) as bigint) as n_shingles, m.c as component_id from documents d join s using (doc_id) join (select doc_id, min(c) as c from r group by doc_id) m using (doc_id)
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_merkle_audit": _OP2, "op8_jaccard_join": _OP8, "op9_maxscore": _OP9}
