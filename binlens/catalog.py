"""Name -> query and its SQL, for every method of the engine.  The SQL is written for DuckDB over the same tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from binlens.functions.hashing import u32
from binlens.functions.stats import r6
from binlens.operators import aggregate as ag
from binlens.operators import attribution as at
from binlens.operators import corpus as co
from binlens.operators import probes as pr
from binlens.operators import selectivity as se
from binlens.sources import tables as src
from binlens.sources.index import base_model, corpus_index, kept
from binlens.sources.tables import BENCHES, UNBINNED, tokens

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
SEED = "42"


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def queries():
    return dict(QUERIES)


def oracle_sql():
    return dict(ORACLES)


U = "cast('0x' || substr(md5({}), 1, 8) as bigint)"
TOK = r"list_filter(string_split_regex(trim(lower(text)), '\s+'), lambda x: x <> '')"
CORPUS = (f"corpus as (select doc_id, text, source as topic, lang as format, n_chars, cast(len({TOK}) as bigint) as n_words, source not in ('src18', "
    f"'src19') as is_binned from documents)")
BINS0 = CORPUS + """, grid as (select * from (select distinct topic from corpus) cross join (select distinct format from corpus)),
cells as (select topic, format, count(doc_id) as n_docs, cast(coalesce(sum(n_words), 0) as bigint) as n_words from grid left join corpus using (topic, format) group by topic, format)"""
UP = ("up as (select doc_id, text, source, cast(c as integer) as copy_no, doc_id * 3 + c as pos from documents, unnest(range(0, cast(replace(source, "
    "'src', '') as bigint) % 3 + 1)) t(c))")

# ---- corpus ------------------------------------------------------------------------------------------------


@query("c01_dedup_exact", f"with {UP} select doc_id, min(pos) as pos from up group by doc_id")
def c01(spark, d):
    return co.dedup_exact(src.upsampled(spark, d), ["doc_id"], "pos").select("doc_id", "pos")


BLOOM_N = 100_000
_M = co.bloom_bits(BLOOM_N)
_BITS = ", ".join(U.format(f"'bloom{j}|' || doc_id") + f" % {_M}" for j in range(10))
BLOOM = (UP + f", at_ as (select pos, unnest([{_BITS}]) as b from up), f as (select b, min(pos) as first from at_ group by b), dropped as (select "
    f"pos, bool_and(first < pos) as dropped from at_ join f using (b) group by pos)")


def _bloom_size(spark, d):
    """Ids that the filter is made for: BLOOM_N as in the SQL, or the rows of a larger table."""
    return max(BLOOM_N, src.table(spark, d, "documents").count())


@query("c02_dedup_bloom", f"with {BLOOM} select doc_id, pos, dropped from up join dropped using (pos)")
def c02(spark, d):
    return co.dedup_bloom(src.upsampled(spark, d), "doc_id", "pos", _bloom_size(spark, d)).select("doc_id", "pos", "dropped")


@query("c03_dedup_report", f"with {BLOOM}, e as (select doc_id, min(pos) as pos from up group by doc_id), r as (select up.source as source, dropped, "
    f"e.pos is not null as first from up join dropped using (pos) left join e using (pos)) "
       "select source, count(*) as n_raw, count_if(first) as n_exact, count_if(not dropped) as n_kept, count_if(dropped and first) as n_false from r "
           "group by source")  # fmt: skip
def c03(spark, d):
    up = src.upsampled(spark, d)
    flags = co.dedup_bloom(up, "doc_id", "pos", _bloom_size(spark, d))
    first = co.dedup_exact(up, ["doc_id"], "pos").select("pos", F.lit(True).alias("first"))
    rows = flags.join(first, "pos", "left").fillna(False, ["first"])
    return rows.groupBy("source").agg(F.count("*").alias("n_raw"), F.count_if("first").alias("n_exact"),
        F.count_if(~F.col("dropped")).alias("n_kept"), F.count_if(F.col("dropped") & F.col("first")).alias("n_false"))


@query("c04_minted_ids", "select doc_id, md5(text) as content_id, row_number() over (partition by md5(text) order by doc_id) as ordinal from documents")
def c04(spark, d):
    return co.mint_ids(src.table(spark, d, "documents"), "text", "doc_id").select("doc_id", "content_id", "ordinal")


@query("c05_composition", "select source, count(*) as n_docs, round(count(*) / sum(count(*)) over (), 6) as share from documents group by source")
def c05(spark, d):
    return co.composition(src.table(spark, d, "documents").select("source"), "source")


@query("c06_bin_counts", f"with {BINS0} select * from cells")
def c06(spark, d):
    return co.bin_counts(src.corpus(spark, d))


@query("c07_marginals", f"with {BINS0} select topic, format, cast(sum(n_docs) as bigint) as n_docs, cast(sum(n_words) as bigint) as n_words from "
    f"cells group by grouping sets ((topic), (format), ())")
def c07(spark, d):
    return co.marginals(co.bin_counts(src.corpus(spark, d)))


_G = ("select '{0}' as measure, round(sum((2 * i - n - 1) * x) / (max(n) * sum(x)), 6) as gini from (select {0}::double as x, row_number() over "
    "(order by {0}) as i, count(*) over () as n from cells)")


@query("c08_gini", f"with {BINS0} " + _G.format("n_docs") + " union all " + _G.format("n_words"))
def c08(spark, d):
    b = co.bin_counts(src.corpus(spark, d))
    return co.gini(b, "n_docs").select(F.lit("n_docs").alias("measure"), "gini").union(co.gini(b, "n_words").select(F.lit("n_words"), "gini"))


@query("c09_effective_bins", f"with {BINS0}, p as (select n_docs / sum(n_docs) over () as p from cells where n_docs > 0) select round(-sum(p * "
    f"ln(p)), 6) as entropy, round(exp(-sum(p * ln(p))), 6) as effective_bins from p")
def c09(spark, d):
    return co.effective_bins(co.bin_counts(src.corpus(spark, d)), "n_docs")


@query("c10_skew", f"with {BINS0} select max(n_docs) as largest, min(case when n_docs > 0 then n_docs end) as smallest, count_if(n_docs = 0) as "
    f"n_empty, round(max(n_docs) / min(case when n_docs > 0 then n_docs end), 6) as ratio from cells")
def c10(spark, d):
    return co.skew_summary(co.bin_counts(src.corpus(spark, d)), "n_docs")


_HT = ("select '{0}' as side, cast(row_number() over (order by n_words {1}, topic, format) as integer) as rank, topic, format, n_words, "
    "round(sum(n_words) over (order by n_words {1}, topic, format rows unbounded preceding) / sum(n_words) over (), 6) as running_share from cells "
    "where n_words > 0 qualify rank <= 20")


@query("c11_head_tail", f"with {BINS0} " + _HT.format("head", "desc") + " union all " + _HT.format("tail", "asc"))
def c11(spark, d):
    return co.head_tail(co.bin_counts(src.corpus(spark, d)), "n_words")


@query("c12_log_grid", f"with {BINS0} select topic, format, case when n_docs > 0 then round(log10(n_docs), 6) end as log_docs, case when n_words > 0 "
    f"then round(log10(n_words), 6) end as log_words from cells")
def c12(spark, d):
    return co.log_grid(co.bin_counts(src.corpus(spark, d)))


@query("c13_population", f"with {CORPUS} select count(*) as n_docs, count_if(is_binned) as n_binned, round(count_if(is_binned) / count(*), 6) as "
    f"share_binned from corpus")
def c13(spark, d):
    return co.population(src.corpus(spark, d))


STAR = """star as (select l_orderkey, l_linenumber, p_brand as topic, s_nationkey as format, o_orderpriority as bench, l_extendedprice * (1 - l_discount) as score
from lineitem join part on l_partkey = p_partkey join supplier on l_suppkey = s_suppkey join orders on l_orderkey = o_orderkey)"""


@query("c14_star_counts", f"with {STAR} select topic, format, count(*) as n_rows from star group by topic, format")
def c14(spark, d):
    return src.star_scores(spark, d).groupBy("topic", "format").agg(F.count("*").alias("n_rows"))


STRAT = (CORPUS + f", strat as (select *, row_number() over (partition by topic, format order by {U.format(repr(SEED) + ' || chr(124) || doc_id')}, "
    f"doc_id) as draw_rank from corpus qualify draw_rank <= 10)")
UNI = f", uni as (select * from corpus order by {U.format(repr(SEED) + ' || chr(124) || doc_id')}, doc_id limit 500)"


@query("c15_stratified", f"with {STRAT} select doc_id, topic, format, draw_rank from strat")
def c15(spark, d):
    return co.sample_stratified(src.corpus(spark, d), 10, SEED).select("doc_id", "topic", "format", F.col("draw_rank").cast("long"))


@query("c16_representative", f"with {STRAT}{UNI} select doc_id, topic, format from uni")
def c16(spark, d):
    return co.sample_uniform(src.corpus(spark, d), 500, SEED).select("doc_id", "topic", "format")


GRID = BINS0[BINS0.index("grid as"):]


@query("c17_fill_rates", f"with {STRAT}, {GRID} select topic, format, count(doc_id) as realised, round(count(doc_id) / 10, 6) as fill, count(doc_id) "
    f"< 10 as under_filled from cells left join strat using (topic, format) group by topic, format")
def c17(spark, d):
    c = src.corpus(spark, d)
    return co.fill_rates(co.sample_stratified(c, 10, SEED), co.bin_counts(c), 10)


@query("c18_allocation",
    f"""with {STRAT}{UNI}, {GRID}, a as (select topic, format, count(*) as na from strat group by all), b as (select topic, format, count(*) as nb from uni group by all)
select topic, format, round(case when na is null and nb is null then 0 else log2((na / sum(na) over ()) / (nb / sum(nb) over ())) end, 6) as log2_ratio from cells left join a using (topic, format) left join b using (topic, format)""")
def c18(spark, d):
    c = src.corpus(spark, d)
    return co.allocation_log2(co.sample_stratified(c, 10, SEED), co.sample_uniform(c, 500, SEED), co.bin_counts(c))


@query("c20_ecdf", f"with {CORPUS} select n_words as x, round(sum(count(*)) over (order by n_words) / sum(count(*)) over (), 6) as f from corpus group by n_words")
def c20(spark, d):
    return co.ecdf(src.corpus(spark, d), "n_words")


@query("c20s_ecdf_sketch")
def c20s(spark, d):
    return co.ecdf_sketch(src.corpus(spark, d), "n_words", [10, 100, 300, 1000, 3000])


@query("c21_mean_length", f"with {CORPUS} select topic, format, round(avg(n_words), 6) as mean_words from corpus group by topic, format")
def c21(spark, d):
    return co.mean_length(src.corpus(spark, d))


def _votes(spark, d):
    """Topic and format labels of 24 x 24 by token votes, with and without the source name as a stand-in for a URL."""
    docs = src.table(spark, d, "documents").select("doc_id", "lang", tokens(F.col("text")).alias("w"), "source")
    url = F.array_repeat(u32(F.lit("topic"), F.col("source")) % 24, 3)
    v = docs.select("doc_id", "lang", "source", src.votes(F.col("w"), "topic", 24).alias("a"), src.votes(F.col("w"), "format", 24).alias("b"))
    v = v.select("doc_id", "lang", "a", "b", F.concat("a", url).alias("c"))  # columns, so that no label hashes a word again
    return v.select("doc_id", "lang", co.vote_label(F.col("a")).alias("no_url"), co.vote_label(F.col("c")).alias("url"), co.vote_label(F.col("b")).alias("fmt"))


_VOTE = ("""{0} as (select doc_id, arg_min(v, (-k, v)) as label, max(k) / sum(k) as conf from (select doc_id, v, count(*) as k from ({1}) group by doc_id, v) group by doc_id)""")
_TV = f"select doc_id, {U.format(chr(39) + 'topic|' + chr(39) + ' || t')} % 24 as v from (select doc_id, unnest({TOK}) as t from documents)"
_UV = f"{_TV} union all select doc_id, {U.format(chr(39) + 'topic|' + chr(39) + ' || source')} % 24 from documents, range(3)"
VOTES = _VOTE.format("plain", _TV) + ", " + _VOTE.format("url", _UV)


@query("c22_vote_labels", f"with {VOTES} select doc_id, p.label as label, round(p.conf, 6) as conf, u.label as url_label, coalesce(p.label = u.label, "
    f"false) as agree from documents left join plain p using (doc_id) left join url u using (doc_id)")
def c22(spark, d):
    return _votes(spark, d).select("doc_id", F.col("no_url.label").alias("label"), r6("no_url.conf").alias("conf"),
        F.col("url.label").alias("url_label"), F.coalesce(F.col("no_url.label") == F.col("url.label"), F.lit(False)).alias("agree"))


@query("c23_classifier_accuracy",
    f"""with {VOTES}, j as (select lang, (p.label % 2 = quality)::int::double as ok from plain p join labels using (doc_id) join documents using (doc_id) where {U.format("'teacher|' || doc_id")} % 100 >= 25),
g as (select lang, count(*) as n, avg(ok) as acc from j group by lang) select cast(sum(n) as bigint) as n, round(sum(acc * n) / sum(n), 6) as mean_acc, round(min(acc), 6) as worst_group_acc from g""")
def c23(spark, d):
    """Only documents that a confident teacher has labelled are voted on."""
    gold = src.table(spark, d, "labels").select("doc_id", F.col("quality").alias("gold"), ((u32(F.lit("teacher"), F.col("doc_id")) % 100) / 100).alias("teacher_conf"))
    docs = src.table(spark, d, "documents").select("doc_id", "lang", "text").join(gold.where("teacher_conf >= 0.25"), "doc_id", "left_semi")
    votes = co.vote_labels(src.spread(docs), ["doc_id", "lang"], tokens(F.col("text")), "topic", 24)
    pred = votes.select("doc_id", "lang", (F.col("label") % 2).alias("label")).where("label is not null")
    return co.classifier_accuracy(pred, gold, "lang", 0.25)


@query("c24_shards", f"select {U.format(repr('shard') + ' || chr(124) || doc_id')} % 8 as shard, count(*) as n_docs from documents group by all")
def c24(spark, d):
    return co.shard(src.table(spark, d, "documents").select("doc_id"), 8, "doc_id").groupBy("shard").agg(F.count("*").alias("n_docs"))


@query("c26_receipt", f"with {UP} select count(*) as n_rows, count(distinct doc_id) as n_ids, (select count(*) from labels where doc_id not in "
    f"(select doc_id from documents)) as n_missing, count(*) - count(distinct doc_id) as n_repeats, count(distinct "
    f"{U.format(repr('shard') + ' || chr(124) || doc_id')} % 8) as n_shards, count(distinct source) as n_sources, "
    f"bit_xor({U.format("doc_id || '|' || md5(text)")}) as content from up")
def c26(spark, d):
    return co.coverage_receipt(src.upsampled(spark, d), src.table(spark, d, "labels").select("doc_id"))


# ---- attribution -------------------------------------------------------------------------------------------

_S = ", ".join(f"sum((u >> {i}) & 1) * 2 - count(*)" for i in range(at.D))
_PAIR = "case when len(w) > 1 then list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]) else [] end"
_SG = U.format("'s|' || module || '|' || t")


def _sums(name: str, source: str, keys: str) -> str:
    """source: (keys, uni list, bi list)."""
    return (
        f"{name} as (select {keys}, module, count(*) as n, [{_S}] as s from (select {keys}, module, {_SG} as u from (select {keys}, 'uni' as module, "
            f"unnest(uni) as t from {source} union all select {keys}, 'bi', unnest(bi) from {source})) group by {keys}, module)"
    )


def _model(name: str, sums: str) -> str:
    return f"{name} as (select module, [{', '.join(f'sum(s[{i + 1}]) / sum(n)' for i in range(at.D))}] as p from {sums} group by module)"


def _grad(name: str, sums: str, keys: str, model: str) -> str:
    return (
        f"{name}_r as (select {keys}, module, list_transform(list_zip(s, p), lambda z: z[1] / n - z[2]) as v from {sums} join {model} using (module)),"
        f"{name} as (select {keys}, module, list_transform(v, lambda x: coalesce(x / nullif(sqrt(list_sum(list_transform(v, lambda y: y * y))), 0), "
            f"0)) as g from {name}_r)"
    )


_BENCH = "['SR', 'TR', 'SK', 'TK'][item_id % 4 + 1]"
DOCS = (f"dw as (select doc_id, source as topic, lang as format, w as uni, {_PAIR} as bi from (select doc_id, source, lang, {TOK} as w from "
    f"documents)), " + _sums("ds", "dw", "doc_id") + ", " + _model("base", "ds") + ", " + _grad("dg", "ds", "doc_id", "base"))
QRYS = (
    f"qw0 as (select item_id as query_id, {_BENCH} as bench, {TOK} as w from benchmark), qw1 as (select query_id, bench, w[len(w) // 2 + 1:] as uni, "
        f"w[greatest(len(w) // 2, 1):] as bth, len(w) // 2 as h from qw0),"
    "qw as (select query_id, bench, uni, list_transform(range(1, len(bth)), lambda i: bth[i] || ' ' || bth[i + 1]) as bi from qw1), " + _sums("qs",
        "qw", "bench, query_id")
)
_DOTS = "list_sum(list_transform(list_zip(g, q), lambda z: z[1] * z[2]))"
QM = f"qm as (select bench, module, [{', '.join(f'avg(g[{i + 1}])' for i in range(at.D))}] as q from qg group by bench, module)"
SCORES = (DOCS + ", " + QRYS + ", " + _grad("qg", "qs", "bench, query_id", "base") + ", " + QM + f", scores as (select doc_id, topic, format, bench, "
    f"sum({_DOTS}) as score from dg join qm using (module) join dw using (doc_id) group by doc_id, topic, format, bench)")
BINS = (SCORES + ", bins0 as (select bench, topic, format, count(*) as n_docs, avg(score) as mean, stddev_samp(score) as sd from scores group by "
    "all), bins as (select *, (mean - avg(mean) over (partition by bench)) / nullif(stddev_pop(mean) over (partition by bench), 0) as z from bins0)")


def _index(spark, d):
    """Sign sums of all documents, from the kept index, and the base model made from them."""
    return corpus_index(spark, d), base_model(spark, d)


def _query_grad(spark, d, model):
    return at.gradients(at.query_sums(src.bench_queries(spark, d)), model)


def _scores(spark, d, model=None):
    sums, base = _index(spark, d)
    means = at.reduce_queries(_query_grad(spark, d, model(spark, d, sums) if model else base), ["bench"])
    return at.score_index(at.gradients(sums, base), means, ["doc_id", "topic", "format"], ["bench"])


def _bins(spark, d):
    return ag.zscore(ag.bin_mean(_scores(spark, d)))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Attribution map: signed bin means of documents against benchmarks, and z within each benchmark."""
    return _bins(spark, sf_dir).select("bench", "topic", "format", "n_docs", r6("mean").alias("mean"), r6("z").alias("z"))


@query("a01_queries", f"with {QRYS.split(', ' + 'qs as')[0]} select query_id, bench, len(uni) as n_completion, h as n_prompt, array_to_string(uni, ' "
    f"') as completion from qw1")
def a01(spark, d):
    q = src.bench_queries(spark, d)
    return q.select("query_id", "bench", F.size("completion").cast("long").alias("n_completion"), F.size("prompt").cast("long").alias("n_prompt"),
        F.array_join("completion", " ").alias("completion"))


@query("a03_gradients", f"with {DOCS} select doc_id, module, round(g[1], 6) as g1, round(g[8], 6) as g8, round(g[16], 6) as g16 from dg")
def a03(spark, d):
    sums, base = _index(spark, d)
    return at.by_module(at.gradients(sums, base)).select("doc_id", "module", *[r6(F.col("g")[i - 1]).alias(f"g{i}") for i in (1, 8, 16)])


_VEC = """parts as (select vec_id, label as topic, vec_id % 4 as format, m as module, list_transform(embedding[m * 16 + 1 : m * 16 + 16], lambda x: x::double) as v from embeddings, range(4) t(m)),
pg as (select vec_id, topic, format, module, list_transform(v, lambda x: coalesce(x / nullif(sqrt(list_sum(list_transform(v, lambda y: y * y))), 0), 0)) as g from parts),
vq as (select (vec_id // 10) % 4 as bench, module, [""" + ", ".join(f"avg(g[{i + 1}])" for i in range(16)) + """] as q from pg where vec_id % 10 = 0 group by all),
vs as (select vec_id, topic, format, bench, sum(""" + _DOTS + """) as score from pg join vq using (module) where vec_id % 10 <> 0 group by all)"""


@query("a04_vector_scores", f"with {_VEC} select vec_id, topic, format, bench, round(score, 6) as score from vs")
def a04(spark, d):
    return at.vector_scores(src.table(spark, d, "embeddings")).select("vec_id", "topic", "format", "bench", r6("score").alias("score"))


@query("a05_score_histogram", f"with {SCORES} select bench, cast(least(greatest(floor((score + 1) / 0.1), 0), 19) as bigint) as bucket, count(*) as n "
    f"from scores group by all")
def a05(spark, d):
    return _scores(spark, d).groupBy("bench", F.least(F.greatest(F.floor((F.col("score") + 1) / 0.1), F.lit(0)),
        F.lit(19)).cast("long").alias("bucket")).agg(F.count("*").alias("n"))


@query("a06_scores", f"with {SCORES} select doc_id, bench, round(score, 6) as score from scores")
def a06(spark, d):
    return _scores(spark, d).select("doc_id", "bench", r6("score").alias("score"))


PAIRS = (DOCS + ", " + QRYS + ", " + _grad("qg", "qs", "bench, query_id", "base") + f", pairs as (select doc_id, bench, query_id, "
    f"sum(list_sum(list_transform(list_zip(a.g, b.g), lambda z: z[1] * z[2]))) as score from dg a join qg b using (module) group by all)")


def _pairs(spark, d):
    sums, base = _index(spark, d)
    return at.score_index(at.gradients(sums, base), _query_grad(spark, d, base), ["doc_id", "topic", "format"], ["bench", "query_id"])


@query("a07_reduced_equals_mean", f"with {SCORES} select doc_id, bench, round(score, 6) as score from scores")
def a07(spark, d):
    """Mean over queries of the pair scores; the oracle scores the mean query."""
    return _pairs(spark, d).groupBy("doc_id", "bench").agg(r6(F.avg("score")).alias("score"))


VALUE_SAMPLE = 100_000  # random documents that the value preconditioner is made from
LEADING = at.D // 4  # eigenvalues clipped to the last of them: a share of d, as 1,000 is more than there are


@query("a08_preconditioned")
def a08(spark, d):
    sums, base = _index(spark, d)
    g, q = at.gradients(sums, base), _query_grad(spark, d, base)
    hv, hq = at.second_moments(co.sample_uniform(g, VALUE_SAMPLE, SEED)), at.second_moments(q)
    roots = {m: at.mix_precond(hv[m], hq[m], leading=LEADING) for m in hv}
    return at.score_index(at.whiten(g, roots), at.reduce_queries(at.whiten(q, roots), ["bench"]), ["doc_id"], ["bench"]).select("doc_id", "bench",
        r6("score").alias("score"))


_DIAG = ", ".join(f"avg(g[{i + 1}] * g[{i + 1}])" for i in range(at.D))


@query("a08d_preconditioned_diagonal", f"with {SCORES}, hv as (select module, [{_DIAG}] as h from dg group by module), hq as (select module, "
    f"[{_DIAG}] as k from qg group by module), "
       f"w as (select module, list_transform(list_zip(h, k), lambda z: 0.5 * z[1] + 0.5 * z[2] + 1e-6) as w from hv join hq using (module)) select "
           f"doc_id, bench, round(sum(list_sum(list_transform(list_zip(g, q, w), lambda z: z[1] * z[2] / z[3]))), 6) as score from dg join qm using "
           f"(module) join w using (module) group by doc_id, bench")  # fmt: skip
def a08d(spark, d):
    sums, base = _index(spark, d)
    g, q = at.gradients(sums, base), _query_grad(spark, d, base)

    def diag(x, tag):
        return x.agg(*[F.array(*[F.avg(F.col(m)[i] * F.col(m)[i]) for i in range(at.D)]).alias(f"{tag}_{m}") for m in at.MODULES])

    w = diag(g, "h").crossJoin(F.broadcast(diag(q, "k")))  # one row each
    w = w.select(*[F.zip_with(f"h_{m}", f"k_{m}", lambda x, y: 0.5 * x + 0.5 * y + 1e-6).alias(f"w_{m}") for m in at.MODULES])
    scaled = g.crossJoin(F.broadcast(w)).withColumns({m: F.zip_with(m, f"w_{m}", lambda x, y: x / y) for m in at.MODULES})
    return at.score_index(scaled, at.reduce_queries(q, ["bench"]), ["doc_id"], ["bench"]).select("doc_id", "bench", r6("score").alias("score"))


@query("a09_topk_by_topic", f"with {SCORES} select bench, topic, doc_id, cast(row_number() over (partition by bench, topic order by score desc, "
    f"doc_id) as integer) as rank from scores qualify rank <= 5")
def a09(spark, d):
    return at.topk_docs(_scores(spark, d), 5, ["bench", "topic"]).select("bench", "topic", "doc_id", "rank")


@query("a10_topk_bin_stats", f"with {PAIRS}, k as (select *, row_number() over (partition by query_id order by score desc, doc_id) as rank from pairs "
    f"qualify rank <= 100) select bench, source as topic, lang as format, count(*) as hits, round(avg(score), 6) as mean_score, round(avg(rank), 6) "
    f"as mean_rank from k join documents using (doc_id) group by all")
def a10(spark, d):
    return at.topk_docs(_pairs(spark, d), 100, ["query_id"]).groupBy("bench", "topic", "format").agg(F.count("*").alias("hits"),
        r6(F.avg("score")).alias("mean_score"), r6(F.avg("rank")).alias("mean_rank"))


@query("a11_planted_recall", f"with {PAIRS}, k as (select doc_id, query_id, row_number() over (partition by query_id order by score desc, doc_id) as "
    f"rank from pairs), h as (select k.* from k join documents d using (doc_id) join benchmark b on b.item_id = query_id where contains(d.text, "
    f"b.text)) select count(*) as n_pairs, round(avg((rank <= 1)::int::double), 6) as recall_1, round(avg((rank <= 10)::int::double), 6) as "
    f"recall_10, round(avg(1.0 / rank), 6) as mrr from h")
def a11(spark, d):
    docs, b = src.table(spark, d, "documents").select("doc_id", "text"), src.table(spark, d, "benchmark").select(F.col("item_id").alias("query_id"),
        F.col("text").alias("t"))
    return at.planted_recall(_pairs(spark, d), at.planted(docs, b))


CONV = (f"cw as (select conv_id, turn, w as uni, {_PAIR} as bi from (select conv_id, turn, {TOK} as w from conversations where role = 'assistant')), "
    f"" + _sums("cs", "cw", "conv_id, turn") + ", " + _model("conv", "cs") + ", inst as (select module, list_transform(list_zip(a.p, b.p), lambda z: "
    "0.5 * z[1] + 0.5 * z[2]) as p from base a join conv b using (module))")
INST = (DOCS + ", " + QRYS + ", " + CONV + ", " + _grad("qg", "qs", "bench, query_id", "inst") + ", " + QM + f", scores as (select doc_id, bench, "
    f"sum({_DOTS}) as score from dg join qm using (module) group by doc_id, bench)")


def _instruct(spark, d, sums):
    turns = src.table(spark, d, "conversations").where("role = 'assistant'")
    return at.model_means(sums, at.sign_sums(turns, ["conv_id", "turn"], tokens(F.col("text"))))


@query("a12_two_model_scores", f"with {INST} select doc_id, bench, round(score, 6) as score from scores")
def a12(spark, d):
    """Documents on the base model, queries on the instruct model; a06 is the base-query variant."""
    return at.check_pairing(_scores(spark, d, _instruct)).select("doc_id", "bench", r6("score").alias("score"))


# ---- bins, contrasts, inference ---------------------------------------------------------------------------


@query("g01_bin_means", f"with {BINS} select bench, topic, format, n_docs, round(mean, 6) as mean from bins")
def g01(spark, d):
    return ag.bin_mean(_scores(spark, d)).select("bench", "topic", "format", "n_docs", r6("mean").alias("mean"))


@query("g02_bin_medians", f"with {SCORES} select bench, topic, format, round(median(score), 6) as median from scores group by all")
def g02(spark, d):
    return ag.bin_mean(_scores(spark, d), "median").select("bench", "topic", "format", r6("mean").alias("median"))


@query("g03_z", f"with {BINS} select bench, topic, format, n_docs, round(mean, 6) as mean, round(z, 6) as z from bins")
def g03(spark, d):
    return flagship(spark, d)


def _t_sql(t: str, df: str) -> str:
    """P(T > t) by direct summation of the series, for the oracle."""
    th = f"atan({t} / sqrt({df}))"
    c2 = f"pow(cos({th}), 2)"
    odd = f"(2 / pi() * ({th} + case when {df} > 1 then sin({th}) * cos({th}) * (1 + coalesce(list_sum(list_transform(range(1, ({df} - 1) // 2), lambda k: pow({c2}, k) * list_product(list_transform(range(1, k + 1), lambda j: 2.0 * j / (2 * j + 1))))), 0)) else 0 end))"
    even = f"(sin({th}) * (1 + coalesce(list_sum(list_transform(range(1, {df} // 2), lambda k: pow({c2}, k) * list_product(list_transform(range(1, k + 1), lambda j: (2.0 * j - 1) / (2 * j))))), 0)))"
    return f"((1 - case when {df} % 2 = 1 then {odd} else {even} end) / 2)"


def _bh_sql(source: str, family: str, out: str = "p_adj") -> str:
    return f"select *, case when p is not null then least(1.0, min(raw_) over (partition by {family} order by p desc nulls first range unbounded preceding)) end as {out} from (select *, p * count(p) over (partition by {family}) / count(*) over (partition by {family} order by p nulls last range unbounded preceding) as raw_ from {source})"


@query("g04_bin_tests", f"with {BINS}, t as (select bench, topic, format, n_docs, mean / nullif(sd / sqrt(n_docs), 0) as t, n_docs - 1 as df from "
    f"bins), p as (select *, case when n_docs > 1 then least(1, 2 * {_t_sql('abs(t)', 'df')}) end as p from t), a as ({_bh_sql('p', 'bench')}) select "
    f"bench, topic, format, round(t, 6) as t, round(p, 6) as p, round(p_adj, 6) as p_adj from a")
def g04(spark, d):
    return ag.bin_tests(ag.bin_mean(_scores(spark, d))).select("bench", "topic", "format", r6("t").alias("t"), r6("p").alias("p"), r6("p_adj").alias("p_adj"))


@query("g05_capped", f"with {BINS}, c as (select quantile_cont(abs(z), 0.95) as cap from bins) select bench, topic, format, round(greatest(least(z, "
    f"cap), -cap), 6) as capped from bins, c")
def g05(spark, d):
    return ag.capped(_bins(spark, d)).select("bench", "topic", "format", r6("capped").alias("capped"))


TM = ", tm as (select bench, topic, avg(z) as z from bins group by all)"
FM = ", fm as (select bench, format, avg(z) as z from bins group by all)"


@query("g06_topic_marginal", f"with {BINS}{TM} select bench, topic, round(z, 6) as z from tm")
def g06(spark, d):
    return ag.marginal_z(_bins(spark, d), "topic").select("bench", "topic", r6("z").alias("z"))


@query("g07_format_marginal", f"with {BINS}{FM} select bench, format, round(z, 6) as z from fm")
def g07(spark, d):
    return ag.marginal_z(_bins(spark, d), "format").select("bench", "format", r6("z").alias("z"))


@query("g08_extremes", f"with {BINS}{TM} select bench, topic, cast(row_number() over (partition by bench order by z desc, topic) as integer) as up, "
    f"cast(row_number() over (partition by bench order by z, topic) as integer) as down, round(z, 6) as z from tm qualify up <= 3 or down <= 3")
def g08(spark, d):
    return ag.extremes(ag.marginal_z(_bins(spark, d), "topic"), "topic")


@query("g08f_format_extremes", f"with {BINS}{FM} select bench, format, cast(row_number() over (partition by bench order by z desc, format) as "
    f"integer) as up, cast(row_number() over (partition by bench order by z, format) as integer) as down, round(z, 6) as z from fm qualify up <= 3 or down <= 3")
def g08f(spark, d):
    return ag.extremes(ag.marginal_z(_bins(spark, d), "format"), "format")


@query("g25_signed_split", f"with {BINS} select bench, count_if(mean > 0) as n_supportive, count_if(mean < 0) as n_suppressive, round(avg(abs(mean)), "
    f"6) as absolute, round(avg(case when mean > 0 then mean end), 6) as supportive, round(avg(case when mean < 0 then mean end), 6) as suppressive, "
       "round(sum(case when mean > 0 then mean else 0 end) / nullif(sum(abs(mean)), 0), 6) as share_supportive from bins group by bench")  # fmt: skip
def g25(spark, d):
    return _rounded(ag.signed_split(_bins(spark, d)))


@query("g09_vs_rest", f"with {BINS}{FM} select format, round(avg(case when bench = 'SR' then z end) - avg(case when bench <> 'SR' then z end), 6) as "
    f"gap from fm group by format")
def g09(spark, d):
    return ag.vs_rest(ag.marginal_z(_bins(spark, d), "format"), "format", "SR").select("format", r6("gap").alias("gap"))


_CON = "max(case when bench = '{}' then z end) - max(case when bench = '{}' then z end)"


@query("g10_contrast", f"with {BINS} select topic, format, round({_CON.format('SR', 'TR')}, 6) as delta from bins group by all")
def g10(spark, d):
    return ag.contrast(_bins(spark, d), "SR", "TR").select("topic", "format", r6("delta").alias("delta"))


@query("g11_topic_tilt", f"with {BINS}{TM}, x as (select topic, {_CON.format('SR', 'TR')} as delta from tm group by topic) select topic, "
    f"cast(row_number() over (order by delta desc, topic) as integer) as up, cast(row_number() over (order by delta, topic) as integer) as down, "
    f"round(delta, 6) as delta from x qualify up <= 3 or down <= 3")
def g11(spark, d):
    return ag.topic_tilt(ag.marginal_z(_bins(spark, d), "topic"), "topic", "SR", "TR").select("topic", "up", "down", r6("delta").alias("delta"))


@query("g12_sign_flips", f"with {BINS}{TM} select topic from tm group by topic having bool_and(case when bench = 'SR' then z > 0 else z < 0 end)")
def g12(spark, d):
    return ag.sign_flips(ag.marginal_z(_bins(spark, d), "topic"), "topic", "SR")


@query("g13_span_ratio", f"with {BINS}{TM}, x as (select topic, {_CON.format('SR', 'TR')} as a, {_CON.format('SK', 'TK')} as b from tm group by "
    f"topic) select round(max(abs(a)), 6) as reasoning, round(max(abs(b)), 6) as knowledge, round(max(abs(a)) / max(abs(b)), 6) as ratio from x")
def g13(spark, d):
    m = ag.marginal_z(_bins(spark, d), "topic").groupBy("topic").pivot("bench", list(BENCHES)).agg(F.first("z"))
    a, b = F.max(F.abs(F.col("SR") - F.col("TR"))), F.max(F.abs(F.col("SK") - F.col("TK")))
    return m.agg(r6(a).alias("reasoning"), r6(b).alias("knowledge"), r6(a / b).alias("ratio"))


R = ", r as (select x.bench as a, y.bench as b, corr(x.z, y.z) as r from bins x join bins y using (topic, format) group by all)"


@query("g14_pearson", f"with {BINS}{R} select a, b, round(r, 6) as r from r")
def g14(spark, d):
    return ag.profile_corr(_bins(spark, d)).select("a", "b", r6("r").alias("r"))


@query("g15_spearman", f"with {BINS}, k as (select bench, topic, format, rank() over (partition by bench order by z) + (count(*) over (partition by "
    f"bench, z) - 1) / 2 as z from bins) select x.bench as a, y.bench as b, round(corr(x.z, y.z), 6) as r from k x join k y using (topic, format) group by all")
def g15(spark, d):
    return ag.profile_corr(_bins(spark, d), how="spearman").select("a", "b", r6("r").alias("r"))


_OUT = ("select bench, round(avg(case when a = bench or b = bench then r end), 6) as c, round(avg(case when a <> bench and b <> bench then r end) - "
    "avg(case when a = bench or b = bench then r end), 6) as delta from r, (select unnest(['SR', 'TR', 'SK', 'TK']) as bench) where a < b group by bench")


@query("g16_outlier", f"with {BINS}{R} {_OUT}")
def g16(spark, d):
    return ag.outlier_stat(ag.profile_corr(_bins(spark, d)), BENCHES).select("bench", r6("c").alias("c"), r6("delta").alias("delta"))


@query("g16f_outlier_on_formats", f"with {BINS}{FM}, r as (select x.bench as a, y.bench as b, corr(x.z, y.z) as r from fm x join fm y using (format) "
    f"group by all) {_OUT}")
def g16f(spark, d):
    return ag.outlier_stat(ag.profile_corr(ag.marginal_z(_bins(spark, d), "format"), ["format"]), BENCHES).select("bench", r6("c").alias("c"), r6("delta").alias("delta"))


@query("g16m_outlier_on_marginals", f"with {BINS}{TM}, r as (select x.bench as a, y.bench as b, corr(x.z, y.z) as r from tm x join tm y using (topic) "
    f"group by all) {_OUT}")
def g16m(spark, d):
    return ag.outlier_stat(ag.profile_corr(ag.marginal_z(_bins(spark, d), "topic"), ["topic"]), BENCHES).select("bench", r6("c").alias("c"), r6("delta").alias("delta"))


#: Resamples of bins and axes, of label permutations, of queries, of documents, and of pooled rows: those of the reference.
BIN_REPS, PERM_REPS, QUERY_REPS, DOC_REPS, REPS = 10_000, 10_000, 2_000, 1_000, 1_000


def _boot_sql(unit: str, bins: str, key: str, reps: int = BIN_REPS) -> str:
    return (
        f", un as (select {key}, row_number() over (order by {key}) - 1 as unit from (select distinct {key} from {bins})), n as (select count(*) as n from un), "
        f"dr as (select rep, {U.format(repr(unit) + ' || chr(124) || rep || chr(124) || i')} % n as unit from n, range({reps}) a(rep), range(n) b(i)), "
        f"bw as (select unit, x.bench as a, y.bench as b, x.z as za, y.z as zb from un join {bins} x using ({key}) join {bins} y using ({key}) where "
            f"x.bench < y.bench and x.z is not null and y.z is not null), "
        "bt as (select rep, a, b, case when min(za) < max(za) and min(zb) < max(zb) then corr(za, zb) end as r from dr join bw using (unit) group by all)"
    )


_CI = " select a, b, round(quantile_cont(r, 0.025), 6) as lo, round(quantile_cont(r, 0.975), 6) as hi from bt group by a, b"


def _ci(boot):
    c = ag.percentile_ci(boot, ["a", "b"], "r")
    return c.select("a", "b", r6("lo").alias("lo"), r6("hi").alias("hi"))


_DCI = (
    ", ob as (select rep, bench, avg(case when a = bench or b = bench then r end) as c, avg(case when a <> bench and b <> bench then r end) - "
        "avg(case when a = bench or b = bench then r end) as delta "
    "from bt, (select unnest(['SR', 'TR', 'SK', 'TK']) as bench) group by rep, bench) "
    "select bench, round(quantile_cont(c, 0.025), 6) as c_lo, round(quantile_cont(c, 0.975), 6) as c_hi, round(quantile_cont(delta, 0.025), 6) as "
        "delta_lo, round(quantile_cont(delta, 0.975), 6) as delta_hi from ob group by bench"
)


def _outlier_ci(boot):
    """Intervals of c_b and Delta_b over the resamples of a bootstrap."""
    o = ag.outlier_stat(boot, BENCHES, ["rep"])
    c, e = (ag.percentile_ci(o, ["bench"], v).withColumnsRenamed({"lo": f"{v}_lo", "hi": f"{v}_hi"}) for v in ("c", "delta"))
    return _rounded(c.join(e, "bench"))


@query("g17_bin_bootstrap", f"with {BINS}{_boot_sql('bin', 'bins', 'topic, format')}{_CI}")
def g17(spark, d):
    return _ci(ag.bin_bootstrap(_bins(spark, d), BIN_REPS, "bin"))


@query("g17d_outlier_ci", f"with {BINS}{_boot_sql('bin', 'bins', 'topic, format')}{_DCI}")
def g17d(spark, d):
    return _outlier_ci(ag.bin_bootstrap(_bins(spark, d), BIN_REPS, "bin"))


@query("g18_axis_bootstrap", f"with {BINS}{TM}{_boot_sql('axis', 'tm', 'topic')}{_CI}")
def g18(spark, d):
    return _ci(ag.bin_bootstrap(ag.marginal_z(_bins(spark, d), "topic"), BIN_REPS, "axis", ["topic"]))


@query("g18d_topic_outlier_ci", f"with {BINS}{TM}{_boot_sql('axis', 'tm', 'topic')}{_DCI}")
def g18d(spark, d):
    return _outlier_ci(ag.bin_bootstrap(ag.marginal_z(_bins(spark, d), "topic"), BIN_REPS, "axis", ["topic"]))


@query("g18f_format_outlier_ci", f"with {BINS}{FM}{_boot_sql('axis', 'fm', 'format')}{_DCI}")
def g18f(spark, d):
    return _outlier_ci(ag.bin_bootstrap(ag.marginal_z(_bins(spark, d), "format"), BIN_REPS, "axis", ["format"]))


_PERM = U.format("'perm|' || rep || '|' || topic || '|' || format || '|' || bench")


@query("g19_permutation", f"with {BINS}, own as (select topic, format, list(bench order by bench) as names, list(z order by bench) as zs from bins group by all), "
       f"pm as (select rep, topic, format, names, list_transform(list_sort(list_transform(range(1, len(names) + 1), lambda i: {{'k': "
           f"{U.format("'perm|' || rep || '|' || topic || '|' || format || '|' || names[i]")}, 'b': names[i], 'z': zs[i]}})), lambda x: x.z) as zs "
           f"from own, range({PERM_REPS}) t(rep)), "
       "pb as (select rep, topic, format, unnest(names) as bench, unnest(zs) as z from pm), "
       "r as (select x.rep, x.bench as a, y.bench as b, corr(x.z, y.z) as r from pb x join pb y using (rep, topic, format) where x.bench < y.bench group by all), "
       "o as (select rep, avg(case when a <> 'SR' and b <> 'SR' then r end) - avg(case when a = 'SR' or b = 'SR' then r end) as delta from r group by rep), "
       "r0 as (select x.bench as a, y.bench as b, corr(x.z, y.z) as r from bins x join bins y using (topic, format) where x.bench < y.bench group by all), "
       "o0 as (select avg(case when a <> 'SR' and b <> 'SR' then r end) - avg(case when a = 'SR' or b = 'SR' then r end) as delta from r0) select "
           "round(o0.delta, 6) as observed, round((1 + count_if(o.delta >= o0.delta)) / (1 + count(*)), 6) as p from o, o0 group by o0.delta")  # fmt: skip
def g19(spark, d):
    b = _bins(spark, d)
    seen = ag.outlier_stat(ag.profile_corr(b), BENCHES).where("bench = 'SR'").select(F.col("delta").alias("observed"))
    null = ag.outlier_stat(ag.permuted_corr(b, PERM_REPS, "perm"), BENCHES, ["rep"]).where("bench = 'SR'")
    return null.crossJoin(F.broadcast(seen)).groupBy("observed").agg((1 + F.count_if(F.col("delta") >= F.col("observed"))).alias("k"),
        F.count("*").alias("n")).select(r6("observed").alias("observed"), r6(F.col("k") / (1 + F.col("n"))).alias("p"))


_DB = U.format("'doc|' || rep || '|' || topic || '|' || format || '|' || slot")
DOCB = (
    f"{SCORES}, bl as (select bench, topic, format, {U.format("'doc|' || doc_id")} % {ag.BLOCKS} as block, count(*) as n, sum(score) as total from scores group by all), "
    "nb as (select *, row_number() over (partition by bench, topic, format order by block) - 1 as i, count(*) over (partition by bench, topic, format) as m from bl), "
    f"dr as (select topic, format, rep, {_DB} % m as i from (select distinct topic, format, m from nb), range({DOC_REPS}) t(rep), unnest(range(m)) s(slot)), "
    "bm as (select rep, bench, topic, format, sum(total) / sum(n) as mean from dr join nb using (topic, format, i) group by all)"
)


@query("g20_doc_bootstrap", f"with {DOCB} select bench, topic, format, round((quantile_cont(mean, 0.975) - quantile_cont(mean, 0.025)) / 2, 6) as "
    f"floor from bm group by all")
def g20(spark, d):
    c = ag.percentile_ci(ag.doc_bootstrap(_scores(spark, d), DOC_REPS, "doc"), ["bench", "topic", "format"], "mean")
    return c.select("bench", "topic", "format", r6((F.col("hi") - F.col("lo")) / 2).alias("floor"))


@query("g20d_delta_floor", f"with {DOCB}, zb as (select *, (mean - avg(mean) over (partition by rep, bench)) / nullif(stddev_pop(mean) over "
    f"(partition by rep, bench), 0) as z from bm), "
       f"db as (select rep, topic, format, {_CON.format('SR', 'TR')} as d from zb group by all), fl as (select topic, format, (quantile_cont(d, "
           f"0.975) - quantile_cont(d, 0.025)) / 2 as floor from db group by all), "
       "b0 as (select bench, topic, format, avg(score) as mean from scores group by all), bins as (select *, (mean - avg(mean) over (partition by "
           "bench)) / nullif(stddev_pop(mean) over (partition by bench), 0) as z from b0), "
       f"ob as (select topic, format, {_CON.format('SR', 'TR')} as delta from bins group by all) select topic, format, round(delta, 6) as delta, "
           f"round(floor, 6) as floor, abs(delta) > floor as reported from ob join fl using (topic, format)")  # fmt: skip
def g20d(spark, d):
    s = _scores(spark, d)
    return _rounded(ag.delta_floor(ag.doc_bootstrap(s, DOC_REPS, "doc"), ag.zscore(ag.bin_mean(s)), "SR", "TR"))


CH = (
    f"q as (select item_id as query_id, {_BENCH} as bench, w[1:len(w) // 2] as prompt, w[len(w) // 2 + 1:] as completion from (select item_id, "
        f"{TOK} as w from benchmark)), qi as (select *, row_number() over (partition by bench order by query_id) - 1 as i, count(*) over (partition "
        f"by bench) as m from q), "
    "ch as (select a.bench, a.query_id, c.choice, b.completion as words, a.prompt from qi a, range(4) c(choice), qi b where a.bench = b.bench and b.i "
        "= (a.i + c.choice) % a.m), "
    f"vc as (select t, count(*) as c from (select unnest({TOK}) as t from documents) group by t), tot as (select sum(c) as total, count(*) as v from vc), "
    "tk as (select bench, query_id, choice, prompt, len(array_to_string(words, ' ')) as chars, unnest(words) as t from ch), "
    "sc as (select bench, query_id, choice, sum(ln(0.5 * (coalesce(c, 0) + 1) / (total + v) + 0.5 * coalesce(len(list_filter(prompt, lambda x: x = "
        "tk.t)) / nullif(len(prompt), 0), 0))) / max(chars) as score from tk left join vc using (t), tot group by all), "
    "ou as (select bench, query_id, arg_max(choice, (round(score, 9), -choice)) as chosen, max(case when choice = 0 then score end) - max(case when "
        "choice > 0 then score end) as margin from sc group by all)"
)


def _outcomes(spark, d):
    """Which choice of each item the base model prefers: its real outcome, by which items are split into cohorts."""
    return pr.outcomes(pr.score_choices(pr.choices(src.bench_queries(spark, d)), _token_counts(spark, d)))


def _token_counts(spark, d):
    docs = src.table(spark, d, "documents")
    return kept(spark, "token_counts", [docs], lambda path: pr.token_counts(src.spread(docs), tokens(F.col("text"))).write.parquet(path))


COH = (DOCS + ", " + QRYS + ", " + _grad("qg", "qs", "bench, query_id",
    "base") + ", " + CH + ", qc as (select bench, chosen = 0 as correct, module, [" + ", ".join(f"avg(g[{i + 1}])" for i in range(at.D)) + f"] as q "
    f"from qg join ou using (bench, query_id) group by all), scores as (select doc_id, topic, format, bench, correct, sum({_DOTS}) as score from dg "
    f"join qc using (module) join dw using (doc_id) group by all), cb0 as (select bench, correct, topic, format, avg(score) as mean from scores group "
    f"by all), cb as (select *, (mean - avg(mean) over (partition by bench, correct)) / nullif(stddev_pop(mean) over (partition by bench, correct), 0) as z from cb0)")


def _cohorts(spark, d):
    sums, base = _index(spark, d)
    q = _query_grad(spark, d, base).join(_outcomes(spark, d).select("bench", "query_id", "correct"), ["bench", "query_id"])
    s = at.score_index(at.gradients(sums, base), at.reduce_queries(q, ["bench", "correct"]), ["doc_id", "topic", "format"], ["bench", "correct"])
    b = s.groupBy("bench", "correct", "topic", "format").agg(F.avg("score").alias("mean"))
    return ag.zscore(b, ("bench", "correct"))


@query("g21_cohort_bins", f"with {COH} select bench, correct, topic, format, round(z, 6) as z from cb")
def g21(spark, d):
    return _cohorts(spark, d).select("bench", "correct", "topic", "format", r6("z").alias("z"))


@query("g22_correctness_delta", f"with {COH} select bench, topic, format, round(max(case when correct then z end) - max(case when not correct then z "
    f"end), 6) as delta from cb group by all")
def g22(spark, d):
    p = _cohorts(spark, d).groupBy("bench", "topic", "format").agg((F.max(F.when(F.col("correct"), F.col("z"))) - F.max(F.when(~F.col("correct"),
        F.col("z")))).alias("delta"))
    return p.select("bench", "topic", "format", r6("delta").alias("delta"))


@query("g22x_differential_extremes", f"with {COH}, dl as (select bench, topic, format, max(case when correct then z end) as zc, max(case when not "
    f"correct then z end) as zi from cb group by all), "
       "dx as (select bench, topic, format, zc, zi, zc - zi as delta, row_number() over (partition by bench order by zc - zi desc, topic, format) as "
           "up, row_number() over (partition by bench order by zc - zi, topic, format) as down, max(abs(zc - zi)) over (partition by bench) as "
           "largest from dl where zc - zi is not null), "
       "lg as (select bench, largest, largest / nullif(max(largest) over (order by largest desc rows between 1 following and 1 following), 0) as "
           "ratio_to_next from (select distinct bench, largest from dx)) "
       "select bench, topic, format, case when up = 1 then 'positive' else 'negative' end as side, round(zc, 6) as z_correct, round(zi, 6) as "
           "z_incorrect, round(delta, 6) as delta, round(largest, 6) as largest, round(ratio_to_next, 6) as ratio_to_next from dx join lg using "
           "(bench, largest) where up = 1 or down = 1")  # fmt: skip
def g22x(spark, d):
    """The strongest bins on both sides, each cohort's z there, and how far a benchmark's largest difference is beyond the next one's."""
    return _rounded(ag.differential_extremes(_cohorts(spark, d)))


# ---- ledger statistics -------------------------------------------------------------------------------------

LED = """runs as (select case o_orderstatus when 'F' then 'influence' when 'O' then 'random' else 'naive' end as recipe, cast(c_nationkey as bigint) as topic, o_orderkey % 3 + 42 as seed, ['SR', 'TR', 'SK', 'TK'][o_orderkey % 4 + 1] as target,
case o_orderpriority when '1-URGENT' then 'SR' when '2-HIGH' then 'TR' when '3-MEDIUM' then 'SK' else 'TK' end as bench, round(avg(o_totalprice) / 1e6 - 0.15, 9) as gamma, cast(sum(o_orderkey) % 400 + 100 as bigint) as steps
from orders join customer on o_custkey = c_custkey where c_nationkey < 24 and o_orderpriority in ('1-URGENT', '2-HIGH', '3-MEDIUM', '4-NOT SPECIFIED') group by all)"""
PD = (LED + ", tg as (select * from runs where target = bench), d as (select a.topic, a.seed, a.target, round(a.gamma - b.gamma, 9) as d, b.steps - "
    "a.steps as saved from tg a join tg b using (topic, seed, target) where a.recipe = 'influence' and b.recipe = 'random')")


def _led(spark, d):
    return src.ledger(spark, d)


def _rounded(df: DataFrame) -> DataFrame:
    return df.select(*[r6(c).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


@query("v01_paired", f"with {PD} select * from d")
def v01(spark, d):
    return se.paired(_led(spark, d))


_NU = "(case when {0} >= 0 then e_ else 1 - e_ end)"
_ERF = "0.5 * (t_ * (0.254829592 + t_ * (-0.284496736 + t_ * (1.421413741 + t_ * (-1.453152027 + t_ * 1.061405429))))) * exp(-z * z / 2)"
WX = ", wr as (select target, d, abs(d) as a, rank() over (partition by target order by abs(d)) + (count(*) over (partition by target, abs(d)) - 1) / 2 as k, count(*) over (partition by target, abs(d)) as ties from d where d <> 0), w0 as (select target, count(*) as n, sum(case when d > 0 then k else 0 end) as w_plus, sum((ties * ties - 1) / 48.0) as c from wr group by target), " \
     "w1 as (select target, n, w_plus, (w_plus - n * (n + 1) / 4) / sqrt(n * (n + 1) * (2 * n + 1) / 24 - c) as z from w0), w2 as (select *, 1 / (1 + 0.3275911 * abs(z) / sqrt(2)) as t_ from w1), w as (select target, n, w_plus, z, case when z >= 0 then " + _ERF + " else 1 - " + _ERF + " end as p from w2)"  # fmt: skip


@query("v02_wilcoxon", f"with {PD}{WX} select target, n, w_plus, round(z, 6) as z, round(p, 6) as p from w")
def v02(spark, d):
    return _rounded(se.wilcoxon_by_target(se.paired(_led(spark, d))))


TT = (f", t0 as (select target, topic, avg(d) as m from d group by all), t1 as (select target, count(*) as n, avg(m) as mean, stddev_samp(m) as sd "
    f"from t0 group by target), t2 as (select *, mean / (sd / sqrt(n)) as t, n - 1 as df from t1), tt as (select target, n, mean, sd, t, "
    f"{_t_sql('t', 'df')} as p_one from t2)")


@query("v03_paired_t", f"with {PD}{TT} select target, n, round(t, 6) as t, round(p_one, 6) as p_one, round(2 * least(p_one, 1 - p_one), 6) as p_two from tt")
def v03(spark, d):
    return _rounded(se.topic_t(se.paired(_led(spark, d))).select("target", "n", "t", "p_one", "p_two"))


@query("v04_bh_families", f"with {PD}{WX}{TT}, f as (select target, 'wilcoxon' as test, p, 1 as al from w union all select target, 't', p_one, 1 from "
    f"tt), f8 as ({_bh_sql('f', 'al', 'p_of_8')}), f4 as ({_bh_sql('(select target, test, p, p_of_8 from f8)', 'test', 'p_of_4')}) select target, "
    f"test, round(p, 6) as p, round(p_of_8, 6) as p_of_8, round(p_of_4, 6) as p_of_4 from f4")
def v04(spark, d):
    return _rounded(se.families(se.paired(_led(spark, d))))


@query("v05_median_ci", f"with {PD}, i as (select target, d, row_number() over (partition by target order by topic, seed) - 1 as i, count(*) over "
    f"(partition by target) as n from d), p as (select target, rep, "
    f"{U.format(chr(39) + 'med|' + chr(39) + ' || rep || chr(124) || target || chr(124) || slot')} % n as i from (select target, n, i as slot, rep "
    f"from i, range({REPS}) t(rep))), m as (select target, rep, median(d) as m from p join i using (target, i) group by all) select target, "
    f"round(quantile_cont(m, 0.025), 6) as lo, round(quantile_cont(m, 0.975), 6) as hi from m group by target")
def v05(spark, d):
    return _rounded(se.median_ci(se.paired(_led(spark, d)), REPS, "med"))


@query("v06_cohen_dz", f"with {PD} select target, count(*) as n, round(avg(d) / stddev_samp(d), 6) as dz, round(median(d), 6) as median_d from d group by target")
def v06(spark, d):
    return _rounded(se.cohen_dz(se.paired(_led(spark, d))))


@query("v07_seed_summary", f"with {PD} select recipe, topic, target, count(*) as n, round(avg(gamma), 6) as mean, round(stddev_samp(gamma), 6) as sd "
    f"from tg group by recipe, topic, target")
def v07(spark, d):
    return _rounded(se.seed_summary(_led(spark, d)))


_PV = ", ".join(f"round(avg(case when bench = '{b}' then gamma end), 6) as {b}" for b in BENCHES)


@query("v08_sweep", f"with {LED} select topic, {_PV} from runs where recipe = 'influence' group by topic")
def v08(spark, d):
    return se.sweep(_led(spark, d), BENCHES)


@query("v09_box_vs_control", f"with {LED}, t as (select bench, topic, avg(gamma) as g from runs where recipe = 'influence' group by all), b as "
    f"(select bench, min(g) as lowest, quantile_cont(g, 0.25) as q1, median(g) as middle, quantile_cont(g, 0.75) as q3, max(g) as highest from t "
    f"group by bench), c as (select bench, avg(gamma) as control from runs where recipe = 'random' group by bench) select bench, round(lowest, 6) as "
    f"lowest, round(q1, 6) as q1, round(middle, 6) as middle, round(q3, 6) as q3, round(highest, 6) as highest, round(control, 6) as control, case "
    f"when control > q3 then 'above' when control < q1 then 'below' else 'inside' end as place from b join c using (bench)")
def v09(spark, d):
    return _rounded(se.box_vs_control(_led(spark, d)))


@query("v10_step_gain", f"with {PD} select target, count(*) as n, round(avg(saved), 6) as mean_saved, median(saved)::double as median_saved from d group by target")
def v10(spark, d):
    return _rounded(se.paired(_led(spark, d)).groupBy("target").agg(F.count("*").alias("n"), F.avg("saved").alias("mean_saved"), F.median("saved").alias("median_saved")))


def _sel(by: str, where: str = "true", name: str = "sel") -> str:
    return (
        f", {name}g as (select {by}, target, bench, avg(gamma) as g from runs where {where} group by all), {name}s as (select {by}, target, sum(case "
            f"when bench = target then g end) as t, avg(case when bench <> target then abs(g) end) as rest, max(case when bench <> target then abs(g) end) as worst, "
        f"avg(case when bench <> target and bench <> 'TR' then abs(g) end) as no_tr, avg(case when bench <> target then g end) as signed, sqrt(sum(g "
            f"* g)) as norm, sum(abs(g)) as total, sum(case when g <> 0 then abs(g) * ln(abs(g)) end) as x from {name}g group by all), "
        f"{name} as (select {by}, target, abs(t) / nullif(rest, 0) as mean_ratio, abs(t) / nullif(worst, 0) as worst_ratio, abs(t) / nullif(no_tr, 0) "
            f"as excluding_ratio, t / nullif(signed, 0) as signed_ratio, t / nullif(norm, 0) as cosine, x / nullif(total, 0) - ln(nullif(total, 0)) "
            f"as neg_entropy from {name}s)"
    )


_SIX = ", ".join(f"round({m}, 6) as {m}" for m in se.METRICS)


@query("v12_selectivity", f"with {LED}{_sel('recipe')} select recipe, target, {_SIX} from sel")
def v12(spark, d):
    return _rounded(se.selectivity(_led(spark, d), ["recipe"]))


@query("v13_factorial", f"with {PD}{_sel('recipe')}, p as (select target, max(case when recipe = 'influence' then mean_ratio end) as influence, "
    f"max(case when recipe = 'naive' then mean_ratio end) as naive, max(case when recipe = 'random' then mean_ratio end) as random from sel group by "
    f"target), o as (select target, abs(avg(gamma)) > 0.003 as scorable from tg where recipe = 'influence' group by target) select target, "
    f"round(influence, 6) as influence, round(naive, 6) as naive, round(random, 6) as random, round(influence / random, 6) as influence_effect, "
    f"round(influence / naive, 6) as topic_effect, scorable from p join o using (target)")
def v13(spark, d):
    return _rounded(se.factorial(_led(spark, d)))


# attribution beside the ledger: star-grid topic marginals with nations as topics
NB = (", nb0 as (select s_nationkey::bigint as topic, case o_orderpriority when '1-URGENT' then 'SR' when '2-HIGH' then 'TR' when '3-MEDIUM' then "
    "'SK' else 'TK' end as bench, avg(l_extendedprice * (1 - l_discount)) as mean from lineitem join supplier on l_suppkey = s_suppkey join orders on "
    "l_orderkey = o_orderkey where s_nationkey < 24 and o_orderpriority <> '5-LOW' group by all), nb as (select topic, bench, (mean - avg(mean) over "
    "(partition by bench)) / stddev_pop(mean) over (partition by bench) as z from nb0)")


def _nation_z(spark, d):
    names = {"1-URGENT": "SR", "2-HIGH": "TR", "3-MEDIUM": "SK"}
    s = src.star_scores(spark, d).where("format < 24 and bench <> '5-LOW'")
    bench = F.coalesce(*[F.when(F.col("bench") == k, v) for k, v in names.items()], F.lit("TK"))
    return ag.zscore(s.groupBy(F.col("format").cast("long").alias("topic"), bench.alias("bench")).agg(F.avg("score").alias("mean"))).select("topic", "bench", "z")


@query("v11_regression", f"with {PD}{NB} select recipe, target, count(*) as n, round(regr_slope(gamma, z), 6) as slope, round(regr_intercept(gamma, "
    f"z), 6) as intercept, round(regr_r2(gamma, z), 6) as r2 from (select recipe, target, gamma, z from tg join nb on nb.bench = tg.target and "
    f"nb.topic = tg.topic) group by recipe, target")
def v11(spark, d):
    return _rounded(se.regression(_led(spark, d), _nation_z(spark, d)))


@query("v14_head_to_head", f"with "
    f"{LED}{NB}{_sel('topic', chr(114) + 'ecipe = ' + chr(39) + 'influence' + chr(39))}{_sel('recipe', chr(114) + 'ecipe = ' + chr(39) + 'naive' + chr(39), 'nv')}, "
    f"top as (select bench as target, arg_max(topic, (z, -topic)) as topic from nb group by bench) select target, topic, round(sel.mean_ratio, 6) as "
    f"chosen, round(nv.mean_ratio, 6) as naive, round(sel.mean_ratio / nv.mean_ratio, 6) as ratio from sel join top using (target, topic) join nv using (target)")
def v14(spark, d):
    return _rounded(se.head_to_head(_led(spark, d), _nation_z(spark, d)))


@query("v15_linear_prediction", f"with {LED}, k as (select s_nationkey::bigint as topic, case o_orderpriority when '1-URGENT' then 'SR' when '2-HIGH' "
    f"then 'TR' when '3-MEDIUM' then 'SK' else 'TK' end as bench, row_number() over (partition by o_orderpriority order by l_extendedprice * (1 - "
    f"l_discount) desc, l_orderkey, l_linenumber) as r from lineitem join supplier on l_suppkey = s_suppkey join orders on l_orderkey = o_orderkey "
    f"where s_nationkey < 24 and o_orderpriority <> '5-LOW' qualify r <= 200), "
       "s as (select bench, topic, count(*) / 200 as share from k group by all), g as (select topic, bench, avg(gamma) as g from runs where recipe = "
           "'influence' and target = bench group by all) select bench, round(sum(share * g), 6) as predicted from s join g using (bench, topic) group "
           "by bench")  # fmt: skip
def v15(spark, d):
    names = {"1-URGENT": "SR", "2-HIGH": "TR", "3-MEDIUM": "SK"}
    s = src.star_scores(spark, d).where("format < 24 and bench <> '5-LOW'").withColumn("bench", F.coalesce(*[F.when(F.col("bench") == k, v) for k,
        v in names.items()], F.lit("TK")))
    from pyspark.sql.window import Window

    top = s.withColumn("r", F.row_number().over(Window.partitionBy("bench").orderBy(F.desc("score"), "l_orderkey", "l_linenumber"))).where("r <= 200")
    shares = top.groupBy("bench", F.col("format").cast("long").alias("topic")).agg((F.count("*") / 200).alias("share"))
    return _rounded(se.predict_naive(shares, _led(spark, d)))


_INF = "recipe = 'influence'"


@query("v16_pilot", f"with {LED}{NB}{_sel('topic', _INF)}, u as (select topic, bench as target, z - (sum(z) over (partition by topic) - z) / "
    f"(count(*) over (partition by topic) - 1) as u from nb), s as (select target, topic, cast(row_number() over (partition by target order by u "
    f"desc, topic) as integer) as shortlist_rank from u qualify shortlist_rank <= 3) select target, topic, shortlist_rank, round(mean_ratio, 6) as "
    f"mean_ratio from sel join s using (target, topic) where mean_ratio is not null qualify row_number() over (partition by target order by "
    f"sel.mean_ratio desc, topic) = 1")
def v16(spark, d):
    return _rounded(se.pilot(_nation_z(spark, d), _led(spark, d)))


@query("v17_hindsight", f"with {LED}{_sel('topic', _INF)} select target, topic, round(mean_ratio, 6) as mean_ratio from sel where mean_ratio is not "
    f"null qualify row_number() over (partition by target order by sel.mean_ratio desc, topic) = 1")
def v17(spark, d):
    return _rounded(se.hindsight(_led(spark, d)))


@query("v18_cross_method", f"with {PD}, a as (select target, avg(gamma) as x from tg where recipe = 'influence' group by target), b as (select "
    f"target, avg(gamma) as y from tg where recipe = 'naive' group by target) select target, case when x > 0 and y > 0 then 'both' when x > 0 then "
    f"'first' when y > 0 then 'second' else 'neither' end as pattern from a join b using (target)")
def v18(spark, d):
    t = se.on_target(_led(spark, d)).groupBy("recipe", "target").agg(F.avg("gamma").alias("gamma"))
    return se.cross_method(t.where("recipe = 'influence'").drop("recipe"), t.where("recipe = 'naive'").drop("recipe"))


_UNP = " union all ".join(f"select recipe, target, '{m}' as metric, {m} as v from sel" for m in se.METRICS)


@query("v19_robustness", f"with {LED}{_sel('recipe')}, l as ({_UNP}) select metric, count_if(a.v > b.v) as wins, count(*) as n from l a join l b "
    f"using (target, metric) where a.recipe = 'influence' and b.recipe = 'naive' group by metric")
def v19(spark, d):
    return se.robustness(_led(spark, d))


@query("v20_collateral", f"with {LED} select recipe, round(avg(gamma), 6) as mean, round(median(gamma), 6) as middle, round(max(gamma), 6) as largest "
    f"from runs where bench <> target and recipe in ('influence', 'random') group by recipe")
def v20(spark, d):
    return _rounded(se.collateral(_led(spark, d)))


@query("v21_task_definitions", f"with {PD}, t as (select case when bench = 'SR' then 'easy' else 'hard' end as task, gamma from tg where bench in "
    f"('SR', 'TR')) select task, count(*) as n, round(avg(gamma), 6) as mean, round(stddev_samp(gamma), 6) as sd from (select * from t union all "
    f"select 'union', gamma from t) group by task")
def v21(spark, d):
    return _rounded(se.task_definitions(_led(spark, d)))


@query("v22_net_effect", f"with {LED}, c as (select bench, avg(gamma) as c from runs where recipe = 'random' group by bench) select topic, bench, "
    f"round(avg(gamma) - max(c), 6) as net from runs join c using (bench) where recipe = 'influence' group by topic, bench")
def v22(spark, d):
    return _rounded(se.net_effect(_led(spark, d)))


@query("v23_sign_test", f"with {PD}, s as (select target, count(*) as n, count_if(d > 0) as k from d where d <> 0 group by target) select target, n, "
    f"k, round(least(1.0, 2 * list_sum(list_transform(range(0, cast(least(k, n - k) + 1 as bigint)), lambda i: exp(lgamma(n + 1) - lgamma(i + 1) - "
    f"lgamma(n - i + 1) - n * ln(2))))), 6) as p from s")
def v23(spark, d):
    return _rounded(se.sign_test(se.paired(_led(spark, d))))


@query("v24_jackknife", f"with {PD}, t as (select target, topic, sum(d) as s, count(*) as n from d group by all), l as (select target, (sum(s) over "
    f"(partition by target) - s) / (sum(n) over (partition by target) - n) as m from t) select target, round(min(m), 6) as lowest, round(max(m), 6) "
    f"as highest from l group by target")
def v24(spark, d):
    return _rounded(se.jackknife(se.paired(_led(spark, d))))


@query("v28_topic_local", f"with {LED}, g as (select topic, bench, avg(gamma) as g from runs where recipe = 'influence' group by all), m as (select "
    f"topic, avg(abs(g)) as m from g group by topic) select count_if(m < 0.03) as n_local, count(*) as n_topics from m")
def v28(spark, d):
    return se.topic_local(_led(spark, d))


@query("v29_convergence", f"with {LED} select recipe, quantile_cont(steps, 0.25) as q1, quantile_cont(steps, 0.5) as middle, quantile_cont(steps, "
    f"0.75) as q3, count_if(steps >= 450) as at_cap from runs group by recipe")
def v29(spark, d):
    return se.convergence(_led(spark, d))


# ---- star grid ---------------------------------------------------------------------------------------------

SB = (STAR + ", bins0 as (select bench, topic, format, count(*) as n_docs, avg(score) as mean from star group by all), bins as (select *, (mean - "
    "avg(mean) over (partition by bench)) / nullif(stddev_pop(mean) over (partition by bench), 0) as z from bins0)")


def _star(spark, d):
    return ag.zscore(ag.bin_mean(src.star_scores(spark, d)))


@query("b01_star_bins", f"with {SB} select bench, topic, format, n_docs, round(log10(mean), 6) as log_mean from bins")
def b01(spark, d):
    return ag.bin_mean(src.star_scores(spark, d)).select("bench", "topic", "format", "n_docs", r6(F.log10("mean")).alias("log_mean"))


@query("b02_star_z", f"with {SB} select bench, topic, format, round(z, 6) as z from bins")
def b02(spark, d):
    return _star(spark, d).select("bench", "topic", "format", r6("z").alias("z"))


@query("b03_star_contrast", f"with {SB} select topic, format, round({_CON.format('1-URGENT', '2-HIGH')}, 6) as delta from bins group by all")
def b03(spark, d):
    return ag.contrast(_star(spark, d), "1-URGENT", "2-HIGH").select("topic", "format", r6("delta").alias("delta"))


@query("b04_star_corr", f"with {SB}{R} select a, b, round(r, 6) as r from r")
def b04(spark, d):
    return ag.profile_corr(_star(spark, d)).select("a", "b", r6("r").alias("r"))


@query("b05_star_topk", f"with {STAR} select bench, topic, l_orderkey, l_linenumber, cast(row_number() over (partition by bench, topic order by score "
    f"desc, l_orderkey, l_linenumber) as integer) as rank from star qualify rank <= 10")
def b05(spark, d):
    from pyspark.sql.window import Window

    w = Window.partitionBy("bench", "topic").orderBy(F.desc("score"), "l_orderkey", "l_linenumber")
    return src.star_scores(spark, d).withColumn("rank", F.row_number().over(w)).where("rank <= 10").select("bench", "topic", "l_orderkey", "l_linenumber", "rank")


@query("b06_star_bootstrap", f"with {SB}{_boot_sql('star', 'bins', 'topic, format')}{_CI}")
def b06(spark, d):
    return _ci(ag.bin_bootstrap(_star(spark, d), BIN_REPS, "star"))


from binlens import catalog_extra, catalog_more, catalog_rest  # noqa: E402, F401  (they register their queries)
