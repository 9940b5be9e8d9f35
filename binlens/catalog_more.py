"""Queries of probes, lexical profiles, unlearning, replication, cost and streams, with their SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from binlens.catalog import _BENCH, _DOTS, _PAIR, BENCHES, BINS, CH, CORPUS, DOCS, PAIRS, QRYS, SCORES, TOK, U, _bins, _grad, _index, _outcomes, _pairs, _query_grad, _rounded, _scores, _sums, query
from binlens.functions.stats import r6
from binlens.operators import aggregate as ag
from binlens.operators import attribution as at
from binlens.operators import lexical as lx
from binlens.operators import probes as pr
from binlens.operators import unlearn as un
from binlens.sources import tables as src
from binlens.sources.tables import tokens
from binlens.streaming import scores as st

# ---- probes ------------------------------------------------------------------------------------------------

@query("p01_choice_scoring", f"with {CH} select bench, query_id, cast(chosen as integer) as chosen, chosen = 0 as correct, round(margin, 6) as margin from ou")
def p01(spark, d):
    return _rounded(_outcomes(spark, d))


_W = "1.959964 * 1.959964"


@query("p02_gate", f"with {CH}, g as (select bench, count(*) as n, count_if(chosen = 0) as k from ou group by bench), i as (select *, k / n as acc, "
    f"(k / n + {_W} / (2 * n)) / (1 + {_W} / n) as mid, 1.959964 * sqrt(k / n * (1 - k / n) / n + {_W} / (4 * n * n)) / (1 + {_W} / n) as half from "
    f"g) select bench, n, k, round(acc, 6) as acc, round(mid - half, 6) as lo, round(mid + half, 6) as hi, case when mid - half > 0.25 then 'main' "
    f"when mid + half >= 0.25 then 'caution' else 'failure control' end as tier from i")
def p02(spark, d):
    return _rounded(pr.gate(_outcomes(spark, d), ["bench"]))


@query("p04_subset_masks", f"with {CH}, s as (select bench, query_id // 4 % 2 as subset, count(*) as n, count_if(chosen = 0) as k from ou group by "
    f"all) select bench, count_if(k >= 0.25 * n) as n_kept, count(*) as n_subsets, round(sum(case when k >= 0.25 * n then k end) / sum(case when k >= "
    f"0.25 * n then n end), 6) as masked_acc from s group by bench")
def p04(spark, d):
    return _rounded(pr.subset_masks(_outcomes(spark, d).withColumn("subset", F.floor(F.col("query_id") / 4) % 2)))


PQ = (f"qw as (select conv_id * 100 + turn as query_id, conv_id % 9 as bench, w as uni, {_PAIR} as bi from (select conv_id, turn, {TOK} as w from "
    f"conversations where role = 'assistant')), " + _sums("qs", "qw", "bench, query_id"))
PB = (DOCS + ", " + PQ + ", " + _grad("qg", "qs", "bench, query_id",
    "base") + ", qm as (select bench, module, [" + ", ".join(f"avg(g[{i + 1}])" for i in range(at.D)) + f"] as q from qg group by all), scores as "
    f"(select doc_id, topic, format, bench, sum({_DOTS}) as score from dg join qm using (module) join dw using (doc_id) group by all), pb0 as (select "
    f"bench, topic, format, avg(score) as mean from scores group by all), pb as (select *, (mean - avg(mean) over (partition by bench)) / "
    f"nullif(stddev_pop(mean) over (partition by bench), 0) as z from pb0)")


def _probe_grad(spark, d, base):
    turns = src.table(spark, d, "conversations").where("role = 'assistant'").withColumn("query_id",
        F.col("conv_id") * 100 + F.col("turn")).withColumn("bench", F.col("conv_id") % 9)
    return at.gradients(at.sign_sums(turns, ["bench", "query_id"], tokens(F.col("text"))), base)


def _probe_bins(spark, d):
    """All probes in one pass over the index."""
    sums, base = _index(spark, d)
    s = at.score_index(at.gradients(sums, base), at.reduce_queries(_probe_grad(spark, d, base), ["bench"]), ["doc_id", "topic", "format"], ["bench"])
    return ag.zscore(s.groupBy("bench", "topic", "format").agg(F.avg("score").alias("mean")))


@query("p05_probe_bins", f"with {PB} select bench, topic, format, round(z, 6) as z from pb")
def p05(spark, d):
    return _probe_bins(spark, d).select("bench", "topic", "format", r6("z").alias("z"))


@query("p06_cross_mask", f"with {PB} select topic, format, round(avg(z), 6) as mean_z, round(var_samp(z), 6) as var_z from pb group by topic, format")
def p06(spark, d):
    return _rounded(pr.cross_mask(_probe_bins(spark, d)))


@query("p07_consensus", f"with {PB}, c as (select topic, format, count_if(bench < 7 and z > 0) as n_positive, count_if(bench < 7 and z >= 1) as "
    f"n_strong, avg(case when bench < 7 then z end) as mean_z, avg(case when bench >= 7 then z end) as control_z from pb group by all) select topic, "
    f"format, n_positive, n_strong, round(mean_z, 6) as mean_z, round(control_z, 6) as control_z, round(mean_z - control_z, 6) as specificity from c")
def p07(spark, d):
    return _rounded(pr.consensus(_probe_bins(spark, d), [7, 8]))


@query("p08_recurrence", f"with {PAIRS}, k as (select *, row_number() over (partition by query_id order by score desc, doc_id) as rank from pairs "
    f"qualify rank <= 20), n as (select bench, count(distinct query_id) as n from k group by bench), s as (select bench, doc_id, sum(1.0 / rank) / "
    f"max(n) as w from k join n using (bench) group by all), z as (select *, (w - avg(w) over (partition by bench)) / nullif(stddev_pop(w) over "
    f"(partition by bench), 0) as z from s) select doc_id, count_if(z >= 1) as n_probes from z group by doc_id having count_if(z >= 1) >= 2")
def p08(spark, d):
    return pr.recurrence(at.topk_docs(_pairs(spark, d), 20, ["query_id"]))


_LOAD = "ld as (select bench, avg(case when format in ('de', 'en') then z end) - avg(case when format in ('es', 'fr') then z end) as loading from pb group by bench)"


@query("p09_register_loading", f"with {PB}, {_LOAD} select bench, round(loading, 6) as loading from ld")
def p09(spark, d):
    return _rounded(pr.register_loading(_probe_bins(spark, d)))


@query("p09r_register_rule", f"with {PB}, {_LOAD} select round(avg(loading), 6) as mean_loading, count_if(loading > 0) as n_positive, count(*) as n, "
    f"avg(loading) >= 0.3 and count_if(loading > 0) >= 5 as passed from ld")
def p09r(spark, d):
    return _rounded(pr.register_rule(pr.register_loading(_probe_bins(spark, d))))


PR = ", r as (select x.bench as a, y.bench as b, corr(x.z, y.z) as r from pb x join pb y using (topic, format) group by all)"


@query("p10_geometry", f"with {PB}{PR} select round(avg(case when a <> 0 and b <> 0 then r end), 6) as within_r, round(avg(case when a = 0 then r "
    f"end), 6) as anchor_r, arg_max(b, (r, -b)) filter (a = 0) as best_proxy, round(max(r) filter (a = 0), 6) as best_r from r where a <> b")
def p10(spark, d):
    return _rounded(pr.geometry(ag.profile_corr(_probe_bins(spark, d)), 0))


@query("p11_linkage")
def p11(spark, d):
    """Average linkage over nine probes: 81 correlations reach the driver."""
    r = {(str(x.a), str(x.b)): x.r for x in ag.profile_corr(_probe_bins(spark, d)).collect()}
    merges = ag.linkage(r, sorted({a for a, _ in r}))
    return spark.createDataFrame([(k, *m) for k, m in enumerate(merges)], "step int, left string, right string, height double, size int")


@query("p11c_clusters")
def p11c(spark, d):
    """Leaf order of the dendrogram and its cut into three clusters."""
    r = {(str(x.a), str(x.b)): x.r for x in ag.profile_corr(_probe_bins(spark, d)).collect()}
    names = sorted({a for a, _ in r})
    merges = ag.linkage(r, names)
    cut = ag.cut_tree(merges, names, 3)
    return spark.createDataFrame([(k, n, cut[n]) for k, n in enumerate(ag.leaf_order(merges))], "position int, probe string, cluster int")


@query("p15_macro_average", f"with {CH}, sb as (select bench, query_id // 4 % 2 as subset, count(*) as n, count_if(chosen = 0) as k, count_if(margin "
    f"is null) as bad from ou group by all) select bench, count(*) as n_subsets, round(sum(k) / sum(n), 6) as micro, round(avg(k / n), 6) as macro, "
    f"round(sum(bad) / sum(n), 6) as invalid from sb group by bench")
def p15(spark, d):
    return _rounded(pr.macro_average(_outcomes(spark, d).withColumn("subset", F.floor(F.col("query_id") / 4) % 2)))


@query("p12_pairwise_count", f"with {PB}{PR}, k as (select a, avg(case when b in (1, 2) then r end) as k, max(case when b = 0 then r end) as s from r "
    f"where a not in (0, 1, 2) group by a) select count_if(k > s) as closer, count(*) as n from k")
def p12(spark, d):
    return pr.pairwise_count(ag.profile_corr(_probe_bins(spark, d)), 0, [1, 2])


# ---- lexical -----------------------------------------------------------------------------------------------

LEX = "lex(dim, family, t) as (values " + ", ".join(f"('{a}', '{b}', '{c}')" for a, b, c in lx.pairs()) + ")"
LC = (CORPUS + ", " + LEX + f", lc as (select doc_id, topic, format, dim, family, count(*) as count from (select doc_id, topic, format, unnest({TOK}) "
    f"as t from corpus) join lex using (t) group by all)")
LM = (LC + ", sz as (select topic, format, sum(n_words) as n_words, count(*) as n_docs from corpus group by all), dm as (select distinct dim, family "
    "from lex), gm as (select topic, format, dim, sum(count) as count from lc group by all), lm as (select topic, format, dim, family, 1000 * "
    "coalesce(count, 0) / nullif(n_words, 0) as rate from sz cross join dm left join gm using (topic, format, dim)), lz as (select *, (rate - "
    "avg(rate) over (partition by dim)) / nullif(stddev_pop(rate) over (partition by dim), 0) as lz from lm)")


def _lex(spark, d):
    c = src.corpus(spark, d)
    n = lx.counts(c, tokens(F.col("text")))
    return lx.lex_z(lx.bin_matrix(n, c.groupBy("topic", "format").agg(F.sum("n_words").alias("n_words"))))


@query("l01_text_stats", f"select doc_id, cast(len({TOK}) as bigint) as n_words, cast(length(text) as bigint) as n_chars, "
    f"cast(len(regexp_extract_all(text, '[.!?]')) as bigint) as n_stops, cast(len(regexp_extract_all(text, ',')) as bigint) as n_commas, "
    f"cast(len(regexp_extract_all(text, '\\n')) as bigint) as n_lines from documents")
def l01(spark, d):
    return lx.text_stats(src.table(spark, d, "documents"), tokens(F.col("text")))


@query("l02_lexicon_counts", f"with {LC} select doc_id, dim, count from lc")
def l02(spark, d):
    return lx.counts(src.corpus(spark, d), tokens(F.col("text"))).select("doc_id", "dim", "count")


@query("l04_bin_matrix", f"with {LM} select topic, format, dim, round(rate, 6) as rate from lm")
def l04(spark, d):
    return _lex(spark, d).select("topic", "format", "dim", r6("rate").alias("rate"))


@query("l05_full_grid_z", f"with {LM} select topic, format, dim, round(lz, 6) as lz from lz")
def l05(spark, d):
    return _lex(spark, d).select("topic", "format", "dim", r6("lz").alias("lz"))


TOP = BINS + ", top as (select bench, topic, format, row_number() over (partition by bench order by z desc, topic, format) as rank, z from bins qualify rank <= 20)"
TL = TOP + ", " + LM + ", tl as (select bench, topic, format, rank, dim, family, lz from top join lz using (topic, format))"


def _top_lex(spark, d):
    return lx.top_bins(_bins(spark, d)).join(_lex(spark, d), ["topic", "format"])


@query("l06_top_bin_matrix", f"with {TL} select bench, topic, format, cast(rank as integer) as rank, dim, round(lz, 6) as lz from tl")
def l06(spark, d):
    return _top_lex(spark, d).select("bench", "topic", "format", "rank", "dim", r6("lz").alias("lz"))


@query("l07_cluster_composition", f"with {TOP} select bench, case format when 'en' then 'dialogic' when 'fr' then 'personal' when 'de' then "
    f"'expository' else 'structured' end as cluster, count(*) as n, round(count(*) / 20, 6) as share from top group by all")
def l07(spark, d):
    cluster = F.coalesce(*[F.when(F.col("format") == f, c) for f, c in lx.CLUSTERS.items()])
    return lx.top_bins(_bins(spark, d)).groupBy("bench", cluster.alias("cluster")).agg(F.count("*").alias("n"), r6(F.count("*") / 20).alias("share"))


@query("l10_family_loadings", f"with {TL} select bench, family, round(avg(lz), 6) as loading from tl group by all")
def l10(spark, d):
    return _top_lex(spark, d).groupBy("bench", "family").agg(r6(F.avg("lz")).alias("loading"))


@query("l11_range_dims", f"with {TL}, m as (select bench, dim, avg(lz) as m from tl group by all) select dim, round(max(m) - min(m), 6) as range from "
    f"m group by dim order by max(m) - min(m) desc nulls last, dim limit 18")
def l11(spark, d):
    m = _top_lex(spark, d).groupBy("bench", "dim").agg(F.avg("lz").alias("m")).groupBy("dim").agg((F.max("m") - F.min("m")).alias("x"))
    return m.orderBy(F.desc_nulls_last("x"), "dim").limit(18).select("dim", r6("x").alias("range"))


_GZ = "coalesce(max(case when dim = '{}' then m end), 0)"
_Z = {k: _GZ.format(k) for k in lx.LEXICON}


@query("l09_proxies", f"with {TL}, m as (select bench, dim, avg(lz) as m from tl group by all), p as (select bench, {_Z['article']} + "
    f"{_Z['preposition']} - {_Z['pronoun_1']} - {_Z['auxiliary']} - {_Z['negation']} as a, {_Z['affect']} - {_Z['negation']} as t, "
    f"{_Z['pronoun_2']} - {_Z['pronoun_1']} as c, {_Z['pronoun_1']} + {_Z['mental_state']} - {_Z['negation']} as u from m group by bench) select "
    f"bench, " + ", ".join(f"round(50 + 10 * greatest(-5, least(5, {x})), 6) as {n}" for x, n in (("a", "analytic"), ("t", "tone"), ("c", "clout"),
    ("u", "authentic"))) + " from p")
def l09(spark, d):
    m = _top_lex(spark, d).groupBy("bench", "dim").agg(F.avg("lz").alias("m")).where("m is not null")
    return _rounded(lx.proxies(m.groupBy("bench").agg(F.map_from_entries(F.collect_list(F.struct("dim", "m"))).alias("m"))))


@query("l12_baseline_bins", f"with {LM}, b as (select topic, format, n_docs from sz order by n_docs desc, topic, format limit 10) select topic, "
    f"format, n_docs, dim, round(rate, 6) as rate from b join lm using (topic, format)")
def l12(spark, d):
    b = src.corpus(spark, d).groupBy("topic", "format").agg(F.count("*").alias("n_docs")).orderBy(F.desc("n_docs"), "topic", "format").limit(10)
    return b.join(_lex(spark, d), ["topic", "format"]).select("topic", "format", "n_docs", "dim", r6("rate").alias("rate"))


@query("l18_doc_mean_matrix", f"with {LC}, sz as (select topic, format, count(*) as n_docs from corpus where n_words > 0 group by all), gm as (select "
    f"topic, format, dim, sum(1000 * count / n_words) as total from lc join corpus using (doc_id, topic, format) group by all), "
       "dm as (select distinct dim, family from lex) select topic, format, dim, round(coalesce(total, 0) / n_docs, 6) as rate from sz cross join dm "
           "left join gm using (topic, format, dim)")  # fmt: skip
def l18(spark, d):
    """The other estimator: a bin's mean of its documents' rates."""
    c = src.corpus(spark, d)
    return _rounded(lx.doc_mean_matrix(lx.counts(c, tokens(F.col("text"))), c).select("topic", "format", "dim", "rate"))


# ---- unlearning --------------------------------------------------------------------------------------------

_RK = U.format("'42|' || doc_id")


@query("u01_forget_sets", f"with {SCORES}, i as (select bench, topic, doc_id, 'influence' as arm from scores qualify row_number() over (partition by "
    f"topic, bench order by score desc, doc_id) <= 5), n as (select bench, null as topic, doc_id, 'naive' as arm from scores qualify row_number() "
    f"over (partition by bench order by score desc, doc_id) <= 20), "
       f"r as (select null as bench, source as topic, doc_id, 'random' as arm from documents qualify row_number() over (partition by source order by "
           f"{_RK}, doc_id) <= 25), g as (select null as bench, null as topic, doc_id, 'global' as arm from documents qualify row_number() over "
           f"(order by {_RK}, doc_id) <= 25) select * from i union all select * from n union all select * from r union all select * from g")  # fmt: skip
def u01(spark, d):
    s, docs = _scores(spark, d), src.corpus(spark, d)
    return un.forget_influence(s, 5).unionByName(un.forget_naive(s, 20)).unionByName(un.forget_random(docs, 25,
        "42")).unionByName(un.forget_random(docs, 25, "42", False))


@query("u02_retain_set", f"with f as (select doc_id, source as topic from documents qualify row_number() over (partition by source order by {_RK}, "
    f"doc_id) <= 25) select doc_id, source as topic from documents where doc_id not in (select doc_id from f) order by "
    f"{U.format(chr(39) + '43|' + chr(39) + ' || doc_id')}, doc_id limit 300")
def u02(spark, d):
    docs = src.corpus(spark, d)
    return un.retain_set(docs, un.forget_random(docs, 25, "42"), 300, "43")


@query("u03_shuffled_segments", f"with w as (select doc_id, {TOK} as w from documents), s as (select doc_id, i, "
    f"{U.format(chr(39) + 'seg|' + chr(39) + ' || doc_id || chr(124) || i')} as k, array_to_string(w[i * 8 + 1 : i * 8 + 8], ' ') as t from w, "
    f"unnest(range(0, cast(ceil(len(w) / 8) as bigint))) r(i)) select doc_id, md5(string_agg(t, ' ' order by k, i)) as digest from s group by doc_id")
def u03(spark, d):
    w = src.table(spark, d, "documents").select("doc_id", tokens(F.col("text")).alias("w")).where("size(w) > 0")
    return w.select("doc_id", F.md5(F.array_join(un.shuffle_segments(F.col("w"), F.col("doc_id"), "seg"), " ")).alias("digest"))


@query("u05_bigram_frequencies", f"with w as (select doc_id, list_transform({TOK}, lambda t: {U.format(chr(39) + 'v|' + chr(39) + ' || t')} % {un.V}) "
    f"as h from documents), b as (select doc_id, h[i] as u, h[i + 1] as v, 1.0::double / (len(h) - 1) as f from w, unnest(range(1, len(h))) r(i) "
    f"where len(h) > 1) select cast(u as integer) as u, cast(v as integer) as v, round(1000 * sum(f) / (select count(*) from documents), 6) as f from b group by all")
def u05(spark, d):
    docs = src.corpus(spark, d)
    s = un.set_stats(docs.select(F.lit("all").alias("run_id"), "doc_id", F.lit("all").alias("role")), docs, tokens(F.col("text")))
    return s.select("u", "v", r6(1000 * F.col("f")).alias("f"))


# ---- replication, cost -------------------------------------------------------------------------------------


@query("r05_parity_receipt", "select status, count(*) as n from (select case when md5(text) in (select md5(text) from documents) then 'equivalent' "
    "else 'generated' end as status from conversations) group by status")
def r05(spark, d):
    c, t = src.table(spark, d, "conversations").select(F.md5("text").alias("m")), src.table(spark, d, "documents").select(F.md5("text").alias("m"),
        F.lit(True).alias("hit")).distinct()
    return c.join(t, "m", "left").groupBy(F.when(F.col("hit"), "equivalent").otherwise("generated").alias("status")).agg(F.count("*").alias("n"))


@query("r07_third_corpus_baseline", f"with c as (select role as topic, {TOK} as w from conversations), {LEX} select topic, dim, count(*) as count "
    f"from (select topic, unnest(w) as t from c) join lex using (t) group by all")
def r07(spark, d):
    c = src.table(spark, d, "conversations").select((F.col("conv_id") * 100 + F.col("turn")).alias("doc_id"), F.col("role").alias("topic"),
        F.lit("").alias("format"), "text")
    return lx.counts(c, tokens(F.col("text"))).groupBy("topic", "dim").agg(F.sum("count").alias("count"))


@query("k01_job_count", "select 65718 * 4 as reference_jobs, (select count(*) from documents) as documents, 4 as benches, 1 as index_scans")
def k01(spark, d):
    n = src.table(spark, d, "documents").agg(F.count("*").alias("documents"))
    return n.select(F.lit(65718 * 4).alias("reference_jobs"), "documents", F.lit(4).alias("benches"), F.lit(1).alias("index_scans"))


@query("k02_index_bytes", "select count(*) * 2 * 16 * 4 as index_bytes, 2 * 16 * 4 as bytes_per_doc from documents")
def k02(spark, d):
    return src.table(spark, d, "documents").agg((F.count("*") * (2 * at.D * 4)).alias("index_bytes")).withColumn("bytes_per_doc", F.lit(2 * at.D * 4))


# ---- streams -----------------------------------------------------------------------------------------------

EV = "ev as (select *, cast(json_extract_string(props, '$.k') as bigint) % 24 as topic, event_type as format from events)"


@query("s01_bin_sums", f"with {EV} select topic, format, count(*) as n, round(sum(value), 4) as total from ev group by all")
def s01(spark, d):
    return st.run_once(st.bin_sums(st.score_stream(spark, d)), "complete").select("topic", "format", "n", F.round("total", 4).alias("total"))


@query("s02_tumbling", f"with {EV} select date_trunc('day', ts) as start, format, count(*) as n from ev group by all")
def s02(spark, d):
    return st.run_once(st.tumbling(st.score_stream(spark, d)), "complete").select("start", "format", "n")


@query("s03_sliding", f"with {EV}, s as (select format, unnest([date_trunc('hour', ts) - to_hours(h::bigint) for h in range(6)]) as start from ev) "
    f"select start, format, count(*) as n from s group by all")
def s03(spark, d):
    return st.run_once(st.tumbling(st.score_stream(spark, d), "6 hours", "1 hour"), "complete").select("start", "format", "n")


@query("s04_sessions", f"with {EV}, g as (select user_id, ts, case when ts >= lag(ts) over (partition by user_id order by ts) + interval 6 hour then "
    f"1 when lag(ts) over (partition by user_id order by ts) is null then 1 else 0 end as new from ev), k as (select user_id, ts, sum(new) over "
    f"(partition by user_id order by ts rows unbounded preceding) as k from g) select user_id, min(ts) as start, count(*) as n from k group by user_id, k")
def s04(spark, d):
    return st.run_once(st.sessions(st.score_stream(spark, d)), "complete").select("user_id", "start", "n")


@query("s05_dedup", "select count(*) as n from (select distinct event_id from events)")
def s05(spark, d):
    return st.run_once(st.deduplicated(st.score_stream(spark, d)), "append").agg(F.count("*").alias("n"))


@query("s05b_dedup_bloom", "select count(*) as n from (select distinct event_id from events)")
def s05b(spark, d):
    """The filter is wide enough here that no first delivery is dropped."""
    return st.run_once(st.deduplicated_bloom(st.score_stream(spark, d)), "append").agg(F.count("*").alias("n"))
