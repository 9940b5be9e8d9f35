"""Queries of frequencies, query bootstrap, tiers, group contrasts, stop targets, further corpora, cost and stateful streams."""

from __future__ import annotations

from pyspark.sql import functions as F

from binlens.catalog import _BENCH, _DOTS, _PAIR, BIN_REPS, BINS, CH, CORPUS, DOCS, LED, PD, QRYS, QUERY_REPS, REPS, SB, SCORES, SEED, TOK, U, _VOTE, _bins, _grad, _index, _instruct, _led, _model, _outcomes, _query_grad, _rounded, _scores, _star, _sums, CONV, query
from binlens.catalog_more import EV, LC, LM, TL, TOP, _lex, _top_lex
from binlens.functions.hashing import u32
from binlens.functions.stats import average_rank, r6
from binlens.operators import aggregate as ag
from binlens.operators import attribution as at
from binlens.operators import cost
from binlens.operators import lexical as lx
from binlens.operators import probes as pr
from binlens.operators import replicate as rp
from binlens.operators import selectivity as se
from binlens.operators import unlearn as un
from binlens.sources import tables as src
from binlens.sources.index import kept
from binlens.sources.tables import tokens
from binlens.streaming import scores as st


def _key(*parts: str) -> str:
    """SQL of ``u32`` over constants in quotes and columns."""
    return U.format(" || '|' || ".join(parts))


def _values(rows) -> str:
    return ", ".join("(" + ", ".join(f"'{x}'" if isinstance(x, str) else str(x).lower() for x in r) + ")" for r in rows)


# ---- corpus, attribution -----------------------------------------------------------------------------------


@query("c19_hash_uniform", f"with {CORPUS} select topic, format, count(*) as n, count_if({_key(repr(SEED), 'doc_id')} < 2147483648) as drawn from corpus group by all")
def c19(spark, d):
    """A Bernoulli draw by hash threshold, beside the corpus it is drawn from: no sort, no shuffle of rows."""
    hit = u32(F.lit(SEED), F.col("doc_id")) < 2**31
    return src.corpus(spark, d).groupBy("topic", "format").agg(F.count("*").alias("n"), F.count_if(hit).alias("drawn"))


@query("a02_token_frequencies", f"with w as (select {TOK} as w from documents), t as (select 'uni' as module, unnest(w) as token from w union all "
    f"select 'bi', unnest({_PAIR}) from w) select module, token, count(*) as n from t group by all")
def a02(spark, d):
    t = src.table(spark, d, "documents").select(F.explode(at.module_tokens(tokens(F.col("text")))).alias("t"))
    return t.groupBy("t.module", "t.token").agg(F.count("*").alias("n"))


@query("a05s_score_symmetry", f"with {SCORES}, m as (select *, avg(score) over (partition by bench) as m from scores) select bench, count(*) as n, "
    f"round(avg((score - m) ** 3) / stddev_pop(score) ** 3, 6) as skew, round(count_if(score > 0) / count(*), 6) as share_positive from m group by bench")
def a05s(spark, d):
    s = _scores(spark, d).groupBy("bench").agg(F.count("*").alias("n"), F.skewness("score").alias("skew"),
        (F.count_if(F.col("score") > 0) / F.count("*")).alias("share_positive"))
    return _rounded(s)


# ---- inference ---------------------------------------------------------------------------------------------

_QG = ", ".join(f"avg(g[{i + 1}])" for i in range(at.D))
QB = (
    DOCS + ", " + QRYS + ", " + _grad("qg", "qs", "bench, query_id", "base") + ", " + CH
    + f", bn as (select topic, format, count(distinct doc_id) as n from dg join dw using (doc_id) group by all), bg as (select topic, format, module, "
        f"[{', '.join(f'sum(g[{i + 1}]) / max(n)' for i in range(at.D))}] as g from dg join dw using (doc_id) join bn using (topic, format) group by all), "
    "qo as (select bench, query_id, chosen = 0 as correct, row_number() over (partition by bench order by query_id) - 1 as i, count(*) over "
        "(partition by bench) as n from (select distinct bench, query_id from qg) join ou using (bench, query_id)), "
    f"pk as (select bench, rep, {_key(repr('query'), 'rep', 'bench', 'i')} % n as i from qo, range({QUERY_REPS}) t(rep)), "
    f"rm as (select rep, bench, correct, module, [{_QG}] as q from pk join qo using (bench, i) join qg using (bench, query_id) group by all), "
    f"rc as (select rep, bench, correct, topic, format, sum({_DOTS}) as mean from bg join rm using (module) group by all), "
    "rz as (select *, (mean - avg(mean) over w) / nullif(stddev_pop(mean) over w, 0) as z from rc window w as (partition by rep, bench, correct)), "
    "rd as (select rep, bench, topic, format, max(case when correct then z end) - max(case when not correct then z end) as delta from rz group by all)"
)


@query("g23_query_bootstrap", f"with {QB} select bench, topic, format, round(quantile_cont(delta, 0.025), 6) as lo, round(quantile_cont(delta, "
    f"0.975), 6) as hi from rd group by all")
def g23(spark, d):
    sums, base = _index(spark, d)
    q = _query_grad(spark, d, base).join(_outcomes(spark, d).select("bench", "query_id", "correct"), ["bench", "query_id"])
    boot = ag.query_bootstrap(q, ag.bin_gradients(at.gradients(sums, base), at.D), QUERY_REPS, "query", at.D)
    return _rounded(ag.percentile_ci(boot, ["bench", "topic", "format"], "delta"))


@query("g24_gap_ci", f"with {BINS}, un as (select topic, row_number() over (order by topic) - 1 as unit from (select distinct topic from bins)), n as "
    f"(select count(*) as n from un), dr as (select rep, {_key(repr('gap'), 'rep', 'i')} % n as unit from n, range({BIN_REPS}) a(rep), range(n) b(i)), "
       "m as (select rep, bench, format, avg(z) as z from dr join un using (unit) join bins using (topic) group by all), gp as (select rep, format, "
           "avg(case when bench = 'SR' then z end) - avg(case when bench <> 'SR' then z end) as gap from m group by all), "
       "m0 as (select bench, format, avg(z) as z from bins group by all), g0 as (select format, avg(case when bench = 'SR' then z end) - avg(case "
           "when bench <> 'SR' then z end) as gap from m0 group by all), "
       "c as (select format, quantile_cont(gap, 0.025) as lo, quantile_cont(gap, 0.975) as hi from gp group by format) select format, round(gap, 6) "
           "as gap, round(lo, 6) as lo, round(hi, 6) as hi, lo > 0 or hi < 0 as excludes_0 from g0 join c using (format)")  # fmt: skip
def g24(spark, d):
    b = _bins(spark, d)
    seen = ag.vs_rest(ag.marginal_z(b, "format"), "format", "SR")
    c = seen.join(ag.percentile_ci(ag.gap_bootstrap(b, "format", "SR", BIN_REPS, "gap"), ["format"], "gap"), "format")
    return _rounded(c.withColumn("excludes_0", (F.col("lo") > 0) | (F.col("hi") < 0)))


# ---- probes ------------------------------------------------------------------------------------------------

_GT = (f"{CH}, g0 as (select bench, count(*) as n, count_if(chosen = 0) as k from ou group by bench), g1 as (select *, (k / n + 1.959964 * 1.959964 / "
    f"(2 * n)) / (1 + 1.959964 * 1.959964 / n) as mid, 1.959964 * sqrt(k / n * (1 - k / n) / n + 1.959964 * 1.959964 / (4 * n * n)) / (1 + 1.959964 * "
    f"1.959964 / n) as half from g0), gt as (select bench, n, k, k / n as acc, mid - half as lo, mid + half as hi, case when mid - half > 0.25 then "
    f"'main' when mid + half >= 0.25 then 'caution' else 'failure control' end as tier from g1)")


@query("p03_tiers", f"with {_GT}, po(bench, role, has_split) as (values {_values(pr.POLICY)}) select bench, tier as gate, case when role = 'excluded' "
    f"then role when tier = 'main' then role else tier end as tier, has_split and tier = 'main' and role <> 'excluded' as split_used from gt join po using (bench)")
def p03(spark, d):
    return pr.assign_tiers(pr.gate(_outcomes(spark, d), ["bench"]), pr.POLICY)


def _variant(tag: str, grad: str, docs: str = "dg", words: str = "dw") -> str:
    """SQL of bins with z under one set of query gradients."""
    return (
        f"{tag}m as (select bench, module, [{_QG}] as q from {grad} group by all), {tag}s as (select doc_id, topic, format, bench, sum({_DOTS}) as "
            f"score from {docs} join {tag}m using (module) join {words} using (doc_id) group by all), "
        f"{tag}0 as (select bench, topic, format, count(*) as n_docs, avg(score) as mean from {tag}s group by all), {tag} as (select *, (mean - "
            f"avg(mean) over (partition by bench)) / nullif(stddev_pop(mean) over (partition by bench), 0) as z from {tag}0)"
    )


TWO = (DOCS + ", " + QRYS + ", " + CONV + ", " + _grad("qa", "qs", "bench, query_id", "base") + ", " + _grad("qb", "qs", "bench, query_id",
    "inst") + ", " + _variant("ba", "qa") + ", " + _variant("bb", "qb"))


def _two(spark, d):
    return (ag.zscore(ag.bin_mean(_scores(spark, d, m))) for m in (None, _instruct))


@query("p14_variant_shift", f"with {TWO}, " + ", ".join(f"l{t} as (select bench, avg(case when format in ('de', 'en') then z end) - avg(case when "
    f"format in ('es', 'fr') then z end) as l from b{t} group by bench)" for t in "ab") + " select bench, round(la.l, 6) as before, round(lb.l, 6) as "
    "after, round(lb.l - la.l, 6) as shift from la join lb using (bench)")
def p14(spark, d):
    return _rounded(rp.variant_shift(*(pr.register_loading(b) for b in _two(spark, d))))


@query("p19_variant_corr", f"with {TWO} select bench, count(*) as n_bins, round(corr(ba.z, bb.z), 6) as r from ba join bb using (bench, topic, format) group by bench")
def p19(spark, d):
    return _rounded(rp.profile_agreement(*_two(spark, d)))


_NET = ("c as (select bench, seed, avg(gamma) as c from runs where recipe = 'random' group by all), net as (select topic, bench, seed, avg(gamma) - "
    "max(c) as d from runs join c using (bench, seed) where recipe = 'influence' group by all)")


@query("p20_heldout_unlearning", f"with {LED}, {_NET}, a as (select topic, count(*) as n, avg(d) as mean, stddev_samp(d) as sd, count_if(d < 0) as "
    f"n_negative, count_if(d <> 0) as m, count_if(d > 0) as k from net group by topic), b as (select topic, bench, sum(d) as s, count(*) as n from "
    f"net group by all), j as (select topic, min(x) as lowest, max(x) as highest from (select topic, (sum(s) over (partition by topic) - s) / (sum(n) "
    f"over (partition by topic) - n) as x from b) group by topic) "
       "select topic, n, n_negative, round(mean, 6) as mean, round(mean - 1.959964 * sd / sqrt(n), 6) as lo, round(mean + 1.959964 * sd / sqrt(n), 6) "
           "as hi, round((mean - avg(mean) over ()) / nullif(stddev_pop(mean) over (), 0), 6) as z, round(least(1.0, 2 * "
           "list_sum(list_transform(range(0, cast(least(k, m - k) + 1 as bigint)), lambda i: exp(lgamma(m + 1) - lgamma(i + 1) - lgamma(m - i + 1) - "
           "m * ln(2))))), 6) as p, round(lowest, 6) as lowest, round(highest, 6) as highest from a join j using (topic)")  # fmt: skip
def p20(spark, d):
    return _rounded(se.heldout_unlearning(_led(spark, d)))


_CASE = "case bench when '1-URGENT' then 'SR' when '2-HIGH' then 'TR' when '3-MEDIUM' then 'SK' when '4-NOT SPECIFIED' then 'TK' end"


@query("p21_damage_spearman", f"with {SB}, {LED}, m as (select {_CASE} as bench, format as topic, avg(z) as x from bins group by all), g as (select "
    f"bench, topic, avg(gamma) as y from runs where recipe = 'influence' group by all), k as (select bench, rank() over (partition by bench order by "
    f"x) + (count(*) over (partition by bench, x) - 1) / 2 as x, rank() over (partition by bench order by y) + (count(*) over (partition by bench, y) "
    f"- 1) / 2 as y from m join g using (bench, topic)) select bench, count(*) as n, round(corr(x, y), 6) as rho from k group by bench")
def p21(spark, d):
    """Attribution of a nation on the star grid against the ledger's damage of that nation: Spearman."""
    names = {"1-URGENT": "SR", "2-HIGH": "TR", "3-MEDIUM": "SK", "4-NOT SPECIFIED": "TK"}
    m = ag.marginal_z(_star(spark, d), "format").select(F.coalesce(*[F.when(F.col("bench") == k, v) for k, v in names.items()]).alias("bench"),
        F.col("format").cast("long").alias("topic"), F.col("z").alias("x"))
    g = _led(spark, d).where("recipe = 'influence'").groupBy("bench", "topic").agg(F.avg("gamma").alias("y"))
    k = average_rank(average_rank(m.join(g, ["bench", "topic"]), "x", ["bench"], "rx"), "y", ["bench"], "ry")
    return k.groupBy("bench").agg(F.count("*").alias("n"), r6(F.corr("rx", "ry")).alias("rho"))


@query("v10s_control_by_seed", f"with {LED}, t as (select bench, topic, avg(gamma) as g from runs where recipe = 'influence' group by all), b as "
    f"(select bench, quantile_cont(g, 0.25) as q1, quantile_cont(g, 0.75) as q3 from t group by bench), c as (select bench, seed, avg(gamma) as "
    f"control from runs where recipe = 'random' group by all) select bench, seed, round(control, 6) as control, case when control > q3 then 'above' "
    f"when control < q1 then 'below' else 'inside' end as place from b join c using (bench)")
def v10s(spark, d):
    return _rounded(se.control_by_seed(_led(spark, d)))


# ---- lexical -----------------------------------------------------------------------------------------------


@query("l03_densities", f"with {LC} select doc_id, dim, round(1000 * count / n_words, 6) as density from lc join corpus using (doc_id)")
def l03(spark, d):
    c = src.corpus(spark, d)
    return _rounded(lx.densities(lx.counts(c, tokens(F.col("text"))), c.select("doc_id", "n_words")))


GROUPS = {"social": ("SR",), "commonsense": ("TR",), "expository": ("SK", "TK")}
CONTRASTS = [("commonsense", "expository"), ("social", "expository"), ("social", "commonsense")]
_GRP = "case bench when 'SR' then 'social' when 'TR' then 'commonsense' else 'expository' end"
_GC = (
    f"{TL}, gr0 as (select {_GRP} as grp, bench, rank, dim, lz from tl where lz is not null), gr as (select grp, dim, lz, row_number() over "
        f"(partition by grp, dim order by bench, rank) - 1 as i, count(*) over (partition by grp, dim) as n from gr0), "
    f"gk as (select grp, dim, rep, {_key(repr(SEED), 'rep', 'grp', 'i')} % n as i from gr, range({REPS}) t(rep)), gx as (select rep, grp, dim, "
        f"avg(lz) as m from gk join gr using (grp, dim, i) group by all union all select -1, grp, dim, avg(lz) from gr group by all), "
    f"ct(a, b) as (values {_values(CONTRASTS)}), gd as (select rep, a, b, dim, max(case when grp = a then m end) - max(case when grp = b then m end) "
        f"as d from gx, ct group by all)"
)


@query("l08_group_contrast", f"with {_GC} select a, b, dim, round(max(case when rep < 0 then d end), 6) as delta, round(quantile_cont(case when rep "
    f">= 0 then d end, 0.025), 6) as lo, round(quantile_cont(case when rep >= 0 then d end, 0.975), 6) as hi from gd group by a, b, dim")
def l08(spark, d):
    return _rounded(lx.group_contrast(_top_lex(spark, d), GROUPS, CONTRASTS, REPS, SEED))


@query("l13_bimodal_split", f"with {TOP} select bench, count_if(format in ('en', 'fr')) as interactional, count_if(format in ('de', 'es')) as "
    f"expository, count_if(format in ('en', 'fr')) >= 8 and count_if(format in ('de', 'es')) >= 8 as bimodal from top group by bench")
def l13(spark, d):
    return lx.bimodal_split(lx.top_bins(_bins(spark, d)))


@query("l14_wide_matrix", f"with {LM} select topic, format, " + ", ".join(f"round(max(case when dim = '{x}' then rate end), 6) as "
    f"{x}" for x in lx.LEXICON) + " from lm group by topic, format")
def l14(spark, d):
    return _rounded(lx.wide_matrix(_lex(spark, d)))


@query("l15_claim_tiers", f"select * from (values {_values(lx.claim_tiers())}) t(family, tier, claim)")
def l15(spark, d):
    return spark.createDataFrame(lx.claim_tiers(), "family string, tier string, claim string")


@query("l16_composites", f"with {TL}, cp(composite, dim) as (values {_values((c, x) for c, xs in lx.COMPOSITES.items() for x in xs)}) select bench, "
    f"composite, round(avg(lz), 6) as z from tl join cp using (dim) group by all")
def l16(spark, d):
    return _rounded(lx.composites(_top_lex(spark, d)))


@query("l17_row_normalised", f"with {TL}, m as (select dim, bench, avg(lz) as m from tl group by all) select dim, bench, round((m - avg(m) over "
    f"(partition by dim)) / nullif(stddev_pop(m) over (partition by dim), 0), 6) as z from m")
def l17(spark, d):
    return _rounded(lx.row_normalised(_top_lex(spark, d)))


# ---- unlearning --------------------------------------------------------------------------------------------

_H = f"list_transform({{}}, lambda t: {_key(repr('v'), 't')} % {un.V})"
_BF = ("select {k}u, v, sum(1.0::double / (len(h) - 1)) as f from (select {k}h, h[i] as u, h[i + 1] as v from {s}, unnest(range(1, len(h))) r(i) "
    "where len(h) > 1) group by all")
_RND = f"(select doc_id, source as topic from documents qualify row_number() over (partition by source order by {_key(repr('42'), 'doc_id')}, doc_id) <= 25)"
STOP = (
    f"wd as (select doc_id, {TOK} as w from documents), sg as (select doc_id, i, {_key(repr('seg'), 'doc_id', 'i')} as k, w[i * 8 + 1 : i * 8 + 8] as "
        f"s from wd, unnest(range(0, cast(ceil(len(w) / 8) as bigint))) r(i)), sw as (select doc_id, flatten(list(s order by k, i)) as w from sg group by doc_id), "
    f"fs as {_RND}, h0 as (select doc_id, {_H.format('w')} as h from wd), h1 as (select 'forget' as role, topic, h from h0 join fs using (doc_id) "
        f"union all select 'shuffled', topic, {_H.format('w')} from sw join fs using (doc_id)), "
    f"bf as ({_BF.format(k='role, topic, ', s='h1')}), b0 as ({_BF.format(k='', s='h0')}), gd as (select u, v, 0.5 + 1e5 * coalesce(f, 0) / (select "
        f"count(*) from documents) as c from (select u, v from range({un.V}) a(u), range({un.V}) b(v)) left join b0 using (u, v)), "
    "lp as (select u, v, ln(c / sum(c) over (partition by u)) as lp from gd), pp as (select role, topic, exp(-sum(f * lp) / sum(f)) as ppl from bf "
        "join lp using (u, v) group by all)"
)


def _runs(spark, d):
    """(all statistics of the corpus, forget sets with their shuffled form by run)."""
    docs, words = src.corpus(spark, d), tokens(F.col("text"))
    rnd = un.forget_random(docs, 25, "42").select(F.col("topic").alias("run_id"), "doc_id")
    return un.corpus_stats(docs, words), un.forget_stats(rnd, docs, words, "seg")


@query("u06_stop_target", f"with {STOP} select topic as run_id, round(max(case when role = 'forget' then ppl end), 6) as base_ppl, round(max(case "
    f"when role = 'shuffled' then ppl end), 6) as target_ppl from pp group by topic")
def u06(spark, d):
    return _rounded(un.stop_targets(*_runs(spark, d)))


@query("u07_multi_bin", f"with {SCORES}, i as (select distinct doc_id, bench from scores where topic in ('src0', 'src1') qualify row_number() over "
    f"(partition by topic, bench order by score desc, doc_id) <= 5) select bench, doc_id, 'multi' as arm from i")
def u07(spark, d):
    s = un.forget_influence(_scores(spark, d).where("topic in ('src0', 'src1')"), 5)
    return un.forget_multi([s.where(F.col("topic") == t) for t in ("src0", "src1")])


# ---- replication -------------------------------------------------------------------------------------------

_PAGE = (f"trim(regexp_replace(replace(regexp_replace(regexp_replace(html, '{src.PAGE_NOISE}', ' ', 'g'), '{src.PAGE_TAG}', ' ', 'g'), '&amp;', '&'), "
    f"'[ \\t\\r\\n]+', ' ', 'g'))")
_E2 = f"select cast('0x' || substr(md5(text), 1, 15) as bigint) as doc_id, text from (select distinct {_PAGE} as text from pages) where text <> ''"


def _eco(tag: str, source: str) -> str:
    tv = f"select doc_id, {_key(repr('topic'), 't')} % 24 as v from (select doc_id, unnest(w) as t from {tag}t)"
    return (
        f"{tag}t as (select doc_id, {TOK} as w from ({source})), " + _VOTE.format(f"{tag}a", tv) + ", " + _VOTE.format(f"{tag}b", tv.replace("'topic'", "'format'"))
        + f", {tag}w as (select doc_id, {tag}a.label as topic, {tag}b.label as format, w as uni, {_PAIR} as bi from {tag}t join {tag}a using (doc_id) "
            f"join {tag}b using (doc_id)), "
        + _sums(f"{tag}s_", f"{tag}w", "doc_id") + ", " + _model(f"{tag}p", f"{tag}s_") + ", " + _grad(f"{tag}g", f"{tag}s_", "doc_id",
            f"{tag}p") + ", " + _grad(f"{tag}q", "qs", "bench, query_id", f"{tag}p") + ", " + _variant(tag, f"{tag}q", f"{tag}g", f"{tag}w")
    )


ECO = QRYS + ", " + _eco("x1", "select doc_id, text from documents") + ", " + _eco("x2", _E2)


def _eco_bins(spark, d, name, table, docs):
    """Bins of one ecosystem: its index and model are made once for a state of its tables, and only the bins are kept."""
    sources = [src.table(spark, d, table), src.table(spark, d, "benchmark")]
    return kept(spark, name, sources, lambda path: rp.ecosystem_bins(rp.labelled(docs), src.bench_queries(spark, d)).write.parquet(path))


def _e1(spark, d):
    return _eco_bins(spark, d, "e1_bins", "documents", src.spread(src.table(spark, d, "documents").select("doc_id", "text")))


def _e2_docs(spark, d):
    return rp.minted(src.spread(src.table(spark, d, "pages").select("html")), src.page_text(F.col("html")))


def _e2(spark, d):
    return _eco_bins(spark, d, "e2_bins", "pages", _e2_docs(spark, d))


@query("r01_page_documents", f"select doc_id, text, cast(length(text) as bigint) as n_chars from ({_E2})")
def r01(spark, d):
    return _e2_docs(spark, d).withColumn("n_chars", F.length("text").cast("long"))


@query("r02_second_corpus_bins", f"with {QRYS}, {_eco('x2', _E2)} select bench, topic, format, n_docs, round(mean, 6) as mean, round(z, 6) as z from x2")
def r02(spark, d):
    return _rounded(_e2(spark, d).select("bench", "topic", "format", "n_docs", "mean", "z"))


@query("r03_profile_agreement", f"with {ECO} select bench, count(*) as n_bins, round(corr(x1.z, x2.z), 6) as r from x1 join x2 using (bench, topic, "
    f"format) group by bench")
def r03(spark, d):
    return _rounded(rp.profile_agreement(_e1(spark, d), _e2(spark, d)))


@query("r04_register_flips", f"with {ECO}, {_GT.replace('qi as', 'qj as').replace('from qi a', 'from qj a').replace('qi b', 'qj b')}, "
    f"" + ", ".join(f"l{k} as (select bench, avg(case when format < 12 then z end) - avg(case when format >= 12 then z end) as l from x{k} group by "
    f"bench)" for k in "12") + " select bench, round(l1.l, 6) as e1, round(l2.l, 6) as e2, l1.l * l2.l < 0 as flip from l1 join l2 using (bench) join "
    "gt using (bench) where tier <> 'failure control'")
def r04(spark, d):
    tiers = pr.gate(_outcomes(spark, d), ["bench"])
    return _rounded(rp.register_flip(rp.register_loading(_e1(spark, d)), rp.register_loading(_e2(spark, d)), tiers))


@query("r10_ecosystem_products", f"with {QRYS}, {_eco('x2', _E2)}, tm as (select bench, topic, avg(z) as z from x2 group by all), fm as (select "
    f"bench, format, avg(z) as z from x2 group by all), "
       "r as (select x.bench as a, y.bench as b, corr(x.z, y.z) as r from x2 x join x2 y using (topic, format) group by all), "
       "l as (select bench, avg(case when format < 12 then z end) - avg(case when format >= 12 then z end) as loading from x2 group by bench) "
       "select 'bins' as product, bench, topic::varchar as a, format::varchar as b, round(z, 6) as value from x2 union all select 'topics', bench, "
           "topic::varchar, null, round(z, 6) from tm union all "
       "select 'formats', bench, format::varchar, null, round(z, 6) from fm union all select 'correlation', a, b, null, round(r, 6) from r union all "
           "select 'loading', bench, null, null, round(loading, 6) from l")  # fmt: skip
def r10(spark, d):
    """One runner's products of the second corpus."""
    return _rounded(rp.as_long(rp.run_ecosystem(rp.labelled(_e2_docs(spark, d)), src.bench_queries(spark, d))))


@query("r11_product_parity")
def r11(spark, d):
    """Products of the second ecosystem against those of the first, which has no minted ids to report."""
    items = src.bench_queries(spark, d)
    first = rp.run_ecosystem(rp.labelled(src.table(spark, d, "documents").select("doc_id", "text")), items)
    docs = _e2_docs(spark, d)
    second = rp.run_ecosystem(rp.labelled(docs), items) | {"minted_ids": docs.select("doc_id")}
    return rp.parity(spark, first, second).groupBy("status").agg(F.count("*").alias("n"))


_TQ = (f"c0 as (select conv_id, turn, role, {TOK} as w from conversations), q as (select b.conv_id * 100 + b.turn as query_id, b.conv_id % 9 as "
    f"bench, a.w as prompt, b.w as completion from c0 a join c0 b on a.conv_id = b.conv_id and b.turn = a.turn + 1 where a.role = 'user' and b.role = "
    f"'assistant'), " + CH[CH.index("qi as"):])


@query("r06_descriptive_eval", f"with {_GT.replace(CH, _TQ)} select bench, n, k, round(acc, 6) as acc, round(lo, 6) as lo, round(hi, 6) as hi, tier, "
    f"'descriptive' as claim_scope from gt")
def r06(spark, d):
    """Evaluation of the third corpus; its scope refuses causal and recurrence claims."""
    counts = pr.token_counts(src.table(spark, d, "documents"), tokens(F.col("text")))
    out = pr.outcomes(pr.score_choices(pr.choices(src.turn_queries(spark, d)), counts))
    return _rounded(pr.gate(out, ["bench"]).withColumn("claim_scope", F.lit(rp.require_scope("E3", "probes"))))


_DZ = ("select target, avg(d) / stddev_samp(d) as dz, median(d) as m from (select target, round(a.gamma - b.gamma, 9) as d from tg a join tg b using "
    "(topic, seed, target) where a.recipe = 'influence' and b.recipe = '{}') group by target")


@query("r08_compare_controls", f"with {PD}, a as ({_DZ.format('random')}), b as ({_DZ.format('naive')}) select target, round(a.dz, 6) as dz_a, "
    f"round(a.m, 6) as median_a, round(b.dz, 6) as dz_b, round(b.m, 6) as median_b, round(abs(a.dz - b.dz), 6) as shift from a join b using (target)")
def r08(spark, d):
    return _rounded(rp.compare_effects(*(se.cohen_dz(se.paired(_led(spark, d), b=c)) for c in ("random", "naive"))))


@query("r09_claim_scopes", f"select * from (values {_values(rp.scope_table())}) t(corpus, family, claim_scope)")
def r09(spark, d):
    return spark.createDataFrame(rp.scope_table(), "corpus string, family string, claim_scope string")


# ---- cost --------------------------------------------------------------------------------------------------

_RATE = "case seed when 42 then 1.0 when 43 then 0.5 else 0.125 end"


@query("k03_device_hours", f"with {LED} select recipe as phase, count(*) as n_jobs, cast(ceil(round(sum(steps / 100 * {_RATE}), 6)) as bigint) as "
    f"hours from runs group by recipe")
def k03(spark, d):
    device = F.when(F.col("seed") == 42, "large").when(F.col("seed") == 43, "medium").otherwise("small")
    return cost.normalise_hours(_led(spark, d).select(F.col("recipe").alias("phase"), device.alias("device"), (F.col("steps") / 100).alias("hours")))


@query("k05_phase_report")
def k05(spark, d):
    """Wall clock of each phase here; the labels' rows per second are the classifier's throughput."""
    docs, words = src.corpus(spark, d), tokens(F.col("text"))
    sums, base = _index(spark, d)
    g, q = at.gradients(sums, base), _query_grad(spark, d, base)
    phases = {
        "labels": lambda: rp.labelled(docs), "index": lambda: g, "queries": lambda: q,
            "preconditioner": lambda: g.agg(*[F.avg(F.col(m)[i] * F.col(m)[i]).alias(f"{m}{i}") for m in at.MODULES for i in range(at.D)]),
        "scoring": lambda: _scores(spark, d), "unlearning statistics": lambda: un.corpus_stats(docs, words),
    }
    return cost.phase_report(spark, phases)


@query("k06_steps", f"with {LED} select recipe, count(*) as n_runs, min(steps) as least, round(avg(steps), 6) as mean, max(steps) as most, "
    f"cast(sum(steps // 250 + 1) as bigint) as n_evals from runs group by recipe")
def k06(spark, d):
    return _rounded(cost.steps_report(_led(spark, d)))


# ---- streams -----------------------------------------------------------------------------------------------


@query("s06_late_data", f"with {EV}, m as (select max(ts) - interval 1 hour as wm from ev where event_id % 2 = 0), k as (select format, count(*) as "
    f"n, count_if(event_id % 2 = 0 or date_trunc('day', ts) + interval 1 day > wm) as n_kept from ev, m group by format) select format, n_kept, n - "
    f"n_kept as n_late from k")
def s06(spark, d):
    """Events of odd id arrive after all others."""
    ev = src.table(spark, d, "events")
    return st.late_report(st.replayed(ev.where("event_id % 2 = 0"), ev.where("event_id % 2 <> 0")), ev.withColumnRenamed("event_type", "format"))


@query("s07_stream_static", f"with {EV} select c_mktsegment as segment, format, count(*) as n from ev join customer on user_id = c_custkey group by all")
def s07(spark, d):
    owners = src.table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), F.col("c_mktsegment").alias("segment"))
    joined = st.with_owner(st.score_stream(spark, d), owners).groupBy("segment", "format").agg(F.count("*").alias("n"))
    return st.run_once(joined, "complete")


@query("s07i_interval_join", f"with {EV} select a.user_id as user_id, a.event_id as first_id, b.event_id as then_id from ev a join ev b on a.user_id "
    f"= b.user_id and b.ts between a.ts and a.ts + interval 1 hour where a.format = 'view' and b.format = 'purchase'")
def s07i(spark, d):
    return st.run_once(st.followed_by(st.score_stream(spark, d), "view", "purchase"), "append")


@query("s08_running_topk", f"with {EV} select topic, format, cast(row_number() over (partition by topic, format order by value desc, event_id) as "
    f"integer) as rank, event_id, value from ev where value is not null qualify rank <= 5")
def s08(spark, d):
    return st.latest(st.run_once(st.running_topk(st.score_stream(spark, d)), "update"))


@query("s08m_convergence_monitor", f"with {EV} select topic, format, min(ts) as ts from ev where value >= 200 group by all")
def s08m(spark, d):
    return st.run_once(st.fires_once(st.score_stream(spark, d), 200.0), "append")
