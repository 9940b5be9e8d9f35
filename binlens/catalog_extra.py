"""Queries of the trained classifier, masks, caps, shards of the score stage and the kept index, with their SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from binlens.catalog import _DOTS, BENCHES, BINS, CH, CORPUS, DOCS, LED, QRYS, SCORES, SEED, _bins, _grad, _index, _led, _nation_z, _outcomes, _query_grad, _rounded, _scores, _sel, query
from binlens.catalog import NB as NB_SQL
from binlens.catalog_rest import _QG, _key
from binlens.operators import aggregate as ag
from binlens.operators import attribution as at
from binlens.operators import corpus as co
from binlens.operators import probes as pr
from binlens.operators import selectivity as se
from binlens.operators import unlearn as un
from binlens.sources import tables as src
from binlens.sources.index import corpus_index, kept
from binlens.sources.tables import tokens

# ---- trained classifier ------------------------------------------------------------------------------------

_LANG = r"""regexp_extract(html, '<html lang="([a-z]+)"', 1)"""
_PTXT = (f"trim(regexp_replace(replace(regexp_replace(regexp_replace(html, '{src.PAGE_NOISE}', ' ', 'g'), '{src.PAGE_TAG}', ' ', 'g'), '&amp;', '&'), "
    f"'[ \\t\\r\\n]+', ' ', 'g'))")
_UTOK = "list_filter(string_split_regex(lower(url), '[^a-z]+'), lambda x: x <> '')"
PG = (
    f"pg as (select page_id as doc_id, {_LANG} as label, {_key(repr('fold'), 'page_id')} % 4 as fold, w as plain, list_concat(w, list_transform(u, "
        f"lambda x: 'url:' || x)) as with_url "
    f"from (select page_id, html, {_UTOK} as u, list_filter(string_split_regex(lower({_PTXT}), '\\s+'), lambda x: x <> '') as w from pages))"
)


def _nb_sql(tag: str, feature: str, fold: int) -> str:
    """Naive Bayes trained on one fold, asked about the held-out one."""
    return (
        f"{tag}s as (select label, t, count(*) as k from (select label, unnest({feature}) as t from pg where fold = {fold}) group by all), {tag}v as "
            f"(select count(distinct t) as v from {tag}s), "
        f"{tag}l as (select label, ln(docs / sum(docs) over ()) as prior, -ln(coalesce(n, 0) + v) as unseen from (select label, count(*) as docs from "
            f"pg where fold = {fold} group by label) left join (select label, sum(k) as n from {tag}s group by label) using (label), {tag}v), "
        f"{tag}o as (select doc_id, s.label, sum(ln(k + 1)) as w from (select doc_id, unnest({feature}) as t from pg where fold = 3) join {tag}s s "
            f"using (t) group by all), "
        f"{tag}a as (select p.doc_id, l.label, round(prior + len(p.{feature}) * unseen + coalesce(w, 0), 9) as s from pg p cross join {tag}l l left "
            f"join {tag}o o on o.doc_id = p.doc_id and o.label = l.label where p.fold = 3), "
        f"{tag} as (select doc_id, min(case when s = top then label end) as label, 1 / sum(exp(s - top)) as conf from (select *, max(s) over "
            f"(partition by doc_id) as top from {tag}a) group by doc_id)"
    )


NB = PG + ", " + ", ".join(_nb_sql(t, f, k) for t, f, k in (("ta", "with_url", 0), ("tb", "with_url", 1), ("su", "with_url", 2), ("sp", "plain", 2)))
NB += ", fl as (select p.doc_id, p.label as gold, ta.label as teacher, ta.conf as teacher_conf, tb.label as other_teacher, su.label as url_label, sp.label as label, sp.conf as conf from pg p join ta using (doc_id) join tb using (doc_id) join su using (doc_id) join sp using (doc_id) where p.fold = 3)"


def _page_features(spark, d):
    rows = src.table(spark, d, "pages").select(F.col("page_id").alias("doc_id"), F.regexp_extract("html", r'<html lang="([a-z]+)"', 1).alias("gold"),
        F.filter(F.split(F.lower("url"), "[^a-z]+"), lambda x: x != "").alias("u"), tokens(src.page_text(F.col("html"))).alias("plain"))
    fold = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit("fold"), F.col("doc_id").cast("string"))), 1, 8), 16, 10).cast("long") % 4
    return rows.select("doc_id", "gold", fold.alias("fold"), "plain", F.concat("plain", F.transform("u", lambda x: F.concat(F.lit("url:"), x))).alias("with_url"))


def _classified(spark, d):
    """Held-out pages with the labels of two teachers (text and URL, trained on a fold each) and of two students, with
    and without the URL, trained on a third fold."""
    pages = _page_features(spark, d)
    held = pages.where("fold = 3")

    def one(feature, fold, name, conf=None):
        out = co.classify(held, co.naive_bayes(pages.where(F.col("fold") == fold), "gold", feature), "gold", feature)
        return out.select("doc_id", F.col("label").alias(name), *([F.col("conf").alias(conf)] if conf else []))

    out = held.select("doc_id", "gold").join(one("with_url", 0, "teacher", "teacher_conf"), "doc_id").join(one("with_url", 1, "other_teacher"), "doc_id")
    return out.join(one("with_url", 2, "url_label"), "doc_id").join(one("plain", 2, "label", "conf"), "doc_id")


@query("c27_trained_labels", f"with {NB} select doc_id, gold, teacher, round(teacher_conf, 4) as teacher_conf, other_teacher, url_label, label, "
    f"round(conf, 4) as conf from fl")
def c27(spark, d):
    return _classified(spark, d).select("doc_id", "gold", "teacher", F.round("teacher_conf", 4).alias("teacher_conf"), "other_teacher", "url_label",
        "label", F.round("conf", 4).alias("conf"))


_VARIANTS = {"url": "url_label", "no_url": "label", "teacher_self": "other_teacher"}
_ACC = ("select '{0}' as variant, cast(sum(n) as bigint) as n, round(sum(ok) / sum(n), 6) as mean_acc, round(min(ok / n), 6) as worst_group_acc, "
    "round(sum(gold_ok) / sum(n), 6) as gold_acc from (select teacher, count(*) as n, count_if({1} = teacher) as ok, count_if({1} = gold) as gold_ok "
    "from fl where teacher_conf >= 0.75 group by teacher)")


@query("c28_trained_accuracy", f"with {NB} " + " union all ".join(_ACC.format(*v) for v in _VARIANTS.items()))
def c28(spark, d):
    """Accuracy on pages of which the teacher is sure (0.75), mean and of the worst label, with and without the URL; and
    the teacher's agreement with its like, trained on another fold."""
    return co.accuracy_report(_classified(spark, d), _VARIANTS, 0.75)


@query("c29_format_agreement", f"with {NB} select gold, url_label, label, count(*) as n from fl group by all")
def c29(spark, d):
    """Confusion of the two variants' labels."""
    return _classified(spark, d).groupBy("gold", "url_label", "label").agg(F.count("*").alias("n"))


# ---- caps, shards, top lists, the kept index -------------------------------------------------------------

CAP = 5


@query("a13_query_cap", f"with {QRYS.split(', qs as')[0]} select bench, query_id, cast(row_number() over (partition by bench order by "
    f"{_key(repr(SEED), 'query_id')}, query_id) as integer) as rank from qw1 qualify rank <= {CAP}")
def a13(spark, d):
    return pr.cap_queries(src.bench_queries(spark, d), CAP, SEED).select("bench", "query_id", "rank")


@query("a14_scores_by_shard", f"with {SCORES} select {_key(repr('shard'), 'doc_id')} % 8 as shard, bench, count(*) as n, round(sum(score), 5) as "
    f"total, round(max(score), 6) as best from scores group by all")
def a14(spark, d):
    """The score stage's receipt for each (shard, benchmark): what the reference runs as one job each is one pass."""
    s = co.shard(_scores(spark, d), 8, "doc_id")
    return s.groupBy("shard", "bench").agg(F.count("*").alias("n"), F.round(F.sum("score"), 5).alias("total"), F.round(F.max("score"), 6).alias("best"))


@query("a15_topk_by_bench", f"with {SCORES} select bench, doc_id, cast(row_number() over (partition by bench order by score desc, doc_id) as integer) "
    f"as rank, round(score, 6) as score from scores qualify rank <= 100")
def a15(spark, d):
    return at.topk_docs(_scores(spark, d), 100, ["bench"]).select("bench", "doc_id", "rank", F.round("score", 6).alias("score"))


@query("a16_index_receipt", f"with {DOCS} select module, count(*) as n_docs, cast(sum(n) as bigint) as n_tokens, cast(sum(s[1]) as bigint) as s1, "
    f"cast(sum(s[16]) as bigint) as s16 from ds group by module")
def a16(spark, d):
    """The kept index against one made anew by the SQL: documents, tokens and signs of each module."""
    rows = at.by_module(corpus_index(spark, d)).where("g.n > 0")
    return rows.groupBy("module").agg(F.count("*").alias("n_docs"), F.sum("g.n").alias("n_tokens"), F.sum(F.col("g.s")[0]).alias("s1"),
        F.sum(F.col("g.s")[15]).alias("s16"))


@query("k02m_index_measured")
def k02m(spark, d):
    """Bytes of the kept index on disk, beside the formula's."""
    rows = corpus_index(spark, d).groupBy(F.col("_metadata.file_path").alias("f"), F.col("_metadata.file_size").alias("size")).agg(F.count("*").alias("n"))
    return rows.agg(F.sum("size").alias("bytes_on_disk"), (F.sum("n") * 2 * at.D * 4).alias("formula_bytes"), F.round(F.sum("size") / F.sum("n"),
        2).alias("bytes_per_doc"))


# ---- masks -------------------------------------------------------------------------------------------------

MB = (
    DOCS + ", " + QRYS + ", " + _grad("qg", "qs", "bench, query_id", "base") + ", " + CH + ", mk as (select bench, query_id // 4 % 2 as subset from "
        "ou group by all having count_if(chosen = 0) >= 0.25 * count(*)), "
    f"qk as (select bench || '/' || subset as mask, module, [{_QG}] as q from qg join mk using (bench) where query_id // 4 % 2 = subset group by all), "
    f"ms as (select doc_id, topic, format, mask as bench, sum({_DOTS}) as score from dg join qk using (module) join dw using (doc_id) group by all), "
        f"mb0 as (select bench, topic, format, avg(score) as mean from ms group by all), "
    "mb as (select *, (mean - avg(mean) over (partition by bench)) / nullif(stddev_pop(mean) over (partition by bench), 0) as z from mb0)"
)


def _mask_bins(spark, d):
    """Bins with z of each retained subset of a benchmark: subsets below chance are masked out; one pass for all masks."""
    out = _outcomes(spark, d).withColumn("subset", F.floor(F.col("query_id") / 4) % 2)
    sums, base = _index(spark, d)
    q = _query_grad(spark, d, base).join(pr.retained(out), ["bench", "query_id"]).withColumn("bench", F.concat_ws("/", "bench", F.col("subset").cast("string")))
    s = at.score_index(at.gradients(sums, base), at.reduce_queries(q, ["bench"]), ["doc_id", "topic", "format"], ["bench"])
    return ag.zscore(s.groupBy("bench", "topic", "format").agg(F.avg("score").alias("mean")))


@query("p13_mask_bins", f"with {MB} select bench, topic, format, round(z, 6) as z from mb")
def p13(spark, d):
    return _rounded(_mask_bins(spark, d).select("bench", "topic", "format", "z"))


@query("p13m_mask_topics", f"with {MB} select bench, topic, round(avg(z), 6) as z from mb group by bench, topic")
def p13m(spark, d):
    return _rounded(ag.marginal_z(_mask_bins(spark, d), "topic"))


@query("p13c_mask_consensus", f"with {MB} select topic, format, round(avg(z), 6) as mean_z, round(var_samp(z), 6) as var_z from mb group by topic, format")
def p13c(spark, d):
    return _rounded(pr.cross_mask(_mask_bins(spark, d)))


# ---- influence against damage --------------------------------------------------------------------------------

_INF = "recipe = 'influence'"


@query("v30_rank_gap", f"with {LED}{NB_SQL}, g as (select target, topic, avg(gamma) as g from runs where {_INF} and target = bench group by all), "
       "j as (select g.target, g.topic, g, z from g join nb on nb.bench = g.target and nb.topic = g.topic), "
       "r as (select *, row_number() over (partition by target order by z desc, topic) as by_influence, row_number() over (partition by target order "
           "by g desc, topic) as by_damage, count(*) over (partition by target) as n from j) "
       "select target, topic, cast(by_damage as integer) as by_damage, n from r where by_influence = 1")  # fmt: skip
def v30(spark, d):
    return se.rank_gap(_led(spark, d), _nation_z(spark, d))


_SB2 = ("b2 as (select s_nationkey::bigint as topic, p_brand as format, case o_orderpriority when '1-URGENT' then 'SR' when '2-HIGH' then 'TR' when "
    "'3-MEDIUM' then 'SK' else 'TK' end as bench, avg(l_extendedprice * (1 - l_discount)) as mean from lineitem join supplier on l_suppkey = "
    "s_suppkey join orders on l_orderkey = o_orderkey join part on l_partkey = p_partkey where s_nationkey < 24 and o_orderpriority <> '5-LOW' group "
    "by all), bz as (select *, (mean - avg(mean) over (partition by bench)) / stddev_pop(mean) over (partition by bench) as z from b2)")


@query("v14p_parent_of_max_bin", f"with {LED}, "
    f"{_SB2}{_sel('topic', _INF)}{_sel('recipe', chr(114) + 'ecipe = ' + chr(39) + 'naive' + chr(39), 'nv')}, top as (select bench as target, topic "
    f"from bz qualify row_number() over (partition by bench order by z desc, topic, format) = 1) select target, topic, round(sel.mean_ratio, 6) as "
    f"chosen, round(nv.mean_ratio, 6) as naive, round(sel.mean_ratio / nv.mean_ratio, 6) as ratio from sel join top using (target, topic) join nv using (target)")
def v14p(spark, d):
    names = {"1-URGENT": "SR", "2-HIGH": "TR", "3-MEDIUM": "SK"}
    s = src.star_scores(spark, d).where("format < 24 and bench <> '5-LOW'")
    bench = F.coalesce(*[F.when(F.col("bench") == k, v) for k, v in names.items()], F.lit("TK"))
    bins = ag.zscore(s.groupBy(F.col("format").cast("long").alias("topic"), F.col("topic").alias("format"), bench.alias("bench")).agg(F.avg("score").alias("mean")))
    return _rounded(se.head_to_head(_led(spark, d), bins, "parent_of_max_bin"))


# ---- unlearning --------------------------------------------------------------------------------------------------


def _unlearning(spark, d):
    """All runs of the grid, made once for a state of the tables."""
    docs, items = src.corpus(spark, d), src.bench_queries(spark, d)

    def write(path):
        s, words, n = _scores(spark, d), tokens(F.col("text")), docs.count()
        sources = [src.table(spark, d, "documents"), src.table(spark, d, "benchmark")]
        sets = kept(spark, "forget_sets", sources, lambda at_: un.grid_sets(s, _bins(spark, d), docs, n).write.parquet(at_))
        gone = sets.select("doc_id").withColumn("topic", F.lit(""))
        keep = [un.retain_set(docs, gone, max(1, min(un.SIZES["retain"][0], int(un.SIZES["retain"][1] * n))),
            f"{k}r").select(F.lit(str(k)).alias("run_id"), "doc_id", F.lit("retain").alias("role")) for k in un.SEEDS]
        keep = keep[0].union(keep[1]).union(keep[2])
        split = src.spread(docs.select("doc_id", "text"))
        retain = kept(spark, "retain_stats", sources, lambda at_: un.set_stats(keep, split, words).write.parquet(at_))
        runs = un.run_grid(un.forget_texts(sets, split, words, "seg"), retain, un.corpus_stats(split, words), un.eval_items(pr.choices(items)), n)
        runs.write.parquet(path)

    return kept(spark, "unlearning", [src.table(spark, d, "documents"), src.table(spark, d, "benchmark")], write)


def _run_ledger(spark, d):
    return un.ledger_of(_unlearning(spark, d), BENCHES)


@query("u04_unlearning_grid")
def u04(spark, d):
    """Every run: five arms, all topics of the grid, four targets, three seeds, and the null-bin control."""
    return _rounded(_unlearning(spark, d))


@query("u08_paired_tests")
def u08(spark, d):
    """The paired analysis on the runs: influence against random in topic, by topic and seed, with both families of p."""
    p = se.paired(_run_ledger(spark, d))
    effect = se.cohen_dz(p)
    return _rounded(se.families(p).join(effect, "target"))


@query("u09_arms")
def u09(spark, d):
    """Each arm's damage on and off its target, steps, and what it does to general text."""
    runs = _unlearning(spark, d)
    led = un.ledger_of(runs, BENCHES)
    on, off = F.avg(F.when(F.col("target") == F.col("bench"), F.col("gamma"))), F.avg(F.when(F.col("target") != F.col("bench"), F.col("gamma")))
    g = led.groupBy("recipe").agg(on.alias("on_target"), off.alias("off_target"), F.avg("steps").alias("mean_steps"))
    return _rounded(g.join(un.collateral_ppl(runs), "recipe"))


@query("u10_cross_method")
def u10(spark, d):
    """Bin-level against per-document forget sets: the same pilot on both, and whose chosen topic beats naive selection."""
    led, z = _run_ledger(spark, d), ag.marginal_z(_bins(spark, d), "topic")
    naive = se.selectivity(led.where("recipe = 'naive'"), ["recipe"]).select("target", F.col("mean_ratio").alias("naive"))

    def pilot(recipe):
        runs = led.where(F.col("recipe") == recipe).withColumn("recipe", F.lit("influence"))
        return se.pilot(z, runs).join(naive, "target").select("target", F.try_divide("mean_ratio", "naive").alias("gamma"))

    both = pilot("bin").select("target", F.col("gamma").alias("bin_ratio")).join(pilot("influence").select("target",
        F.col("gamma").alias("document_ratio")), "target", "full_outer")
    pattern = F.when((F.col("bin_ratio") > 1) & (F.col("document_ratio") > 1), "both").when(F.col("bin_ratio") > 1,
        "bin").when(F.col("document_ratio") > 1, "document").otherwise("neither")
    return _rounded(both.withColumn("pattern", pattern))


@query("u11_net_of_null")
def u11(spark, d):
    return _rounded(un.net_of_null(_unlearning(spark, d)))


@query("u12_exact_reference")
def u12(spark, d):
    """Damage by unlearning beside that of the head made anew without the documents, by arm and benchmark."""
    g = _unlearning(spark, d).groupBy("recipe", "bench").agg(F.count("*").alias("n"), F.avg("gamma").alias("gamma"), F.avg("gamma_exact").alias("gamma_exact"))
    return _rounded(g)


@query("u13_bin_level_sets", f"with {BINS}, w as (select b.bench, topic, d.doc_id, row_number() over (partition by b.bench, topic order by b.z desc, "
    f"{_key(repr(SEED), 'd.doc_id')}, d.doc_id) as r from bins b join (select doc_id, source as topic, lang as format from documents) d using (topic, "
    f"format)) select bench, topic, doc_id, cast(r as integer) as rank from w where r <= 5")
def u13(spark, d):
    return un.forget_bin_level(_bins(spark, d), src.corpus(spark, d), 5, SEED).select("bench", "topic", "doc_id", "rank")


@query("u14_null_bin", f"with {CORPUS} select doc_id from corpus where not is_binned order by {_key(repr(SEED), 'doc_id')}, doc_id limit 10")
def u14(spark, d):
    return un.forget_null(src.corpus(spark, d).where("not is_binned"), 10, SEED).select("doc_id")


_RND5 = (f"f as (select doc_id, source as topic from documents where source in ('src0', 'src3') qualify row_number() over (partition by source order "
    f"by {_key(repr(SEED), 'doc_id')}, doc_id) <= 5)")


def _few(spark, d):
    return un.forget_random(src.corpus(spark, d).where("topic in ('src0', 'src3')"), 5, SEED)  # the sets that retained documents must avoid


@query("u15_retain_uniform", f"with {_RND5} select doc_id, source as topic from documents where doc_id not in (select doc_id from f) and source not "
    f"in (select topic from f) order by {_key(repr('43'), 'doc_id')}, doc_id limit 60")
def u15(spark, d):
    return un.retain_set(src.corpus(spark, d), _few(spark, d), 60, "43", "uniform")


@query("u16_retain_stratified", f"with {_RND5}, r as (select doc_id, source as topic, {_key(repr('43'), 'doc_id')} as u, row_number() over (partition "
    f"by source order by {_key(repr('43'), 'doc_id')}, doc_id) as r from documents where doc_id not in (select doc_id from f)) select doc_id, topic "
    f"from r order by r, u, doc_id limit 60")
def u16(spark, d):
    return un.retain_set(src.corpus(spark, d), _few(spark, d), 60, "43", "stratified")


@query("u17_gamma_modes", f"with {LED} select recipe, target, bench, round(avg(gamma), 6) as raw, round(avg(gamma) / 0.6, 6) as relative, "
    f"sign(avg(gamma)) as sign from runs group by all")
def u17(spark, d):
    """The three readings of damage on the synthetic ledger, with a base accuracy of 0.6."""
    g = _led(spark, d).groupBy("recipe", "target", "bench").agg(F.avg("gamma").alias("g"))
    base, after = F.lit(0.6), F.lit(0.6) - F.col("g")
    return g.select("recipe", "target", "bench", *[F.round(un.gamma(base, after, m), 6).alias(m) for m in ("raw", "relative")], un.gamma(F.lit(0.0),
        -F.round("g", 12), "sign").cast("int").alias("sign"))
