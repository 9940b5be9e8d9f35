"""Held-out probes: likelihood scoring of choices, gates and tiers, masks, consensus, recurrence, register, geometry."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from binlens.functions.hashing import u32
from binlens.functions.stats import wilson

#: Formats of the two register groups on the native grid.
PRESCRIPTIVE, INTERPERSONAL = ("de", "en"), ("es", "fr")
#: (benchmark, role, whether a split by correctness is defined).
POLICY = [("SR", "main", True), ("TR", "supporting", True), ("SK", "secondary", False), ("TK", "excluded", True)]


def token_counts(df: DataFrame, words) -> DataFrame:
    return df.select(F.explode(words).alias("t")).groupBy("t").agg(F.count("*").alias("c"))


def choices(queries: DataFrame, n: int = 4) -> DataFrame:
    """(bench, query_id, choice, words, prompt): own completion as choice 0, then those of the next items of the benchmark."""
    w = Window.partitionBy("bench").orderBy("query_id")
    q = queries.withColumn("i", F.row_number().over(w) - 1).withColumn("m", F.count("*").over(Window.partitionBy("bench")))
    mine = q.select("bench", "query_id", "prompt", "i", "m", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("choice")).withColumn("j",
        (F.col("i") + F.col("choice")) % F.col("m"))
    return mine.join(q.select("bench", F.col("i").alias("j"), F.col("completion").alias("words")), ["bench", "j"]).select("bench", "query_id",
        "choice", "words", "prompt")


def score_choices(ch: DataFrame, counts: DataFrame) -> DataFrame:
    """Log-likelihood for each character under an even mixture of a smoothed unigram head and the prompt's words."""
    total = counts.agg(F.sum("c").alias("total"), F.count("*").alias("v"))
    t = ch.select("bench", "query_id", "choice", "prompt", F.length(F.array_join("words", " ")).alias("chars"), F.explode("words").alias("t"))
    t = t.join(counts, "t", "left").crossJoin(F.broadcast(total))  # total: one row
    own = F.coalesce(F.try_divide(F.size(F.filter("prompt", lambda x: x == F.col("t"))).cast("double"), F.size("prompt").cast("double")), F.lit(0.0))
    p = 0.5 * (F.coalesce("c", F.lit(0)) + 1) / (F.col("total") + F.col("v")) + 0.5 * own
    return t.groupBy("bench", "query_id", "choice").agg((F.sum(F.ln(p)) / F.max("chars")).alias("score"))


def outcomes(scored: DataFrame) -> DataFrame:
    """(bench, query_id, chosen, correct, margin): lowest choice on ties; the gold choice is 0."""
    best = F.max(F.struct(F.round("score", 9).alias("s"), (-F.col("choice")).alias("neg")))
    gold, rest = F.max(F.when(F.col("choice") == 0, F.col("score"))), F.max(F.when(F.col("choice") > 0, F.col("score")))
    g = scored.groupBy("bench", "query_id").agg(best.alias("b"), (gold - rest).alias("margin"))
    return g.select("bench", "query_id", (-F.col("b.neg")).cast("int").alias("chosen"), (F.col("b.neg") == 0).alias("correct"), "margin")


def gate(out: DataFrame, by: list[str], chance: float = 0.25) -> DataFrame:
    """Accuracy, Wilson interval and tier: main above chance, caution if the interval reaches it, control below."""
    g = out.groupBy(*by).agg(F.count("*").alias("n"), F.count_if("correct").alias("k"))
    lo, hi = wilson(F.col("k"), F.col("n"))
    g = g.withColumn("acc", F.col("k") / F.col("n")).withColumn("lo", lo).withColumn("hi", hi)
    return g.withColumn("tier", F.when(F.col("lo") > chance, "main").when(F.col("hi") >= chance, "caution").otherwise("failure control"))


def assign_tiers(gated: DataFrame, policy: list[tuple[str, str, bool]]) -> DataFrame:
    """(bench, gate, tier, split_used): the policy's role where the gate is passed, else what the gate says; an excluded
    benchmark stays excluded, and only passed ones with a split are split by correctness."""
    p = gated.sparkSession.createDataFrame(policy, "bench string, role string, has_split boolean")
    out, passed = F.col("role") == "excluded", F.col("tier") == "main"
    tier = F.when(out, F.col("role")).when(passed, F.col("role")).otherwise(F.col("tier"))
    return gated.join(F.broadcast(p), "bench").select("bench", F.col("tier").alias("gate"), tier.alias("tier"), (F.col("has_split") & passed & ~out).alias("split_used"))


def subset_masks(out: DataFrame, chance: float = 0.25) -> DataFrame:
    """Per benchmark: subsets kept (accuracy at chance or better), and accuracy over those only."""
    s = out.groupBy("bench", "subset").agg(F.count("*").alias("n"), F.count_if("correct").alias("k")).withColumn("kept", F.col("k") >= chance * F.col("n"))
    k, n = F.sum(F.when(F.col("kept"), F.col("k"))), F.sum(F.when(F.col("kept"), F.col("n")))
    return s.groupBy("bench").agg(F.count_if("kept").alias("n_kept"), F.count("*").alias("n_subsets"), F.try_divide(k.cast("double"),
        n.cast("double")).alias("masked_acc"))


def macro_average(out: DataFrame) -> DataFrame:
    """(bench, n_subsets, micro, macro, invalid): accuracy over items and over subsets, and the share without a margin."""
    s = out.groupBy("bench", "subset").agg(F.count("*").alias("n"), F.count_if("correct").alias("k"), F.count_if(F.col("margin").isNull()).alias("bad"))
    share = lambda x: F.sum(x) / F.sum("n")
    return s.groupBy("bench").agg(F.count("*").alias("n_subsets"), share("k").alias("micro"), F.avg(F.col("k") / F.col("n")).alias("macro"),
        share("bad").alias("invalid"))


def retained(out: DataFrame, chance: float = 0.25) -> DataFrame:
    """(bench, query_id, subset): the items of subsets at chance or better."""
    w = Window.partitionBy("bench", "subset")
    share = F.avg(F.col("correct").cast("double")).over(w)
    return out.withColumn("share", share).where(F.col("share") >= chance).select("bench", "query_id", "subset")


def cap_queries(queries: DataFrame, n: int, seed: str) -> DataFrame:
    """At most ``n`` items of each benchmark, those with the smallest hash, ranked."""
    w = Window.partitionBy("bench").orderBy(u32(F.lit(seed), F.col("query_id")), "query_id")
    return queries.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= n)


def cross_mask(bins: DataFrame) -> DataFrame:
    return bins.groupBy("topic", "format").agg(F.avg("z").alias("mean_z"), F.var_samp("z").alias("var_z"))


def consensus(bins: DataFrame, controls: list) -> DataFrame:
    """Bins ranked by (probes positive, probes with z >= 1, mean z); specificity = mean z less the controls' mean z."""
    head, ctl = ~F.col("bench").isin(controls), F.col("bench").isin(controls)
    g = bins.groupBy("topic", "format").agg(F.count_if(head & (F.col("z") > 0)).alias("n_positive"),
        F.count_if(head & (F.col("z") >= 1)).alias("n_strong"), F.avg(F.when(head, F.col("z"))).alias("mean_z"), F.avg(F.when(ctl, F.col("z"))).alias("control_z"))
    return g.withColumn("specificity", F.col("mean_z") - F.col("control_z"))


def recurrence(topk: DataFrame, strong: float = 1.0, min_probes: int = 2) -> DataFrame:
    """Documents with strong rank-weighted support in several probes: ids only."""
    n = topk.groupBy("bench").agg(F.countDistinct("query_id").alias("n"))
    s = topk.groupBy("bench", "doc_id").agg(F.sum(1.0 / F.col("rank")).alias("w")).join(n, "bench").withColumn("w", F.col("w") / F.col("n"))
    by = Window.partitionBy("bench")
    z = s.withColumn("z", F.try_divide(F.col("w") - F.avg("w").over(by), F.stddev_pop("w").over(by)))
    return z.groupBy("doc_id").agg(F.count_if(F.col("z") >= strong).alias("n_probes")).where(F.col("n_probes") >= min_probes)


def register_loading(bins: DataFrame) -> DataFrame:
    return bins.groupBy("bench").agg((F.avg(F.when(F.col("format").isin(*PRESCRIPTIVE),
        F.col("z"))) - F.avg(F.when(F.col("format").isin(*INTERPERSONAL), F.col("z")))).alias("loading"))


def register_rule(loadings: DataFrame, block: float = 0.3, positive: int = 5) -> DataFrame:
    g = loadings.agg(F.avg("loading").alias("mean_loading"), F.count_if(F.col("loading") > 0).alias("n_positive"), F.count("*").alias("n"))
    return g.withColumn("passed", (F.col("mean_loading") >= block) & (F.col("n_positive") >= positive))


def geometry(r: DataFrame, anchor) -> DataFrame:
    """Mean correlation within the block of other probes, of the anchor to it, and its closest probe."""
    x = r.where("a <> b")
    inside = x.where((F.col("a") != anchor) & (F.col("b") != anchor)).agg(F.avg("r").alias("within_r"))
    to = x.where(F.col("a") == anchor).agg(F.avg("r").alias("anchor_r"), F.max(F.struct("r", (-F.col("b")).alias("neg"))).alias("m"))
    return inside.crossJoin(to).select("within_r", "anchor_r", (-F.col("m.neg")).alias("best_proxy"), F.col("m.r").alias("best_r"))  # one row each


def pairwise_count(r: DataFrame, anchor, knowledge: list) -> DataFrame:
    """Probes that correlate more with the knowledge set than with the anchor."""
    rest = ~F.col("a").isin(anchor, *knowledge)
    k = r.where(rest).groupBy("a").agg(F.avg(F.when(F.col("b").isin(*knowledge), F.col("r"))).alias("k"), F.max(F.when(F.col("b") == anchor, F.col("r"))).alias("s"))
    return k.agg(F.count_if(F.col("k") > F.col("s")).alias("closer"), F.count("*").alias("n"))
