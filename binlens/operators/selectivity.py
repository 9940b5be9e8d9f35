"""Validation statistics and selectivity over a run ledger (recipe, topic, seed, target, bench, gamma, steps)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from binlens.functions.hashing import u32
from binlens.functions.stats import bh, normal_upper, r6, t_upper, wilcoxon

CELL = ["topic", "seed", "target"]


def on_target(runs: DataFrame) -> DataFrame:
    return runs.where("target = bench")


def paired(runs: DataFrame, a: str = "influence", b: str = "random") -> DataFrame:
    """d = gamma(a) - gamma(b) for cells that both arms have; steps saved beside it."""
    x = on_target(runs).where(F.col("recipe") == a).select(*CELL, F.col("gamma").alias("ga"), F.col("steps").alias("sa"))
    y = on_target(runs).where(F.col("recipe") == b).select(*CELL, F.col("gamma").alias("gb"), F.col("steps").alias("sb"))
    return x.join(y, CELL).select(*CELL, F.round(F.col("ga") - F.col("gb"), 9).alias("d"), (F.col("sb") - F.col("sa")).alias("saved"))


def wilcoxon_by_target(d: DataFrame) -> DataFrame:
    return wilcoxon(d, "d", ["target"])


def topic_t(d: DataFrame) -> DataFrame:
    """Paired t over per-topic seed means: n, t, one- and two-sided p."""
    m = d.groupBy("target", "topic").agg(F.avg("d").alias("m")).groupBy("target").agg(F.count("*").alias("n"), F.avg("m").alias("mean"), F.stddev_samp("m").alias("sd"))
    m = m.withColumn("t", F.try_divide(F.col("mean"), F.col("sd") / F.sqrt("n")))
    one = t_upper(F.col("t"), (F.col("n") - 1).cast("int"))
    return m.withColumn("p_one", one).withColumn("p_two", 2 * F.least("p_one", 1 - F.col("p_one")))


def families(d: DataFrame) -> DataFrame:
    """Both tests' p-values, adjusted in one family of eight and in two of four."""
    w = wilcoxon_by_target(d).select("target", F.lit("wilcoxon").alias("test"), "p")
    t = topic_t(d).select("target", F.lit("t").alias("test"), F.col("p_one").alias("p"))
    rows = w.union(t).withColumn("all", F.lit(1))
    return bh(bh(rows, "p", ["all"], "p_of_8"), "p", ["test"], "p_of_4").drop("all")


def median_ci(d: DataFrame, reps: int, seed: str) -> DataFrame:
    w = Window.partitionBy("target")
    rows = d.withColumn("i", F.row_number().over(w.orderBy("topic", "seed")) - 1).withColumn("n", F.count("*").over(w))
    pick = rows.select("target", "n", F.col("i").alias("slot"), F.explode(F.sequence(F.lit(0), F.lit(reps - 1))).alias("rep"))
    pick = pick.withColumn("i", u32(F.lit(seed), F.col("rep"), F.col("target"), F.col("slot")) % F.col("n"))
    med = pick.join(rows.select("target", "i", "d"), ["target", "i"]).groupBy("target", "rep").agg(F.median("d").alias("m"))
    return med.groupBy("target").agg(F.percentile("m", 0.025).alias("lo"), F.percentile("m", 0.975).alias("hi"))


def cohen_dz(d: DataFrame) -> DataFrame:
    return d.groupBy("target").agg(F.count("*").alias("n"), F.try_divide(F.avg("d"), F.stddev_samp("d")).alias("dz"), F.median("d").alias("median_d"))


def seed_summary(runs: DataFrame) -> DataFrame:
    return on_target(runs).groupBy("recipe", "topic", "target").agg(F.count("*").alias("n"), F.avg("gamma").alias("mean"), F.stddev_samp("gamma").alias("sd"))


def sweep(runs: DataFrame, benches: tuple, recipe: str = "influence") -> DataFrame:
    return runs.where(F.col("recipe") == recipe).groupBy("topic").pivot("bench", list(benches)).agg(F.round(F.avg("gamma"), 6))


def box_vs_control(runs: DataFrame, control: str = "random") -> DataFrame:
    """Five numbers of the topics' mean damage, and where the control's mean stands."""
    t = runs.where("recipe = 'influence'").groupBy("bench", "topic").agg(F.avg("gamma").alias("g"))
    box = t.groupBy("bench").agg(*[F.percentile("g", q).alias(n) for n, q in (("lowest", 0.0), ("q1", 0.25), ("middle", 0.5), ("q3", 0.75), ("highest", 1.0))])
    c = runs.where(F.col("recipe") == control).groupBy("bench").agg(F.avg("gamma").alias("control"))
    return box.join(c, "bench").withColumn("place", F.when(F.col("control") > F.col("q3"), "above").when(F.col("control") < F.col("q1"), "below").otherwise("inside"))


def regression(runs: DataFrame, influence: DataFrame) -> DataFrame:
    """On-target damage against the topic's influence score, for each target and arm.  influence: (bench, topic, z)."""
    x = influence.select(F.col("bench").alias("target"), "topic", "z")
    rows = on_target(runs).join(x, ["target", "topic"]).groupBy("recipe", "target")
    return rows.agg(F.count("*").alias("n"), F.regr_slope("gamma", "z").alias("slope"), F.regr_intercept("gamma", "z").alias("intercept"),
        F.regr_r2("gamma", "z").alias("r2"))


def damage(runs: DataFrame, by: list[str]) -> DataFrame:
    """Mean damage by (by, target, bench)."""
    return runs.groupBy(*by, "target", "bench").agg(F.avg("gamma").alias("gamma"))


def selectivity(runs: DataFrame, by: list[str]) -> DataFrame:
    """Six ratios of damage on the target to damage elsewhere, for each (by, target)."""
    g = damage(runs, by)
    own, other = F.col("bench") == F.col("target"), F.col("bench") != F.col("target")
    a = F.abs("gamma")
    s = g.groupBy(*by, "target").agg(
        F.sum(F.when(own, F.col("gamma"))).alias("t"), F.avg(F.when(other, a)).alias("rest"), F.max(F.when(other, a)).alias("worst"),
            F.avg(F.when(other & (F.col("bench") != "TR"), a)).alias("no_tr"),
        F.avg(F.when(other, F.col("gamma"))).alias("signed"), F.sqrt(F.sum(F.col("gamma") ** 2)).alias("norm"), F.sum(a).alias("total"),
            F.sum(F.when(a > 0, a * F.ln(a))).alias("xlogx"),
    )
    div = F.try_divide
    return s.select(
        *by, "target", div(F.abs("t"), F.col("rest")).alias("mean_ratio"), div(F.abs("t"), F.col("worst")).alias("worst_ratio"), div(F.abs("t"),
            F.col("no_tr")).alias("excluding_ratio"),
        div(F.col("t"), F.col("signed")).alias("signed_ratio"), div(F.col("t"), F.col("norm")).alias("cosine"), (div(F.col("xlogx"),
            F.col("total")) - F.ln(F.nullif("total", F.lit(0.0)))).alias("neg_entropy"),
    )


METRICS = ("mean_ratio", "worst_ratio", "excluding_ratio", "signed_ratio", "cosine", "neg_entropy")


def factorial(runs: DataFrame, eps: float = 0.003) -> DataFrame:
    """Influence effect and topic effect as ratios of selectivity; targets with damage near 0 can't be scored."""
    s = selectivity(runs, ["recipe"]).groupBy("target").pivot("recipe", ["influence", "naive", "random"]).agg(F.first("mean_ratio"))
    own = on_target(runs).where("recipe = 'influence'").groupBy("target").agg((F.abs(F.avg("gamma")) > eps).alias("scorable"))
    return s.join(own, "target").select("target", "influence", "naive", "random", F.try_divide("influence", "random").alias("influence_effect"),
        F.try_divide("influence", "naive").alias("topic_effect"), "scorable")


def robustness(runs: DataFrame, a: str = "influence", b: str = "naive") -> DataFrame:
    """For each metric the targets of which recipe a beats b."""
    s = selectivity(runs, ["recipe"]).unpivot(["recipe", "target"], list(METRICS), "metric", "value")
    both = s.where(F.col("recipe") == a).select("target", "metric", F.col("value").alias("x")).join(s.where(F.col("recipe") == b).select("target",
        "metric", F.col("value").alias("y")), ["target", "metric"])
    return both.groupBy("metric").agg(F.count_if(F.col("x") > F.col("y")).alias("wins"), F.count("*").alias("n"))


def hindsight(runs: DataFrame) -> DataFrame:
    """The most selective topic of each target once all were run: an upper bound only."""
    s = selectivity(runs.where("recipe = 'influence'"), ["topic"]).where("mean_ratio is not null")
    w = Window.partitionBy("target").orderBy(F.desc("mean_ratio"), "topic")
    return s.withColumn("k", F.row_number().over(w)).where("k = 1").select("target", "topic", "mean_ratio")


def chosen_topics(bins: DataFrame, rule: str) -> DataFrame:
    """(target, topic): the topic with the largest marginal z (bins: bench, topic, z), or the one that the bin with the
    largest z belongs to (bins: bench, topic, format, z)."""
    if rule not in ("max_topic_marginal", "parent_of_max_bin"):
        raise ValueError(f"no such rule: {rule}")
    order = [F.desc_nulls_last("z"), "topic"] + (["format"] if rule == "parent_of_max_bin" else [])
    top = bins.withColumn("r", F.row_number().over(Window.partitionBy("bench").orderBy(*order))).where("r = 1")
    return top.select(F.col("bench").alias("target"), "topic")


def rank_gap(runs: DataFrame, bins: DataFrame) -> DataFrame:
    """(target, topic, by_damage, n): where the topic that attribution puts first stands by measured damage."""
    g = damage(runs.where("recipe = 'influence'"), ["topic"]).where("target = bench").select("target", "topic", "gamma")
    rows = g.join(bins.select(F.col("bench").alias("target"), "topic", "z"), ["target", "topic"])
    w = Window.partitionBy("target")
    rows = rows.withColumn("by_influence", F.row_number().over(w.orderBy(F.desc("z"), "topic"))).withColumn("by_damage",
        F.row_number().over(w.orderBy(F.desc("gamma"), "topic")))
    return rows.withColumn("n", F.count("*").over(w)).where("by_influence = 1").select("target", "topic", "by_damage", "n")


def head_to_head(runs: DataFrame, bins: DataFrame, rule: str = "max_topic_marginal") -> DataFrame:
    """Selectivity of the topic chosen by attribution (``chosen_topics``) against that of naive selection."""
    top = chosen_topics(bins, rule)
    mine = selectivity(runs.where("recipe = 'influence'"), ["topic"]).join(top, ["target", "topic"]).select("target", "topic", F.col("mean_ratio").alias("chosen"))
    naive = selectivity(runs.where("recipe = 'naive'"), ["recipe"]).select("target", F.col("mean_ratio").alias("naive"))
    return mine.join(naive, "target").withColumn("ratio", F.try_divide("chosen", "naive"))


def predict_naive(shares: DataFrame, runs: DataFrame) -> DataFrame:
    """Linear prediction of naive selection: a topic's share of the global top times its own damage.  shares: (bench, topic, share)."""
    g = damage(runs.where("recipe = 'influence'"), ["topic"]).where("target = bench")
    return shares.join(g, ["bench", "topic"]).groupBy("bench").agg(F.sum(F.col("share") * F.col("gamma")).alias("predicted"))


def pilot(bins: DataFrame, runs: DataFrame, n: int = 3) -> DataFrame:
    """Shortlist n topics by unique z, run them, keep the most selective.  bins: (bench, topic, z)."""
    w = Window.partitionBy("topic")
    k = F.count("*").over(w)
    unique = bins.withColumn("u", F.col("z") - (F.sum("z").over(w) - F.col("z")) / (k - 1))
    short = unique.withColumn("r", F.row_number().over(Window.partitionBy("bench").orderBy(F.desc("u"),
        "topic"))).where(F.col("r") <= n).select(F.col("bench").alias("target"), "topic", "r")
    s = selectivity(runs.where("recipe = 'influence'"), ["topic"]).join(short, ["target", "topic"]).where("mean_ratio is not null")
    return s.withColumn("k", F.row_number().over(Window.partitionBy("target").orderBy(F.desc("mean_ratio"), "topic"))).where("k = 1").select("target",
        "topic", F.col("r").alias("shortlist_rank"), "mean_ratio")


def task_definitions(runs: DataFrame) -> DataFrame:
    """Mean and deviation of on-target damage under an easy, a hard and the united task: SR, TR and both."""
    t = on_target(runs).where("bench in ('SR', 'TR')").select(F.when(F.col("bench") == "SR", "easy").otherwise("hard").alias("task"), "gamma")
    return t.union(t.select(F.lit("union"), "gamma")).groupBy("task").agg(F.count("*").alias("n"), F.avg("gamma").alias("mean"), F.stddev_samp("gamma").alias("sd"))


def collateral(runs: DataFrame) -> DataFrame:
    """Off-target damage of each arm: mean, median, largest."""
    return runs.where("bench <> target and recipe in ('influence', 'random')").groupBy("recipe").agg(F.avg("gamma").alias("mean"),
        F.median("gamma").alias("middle"), F.max("gamma").alias("largest"))


def net_effect(runs: DataFrame, control: str = "random") -> DataFrame:
    """A topic's damage less that of the control over all topics."""
    c = runs.where(F.col("recipe") == control).groupBy("bench").agg(F.avg("gamma").alias("c"))
    return runs.where("recipe = 'influence'").groupBy("topic", "bench").agg(F.avg("gamma").alias("g")).join(c, "bench").select("topic", "bench",
        (F.col("g") - F.col("c")).alias("net"))


def control_by_seed(runs: DataFrame, control: str = "random") -> DataFrame:
    """Each seed's control mean against the quartiles of the topics' damage."""
    t = runs.where("recipe = 'influence'").groupBy("bench", "topic").agg(F.avg("gamma").alias("g")).groupBy("bench").agg(F.percentile("g",
        0.25).alias("q1"), F.percentile("g", 0.75).alias("q3"))
    c = runs.where(F.col("recipe") == control).groupBy("bench", "seed").agg(F.avg("gamma").alias("control")).join(t, "bench")
    return c.select("bench", "seed", "control", F.when(F.col("control") > F.col("q3"), "above").when(F.col("control") < F.col("q1"),
        "below").otherwise("inside").alias("place"))


def heldout_unlearning(runs: DataFrame, control: str = "random") -> DataFrame:
    """One row for each topic: damage less the control's of the same benchmark and seed, pooled over both, with its
    interval, sign test, range with one benchmark left out, and how far it stands out among the topics."""
    c = runs.where(F.col("recipe") == control).groupBy("bench", "seed").agg(F.avg("gamma").alias("c"))
    net = runs.where("recipe = 'influence'").groupBy("topic", "bench", "seed").agg(F.avg("gamma").alias("g")).join(c, ["bench",
        "seed"]).select("topic", "bench", (F.col("g") - F.col("c")).alias("d"))
    half = 1.959964 * F.col("sd") / F.sqrt("n")
    a = net.groupBy("topic").agg(F.count("*").alias("n"), F.count_if(F.col("d") < 0).alias("n_negative"), F.avg("d").alias("mean"), F.stddev_samp("d").alias("sd"))
    whole = Window.partitionBy()  # one row for each topic
    a = a.withColumn("lo", F.col("mean") - half).withColumn("hi", F.col("mean") + half).withColumn("z",
        F.try_divide(F.col("mean") - F.avg("mean").over(whole), F.stddev_pop("mean").over(whole))).drop("sd")
    signs = sign_test(net.select(F.col("topic").alias("target"), "d")).select(F.col("target").alias("topic"), "p")
    left = jackknife(net.select(F.col("topic").alias("target"), F.col("bench").alias("topic"), "d")).withColumnRenamed("target", "topic")
    return a.join(signs, "topic").join(left, "topic")


def sign_test(d: DataFrame) -> DataFrame:
    """Two-sided sign test of d by target, exact binomial by log-factorials."""
    s = d.where("d <> 0").groupBy("target").agg(F.count("*").alias("n"), F.count_if(F.col("d") > 0).alias("k"))
    low = F.least(F.col("k"), F.col("n") - F.col("k")).cast("int")
    logs = lambda x: F.aggregate(F.sequence(F.lit(1), F.greatest(x, F.lit(1))), F.lit(0.0), lambda a, i: a + F.ln(i.cast("double")))
    n = F.col("n").cast("int")
    tail = F.aggregate(F.sequence(F.lit(0), low), F.lit(0.0), lambda a, i: a + F.exp(logs(n) - logs(i) - logs(n - i) - n * F.ln(F.lit(2.0))))
    return s.withColumn("p", F.least(F.lit(1.0), 2 * tail))


def jackknife(d: DataFrame) -> DataFrame:
    """Range of the mean effect with one topic left out at a time."""
    t = d.groupBy("target", "topic").agg(F.sum("d").alias("s"), F.count("*").alias("n"))
    w = Window.partitionBy("target")
    left = t.withColumn("m", F.try_divide(F.sum("s").over(w) - F.col("s"), (F.sum("n").over(w) - F.col("n")).cast("double")))
    return left.groupBy("target").agg(F.min("m").alias("lowest"), F.max("m").alias("highest"))


def topic_local(runs: DataFrame, floor: float = 0.03) -> DataFrame:
    """Topics whose mean damage stays under the floor on every benchmark."""
    g = runs.where("recipe = 'influence'").groupBy("topic", "bench").agg(F.avg("gamma").alias("g")).groupBy("topic").agg(F.avg(F.abs("g")).alias("m"))
    return g.agg(F.count_if(F.col("m") < floor).alias("n_local"), F.count("*").alias("n_topics"))


def convergence(runs: DataFrame, cap: int = 450) -> DataFrame:
    return runs.groupBy("recipe").agg(F.percentile("steps", 0.25).alias("q1"), F.percentile("steps", 0.5).alias("middle"), F.percentile("steps",
        0.75).alias("q3"), F.count_if(F.col("steps") >= cap).alias("at_cap"))


def cross_method(a: DataFrame, b: DataFrame) -> DataFrame:
    """Agreement of two constructions' on-target signs.  a, b: (target, gamma)."""
    both = a.withColumnRenamed("gamma", "x").join(b.withColumnRenamed("gamma", "y"), "target")
    return both.select("target", F.when((F.col("x") > 0) & (F.col("y") > 0), "both").when(F.col("x") > 0, "first").when(F.col("y") > 0,
        "second").otherwise("neither").alias("pattern"))
