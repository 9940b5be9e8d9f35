"""Bins, z-scores, contrasts, profile geometry and resampling over the (bench, topic, format) grid."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from binlens.functions.hashing import u32
from binlens.functions.stats import average_rank, bh, draws, pearson, r6, t_upper

BIN = ["topic", "format"]


def bin_mean(scores: DataFrame, how: str = "mean") -> DataFrame:
    """Mean (or median) over a bin's documents of their mean score; partial sums absorb heavy bins."""
    x = F.avg("score") if how == "mean" else F.median("score")
    return scores.groupBy("bench", *BIN).agg(F.count("*").alias("n_docs"), x.alias("mean"), F.stddev_samp("score").alias("sd"))


def zscore(bins: DataFrame, by: tuple = ("bench",), value: str = "mean") -> DataFrame:
    """z over the bins of one benchmark, population deviation; null where that is 0."""
    w = Window.partitionBy(*by)
    return bins.withColumn("z", F.try_divide(F.col(value) - F.avg(value).over(w), F.stddev_pop(value).over(w)))


def marginal_z(bins: DataFrame, axis: str) -> DataFrame:
    """Mean z over the other axis, each bin weighing alike."""
    return bins.groupBy("bench", axis).agg(F.avg("z").alias("z"))


def extremes(marg: DataFrame, axis: str, k: int = 3) -> DataFrame:
    up = Window.partitionBy("bench").orderBy(F.desc("z"), axis)
    down = Window.partitionBy("bench").orderBy("z", axis)
    m = marg.withColumn("up", F.row_number().over(up)).withColumn("down", F.row_number().over(down))
    return m.where(f"up <= {k} or down <= {k}").select("bench", axis, "up", "down", r6("z").alias("z"))


def signed_split(bins: DataFrame, value: str = "mean") -> DataFrame:
    """Absolute influence of each benchmark's bins, and its supportive and suppressive parts."""
    x = F.col(value)
    up, down, size = F.when(x > 0, x), F.when(x < 0, x), F.abs(value)
    return bins.groupBy("bench").agg(
        F.count(up).alias("n_supportive"), F.count(down).alias("n_suppressive"), F.avg(size).alias("absolute"), F.avg(up).alias("supportive"),
            F.avg(down).alias("suppressive"),
        F.try_divide(F.sum(F.when(x > 0, x).otherwise(0.0)), F.sum(size)).alias("share_supportive"),
    )


def differential_extremes(cohorts: DataFrame) -> DataFrame:
    """The strongest bin on either side of each benchmark's correctness differential.  cohorts: bench, correct, bin, z."""
    z = cohorts.groupBy("bench", *BIN).agg(F.max(F.when(F.col("correct"), F.col("z"))).alias("z_correct"), F.max(F.when(~F.col("correct"),
        F.col("z"))).alias("z_incorrect"))
    z = z.withColumn("delta", F.col("z_correct") - F.col("z_incorrect")).where("delta is not null")
    w = Window.partitionBy("bench")
    ends = z.withColumn("up", F.row_number().over(w.orderBy(F.desc("delta"), *BIN))).withColumn("down", F.row_number().over(w.orderBy("delta", *BIN)))
    ends = ends.withColumn("largest", F.max(F.abs("delta")).over(w)).where("up = 1 or down = 1")
    most = ends.select("bench", "largest").distinct()
    most = most.withColumn("ratio_to_next", F.try_divide("largest", F.lead("largest").over(Window.orderBy(F.desc("largest")))))  # one row for each benchmark
    side = F.when(F.col("up") == 1, "positive").otherwise("negative").alias("side")
    return ends.join(most, ["bench", "largest"]).select("bench", *BIN, side, "z_correct", "z_incorrect", "delta", "largest", "ratio_to_next")


def capped(bins: DataFrame, q: float = 0.95) -> DataFrame:
    """z clipped at the shared percentile of |z|."""
    cap = bins.agg(F.percentile(F.abs("z"), q).alias("cap"))
    return bins.crossJoin(F.broadcast(cap)).withColumn("capped", F.greatest(F.least("z", "cap"), -F.col("cap")))  # cap: one row


def bin_tests(bins: DataFrame, alpha: float = 0.05) -> DataFrame:
    """Two-sided t test of each bin mean against 0, adjusted within the benchmark; bins of one document have no p."""
    t = F.try_divide(F.col("mean"), F.col("sd") / F.sqrt("n_docs"))
    rows = bins.withColumn("t", t).withColumn("p", F.when((F.col("n_docs") > 1) & F.col("t").isNotNull(), F.least(F.lit(1.0), 2 * t_upper(F.abs("t"),
        (F.col("n_docs") - 1).cast("int")))))
    return bh(rows, "p", ["bench"]).withColumn("significant", F.col("p_adj") < alpha)


def wide(bins: DataFrame, benches: tuple) -> DataFrame:
    return bins.groupBy(*BIN).pivot("bench", list(benches)).agg(F.first("z"))


def contrast(bins: DataFrame, a: str, b: str) -> DataFrame:
    return bins.groupBy(*BIN).agg((F.max(F.when(F.col("bench") == a, F.col("z"))) - F.max(F.when(F.col("bench") == b, F.col("z")))).alias("delta"))


def vs_rest(marg: DataFrame, axis: str, target: str) -> DataFrame:
    own, rest = F.avg(F.when(F.col("bench") == target, F.col("z"))), F.avg(F.when(F.col("bench") != target, F.col("z")))
    return marg.groupBy(axis).agg((own - rest).alias("gap"))


def sign_flips(marg: DataFrame, axis: str, target: str) -> DataFrame:
    """Labels that are positive for the target and negative for all others."""
    is_t = F.col("bench") == target
    flip = F.bool_and(F.when(is_t, F.col("z") > 0).otherwise(F.col("z") < 0))
    return marg.groupBy(axis).agg(flip.alias("flip")).where("flip").select(axis)


def topic_tilt(marg: DataFrame, axis: str, a: str, b: str, k: int = 3) -> DataFrame:
    d = marg.groupBy(axis).agg((F.max(F.when(F.col("bench") == a, F.col("z"))) - F.max(F.when(F.col("bench") == b, F.col("z")))).alias("delta"))
    d = d.withColumn("up", F.row_number().over(Window.orderBy(F.desc("delta"), axis))).withColumn("down", F.row_number().over(Window.orderBy("delta", axis)))
    return d.where(f"up <= {k} or down <= {k}")


def profile_corr(bins: DataFrame, key: list[str] = BIN, how: str = "pearson", extra: list[str] | None = None) -> DataFrame:
    """(a, b, r): correlation of two benchmarks' profiles over the bins both have."""
    extra = extra or []
    rows = bins.where("z is not null").select("bench", "z", *key, *extra)
    if how == "spearman":
        rows = average_rank(rows, "z", ["bench", *extra], "_r").drop("z").withColumnRenamed("_r", "z")
    other = rows.withColumnsRenamed({"bench": "b", "z": "zb"})
    return rows.withColumnRenamed("bench", "a").join(other, [*key, *extra]).groupBy("a", "b", *extra).agg(pearson("z", "zb").alias("r"))


def outlier_stat(r: DataFrame, benches: tuple, extra: list[str] | None = None) -> DataFrame:
    """Delta_b: mean correlation among the others less mean correlation to b."""
    extra = extra or []
    b = r.sparkSession.createDataFrame([(x,) for x in benches], "bench string")
    pairs = r.where("a < b").crossJoin(F.broadcast(b))  # four or a few benchmarks
    mine = (F.col("a") == F.col("bench")) | (F.col("b") == F.col("bench"))
    return pairs.groupBy("bench", *extra).agg(F.avg(F.when(mine, F.col("r"))).alias("c"), (F.avg(F.when(~mine, F.col("r"))) - F.avg(F.when(mine,
        F.col("r")))).alias("delta"))


def numbered(bins: DataFrame, key: list[str] = BIN) -> DataFrame:
    """Bins with a unit number from 0 in key order."""
    units = bins.select(*key).distinct().withColumn("unit", (F.row_number().over(Window.orderBy(*key)) - 1).cast("long"))
    return bins.join(F.broadcast(units), key)  # at most the grid's cells


def bin_pairs(bins: DataFrame, key: list[str] = BIN) -> DataFrame:
    """(key, a, b, za, zb): the z of each two benchmarks in one unit, both known; a unit's benchmarks meet in its own row."""
    cells = bins.where("z is not null").groupBy(*key).agg(F.array_sort(F.collect_list(F.struct("bench", "z"))).alias("own"))  # at most the benchmarks
    return cells.select(*key, F.inline(_couples(F.col("own"))))


def _couples(cell) -> Column:
    def with_others(x):
        return F.transform(F.filter(cell, lambda y: y["bench"] > x["bench"]), lambda y: F.struct(x["bench"].alias("a"), y["bench"].alias("b"),
            x["z"].alias("za"), y["z"].alias("zb")))

    return F.flatten(F.transform(cell, with_others))


def unit_count(numbered_: DataFrame) -> DataFrame:
    return numbered_.agg((F.max("unit") + 1).alias("n"))


def bin_bootstrap(bins: DataFrame, reps: int, seed: str, key: list[str] = BIN) -> DataFrame:
    """(rep, a, b, r): correlations under one resample of bins for all benchmarks; reps x bins narrow rows, whatever the corpus."""
    b = numbered(bins, key)
    units = b.select(*key, "unit").distinct()
    rows = draws(bins.sparkSession, reps, unit_count(b), seed).join(F.broadcast(bin_pairs(bins, key).join(F.broadcast(units), key)), "unit")  # units: the grid's cells
    return rows.groupBy("rep", "a", "b").agg(pearson("za", "zb").alias("r"))


def percentile_ci(df: DataFrame, by: list[str], value: str, level: float = 0.95) -> DataFrame:
    t = (1 - level) / 2
    return df.groupBy(*by).agg(F.percentile(value, t).alias("lo"), F.percentile(value, 1 - t).alias("hi"))


def _permuted(bins: DataFrame, reps: int, seed: str) -> DataFrame:
    """(rep, topic, format, cell): each bin's z dealt to its benchmarks in an order of its own for each rep, within one row."""
    cells = bins.groupBy(*BIN).agg(F.array_sort(F.collect_list(F.struct("bench", "z"))).alias("own"))  # at most the benchmarks
    rows = cells.withColumn("rep", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(reps - 1).cast("long"))))
    key = [F.lit(seed), F.col("rep"), F.col("topic"), F.col("format")]
    dealt = F.array_sort(F.transform("own", lambda x: F.struct(u32(*key, x["bench"]).alias("k"), x["bench"].alias("bench"), x["z"].alias("z"))))
    return rows.select("rep", *BIN, F.zip_with("own", dealt, lambda x, y: F.struct(x["bench"].alias("bench"), y["z"].alias("z"))).alias("cell"))


def permute_labels(bins: DataFrame, reps: int, seed: str) -> DataFrame:
    """(rep, topic, format, bench, z): benchmark labels permuted within each bin."""
    return _permuted(bins, reps, seed).select("rep", *BIN, F.inline("cell"))


def permuted_corr(bins: DataFrame, reps: int, seed: str) -> DataFrame:
    """(rep, a, b, r): correlations under permuted labels; a bin's benchmarks are coupled in its own row."""
    rows = _permuted(bins, reps, seed).select("rep", F.filter("cell", lambda x: x["z"].isNotNull()).alias("cell"))
    return rows.select("rep", F.inline(_couples(F.col("cell")))).groupBy("rep", "a", "b").agg(pearson("za", "zb").alias("r"))


BLOCKS = 64


def doc_blocks(scores: DataFrame, seed: str, blocks: int = BLOCKS) -> DataFrame:
    """(bench, topic, format, block, n, total): a bin's documents in blocks by hash, one partial sum each."""
    block = (u32(F.lit(seed), F.col("doc_id")) % blocks).alias("block")
    return scores.groupBy("bench", *BIN, block).agg(F.count("*").alias("n"), F.sum("score").alias("total"))


def doc_bootstrap(scores: DataFrame, reps: int, seed: str, blocks: int = BLOCKS) -> DataFrame:
    """(rep, bench, topic, format, mean): documents drawn anew within their bin, the same draw for all benchmarks.

    Documents are drawn by the block, at most ``blocks`` in a bin, each a random group of its documents: the one pass
    over the scores makes the blocks' sums, and resamples cost bins x reps rows however many documents a bin holds.
    """
    at = F.struct("block", "n", "total")
    cells = doc_blocks(scores, seed, blocks).groupBy("bench", *BIN).agg(F.array_sort(F.collect_list(at)).alias("own"))  # at most ``blocks``
    sums = cells.groupBy(*BIN).agg(F.collect_list(F.struct("bench", F.col("own.n").alias("n"), F.col("own.total").alias("total"))).alias("cells"),
        F.max(F.size("own")).alias("m"))
    rows = sums.withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))))
    pick = F.transform(F.sequence(F.lit(0), F.col("m") - 1), lambda i: (u32(F.lit(seed), F.col("rep"), F.col("topic"), F.col("format"), i) % F.col("m")).cast("int"))
    rows = rows.select("rep", *BIN, "cells", pick.alias("pick")).select("rep", *BIN, "pick", F.inline("cells"))

    def drawn(column):
        return F.aggregate("pick", F.lit(0.0), lambda acc, i: acc + F.get(column, i))

    return rows.select("rep", "bench", *BIN, F.try_divide(drawn("total"), drawn("n")).alias("mean"))


def delta_floor(means: DataFrame, observed: DataFrame, a: str, b: str) -> DataFrame:
    """(topic, format, delta, floor, reported): bins whose difference of z passes its own noise floor, half the width of
    the difference's interval over resamples.  means: (rep, bench, topic, format, mean); observed: bins with z."""
    deltas = zscore(means, ("rep", "bench")).groupBy("rep", *BIN).agg((F.max(F.when(F.col("bench") == a,
        F.col("z"))) - F.max(F.when(F.col("bench") == b, F.col("z")))).alias("delta"))
    ci = percentile_ci(deltas, BIN, "delta")
    out = contrast(observed, a, b).join(ci, BIN).withColumn("floor", (F.col("hi") - F.col("lo")) / 2)
    return out.withColumn("reported", F.abs("delta") > F.col("floor")).select(*BIN, "delta", "floor", "reported")


def bin_gradients(grad: DataFrame, d: int) -> DataFrame:
    """(topic, format, uni, bi): summed document gradients of a bin over its documents, so that a query's product
    with it is the bin's mean score and no document is scored."""
    rows = grad.where("uni is not null or bi is not null")
    return rows.groupBy(*BIN).agg(*[F.array(*[F.coalesce(F.sum(F.col(m)[i]) / F.count("*"), F.lit(0.0)) for i in range(d)]).alias(m) for m in ("uni", "bi")])


def query_bootstrap(queries: DataFrame, bins: DataFrame, reps: int, seed: str, d: int) -> DataFrame:
    """(rep, bench, topic, format, delta): correctness differential under queries drawn anew within their benchmark.

    ``queries``: bench, query_id, correct, uni, bi; ``bins`` of ``bin_gradients``.  Scores are linear in the queries, so
    each resample is a mean query gradient: reps x queries narrow rows, then reps x bins products, and no document."""
    w = Window.partitionBy("bench")
    ids = queries.select("bench", "query_id").distinct().withColumn("i", F.row_number().over(w.orderBy("query_id")) - 1).withColumn("n", F.count("*").over(w))
    pick = ids.select("bench", "n", F.col("i").alias("slot"), F.explode(F.sequence(F.lit(0), F.lit(reps - 1))).alias("rep"))
    pick = pick.select("rep", "bench", (u32(F.lit(seed), F.col("rep"), F.col("bench"), F.col("slot")) % F.col("n")).alias("i"))
    known = ids.select("bench", "i", "query_id").join(queries, ["bench", "query_id"])
    rows = pick.join(F.broadcast(known), ["bench", "i"])  # known: the benchmark's items
    means = [F.array(*[F.coalesce(F.avg(F.col(m)[i]), F.lit(0.0)) for i in range(d)]).alias(f"q_{m}") for m in ("uni", "bi")]
    means = rows.groupBy("rep", "bench", "correct").agg(*means)

    def product(m):
        return F.aggregate(F.zip_with(m, f"q_{m}", lambda x, y: x * y), F.lit(0.0), lambda a, x: a + x)

    one = bins.agg(F.collect_list(F.struct(*BIN, "uni", "bi")).alias("cells"))  # the grid's cells, at most
    cells = means.crossJoin(F.broadcast(one)).select("rep", "bench", "correct", "q_uni", "q_bi", F.inline("cells"))
    cells = cells.select("rep", "bench", "correct", *BIN, (product("uni") + product("bi")).alias("mean"))
    z = zscore(cells, ("rep", "bench", "correct"))
    return z.groupBy("rep", "bench", *BIN).agg((F.max(F.when(F.col("correct"), F.col("z"))) - F.max(F.when(~F.col("correct"), F.col("z")))).alias("delta"))


def gap_bootstrap(bins: DataFrame, axis: str, target: str, reps: int, seed: str) -> DataFrame:
    """(rep, axis, gap): target's marginal z less the others' mean, under draws of the other axis' labels."""
    other = [c for c in BIN if c != axis]
    b = numbered(bins, other)
    rows = draws(bins.sparkSession, reps, unit_count(b), seed).join(F.broadcast(b.select("unit", "bench", axis, "z")), "unit")
    m = rows.groupBy("rep", "bench", axis).agg(F.avg("z").alias("z"))
    own, rest = F.avg(F.when(F.col("bench") == target, F.col("z"))), F.avg(F.when(F.col("bench") != target, F.col("z")))
    return m.groupBy("rep", axis).agg((own - rest).alias("gap"))


def leaf_order(merges: list[tuple[str, str, float, int]]) -> list[str]:
    """Names in the order in which a dendrogram of the merges draws them."""
    return (merges[-1][0] + "," + merges[-1][1]).replace("(", "").replace(")", "").split(",") if merges else []


def cut_tree(merges: list[tuple[str, str, float, int]], names: list[str], k: int) -> dict[str, int]:
    """Cluster number of each name when the last k - 1 merges are undone; clusters are numbered by their smallest name."""
    groups = {n: [n] for n in names}
    for p, q, _, _ in merges[: max(0, len(names) - k)]:
        groups[f"({p},{q})"] = groups.pop(p) + groups.pop(q)
    return {n: i for i, g in enumerate(sorted(groups.values(), key=min)) for n in g}


def linkage(r: dict[tuple[str, str], float], names: list[str]) -> list[tuple[str, str, float, int]]:
    """Average linkage on 1 - r over a few probes, on the driver: merges (left, right, height, size)."""
    groups = {n: [n] for n in names}
    out = []
    while len(groups) > 1:
        best = min(((sum(1 - r[a, b] for a in x for b in y) / (len(x) * len(y)), p, q) for p, x in groups.items() for q, y in groups.items() if p < q))
        h, p, q = best
        merged = groups.pop(p) + groups.pop(q)
        groups[f"({p},{q})"] = merged
        out.append((p, q, h, len(merged)))
    return out
