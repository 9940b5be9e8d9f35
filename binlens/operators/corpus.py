"""Corpus construction and characterisation: dedup, labels, grid counts, concentration, samples, lengths, receipts."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType
from pyspark.sql.window import Window

from binlens.functions.hashing import coded, flat_words, u32, u32_each
from binlens.functions.stats import r6


def dedup_exact(df: DataFrame, keys: list[str], order: str) -> DataFrame:
    """The first row of each key."""
    return df.withColumn("_k", F.row_number().over(Window.partitionBy(*keys).orderBy(order))).where("_k = 1").drop("_k")


def bloom_bits(n_expected: int, fpp: float = 1e-3) -> int:
    return math.ceil(-n_expected * math.log(fpp) / math.log(2) ** 2)


def dedup_bloom(df: DataFrame, key: str, order: str, n_expected: int, fpp: float = 1e-3, hashes: int = 10) -> DataFrame:
    """Bloom-filter dedup in set form, equal to the sequential rule: a row goes iff each of its bits was first set
    by an earlier row.  Adds ``dropped``.  Each position is reduced before anything is joined."""
    m = bloom_bits(n_expected, fpp)
    at = df.select(F.col(order).alias("_o"), F.explode(F.array(*[u32(F.lit(f"bloom{j}"), F.col(key)) % m for j in range(hashes)])).alias("_bit"))
    first = at.groupBy("_bit").agg(F.min("_o").alias("_first"))
    gone = at.join(first, "_bit").groupBy("_o").agg(F.bool_and(F.col("_first") < F.col("_o")).alias("dropped"))
    return df.join(gone, df[order] == gone["_o"]).drop("_o")


def mint_ids(df: DataFrame, text: str, order: str) -> DataFrame:
    """Deterministic ids from content: MD5 and the number of the occurrence."""
    df = df.withColumn("content_id", F.md5(F.col(text)))
    return df.withColumn("ordinal", F.row_number().over(Window.partitionBy("content_id").orderBy(order)).cast("long"))


def composition(df: DataFrame, by: str) -> DataFrame:
    g = df.groupBy(by).agg(F.count("*").alias("n_docs"))
    return g.withColumn("share", r6(F.col("n_docs") / F.sum("n_docs").over(Window.partitionBy())))


def bin_counts(df: DataFrame) -> DataFrame:
    """Documents and words of every cell of the grid, empty cells as 0."""
    cells = df.select("topic").distinct().crossJoin(F.broadcast(df.select("format").distinct()))  # 24 x 24 at most
    got = df.groupBy("topic", "format").agg(F.count("*").alias("n_docs"), F.sum("n_words").alias("n_words"))
    return cells.join(got, ["topic", "format"], "left").fillna(0, ["n_docs", "n_words"])


def marginals(bins: DataFrame) -> DataFrame:
    """Topic, format and grand totals in one scan."""
    return bins.sparkSession.sql("select topic, format, sum(n_docs) n_docs, sum(n_words) n_words from {b} group by grouping sets ((topic), (format), ())", b=bins)


def gini(bins: DataFrame, measure: str) -> DataFrame:
    w = Window.orderBy(measure)
    x = bins.select(F.col(measure).cast("double").alias("x"), F.row_number().over(w).alias("i"), F.count("*").over(Window.partitionBy()).alias("n"))
    return x.agg(r6(F.try_divide(F.sum((2 * F.col("i") - F.col("n") - 1) * F.col("x")), F.max("n") * F.sum("x"))).alias("gini"))


def effective_bins(bins: DataFrame, measure: str) -> DataFrame:
    p = F.col(measure) / F.sum(measure).over(Window.partitionBy())
    h = bins.where(F.col(measure) > 0).select(p.alias("p")).agg((-F.sum(F.col("p") * F.ln("p"))).alias("h"))
    return h.select(r6("h").alias("entropy"), r6(F.exp("h")).alias("effective_bins"))


def skew_summary(bins: DataFrame, measure: str) -> DataFrame:
    c = F.col(measure)
    return bins.agg(F.max(c).alias("largest"), F.min(F.when(c > 0, c)).alias("smallest"), F.count_if(c == 0).alias("n_empty"),
        r6(F.try_divide(F.max(c), F.min(F.when(c > 0, c)))).alias("ratio"))


def head_tail(bins: DataFrame, measure: str, k: int = 20) -> DataFrame:
    """The k heaviest and lightest non-empty cells with the running share of each list."""
    total = F.sum(measure).over(Window.partitionBy())
    ranked = bins.where(F.col(measure) > 0).withColumn("_t", total)
    out = []
    for side, order in (("head", F.desc(measure)), ("tail", F.asc(measure))):
        w = Window.orderBy(order, "topic", "format")
        one = ranked.withColumn("rank", F.row_number().over(w)).withColumn("run", F.sum(measure).over(w.rowsBetween(Window.unboundedPreceding,
            0))).where(F.col("rank") <= k)
        out.append(one.select(F.lit(side).alias("side"), "rank", "topic", "format", measure, r6(F.col("run") / F.col("_t")).alias("running_share")))
    return out[0].union(out[1])


def log_grid(bins: DataFrame) -> DataFrame:
    return bins.select("topic", "format", r6(F.when(F.col("n_docs") > 0, F.log10("n_docs"))).alias("log_docs"), r6(F.when(F.col("n_words") > 0,
        F.log10("n_words"))).alias("log_words"))


def population(df: DataFrame) -> DataFrame:
    return df.agg(F.count("*").alias("n_docs"), F.count_if("is_binned").alias("n_binned"), r6(F.count_if("is_binned") / F.count("*")).alias("share_binned"))


def lowest(rows: DataFrame, n: int, by: list[str], order: str, bits: int) -> DataFrame:
    """Exactly the ``n`` rows of each group with the smallest hash ``_u`` (32 bits), ties by ``order``; all rows of a
    smaller group.

    Rows are counted by the hash's first ``bits`` bits; whole cells are taken up to the one where the group's count
    passes n, and only that cell's rows are ranked.  So no task ranks a group, however large, or gathers the sample.
    """
    cell = F.shiftright("_u", 32 - bits)
    counts = rows.groupBy(*by, cell.alias("_cell")).agg(F.count("*").alias("_k"))
    w = Window.partitionBy(*by).orderBy("_cell").rowsBetween(Window.unboundedPreceding, 0)  # at most 2^bits counts a group
    passed = counts.withColumn("_run", F.sum("_k").over(w)).where(F.col("_run") > n)
    first = F.min(F.struct("_cell", (F.col("_run") - F.col("_k")).alias("before"))).alias("_edge")
    edge = F.broadcast(passed.groupBy(*by).agg(first))  # one row for each group
    known = (rows.join(edge, by, "left") if by else rows.crossJoin(edge)).withColumn("_cell", cell)
    sure = known.where(F.col("_edge").isNull() | (F.col("_cell") < F.col("_edge._cell")))
    rank = F.row_number().over(Window.partitionBy(*by).orderBy("_u", order))
    last = known.where(F.col("_cell") == F.col("_edge._cell")).withColumn("_rank", rank).where(F.col("_rank") <= n - F.col("_edge.before"))
    return sure.unionByName(last.drop("_rank")).drop("_edge", "_cell")


def sample_stratified(df: DataFrame, per_bin: int, seed: str) -> DataFrame:
    """At most ``per_bin`` rows of each bin, uniform within it, ranked by their draw; short bins keep every row."""
    rows = lowest(df.withColumn("_u", u32(F.lit(seed), F.col("doc_id"))), per_bin, ["topic", "format"], "doc_id", 12)
    w = Window.partitionBy("topic", "format").orderBy("_u", "doc_id")
    return rows.withColumn("draw_rank", F.row_number().over(w)).drop("_u")


def sample_uniform(df: DataFrame, n: int, seed: str) -> DataFrame:
    """n rows with the smallest hash: a proportional, representative draw."""
    return lowest(df.withColumn("_u", u32(F.lit(seed), F.col("doc_id"))), n, [], "doc_id", 20).drop("_u")


def fill_rates(sample: DataFrame, cells: DataFrame, target: int) -> DataFrame:
    got = sample.groupBy("topic", "format").agg(F.count("*").alias("realised"))
    out = cells.select("topic", "format").join(got, ["topic", "format"], "left").fillna(0, ["realised"])
    return out.select("topic", "format", "realised", r6(F.col("realised") / target).alias("fill"), (F.col("realised") < target).alias("under_filled"))


def allocation_log2(a: DataFrame, b: DataFrame, cells: DataFrame) -> DataFrame:
    """log2 of the shares of each cell of the grid in two samples; 0 where both are empty, null where one is."""
    x = a.groupBy("topic", "format").agg(F.count("*").alias("na"))
    y = b.groupBy("topic", "format").agg(F.count("*").alias("nb"))
    both = cells.select("topic", "format").join(x, ["topic", "format"], "left").join(y, ["topic", "format"], "left").fillna(0, ["na", "nb"])
    whole = Window.partitionBy()  # one row for each cell
    share = [F.try_divide(F.col(c), F.sum(c).over(whole)) for c in ("na", "nb")]
    ratio = F.when((F.col("na") > 0) & (F.col("nb") > 0), F.log2(F.try_divide(*share))).when((F.col("na") == 0) & (F.col("nb") == 0), 0.0)
    return both.select("topic", "format", r6(ratio).alias("log2_ratio"))


def ecdf(df: DataFrame, col: str) -> DataFrame:
    """Distinct values and share of rows at or below; values are reduced before the one window."""
    g = df.groupBy(F.col(col).alias("x")).agg(F.count("*").alias("n"))
    run = F.sum("n").over(Window.orderBy("x").rowsBetween(Window.unboundedPreceding, 0))
    return g.select("x", r6(run / F.sum("n").over(Window.partitionBy())).alias("f"))


def ecdf_sketch(df: DataFrame, col: str, points: list[float]) -> DataFrame:
    """The same at scale: one mergeable quantile sketch, asked for the ranks of a few points."""
    s = df.agg(F.expr(f"kll_sketch_agg_bigint({col})").alias("s"))
    ranks = [F.struct(F.lit(int(p)).alias("x"), F.expr(f"kll_sketch_get_rank_bigint(s, {int(p)}L)").alias("f")) for p in points]
    return s.select(F.inline(F.array(*ranks)))


def mean_length(df: DataFrame) -> DataFrame:
    return df.groupBy("topic", "format").agg(r6(F.avg("n_words")).alias("mean_words"))


def shard(df: DataFrame, n: int, order: str) -> DataFrame:
    """Shard number by hash of the key: a narrow pass, the same whatever the order or partitioning."""
    return df.withColumn("shard", u32(F.lit("shard"), F.col(order)) % n)


def vote_label(vote: Column) -> Column:
    """Struct (label, conf): the label with most votes, the lowest on ties; null without votes."""
    n = F.size(vote)
    counted = F.transform(F.array_distinct(vote), lambda v: F.struct((n - F.size(F.array_remove(vote, v))).alias("k"), (-v).alias("neg")))
    best = F.transform(F.array(F.array_max(counted)), lambda b: F.struct((-b["neg"]).alias("label"), (b["k"] / n).alias("conf")))  # named once, so found once
    return F.when(n > 0, best[0])


def vote_labels(docs: DataFrame, keys: list[str], words: Column, kind: str, n: int) -> DataFrame:
    """Keys, label, conf: ``vote_label`` of the words' votes, counted for a batch of rows at once; null without words."""

    def count(batches):
        for batch in batches:
            flat, starts = flat_words(batch.column("words"))
            index, known = coded(flat)
            row = np.repeat(np.arange(len(starts) - 1), np.diff(starts))
            votes = np.bincount(row * n + (u32_each(known, kind) % n)[index], minlength=n * batch.num_rows).reshape(-1, n)
            none, total = votes.sum(1) == 0, np.maximum(votes.sum(1), 1)
            got = [pa.array(votes.argmax(1), pa.int64(), mask=none), pa.array(votes.max(1) / total, pa.float64(), mask=none)]
            yield pa.RecordBatch.from_arrays([*[batch.column(k) for k in keys], *got], [*keys, "label", "conf"])

    kept = docs.select(*keys)
    schema = StructType(kept.schema.fields).add("label", "long").add("conf", "double")
    return docs.select(*keys, words.alias("words")).mapInArrow(count, schema)


def classifier_accuracy(pred: DataFrame, gold: DataFrame, group: str, min_conf: float) -> DataFrame:
    """Mean and worst-group accuracy on rows whose teacher is confident."""
    g = pred.join(gold, "doc_id").where(F.col("teacher_conf") >= min_conf)
    by = g.groupBy(group).agg(F.count("*").alias("n"), F.avg((F.col("label") == F.col("gold")).cast("double")).alias("acc"))
    return by.agg(F.sum("n").alias("n"), r6(F.sum(F.col("acc") * F.col("n")) / F.sum("n")).alias("mean_acc"), r6(F.min("acc")).alias("worst_group_acc"))


def accuracy_report(rows: DataFrame, variants: dict[str, str], min_conf: float) -> DataFrame:
    """(variant, n, mean_acc, worst_group_acc, gold_acc) against the teacher's labels, where it is sure; a group is one of
    the teacher's labels.  ``variants``: name -> column of labels."""
    pairs = F.explode(F.array(*[F.struct(F.lit(n).alias("variant"), F.col(c).alias("guess")) for n, c in variants.items()])).alias("p")
    sure = rows.where(F.col("teacher_conf") >= min_conf).select("teacher", "gold", pairs).select("teacher", "gold", "p.*")
    by = sure.groupBy("variant", "teacher").agg(F.count("*").alias("n"), F.count_if(F.col("guess") == F.col("teacher")).alias("ok"),
        F.count_if(F.col("guess") == F.col("gold")).alias("gold_ok"))
    share = lambda x: r6(F.sum(x) / F.sum("n"))
    return by.groupBy("variant").agg(F.sum("n").alias("n"), share("ok").alias("mean_acc"),
        r6(F.min(F.col("ok") / F.col("n"))).alias("worst_group_acc"), share("gold_ok").alias("gold_acc"))


def coverage_receipt(df: DataFrame, expected: DataFrame, shards: int = 8) -> DataFrame:
    """One row: rows, distinct ids, repeats, shards and bins that hold rows, a content hash that no order or partitioning
    changes, and expected ids that are missing."""
    content = F.bit_xor(u32(F.col("doc_id"), F.md5("text")))
    got = df.agg(F.count("*").alias("n_rows"), F.countDistinct("doc_id").alias("n_ids"), F.countDistinct(u32(F.lit("shard"),
        F.col("doc_id")) % shards).alias("n_shards"), F.countDistinct("source").alias("n_sources"), content.alias("content"))
    missing = expected.join(df.select("doc_id").distinct(), "doc_id", "left_anti").agg(F.count("*").alias("n_missing"))
    return got.crossJoin(F.broadcast(missing)).withColumn("n_repeats", F.col("n_rows") - F.col("n_ids"))


def naive_bayes(labelled: DataFrame, label: str, feature: str) -> tuple[DataFrame, DataFrame]:
    """Multinomial naive Bayes from rows (label, features): log weights (feature, label, w) with add-one smoothing, and
    one row for each label (label, prior, unseen).  Counting is all there is to training, so it is one aggregate."""
    rows = labelled.select(label, F.explode(feature).alias("t"))
    seen = rows.groupBy(label, "t").agg(F.count("*").alias("k"))
    size = seen.agg(F.countDistinct("t").alias("v"))
    totals = seen.groupBy(label).agg(F.sum("k").alias("n"))
    docs = labelled.groupBy(label).agg(F.count("*").alias("docs"))
    labels = docs.join(totals, label, "left").fillna(0, ["n"]).crossJoin(F.broadcast(size))  # a row for each label
    labels = labels.withColumn("share", F.col("docs") / F.sum("docs").over(Window.partitionBy()))
    labels = labels.select(label, F.ln("share").alias("prior"), (-F.ln(F.col("n") + F.col("v"))).alias("unseen"))
    weights = seen.select("t", label, F.ln(F.col("k") + 1).alias("w"))  # beyond that of an unseen feature
    return weights, labels


def classify(docs: DataFrame, model: tuple[DataFrame, DataFrame], label: str, feature: str) -> DataFrame:
    """(doc_id, label, conf): the most probable label, the smaller one on ties, and its probability."""
    weights, labels = model
    rows = docs.select("doc_id", F.size(feature).alias("m"), F.explode_outer(feature).alias("t"))
    own = rows.join(weights, "t").groupBy("doc_id", label).agg(F.sum("w").alias("w"))
    size = docs.select("doc_id", F.size(feature).alias("m"))
    scored = size.crossJoin(F.broadcast(labels)).join(own, ["doc_id", label], "left")  # documents x labels
    scored = scored.select("doc_id", label, (F.col("prior") + F.col("m") * F.col("unseen") + F.coalesce("w", F.lit(0.0))).alias("s"))
    best = scored.groupBy("doc_id").agg(F.collect_list(F.struct(F.round("s", 9).alias("s"), label)).alias("all"))  # one entry for each label
    top = F.array_max(F.transform("all", lambda x: x["s"]))
    best = best.select("doc_id", "all", top.alias("top"))
    first = F.array_min(F.transform(F.filter("all", lambda x: x["s"] == F.col("top")), lambda x: x[label]))
    mass = F.aggregate("all", F.lit(0.0), lambda acc, x: acc + F.exp(x["s"] - F.col("top")))
    return best.select("doc_id", first.alias("label"), (1 / mass).alias("conf"))
