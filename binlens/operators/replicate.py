"""Replication on further corpora: the same pipeline under other ids and labels, flips between them, claim scopes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from binlens.operators import aggregate as ag
from binlens.operators import attribution as at
from binlens.operators.corpus import vote_label
from binlens.sources.tables import BENCHES, tokens, votes

#: Labels of each axis; formats below GROUP are the prescriptive register, the others the interpersonal one.
LABELS, GROUP = 24, 12
#: What a corpus allows to be claimed, and what is refused on it.
SCOPES = {"E1": "causal", "E2": "causal", "E3": "descriptive"}
#: Method family -> scope of what it shows.
FAMILIES = {"attribution": "attributional", "inference": "attributional", "probes": "attributional", "lexical": "descriptive", "unlearning": "causal",
    "selectivity": "causal", "recurrence": "attributional"}
REFUSED = {"descriptive": ("unlearning", "selectivity", "recurrence")}


def labelled(docs: DataFrame) -> DataFrame:
    """(doc_id, text, topic, format): both labels by votes of the words, without any URL; texts without words go."""
    w = docs.select("doc_id", "text", tokens(F.col("text")).alias("w"))
    v = w.select("doc_id", "text", votes(F.col("w"), "topic", LABELS).alias("a"), votes(F.col("w"), "format",
        LABELS).alias("b")).where(F.size("a") > 0)  # columns, so that no label hashes a word again
    return v.select("doc_id", "text", vote_label(F.col("a"))["label"].alias("topic"), vote_label(F.col("b"))["label"].alias("format"))


def ecosystem_bins(docs: DataFrame, queries: DataFrame) -> DataFrame:
    """Bins with z of one corpus: its own index, its own model, shared benchmarks."""
    sums = at.sign_sums(docs, ["doc_id", "topic", "format"], tokens(F.col("text")))
    base = at.model_means(sums)
    q = at.reduce_queries(at.gradients(at.query_sums(queries), base), ["bench"])
    return ag.zscore(ag.bin_mean(at.score_index(at.gradients(sums, base), q, ["doc_id", "topic", "format"], ["bench"])))


def run_ecosystem(docs: DataFrame, queries: DataFrame) -> dict[str, DataFrame]:
    """Every product of the analysis of one corpus (doc_id, text, topic, format), by name: what runs on one ecosystem runs
    on another by giving it other documents.  All are plans; nothing is computed before one is asked for."""
    bins = ecosystem_bins(docs, queries)
    topics, formats = ag.marginal_z(bins, "topic"), ag.marginal_z(bins, "format")
    r = ag.profile_corr(bins)
    benches = tuple(BENCHES)
    return {
        "composition": docs.groupBy("topic", "format").agg(F.count("*").alias("n_docs")), "bins": bins, "topics": topics, "formats": formats,
            "capped": ag.capped(bins), "tests": ag.bin_tests(bins),
        "signed": ag.signed_split(bins), "topic_extremes": ag.extremes(topics, "topic"), "format_extremes": ag.extremes(formats, "format"),
            "correlation": r, "rank_correlation": ag.profile_corr(bins, how="spearman"),
        "outlier": ag.outlier_stat(r, benches), "topic_outlier": ag.outlier_stat(ag.profile_corr(topics, ["topic"]), benches),
            "format_outlier": ag.outlier_stat(ag.profile_corr(formats, ["format"]), benches),
        "loading": register_loading(bins),
    }


def parity(spark: SparkSession, ours: dict[str, DataFrame], theirs: dict[str, DataFrame]) -> DataFrame:
    """(product, status): equivalent where both ecosystems have a product with the same columns, generated where only the
    second has it, missing where only the first has it, blocked where the columns differ."""
    rows = []
    for name in sorted(ours.keys() | theirs.keys()):
        if name not in theirs:
            status = "missing"
        elif name not in ours:
            status = "generated"
        else:
            status = "equivalent" if ours[name].columns == theirs[name].columns else "blocked"
        rows.append((name, status))
    return spark.createDataFrame(rows, "product string, status string")


def as_long(products: dict[str, DataFrame]) -> DataFrame:
    """The numeric products as one table (product, bench, a, b, value)."""
    cols = {"bins": ("bench", "topic", "format", "z"), "topics": ("bench", "topic", None, "z"), "formats": ("bench", "format", None, "z"),
        "correlation": ("a", "b", None, "r"), "loading": ("bench", None, None, "loading")}
    out = None
    for name, (bench, a, b, value) in cols.items():
        key = [(F.col(c) if c else F.lit(None)).cast("string").alias(n) for c, n in ((bench, "bench"), (a, "a"), (b, "b"))]
        one = products[name].select(F.lit(name).alias("product"), *key, F.col(value).alias("value"))
        out = one if out is None else out.unionByName(one)
    return out


def register_loading(bins: DataFrame) -> DataFrame:
    low = F.col("format") < GROUP
    return bins.groupBy("bench").agg((F.avg(F.when(low, F.col("z"))) - F.avg(F.when(~low, F.col("z")))).alias("loading"))


def profile_agreement(a: DataFrame, b: DataFrame) -> DataFrame:
    """(bench, n_bins, r) over bins that both corpora fill."""
    other = b.select("bench", "topic", "format", F.col("z").alias("zb"))
    return a.select("bench", "topic", "format", "z").join(other, ["bench", "topic", "format"]).groupBy("bench").agg(F.count("*").alias("n_bins"),
        F.corr("z", "zb").alias("r"))


def register_flip(a: DataFrame, b: DataFrame, tiers: DataFrame) -> DataFrame:
    """Loadings in two corpora and whether the sign turns, for benchmarks that aren't failure controls."""
    x, y = a.withColumnRenamed("loading", "e1"), b.withColumnRenamed("loading", "e2")
    kept = tiers.where("tier <> 'failure control'").select("bench")
    return x.join(y, "bench").join(kept, "bench", "left_semi").withColumn("flip", F.col("e1") * F.col("e2") < 0)


def variant_shift(a: DataFrame, b: DataFrame) -> DataFrame:
    """Change of the loading when only the queries' model changes."""
    return a.withColumnRenamed("loading", "before").join(b.withColumnRenamed("loading", "after"), "bench").withColumn("shift", F.col("after") - F.col("before"))


def compare_effects(a: DataFrame, b: DataFrame) -> DataFrame:
    """Paired effects (target, n, dz, median_d) under two controls, and the move of the effect size between them."""
    x, y = (d.select("target", F.col("dz").alias(f"dz_{k}"), F.col("median_d").alias(f"median_{k}")) for k, d in (("a", a), ("b", b)))
    return x.join(y, "target").withColumn("shift", F.abs(F.col("dz_a") - F.col("dz_b")))


def require_scope(corpus: str, family: str) -> str:
    """Scope of a family's results on a corpus; raises where the corpus allows no such claim."""
    allowed = SCOPES[corpus]
    if family in REFUSED.get(allowed, ()):
        raise ValueError(f"{corpus} is {allowed}: no {family}")
    return "descriptive" if allowed == "descriptive" else FAMILIES[family]


def scope_table() -> list[tuple[str, str, str]]:
    """(corpus, family, scope), refusals stated."""
    return [(c, f, "refused" if f in REFUSED.get(SCOPES[c], ()) else require_scope(c, f)) for c in SCOPES for f in FAMILIES]


def minted(pages: DataFrame, text) -> DataFrame:
    """Pages as documents whose id is made from content: 15 hexadecimal digits of the MD5, so repeated texts are one."""
    rows = pages.select(text.alias("text")).where("text <> ''")
    return rows.select(F.conv(F.substring(F.md5("text"), 1, 15), 16, 10).cast("long").alias("doc_id"), "text").groupBy("doc_id").agg(F.min("text").alias("text"))


