"""The given tables as the engine's artifacts: corpus, queries, ledger, star grid; and JSONL, CSV and Parquet ends."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from binlens.functions.hashing import u32

BENCHES = ("SR", "TR", "SK", "TK")
UNBINNED = ("src18", "src19")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def spread(rows: DataFrame) -> DataFrame:
    """Rows dealt out anew where a table has fewer row groups or files than there are cores, which only a small one has."""
    width = rows.sparkSession.sparkContext.defaultParallelism
    return rows.repartition(width) if rows.rdd.getNumPartitions() < width else rows


def tokens(text) -> F.Column:
    """Lower-case white-space words; empty text has none."""
    return F.filter(F.split(F.trim(F.lower(text)), r"\s+"), lambda t: t != "")


def corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents on the native grid: topic = source, format = language."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", F.col("source").alias("topic"), F.col("lang").alias("format"), "n_chars")
    return docs.withColumn("n_words", F.size(tokens(F.col("text"))).cast("long")).withColumn("is_binned", ~F.col("topic").isin(*UNBINNED))


def upsampled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each document 1 + (source number mod 3) times, as a corpus with repeated ids."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    copies = F.regexp_replace("source", "src", "").cast("int") % 3
    return docs.withColumn("copy_no", F.explode(F.sequence(F.lit(0), copies))).withColumn("pos", F.col("doc_id") * 3 + F.col("copy_no"))


def bench_queries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Benchmark items as prompt (first half of the words) and completion; four benchmarks by item number."""
    rows = table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("query_id"), tokens(F.col("text")).alias("w"))
    half = F.floor(F.size("w") / 2).cast("int")
    names = F.element_at(F.array(*[F.lit(b) for b in BENCHES]), (F.col("query_id") % 4 + 1).cast("int"))
    return rows.select("query_id", names.alias("bench"), F.slice("w", 1, half).alias("prompt"), F.slice("w", half + 1, F.greatest(F.size("w") - half,
        F.lit(0))).alias("completion"), F.when(half > 0, F.element_at("w", half)).alias("last_word"))


def ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A synthetic run ledger, pure arithmetic over orders: (recipe, topic, seed, target, bench, gamma, steps)."""
    o = table(spark, sf_dir, "orders").join(table(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey")).where("c_nationkey < 24")
    bench = {"1-URGENT": "SR", "2-HIGH": "TR", "3-MEDIUM": "SK", "4-NOT SPECIFIED": "TK"}
    o = o.where(F.col("o_orderpriority").isin(*bench))
    mapped = F.coalesce(*[F.when(F.col("o_orderpriority") == k, v) for k, v in bench.items()])
    recipe = F.when(F.col("o_orderstatus") == "F", "influence").when(F.col("o_orderstatus") == "O", "random").otherwise("naive")
    target = F.element_at(F.array(*[F.lit(b) for b in BENCHES]), (F.col("o_orderkey") % 4 + 1).cast("int"))
    rows = o.select(recipe.alias("recipe"), F.col("c_nationkey").cast("long").alias("topic"), (F.col("o_orderkey") % 3 + 42).alias("seed"),
        target.alias("target"), mapped.alias("bench"), "o_totalprice", "o_orderkey")
    return rows.groupBy("recipe", "topic", "seed", "target", "bench").agg(F.round(F.avg("o_totalprice") / 1e6 - 0.15, 9).alias("gamma"),
        (F.sum("o_orderkey") % 400 + 100).alias("steps"))


def star_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Numeric stand-in at scale: brand x nation bins, order priority as benchmark, net revenue as score."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber",
        (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("score"))
    part = table(spark, sf_dir, "part").select("p_partkey", F.col("p_brand").alias("topic"))
    supp = table(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_nationkey").alias("format"))
    orders = table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_orderpriority").alias("bench"))
    return line.join(part, F.col("l_partkey") == F.col("p_partkey")).join(supp, F.col("l_suppkey") == F.col("s_suppkey")).join(orders,
        F.col("l_orderkey") == F.col("o_orderkey")).select("l_orderkey", "l_linenumber", "topic", "format", "bench", "score")


def write_queries_jsonl(queries: DataFrame, path: str) -> None:
    queries.select("query_id", "bench", F.array_join("prompt", " ").alias("prompt"), F.array_join("completion",
        " ").alias("completion")).write.mode("overwrite").json(path)


def read_queries_jsonl(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("query_id long, bench string, prompt string, completion string").json(path)


def write_scores(scores: DataFrame, path: str, partition: str = "bench") -> None:
    """Scores by benchmark, so that a stage reads one benchmark's folder."""
    scores.write.mode("overwrite").partitionBy(partition).parquet(path)


def votes(text_tokens, kind: str, n: int) -> F.Column:
    """Label votes of tokens: array of label numbers."""
    return F.transform(text_tokens, lambda t: u32(F.lit(kind), t) % n)


#: Blocks of a page that carry no running text, then any tag.
PAGE_NOISE, PAGE_TAG = r"(?s)<head.*?</head>|<nav.*?</nav>|<footer.*?</footer>|<script.*?</script>|<style.*?</style>|<!--.*?-->", r"<[^>]*>"


def page_text(html) -> F.Column:
    """Plain words of a page, by two replacements inside the plan: enough to label and score a page as a document."""
    t = F.regexp_replace(F.regexp_replace(html, PAGE_NOISE, " "), PAGE_TAG, " ")
    return F.trim(F.regexp_replace(F.replace(t, F.lit("&amp;"), F.lit("&")), r"[ \t\r\n]+", " "))


def turn_queries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Assistant turns that answer a user turn: prompt = the user's words, completion = the answer's, nine probes."""
    c = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", tokens(F.col("text")).alias("w"))
    asked = c.where("role = 'user'").select("conv_id", (F.col("turn") + 1).alias("turn"), F.col("w").alias("prompt"))
    rows = c.where("role = 'assistant'").join(asked, ["conv_id", "turn"])
    return rows.select((F.col("conv_id") * 100 + F.col("turn")).alias("query_id"), (F.col("conv_id") % 9).alias("bench"), "prompt", F.col("w").alias("completion"))
