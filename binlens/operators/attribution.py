"""Attribution: projected, unit-normalised per-module gradients of log-linear heads; scores against benchmark queries.

A head's gradient for a text is its token distribution less the model's.  Projected on d random signs, the first
part is the mean sign vector of the text's tokens and the second the mean over all tokens of the model's corpus:
one narrow pass and one tiny aggregate.  Modules: words, and pairs of adjacent words, as columns of one row a text.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, LongType, StructType
from pyspark.sql.window import Window

from binlens.functions.hashing import coded, flat_words, u32_each
from binlens.functions.stats import r6

D = 16
MODULES = ("uni", "bi")


def pairs_of(words) -> Column:
    """Adjacent pairs of words, as one token each."""
    n = F.size(words)
    rest = F.greatest(n - 1, F.lit(0))
    return F.when(n > 1, F.zip_with(F.slice(words, 1, rest), F.slice(words, 2, rest), lambda a, b: F.concat_ws(" ", a, b))).otherwise(F.slice(words, 1, 0))


def module_tokens(words) -> Column:
    """Array of (module, token): words, and adjacent pairs."""

    def named(tokens, module):
        return F.transform(tokens, lambda t: F.struct(F.lit(module).alias("module"), t.alias("token")))

    return F.concat(named(words, "uni"), named(pairs_of(words), "bi"))


def sign_bits(hashes: np.ndarray, index: np.ndarray, starts: np.ndarray, d: int) -> pa.Array:
    """Summed signs of each row's tokens, an array of ``d`` a row; ``index`` leads from a token to its hash."""
    out, some = np.zeros((len(starts) - 1, d), np.int64), np.flatnonzero(np.diff(starts))
    if len(some):
        for i in range(d):
            out[some, i] = np.add.reduceat((2 * (hashes >> i & 1) - 1).astype(np.int32)[index], starts[some], dtype=np.int64)
    return pa.ListArray.from_arrays(pa.array(np.arange(len(out) + 1) * d, pa.int32()), pa.array(out.ravel(), pa.int64()))


def token_signs(df: DataFrame, key: list[str], words: dict[str, Column], d: int = D) -> DataFrame:
    """(key, uni, bi): for each module the number of tokens ``n`` and their summed signs ``s``, an array of ``d``.

    ``words``: an array for each module, whose tokens are the words and the pairs of adjacent ones; null counts as empty.
    A narrow pass: a batch's different tokens are hashed once each and nothing is exploded or shuffled."""

    def count(batches):
        for batch in batches:
            sums = []
            for m in MODULES:
                flat, starts = flat_words(batch.column(f"_{m}"))
                index, known = coded(flat)
                index = index.astype(np.int64)
                if m == "bi":
                    sizes = np.diff(starts)
                    later = np.ones(len(index), bool)
                    later[starts[:-1][sizes > 0]] = False
                    at = np.flatnonzero(later)
                    few, index = np.unique(index[at - 1] * len(known) + index[at], return_inverse=True)
                    known = [known[a] + b" " + known[b] for a, b in zip((few // max(len(known), 1)).tolist(), (few % max(len(known), 1)).tolist(), strict=True)]
                    starts = np.concatenate([[0], np.cumsum(np.maximum(sizes - 1, 0))])
                n = pa.array(np.diff(starts), pa.int64())
                sums.append(pa.StructArray.from_arrays([n, sign_bits(u32_each(known, "s", m), index, starts, d)], ["n", "s"]))
            yield pa.RecordBatch.from_arrays([*[batch.column(k) for k in key], *sums], [*key, *MODULES])

    kind = StructType().add("n", "long").add("s", ArrayType(LongType()))
    schema = StructType(df.select(*key).schema.fields)
    for m in MODULES:
        schema = schema.add(m, kind)
    return df.select(*key, *[words[m].alias(f"_{m}") for m in MODULES]).mapInArrow(count, schema)


def sign_sums(df: DataFrame, key: list[str], words, d: int = D) -> DataFrame:
    """``token_signs`` of texts given as arrays of words: the index, one row for each text, from which gradients under
    any model follow row by row."""
    split = df.select(*key, words.alias("_w"))
    return token_signs(split, key, {"uni": F.col("_w"), "bi": F.col("_w")}, d)


def model_means(sums: DataFrame, extra: DataFrame | None = None, a: float = 0.5, d: int = D) -> DataFrame:
    """One row (p_uni, p_bi), arrays of d: the model's projected distribution; with ``extra`` an interpolation with a second corpus."""

    def one(x, tag):
        cols = [F.array(*[F.try_divide(F.sum(F.col(f"{m}.s")[i]).cast("double"), F.sum(f"{m}.n")) for i in range(d)]).alias(f"{tag}_{m}") for m in MODULES]
        return x.agg(*cols)

    base = one(sums, "p")
    if extra is None:
        return base
    both = base.crossJoin(F.broadcast(one(extra, "q")))  # one row each
    return both.select(*[F.zip_with(f"p_{m}", f"q_{m}", lambda x, y: (1 - a) * x + a * y).alias(f"p_{m}") for m in MODULES])


def norm(v) -> Column:
    return F.sqrt(F.aggregate(v, F.lit(0.0), lambda acc, x: acc + x * x))


def unit(v) -> Column:
    """v / norm(v); zeros where the norm is 0.  The norm is bound by a lambda, or it would be taken for each element."""
    return F.transform(F.array(norm(v)), lambda size: F.transform(v, lambda x: F.coalesce(F.try_divide(x, size), F.lit(0.0))))[0]


def gradients(sums: DataFrame, model: DataFrame) -> DataFrame:
    """Keys, uni, bi: unit gradients, zeros where the norm is 0, null for a module without tokens.  A narrow pass; the
    model is one row, so it is broadcast."""
    key = [c for c in sums.columns if c not in MODULES]

    def less_model(n):
        return lambda x, p: x / n - p

    raw = [F.when(F.col(f"{m}.n") > 0, F.zip_with(F.col(f"{m}.s"), f"p_{m}", less_model(F.col(f"{m}.n")))).alias(m) for m in MODULES]
    return sums.crossJoin(F.broadcast(model)).select(*key, *raw).select(*key, *[unit(F.col(m)).alias(m) for m in MODULES])


def by_module(grad: DataFrame) -> DataFrame:
    """Keys, module, g: a row for each module that isn't null."""
    key = [c for c in grad.columns if c not in MODULES]
    rows = F.array(*[F.struct(F.lit(m).alias("module"), F.col(m).alias("g")) for m in MODULES])
    return grad.select(*key, F.inline(rows)).where("g is not null")


def reduce_queries(grad: DataFrame, by: list[str], d: int = D) -> DataFrame:
    """Mean query gradient of each group and module: scoring one mean equals the mean of the scores."""
    means = [F.when(F.count(m) > 0, F.array(*[F.avg(F.col(m)[i]) for i in range(d)])).alias(m) for m in MODULES]
    return grad.groupBy(*by).agg(*means)


def dot(a, b) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda acc, x: acc + x)


MAX_QUERIES = 100_000  # query groups that one scan of the index carries along (some 30 MB)


def score_index(index: DataFrame, means: DataFrame, keys: list[str], by: list[str]) -> DataFrame:
    """Score of each document for each query group: all groups in one narrow scan of the index.

    The groups travel as one row, broadcast; more than ``MAX_QUERIES`` of them are refused, as they would have to be
    scored in several scans.
    """
    group = F.collect_list(F.struct(*by, *[F.col(m).alias(f"q_{m}") for m in MODULES])).alias("_q")
    size = F.when(F.count("*") > MAX_QUERIES, F.raise_error(F.lit("too many query groups for one scan"))).otherwise(F.lit(0)).alias("_size")
    one = means.agg(group, size).where("_size = 0").select("_q")
    rows = index.crossJoin(F.broadcast(one)).select(*keys, *MODULES, F.explode("_q").alias("_q"))
    parts = [dot(m, F.col(f"_q.q_{m}")) for m in MODULES]
    rows = rows.select(*keys, *[F.col(f"_q.{c}").alias(c) for c in by], *[p.alias(m) for p, m in zip(parts, MODULES)])
    return rows.where("uni is not null or bi is not null").select(*keys, *by, (F.coalesce("uni", F.lit(0.0)) + F.coalesce("bi", F.lit(0.0))).alias("score"))


def check_pairing(scores: DataFrame) -> DataFrame:
    """Raise if index and queries come from crossed models: all scores are then zero."""
    if not scores.where("abs(score) > 0").limit(1).count():
        raise ValueError("all scores are zero: index and queries don't come from one checkpoint pair")
    return scores


def second_moments(grad: DataFrame, d: int = D) -> dict[str, np.ndarray]:
    """Second-moment matrix of each module: one aggregate of d * d sums, then d x d numbers on the driver."""
    cells = [(m, i, j) for m in MODULES for i in range(d) for j in range(i, d)]
    row = grad.agg(*[F.avg(F.col(m)[i] * F.col(m)[j]).alias(f"{m}_{i}_{j}") for m, i, j in cells]).first()
    out = {m: np.zeros((d, d)) for m in MODULES}
    for m, i, j in cells:
        out[m][i, j] = out[m][j, i] = row[f"{m}_{i}_{j}"] or 0.0
    return out


def mix_precond(value: np.ndarray, query: np.ndarray, mix: float = 0.5, leading: int = 1000, eps: float = 1e-6) -> np.ndarray:
    """Inverse root of the mixed second moment, its leading eigenvalues clipped to the last of them, ridge on top."""
    h = mix * value + (1 - mix) * query
    w, v = np.linalg.eigh(h)
    r = min(leading, len(w)) - 1
    cap = np.sort(w)[::-1][min(r, len(w) - 1)] if leading < len(w) else w.max()
    w = np.maximum(np.minimum(w, max(cap, 0)), 0) + eps * max(np.trace(h) / len(w), 1e-12)
    return (v / np.sqrt(w)) @ v.T


def whiten(grad: DataFrame, roots: dict[str, np.ndarray]) -> DataFrame:
    """Multiply gradients by a module's inverse root at index build, so that scoring is a bare dot product."""

    def product(m):
        return F.when(F.col(m).isNotNull(), F.array(*[dot(F.col(m), F.array(*[F.lit(float(x)) for x in row])) for row in roots[m]]))

    return grad.withColumns({m: product(m) for m in MODULES})


def topk_docs(scores: DataFrame, k: int, by: list[str]) -> DataFrame:
    """The k best documents of each group; k per partition and group move."""
    w = Window.partitionBy(*by).orderBy(F.desc("score"), "doc_id")
    return scores.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def vector_scores(vectors: DataFrame, modules: int = 4, width: int = 64) -> DataFrame:
    """Ready vectors as an index: cut into modules, unit in each; every tenth is a query of one of four benchmarks.

    A vector's unit modules stand side by side in one array, so a score is one product in a narrow scan."""
    size = width // modules
    rows = vectors.select("vec_id", F.col("label").alias("topic"), (F.col("vec_id") % 4).alias("format"), F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    cut = [F.slice("v", k * size + 1, size) for k in range(modules)]
    whole = F.concat(*[unit(c) for c in cut])
    rows = rows.select("vec_id", "topic", "format", whole.alias("uni"), F.lit(None).cast("array<double>").alias("bi"))
    asked = rows.where("vec_id % 10 = 0").withColumn("bench", F.floor(F.col("vec_id") / 10) % 4)
    return score_index(rows.where("vec_id % 10 <> 0"), reduce_queries(asked, ["bench"], width), ["vec_id", "topic", "format"], ["bench"])


def query_sums(q: DataFrame, d: int = D) -> DataFrame:
    """Sign sums of completions: words of the completion, pairs that end in it."""
    both = F.when(F.col("last_word").isNotNull(), F.concat(F.array("last_word"), F.col("completion"))).otherwise(F.col("completion"))
    return token_signs(q, ["bench", "query_id"], {"uni": F.col("completion"), "bi": both}, d)


def planted(docs: DataFrame, items: DataFrame, size: int = 5) -> DataFrame:
    """(query_id, doc_id): documents that hold an item's whole text.

    An item is looked up by a window of ``size`` words from its inside, which stands as whole words in any document that
    holds it; only documents with that window are searched.  Items too short for a window are searched for everywhere."""
    words = lambda c: F.filter(F.split(c, r"\s+"), lambda t: t != "")
    asked = items.withColumn("w", words(F.col("t"))).withColumn("key", F.when(F.size("w") >= size + 2, F.array_join(F.slice("w", 2, size), " ")))
    keyed, short = F.broadcast(asked.where("key is not null").select("query_id", "t", "key")), asked.where("key is null").select("query_id",
        "t")  # the benchmark is bounded
    n = F.size("w") - size
    windows = F.when(n >= 0, F.transform(F.sequence(F.lit(1), n + 1), lambda i: F.array_join(F.slice("w", i, F.lit(size)),
        " "))).otherwise(F.array().cast("array<string>"))
    rows = docs.select("doc_id", "text", words(F.col("text")).alias("w")).select("doc_id", "text", F.explode(F.array_distinct(windows)).alias("key"))
    found = rows.join(keyed, "key").where(F.col("text").contains(F.col("t"))).select("query_id", "doc_id")
    return found.unionByName(docs.join(F.broadcast(short), F.col("text").contains(F.col("t"))).select("query_id", "doc_id")).distinct()


def planted_recall(pair_scores: DataFrame, truth: DataFrame, ks=(1, 10)) -> DataFrame:
    """Recall and mean reciprocal rank of the documents known to hold a query's text."""
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "doc_id")
    hit = pair_scores.withColumn("rank", F.row_number().over(w)).join(truth, ["query_id", "doc_id"], "left_semi")
    return hit.agg(F.count("*").alias("n_pairs"), *[r6(F.avg((F.col("rank") <= k).cast("double"))).alias(f"recall_{k}") for k in ks],
        r6(F.avg(1.0 / F.col("rank"))).alias("mrr"))
