"""Unlearning on a conditional bigram head: forget and retain sets, normalised gradient difference, low-rank adapter.

A set's gradient depends on its mean per-document bigram frequencies only, so one distributed count serves all
runs, and a run is a loop over a V x V matrix in one process; runs are dealt over tasks, which sum their sets as they read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from binlens.functions.hashing import coded, flat_words, u32, u32_each
from binlens.operators.corpus import lowest

V = 1024  # hash buckets of words: the head has V x V logits
#: Set sizes: those of the reference, and the share of a topic (or corpus) that a set may take where there are fewer documents.
SIZES = {"influence": (200, 0.1), "bin": (200, 0.1), "random": (1000, 0.25), "naive": (2000, 0.05), "global": (1000, 0.05), "null": (200, 0.02), "retain": (9000, 0.3)}
SEEDS = (42, 43, 44)


def size_of(arm: str, total) -> F.Column:
    """Documents of a set: at least one, at most the arm's, and at most its share of ``total``."""
    most, share = SIZES[arm]
    return F.greatest(F.lit(1), F.least(F.lit(most), F.floor(F.lit(share) * total))).cast("int")


def forget_influence(scores: DataFrame, n: int) -> DataFrame:
    w = Window.partitionBy("topic", "bench").orderBy(F.desc("score"), "doc_id")
    return scores.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= n).select("bench", "topic", "doc_id", F.lit("influence").alias("arm"))


def forget_naive(scores: DataFrame, n: int) -> DataFrame:
    w = Window.partitionBy("bench").orderBy(F.desc("score"), "doc_id")
    return scores.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= n).select("bench", F.lit(None).cast("string").alias("topic"),
        "doc_id", F.lit("naive").alias("arm"))


def forget_random(docs: DataFrame, n: int, seed: str, by_topic: bool = True) -> DataFrame:
    """Random arm: in topic, or global."""
    rows = lowest(docs.select("topic", "doc_id", u32(F.lit(seed), F.col("doc_id")).alias("_u")), n, ["topic"] if by_topic else [], "doc_id", 12 if by_topic else 20)
    topic = "topic" if by_topic else F.lit(None).cast("string").alias("topic")
    return rows.select(F.lit(None).cast("string").alias("bench"), topic, "doc_id", F.lit("random" if by_topic else "global").alias("arm"))


def forget_bin_level(bins: DataFrame, docs: DataFrame, n: int, seed: str) -> DataFrame:
    """Documents of a topic, those of its strongest bins first."""
    w = Window.partitionBy("bench", "topic").orderBy(F.desc("z"), u32(F.lit(seed), F.col("doc_id")), "doc_id")
    rows = docs.join(bins.select("bench", "topic", "format", "z"), ["topic", "format"])
    return rows.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= n).select("bench", "topic", "doc_id", "rank", F.lit("bin").alias("arm"))


def forget_multi(sets: list[DataFrame]) -> DataFrame:
    """Union of several bins' forget sets as one run; a document in two of them counts once."""
    out = sets[0]
    for s in sets[1:]:
        out = out.unionByName(s)
    return out.select("bench", "doc_id").distinct().withColumn("arm", F.lit("multi"))


def grid_sets(scores: DataFrame, bins: DataFrame, docs: DataFrame, n_docs: int, seeds: tuple = SEEDS) -> DataFrame:
    """(run_id, doc_id): the forget sets of the whole grid, run_id "arm/topic/target/seed".

    In each topic of the grid: the target's most influential documents and, by the z of their bins, those of its strongest
    bins; random ones of each seed.  Without a topic: each target's most influential documents, random ones, and the
    null-bin control's, from documents outside the grid.  Sizes are those of ``SIZES``."""
    binned = docs.where("is_binned")
    total = F.broadcast(binned.groupBy("topic").agg(F.count("*").alias("total")))  # one row for each topic

    def ranked(rows, arm, by, *order):
        few = rows.withColumn("rank", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("rank") <= SIZES[arm][0])
        return few.join(total, "topic").where(F.col("rank") <= size_of(arm, F.col("total")))

    def named(rows, arm, topic="topic", target="bench", seed="*"):
        part = lambda c: F.col(c) if c else F.lit("")
        return rows.select(F.concat(F.lit(f"{arm}/"), part(topic), F.lit("/"), part(target), F.lit(f"/{seed}")).alias("run_id"), "doc_id")

    inside = scores.join(total.select("topic"), "topic", "left_semi")
    sets = [named(ranked(inside, "influence", ["topic", "bench"], F.desc("score"), "doc_id"), "influence")]
    by_bin = forget_bin_level(bins, binned, SIZES["bin"][0], str(seeds[0])).join(total, "topic").where(F.col("rank") <= size_of("bin", F.col("total")))
    sets.append(named(by_bin, "bin", seed=seeds[0]))
    few = {arm: max(1, min(SIZES[arm][0], int(SIZES[arm][1] * n_docs))) for arm in ("naive", "global", "null")}
    sets.append(named(forget_naive(inside, few["naive"]), "naive", topic=None))
    for s in map(str, seeds):
        draw = u32(F.lit(s), F.col("doc_id"))
        sets.append(named(ranked(binned.select("topic", "doc_id", draw.alias("u")), "random", ["topic"], "u", "doc_id"), "random", target=None, seed=s))
        sets.append(named(forget_random(binned, few["global"], s, False), "global", None, None, s))
        sets.append(named(forget_null(docs.where("not is_binned"), few["null"], s), "null", None, None, s))
    out = sets[0]
    for x in sets[1:]:
        out = out.unionByName(x)
    return out


def forget_null(pool: DataFrame, n: int, seed: str) -> DataFrame:
    """Null-bin control: documents of a reserved pool that no topic of the grid uses."""
    rows = lowest(pool.withColumn("_u", u32(F.lit(seed), F.col("doc_id"))), n, [], "doc_id", 20)
    return rows.select("doc_id", F.lit("null").alias("arm"))


def retain_set(docs: DataFrame, forget: DataFrame, n: int, seed: str, mode: str = "flat") -> DataFrame:
    """Retained documents, disjoint from the forget set: flat, uniform outside its topics, or stratified over topics
    (each topic gives its lowest draws, as many as any other as long as it has some)."""
    rest = docs.join(forget.select("doc_id").distinct(), "doc_id", "left_anti")
    if mode == "uniform":
        rest = rest.join(forget.select("topic").distinct(), "topic", "left_anti")
    rest = rest.select("doc_id", "topic", u32(F.lit(seed), F.col("doc_id")).alias("_u"))
    if mode == "stratified":
        few = lowest(rest, n, ["topic"], "doc_id", 12)  # no topic can give more than n
        ranked = few.withColumn("r", F.row_number().over(Window.partitionBy("topic").orderBy("_u", "doc_id")))
        return ranked.orderBy("r", "_u", "doc_id").limit(n).select("doc_id", "topic")
    return lowest(rest, n, [], "doc_id", 20).select("doc_id", "topic")


def shuffle_segments(words, doc_id, seed: str, size: int = 8):
    """Words cut into segments, segments in hash order: the stop rule's random text."""
    n = F.ceil(F.size(words) / size).cast("int")
    seg = F.transform(F.sequence(F.lit(0), F.greatest(n - 1, F.lit(0))), lambda i: F.struct(u32(F.lit(seed), doc_id, i).alias("k"), i.alias("i"),
        F.slice(words, i * size + 1, F.lit(size)).alias("w")))
    return F.flatten(F.transform(F.array_sort(seg), lambda s: s["w"]))


def numbered(words: pa.ListArray, v: int) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of the words of all rows one after another, and where each row's begin."""
    flat, starts = flat_words(words)
    index, known = coded(flat)
    return (u32_each(known, "v") % v)[index], starts


def bigrams(h: np.ndarray, starts: np.ndarray, v: int) -> tuple[np.ndarray, np.ndarray]:
    """(u * v + v, row) of each two adjacent buckets of a row."""
    sizes = np.diff(starts)
    later = np.ones(len(h), bool)
    later[starts[:-1][sizes > 0]] = False
    at = np.flatnonzero(later)
    return h[at - 1] * v + h[at], np.repeat(np.arange(len(sizes)), sizes)[at]


def cells(code: np.ndarray, f: np.ndarray, v: int) -> list[pa.Array]:
    return [pa.array(code // v, pa.int32()), pa.array(code % v, pa.int32()), pa.array(f, pa.float64())]


BROADCAST_MEMBERS = 1_000_000  # memberships up to which documents meet them by broadcast
DENSE = 4 << 20  # cells that a task sums in place; with more sets than that, each batch gives its own sums


def set_stats(membership: DataFrame, docs: DataFrame, words, v: int = V) -> DataFrame:
    """(run_id, role, u, v, f): mean over a set's documents of their bigram frequencies; runs x V^2 rows at most.

    A document's words are hashed once whatever the sets that hold it, and tasks give sums of sets."""
    sizes = membership.groupBy("run_id", "role").agg(F.count("*").alias("n")).collect()  # a row for each set
    names = docs.sparkSession.createDataFrame([(k, *r) for k, r in enumerate(sizes)], "set int, run_id string, role string, n long")
    own = membership.join(F.broadcast(names), ["run_id", "role"]).groupBy("doc_id").agg(F.collect_list("set").alias("sets"))
    if sum(r.n for r in sizes) <= BROADCAST_MEMBERS:
        own = F.broadcast(own)
    dense = len(sizes) * v * v <= DENSE

    def out(key, f):
        return pa.RecordBatch.from_arrays([pa.array(key // (v * v), pa.int32()), *cells(key % (v * v), f, v)], ["set", "u", "v", "f"])

    def count(batches):
        total = np.zeros(len(sizes) * v * v if dense else 0)
        for batch in batches:
            h, starts = numbered(batch.column("words"), v)
            code, row = bigrams(h, starts, v)
            f = (1 / np.maximum(np.diff(starts) - 1, 1))[row]
            sets, first = flat_words(batch.column("sets"))
            sets, each = sets.to_numpy(zero_copy_only=False), np.diff(first)
            for k in range(each.max(initial=0)):  # each document's k-th set
                has = each[row] > k
                key = sets[first[:-1][row[has]] + k].astype(np.int64) * (v * v) + code[has]
                if dense:
                    total += np.bincount(key, f[has], len(total))
                else:
                    few, index = np.unique(key, return_inverse=True)
                    yield out(few, np.bincount(index, f[has], len(few)))
        if dense:
            some = np.flatnonzero(total)
            yield out(some, total[some])

    rows = docs.join(own, "doc_id").select("sets", words.alias("words")).mapInArrow(count, "set int, u int, v int, f double")
    return rows.groupBy("set", "u", "v").agg(F.sum("f").alias("f")).join(F.broadcast(names), "set").select("run_id", "role", "u", "v",
        (F.col("f") / F.col("n")).alias("f"), "n")


SCALE = 1e5  # documents that the base head's counts stand for


def corpus_stats(docs: DataFrame, words, v: int = V) -> DataFrame:
    """(u, v, f): bigram frequencies of the whole corpus on the scale of 1e5 documents, for the base head."""

    def count(batches):
        total = np.zeros(v * v)
        for batch in batches:
            h, starts = numbered(batch.column("words"), v)
            code, row = bigrams(h, starts, v)
            total += np.bincount(code, (1 / np.maximum(np.diff(starts) - 1, 1))[row], v * v)
        some = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays(cells(some, total[some], v), ["u", "v", "f"])

    sums = docs.select(words.alias("words")).mapInArrow(count, "u int, v int, f double").groupBy("u", "v").agg(F.sum("f").alias("f"))
    return sums.crossJoin(F.broadcast(docs.agg(F.count("*").alias("n")))).select("u", "v", (F.col("f") / F.col("n") * SCALE).alias("f"))  # one row


def forget_stats(members: DataFrame, docs: DataFrame, words, seed: str) -> DataFrame:
    """(run_id, role, u, v, f) of forget sets (run_id, doc_id), as they are and with their segments shuffled."""
    few = docs.join(members.select("doc_id").distinct(), "doc_id", "left_semi").select("doc_id", words.alias("w"))  # split once, members only
    plain = set_stats(members.withColumn("role", F.lit("forget")), few, F.col("w"))
    return plain.unionByName(set_stats(members.withColumn("role", F.lit("shuffled")), few.where("size(w) > 0").select("doc_id",
        shuffle_segments(F.col("w"), F.col("doc_id"), seed).alias("w")), F.col("w")))


PIECE = 2048  # pairs of words in a row of ``forget_texts``


def forget_texts(members: DataFrame, docs: DataFrame, words, seed: str, v: int = V, segment: int = 8) -> DataFrame:
    """(run_id, n, n_words, plain, shuffled): buckets of the words of each forget set's documents, and those with the
    segments of ``shuffle_segments`` in hash order, in pieces that share one word; ``n`` is the set's size.  A document
    is hashed once, whatever the sets that hold it.  Sets are bounded by ``SIZES``, so membership is broadcast."""

    def cut(batches):
        for batch in batches:
            h, starts = numbered(batch.column("words"), v)
            rows, plain, shuffled = [], [], []
            for i, name in enumerate(batch.column("name").to_pylist()):
                one = h[starts[i] : starts[i + 1]].astype(np.int32)
                n = len(one)
                if n < 2 or name is None:
                    continue
                keys = u32_each([str(k).encode() for k in range(-(-n // segment))], seed, name)
                at = (np.argsort(keys, kind="stable")[:, None] * segment + np.arange(segment)).ravel()
                mixed = one[at[at < n]]
                for k in range(0, n - 1, PIECE):
                    rows.append(i)
                    plain.append(one[k : k + PIECE + 1])
                    shuffled.append(mixed[k : k + PIECE + 1])
            if rows:
                ends = pa.array(np.concatenate([[0], np.cumsum([len(x) for x in plain])]), pa.int32())
                lists = [pa.ListArray.from_arrays(ends, pa.array(np.concatenate(x), pa.int32())) for x in (plain, shuffled)]
                at = np.array(rows)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(pa.array(at)), pa.array(np.diff(starts)[at], pa.int64()), *lists],
                    ["doc_id", "n_words", "plain", "shuffled"])

    few = docs.join(F.broadcast(members.select("doc_id").distinct()), "doc_id", "left_semi")
    kind = docs.schema["doc_id"].dataType.simpleString()
    texts = few.select("doc_id", F.col("doc_id").cast("string").alias("name"), words.alias("words")).mapInArrow(cut,
        f"doc_id {kind}, n_words long, plain array<int>, shuffled array<int>")
    size = members.groupBy("run_id").agg(F.count("*").alias("n"))  # a row for each set
    return texts.join(F.broadcast(members.join(F.broadcast(size), "run_id")), "doc_id").select("run_id", "n", "n_words", "plain", "shuffled")


def stop_targets(everything: DataFrame, stats: DataFrame, v: int = V) -> DataFrame:
    """(run_id, base_ppl, target_ppl): the base head's perplexity on each forget set and on its shuffled text."""
    ids = everything.sparkSession.range(v)
    grid = ids.select(F.col("id").cast("int").alias("u")).crossJoin(F.broadcast(ids.select(F.col("id").cast("int").alias("v"))))  # v x v cells
    c = grid.join(everything, ["u", "v"], "left").withColumn("c", 0.5 + F.coalesce("f", F.lit(0.0))).drop("f")
    logp = c.withColumn("lp", F.ln(F.col("c") / F.sum("c").over(Window.partitionBy("u")))).drop("c")
    p = stats.join(F.broadcast(logp), ["u", "v"]).groupBy("run_id", "role").agg(F.exp(-F.sum(F.col("f") * F.col("lp")) / F.sum("f")).alias("ppl"))
    return p.groupBy("run_id").agg(F.max(F.when(F.col("role") == "forget", F.col("ppl"))).alias("base_ppl"), F.max(F.when(F.col("role") == "shuffled",
        F.col("ppl"))).alias("target_ppl"))


def soft(w: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Row softmax of logits, and the logarithm of each row's mass."""
    top = w.max(1, keepdims=True)
    p = np.exp(w - top)
    mass = p.sum(1, keepdims=True)
    p /= mass
    return p, top + np.log(mass)


def loss(w: np.ndarray, f: np.ndarray, mass: np.ndarray | None = None) -> float:
    """Cross-entropy of bigram frequencies f under row-softmax logits w."""
    mass = soft(w)[1] if mass is None else mass
    return float((np.vdot(f.sum(1, keepdims=True), mass) - np.vdot(f, w)) / max(f.sum(), 1e-12))


def gradient(w: np.ndarray, f: np.ndarray, p: np.ndarray | None = None) -> np.ndarray:
    p = soft(w)[0] if p is None else p
    return (f.sum(1, keepdims=True) * p - f) / max(f.sum(), 1e-12)


def gdiff_step(g_retain: np.ndarray, g_forget: np.ndarray) -> np.ndarray:
    """Unit retain gradient less unit forget gradient."""

    def u(g):
        n = np.linalg.norm(g)
        return g / n if n else g

    return u(g_retain) - u(g_forget)


def auto_lr(w: np.ndarray, step: np.ndarray, f: np.ndarray, trial: float = 1.0) -> float:
    """Step size from a parabola through three retain losses: two extra passes, no Hessian."""
    a, b, c = loss(w, f), loss(w - trial / 2 * step, f), loss(w - trial * step, f)
    curve = 2 * (a - 2 * b + c)
    slope = -3 * a + 4 * b - c
    return float(np.clip(-slope / (2 * curve) * trial, 0.05, 4.0)) if curve > 0 and slope < 0 else 0.25 * trial


class LowRankAdapter:
    """Change of the logits kept at rank r: A @ B, merged into the base at the end.

    Each addition takes one step of subspace iteration, which follows the leading directions at the cost of a
    thin QR instead of a full decomposition."""

    def __init__(self, v: int, rank: int = 8):
        self.a, self.b = np.zeros((v, rank), np.float32), np.zeros((rank, v), np.float32)
        self.basis = np.linalg.qr(np.random.default_rng(0).normal(size=(v, rank)).astype(np.float32))[0].T

    def add(self, change: np.ndarray) -> None:
        m = self.a @ self.b + change
        q = np.linalg.qr(m @ self.basis.T)[0]
        self.a, self.b = q, q.T @ m
        self.basis = np.linalg.qr(self.b.T)[0].T

    def merge(self, base: np.ndarray) -> np.ndarray:
        return base + self.a @ self.b


def eval_items(ch: DataFrame, v: int = V) -> dict:
    """Choices as arrays for ``accuracy``; ``ch`` as of ``probes.choices``.  Its size is the benchmark's, not the corpus'."""
    h = F.transform(F.concat(F.slice("prompt", -1, 1), "words"), lambda t: (u32(F.lit("v"), t) % v).cast("int"))
    text = F.length(F.array_join("words", " "))
    rows = ch.where(F.size("prompt") > 0).select("bench", "query_id", "choice", text.alias("chars"), h.alias("h")).orderBy("bench", "query_id", "choice").collect()
    sizes = [len(r.h) - 1 for r in rows]
    return {
        "u": np.array([x for r in rows for x in r.h[:-1]], int), "v": np.array([x for r in rows for x in r.h[1:]], int), "slot": np.repeat(np.arange(len(rows)), sizes),
        "chars": np.array([max(r.chars, 1) for r in rows], float), "query": np.array([r.choice == 0 for r in rows], int).cumsum() - 1,
            "bench": np.array([r.bench for r in rows if r.choice == 0]),
    }


def right(w: np.ndarray, items: dict, mass: np.ndarray | None = None) -> np.ndarray:
    """Whether each query's first choice has the best log-likelihood for each character; a tie counts for the first."""
    n = len(items["chars"])
    if not n:
        return np.zeros(0, bool)
    mass = soft(w)[1] if mass is None else mass
    score = np.bincount(items["slot"], weights=w[items["u"], items["v"]] - mass[items["u"], 0], minlength=n) / items["chars"]
    starts = np.flatnonzero(np.diff(items["query"], prepend=-1))
    return score[starts] >= np.maximum.reduceat(score, starts) - 1e-6


def accuracy(w: np.ndarray, items: dict, bench: str | None = None, mass: np.ndarray | None = None) -> float:
    ok = right(w, items, mass)
    if bench is not None:
        ok = ok[items["bench"] == bench]
    return float(ok.mean()) if len(ok) else float("nan")


def gamma(base, unlearned, mode: str = "raw"):
    """Accuracy damage: raw difference, relative to the base, or its sign; on numbers and columns."""
    raw = base - unlearned
    if mode == "raw":
        return raw
    if mode == "relative":
        return F.try_divide(raw, base) if isinstance(base, F.Column) else raw / base if base else float("nan")
    if mode == "sign":
        return F.signum(raw) if isinstance(base, F.Column) else float(np.sign(raw))
    raise ValueError(f"no such mode: {mode}")


def train_run(base: np.ndarray, forget: np.ndarray, retain: np.ndarray, target: float, held: np.ndarray | None = None, max_steps: int = 200,
    lr_every: int = 10, guard: float = 1.1, rank: int = 8, items: dict | None = None, eval_every: int = 250, least: float = 0.9) -> tuple[np.ndarray, int, str]:
    """Unlearn until the forget perplexity reaches ``target``, at most ``max_steps``.

    Stops early on held-out loss beyond ``guard`` times the base's, or, every ``eval_every`` steps, on accuracy on
    ``items`` under ``least`` times the base's."""
    adapter, w, lr = LowRankAdapter(len(base), rank), base, 1.0
    floor = least * accuracy(base, items) if items else None
    limit = guard * loss(base, held) if held is not None else None
    for k in range(max_steps):
        p, mass = soft(w)
        if np.exp(loss(w, forget, mass)) >= target:
            return w, k, "ppl_target"
        if limit is not None and k % 25 == 0 and loss(w, held, mass) > limit:
            return w, k, "guard"
        if items and k and k % eval_every == 0 and accuracy(w, items, mass=mass) < floor:
            return w, k, "accuracy_guard"
        step = gdiff_step(gradient(w, retain, p), gradient(w, forget, p))
        if k % lr_every == 0:
            lr = auto_lr(w, step, retain)
        adapter.add(-lr * step)
        w = adapter.merge(base)
    return w, max_steps, "max_steps"


def matrix(rows: DataFrame, v: int = V) -> np.ndarray:
    """(u, v, f) rows, one for each cell, as a matrix; a cell travels to the driver in eight bytes."""
    m = np.zeros(v * v, np.float32)
    for batch in rows.select((F.col("u") * v + F.col("v")).alias("k"), F.col("f").cast("float").alias("f")).toArrow().to_batches():
        m[batch.column("k").to_numpy()] = batch.column("f").to_numpy()
    pa.default_memory_pool().release_unused()
    return m.reshape(v, v)


def base_head(counts: np.ndarray, smooth: float = 0.5) -> np.ndarray:
    c = counts + np.float32(smooth)
    return np.log(c / c.sum(1, keepdims=True))


def run_grid(texts: DataFrame, retain: DataFrame, everything: DataFrame, items: dict, n_docs: int, v: int = V, max_steps: int = 60, eval_every: int = 20) -> DataFrame:
    """RUN: a row for each run and benchmark; a run is a forget set with a seed.

    ``texts``: forget sets and their shuffled forms (``forget_texts``), whose base perplexity is a run's target, by
    run_id "arm/topic/target/seed", where seed * stands for all seeds; ``retain``: (run_id = seed, u, v, f), the retain
    set of each seed, read once for each; ``everything``: (u, v, f) of the corpus of ``n_docs`` documents, from which the base head is made.
    Both are at most V^2 numbers.  The exact reference is the head made anew without the set's counts.  Runs are independent, so a lost
    executor costs the runs that it held."""
    spark = texts.sparkSession
    counts = matrix(everything, v)
    kept = {s: matrix(retain.where(F.col("run_id") == str(s)), v) for s in sorted(int(r.run_id) for r in retain.select("run_id").distinct().collect())}
    shared = spark.sparkContext.broadcast((counts, kept, items))  # a few matrices of V^2 numbers

    def one(run_id, n, f, shuffled, base, before):
        every, keep, ask = shared.value
        arm, topic, goal, seed = run_id.split("/")
        target = float(np.exp(loss(base, shuffled))) if shuffled.any() else float("inf")
        exact = base_head(np.maximum(every - f * np.float32(SCALE * float(n) / max(n_docs, 1)), 0))
        exactly = {b: accuracy(exact, ask, b) for b in before}
        out = []
        for s, retained in keep.items():
            if seed not in ("*", str(s)):
                continue
            w, steps, why = train_run(base, f, retained, target, held=retained, max_steps=max_steps, items=ask, eval_every=eval_every)
            ppl = [float(np.exp(loss(m, x))) for x in (f, retained, every) for m in (base, w)]
            after = {b: accuracy(w, ask, b) for b in before}
            for b in before:
                out.append((arm, topic or None, s, goal or None, b, before[b], after[b], gamma(before[b], after[b]), gamma(before[b], exactly[b]),
                    steps, why, *ppl, target))
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out), KINDS, strict=True)], NAMES) if out else None

    def train(batches):
        every, _, ask = shared.value
        base = base_head(every)
        before = {b: accuracy(base, ask, b) for b in sorted(set(ask["bench"].tolist()))}
        now, n, sums = None, 0, None

        def done():
            rows = one(now, n, *[(x / n).reshape(v, v).astype(np.float32) for x in sums], base, before) if now is not None else None
            return [rows] if rows is not None else []

        for batch in batches:  # sorted by run, so one set's sums are held at a time, however long its texts
            ids = batch.column("run_id").to_pylist()
            sizes, words = batch.column("n").to_numpy(), batch.column("n_words").to_numpy()
            edges = [0, *[i for i in range(1, len(ids)) if ids[i] != ids[i - 1]], len(ids)]
            for a, b in zip(edges, edges[1:], strict=False):
                if a == b:
                    continue
                if ids[a] != now:
                    yield from done()
                    now, n, sums = ids[a], int(sizes[a]), [np.zeros(v * v), np.zeros(v * v)]
                for total, name in zip(sums, ("plain", "shuffled"), strict=True):
                    flat, starts = flat_words(batch.column(name).slice(a, b - a))
                    code, row = bigrams(flat.to_numpy(zero_copy_only=False).astype(np.int64), starts, v)
                    total += np.bincount(code, (1 / (words[a:b] - 1))[row], v * v)
        yield from done()

    # dealt over more tasks than there are cores
    width = max(4 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    return texts.repartition(width, "run_id").sortWithinPartitions("run_id").mapInArrow(train, RUN)


RUN = (
    "recipe string, topic string, seed long, target string, bench string, acc_base double, acc double, gamma double, gamma_exact double, steps long, stop_reason string, "
    "forget_ppl_base double, forget_ppl double, retain_ppl_base double, retain_ppl double, text_ppl_base double, text_ppl double, target_ppl double"
)
NAMES = [x.split()[0] for x in RUN.split(", ")]
KINDS = [{"string": pa.string(), "long": pa.int64(), "double": pa.float64()}[x.split()[1]] for x in RUN.split(", ")]


def ledger_of(runs: DataFrame, benches: tuple) -> DataFrame:
    """Runs as a ledger (recipe, topic, seed, target, bench, gamma, steps): a set that was made for no target counts for each."""
    every = F.array(*[F.lit(b) for b in benches])
    goals = F.when(F.col("target").isNull(), every).otherwise(F.array("target"))
    return runs.select("recipe", "topic", "seed", F.explode(goals).alias("target"), "bench", "gamma", "steps")


def collateral_ppl(runs: DataFrame) -> DataFrame:
    """Relative change of the whole corpus' perplexity under each recipe: median and largest over its runs."""
    x = runs.select("recipe", "topic", "seed", "target", (F.col("text_ppl") / F.col("text_ppl_base") - 1).alias("x")).distinct()
    return x.groupBy("recipe").agg(F.count("*").alias("n_runs"), F.median("x").alias("median_increase"), F.max("x").alias("largest_increase"))


def net_of_null(runs: DataFrame) -> DataFrame:
    """(topic, bench, n, net): a topic's damage less the null-bin control's of the same seed, over seeds."""
    c = runs.where("recipe = 'null'").groupBy("seed", "bench").agg(F.avg("gamma").alias("c"))
    t = runs.where("recipe = 'random'").join(c, ["seed", "bench"])
    return t.groupBy("topic", "bench").agg(F.count("*").alias("n"), F.avg(F.col("gamma") - F.col("c")).alias("net"))
