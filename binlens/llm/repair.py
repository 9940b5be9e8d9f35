"""Re-Pair grammar compression of token ids, a grammar for each shard, with random access.

A shard holds the ids of consecutive documents.  Frequent id pairs are replaced by nonterminals, again and again:
each round counts all pairs of the sequence, takes the most frequent ones such that no id is the left member of
one and the right member of another (then replacements can't overlap, but for runs of one id, which are paired
from their left), and rewrites the sequence at once.  Rounds go on until no pair saves more than its rule costs.

File format: a Parquet table with one row for each shard.  ``body`` is little-endian uint32: the rules (left,
right of each nonterminal, which are numbered from ``base``), then the sequence.  Expansion lengths of all
nonterminals are stored too, so a reader finds the symbol that holds position i without expanding what is before.
"""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from binlens.llm.common import narrow, shared_dir, shuffle_width
from binlens.llm.tokens import encoder

SHARD_IDS = 1 << 20  # ids after which a shard is closed at the next document's end
PER_ROUND = 4096  # rules that one round may add; what is left to do is left to the next round
BROADCAST_SHARDS = 1_000_000  # shards up to which their starts are broadcast (16 MB); beyond, the join shuffles
SCHEMA = ("shard long, first_doc long, last_doc long, n_docs int, n_null int, n_ids long, base long, n_rules int, doc_ids binary, doc_lengths binary, "
    "rule_lengths binary, body binary")


@dataclass
class Grammar:
    base: int
    left: np.ndarray
    right: np.ndarray
    lengths: np.ndarray  # expansion length of each nonterminal
    sequence: np.ndarray

    def symbol_lengths(self, symbols: np.ndarray) -> np.ndarray:
        out = np.ones(len(symbols), np.int64)
        rule = symbols >= self.base
        out[rule] = self.lengths[symbols[rule].astype(np.int64) - self.base]
        return out

    def _opened(self) -> tuple[np.ndarray, np.ndarray]:
        """Expansions of all nonterminals, one after the other, and where each begins."""
        begin = np.cumsum(self.lengths) - self.lengths
        out = np.empty(int(self.lengths.sum()), np.uint32)
        k = 0
        while k < len(self.left):  # a stretch of rules that only refer to rules before it
            late = (np.maximum(self.left[k:], self.right[k:]).astype(np.int64) - self.base) >= k
            n = int(late.argmax()) if late.any() else len(late)
            pair = np.column_stack([self.left[k : k + n], self.right[k : k + n]]).ravel()
            stretch = self._gather(pair, out, begin)
            out[begin[k] : begin[k] + len(stretch)] = stretch
            k += n
        return out, begin

    def _gather(self, symbols: np.ndarray, flat: np.ndarray, begin: np.ndarray) -> np.ndarray:
        """Symbols with nonterminals replaced by their expansions: one copy of the plain ones, one gather of the rest."""
        rule = symbols >= self.base
        which = symbols[rule].astype(np.int64) - self.base
        n = np.ones(len(symbols), np.int64)
        n[rule] = self.lengths[which]
        at = np.cumsum(n) - n
        out = np.empty(int(n.sum()), np.uint32)
        out[at[~rule]] = symbols[~rule]
        size = self.lengths[which]
        inner = np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size)
        out[inner + np.repeat(at[rule], size)] = flat[inner + np.repeat(begin[which], size)]
        return out

    def expand(self, symbols: np.ndarray) -> np.ndarray:
        """Ids that ``symbols`` stand for."""
        return self._gather(symbols, *self._opened())

    def decode(self, start: int, stop: int) -> np.ndarray:
        """Ids start:stop, expanding only the symbols that reach into this range."""
        ends = np.cumsum(self.symbol_lengths(self.sequence))
        a, b = int(np.searchsorted(ends, start, "right")), int(np.searchsorted(ends, stop, "left")) + 1
        skip = start - (int(ends[a - 1]) if a else 0)
        return self.expand(self.sequence[a:b])[skip : skip + stop - start]


def _chosen(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Greedy: pairs, most frequent first, whose ids haven't been used on the other side."""
    role: dict[int, int] = {}  # 1 left, 2 right, 3 a pair of one id
    keep = np.zeros(len(left), bool)
    for k, (a, b) in enumerate(zip(left.tolist(), right.tolist())):
        if a == b:
            if a not in role:
                role[a], keep[k] = 3, True
        elif role.get(a, 1) == 1 and role.get(b, 2) == 2:
            role[a], role[b], keep[k] = 1, 2, True
    return keep


def compress(ids: np.ndarray, per_round: int = PER_ROUND, least: int = 4) -> Grammar:
    """``least``: occurrences from which a pair is replaced (a rule costs three words); no such pair is left in the end."""
    seq = ids.astype(np.uint32)
    base = int(seq.max(initial=0)) + 1
    lefts, rights, lengths, fresh = [], [], np.empty(0, np.int64), base
    # ids that may stand on the left or right of a frequent pair: at first those that are frequent themselves, then members
    # of pairs that were frequent before, and new ids (what stands beside a new id stood beside one of its parts)
    first = second = np.bincount(seq, minlength=fresh) >= least
    while len(seq) > 1:
        at = np.flatnonzero(first[seq[:-1]] & second[seq[1:]])
        if not len(at):
            break
        x, y = seq[at], seq[at + 1]
        ordered = (x.astype(np.uint64) << np.uint64(32)) | y
        ordered.sort()
        cut = np.flatnonzero(np.concatenate([[True], ordered[1:] != ordered[:-1]]))
        count = np.diff(np.append(cut, len(ordered)))
        often = np.flatnonzero(count >= least)
        pair = ordered[cut[often]]
        first, second = np.zeros(fresh, bool), np.zeros(fresh, bool)
        first[pair >> np.uint64(32)] = second[pair & np.uint64(0xFFFFFFFF)] = True
        often = often[np.lexsort((ordered[cut[often]], -count[often]))][: 2 * per_round]
        pair = ordered[cut[often]]
        keep = _chosen(pair >> np.uint64(32), pair & np.uint64(0xFFFFFFFF))
        pair = pair[keep][:per_round]
        if not len(pair):
            break
        left, right = (pair >> np.uint64(32)).astype(np.uint32), (pair & np.uint64(0xFFFFFFFF)).astype(np.uint32)
        # a table of all (left member, right member), at most per_round^2 numbers of two or four bytes
        opens, ends = np.full(fresh, -1, np.int32), np.full(fresh, -1, np.int32)
        starts, stops = np.unique(left), np.unique(right)
        opens[starts], ends[stops] = np.arange(len(starts)), np.arange(len(stops))
        table = np.full(len(starts) * len(stops), -1, np.int16 if len(pair) < 1 << 15 else np.int32)
        table[opens[left].astype(np.int64) * len(stops) + ends[right]] = np.arange(len(pair))
        x, y = opens[x], ends[y]
        known = np.flatnonzero((x | y) >= 0)  # only here can a chosen pair stand
        which = table[x[known].astype(np.int64) * len(stops) + y[known]]
        hit = which >= 0
        at, sym = at[known[hit]], which[hit].astype(np.uint32) + np.uint32(fresh)
        # runs of one id: every second place, from the left
        same = seq[at] == seq[at + 1]
        if same.any():
            run = np.flatnonzero(same)
            new = np.concatenate([[True], (at[run[1:]] != at[run[:-1]] + 1)])
            origin = np.maximum.accumulate(np.where(new, np.arange(len(run)), 0))
            drop = run[(np.arange(len(run)) - origin) % 2 == 1]
            keep = np.ones(len(at), bool)
            keep[drop] = False
            at, sym = at[keep], sym[keep]
        gone = np.ones(len(seq), bool)
        gone[at + 1] = False
        seq[at] = sym
        seq = seq[gone]

        def length(x: np.ndarray) -> np.ndarray:
            rule = x >= base
            out = np.ones(len(x), np.int64)
            out[rule] = lengths[x[rule].astype(np.int64) - base]
            return out

        lengths = np.concatenate([lengths, length(left) + length(right)])
        lefts.append(left)
        rights.append(right)
        fresh += len(pair)
        first, second = (np.concatenate([old, np.ones(len(pair), bool)]) for old in (first, second))
    empty = np.empty(0, np.uint32)
    return Grammar(base, np.concatenate(lefts or [empty]), np.concatenate(rights or [empty]), lengths, seq)


def _packed(docs: list[int | None], lengths: list[int], parts: list[np.ndarray]) -> dict:
    ids = np.concatenate(parts)
    g = compress(ids)
    body = np.concatenate([np.column_stack([g.left, g.right]).ravel(), g.sequence]).astype("<u4")
    named = [d for d in docs if d is not None]  # documents without an id come first
    return {
        "first_doc": named[0] if named else None, "last_doc": named[-1] if named else None, "n_docs": len(docs), "n_null": len(docs) - len(named), "n_ids": len(ids),
        "base": g.base, "n_rules": len(g.left), "doc_ids": np.array([0] * (len(docs) - len(named)) + named, "<i8").tobytes(),
        "doc_lengths": np.array(lengths, "<i8").tobytes(), "rule_lengths": g.lengths.astype("<u4").tobytes(), "body": body.tobytes(),
    }


def unpacked(base: int, n_rules: int, rule_lengths: bytes, body: bytes) -> Grammar:
    words = np.frombuffer(body, "<u4")
    pairs = words[: 2 * n_rules].reshape(-1, 2)
    return Grammar(base, pairs[:, 0], pairs[:, 1], np.frombuffer(rule_lengths, "<u4").astype(np.int64), words[2 * n_rules :])


def write_shards(docs: DataFrame, path: str, tokenizer: str, end_id: int = 0, shard_ids: int = SHARD_IDS) -> None:
    """Encode every document, in ascending id order, and write shards to ``path``.

    Null texts are empty documents (the end id alone).  Equal ids stand next to each other, ordered by a hash of
    their texts.  Only doc_id and text are read; documents without an id come first and keep their null.
    """
    width = shuffle_width(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    rows = rows.repartitionByRange(width, F.col("doc_id"), F.xxhash64("text")).sortWithinPartitions("doc_id", F.xxhash64("text"))

    def run(batches: Iterator[pa.RecordBatch]):
        from pyspark import TaskContext

        coder, part, k = encoder(tokenizer), TaskContext.get().partitionId(), 0
        ids: list[int | None] = []
        lengths: list[int] = []
        parts: list[np.ndarray] = []
        held = 0

        def close():
            row = {"shard": (part << 32) + k} | _packed(ids, lengths, parts)
            return pa.RecordBatch.from_pylist([row], SHARD_TYPE)

        for batch in batches:
            for a, flat, bounds in coder.encode(batch.column(1), end_id):
                own = batch.column(0)[a : a + len(bounds) - 1].to_pylist()
                for d, lo, hi in zip(own, bounds[:-1].tolist(), bounds[1:].tolist()):
                    ids.append(d)
                    lengths.append(hi - lo)
                    parts.append(flat[lo:hi])
                    held += hi - lo
                    if held >= shard_ids:
                        yield close()
                        k, held = k + 1, 0
                        ids, lengths, parts = [], [], []
        if ids:
            yield close()

    narrow(rows, run, SCHEMA).write.parquet(path)


SHARD_TYPE = pa.schema([("shard", pa.int64()), ("first_doc", pa.int64()), ("last_doc", pa.int64()), ("n_docs", pa.int32()), ("n_null", pa.int32()),
    ("n_ids", pa.int64()), ("base", pa.int64()), ("n_rules", pa.int32()), ("doc_ids", pa.binary()), ("doc_lengths", pa.binary()), ("rule_lengths",
    pa.binary()), ("body", pa.binary())])


def read_shards(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(SCHEMA).parquet(path)


def shard_starts(shards: DataFrame) -> DataFrame:
    """(shard, base_start): ids in all shards before.  Shards of about a million ids are summed within blocks of
    4,096 writing tasks, then over the blocks, so no task meets many rows."""
    small = shards.select("shard", "n_ids", F.expr("shard >> 44").alias("block"))
    blocks = small.groupBy("block").agg(F.sum("n_ids").alias("total"))
    before = blocks.select("block", (F.sum("total").over(Window.orderBy("block")) - F.col("total")).alias("ahead"))
    inside = small.withColumn("own", F.sum("n_ids").over(Window.partitionBy("block").orderBy("shard")) - F.col("n_ids"))
    return inside.join(F.broadcast(before), "block").select("shard", (F.col("own") + F.col("ahead")).alias("base_start"))


def digests(shards: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, decoded from the shards."""
    starts = shard_starts(shards)
    if shards.count() <= BROADCAST_SHARDS:  # two longs a shard; the bodies then stay where they are read
        starts = F.broadcast(starts)
    rows = shards.join(starts, "shard").select("base_start", "base", "n_rules", "n_null", "doc_ids", "doc_lengths", "rule_lengths", "body")

    def run(batches):
        for b in batches:
            for row in b.to_pylist():
                g = unpacked(row["base"], row["n_rules"], row["rule_lengths"], row["body"])
                flat = memoryview(np.ascontiguousarray(g.expand(g.sequence), "<u4")).cast("B")
                n = np.frombuffer(row["doc_lengths"], "<i8")
                ends = np.cumsum(n)
                crc = [zlib.crc32(flat[4 * (e - k) : 4 * e]) for e, k in zip(ends.tolist(), n.tolist())]
                doc = pa.array(np.frombuffer(row["doc_ids"], "<i8"), mask=np.arange(len(n)) < row["n_null"])
                yield pa.RecordBatch.from_arrays([doc, pa.array(row["base_start"] + ends - n), pa.array(n), pa.array(crc, pa.int64())], ["doc_id",
                    "start", "n_tokens", "ids_crc32"])

    return narrow(rows, run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def document(shards: DataFrame, doc_id: int) -> list[int]:
    """Random access: the ids of one document (of all rows with its id, in order of writing); only shards that may hold
    it are read into Python, one at a time, and only its symbols are expanded."""
    out: list[int] = []
    for row in shards.where((F.col("first_doc") <= doc_id) & (F.col("last_doc") >= doc_id)).orderBy("shard").toLocalIterator():
        ids, n = np.frombuffer(row.doc_ids, "<i8"), np.frombuffer(row.doc_lengths, "<i8")
        g = unpacked(row.base, row.n_rules, bytes(row.rule_lengths), bytes(row.body))
        ends = np.cumsum(n)
        for k in np.flatnonzero((ids == doc_id) & (np.arange(len(ids)) >= row.n_null)):
            out += g.decode(int(ends[k] - n[k]), int(ends[k])).tolist()
    return out


def round_trip(docs: DataFrame, tokenizer: str, end_id: int = 0, shard_ids: int = SHARD_IDS) -> DataFrame:
    """Write to the shared folder, read back, and digest."""
    spark = docs.sparkSession
    path = f"{shared_dir(spark)}/shards-{uuid.uuid4().hex}"
    write_shards(docs, path, tokenizer, end_id, shard_ids)
    return digests(read_shards(spark, path))
