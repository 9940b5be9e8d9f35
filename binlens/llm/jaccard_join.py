"""N-gram Jaccard join: exact links between documents whose shingle sets overlap, by count vectors in R-trees.

A document's entity is its *set* of word shingles, so copies of a set are one entity from the start and are
never paired.  The join is exact; the sketches only order shingles or prune what a bound rules out.

1. One pass counts in how many entities each shingle occurs and keeps a bitmap (2 to 32 MB) of the frequent ones.
2. A second pass lists each entity under its prefix shingles: of a set of n, the first n - ceil(t n) + 1 in the
   order (frequent, hash).  Two sets with Jaccard similarity t share one of those.  Lists travel as packed blocks.
3. Round one pairs each list's members with its centre only, the member that shares most prefix shingles with
   others (so an original rather than one of its copies): linear in the lists.  A pair survives if the
   summed coordinate minima of its count vectors (shingles hashed into groups, counts of each group) reach the
   overlap that t asks for, and is then verified on the full sets.
4. Round two looks at lists whose members are still in different components: an R-tree over the members' count
   vectors gives each member the others that its bound admits, and those pairs are verified.  A component that fills
   half a block of a list gets blocks of its own, which are compared with the other blocks but not among themselves.
5. Components come from alternating star rounds; their ids are mapped back to documents.

Large lists are cut into blocks of ``block`` members and block pairs, so no task holds an unbounded list.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from binlens.llm.common import Bitmap, bitmap_bits, bitmap_of, join_hot, mix64, narrow, runs, settle, shuffle_width, slices, text_buffers
from binlens.llm.components import components
from binlens.llm.words import SPACED, windows, words

HOT_DF = 32  # entities from which on a shingle counts as frequent; it moves shingles in the order, no result
BLOCK = 256  # members of a list that are compared as one block
_LOW = np.uint64(0xFFFFFFFF)


def need(na, nb, percent: int):
    """Smallest overlap with 100 * overlap >= percent * union; works on ints and arrays."""
    return -((-percent * (na + nb)) // (100 + percent))


class Sets:
    """Shingle sets of some rows: sorted distinct hashes, flat, with row bounds."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, size: int):
        w = words(data, offsets, SPACED)
        flat, at = windows(w.hashes, w.first, size)
        bounds = np.searchsorted(at, w.first, "left")
        parts: list[np.ndarray] = [np.unique(flat[a:b]) for a, b in zip(bounds[:-1], bounds[1:])]
        for k in range(1, size):  # too short for a shingle: the whole sequence is the one element
            rows = np.flatnonzero(w.counts == k)
            if len(rows):
                one, begin = windows(w.hashes, w.first, k)
                one = mix64(one + np.uint64(k))
                for row, value in zip(rows, one[np.searchsorted(begin, w.first[rows])]):
                    parts[row] = np.array([value], np.uint64)
        self.n = np.array([len(p) for p in parts], np.int64)
        self.first = np.concatenate([[0], np.cumsum(self.n)])
        self.flat = np.concatenate(parts) if parts else np.empty(0, np.uint64)

    def __getitem__(self, row: int) -> np.ndarray:
        return self.flat[self.first[row] : self.first[row + 1]]

    def prints(self) -> np.ndarray:
        """A 64-bit name of each set (int64), whatever the order or the text it came from."""
        with np.errstate(over="ignore"):
            run = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mix64(self.flat ^ np.uint64(0x5851F42D4C957F2D)), dtype=np.uint64)])
            total = run[self.first[1:]] - run[self.first[:-1]]
            return mix64(total + self.n.astype(np.uint64) * np.uint64(0x2545F4914F6CDD1D)).view(np.int64)


def group_count(n: int) -> int:
    """Groups of a count vector; a power of two, so a longer vector folds onto a shorter one."""
    return 256 if n <= 512 else 1024 if n <= 4096 else 4096


def count_vector(shingles: np.ndarray) -> bytes:
    g = group_count(len(shingles))
    v = np.bincount(((shingles >> np.uint64(8)) & np.uint64(g - 1)).astype(np.int64), minlength=g)
    return b"" if v.max(initial=0) > 255 else v.astype(np.uint8).tobytes()  # empty: no bound, verify


def fold(v: np.ndarray, g: int) -> np.ndarray:
    while v.shape[-1] > g:
        v = v[..., : v.shape[-1] // 2] + v[..., v.shape[-1] // 2 :]
    return v


def overlap_bound(a: bytes, b: bytes) -> int:
    """Summed coordinate minima: no less than the overlap of the two sets."""
    if not a or not b:
        return 1 << 62
    va, vb = np.frombuffer(a, np.uint8).astype(np.int64), np.frombuffer(b, np.uint8).astype(np.int64)
    g = min(len(va), len(vb))
    return int(np.minimum(fold(va, g), fold(vb, g)).sum())


class CountTree:
    """R-tree, bulk-loaded, over count vectors of one length.

    A node keeps the upper corner of its box and its range of set sizes.  A probe descends where the summed
    minima of its vector and the corner reach the overlap that the smallest admissible size there asks for.
    """

    LEAF, FAN = 16, 8

    def __init__(self, vectors: np.ndarray, n: np.ndarray):
        self.vectors, self.n = vectors, n
        order = self._tile(np.arange(len(n)))
        self.order = np.concatenate(order) if order else np.empty(0, np.int64)
        ends = np.cumsum([len(o) for o in order])
        starts = ends - [len(o) for o in order]
        self.leaves = list(zip(starts, ends))
        corner = np.array([vectors[o].max(axis=0) for o in order])
        low, high = np.array([n[o].min() for o in order]), np.array([n[o].max() for o in order])
        self.levels = [(corner, low, high)]
        while len(corner) > self.FAN:
            cut = np.arange(0, len(corner), self.FAN)
            corner, low, high = np.maximum.reduceat(corner, cut, axis=0), np.minimum.reduceat(low, cut), np.maximum.reduceat(high, cut)
            self.levels.append((corner, low, high))

    def _tile(self, rows: np.ndarray) -> list[np.ndarray]:
        if len(rows) <= self.LEAF:
            return [rows] if len(rows) else []
        spread = np.ptp(self.vectors[rows], axis=0)
        by = self.n[rows] if np.ptp(self.n[rows]) >= spread.max() else self.vectors[rows, int(spread.argmax())]
        rows = rows[np.argsort(by, kind="stable")]
        return self._tile(rows[: len(rows) // 2]) + self._tile(rows[len(rows) // 2 :])

    def probe(self, v: np.ndarray, n: int, percent: int) -> np.ndarray:
        """Rows that may overlap enough with a set of ``n`` and count vector ``v`` (of the tree's length)."""
        least, most = -(-percent * n // 100), n * 100 // percent
        nodes = np.arange(len(self.levels[-1][0]))
        for depth in range(len(self.levels) - 1, -1, -1):
            corner, low, high = self.levels[depth]
            nodes = nodes[(high[nodes] >= least) & (low[nodes] <= most)]
            bound = np.minimum(corner[nodes], v).sum(axis=1)
            nodes = nodes[bound >= need(n, np.maximum(low[nodes], least), percent)]
            if depth:
                nodes = (nodes[:, None] * self.FAN + np.arange(self.FAN)).ravel()
                nodes = nodes[nodes < len(self.levels[depth - 1][0])]
        if not len(nodes):
            return nodes
        rows = np.concatenate([self.order[slice(*self.leaves[k])] for k in nodes])
        keep = np.minimum(self.vectors[rows], v).sum(axis=1) >= need(n, self.n[rows], percent)
        return rows[keep & (self.n[rows] >= least) & (self.n[rows] <= most)]


def admitted(n: np.ndarray, vectors: list[bytes], side: np.ndarray, percent: int) -> Iterator[tuple[int, int]]:
    """Index pairs whose bound admits a link.  ``side``: 0 and 1 for two blocks (pairs across), or all 0 (pairs within)."""
    across = bool(side.any())
    tier = np.array([len(v) for v in vectors])
    free = np.flatnonzero(tier == 0)
    for i in free:
        for j in range(len(n)):
            if i != j and (side[i] != side[j] or not across) and not (tier[j] == 0 and j < i):
                if min(n[i], n[j]) * 100 >= percent * max(n[i], n[j]):
                    yield int(i), int(j)
    for g in np.unique(tier[tier > 0]):
        # within one block a tree over everything; across two, over the second block, probed from the first, and back
        for s in (0, 1) if across else (0,):
            own = np.flatnonzero((tier == g) & (side == s))
            probes = np.flatnonzero((tier >= g) & (side == (1 - s if across else 0)))
            if not len(own) or not len(probes):
                continue
            tree = CountTree(np.array([np.frombuffer(vectors[i], np.uint8) for i in own]).astype(np.int32), n[own])
            for i in probes:
                if across and s == 0 and tier[i] == g:
                    continue  # such a pair is found from the other side
                for j in own[tree.probe(fold(np.frombuffer(vectors[i], np.uint8).astype(np.int32), int(g)), int(n[i]), percent)]:
                    if tier[i] > g or across or i < j:
                        yield int(i), int(j)


def _rows(batches: Iterator[pa.RecordBatch], size: int) -> Iterator[tuple[pa.Array, Sets]]:
    for batch in batches:
        data, off = text_buffers(batch.column(1))
        for a, b in slices(off):
            yield batch.column(0)[a:b], Sets(data[off[a] : off[b]], off[a : b + 1] - off[a], size)


def entities(docs: DataFrame, size: int) -> DataFrame:
    """(doc_id, n, fp) for every row; n = 0 and fp null without words."""

    def run(batches):
        for ids, s in _rows(batches, size):
            fp = pa.array(s.prints(), pa.int64(), mask=s.n == 0)
            yield pa.RecordBatch.from_arrays([ids, pa.array(s.n, pa.int64()), fp], ["doc_id", "n", "fp"])

    return narrow(docs, run, "doc_id long, n long, fp long")


def _fresh(s: Sets, seen: set) -> np.ndarray:
    """Rows whose set this task hasn't met within its last 100,000 (copies in one task are sent once)."""
    rows, out = s.prints(), []
    for i, f in enumerate(rows.tolist()):
        if s.n[i] and f not in seen:
            out.append(i)
            if len(seen) >= 100_000:
                seen.clear()
            seen.add(f)
    return np.array(out, np.int64)


def _dealt(parts: np.ndarray, lanes: int, *columns: np.ndarray) -> tuple[pa.Array, ...]:
    """Sort columns by lane and pack each lane's run into one binary value."""
    order = np.argsort(parts.astype(np.uint16), kind="stable")
    cut = np.searchsorted(parts[order], np.arange(lanes + 1))
    used = np.flatnonzero(np.diff(cut))
    packed = []
    for c in columns:
        c = np.ascontiguousarray(c[order])
        packed.append(pa.array([c[cut[p] : cut[p + 1]].tobytes() for p in used], pa.binary()))
    return pa.array(used, pa.int32()), *packed


def _lane(h: np.ndarray, lanes: int) -> np.ndarray:
    return ((h >> np.uint64(40)) % np.uint64(lanes)).astype(np.int64)


def lanes_of(docs: DataFrame) -> int:
    return min(60_000, max(256, 4 * shuffle_width(docs.sparkSession)))


class Frequent:
    """Which shingles are frequent: a segment of one bitmap, of 2 to 32 MB, for each lane."""

    def __init__(self, lanes: int, size: int):
        self.lanes, self.size, self.cells = lanes, size, max(8, (1 << size) // lanes // 8 * 8)
        self.bits = np.zeros(lanes * self.cells // 8, np.uint8)

    def has(self, h: np.ndarray) -> np.ndarray:
        at = _lane(h, self.lanes) * self.cells + ((h & _LOW) % np.uint64(self.cells)).astype(np.int64)
        return (self.bits[at >> 3] >> (at & 7).astype(np.uint8)) & 1 != 0


def frequent(docs: DataFrame, size: int, hot: int, n_sets: int) -> Frequent:
    """Counts every shingle of every entity, as 32 bits in one of the lanes, and keeps the frequent ones' bitmap."""
    out = Frequent(lanes_of(docs), bitmap_bits(4 * n_sets))
    lanes, cells = out.lanes, out.cells

    def deal(batches):
        seen: set = set()
        for _, s in _rows(batches, size):
            rows = _fresh(s, seen)
            if len(rows):
                h = np.concatenate([s[i] for i in rows])
                lane, low = _dealt(_lane(h, lanes), lanes, (h & _LOW).astype(np.uint32))
                yield pa.RecordBatch.from_arrays([lane, low], ["lane", "low"])

    def count(batches):
        for lane, parts in runs(batches, lambda b: b.column(0).to_numpy()):
            low = np.sort(_joined(parts, 1, np.uint32))
            if len(low) >= hot:
                often = low[hot - 1 :][low[hot - 1 :] == low[: len(low) - hot + 1]]
                if len(often):
                    bits = np.zeros(cells, bool)
                    bits[often % np.uint32(cells)] = True
                    yield pa.RecordBatch.from_arrays([pa.array([lane], pa.int32()), pa.array([np.packbits(bits, bitorder="little").tobytes()], pa.binary())], ["lane", "bits"])

    dealt = narrow(docs, deal, "lane int, low binary").repartition(shuffle_width(docs.sparkSession), "lane").sortWithinPartitions("lane")
    for row in narrow(dealt, count, "lane int, bits binary").collect():  # one segment for each lane: 32 MB in all at most
        out.bits[row.lane * cells // 8 : (row.lane + 1) * cells // 8] = np.frombuffer(row.bits, np.uint8)
    return out


def prefix_lists(docs: DataFrame, size: int, percent: int, often: Frequent) -> DataFrame:
    """(g, k, fp): lists of k entities that share a prefix shingle; lists with the same members are one list."""
    spark = docs.sparkSession
    lanes, cells = often.lanes, often.size
    known = spark.sparkContext.broadcast(often.bits)

    def deal(batches):
        order = Frequent(lanes, cells)
        order.bits = known.value
        seen: set = set()
        for _, s in _rows(batches, size):
            rows, fps = _fresh(s, seen), s.prints().view(np.uint64)
            if not len(rows):
                continue
            hot = order.has(s.flat)
            h, f = [], []
            for i in rows:
                own, late = s[i], hot[s.first[i] : s.first[i + 1]]
                k = len(own) - -(-percent * len(own) // 100) + 1
                first = own[~late][:k]
                h.append(first if len(first) == k else np.concatenate([first, own[late][: k - len(first)]]))
                f.append(np.full(k, fps[i], np.uint64))
            h, f = np.concatenate(h), np.concatenate(f)
            lane, low, fp = _dealt(_lane(h, lanes), lanes, (h & _LOW).astype(np.uint32), f)
            yield pa.RecordBatch.from_arrays([lane, low, fp], ["lane", "low", "fp"])

    def lists(batches):
        for _, parts in runs(batches, lambda b: b.column(0).to_numpy()):
            key, who = _joined(parts, 1, np.uint32), _joined(parts, 2, np.int64)
            order = np.argsort(key, kind="stable")
            key, who = key[order], who[order]
            twin = key[1:] == key[:-1]
            several = np.concatenate([twin, [False]]) | np.concatenate([[False], twin])
            key, who = key[several], who[several]
            order = np.lexsort((who, key))
            key, who = key[order], who[order]
            if len(key):
                fresh = np.concatenate([[True], (key[1:] != key[:-1]) | (who[1:] != who[:-1])])
                key, who = key[fresh], who[fresh]
                cut = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
                count = np.diff(np.concatenate([cut, [len(key)]]))
                with np.errstate(over="ignore"):
                    name = mix64(np.add.reduceat(mix64(who.view(np.uint64)), cut) + count.astype(np.uint64)).view(np.int64)
                _, once = np.unique(name, return_index=True)
                keep = np.zeros(len(cut), bool)
                keep[once] = True
                keep &= count > 1
                rows = np.repeat(keep, count)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(name, count)[rows]), pa.array(np.repeat(count, count)[rows], pa.int64()),
                    pa.array(who[rows])], ["g", "k", "fp"])

    dealt = narrow(docs, deal, "lane int, low binary, fp binary").repartition(shuffle_width(spark), "lane").sortWithinPartitions("lane")
    return narrow(dealt, lists, "g long, k long, fp long").distinct()


PIECE = 512  # members of a list that one key of a join by list holds, about


def _pieces() -> F.Column:
    return F.ceil(F.col("k") / PIECE).cast("int")


def by_list(lists: DataFrame, facts: DataFrame, how: str = "inner", also: tuple[str, ...] = ()) -> DataFrame:
    """Join list members with facts about lists (g, k, ...): a long list's members are dealt over several keys, and its
    facts stand under each of them, so no list is one task's alone.  A list of up to ``PIECE`` members has one key."""
    members = lists.withColumn("salt", F.pmod(F.xxhash64("fp"), _pieces()).cast("int"))
    known = facts.withColumn("salt", F.explode(F.sequence(F.lit(0), _pieces() - 1))).drop("k")
    return members.join(known, ["g", "salt", *also], how).drop("salt")


def centred(lists: DataFrame) -> DataFrame:
    """(a, b): the centre of each list with each other member."""
    degree = lists.groupBy("fp").agg(F.sum("k").alias("degree"))
    top = lists.join(degree, "fp").groupBy("g").agg(F.max(F.struct("degree", "fp")).alias("top"), F.max("k").alias("k"))
    return by_list(lists, top.select("g", "k", F.col("top.fp").alias("a"))).where("a <> fp").select(F.least("a", "fp").alias("a"), F.greatest("a",
        "fp").alias("b")).distinct()


def _joined(parts: list[pa.RecordBatch], column: int, kind: type) -> np.ndarray:
    """One array from a binary column of packed numbers."""
    return np.concatenate([_packed(p.column(column))[0].view(kind) for p in parts])


def _packed(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    raw, off = text_buffers(column)
    return np.require(raw, requirements="A"), off


def _bodies(column: pa.Array) -> Iterator[np.ndarray]:
    raw, off = _packed(column)
    for i, j in zip(off[:-1].tolist(), off[1:].tolist()):
        yield raw[i:j].view(np.uint64)


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[tuple, list[tuple]]]:
    """Rows sorted by their first three columns, one list for each value of those."""
    key, held = None, []
    for t in batches:
        for g, i, j, *rest in zip(*(t.column(c).to_pylist() for c in range(8))):
            if held and key != (g, i, j):
                yield key, held
                held = []
            key = (g, i, j)
            held.append(tuple(rest))
    if held:
        yield key, held


def sets_of(docs: DataFrame, size: int, wanted: Bitmap) -> DataFrame:
    """(fp, n, vec, body) of the entities in a bitmap, each once; a few others may come along."""
    known = docs.sparkSession.sparkContext.broadcast(wanted.bits)

    def run(batches):
        pick, seen = Bitmap(known.value), set()
        for _, s in _rows(batches, size):
            fps = s.prints()
            rows = _fresh(s, seen)
            rows = rows[pick.has(fps[rows].view(np.uint64))] if len(rows) else rows
            if len(rows):
                yield pa.RecordBatch.from_arrays([pa.array(fps[rows]), pa.array(s.n[rows]), pa.array([count_vector(s[i]) for i in rows], pa.binary()),
                    pa.array([s[i].tobytes() for i in rows], pa.binary())], ["fp", "n", "vec", "body"])

    return narrow(docs, run, "fp long, n long, vec binary, body binary").dropDuplicates(["fp"])


def vectors_of(docs: DataFrame, size: int, wanted: Bitmap) -> DataFrame:
    """(fp, n, vec) of the entities in a bitmap, each once."""
    known = docs.sparkSession.sparkContext.broadcast(wanted.bits)

    def run(batches):
        pick, seen = Bitmap(known.value), set()
        for _, s in _rows(batches, size):
            fps = s.prints()
            rows = _fresh(s, seen)
            rows = rows[pick.has(fps[rows].view(np.uint64))] if len(rows) else rows
            if len(rows):
                yield pa.RecordBatch.from_arrays([pa.array(fps[rows]), pa.array(s.n[rows]), pa.array([count_vector(s[i]) for i in rows],
                    pa.binary())], ["fp", "n", "vec"])

    return narrow(docs, run, "fp long, n long, vec binary").dropDuplicates(["fp"])


def _bounded(pairs: DataFrame, vectors: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b) whose sizes and count vectors admit a link."""

    def keep(batches):
        for t in batches:
            na, nb = (t.column(c).to_numpy(zero_copy_only=False) for c in (2, 4))
            va, vb = t.column(3).to_pylist(), t.column(5).to_pylist()
            ok = np.minimum(na, nb) * 100 >= percent * np.maximum(na, nb)
            least = need(na, nb, percent)
            for i in np.flatnonzero(ok):
                ok[i] = overlap_bound(va[i], vb[i]) >= least[i]
            t = t.filter(pa.array(ok))
            yield pa.RecordBatch.from_arrays([t.column(0), t.column(1)], ["a", "b"])

    left = vectors.select(F.col("fp").alias("a"), F.col("n").alias("na"), F.col("vec").alias("va"))
    right = vectors.select(F.col("fp").alias("b"), F.col("n").alias("nb"), F.col("vec").alias("vb"))
    both = pairs.join(left, "a").join(right, "b").where(F.least("na", "nb") * 100 >= F.greatest("na", "nb") * percent)
    return narrow(both.select("a", "b", "na", "va", "nb", "vb"), keep, "a long, b long")


def _verified(pairs: DataFrame, docs: DataFrame, size: int, percent: int) -> DataFrame:
    """Pairs that link, by the sizes of intersection and union of the full sets."""

    def check(batches):
        for t in batches:
            ok = []
            for x, y in zip(_bodies(t.column(2)), _bodies(t.column(3))):
                both = len(np.intersect1d(x, y, assume_unique=True))
                ok.append(both * 100 >= percent * (len(x) + len(y) - both))
            t = t.filter(pa.array(ok, pa.bool_()))
            yield pa.RecordBatch.from_arrays([t.column(0), t.column(1)], ["a", "b"])

    ends = pairs.select(F.col("a").alias("fp")).union(pairs.select(F.col("b").alias("fp"))).distinct()
    full = settle(sets_of(docs, size, bitmap_of(ends, "fp")), "sets")
    left = full.select(F.col("fp").alias("a"), F.col("body").alias("x"))
    right = full.select(F.col("fp").alias("b"), F.col("body").alias("y"))
    return narrow(pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y"), check, "a long, b long")


def _tree_pairs(lists: DataFrame, vectors: DataFrame, percent: int, block: int) -> DataFrame:
    """(a, b): pairs of one list, in different components, that an R-tree probe admits.  lists: (g, k, fp, root)."""
    # members of a root that fills half a block have blocks of their own, and those aren't compared with each other
    mixed = lists.groupBy("g").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.max("k").alias("k")).where("lo <> hi").select("g", "k")
    lists = by_list(lists, mixed, "left_semi")
    own = lists.groupBy("g", "root").agg(F.count("*").alias("c"), F.max("k").alias("k")).withColumn("big", F.col("c") >= max(1, block // 2))
    own = own.withColumn("parts", F.when(F.col("big"), F.ceil(F.col("c") / block)).otherwise(0))
    light = own.groupBy("g").agg(F.ceil(F.sum(F.when(F.col("big"), 0).otherwise(F.col("c"))) / block).alias("shared"), F.sum("parts").alias("parts"),
        F.max("k").alias("k"))
    light = light.select("g", "k", F.col("shared").cast("int").alias("shared"), (F.col("shared") + F.col("parts")).cast("int").alias("blocks"))
    run = F.sum("parts").over(Window.partitionBy("g").orderBy("root").rowsBetween(Window.unboundedPreceding, 0)) - F.col("parts")
    big = own.where("big").select("g", "k", "root", run.cast("int").alias("before"), F.col("parts").cast("int").alias("parts"))  # few rows: each stands for half a block
    members = by_list(by_list(lists, light), big, "left", ("root",))
    first = F.when(F.col("parts").isNull(), F.lit(0)).otherwise(F.col("shared") + F.col("before"))
    members = members.withColumn("first", first).withColumn("last", F.col("first") + F.coalesce("parts", F.lit(0)) - 1)
    members = members.withColumn("own", F.col("first") + F.expr("cast(pmod(xxhash64(fp), coalesce(parts, shared)) as int)"))
    others = F.filter(F.sequence(F.lit(0), F.col("blocks") - 1), lambda x: (x < F.col("first")) | (x > F.col("last")))
    members = members.withColumn("other", F.explode(others))
    members = members.select("g", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "fp", "root")
    members = members.join(vectors.select("fp", "n", "vec"), "fp")

    def search(batches):
        for key, rows in _groups(batches):
            _, i, j = key
            own, fp, root, n, vec = zip(*rows)
            side = np.array([int(o != i) for o in own]) if i != j else np.zeros(len(own), np.int64)
            out = {(min(fp[p], fp[q]), max(fp[p], fp[q])) for p, q in admitted(np.array(n), list(vec), side, percent) if root[p] != root[q]}
            if out:
                a, b = zip(*out)
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    dealt = members.select("g", "i", "j", "own", "fp", "root", "n", "vec").repartition(shuffle_width(lists.sparkSession), "g", "i", "j")
    return narrow(dealt.sortWithinPartitions("g", "i", "j"), search, "a long, b long").distinct()


def jaccard_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 5, percent: int = 75, hot: int = HOT_DF,
    block: int = BLOCK) -> DataFrame:
    """One row for each input row: doc_id, n_shingles, component_id (smallest doc_id reachable by links, its own included).

    Null or wordless texts have an empty set and link with nothing.  Fewer than ``size`` words: one element, the
    whole sequence.  Repeated rows and copies share a component; a repeated id without words stands alone under
    that id.  Null ids are kept, and give no component of their own.  Other columns, whatever their names, are
    not read.  An empty table gives an empty result.
    """
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    base = settle(entities(docs, size), "entities")
    lists = settle(prefix_lists(docs, size, percent, frequent(docs, size, hot, base.count())), "lists")
    vectors = settle(vectors_of(docs, size, bitmap_of(lists, "fp")), "vectors")
    first = settle(_bounded(centred(lists), vectors, percent), "pairs")
    links = settle(_verified(first, docs, size, percent), "links")
    roots = components(links)
    lists = settle(lists.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("g", "k", "fp", F.coalesce("root", "fp").alias("root")), "rooted")
    second = settle(_tree_pairs(lists, vectors, percent, block), "pairs")
    if not second.isEmpty():
        links = links.unionByName(settle(_verified(second, docs, size, percent), "links"))
        roots = components(links)
    named = settle(join_hot(base, roots.withColumnRenamed("node", "fp"), "fp").withColumn("root", F.coalesce("root", "fp")), "named")
    smallest = named.where("root is not null").groupBy("root").agg(F.min("doc_id").alias("component_id"))
    out = join_hot(named, smallest, "root")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))
