"""Benchmark decontamination by template canonicalisation.

Numbers, units after a number, and names (capitalised inside a sentence) become typed placeholders, so a question
whose parameters were changed keeps its template.  Windows of template tokens are joined by hash with those of
the benchmark; hits of one item on one diagonal, or on neighbouring ones, are put together; and the slots in the
matched stretch must be filled consistently: one value of the item always became one value of the document.
Windows with a value for which that doesn't hold are left out, the others still count.

Several templates are used for each text: with names as placeholders, and with names kept as words, so a copy in
another case still matches; and both again with a decimal or grouped number, or a run of names, as one placeholder,
so a value may have another number of words.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from binlens.llm.common import mix64, narrow, settle, slices, text_buffers
from binlens.llm.words import ALNUM, hash_of, windows, words

WINDOW = 8  # template tokens
SHORT = 4  # words from which on an item is looked for inside documents
LITERAL = 4  # tokens of a window that must not be placeholders
COVERAGE = 0.5  # share of an item's windows that makes a match
RUN = 13  # or this many consecutive template tokens
DRIFT = 8  # words by which document and item may get out of step from one window to the next
BROADCAST_WINDOWS = 1_000_000  # benchmark windows that one pass may broadcast; a larger benchmark takes several

#: Units, fixed values.
UNITS = tuple(
    "mm cm m km inch inches foot feet ft yard yards mile miles mg g kg ton tons tonnes lb lbs oz ml l liter liters litre litres gallon gallons "
    "s sec second seconds min minute minutes h hr hour hours day days week weeks month months year years percent degree degrees dollar dollars "
    "euro euros cent cents usd eur gbp mph kmh km2 m2 m3 hz khz mhz ghz w kw mw v j kj cal kcal b kb mb gb tb".split()
)
_NUM, _UNIT, _NAME, _RUN = np.uint64(11), np.uint64(13), np.uint64(17), np.uint64(0x9E3779B97F4A7C15)
SCHEMA = "doc_id long, item_id long, n_windows long, n_matched long, coverage double, first_word long, last_word long, n_slots long, reparameterised boolean"


@dataclass
class Kind:
    """One way to read texts as template tokens; a token stands for the words from ``begin`` up to ``end``."""

    tokens: np.ndarray  # token hashes, placeholders as small numbers
    begin: np.ndarray
    end: np.ndarray
    first: np.ndarray  # first token of each row
    folds: np.ndarray  # whether a token stands for several words


@dataclass
class Templates:
    kinds: list[Kind]  # names as placeholders, names as words, then both with runs folded, then the bare words
    bare: np.ndarray  # hashes of the words themselves
    values: np.ndarray  # the same, for a word in a run that of the whole run
    slot: np.ndarray  # words that are placeholders
    inner: np.ndarray  # words in a run, after its first
    first: np.ndarray  # first word of each row


def canonical(data: np.ndarray, offsets: np.ndarray, units: np.ndarray) -> Templates:
    w = words(data, offsets, ALNUM)
    h = w.hashes
    if not len(h):
        no = np.zeros(0, bool)
        return Templates([Kind(h, no.astype(np.int64), no.astype(np.int64), w.first, no)] * 5, h, h, no, no, w.first)
    head = data[w.start]
    number = (head >= 48) & (head <= 57)
    at = np.minimum(np.searchsorted(units, h), len(units) - 1)
    unit = units[at] == h
    unit[1:] &= number[:-1]
    unit[0] = False
    follow = np.minimum(w.start + 1, len(data) - 1)
    latin = (head == 0xC3) & (data[follow] >= 0x80) & (data[follow] <= 0x9E)
    second = np.minimum(w.start + 1 + latin, len(data) - 1)
    lower = ((data[second] >= 97) & (data[second] <= 122)) | (data[second] >= 0x80)
    capital = (((head >= 65) & (head <= 90)) | latin) & lower & (second < w.end)
    before = np.empty(len(data) + 1, np.int64)  # sentence ends so far
    before[0] = 0
    np.cumsum((data == 46) | (data == 33) | (data == 63) | (data == 58) | (data == 10), out=before[1:])
    starts = np.ones(len(h), bool)
    starts[1:] = before[w.start[1:]] > before[w.end[:-1]]
    inner = w.first[:-1][w.first[:-1] < len(h)]
    starts[inner] = True
    name = capital & ~starts
    plain = np.where(number, _NUM, np.where(unit, _UNIT, h))
    typed = np.where(name & ~number & ~unit, _NAME, plain)
    between = data[np.minimum(w.end[:-1], len(data) - 1)]
    near = (w.start[1:] - w.end[:-1] == 1) & (typed[1:] == typed[:-1])
    near[inner[inner > 0] - 1] = False
    figures, names = np.zeros(len(h), bool), np.zeros(len(h), bool)
    figures[1:] = near & (typed[1:] == _NUM) & ((between == 44) | (between == 46))
    names[1:] = near & (typed[1:] == _NAME) & ((between == 32) | (between == 45) | (between == 39))
    whole = np.zeros(len(h), bool)
    kinds = [_folded(x, w.first, y) for x, y in ((typed, whole), (plain, whole), (typed, figures | names), (plain, figures), (h, whole))]
    return Templates(kinds, h, _together(h, kinds[2]), _hold(typed), figures | names, w.first)


def _folded(tokens: np.ndarray, first: np.ndarray, inner: np.ndarray) -> Kind:
    """Tokens with each run (a word and the ``inner`` words after it) as one."""
    if not inner.any():
        at = np.arange(len(tokens))
        return Kind(tokens, at, at + 1, first, inner)
    begin = np.flatnonzero(~inner)
    end = np.append(begin[1:], len(tokens))
    return Kind(tokens[begin], begin, end, np.searchsorted(begin, first), end - begin > 1)


def _together(h: np.ndarray, kind: Kind) -> np.ndarray:
    """Hash of each word, the same for all words of one run."""
    if not kind.folds.any():
        return h
    n = kind.end - kind.begin
    place = (np.arange(len(h)) - np.repeat(kind.begin, n)).astype(np.uint64)
    return np.repeat(np.where(kind.folds, np.add.reduceat(mix64(h + place * _RUN), kind.begin), h[kind.begin]), n)


def _hold(tokens: np.ndarray) -> np.ndarray:
    return tokens < np.uint64(32)


def _template_windows(t: Templates, size: int, literal: int, kinds=(0, 1, 2, 3)) -> list[tuple[int, np.ndarray, np.ndarray]]:
    """Kind, hashes and first tokens of the windows; of a folded kind those with a run, as it has the others in common
    with the kind it is folded from.  A short window needs placeholders in less than half of it, at most."""
    out = []
    for kind in kinds:
        k = t.kinds[kind]
        if kind == 0 and not (k.tokens != t.kinds[1].tokens).any() or kind in (2, 3) and not k.folds.any():
            continue
        h, at = windows(k.tokens, k.first, size)
        words_so_far = np.concatenate([[0], np.cumsum(~_hold(k.tokens))])
        enough = words_so_far[at + size] - words_so_far[at] >= min(literal, (size + 1) // 2)
        if kind == 4:
            enough[:] = True
        elif kind > 1:
            runs = np.concatenate([[0], np.cumsum(k.folds)])
            enough &= runs[at + size] > runs[at]
        out.append((kind, mix64(h[enough] + np.uint64(size)), at[enough]))
    return out


@dataclass
class Items:
    """A block of the benchmark: sorted window hashes, what they point at, and the items' templates."""

    hashes: np.ndarray
    item: np.ndarray
    kind: np.ndarray
    place: np.ndarray  # first token of the window, in its kind
    size: np.ndarray  # tokens of the window
    ids: np.ndarray
    starts: list[np.ndarray]  # words of each item at which a usable window begins: one with enough literal tokens
    apart: list[np.ndarray]  # those of windows without runs
    bare: np.ndarray  # sizes of windows over bare words
    templates: Templates
    units: np.ndarray


def items_of(ids: list[int], texts: list[str | None], window: int = WINDOW, literal: int = LITERAL) -> Items:
    """An item shorter than a window is one window by itself.  An item whose placeholders stand so densely that it has no
    usable window is looked for word for word; so is one under 4 words, but only as a whole document, as so few words
    stand in other texts by chance."""
    units = np.sort(np.array([hash_of(u, ALNUM) for u in UNITS], np.uint64))
    data, off = text_buffers(pa.array(texts, pa.string()))
    t = canonical(data, off, units)
    empty = np.empty(0, np.int64)
    parts: list[tuple[np.ndarray, ...]] = [(np.empty(0, np.uint64), empty, empty, empty, empty)]
    has = np.zeros(len(texts), bool)
    for kinds in ((0, 1), (2,), (3,), (4,)):
        first = t.kinds[kinds[0]].first
        n = np.diff(first)
        sizes = np.where(n >= window, window, np.where((n >= SHORT) | (kinds == (4,)), n, 0))
        if kinds == (4,):
            sizes[has] = 0
        for size in np.unique(sizes[sizes > 0]).tolist():
            for kind, h, at in _template_windows(t, size, literal, kinds):
                row = np.searchsorted(first, at, "right") - 1
                ok = sizes[row] == size
                has[row[ok]] = True
                parts.append((h[ok], row[ok], np.full(ok.sum(), kind), at[ok], np.full(ok.sum(), size)))
    h, w, kind, place, size = (np.concatenate(x) for x in zip(*parts))
    order = np.argsort(h, kind="stable")

    def begins(kinds) -> list[np.ndarray]:
        at = np.unique(np.concatenate([np.column_stack([w[kind == k], t.kinds[k].begin[place[kind == k]] - t.first[w[kind == k]]]) for k in kinds]), axis=0)
        return np.split(at[:, 1], np.searchsorted(at[:, 0], np.arange(1, len(texts))))

    return Items(h[order], w[order], kind[order], place[order], size[order], np.array(ids, np.int64), begins(range(5)), begins((0, 1)),
        np.unique(size[kind == 4]), t, units)


def _chain(hits: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The longest chain of places in item and document that go on together, their distance changing by at most
    ``DRIFT`` words from one to the next."""
    ends: dict[int, list[tuple]] = {}  # for each diagonal: length, place, link before
    top = None
    for q, p in sorted(hits):
        before = None
        for e in range(p - q - DRIFT, p - q + DRIFT + 1):
            for link in reversed(ends.get(e, ())):
                if link[1][0] < q and link[1][1] < p:
                    if before is None or link[0] > before[0]:
                        before = link
                    break
        link = (before[0] + 1 if before else 1, (q, p), before)
        ends.setdefault(p - q, []).append(link)
        if top is None or link[0] > top[0]:
            top = link
    out = []
    while top:
        out.append(top[1])
        top = top[2]
    return out[::-1]


def _longest(chain: list[tuple], hits: dict) -> int:
    """Most consecutive template tokens that the windows of a chain cover, both sides going on by one token each time."""
    best, n, after = 0, 0, set()
    for at in chain:
        n = n + 1 if at in after else 1
        after = {one[2] for one in hits[at]}
        best = max(best, n + max(one[3] for one in hits[at]) - 1)
    return best


def _share(chain: list[tuple[int, int]], counted: list[set[int]]) -> float:
    """Share of an item's windows in a chain: of all, of those that don't begin inside a run, or of those without runs."""
    return max(sum(q in some for q, _ in chain) / max(len(some), 1) for some in counted)


def _consistent(chain: list[tuple[int, int]], hits: dict, level: int) -> tuple[dict, list[tuple[int, int]]]:
    """The windows of a chain whose slots agree: where a value became several, those without it or with it unchanged."""
    kept = {at: some for at in chain if (some := [one for one in hits[at] if len(one[4]) > level])}
    became: dict[int, set[int]] = {}
    for some in kept.values():
        for one in some:
            for a, b in one[4][level]:
                became.setdefault(a, set()).add(b)
    torn = {a for a, b in became.items() if len(b) > 1}
    if torn:
        kept = {at: ok for at, some in kept.items() if (ok := [one for one in some if all(a == b for a, b in one[4][level] if a in torn)])}
    return kept, [at for at in chain if at in kept]


def matches(data: np.ndarray, offsets: np.ndarray, items: Items, coverage: float = COVERAGE, run: int = RUN, literal: int = LITERAL) -> list[tuple]:
    """(row, item, windows, matched, coverage, first word, last word, slots, reparameterised) for each match.

    Windows of one diagonal are put together, and those of neighbouring diagonals in a chain, as a slot's value may
    have another number of words.  Where a value of the item became several values, only windows without it, or with
    it unchanged, count.
    """
    if not len(items.hashes):
        return []
    t, known = canonical(data, offsets, items.units), items.templates
    found: dict[tuple[int, int], dict[tuple[int, int], list[tuple]]] = {}  # places in item and document: end of each, next token of each, tokens, slot values
    for size in np.unique(items.size).tolist():
        for kind, h, at in _template_windows(t, size, literal, (0, 1, 2, 3, 4) if size in items.bare else (0, 1, 2, 3)):
            lo = np.searchsorted(items.hashes, h, "left")
            some = np.flatnonzero(items.hashes[np.minimum(lo, len(items.hashes) - 1)] == h)
            hi = np.searchsorted(items.hashes, h[some], "right")
            theirs = t.kinds[kind]
            row = np.searchsorted(theirs.first, at[some], "right") - 1
            for r, a, x, y in zip(row.tolist(), at[some].tolist(), lo[some].tolist(), hi.tolist()):
                p = int(theirs.begin[a] - t.first[r])
                for k in range(x, y):
                    if items.size[k] != size or (size < SHORT and t.first[r + 1] - t.first[r] != size):
                        continue
                    i, b, own = int(items.item[k]), int(items.place[k]), known.kinds[items.kind[k]]
                    q = int(own.begin[b] - known.first[i])
                    slot = np.flatnonzero(known.slot[own.begin[b : b + size]])
                    ours, other = own.begin[b + slot], theirs.begin[a + slot]
                    typed = t.slot[other]  # a name in another case is no placeholder there
                    pairs = [list(zip(np.where(typed, known.values[ours], known.bare[ours]).tolist(), t.values[other].tolist()))]
                    if not own.folds[b : b + size].any() and not theirs.folds[a : a + size].any():
                        pairs.append(list(zip(known.bare[ours].tolist(), t.bare[other].tolist())))
                    q1, p1 = int(own.end[b + size - 1] - known.first[i]), int(theirs.end[a + size - 1] - t.first[r])
                    step = (int(own.end[b] - known.first[i]), int(theirs.end[a] - t.first[r]))
                    found.setdefault((r, i), {}).setdefault((q, p), []).append((q1, p1, step, size, pairs))
    out = []
    for (r, i), hits in sorted(found.items()):
        starts = items.starts[i]
        counted = [set(x.tolist()) for x in (starts, starts[~known.inner[known.first[i] + starts]], items.apart[i])]

        def enough(chain, hits, counted=counted):
            return bool(chain) and (_share(chain, counted) >= coverage or _longest(chain, hits) >= run)

        diagonals: dict[int, list[tuple[int, int]]] = {}
        for q, p in sorted(hits):
            diagonals.setdefault(p - q, []).append((q, p))
        near: list[list[int]] = []
        for d in sorted(diagonals):
            if near and d - near[-1][-1] <= DRIFT:
                near[-1].append(d)
            else:
                near.append([d])
        chains = list(diagonals.values()) + [_chain([at for d in some for at in diagonals[d]]) for some in near if len(some) > 1]
        best = None
        for chain in chains:
            for level in (0, 1):  # slot values of whole runs, then of single words
                kept, whole = _consistent(chain, hits, level)
                if best and len(whole) <= best[3] or not enough(whole, kept):
                    continue
                ones = [(at, one) for at in whole for one in kept[at]]
                cover = np.unique(np.concatenate([np.arange(at[0], one[0]) for at, one in ones]))
                changed = any(a != b for _, one in ones for a, b in one[4][level])
                best = (r, i, len(starts), len(whole), _share(whole, counted), whole[0][1], max(one[1] for _, one in ones) - 1,
                    int(known.slot[known.first[i] + cover].sum()), changed)
        if best:
            out.append(best)
    return out


def benchmark_blocks(benchmark: DataFrame, window: int = WINDOW, literal: int = LITERAL, most: int = BROADCAST_WINDOWS):
    """Blocks of the benchmark, each small enough to broadcast; items stream through the driver one block at a time."""
    ids, texts, held = [], [], 0
    for row in benchmark.select(F.col("item_id").cast("long").alias("item_id"), "text").where("item_id is not null").toLocalIterator():
        ids.append(row.item_id)
        texts.append(row.text or "")
        held += max(1, len(texts[-1]) // 2)  # a text has at most this many words
        if held >= most:
            yield items_of(ids, texts, window, literal)
            ids, texts, held = [], [], 0
    if ids:
        yield items_of(ids, texts, window, literal)


def contaminated(docs: DataFrame, benchmark: DataFrame, coverage: float = COVERAGE, run: int = RUN) -> DataFrame:
    """SCHEMA: one row for each document and benchmark item of which it holds a template.

    Null and empty texts match nothing.  Repeated rows repeat their matches.  Ties between alignments go to the
    first found with most windows.  Only doc_id, item_id and text are read; an empty side gives no rows.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    out = docs.sparkSession.createDataFrame([], SCHEMA)
    for items in benchmark_blocks(benchmark):
        shared = docs.sparkSession.sparkContext.broadcast(items)

        def find(batches, shared=shared):
            known = shared.value
            for b in batches:
                data, off = text_buffers(b.column(1))
                for i, j in slices(off):
                    got = matches(data[off[i] : off[j]], off[i : j + 1] - off[i], known, coverage, run)
                    if got:
                        r, item, *rest = (list(x) for x in zip(*got))
                        ids = b.column(0).take(pa.array([i + k for k in r]))
                        kinds = [pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.int64(), pa.int64(), pa.bool_()]
                        yield pa.RecordBatch.from_arrays([ids, pa.array(known.ids[item]), *(pa.array(x, k) for x, k in zip(rest, kinds))],
                            [c.split()[0] for c in SCHEMA.split(", ")])

        out = out.unionByName(narrow(rows, find, SCHEMA))
    return out


def keep_clean(docs: DataFrame, benchmark: DataFrame, coverage: float = COVERAGE, run: int = RUN) -> DataFrame:
    """The rows of ``docs``, all columns, that match no benchmark item; a narrow pass for each benchmark block.

    Null and empty texts match nothing and stay; repeated rows go or stay alike; other columns are kept as they are.
    Of several passes each is written before the next, so that one task never holds several blocks."""
    at = docs.columns.index("text")
    for n, items in enumerate(benchmark_blocks(benchmark)):
        if n:
            docs = settle(docs, "clean")
        shared = docs.sparkSession.sparkContext.broadcast(items)

        def keep(batches, shared=shared):
            for b in batches:
                data, off = text_buffers(b.column(at))
                good = np.ones(b.num_rows, bool)
                for i, j in slices(off):
                    for m in matches(data[off[i] : off[j]], off[i : j + 1] - off[i], shared.value, coverage, run):
                        good[i + m[0]] = False
                yield b.filter(pa.array(good))

        docs = narrow(docs, keep, docs.schema)
    return docs
