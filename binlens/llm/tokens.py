"""Encoding of Arrow text columns with a public tokenizer file, by the tokenizers library.

Words repeat, and the library spends most of its time on each occurrence anew.  So texts are cut, with numpy, at
places that no piece of the tokenizer's pre-tokenisation can cross; each distinct chunk goes to the library once
and its ids are kept in a table of bounded size; the ids of a text are then gathered by index.

Cuts, for patterns of letters, digits, other signs and white space (both kinds of tokenizer in use):
* before a blank that is followed by a sign other than white space: the piece that holds this blank starts there;
* before and after a line feed that is followed by such a sign: the feed stands alone;
* between an ASCII letter and an ASCII punctuation mark other than the apostrophe.
Rows with a special-token opener ("<|") are not cut.  Chunks are told apart by a 64-bit hash and their length.
"""

from __future__ import annotations

import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from binlens.llm.common import slices, text_buffers
from binlens.llm.words import Alphabet, span_hashes

SLOTS = 17  # table slots at first, as a power of two; it grows when half full
MOST_SLOTS = 21  # and is emptied when half full at this size, some 50 MB
_EXACT = Alphabet(np.ones(256, bool), np.arange(256, dtype=np.uint8))
_SPACE = np.zeros(256, bool)
_SPACE[list(b" \t\n\x0b\x0c\r\x1c\x1d\x1e\x1f")] = True
_MAYBE_SPACE = _SPACE.copy()  # also bytes that may begin white space beyond ASCII
_MAYBE_SPACE[[0xC2, 0xE1, 0xE2, 0xE3]] = True
_LETTER = np.zeros(256, bool)
_LETTER[65:91] = _LETTER[97:123] = True
_MARK = np.array([33 <= i < 127 and not chr(i).isalnum() and i != 39 for i in range(256)])


def cuts(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Start of each chunk, ascending; row starts (of rows with text) among them."""
    n = len(data)
    start = np.zeros(n + 1, bool)
    if n > 1:
        solid = ~_MAYBE_SPACE[data[1:]]
        edge = offsets[1:-1]
        solid[edge[(edge > 0) & (edge < n)] - 1] = False  # the next byte is another row's
        feed = np.flatnonzero((data[:-1] == 10) & solid)
        start[:-2] = (data[:-1] == 32) & solid
        start[feed] = True
        start[feed + 1] = True
        start[1:-1] |= _LETTER[data[:-1]] & _MARK[data[1:]]
        special = np.flatnonzero((data[:-1] == 60) & (data[1:] == 124))
        for row in np.unique(np.searchsorted(offsets, special, "right") - 1):
            start[offsets[row] : offsets[row + 1]] = False
    start[offsets[:-1][np.diff(offsets) > 0]] = True
    return np.flatnonzero(start[:n])


class Encoder:
    """One tokenizer and its table of known chunks; a worker process keeps it between tasks (see ``encoder``)."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.separator = self.mark = None
        for text, byte in (("\n", 10), (" \x01 ", 1)):
            ids = self._one("a" + text + " b")
            if len(mid := self._one(text)) == 1 and ids == self._one("a") + mid + self._one(" b") and self._one("%" + text + "b") == self._one("%") + mid + self._one("b"):
                self.separator, self.mark, self.byte = text, mid[0], byte
                break
        self._forget()

    def _one(self, text: str) -> list[int]:
        return self.library.encode(text, add_special_tokens=False).ids

    def _forget(self, slots: int | None = None) -> None:
        slots = slots or SLOTS
        self._room(slots)
        self.entries, self.used = 0, 0
        self.at, self.n = np.zeros(1 << (slots - 1), np.int64), np.zeros(1 << (slots - 1), np.int32)
        self.flat = np.empty(1 << 17, np.uint32)

    def _room(self, slots: int) -> None:
        self.slots = slots
        self.keys, self.slot_entry = np.zeros(1 << slots, np.uint64), np.zeros(1 << slots, np.int32)

    def _grow(self, slots: int) -> None:
        known = self.keys != 0
        h, entry = self.keys[known], self.slot_entry[known]
        self._room(slots)
        self._insert(h, entry)
        for name in ("at", "n"):
            old = getattr(self, name)
            wider = np.zeros(1 << (slots - 1), old.dtype)
            wider[: len(old)] = old
            setattr(self, name, wider)

    def _slot(self, h: np.ndarray) -> np.ndarray:
        return (h >> np.uint64(64 - self.slots)).astype(np.int64)

    def _find(self, h: np.ndarray) -> np.ndarray:
        """Entry of each hash, -1 where unknown."""
        out = np.full(len(h), -1, np.int32)
        todo, slot, mask = np.arange(len(h)), self._slot(h), (1 << self.slots) - 1
        while len(todo):
            key = self.keys[slot]
            hit = key == h[todo]
            out[todo[hit]] = self.slot_entry[slot[hit]]
            on = ~hit & (key != 0)
            todo, slot = todo[on], (slot[on] + 1) & mask
        return out

    def _insert(self, h: np.ndarray, entry: np.ndarray) -> None:
        """Distinct hashes that the table doesn't hold yet."""
        todo, slot, mask = np.arange(len(h)), self._slot(h), (1 << self.slots) - 1
        while len(todo):
            free = self.keys[slot] == 0
            self.keys[slot[free]] = h[todo[free]]
            won = self.keys[slot] == h[todo]
            self.slot_entry[slot[won]] = entry[todo[won]]
            todo, slot = todo[~won], (slot[~won] + 1) & mask

    def _plain(self, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Chunks that may go to the library side by side: short ones without the separator, special tokens or white space
        but for one blank at their beginning."""
        if self.separator is None:
            return np.zeros(len(start), bool)

        def inside(mask, first, last):
            run = np.zeros(len(mask) + 1, np.int32)
            np.cumsum(mask, out=run[1:])
            return run[last] > run[first]

        blank = data == 32
        special = np.zeros(len(data), bool)
        special[:-1] = (data[:-1] == 60) & (data[1:] == 124)
        odd = inside(data == self.byte, start, end) | inside(blank, start + 1, end) | inside(special, start, np.maximum(end - 1, start))
        return (end - start <= 64) & ~odd & ~_SPACE[data[end - 1]]

    def _learn(self, h: np.ndarray, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> None:
        self._insert(h, np.arange(self.entries, self.entries + len(h), dtype=np.int32))
        raw, plain = data.tobytes(), self._plain(data, start, end)
        n, at, parts, used = np.zeros(len(h), np.int32), np.zeros(len(h), np.int64), [], self.used
        between = (self.separator or "").encode()
        rows = np.flatnonzero(plain)
        groups = [rows[k : k + 512] for k in range(0, len(rows), 512)]
        joined = [between.join([raw[a:b] for a, b in zip(start[g].tolist(), end[g].tolist())]).decode() for g in groups]
        for g, e in zip(groups, self.library.encode_batch_fast(joined, add_special_tokens=False)):
            got = np.array(e.ids, np.uint32)
            marks = np.flatnonzero(got == self.mark)
            if len(marks) != len(g) - 1:
                plain[g] = False
                continue
            size = np.diff(np.concatenate([[-1], marks, [len(got)]])) - 1
            n[g], at[g] = size, used + np.cumsum(size) - size
            parts.append(np.delete(got, marks))
            used += len(parts[-1])
        rest = np.flatnonzero(~plain)
        texts = [raw[a:b].decode() for a, b in zip(start[rest].tolist(), end[rest].tolist())]
        for i, e in zip(rest.tolist(), self.library.encode_batch_fast(texts, add_special_tokens=False)):
            parts.append(np.array(e.ids, np.uint32))
            n[i], at[i] = len(parts[-1]), used
            used += len(parts[-1])
        while used > len(self.flat):
            self.flat = np.concatenate([self.flat, np.empty(len(self.flat), np.uint32)])
        self.flat[self.used : used] = np.concatenate(parts)
        span = slice(self.entries, self.entries + len(n))
        self.n[span], self.at[span] = n, at
        self.used = used
        self.entries += len(n)

    def encode(self, column: pa.Array, end_id: int | None = None, slice_bytes: int = 1 << 19) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """For runs of rows: first row, ids of all rows (uint32, each row closed by the end id), row bounds."""
        data, offsets = text_buffers(column)
        for a, b in slices(offsets, slice_bytes):
            yield a, *self._run(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a], end_id)

    def _run(self, data: np.ndarray, offsets: np.ndarray, end_id: int | None) -> tuple[np.ndarray, np.ndarray]:
        start = cuts(data, offsets)
        end = np.append(start[1:], len(data))[: len(start)]
        h = span_hashes(data, start, end, _EXACT) | np.uint64(1)
        entry = self._find(h)
        lost = np.flatnonzero(entry < 0)
        if len(lost):
            new, first = np.unique(h[lost], return_index=True)
            if (wanted := (self.entries + len(new)).bit_length() + 1) > self.slots:
                if wanted <= MOST_SLOTS:
                    self._grow(wanted)
                else:  # begin anew; only a row longer than a slice may need a larger table
                    lost = np.arange(len(h))
                    new, first = np.unique(h, return_index=True)
                    self._forget(max(SLOTS, len(new).bit_length() + 1))
            first = lost[first]
            self._learn(new, data, start[first], end[first])
            entry[lost] = self._find(h[lost])
        n = self.n[entry].astype(np.int64)
        run = np.concatenate([[0], np.cumsum(n)])
        ids = self.flat[np.arange(run[-1]) + np.repeat(self.at[entry] - run[:-1], n)]
        bounds = run[np.searchsorted(start, offsets, "left")]
        if end_id is not None:
            ids = np.insert(ids, bounds[1:], np.uint32(end_id))
            bounds = bounds + np.arange(len(bounds))
        return ids, bounds


_KNOWN: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """The worker's encoder for a tokenizer file, with what it has learnt so far: learning a chunk costs some ten times
    as much as finding it, and a tokenizer with its table stays under 80 MB.  Another file takes its place."""
    if path not in _KNOWN:
        _KNOWN.clear()
        _KNOWN[path] = Encoder(path)
    return _KNOWN[path]
