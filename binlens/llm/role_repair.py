"""Minimum-cost role repair of conversations.

Legal conversations: an optional system turn, then user and assistant turns in alternation, a user's first and an
assistant's last.  Each turn may be kept, relabelled, or merged into the turn before, and empty turns may be
inserted.  The cheapest repair is a shortest path through the automaton's states (nothing yet, after system,
after user, after assistant).  A turn is a min-plus matrix over those states, and such matrices multiply
associatively: rows are dealt out by (conversation, turn) ranges, each range gives one matrix for each
conversation that it holds a piece of, the pieces of a conversation are solved on the matrices alone, and each
piece is then traced back by itself.  So the longest conversation needs no task of its own.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from binlens.llm.common import narrow, settle, shuffle_width

START, SYSTEM, USER, ASSISTANT = range(4)
ROLES = {"system": SYSTEM, "user": USER, "assistant": ASSISTANT}
NAMES = {v: k for k, v in ROLES.items()}
FAR = 1 << 40
#: Costs of a repair, fixed values: merge, relabel, insert.
MERGE, RELABEL, INSERT = 1, 2, 3
#: Turns that the automaton allows next.
NEXT = {START: (SYSTEM, USER), SYSTEM: (USER,), USER: (ASSISTANT,), ASSISTANT: (USER,)}
SCHEMA = "conv_id long, turn long, role string, repaired_role string, action string, inserted_before string, inserted_after string, cost long, rendered string"


def _arcs(role: int | None) -> list[tuple[int, int, int, str, tuple[int, ...]]]:
    """(from, to, cost, action, inserted turns) for one turn; an unknown role must be relabelled."""
    out = []
    for to in (SYSTEM, USER, ASSISTANT):
        own = 0 if to == role else RELABEL
        name = "keep" if to == role else "relabel"
        for a in range(4):
            if to in NEXT[a]:
                out.append((a, to, own, name, ()))
            if a == to:
                out.append((a, to, own + MERGE, "merge" if to == role else "relabel+merge", ()))
            for mid in NEXT[a]:
                if to in NEXT[mid] and mid != SYSTEM:
                    out.append((a, to, own + INSERT, name, (mid,)))
    return out


ARCS = {r: _arcs(r) for r in (None, SYSTEM, USER, ASSISTANT)}
#: Cost and inserted turns to end legally from each state.
FINISH = {START: (FAR, ()), SYSTEM: (2 * INSERT, (USER, ASSISTANT)), USER: (INSERT, (ASSISTANT,)), ASSISTANT: (0, ())}


def _best(role: int | None) -> tuple[np.ndarray, dict]:
    m, how = np.full((4, 4), FAR, np.int64), {}
    for a, b, cost, action, inserted in ARCS[role]:
        if cost < m[a, b]:
            m[a, b], how[a, b] = cost, (action, inserted)
    return m, how


STEP = {r: _best(r) for r in ARCS}


def times(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.minimum((a[:, :, None] + b[None, :, :]).min(axis=1), FAR)


def role_of(text: str | None) -> int | None:
    return ROLES.get((text or "").strip().lower())


def trace(roles: list[int | None], enter: int, leave: int) -> list[tuple[int, str, tuple[int, ...]]]:
    """(state after, action, inserted before) of each turn on the cheapest way; ties go to the lower state."""
    cost = [np.full(4, FAR, np.int64)]
    cost[0][enter] = 0
    back = []
    for r in roles:
        ways = cost[-1][:, None] + STEP[r][0]
        back.append(ways.argmin(axis=0))
        cost.append(np.minimum(ways.min(axis=0), FAR))
    out, state = [], leave
    for k in range(len(roles) - 1, -1, -1):
        before = int(back[k][state])
        out.append((state, *STEP[roles[k]][1][before, state]))
        state = before
    return out[::-1]


def chain(matrices: list[np.ndarray]) -> tuple[int, list[int]]:
    """Total cost, and the state before the first piece, after it, after the next, ..."""
    cost = np.full(4, FAR, np.int64)
    cost[START] = 0
    back = []
    for m in matrices:
        ways = cost[:, None] + m
        back.append(ways.argmin(axis=0))
        cost = np.minimum(ways.min(axis=0), FAR)
    total = cost + np.array([FINISH[s][0] for s in range(4)])
    state = int(total.argmin())
    path = [state]
    for b in reversed(back):
        path.append(int(b[path[-1]]))
    return int(total.min()), path[::-1]


_MARK = re.compile(r"<(\\*)\|")


def escaped(text: str) -> str:
    """Text that can't be read as one of the template's markers: "<|" gets a backslash between its signs, and one that has
    backslashes there gets one more, so that taking one away gives the text back."""
    return _MARK.sub(r"<\1\\|", text) if "|" in text else text


def _opening(state: int) -> str:
    return f"<|{NAMES[state]}|>\n"


CLOSE = "\n<|end|>\n"


def _runs(batches: Iterator[pa.RecordBatch], width: int) -> Iterator[tuple[int, list[tuple]]]:
    """Consecutive rows of one conversation, in pieces of at most 4,096."""
    key, held = None, []
    for b in batches:
        for row in zip(*(b.column(c).to_pylist() for c in range(width))):
            if held and (row[0] != key or len(held) >= 4096):
                yield key, held
                held = []
            key = row[0]
            held.append(row)
    if held:
        yield key, held


def repair(conversations: DataFrame) -> DataFrame:
    """SCHEMA: one row for each turn, with what becomes of it.  ``rendered`` strings, in order of (turn, role, text),
    spell out the repaired conversation; a merged turn continues the one before after a line feed.  ``cost`` is the
    whole conversation's.

    Texts are escaped, so that none can open or end a turn (``escaped``).  Rows without conv_id are left out.  Null turns come first; null, empty and unknown roles are relabelled; null
    texts are empty.  Turns with one number are ordered by role and a hash of their text; repeated rows are turns
    of their own (and so merge).  Other columns are not read; an empty table gives no rows.
    """
    rows = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"),
        F.col("role").cast("string").alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    keys = [F.col("conv_id"), F.col("turn"), F.col("role"), F.xxhash64("text"), F.col("text")]
    rows = rows.where("conv_id is not null").repartitionByRange(shuffle_width(conversations.sparkSession), *keys[:4]).sortWithinPartitions(*keys)

    def cut(batches):
        from pyspark import TaskContext

        part, k = TaskContext.get().partitionId() << 32, 0
        for conv, run in _runs(batches, 4):
            n = len(run)
            yield pa.RecordBatch.from_arrays(
                [pa.array([conv] * n, pa.int64()), pa.array([part + k] * n, pa.int64()), pa.array(range(n), pa.int32()),
                    *(pa.array([r[c] for r in run], t) for c, t in ((1, pa.int64()), (2, pa.string()), (3, pa.string())))],
                ["conv_id", "piece", "at", "turn", "role", "text"],
            )
            k += 1

    # written once: the ranges must be the same for the matrices and for the way back
    turns = settle(narrow(rows, cut, "conv_id long, piece long, at int, turn long, role string, text string"), "turns")

    def matrices(batches):
        def made(out):
            return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out), (pa.int64(), pa.int64(), pa.binary()))], ["conv_id", "piece", "matrix"])

        out: list[tuple] = []
        for key, run in _pieces(batches):
            m = None
            for r in run:
                step = STEP[role_of(r[4])][0]
                m = step if m is None else times(m, step)
            out.append((run[0][0], key, m.tobytes()))
            if len(out) == 10_000:
                yield made(out)
                out = []
        if out:
            yield made(out)

    order = turns.repartition(shuffle_width(conversations.sparkSession), "piece").sortWithinPartitions("piece", "at")
    small = narrow(order, matrices, "conv_id long, piece long, matrix binary")

    def solve(batches):
        for b in batches:
            conv, piece, enter, leave, cost, last = [], [], [], [], [], []
            for c, pieces in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                total, path = chain([np.frombuffer(p["matrix"], np.int64).reshape(4, 4) for p in pieces])
                for k, p in enumerate(pieces):
                    conv.append(c), piece.append(p["piece"]), enter.append(path[k]), leave.append(path[k + 1]), cost.append(total), last.append(k == len(pieces) - 1)
            yield pa.RecordBatch.from_arrays([pa.array(conv, pa.int64()), pa.array(piece, pa.int64()), pa.array(enter, pa.int32()), pa.array(leave,
                pa.int32()), pa.array(cost, pa.int64()), pa.array(last, pa.bool_())], ["conv_id", "piece", "enter", "leave", "cost", "final"])

    # a conversation's pieces: at most one for each range or 4,096 turns, of 128 bytes
    listed = small.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("piece", "matrix"))).alias("pieces"))
    ways = narrow(listed, solve, "conv_id long, piece long, enter int, leave int, cost long, final boolean").select("piece", "enter", "leave", "cost", "final")

    def write(batches):
        for _, run in _pieces(batches):
            enter, leave, cost, final = run[0][6:10]
            steps = trace([role_of(r[4]) for r in run], enter, leave)
            out = []
            for k, (r, (state, action, inserted)) in enumerate(zip(run, steps)):
                before = enter if k == 0 else steps[k - 1][0]
                if action.endswith("merge"):
                    text = "\n" + escaped(r[5])
                else:
                    text = ("" if before == START else CLOSE) + "".join(_opening(s) + CLOSE for s in inserted) + _opening(state) + escaped(r[5])
                tail: tuple[int, ...] = ()
                if final and k == len(run) - 1:
                    tail = FINISH[leave][1]
                    text += CLOSE + "".join(_opening(s) + CLOSE for s in tail)
                out.append((r[0], r[3], r[4], NAMES[state], action, ",".join(NAMES[s] for s in inserted) or None, ",".join(NAMES[s] for s in tail) or None, cost, text))
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.string(), pa.string(), pa.int64(), pa.string())
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out), kinds)], [c.split()[0] for c in SCHEMA.split(", ")])

    back = turns.join(ways, "piece").select("conv_id", "piece", "at", "turn", "role", "text", "enter", "leave", "cost", "final")
    back = back.repartition(shuffle_width(conversations.sparkSession), "piece").sortWithinPartitions("piece", "at")
    return narrow(back, write, SCHEMA)


def _pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, list[tuple]]]:
    key, held = None, []
    for b in batches:
        for row in zip(*(b.column(c).to_pylist() for c in range(b.num_columns))):
            if held and row[1] != key:
                yield key, held
                held = []
            key = row[1]
            held.append(row)
    if held:
        yield key, held
