"""Minimum-cost role repair of conversations, then rendering.

A legal conversation is one optional system turn, then user and assistant turns
in turn, the first a user's and the last an assistant's.  Each given turn is
kept, relabelled, or merged into the turn before; empty turns may be put in.
The cheapest such repair is a shortest path over the automaton's states
(before any turn, after system, after user, after assistant).

Costs of a run of turns form a matrix from state to state, and matrices of
successive runs multiply by (min, +).  So conversations are cut into ranges of
turns: each range gives its matrix, the few rows of a conversation that spans
ranges are combined, and each range then finds its own path between the states
at its ends.  No conversation has to fit a task.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .ranges import dealt_by_order

START, SYSTEM, USER, ASSISTANT = range(4)
ROLES = {SYSTEM: "system", USER: "user", ASSISTANT: "assistant"}
_STATE = {"system": SYSTEM, "user": USER, "assistant": ASSISTANT, "human": USER, "prompter": USER, "gpt": ASSISTANT, "bot": ASSISTANT, "model": ASSISTANT}
#: Costs of changes; keeping is free.
RELABEL, MERGE, INSERT = 2, 1, 3
#: Legal successors of each state.
_NEXT = {START: (SYSTEM, USER), SYSTEM: (USER,), USER: (ASSISTANT,), ASSISTANT: (USER,)}
_FAR = 1 << 40


def state_of(role: str | None) -> int:
    """The state that a role's turn leads to; 0 for a role that isn't known."""
    return _STATE.get((role or "").strip().lower(), START)


def _steps(given: int) -> list[list[tuple[int, tuple[int, ...], bool] | None]]:
    """For a turn of a role: [from][to] = cheapest (cost, roles put in before, merged)."""
    table: list[list[tuple[int, tuple[int, ...], bool] | None]] = [[None] * 4 for _ in range(4)]

    def offer(s: int, to: int, step: tuple[int, tuple[int, ...], bool]) -> None:
        if table[s][to] is None or step < table[s][to]:
            table[s][to] = step

    for s in range(4):
        for to in (SYSTEM, USER, ASSISTANT):
            cost = 0 if to == given else RELABEL
            if to in _NEXT[s]:
                offer(s, to, (cost, (), False))
            for between in _NEXT[s]:
                if to in _NEXT[between]:
                    offer(s, to, (cost + INSERT, (between,), False))
            if s == to:
                offer(s, to, (cost + MERGE, (), True))
    return table


STEPS = [_steps(r) for r in range(4)]
#: Cost of ending in each state, and the roles put in for that.
ENDINGS = {START: (0, ()), SYSTEM: (2 * INSERT, (USER, ASSISTANT)), USER: (INSERT, (ASSISTANT,)), ASSISTANT: (0, ())}
_COSTS = np.array([[[_FAR if c is None else c[0] for c in row] for row in t] for t in STEPS], np.int64)
_END_COST = np.array([ENDINGS[s][0] for s in range(4)], np.int64)


def matrix(states: list[int]) -> np.ndarray:
    """The (min, +) product of the turns' matrices."""
    m = np.where(np.eye(4, dtype=bool), 0, _FAR)
    for s in states:
        m = np.minimum((m[:, :, None] + _COSTS[s][None]).min(1), _FAR)
    return m


def path(states: list[int], entry: int, leave: int | None) -> tuple[list[int], int]:
    """States after each turn on the cheapest path from a state to a state, or to any ending; and its cost. Ties go to the least states, the last turn first."""
    cost = np.full(4, _FAR)
    cost[entry] = 0
    costs = [cost]
    for s in states:
        costs.append(np.minimum((costs[-1][:, None] + _COSTS[s]).min(0), _FAR))
    last = costs[-1] + (_END_COST if leave is None else 0)
    at = int(np.argmin(last)) if leave is None else leave
    total, out = int(last[at]), [at]
    for i in range(len(states) - 1, -1, -1):
        at = int(np.argmin(costs[i] + _COSTS[states[i]][:, at]))
        out.append(at)
    return out[::-1][1:], total


def _safe(text: str) -> str:
    """Text that can't be taken for a marker."""
    return text.replace("<|", "< |")


def render(states: list[int], given: list[int], texts: list[str], entry: int, last: bool) -> Iterator[tuple[str, str, str]]:
    """(role, action, piece) of each turn; the pieces of a conversation, one after the other, are its rendering."""
    for i, (to, was, text) in enumerate(zip(states, given, texts, strict=True)):
        step = STEPS[was][entry][to]
        close = "" if entry == START else "<|im_end|>\n"
        if step[2]:
            piece, action = "\n" + _safe(text), "merge" if to == was else "merge_relabel"
        else:
            put_in = "".join(f"<|im_start|>{ROLES[r]}\n<|im_end|>\n" for r in step[1])
            piece = f"{close}{put_in}<|im_start|>{ROLES[to]}\n{_safe(text)}"
            action = ("insert_" if step[1] else "") + ("keep" if to == was else "relabel")
        if last and i == len(states) - 1:
            piece += "<|im_end|>\n" + "".join(f"<|im_start|>{ROLES[r]}\n<|im_end|>\n" for r in ENDINGS[to][1])
            action += "_end" if ENDINGS[to][1] else ""
        yield ROLES[to], action, piece
        entry = to


def repair(turns: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """(conv_id, turn, role_in, role_out, action, rendered) of every given turn.

    Turns of a conversation go by number, then role and text; a null number comes first.  Roles
    count without case, some other names of user and assistant are known, and a null or other
    role can be relabelled alone.  Null texts render as empty ones.  Rows with a null conversation
    form one of their own; repeated rows are turns of their own.  An empty table gives an empty result.
    """
    rows = turns.select(F.col(conv_col).alias("conv_id"), F.col(turn_col).alias("turn"), F.col(role_col).cast("string").alias("role_in"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    conv_type, turn_type = rows.schema["conv_id"].dataType.simpleString(), rows.schema["turn"].dataType.simpleString()
    dealt = dealt_by_order(rows, F.col("conv_id"), F.col("turn"), F.col("role_in"), F.col("text"), name="turns")

    def runs(table: pa.Table) -> Iterator[tuple[object, int, int]]:
        convs = table.column("conv_id").to_pylist()
        start = 0
        for i in range(1, len(convs) + 1):
            if i == len(convs) or convs[i] != convs[start]:
                yield convs[start], start, i
                start = i

    def nulls_first(table: pa.Table) -> pa.Table:
        at = pc.sort_indices(table, sort_keys=[(c, "ascending") for c in ("conv_id", "turn", "role_in", "text")], null_placement="at_start")
        return table.take(at)

    def matrices(table: pa.Table) -> pa.Table:
        """Of the first and last conversation of a range, which others may share."""
        table = nulls_first(table)
        found = list(runs(table))
        roles = [state_of(r) for r in table.column("role_in").to_pylist()]
        pid = table.column("pid")[0].as_py()
        ends = found if len(found) < 2 else [found[0], found[-1]]
        return pa.table({"conv_id": pa.array([c for c, _, _ in ends], table.schema.field("conv_id").type), "pid": pa.array([pid] * len(ends), pa.int32()), "m": pa.array([matrix(roles[a:b]).ravel().tolist() for _, a, b in ends], pa.list_(pa.int64()))})

    def joints(table: pa.Table) -> pa.Table:
        """States at the ends of each range of a conversation."""
        order = np.argsort(table.column("pid").to_numpy())
        pids = table.column("pid").to_numpy()[order]
        ms = [np.array(table.column("m")[int(i)].as_py()).reshape(4, 4) for i in order]
        costs = [np.array([0, _FAR, _FAR, _FAR])]
        for m in ms:
            costs.append(np.minimum((costs[-1][:, None] + m).min(0), _FAR))
        at = int(np.argmin(costs[-1] + _END_COST))
        out = [at]
        for i in range(len(ms) - 1, -1, -1):
            at = int(np.argmin(costs[i] + ms[i][:, at]))
            out.append(at)
        out = out[::-1]
        return pa.table({"pid": pa.array(pids, pa.int32()), "conv_id": pa.array([table.column("conv_id")[0].as_py()] * len(pids), table.schema.field("conv_id").type), "entry": pa.array(out[:-1], pa.int32()), "leave": pa.array(out[1:], pa.int32()), "last": pa.array([i == len(pids) - 1 for i in range(len(pids))], pa.bool_())})

    ends = dealt.groupBy("pid").applyInArrow(matrices, f"conv_id {conv_type}, pid int, m array<long>").groupBy("conv_id").applyInArrow(joints, f"pid int, conv_id {conv_type}, entry int, leave int, last boolean")

    def each(left: pa.Table, right: pa.Table) -> pa.Table:
        left = nulls_first(left)
        known = {c: (e, x, z) for c, e, x, z in zip(*(right.column(n).to_pylist() for n in ("conv_id", "entry", "leave", "last")), strict=True)}
        roles, texts, out = [state_of(r) for r in left.column("role_in").to_pylist()], left.column("text").to_pylist(), []
        for conv, a, b in runs(left):
            entry, leave, last = known.get(conv, (START, None, True))
            states, _ = path(roles[a:b], entry, leave)
            out += render(states, roles[a:b], texts[a:b], entry, last)
        return pa.table({"conv_id": left.column("conv_id"), "turn": left.column("turn"), "role_in": left.column("role_in"), "role_out": pa.array([x[0] for x in out], pa.string()), "action": pa.array([x[1] for x in out], pa.string()), "rendered": pa.array([x[2] for x in out], pa.string())})

    return dealt.groupBy("pid").cogroup(ends.groupBy("pid")).applyInArrow(each, f"conv_id {conv_type}, turn {turn_type}, role_in string, role_out string, action string, rendered string")
