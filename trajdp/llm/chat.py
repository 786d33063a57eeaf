"""Chat formatting: conversations repaired at least cost to a legal order of turns.

Legal turns are the paths of an automaton: an optional system turn, then user
and assistant in turn, the last one the assistant's. Turns may be merged into
the one before, given another role, or preceded by empty turns of the roles that
are missing. Dynamic programming over the automaton's states finds the cheapest
repair. Conversations are read in ranges of (conversation, turn), whatever their
length: a range sums up the parts of conversations that cross its ends as
matrices of costs between states, which are chained to find where each part
starts and ends.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import written

#: States are the role of the turn before (0: none yet).
ROLES = ("", "system", "user", "assistant")
LEGAL = {0: (1, 2), 1: (2,), 2: (3,), 3: (2,)}
NAMES = {"system": 1, "developer": 1, "user": 2, "human": 2, "prompter": 2, "assistant": 3, "bot": 3, "model": 3, "gpt": 3}
LAST = 3
FAR = 1 << 40


@dataclass(frozen=True)
class RepairCosts:
    """unknown: cost of giving a role to a turn whose own is null or not known."""

    merge: int = 2
    relabel: int = 3
    insert: int = 4
    unknown: int = 1


@lru_cache(maxsize=None)
def inserted(a: int, b: int) -> tuple[int, ...] | None:
    """The fewest roles to put between states a and b (b excluded); None if b can't be reached."""
    paths = [(a, ())]
    for _ in range(len(ROLES)):
        for last, path in paths:
            if b in LEGAL[last]:
                return path
        paths = [(n, (*path, n)) for last, path in paths for n in LEGAL[last]]
    return None


def link(a: int, b: int, costs: RepairCosts) -> tuple[int, bool]:
    """Cost from state a to a turn of role b, and whether the turn is merged into the one before."""
    path = inserted(a, b)
    new = FAR if path is None else costs.insert * len(path)
    return (costs.merge, True) if a == b and costs.merge <= new else (new, False)


def step(role: int, costs: RepairCosts) -> np.ndarray:
    """Costs from each state to each state over a turn of the role (0: unknown)."""
    m = np.full((4, 4), FAR, np.int64)
    for b in (1, 2, 3):
        label = 0 if b == role else costs.unknown if role == 0 else costs.relabel
        for a in range(4):
            m[a, b] = min(FAR, link(a, b, costs)[0] + label)
    return m


def closing_roles(a: int) -> tuple[int, ...]:
    return () if a == LAST else (*inserted(a, LAST), LAST)


def opened(before: int, role: int) -> str:
    return ("<|end|>\n" if before else "") + f"<|{ROLES[role]}|>\n"


class Tables:
    """What each move of the automaton costs and renders, by state, role and the turn's own role."""

    def __init__(self, costs: RepairCosts):
        self.steps = np.stack([step(r, costs) for r in range(4)])
        self.closing = np.array([costs.insert * len(closing_roles(a)) for a in range(4)], np.int64)
        most = 4
        self.added = np.zeros((4, 4), np.int64)  # turns put in before a turn of the role
        self.added_role = np.zeros((4, 4, most), np.int64)
        self.added_text = np.full((4, 4, most), "", object)
        self.own_text = np.full((4, 4), "", object)
        self.own_cost = np.zeros((4, 4, 4), np.int64)
        self.own_action = np.full((4, 4, 4), "", object)
        for a in range(4):
            for b in (1, 2, 3):
                cost, merge = link(a, b, costs)
                last = a
                for j, r in enumerate(() if merge else inserted(a, b) or ()):
                    self.added[a, b], self.added_role[a, b, j], self.added_text[a, b, j] = j + 1, r, opened(last, r)
                    last = r
                self.own_text[a, b] = "\n" if merge else opened(last, b)
                for own in range(4):
                    label = 0 if own == b else costs.unknown if own == 0 else costs.relabel
                    self.own_cost[a, b, own] = label + (cost if merge else 0)
                    self.own_action[a, b, own] = ("merge" if merge else "keep") + ("+relabel" if label else "")
        self.ends = np.array([len(closing_roles(a)) for a in range(4)], np.int64)
        self.end_role = np.zeros((4, most), np.int64)
        self.end_text = np.full((4, most), "", object)
        for a in range(4):
            last = a
            for j, r in enumerate(closing_roles(a)):
                self.end_role[a, j], self.end_text[a, j] = r, opened(last, r)
                last = r
        self.insert = costs.insert


@lru_cache(maxsize=4)
def tables(costs: RepairCosts) -> Tables:
    return Tables(costs)


def matrix(roles: np.ndarray, costs: RepairCosts) -> np.ndarray:
    """Costs from each state to each state over a run of turns: neighbouring turns' matrices meet in pairs, until one is left."""
    m = np.where(np.eye(4, dtype=bool), 0, FAR)[None] if not len(roles) else tables(costs).steps[np.asarray(roles, int)]
    while len(m) > 1:
        odd = m[len(m) & ~1 :]
        left, right = m[0 : len(m) & ~1 : 2], m[1 : len(m) & ~1 : 2]
        m = np.concatenate([np.minimum((left[:, :, :, None] + right[:, None]).min(axis=2), FAR), odd])
    return m[0]


def cheapest(roles: np.ndarray, sizes: np.ndarray, costs: RepairCosts, start: int = 0, end: int | None = None) -> np.ndarray:
    """The role of each turn in the cheapest repair of runs of ``sizes`` turns, from a state to a state (None: to a legal end).

    All runs go ahead together, turn by turn. Of equal costs the earlier state
    in ROLES wins, from the last turn backwards.
    """
    t, roles, sizes = tables(costs), np.asarray(roles, np.int64), np.asarray(sizes, np.int64)
    first = np.cumsum(sizes) - sizes
    best = np.full((len(sizes), 4), FAR, np.int64)
    best[:, start] = 0
    back = np.zeros((len(roles), 4), np.int8)
    order = np.argsort(-sizes, kind="stable")  # of these, the runs that have a turn k come first
    longest = sizes[order]
    count = np.searchsorted(-longest, -np.arange(int(longest[0]) if len(longest) else 0), side="left")
    for k, n in enumerate(count.tolist()):
        run = order[:n]
        at = first[run] + k
        through = best[run][:, :, None] + t.steps[roles[at]]
        back[at] = through.argmin(axis=1)
        best[run] = through.min(axis=1)
    state = (best + t.closing).argmin(axis=1) if end is None else np.full(len(sizes), end)
    out = np.zeros(len(roles), np.int64)
    for k in range(len(count) - 1, -1, -1):
        run = order[: count[k]]
        at = first[run] + k
        out[at] = state[run]
        state[run] = back[at, state[run]]
    return out


COLUMNS = ["conv_id", "turn", "part", "role", "action", "cost", "rendered"]


NAME = np.array(ROLES, object)


def repaired(run: pd.DataFrame, sizes: np.ndarray, costs: RepairCosts, start: int, end: int | None) -> pd.DataFrame:
    """The repaired turns of runs, each with its fragment of the rendered text: joined in order they are all of it."""
    t, own = tables(costs), run["own"].to_numpy(np.int64)
    role = cheapest(own, sizes, costs, start, end)
    sizes = np.asarray(sizes, np.int64)
    before = np.r_[0, role[:-1]] if len(role) else role
    before[np.cumsum(sizes) - sizes] = start
    conv, turn = run["conv_id"].to_numpy(), run["turn"].to_numpy()
    text = np.array([x if isinstance(x, str) else "" for x in run["text"]], object)

    rows = t.added[before, role] + 1
    at = np.repeat(np.arange(len(role)), rows)
    part = np.arange(len(at)) - np.repeat(np.cumsum(rows) - rows, rows)
    mine = part == rows[at] - 1
    a, b, o = before[at], role[at], own[at]
    out = [pd.DataFrame({
        "conv_id": conv[at], "turn": turn[at], "part": part, "role": NAME[np.where(mine, b, t.added_role[a, b, np.minimum(part, 3)])],
        "action": np.where(mine, t.own_action[a, b, o], "insert"), "cost": np.where(mine, t.own_cost[a, b, o], t.insert),
        "rendered": np.where(mine, t.own_text[a, b] + text[at], t.added_text[a, b, np.minimum(part, 3)]),
    })]
    if end is None and len(role):
        last = np.cumsum(sizes) - 1
        state, n = role[last], t.ends[role[last]]
        at = np.repeat(np.arange(len(last)), n + 1)
        j = np.arange(len(at)) - np.repeat(np.cumsum(n + 1) - n - 1, n + 1)
        close = j == n[at]
        put = t.end_role[state[at], np.minimum(j, 3)]
        final = np.where(n > 0, t.end_role[state, np.maximum(n - 1, 0)], state)
        out.append(pd.DataFrame({
            "conv_id": conv[last][at], "turn": turn[last][at], "part": np.where(close, 2000, 1000 + j), "role": NAME[np.where(close, final[at], put)],
            "action": np.where(close, "end", "insert"), "cost": np.where(close, 0, t.insert), "rendered": np.where(close, "<|end|>\n", t.end_text[state[at], np.minimum(j, 3)]),
        }))
    return pd.concat(out, ignore_index=True)[COLUMNS] if len(run) else pd.DataFrame(columns=COLUMNS)


def filled(run: pd.DataFrame) -> pd.DataFrame:
    """The run with all columns of the intermediate table: numbers it lacks are -1, other values null."""
    for c in ("kind", "pid", "run", "m", "own", "text", *COLUMNS):
        if c not in run:
            run[c] = pd.Series([None] * len(run), dtype=object, index=run.index) if c in ("m", "text", "role", "action", "rendered") else -1
    return run[["kind", "pid", "run", "m", "own", "text", *COLUMNS]]


def formatted(turns: DataFrame, costs: RepairCosts = RepairCosts()) -> DataFrame:
    """The repaired turns: conv_id, turn, part, role, action, cost, rendered.

    ``turns`` needs conv_id, turn, role and text; other columns are ignored.
    Each turn gives one row, and each inserted turn one before it (``part``
    orders them); after a conversation's last turn come the turns that it lacks
    and an ``end`` row. ``rendered`` joined by (turn, part) is the rendered
    conversation; turns of equal number are ordered by role and text and then
    numbered by their order of reading in the row they follow. Null roles and
    unknown names are unknown roles, null texts are empty, null conv_ids are one
    conversation, null turns come first. An empty table gives no rows.
    """
    kinds = dict(turns.dtypes)
    code = F.coalesce(*[F.when(F.lower(F.trim("role")) == k, v) for k, v in NAMES.items()], F.lit(0))
    rows = turns.select("conv_id", "turn", code.alias("own"), "text", F.coalesce(F.length("text"), F.lit(0)).alias("size"))
    order = ["conv_id", "turn", "own", "size", "text"]
    rows = rows.repartitionByRange(*order).sortWithinPartitions(*order)
    fields = f"conv_id {kinds['conv_id']}, turn {kinds['turn']}, part int, role string, action string, cost int, rendered string"

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        """Repairs conversations that lie inside a range; passes on the others' turns and their cost matrices."""
        context = TaskContext.get()
        pid, number, kept, key = context.partitionId() if context else 0, 0, [], None

        def open_run(last: int) -> pd.DataFrame:
            run = pd.concat(kept, ignore_index=True)
            m = matrix(run["own"].to_numpy(np.int64), costs)
            run = run.assign(pid=pid, run=last, m=None)
            run.at[0, "m"] = m.ravel().tolist()
            return filled(run.assign(kind="open"))

        def done(rows: pd.DataFrame, sizes: np.ndarray) -> pd.DataFrame:
            return filled(repaired(rows, sizes, costs, 0, None).assign(kind="done"))

        for batch in batches:
            if not len(batch):
                continue
            ids, null = batch["conv_id"], batch["conv_id"].isna().to_numpy()
            change = ((ids != ids.shift()).to_numpy() & ~(null & np.r_[False, null[:-1]])).astype(bool)
            change[0] = key is not None and (bool(null[0]), None if null[0] else ids.iloc[0]) != key
            at = np.flatnonzero(change)
            key = (bool(null[-1]), None if null[-1] else ids.iloc[-1])
            if not len(at):
                kept.append(batch)
                continue
            kept.append(batch.iloc[: at[0]])
            if number == 0:  # the range's first conversation may have begun before
                yield open_run(0)
            else:
                run = pd.concat(kept, ignore_index=True)
                yield done(run, np.array([len(run)]))
            number = 1
            if len(at) > 1:
                yield done(batch.iloc[at[0] : at[-1]], np.diff(at))
            kept = [batch.iloc[at[-1] :]]
        if kept:
            yield open_run(number)

    schema = f"kind string, pid int, run int, m array<long>, own int, text string, {fields}"
    table = written(rows.select("conv_id", "turn", "own", "text").mapInPandas(cut, schema), "chat-runs")
    finished = table.where("kind = 'done'").select(*COLUMNS)

    # two runs at most for each range: their matrices are few and small
    ends = sorted(table.where("m is not null").select("pid", "run", "conv_id", "m").collect(), key=lambda r: (r["pid"], r["run"]))
    known: dict[tuple[int, int], tuple[int, int | None]] = {}
    for group in chained(ends):
        best = np.full((len(group) + 1, 4), FAR, np.int64)
        best[0, 0] = 0
        ms = [np.array(r["m"]).reshape(4, 4) for r in group]
        for k, m in enumerate(ms):
            best[k + 1] = np.minimum((best[k][:, None] + m).min(axis=0), FAR)
        state, path = int((best[-1] + tables(costs).closing).argmin()), []
        for k in range(len(group) - 1, -1, -1):
            before = int((best[k] + ms[k][:, state]).argmin())
            path.append((group[k], before, state))
            state = before
        for k, (r, before, after) in enumerate(path):
            known[r["pid"], r["run"]] = before, None if k == 0 else after

    def finish(run: pd.DataFrame) -> pd.DataFrame:
        start, end = known[int(run["pid"].iloc[0]), int(run["run"].iloc[0])]
        run = run.assign(size=[len(t) if isinstance(t, str) else 0 for t in run["text"]], t=[t if isinstance(t, str) else "" for t in run["text"]])
        run = run.sort_values(["turn", "own", "size", "t"], kind="stable", na_position="first")
        return repaired(run, np.array([len(run)]), costs, start, end)

    crossing = table.where("kind = 'open'").groupBy("pid", "run").applyInPandas(finish, fields)
    return finished.unionByName(crossing)


def chained(ends: list) -> list[list]:
    """Neighbouring runs of the same conversation."""
    out: list[list] = []
    for r in ends:
        if out and out[-1][-1]["pid"] != r["pid"] and out[-1][-1]["conv_id"] == r["conv_id"]:
            out[-1].append(r)
        else:
            out.append([r])
    return out


def op4_chat_formatting(spark, sf_dir: str) -> DataFrame:
    return formatted(spark.read.parquet(f"{sf_dir}/conversations.parquet"))
