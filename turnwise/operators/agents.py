"""Scripted agents. Each has a behaviour that is known in closed form; none stands for a real model.

An agent is told where a run stands (a State) and gives one act: ("ASK", text) or ("SQL", text).
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable
from dataclasses import dataclass, field

Act = tuple[str, str]


@dataclass
class State:
    """What an agent may use: the sample's annotations, and what has happened so far."""

    run_id: str
    sample_type: str
    l1_question: str
    l2_question: str
    gold_pre: str
    gold_post: str
    other_pre: str  # the query of the alternative reading
    other_post: str
    drifted: bool = False
    asks: int = 0
    replies: list[str] = field(default_factory=list)
    last_sql: str | None = None

    @property
    def chained(self) -> bool:
        return self.sample_type in ("C", "J")


def _query(s: State, right: bool) -> str:
    if s.drifted:
        return s.gold_post if right else s.other_post
    return s.gold_pre if right else s.other_pre


def gold(s: State) -> Act:
    if s.chained and s.asks < 2 and not s.drifted:
        return "ASK", s.l1_question if s.asks == 0 else s.l2_question
    return "SQL", _query(s, True)


def silent(s: State) -> Act:
    return "SQL", _query(s, not s.chained)


def ask_everything(s: State) -> Act:
    if s.asks < 2 and not s.drifted:
        return "ASK", "zzz qqq"
    return "SQL", _query(s, not s.chained)


def ask_l1_only(s: State) -> Act:
    if s.chained and s.asks < 1 and not s.drifted:
        return "ASK", s.l1_question
    return "SQL", _query(s, not s.chained)


def ask_both(s: State) -> Act:
    return gold(s)


def accumulate(s: State) -> Act:
    """Never drops a commitment: after the drift one more condition is put on the same query."""
    if s.drifted:
        return "SQL", f"{s.last_sql} AND 1 = 1" if " where " in (s.last_sql or "").lower() else f"{s.last_sql} WHERE 1 = 1"
    return "SQL", _query(s, True)


def ignore_drift(s: State) -> Act:
    return "SQL", s.last_sql if s.drifted else _query(s, True)


def wipe_filters(s: State) -> Act:
    if s.drifted:
        low = s.last_sql.lower()
        return "SQL", s.last_sql[: low.index(" where ")] if " where " in low else s.last_sql
    return "SQL", _query(s, True)


def wrong_target(s: State) -> Act:
    """Drops the first condition, whatever the user took back."""
    if s.drifted:
        head, mark, tail = s.last_sql.partition(" WHERE ")
        rest = tail.split(" AND ", 1)
        return "SQL", f"{head}{mark}{rest[1]}" if len(rest) > 1 else head
    return "SQL", _query(s, True)


def inherit_chain_error(s: State) -> Act:
    if s.chained and s.asks < 1 and not s.drifted:
        return "ASK", s.l1_question
    return "SQL", _query(s, not s.chained)


def broken_sql(s: State) -> Act:
    return "SQL", "SELECT FROM WHERE"


def replay(chain: float, drift: float, seed: str = "r") -> Callable[[State], Act]:
    """Right with the given rates, independently, by hash of the anchor part of the run id."""

    def act(s: State) -> Act:
        def luck(salt: str) -> float:
            return int(hashlib.md5(f"{seed}|{salt}|{s.run_id.split('|')[0]}".encode()).hexdigest()[:8], 16) / 2**32  # noqa: S324

        right = not s.chained or luck("chain") < chain
        if s.drifted and luck("drift") >= drift:
            return "SQL", s.last_sql
        return "SQL", _query(s, right)

    return act


SCRIPTED: dict[str, Callable[[State], Act]] = {
    f.__name__: f for f in (gold, silent, ask_everything, ask_l1_only, ask_both, accumulate, ignore_drift, wipe_filters, wrong_target, inherit_chain_error, broken_sql)
}
