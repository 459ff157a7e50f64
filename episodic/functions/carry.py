"""Carry maps: what one time segment does to a greedy selection that comes in from the left.

The only thing that a selection carries across a segment's start is the position of its last accepted end. For each
such position the segment gives how many intervals it accepts and which end it hands on. The map is a list of steps
(upper position, count, position handed on): the first step whose upper position exceeds the incoming one applies, and
past all steps the segment changes nothing. Maps compose associatively, left to right.

Positions are (time, event id); the steps of a map are sorted by them.
"""

from __future__ import annotations

import numpy as np

Step = tuple[int, int, int, int, int]  # upper time, upper id, count, time handed on, id handed on
TOP = (1 << 62, 1 << 62)
STEP_SQL = "struct<ut:bigint,ue:bigint,cnt:bigint,ot:bigint,oe:bigint>"


def _next_free(st: np.ndarray, se: np.ndarray, et: np.ndarray, ee: np.ndarray) -> np.ndarray:
    """For each interval end the first interval that starts after it; starts are in order of position."""
    lo, hi = np.searchsorted(st, et, "left"), np.searchsorted(st, et, "right")
    j = np.flatnonzero(lo < hi)  # starts at the very time of the end: ids decide, by one binary search for all at once
    a, b = lo[j], hi[j]
    while (open_ := a < b).any():
        m = (a + b) // 2
        up = open_ & (se[np.minimum(m, len(se) - 1)] <= ee[j])
        a, b = np.where(up, m + 1, a), np.where(open_ & ~up, m, b)
    hi[j] = a
    return hi


def carry_map(st: np.ndarray, se: np.ndarray, et: np.ndarray, ee: np.ndarray, bound: int) -> list[Step]:
    """carry_steps as a list of steps."""
    return [tuple(s) for s in carry_steps(st, se, et, ee, bound).tolist()]


def carry_steps(st: np.ndarray, se: np.ndarray, et: np.ndarray, ee: np.ndarray, bound: int) -> np.ndarray:
    """The map of a segment (bound, ...] from its intervals in order of end, a row for each step; starts are in order too.

    A map can have a step for every start before the bound (selections in a regular stream never meet), so steps stay
    arrays from here to the count.

    All selections that can come in are followed at once, each to its next interval. Those that meet go on as one, so
    only what is accepted is looked up, not every interval of the segment. Some never meet (of A-(0,9]->A the odd and
    the even ones); after n / 512 rounds the next intervals of all are found at once and the rest is followed by them.
    """
    n = len(et)
    if not n:
        return np.zeros((0, 5), np.int64)
    inside = int(np.searchsorted(st, bound, "right"))
    first = np.arange(min(inside, n - 1) + 1)
    rounds: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []  # distinct intervals, which go on, and to which of the next round
    at = first
    while len(at) > 1 and len(rounds) <= n // 512:
        to = _next_free(st, se, et[at], ee[at])
        on = to < n
        after, which = np.unique(to[on], return_inverse=True)
        rounds.append((at, on, which))
        at = after
    count, last = np.ones(len(at), np.int64), at.copy()
    if len(at) == 1:
        count[0], last[0] = _alone(st, se, et, ee, int(at[0]))
    elif len(at):
        count, last = _followed(st, se, et, ee, at)
    for at, on, which in reversed(rounds):
        c, z = np.ones(len(at), np.int64), at.copy()
        c[on] += count[which]
        z[on] = last[which]
        count, last = c, z
    # of starts that go on alike the last is the limit, and of starts at one position the first decides
    ut, ue = st[first].copy(), se[first].copy()
    if inside < n:
        ut[-1], ue[-1] = TOP
    new = np.ones(len(first), bool)
    new[1:] = (ut[1:] != ut[:-1]) | (ue[1:] != ue[:-1])
    k = np.flatnonzero(new)
    k = k[np.append((count[k][1:] != count[k][:-1]) | (last[k][1:] != last[k][:-1]), True)]
    return np.stack([ut[k], ue[k], count[k], et[last[k]], ee[last[k]]], axis=1)


def apply_map(steps: list[Step], t: int, e: int) -> tuple[int, int, int]:
    """(accepted, time, id) of a selection whose last end is at (t, e)."""
    for ut, ue, c, ot, oe in steps:
        if (ut, ue) > (t, e):
            return c, ot, oe
    return 0, t, e


def compose(left: list[Step], right: list[Step]) -> list[Step]:
    """The map of two neighbouring segments."""
    out: list[Step] = []
    for ut, ue, c, ot, oe in left:
        more, t, e = apply_map(right, ot, oe)
        if out and out[-1][2:] == (c + more, t, e):
            out[-1] = (ut, ue, c + more, t, e)
        else:
            out.append((ut, ue, c + more, t, e))
    if left and left[-1][:2] == TOP:
        return out
    top = left[-1][:2] if left else (-(1 << 62), -(1 << 62))
    return out + [s for s in right if s[:2] > top]


def apply_steps(steps: np.ndarray, t: int, e: int) -> tuple[int, int, int]:
    """apply_map for steps as rows of an array."""
    at = _next_after(steps[:, 0], steps[:, 1], t, e)
    return tuple(steps[at, 2:].tolist()) if at < len(steps) else (0, t, e)


def compose_steps(left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """compose for steps as rows of arrays."""
    at, out = _next_free(right[:, 0], right[:, 1], left[:, 3], left[:, 4]), left.copy()
    on = at < len(right)
    out[on, 2] += right[at[on], 2]
    out[on, 3:] = right[at[on], 3:]
    if not len(left):
        return right.copy()  # not a view of the batch that it came in
    out = out[np.append((out[1:, 2:] != out[:-1, 2:]).any(axis=1), True)]  # of steps that go on alike the last is the limit
    top = tuple(left[-1, :2].tolist())
    return out if top == TOP else np.concatenate([out, right[_next_after(right[:, 0], right[:, 1], *top) :]])


def chain_starts(events: dict[str, tuple[np.ndarray, np.ndarray]], nodes: tuple[str, ...], edges: tuple, memo: dict | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(start time, start id, end time, end id) of each event that can end the episode, with its latest start.

    events: times and ids of each symbol in order. Latest starts never fall with the end, so the newest event before
    t - low of the shorter chain is the only one to look at; it serves if it isn't older than t - high. memo keeps the
    tables of prefixes, which candidates with a common beginning share.
    """
    memo = {} if memo is None else memo
    done = memo.get((nodes, edges))
    if done is not None:
        return done
    none = np.zeros(0, np.int64)
    t, e = events.get(nodes[-1], (none, none))
    if len(nodes) == 1:
        out = (t, e, t, e)
    else:
        ps, pe, pt, _ = chain_starts(events, nodes[:-1], edges[:-1], memo)
        low, high = edges[-1]
        if not len(pt) or not len(t):
            out = (none, none, none, none)
        else:
            at = np.searchsorted(pt, t - low, "left") - 1
            ok = at >= 0
            if high is not None:
                ok &= t - pt[np.maximum(at, 0)] <= high
            at = at[ok]
            out = (ps[at], pe[at], t[ok], e[ok])
    memo[(nodes, edges)] = out
    return out


def by_time(t: np.ndarray, e: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(time, first id, last id) of each distinct time of one symbol's events in order of (t, e)."""
    new = np.ones(len(t), bool)
    new[1:] = t[1:] != t[:-1]
    if new.all():
        return t, e, e
    at = np.flatnonzero(new)
    return t[at], e[at], e[np.append(at[1:], len(t)) - 1]


def chain_ends(events: dict[str, tuple[np.ndarray, np.ndarray, np.ndarray]], nodes: tuple[str, ...], edges: tuple, memo: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """chain_starts with one row, the first, for each time at which the episode can end; events as by_time gives them.

    All ends at one time have the same latest start, so the others are never accepted, and a longer chain looks at times
    only. An episode of one node has no such rows: each of its events is an occurrence.
    """
    done = memo.get((nodes, edges))
    if done is not None:
        return done
    none = np.zeros(0, np.int64)
    t, first, last = events.get(nodes[-1], (none, none, none))
    if len(nodes) == 1:
        out = (t, last, t, first)
    else:
        ps, pe, pt, _ = chain_ends(events, nodes[:-1], edges[:-1], memo)
        low, high = edges[-1]
        if not len(pt) or not len(t):
            out = (none, none, none, none)
        else:
            at = np.searchsorted(pt, t - low, "left") - 1
            ok = at >= 0
            if high is not None:
                ok &= t - pt[np.maximum(at, 0)] <= high
            at = at[ok]
            out = (ps[at], pe[at], t[ok], first[ok])
    memo[(nodes, edges)] = out
    return out


def earliest_ends(st: np.ndarray, se: np.ndarray, et: np.ndarray, ee: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of intervals with one start the first only; no selection accepts another one."""
    new = np.ones(len(st), bool)
    new[1:] = (st[1:] != st[:-1]) | (se[1:] != se[:-1])
    return (st, se, et, ee) if new.all() else (st[new], se[new], et[new], ee[new])


def by_prefix(episodes: list[tuple]) -> list[tuple]:
    """(id, nodes, edges) in an order in which those that share a prefix follow one another."""
    return sorted(episodes, key=lambda x: (x[1][0], *zip(((e[0], e[1] is None, e[1] or 0) for e in x[2]), x[1][1:], strict=True)))


def keep_prefixes(memo: dict, nodes: tuple[str, ...], edges: tuple) -> None:
    """Forget the tables that the episode does not begin with: as many are held as it has nodes, however many are counted."""
    for n, e in [k for k in memo if k != (nodes[: len(k[0])], edges[: len(k[1])])]:
        del memo[n, e]


def greedy(st: np.ndarray, se: np.ndarray, et: np.ndarray, ee: np.ndarray) -> list[int]:
    """Places of the intervals, in order of end, that earliest-end selection accepts."""
    return _accepted(st, se, et, ee, 0)


def _followed(st: np.ndarray, se: np.ndarray, et: np.ndarray, ee: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(count, last) of the selections from each of the intervals `at`, in order, on: the next ones of all are found at
    once, then those 2, 4, 8 ... further, until no selection has as many."""
    low, end = int(at[0]), len(et) - int(at[0])
    jumps = [np.append(_next_free(st[low:], se[low:], et[low:], ee[low:]), end)]  # past the end nothing moves
    while (jumps[-1][at - low] < end).any():
        jumps.append(jumps[-1][jumps[-1]])
    count, last = np.ones(len(at), np.int64), at - low
    for power in reversed(range(len(jumps))):
        to = jumps[power][last]
        on = to < end
        count[on] += 1 << power
        last[on] = to[on]
    return count, last + low


def _alone(st: np.ndarray, se: np.ndarray, et: np.ndarray, ee: np.ndarray, i: int) -> tuple[int, int]:
    """(count, last) of one selection from the interval i on; each accepted one is looked up alone while they are few."""
    n, count, last = len(et), 0, i
    few = (n - i) // 128
    while i < n and count < few:
        count, last = count + 1, i
        i = int(_next_after(st, se, et[i], ee[i]))
    if i < n:
        more, z = _followed(st, se, et, ee, np.array([i]))
        count, last = count + int(more[0]), int(z[0])
    return count, last


def _accepted(st: np.ndarray, se: np.ndarray, et: np.ndarray, ee: np.ndarray, i: int) -> list[int]:
    """What is accepted from the interval i on.

    Each accepted one is looked up alone; once they are many against the intervals, the next ones of all are found at once.
    """
    n = len(et)
    few, out = (n - i) // 64, []
    while i < n and len(out) < few:
        out.append(i)
        i = int(_next_after(st, se, et[i], ee[i]))
    if i < n:
        hop = (i + _next_free(st[i:], se[i:], et[i:], ee[i:])).tolist()
        start = i
        while i < n:
            out.append(i)
            i = hop[i - start]
    return out


def _next_after(st: np.ndarray, se: np.ndarray, t: int, e: int) -> int:
    """The first interval that starts after the position (t, e)."""
    lo, hi = np.searchsorted(st, t, "left"), np.searchsorted(st, t, "right")
    return lo + np.searchsorted(se[lo:hi], e, "right") if lo < hi else hi
