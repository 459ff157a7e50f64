"""Reference counters that read one event at a time, and their work counters.

The list automaton is exact: it keeps, for each node, the times that can still be extended. The slot automaton counts
the relaxed form (lower limits 0) with one time a node. Both are single-threaded references and kernels of baselines;
the engine's own counting is in operators.chains and functions.carry.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterable, Sequence
from dataclasses import dataclass, field

import numpy as np

from episodic.model import Episode


#: What a completion adds to the path of an event, past any number of pushes.
DONE = 1 << 20


@dataclass
class Work:
    """Deterministic cost of a run: the stand-in for profiler counters."""

    events_seen: int = 0
    machine_steps: int = 0
    probes: int = 0
    pushes: int = 0
    peak_list: int = 0
    state_slots: int = 0
    completions: int = 0
    resets: int = 0


class ListAutomaton:
    """Exact machine of one episode. Times that no later event can use any more are dropped from the front.

    The lists are in order of time, so the newest time that is old enough is found by bisection; `probes` counts what a
    walk from the newest one would look at.
    """

    def __init__(self, episode: Episode, work: Work | None = None):
        self.nodes, self.edges = episode.nodes, episode.edges
        self.held: list[list[int]] = [[] for _ in self.edges]
        self.heads = [0] * len(self.edges)  # what lies before is dropped
        self.size = 0
        self.work = work or Work()
        self.places: dict[str, list[int]] = {}
        for i in range(len(self.nodes) - 1, -1, -1):  # later nodes first: an event never feeds itself
            self.places.setdefault(self.nodes[i], []).append(i)

    def lists(self) -> list[list[int]]:
        """What is held, for a store; take() puts it into a new machine."""
        return [q[h:] for q, h in zip(self.held, self.heads, strict=True)]

    def take(self, lists: list[list[int]]) -> None:
        for q, old in zip(self.held, lists, strict=False):
            q.extend(old)
            self.size += len(old)

    def _supported(self, i: int, t: int) -> bool:
        edge, held, head = self.edges[i - 1], self.held[i - 1], self.heads[i - 1]
        n = len(held)
        if head == n:
            return False
        if edge.high is not None and held[head] < t - edge.high:
            old, head = head, bisect_left(held, t - edge.high, head)
            self.work.probes += head - old
            self.size -= head - old
            if head > 1_000 and 2 * head > n:
                del held[:head]
                n, head = n - head, 0
            self.heads[i - 1] = head
        young = bisect_left(held, t - edge.low, head)
        self.work.probes += n - young + (young > head)
        return young > head

    def step(self, sym: str, t: int) -> bool:
        """Feed an event; True if it completes an occurrence, after which nothing is held."""
        w = self.work
        for i in self.places.get(sym, ()):
            w.machine_steps += 1
            if i and not self._supported(i, t):
                continue
            if i == len(self.edges):
                w.completions += 1
                w.resets += 1
                for h in self.held:
                    h.clear()
                self.heads = [0] * len(self.edges)
                self.size = 0
                return True
            self.held[i].append(t)
            w.pushes += 1
            self.size += 1
            if self.size > w.peak_list:
                w.peak_list = w.state_slots = self.size
        return False

    def run(self, times: list[int], syms: list[str], paths: list[int] | None = None) -> int:
        """Feeds events of the machine's own symbols as step() does, in one loop, and gives the number of completions.

        paths gets what each event did: the pushes, and DONE for a completion.
        """
        w, held, heads, size, last = self.work, self.held, self.heads, self.size, len(self.edges)
        steps = probes = pushes = done = 0
        peak = w.peak_list
        at = {s: [(i, *((self.edges[i - 1].low, self.edges[i - 1].high, held[i - 1]) if i else (0, None, None)), held[i] if i < last else None) for i in places] for s, places in self.places.items()}
        for t, s in zip(times, syms, strict=True):
            path = 0
            for i, low, high, before, own in at[s]:
                steps += 1
                if i:
                    head, n = heads[i - 1], len(before)
                    if head == n:
                        continue
                    if high is not None and before[head] < t - high:
                        old, head = head, bisect_left(before, t - high, head)
                        probes += head - old
                        size -= head - old
                        if head > 1_000 and 2 * head > n:
                            del before[:head]
                            n, head = n - head, 0
                        heads[i - 1] = head
                    young = bisect_left(before, t - low, head)
                    if young == head:
                        probes += n - young
                        continue
                    probes += n - young + 1
                if i == last:
                    done += 1
                    for h in held:
                        h.clear()
                    heads[:] = [0] * last
                    size = 0
                    path += DONE
                    break
                own.append(t)
                path += 1
                size += 1
                if size > peak:
                    peak = size
            pushes += path % DONE
            if paths is not None:
                paths.append(path)
        self.size = size
        w.machine_steps += steps
        w.probes += probes
        w.pushes += pushes
        w.completions += done
        w.resets += done
        if peak > w.peak_list:
            w.peak_list = w.state_slots = peak
        return done


class SlotAutomaton:
    """Relaxed machine: lower limits 0 and the newest time of each node.

    tie "safe" keeps the two newest distinct times, so that events at one time don't hide an earlier one; "printed"
    keeps one and accepts a delay of 0, which still bounds the exact count from above.
    """

    def __init__(self, episode: Episode, work: Work | None = None, tie: str = "safe"):
        if tie not in ("safe", "printed"):
            raise ValueError("tie is safe or printed")
        self.nodes, self.edges, self.safe = episode.nodes, episode.edges, tie == "safe"
        self.work = work or Work()
        self.work.state_slots = len(self.nodes)
        self.reset()
        self.places: dict[str, list[int]] = {}
        for i in range(len(self.nodes) - 1, -1, -1):
            self.places.setdefault(self.nodes[i], []).append(i)

    def reset(self) -> None:
        self.new: list[int | None] = [None] * len(self.edges)
        self.old: list[int | None] = [None] * len(self.edges)

    def step(self, sym: str, t: int) -> bool:
        w = self.work
        for i in self.places.get(sym, ()):
            w.machine_steps += 1
            if i:
                before = self.new[i - 1]
                w.probes += before is not None
                if self.safe and before == t:
                    before = self.old[i - 1]
                high = self.edges[i - 1].high
                if before is None or (high is not None and t - before > high):
                    continue
            if i == len(self.edges):
                w.completions += 1
                w.resets += 1
                self.reset()
                return True
            if self.new[i] != t:
                self.old[i], self.new[i] = self.new[i], t
            w.pushes += 1
        return False

    def run(self, times: list[int], syms: list[str], paths: list[int] | None = None) -> int:
        """As ListAutomaton.run."""
        w, new, old, last, safe = self.work, self.new, self.old, len(self.edges), self.safe
        steps = probes = pushes = done = 0
        at = {s: [(i, self.edges[i - 1].high if i else None) for i in places] for s, places in self.places.items()}
        for t, s in zip(times, syms, strict=True):
            path = 0
            for i, high in at[s]:
                steps += 1
                if i:
                    before = new[i - 1]
                    if before is None:
                        continue
                    probes += 1
                    if safe and before == t:
                        before = old[i - 1]
                        if before is None:
                            continue
                    if high is not None and t - before > high:
                        continue
                if i == last:
                    done += 1
                    new[:] = old[:] = [None] * last
                    path += DONE
                    break
                if new[i] != t:
                    old[i], new[i] = new[i], t
                path += 1
            pushes += path % DONE
            if paths is not None:
                paths.append(path)
        w.machine_steps += steps
        w.probes += probes
        w.pushes += pushes
        w.completions += done
        w.resets += done
        return done


MACHINES = {"list": ListAutomaton, "slot": SlotAutomaton}


def list_automaton(times: Sequence[int], syms: Sequence[str], episode: Episode, work: Work | None = None) -> tuple[int, list[int]]:
    """(count, end times) of the greedy non-overlapped occurrences of one episode in an ordered stream."""
    m = ListAutomaton(episode, work)
    ends = [t for t, s in zip(times, syms, strict=True) if m.step(s, t)]
    m.work.events_seen += len(times)
    return len(ends), ends


def slot_automaton(times: Sequence[int], syms: Sequence[str], episode: Episode, tie: str = "safe", work: Work | None = None) -> tuple[int, list[int]]:
    """As list_automaton for the relaxed form of the episode."""
    m = SlotAutomaton(episode, work, tie)
    ends = [t for t, s in zip(times, syms, strict=True) if m.step(s, t)]
    m.work.events_seen += len(times)
    return len(ends), ends


@dataclass
class MachineBank:
    """Many machines advanced piece by piece of the stream, each through the events of its own symbols."""

    episodes: dict[int, Episode]
    kernel: str = "list"
    work: Work = field(default_factory=Work)

    def __post_init__(self):
        self.machines = {k: MACHINES[self.kernel](e, Work()) for k, e in self.episodes.items()}
        self.counts = dict.fromkeys(self.episodes, 0)
        self.divergent = 0

    def feed(self, times: Iterable[int], syms: Iterable[str], group: int | None = None) -> None:
        """The next events of the stream. divergent: events at which machines of one group take different paths, if group is given.

        A machine runs through the whole piece before the next one does: its state stays at hand. At an event of a symbol
        that some machine of a group has not, that one stays idle, so only symbols of all of them need their paths.
        """
        times, syms = list(times), list(syms)
        self.work.events_seen += len(times)
        names = {s: c for c, s in enumerate(dict.fromkeys(syms))}
        codes = np.fromiter(map(names.__getitem__, syms), np.int64, len(syms))
        ids, use, own = list(self.episodes), None, ([], [], codes)
        many = group or max(1, len(ids))
        for lane in (ids[i : i + many] for i in range(0, len(ids), many)):
            used = [frozenset(self.episodes[k].nodes) for k in lane]
            shared = frozenset.intersection(*used) if group and len(lane) > 1 else frozenset()
            full = np.array([s in shared for s in names], bool)
            first, split = None, None
            for k, mine in zip(lane, used, strict=True):
                if mine != use:
                    at = np.flatnonzero(np.array([s in mine for s in names], bool)[codes]) if names else codes
                    use, own = mine, ([times[i] for i in at.tolist()], [syms[i] for i in at.tolist()], codes[at])
                paths: list[int] | None = [] if shared else None
                self.counts[k] += self.machines[k].run(own[0], own[1], paths)
                if paths:
                    path = np.array(paths)[full[own[2]]]
                    first, split = (path, np.zeros(len(path), bool)) if first is None else (first, split | (path != first))
            if group and len(lane) > 1:
                idle = frozenset.union(*used) - shared
                self.divergent += sum(int((codes == c).sum()) for s, c in names.items() if s in idle) + (int(split.sum()) if split is not None else 0)

    def run(self, times: Iterable[int], syms: Iterable[str], group: int = 32) -> dict[int, int]:
        """Counts by episode of a whole stream, and its work."""
        self.feed(times, syms, group)
        self.total()
        return self.counts

    def total(self) -> None:
        """Sums the machines' work; once, at the end of the stream."""
        for m in self.machines.values():
            for f in ("machine_steps", "probes", "pushes", "completions", "resets", "state_slots"):
                setattr(self.work, f, getattr(self.work, f) + getattr(m.work, f))
            self.work.peak_list = max(self.work.peak_list, m.work.peak_list)


class SlotBank:
    """All relaxed machines of one size advanced together: their state has a fixed shape, so an event is a few array steps.

    Exact machines have no such form, because their lists differ in length.
    """

    def __init__(self, episodes: dict[int, Episode]):
        self.ids = list(episodes)
        self.size = len(next(iter(episodes.values())).nodes)
        self.at: dict[str, list[tuple[int, np.ndarray]]] = {}
        for i in range(self.size - 1, -1, -1):
            by: dict[str, list[int]] = {}
            for r, e in enumerate(episodes.values()):
                by.setdefault(e.nodes[i], []).append(r)
            for s, rows in by.items():
                self.at.setdefault(s, []).append((i, np.array(rows)))
        edges = max(1, self.size - 1)
        never = -(1 << 62)
        self.never = never
        self.high = np.array([[(1 << 61) if x.high is None else x.high for x in e.edges] or [0] for e in episodes.values()], np.int64).T.copy()
        self.new = np.full((edges, len(episodes)), never, np.int64)
        self.old = self.new.copy()

    def run(self, times: Iterable[int], syms: Iterable[str]) -> dict[int, int]:
        count = np.zeros(len(self.ids), np.int64)
        new, old, high, last = self.new, self.old, self.high, self.size - 1
        done = np.zeros(len(self.ids), bool)
        for t, s in zip(times, syms, strict=True):
            ended = None
            for i, rows in self.at.get(s, ()):
                if ended is not None:
                    rows = rows[~done[rows]]
                if i:
                    before = new[i - 1, rows]
                    before = np.where(before == t, old[i - 1, rows], before)
                    rows = rows[(before > self.never) & (t - before <= high[i - 1, rows])]
                if not len(rows):
                    continue
                if i == last:
                    count[rows] += 1
                    done[rows], ended = True, rows
                    continue
                fresh = rows[new[i, rows] != t]
                old[i, fresh] = new[i, fresh]
                new[i, fresh] = t
            if ended is not None:
                new[:, ended] = self.never
                old[:, ended] = self.never
                done[ended] = False
        return dict(zip(self.ids, count.tolist(), strict=True))


class SlotBanks:
    """Relaxed machines of any sizes, a bank for each, fed a stream in pieces."""

    def __init__(self, episodes: dict[int, Episode]):
        self.counts = dict.fromkeys(episodes, 0)
        self.banks = [SlotBank({k: e for k, e in episodes.items() if len(e.nodes) == n}) for n in sorted({len(e.nodes) for e in episodes.values()})]

    def feed(self, times: Sequence[int], syms: Sequence[str]) -> None:
        for bank in self.banks:
            for k, n in bank.run(times, syms).items():
                self.counts[k] += n


def slot_counts(episodes: dict[int, Episode], times: Sequence[int], syms: Sequence[str]) -> dict[int, int]:
    """Relaxed counts of many episodes of any sizes."""
    banks = SlotBanks(episodes)
    banks.feed(times, syms)
    return banks.counts
