"""Worked examples and random streams: automata, latest starts, carry maps and brute force agree."""

import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from episodic.functions.automata import MachineBank, Work, list_automaton, slot_automaton, slot_counts
from episodic.functions.carry import apply_map, by_prefix, carry_map, chain_starts, compose, greedy, keep_prefixes
from episodic.model import Episode, Interval, format_episode, parse_episode
from episodic.operators import occurrences as listing
from episodic.operators.stitch import machine_tuple
from tests.brute import occurrences, support


def ep(text):
    return parse_episode(text)


def seq(text):
    return [(x[0], int(x[1:])) for x in text.split()]


EXAMPLES = [
    ("A1 A2 B3 A4 B5 B6", "A-(0,99]->B", 2, 2),
    ("A0 A10 B12 B18 C25 C30", "A-(5,10]->B-(10,15]->C", 1, 1),
    ("A0 A8 B10", "A-(5,10]->B", 1, 1),
    ("A0 B5", "A-(5,10]->B", 0, 1),
    ("A0 B10", "A-(5,10]->B", 1, 1),
    ("A0 B11", "A-(5,10]->B", 0, 0),
    ("A1 A2 A3 A4", "A-(0,5]->A", 2, 2),
    ("A1 B2 A3", "A", 2, 2),
    ("A1 B1 B2", "A-(0,5]->B", 1, 1),
    ("A1 A2 B2", "A-(0,5]->B", 1, 1),
    ("A1", "A-(0,5]->B", 0, 0),
]


@pytest.mark.parametrize("stream,episode,exact,relaxed", EXAMPLES)
def test_worked_examples(stream, episode, exact, relaxed):
    s, e = seq(stream), ep(episode)
    times, syms = [t for _, t in s], [x for x, _ in s]
    assert list_automaton(times, syms, e)[0] == exact == support(s, e)
    assert slot_automaton(times, syms, e)[0] == relaxed == list_automaton(times, syms, e.relaxed)[0]


def test_all_and_disjoint_occurrences():
    s = seq("A1 A2 B3 A4 B5 B6")
    assert len(occurrences(s, ep("A-(0,99]->B"))) == 8
    s = seq("A0 A10 B12 B18 C25 C30")
    assert list_automaton([t for _, t in s], [x for x, _ in s], ep("A-(5,10]->B-(10,15]->C"))[1] == [30]
    assert list_automaton([t for _, t in s], [x for x, _ in s], ep("A-(5,10]->B-(10,15]->C").relaxed)[1] == [25]


streams = st.lists(st.tuples(st.sampled_from("ABC"), st.integers(0, 3)), min_size=0, max_size=25)
edges = st.lists(st.tuples(st.integers(0, 4), st.integers(1, 6)), min_size=0, max_size=3)


def _stream(steps):
    t, out = 0, []
    for s, d in steps:
        t += d
        out.append((s, t))
    return out


def _arrays(s):
    return {x: (np.array([t for y, t in s if y == x]), np.array([i for i, (y, _) in enumerate(s) if y == x])) for x in {y for y, _ in s}}


@settings(max_examples=400, deadline=None)
@given(streams, edges, st.data())
def test_counters_agree(steps, limits, data):
    s = _stream(steps)
    e = Episode(tuple(data.draw(st.lists(st.sampled_from("ABC"), min_size=len(limits) + 1, max_size=len(limits) + 1))), tuple(Interval(a, a + b) for a, b in limits))
    times, syms = [t for _, t in s], [x for x, _ in s]
    exact = list_automaton(times, syms, e)[0]
    assert exact == support(s, e)
    lists = tuple((x.low, x.high) for x in e.edges)
    starts = chain_starts(_arrays(s), e.nodes, lists)
    assert len(greedy(*starts)) == exact
    relaxed = slot_automaton(times, syms, e)[0]
    assert relaxed == list_automaton(times, syms, e.relaxed)[0] >= exact
    assert slot_automaton(times, syms, e, "printed")[0] >= exact
    # segments of any width compose to the same count
    width = (e.reach or 0) + data.draw(st.integers(1, 5))
    t0, total, past = 0, 0, (-(1 << 62), -(1 << 62))
    whole = []
    last = times[-1] if times else 0
    for seg in range(-1, last // width + 1):
        own = (starts[2] > seg * width) & (starts[2] <= (seg + 1) * width)
        m = carry_map(*(x[own] for x in starts), seg * width)
        c, *past = apply_map(m, *past)
        total += c
        whole = compose(whole, m)
    assert total == exact == apply_map(whole, -(1 << 62), -(1 << 62))[0]
    assert t0 == 0


def test_bank_matches_single_machines():
    rng = random.Random(3)
    t, s = 0, []
    for _ in range(400):
        t += rng.randint(0, 3)
        s.append((rng.choice("ABCD"), t))
    eps = {i: Episode(tuple(rng.choice("ABCD") for _ in range(3)), (Interval(0, 4), Interval(1, 6))) for i in range(40)}
    times, syms = [t for _, t in s], [x for x, _ in s]
    bank = MachineBank(eps)
    assert bank.run(times, syms) == {i: list_automaton(times, syms, e)[0] for i, e in eps.items()}
    assert bank.divergent > 0
    eps |= {100: Episode(("A",)), 101: Episode(("A", "A"), (Interval(0, 3),))}
    assert slot_counts(eps, times, syms) == {i: slot_automaton(times, syms, e)[0] for i, e in eps.items()}


def test_slot_work_is_smaller():
    rng = random.Random(5)
    t, s = 0, []
    for _ in range(2000):
        t += rng.randint(0, 2)
        s.append((rng.choice("AB"), t))
    e, a, b = ep("A-(5,20]->B-(5,20]->A"), Work(), Work()
    list_automaton([t for _, t in s], [x for x, _ in s], e, a)
    slot_automaton([t for _, t in s], [x for x, _ in s], e, work=b)
    assert b.probes <= a.probes and b.state_slots == 3 < a.peak_list


def test_stitch_counterexample():
    s = seq("A9 A12 B15 A16 B17 B22")
    e = ep("A-(4,9]->B")
    times, syms = [t for _, t in s], [x for x, _ in s]
    left = [machine_tuple(times, syms, e, 0, 20, k) for k in (0, 1)]
    right = [machine_tuple(times, syms, e, 20, 40, k) for k in (0, 1)]
    assert left[0][2] == 22 and {r[0] for r in right} == {20}
    assert list_automaton(times, syms, e)[1] == [15, 22]


def test_notation_and_checks():
    for text in ("A", "A-(5,10]->B", "A-(0,inf]->B-(1,2]->C"):
        assert format_episode(parse_episode(text)) == text
    for bad in ((5, 5), (-1, 4), (6, 3)):
        with pytest.raises(ValueError):
            Interval(*bad)
    with pytest.raises(ValueError):
        Episode(("A", "B"))


def test_work_counters_are_those_of_a_walk():
    """Bisection and pieces of the stream change no counter: probes, peaks and divergence as one event and time after the other give them."""
    rng = random.Random(13)
    times = sorted(rng.randrange(600) for _ in range(500))
    syms = [rng.choice("AB") for _ in times]
    e = parse_episode("A-(4,30]->B")
    held, probes, peak, count = [], 0, 0, 0
    for t, s in zip(times, syms):
        if s == "A":
            held.append(t)
            peak = max(peak, len(held))
            continue
        while held and t - held[0] > 30:
            held.pop(0)
            probes += 1
        for before in reversed(held):
            probes += 1
            if t - before > 4:
                held, count = [], count + 1
                break
    bank = MachineBank({7: e, 8: parse_episode("A-(0,30]->B")})
    for i in range(0, len(times), 90):
        bank.feed(times[i : i + 90], syms[i : i + 90], 32)
    assert bank.counts[7] == count
    bank.total()
    w = bank.machines[7].work
    assert (w.probes, w.peak_list) == (probes, peak)
    whole = MachineBank(bank.episodes)
    whole.run(times, syms)
    assert (whole.counts, whole.work, whole.divergent) == (bank.counts, bank.work, bank.divergent)


def test_prefix_tables_held_do_not_grow_with_the_candidates():
    """A task held a table for every candidate that it had counted: with 1,125 triples over 200,000 events more than an executor has."""
    events = {s: (np.arange(i, 300, 3), np.arange(i, 300, 3)) for i, s in enumerate("ABC")}
    every = [(n, x, ((0, 5),) * (len(x) - 1)) for n, x in enumerate((a, b, c) for a in "ABC" for b in "ABC" for c in "ABC")]
    memo, most = {}, 0
    for _, nodes, edges in by_prefix(every):
        keep_prefixes(memo, nodes, edges)
        got = chain_starts(events, nodes, edges, memo)
        assert all((x == y).all() for x, y in zip(got, chain_starts(events, nodes, edges)))
        most = max(most, len(memo))
    assert most == 3


@pytest.mark.parametrize("kernel", ["list", "slot"])
def test_machines_run_through_a_piece_as_they_step(kernel):
    """A machine's loop over its own events of a piece leaves the counts, work and divergence of single steps of all machines."""
    from episodic.functions.automata import MACHINES

    rng = random.Random(17)
    times = sorted(rng.randrange(900) for _ in range(700))
    syms = [rng.choice("ABCD") for _ in times]
    eps = {i: Episode(tuple(rng.choice("ABC") for _ in range(n)), (Interval(0, 9), Interval(3, 20), Interval(0, None))[: n - 1]) for i, n in enumerate([1, 2, 3, 4, 3, 3, 2, 3])}
    eps |= {20: ep("A-(0,9]->B-(3,20]->C"), 21: ep("A-(4,30]->B-(0,9]->C"), 22: ep("B-(0,9]->A-(0,9]->C"), 23: ep("C-(0,30]->B-(0,9]->A")}
    single, counts, divergent = {k: MACHINES[kernel](e, Work()) for k, e in eps.items()}, dict.fromkeys(eps, 0), 0
    for t, s in zip(times, syms):
        for lane in ([*eps][:8], [*eps][8:]):
            paths = []
            for k in lane:
                if s in eps[k].nodes:
                    before, done = single[k].work.pushes, single[k].step(s, t)
                    counts[k] += done
                    paths.append((done, single[k].work.pushes - before))
            divergent += bool(paths) and (len(paths) < len(lane) or len(set(paths)) > 1)
    bank = MachineBank(eps, kernel)
    for i in range(0, len(times), 110):
        bank.feed(times[i : i + 110], syms[i : i + 110], 8)
    assert bank.counts == counts and bank.divergent == divergent > 0
    assert {k: m.work for k, m in bank.machines.items()} == {k: m.work for k, m in single.items()}
    assert not hasattr(bank, "index")  # no step for each event and machine


def test_carry_maps_look_up_what_is_accepted_only(monkeypatch):
    """A segment of many intervals was searched for the next one of each, though a selection accepts few."""
    from episodic.functions import carry

    looked, real = [], carry._next_free
    monkeypatch.setattr(carry, "_next_free", lambda st, se, et, ee: looked.append(len(et)) or real(st, se, et, ee))
    et, begins = np.arange(1_000, 51_000), np.sort(np.random.default_rng(3).choice(51_000, 2_000, replace=False))
    st, e = begins[np.maximum(0, np.searchsorted(begins, et - 900) - 1)], np.arange(50_000)
    steps = carry.carry_map(st, e, et, e, 1_000)
    assert steps[-1][:2] == carry.TOP and sum(looked) < 5_000
    for past in (-5, 0, 150, 700):
        first = int(np.searchsorted(st, past, "right"))
        at = greedy(st[first:], e[first:], et[first:], e[first:])
        assert carry.apply_map(steps, past, 1 << 61)[:2] == (len(at), int(et[first + at[-1]]))
    looked.clear()
    assert 40 < len(greedy(st, e, et, e)) < 60 and not looked


def test_selections_that_never_meet_are_not_followed_in_rounds(monkeypatch):
    """Of A-(0,9]->A the odd and the even selection never meet: each step of theirs was a round of array operations."""
    from episodic.functions import carry

    calls, real = [], carry._next_free
    monkeypatch.setattr(carry, "_next_free", lambda st, se, et, ee: calls.append(1) or real(st, se, et, ee))
    t = np.arange(0, 40_000, 2)
    st, se, et, ee = chain_starts({"A": (t, t)}, ("A", "A"), ((0, 9),))
    own = int(np.searchsorted(et, 2_000, "right"))
    steps = carry.carry_map(st[own:], se[own:], et[own:], ee[own:], 2_000)
    assert [s[2] for s in steps] == [9_500, 9_499] and len(calls) < 100


def test_ends_of_one_time_are_one_row():
    """Of 50 equal events at each time one is looked at, with the counts of all of them."""
    from episodic.functions.carry import by_time, chain_ends, earliest_ends

    t = np.repeat(np.arange(0, 400, 4), 50)
    events = {"A": (t, np.arange(len(t))), "B": (t + 1, np.arange(len(t)) + 10_000)}
    ends = {s: by_time(*x) for s, x in events.items()}
    for nodes, edges in ((("A", "B"), ((0, 3),)), (("A", "B", "A"), ((0, 9), (2, 9))), (("A", "A"), ((0, 4),)), (("B", "A", "B"), ((1, None), (0, 2)))):
        few = earliest_ends(*chain_ends(ends, nodes, edges, {}))
        assert len(few[0]) <= 100 and len(greedy(*few)) == len(greedy(*chain_starts(events, nodes, edges)))


def test_steps_as_arrays_do_what_lists_do():
    from episodic.functions.carry import apply_steps, carry_steps, compose_steps

    draw, past, whole, lists = np.random.default_rng(5), (0, -(1 << 62), -(1 << 62)), np.zeros((0, 5), np.int64), []
    for t, edges in ((np.arange(0, 3_000, 2), ((3, 90),)), (np.sort(draw.integers(0, 2_000, 3_000)), ((0, 40), (5, 60))), (np.sort(draw.integers(0, 90_000, 3_000)), ((0, 90),))):
        starts = chain_starts({"A": (t, np.arange(len(t)))}, ("A",) * (len(edges) + 1), edges)
        for seg in range(int(t[-1]) // 150 + 1):
            own = (starts[2] > seg * 150) & (starts[2] <= (seg + 1) * 150)
            steps, m = carry_steps(*(x[own] for x in starts), seg * 150), carry_map(*(x[own] for x in starts), seg * 150)
            assert steps.tolist() == [list(x) for x in m]
            c, *to = apply_steps(steps, *past[1:])
            assert (c, *to) == apply_map(m, *past[1:])
            past, whole, lists = (past[0] + c, *to), compose_steps(whole, steps), compose(lists, m)
            assert whole.tolist() == [list(x) for x in lists]
        assert past[0] == len(greedy(*starts)) == apply_steps(whole, -(1 << 62), -(1 << 62))[0] > 0
        past, whole, lists = (0, -(1 << 62), -(1 << 62)), np.zeros((0, 5), np.int64), []


class _Plain:
    """What folds and kernels ask of a table, on one batch in this process."""

    def __init__(self, table):
        self.table, self.columns = table, table.column_names

    def select(self, *names):
        return _Plain(self.table.select(list(names)))

    def repartition(self, *key):
        return self

    sortWithinPartitions = repartition

    def mapInArrow(self, run, schema):
        return list(run(iter(self.table.to_batches())))


def test_maps_of_a_regular_stream_are_never_python_numbers():
    """In a regular stream no selections meet: a map has a step for each start before the bound, and a batch of maps
    became a list of Python numbers, forty bytes each."""
    import tracemalloc

    import pyarrow as pa

    from episodic.operators.segments import _MAPS, compose_maps

    starts = np.arange(800)
    steps = np.stack([starts, starts, np.ones(800, np.int64), starts + 900, starts], axis=1).ravel()
    table = pa.Table.from_arrays([pa.array(np.repeat(np.arange(250), 2)), pa.array(["all"] * 500), pa.array(np.tile([0, 1], 250)), pa.array([steps] * 500, _MAPS.field(3).type)], schema=_MAPS)
    tracemalloc.start()
    counts = pa.Table.from_batches(compose_maps(_Plain(table), 2))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert counts.num_rows == 250 and set(counts.column(2).to_pylist()) == {1} and peak < 10_000_000


def test_maps_leave_in_batches_of_bounded_numbers(monkeypatch):
    from episodic.functions import runs
    from episodic.operators.segments import _MAPS

    monkeypatch.setattr(runs, "MOST_NUMBERS", 10_000)
    steps = np.arange(4_000)
    assert [b.num_rows for b in runs.in_batches(((k, "all", 0, steps) for k in range(7)), _MAPS, 2_000)] == [3, 3, 1]
    assert [b.num_rows for b in runs.in_batches(((k, "all", 0, steps[:5]) for k in range(7)), _MAPS, 4)] == [4, 3]


@pytest.mark.parametrize("most", [1, 3, 40, 10**6])
def test_pieces_unroll_to_every_occurrence(monkeypatch, most):
    """Whatever the size aimed at; a crowded event is cut at its followers, and ids may be null."""
    import pyarrow as pa

    monkeypatch.setattr(listing, "PIECE", most)
    rng = random.Random(most)
    texts = ("A-(0,3]->B", "A-(2,5]->B-(0,4]->A", "B-(0,9]->A-(1,6]->B-(0,2]->B", "A-(0,inf]->B")
    for text in texts * 3:
        e, t, s = ep(text), -20, []
        for _ in range(40):
            t += rng.choice([0, 0, 1, 2])
            s.append((rng.choice("AB"), t))
        rows = [(k, t, None if i == 7 else i, e.edges[k - 1].low if k else None, e.edges[k - 1].high if k else None) for k, n in enumerate(e.nodes) for i, (x, t) in enumerate(s) if x == n]
        kinds = [("node", pa.int32()), *((c, pa.int64()) for c in ("t", "eid", "low", "high"))]
        table = pa.table([pa.array(c, kind) for c, (_, kind) in zip(zip(*rows, strict=True), kinds, strict=True)], names=[c for c, _ in kinds])
        n, got = len(e.nodes), []
        for row in listing.pieces(table, n):
            lists, chains = [row[4 * k : 4 * k + 4] for k in range(n)], [((), i) for i in range(len(row[0]))]
            for k in range(n - 1):
                chains = [((*c, i), j) for c, i in chains for j in range(lists[k][2][i], lists[k][2][i] + lists[k][3][i])]
            found = [(*c, i) for c, i in chains]
            assert len(found) <= 2 * most
            got += [tuple((int(lists[k][0][i]), lists[k][1][i]) for k, i in enumerate(c)) for c in found]
        want = [tuple((s[i][1], None if i == 7 else i) for i in o) for o in occurrences(s, e)]
        assert sorted(map(str, got)) == sorted(map(str, want))
