"""The Spark operators against the automata, and their invariants."""

import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from episodic import sources as S
from episodic.functions.automata import list_automaton, slot_automaton
from episodic.model import Episode, Interval, episode_table, parse_episode
from episodic.operators import measures as M
from episodic.operators.scans import count_episode_parallel, counters, multi_machine_scan
from episodic.operators.segments import count_independent, count_nonoverlapped
from episodic.operators.stitch import count_stitched, machine_tuple, machine_tuples
from episodic.plans import dispatch as D
from episodic.plans import evolve as V
from episodic.plans.mine import culling, mine
from episodic.plans.relax import count_two_pass, upper_counts
from tests.brute import occurrences


@pytest.fixture(scope="module")
def case(spark):
    rng = random.Random(11)
    rows, streams = [], {}
    for key in ("x", "y"):
        t, s = 0, []
        for i in range(300):
            t += rng.choice([0, 1, 1, 2, 5])
            s.append((rng.choice("ABC"), t))
            rows.append((key, s[-1][0], t, i))
        streams[key] = s
    ev = spark.createDataFrame(rows, S.EVENTS).repartition(3).persist()
    eps = [Episode(tuple(rng.choice("ABC") for _ in range(n)), tuple(rng.choice([Interval(0, 3), Interval(2, 6), Interval(0, 9)]) for _ in range(n - 1))) for n in (1, 2, 2, 3, 3, 4) for _ in range(3)]
    return ev, streams, eps


def _expected(streams, eps, kernel=list_automaton):
    return {i: sum(kernel([t for _, t in s], [x for x, _ in s], e)[0] for s in streams.values()) for i, e in enumerate(eps)}


def _got(df, column="support"):
    return {r["episode_id"]: r[column] for r in df.collect()}


@pytest.mark.parametrize("options", [{}, {"width": 40}, {"width": 33, "groups": 3}, {"engine": "relational", "width": 50}, {"engine": "relational"}])
def test_exact_counts(spark, case, options):
    ev, streams, eps = case
    assert _got(count_nonoverlapped(ev, episode_table(spark, eps), **options)) == _expected(streams, eps)


def test_partitioning_does_not_matter(spark, case):
    ev, streams, eps = case
    want = _expected(streams, eps)
    for n in (1, 13):
        assert _got(count_nonoverlapped(ev.repartition(n), episode_table(spark, eps), width=45)) == want


def test_open_ended_edges(spark, case):
    ev, streams, _ = case
    eps = [parse_episode("A-(0,inf]->B"), parse_episode("A-(3,inf]->B-(0,inf]->C")]
    for engine in ("arrow", "relational"):
        assert _got(count_nonoverlapped(ev, episode_table(spark, eps), engine=engine)) == _expected(streams, eps)


def test_parallel_and_scans(spark, case):
    ev, streams, eps = case
    table = episode_table(spark, eps)
    want = _expected(streams, eps)
    assert _got(count_episode_parallel(ev, table, "list", 4)) == want
    assert _got(count_episode_parallel(ev, table, "latest", 4)) == want
    assert _got(count_episode_parallel(ev, table, "slot", 4)) == _expected(streams, eps, slot_automaton)
    assert _got(multi_machine_scan(ev, table)) == want
    two = _got(multi_machine_scan(ev, table, two_pass=True, theta=30))
    assert all(v is None or v == want[k] for k, v in two.items())


def test_bound_cull_and_passes(spark, case):
    ev, streams, eps = case
    table = episode_table(spark, eps)
    want = _expected(streams, eps)
    upper = _got(upper_counts(ev, table), "upper")
    assert upper == _expected(streams, [e.relaxed for e in eps])
    assert all(upper[i] >= want[i] for i in want)
    for theta in (1, 30, 60):
        rows = {r["episode_id"]: r for r in count_two_pass(ev, table, theta).collect()}
        assert {i for i, r in rows.items() if (r["exact"] or 0) >= theta} == {i for i, n in want.items() if n >= theta}
        assert all(r["exact"] is None or r["survived"] for r in rows.values())


def test_stitching(spark, case):
    ev, streams, eps = case
    want = _expected(streams, eps)
    rows = {r["episode_id"]: r for r in count_stitched(ev, episode_table(spark, eps), 60).collect()}
    assert {i: r["support"] for i, r in rows.items()} == want
    assert any(r["matched"] for r in rows.values())
    bad = spark.createDataFrame([("z", x[0], int(x[1:]), i) for i, x in enumerate("A9 A12 B15 A16 B17 B22".split())], S.EVENTS)
    r = count_stitched(bad, episode_table(spark, [parse_episode("A-(4,9]->B")]), 20).first()
    assert (r["support"], r["matched"]) == (2, False)


def test_independent_segments_lose(spark, case):
    ev, streams, eps = case
    want = _expected(streams, eps)
    got = _got(count_independent(ev, episode_table(spark, eps), 40))
    assert all(got[i] <= want[i] for i in want) and any(got[i] < want[i] for i in want)
    s = spark.createDataFrame([("z", "A", 8, 0), ("z", "B", 12, 1)], S.EVENTS)
    table = episode_table(spark, [parse_episode("A-(0,5]->B")])
    assert _got(count_independent(s, table, 10)) == {0: 0} and _got(count_nonoverlapped(s, table, width=10)) == {0: 1}


def test_measures(spark, case):
    ev, streams, _ = case
    eps = [parse_episode("A-(0,3]->B"), parse_episode("A-(0,4]->B-(1,5]->C")]
    table = episode_table(spark, eps)
    every = {i: sum(len(occurrences(s, e)) for s in streams.values()) for i, e in enumerate(eps)}
    assert {k: int(v) for k, v in _got(M.count_all(ev, table)).items()} == every
    listed = {r["episode_id"]: r["count"] for r in M.enumerate_occurrences(ev, table).groupBy("episode_id").count().collect()}
    assert listed == {k: v for k, v in every.items() if v}
    width, slide = 12, 5
    for r in M.window_frequency(ev, table, width, slide).collect():
        s, e = streams[r["stream_key"]], eps[r["episode_id"]]
        lo, hi = (s[0][1] - width) // slide + 1, s[-1][1] // slide
        spans = [(s[o[0]][1], s[o[-1]][1]) for o in occurrences(s, e)]
        assert r["windows"] == hi - lo + 1
        assert r["hit"] == sum(any(i * slide <= a and b < i * slide + width for a, b in spans) for i in range(lo, hi + 1))
    chosen = M.nonoverlapped_intervals(ev, table).groupBy("episode_id").count().collect()
    assert {r["episode_id"]: r["count"] for r in chosen} == _expected(streams, eps)


@pytest.mark.parametrize("strategy,counting", [("two_pass", "auto"), ("one_pass", "segment"), ("two_pass", "episode")])
def test_mining_is_complete(spark, case, strategy, counting):
    ev, streams, _ = case
    intervals, theta = [Interval(0, 3), Interval(2, 6)], 45
    found = mine(ev, intervals, theta, 3, strategy=strategy, counting=counting)
    got = {(tuple(r["nodes"]), tuple(r["low"])): r["support"] for r in found.frequent.collect()}
    every = [Episode((a,)) for a in "ABC"] + [Episode((a, b), (i,)) for a in "ABC" for b in "ABC" for i in intervals]
    every += [Episode((a, b, c), (i, j)) for a in "ABC" for b in "ABC" for c in "ABC" for i in intervals for j in intervals]
    want = _expected(streams, every)
    assert got == {(e.nodes, tuple(x.low for x in e.edges)): want[i] for i, e in enumerate(every) if want[i] >= theta}
    assert [r.size for r in found.report] == [1, 2, 3] and all(0 <= x[3] <= 1 for x in culling(found.report))


def test_mining_refuses(spark, case):
    ev, _, _ = case
    for bad in ({"theta": 0}, {"theta": 5, "strategy": "x"}, {"theta": 1, "budget": 3}):
        with pytest.raises(ValueError):
            mine(ev, [Interval(0, 3)], **bad)


def test_edges(spark):
    none = spark.createDataFrame([], S.EVENTS)
    table = episode_table(spark, [parse_episode("A-(0,5]->B"), parse_episode("A")])
    for engine in ("arrow", "relational"):
        assert _got(count_nonoverlapped(none, table, engine=engine)) == {0: 0, 1: 0}
    raw = spark.createDataFrame([("A", 1, 1), (None, 2, 2), ("B", None, 3), ("B", 4, 4)], "s string, t bigint, e bigint")
    ev = S.as_events(raw, "s", "t", "e")
    assert ev.count() == 2 and _got(count_nonoverlapped(ev, table)) == {0: 1, 1: 1}
    with pytest.raises(Exception, match="null"):
        S.as_events(raw, "s", "t", "e", on_null="fail").collect()
    tied = spark.createDataFrame([("A", 1, 1), ("B", 3, 2), ("A", 3, 3), ("B", 5, 4)], "s string, t bigint, e bigint")
    one = episode_table(spark, [parse_episode("A-(0,5]->B")])
    assert _got(count_nonoverlapped(S.as_events(tied, "s", "t", "e"), one)) == {0: 2}
    assert _got(count_nonoverlapped(S.as_events(tied, "s", "t", tie_order="time"), one)) == {0: 1}


def test_dispatcher():
    m = D.fit_crossover(D.PRINTED_CROSSOVERS)
    assert (round(m.a, 3), round(m.b, 3), round(m.r2, 3)) == (1.658, -0.152, 0.924)
    lin = D.fit_crossover(D.PRINTED_CROSSOVERS, form="linear")
    assert (round(lin.a, 4), round(lin.b, 3), round(lin.r2, 3)) == (-0.0638, 0.536, 0.793) and m.sse < lin.sse
    for n, c in D.PRINTED_CROSSOVERS.items():
        table = D.CrossoverModel(0, c / D.PRINTED_CAPACITY)
        assert D.choose_counting(c + 1, n, 30, 32, table) == "episode" and D.choose_counting(c, n, 30, 32, table) == "segment"
    assert {D.choose_counting(10**6, n, 30) for n in (1, 2, 9, 20)} == {"segment"}


def test_counters(spark, case):
    ev, _, eps = case
    table = episode_table(spark, [e for e in eps if len(e.nodes) > 1])
    a, b = (counters(ev, table, k).first() for k in ("list", "slot"))
    assert a["probes"] >= b["probes"] and a["completions"] <= b["completions"] and a["divergent_groups"] > 0


def test_evolution_and_graph(spark):
    r = spark.createDataFrame([("a", 1, 5), ("a", 2, 7), ("b", 1, 4), ("c", 2, 9)], "episode string, slice bigint, support bigint")
    got = {(x["episode"], x["change"], x["delta"]) for x in V.track_evolution(r, ["episode"]).collect()}
    assert got == {("a", "persists", 2), ("b", "vanishes", -4), ("c", "appears", 9)}
    f = spark.createDataFrame([(["A", "B", "C"], [0, 1], [5, 6], 7), (["A", "B"], [0], [5], 9)], "nodes array<string>, low array<bigint>, high array<bigint>, support bigint")
    rows = {(x["src"], x["dst"]): (x["support"], x["episodes"]) for x in V.connection_graph(f).collect()}
    assert rows == {("A", "B"): (9, 2), ("B", "C"): (7, 1)}


def test_synthetic_chains_are_found(spark):
    from episodic.sources.synth import Chain, synth_spikes

    chain = Chain(("s0", "s1", "s2"), starts=6.0, strength=0.9)
    ev = synth_spikes(spark, seed=4, n_sym=6, rate_hz=4.0, seconds=20, chains=(chain,)).persist()
    found = mine(ev, [Interval(chain.low, chain.high)], 40, 3).frequent
    top = found.filter("size = 3").orderBy(F.desc("support")).first()
    assert tuple(top["nodes"]) == chain.nodes
    assert {tuple(r["nodes"]) for r in found.filter("size = 2").collect()} >= {("s0", "s1"), ("s1", "s2")}
    assert ev.count() == synth_spikes(spark, seed=4, n_sym=6, rate_hz=4.0, seconds=20, chains=(chain,)).repartition(7).count()


def test_stitched_counts_that_match_are_exact(spark):
    """Many segments and lower limits: some neighbours have no partner, and what they leave out is never a match."""
    rng = random.Random(3)
    t, rows = 0, []
    for i in range(900):
        t += rng.choice([1, 1, 2, 3])
        rows.append(("x", rng.choice("AB"), t, i))
    ev = spark.createDataFrame(rows, S.EVENTS)
    eps = [Episode((a, b), (Interval(lo, lo + d),)) for a in "AB" for b in "AB" for lo, d in ((0, 4), (3, 3), (6, 5))]
    want = _expected({"x": [(s, t) for _, s, t, _ in rows]}, eps)
    got = {r["episode_id"]: (r["support"], r["matched"]) for r in count_stitched(ev, episode_table(spark, eps), 24).collect()}
    assert {k: v for k, (v, _) in got.items()} == want
    assert len({m for _, m in got.values()}) == 2  # both kinds are there


def test_complete_stitching_always_matches(spark):
    """Times repeat and neighbours of the plain shifts lack partners; with a machine for every first completion none does."""
    rng = random.Random(5)
    t, rows = 0, []
    for i in range(700):
        t += rng.choice([0, 0, 1, 2, 3])
        rows.append(("x", rng.choice("AB"), t, i))
    ev = spark.createDataFrame(rows, S.EVENTS)
    eps = [Episode((a, b), (Interval(lo, lo + d),)) for a in "AB" for b in "AB" for lo, d in ((0, 4), (3, 3), (6, 5))] + [parse_episode("A-(2,5]->B-(0,4]->A")]
    table = episode_table(spark, eps)
    want = _expected({"x": [(s, t) for _, s, t, _ in rows]}, eps)
    got = {r["episode_id"]: (r["support"], r["matched"]) for r in count_stitched(ev, table, 24, complete=True).collect()}
    assert got == {i: (n, True) for i, n in want.items()}
    plain = {r["episode_id"]: (r["support"], r["matched"]) for r in count_stitched(ev, table, 24).collect()}
    assert {i: n for i, (n, _) in plain.items()} == want and not all(m for _, m in plain.values())


def test_machine_tuples_follow_the_automaton():
    rng = random.Random(9)
    t, times, syms = 0, [], []
    for _ in range(400):
        t += rng.choice([1, 1, 2, 4])
        times.append(t)
        syms.append(rng.choice("ABC"))
    events = {s: tuple(np.array(x, np.int64) for x in zip(*((t, i) for i, (t, y) in enumerate(zip(times, syms)) if y == s))) for s in "ABC"}
    for e in (parse_episode("A-(2,9]->B"), parse_episode("A-(0,6]->B-(3,8]->A"), parse_episode("C-(1,4]->C")):
        for seg in range(1, 12):
            lower, upper = 50 * seg, 50 * seg + 50
            near = {s: (x[0][(k := (x[0] > lower - e.reach) & (x[0] <= upper + e.reach))], x[1][k]) for s, x in events.items()}
            got = [(x[1], x[3], x[4]) for x in machine_tuples(near, e, lower, upper)]
            assert got == [machine_tuple(times, syms, e, lower, upper, k) for k in range(len(e.nodes))]


def test_streams_are_scanned_in_pieces(spark):
    """A stream longer than a piece: machines go on over the cuts, and no task holds more than pieces and a reach."""
    from episodic.operators import scans

    rng = random.Random(21)
    t, s = 0, []
    for _ in range(600):
        t += rng.choice([0, 1, 1, 2, 5])
        s.append((rng.choice("AB"), t))
    eps = [Episode(tuple(rng.choice("AB") for _ in range(n)), tuple(rng.choice([Interval(0, 3), Interval(2, 9), Interval(0, None)]) for _ in range(n - 1))) for n in (1, 2, 2, 3, 3)]
    for group in (eps, [e for e in eps if e.reach is not None]):
        scan = scans._LatestScan(dict(enumerate(group)))
        most = 0
        for i in range(0, 600, 40):
            part = s[i : i + 40]
            scan.feed(pa.table({"sym": [y for y, _ in part], "t": [x for _, x in part], "eid": list(range(i, i + len(part)))}))
            most = max(most, 0 if scan.kept is None else scan.kept.num_rows)
        assert scan.counts == {i: list_automaton([x for _, x in s], [y for y, _ in s], e)[0] for i, e in enumerate(group)}
    assert most < 100  # the last group has limits on every edge


def test_occurrences_are_listed_by_buckets(spark):
    """Each once, at bucket limits and below zero too; the join is on the bucket, not on the symbol alone."""
    rng = random.Random(4)
    t, s = -40, []
    for _ in range(120):
        t += rng.choice([0, 1, 1, 3])
        s.append((rng.choice("AB"), t))
    ev = spark.createDataFrame([("x", y, x, i) for i, (y, x) in enumerate(s)], S.EVENTS)
    eps = [parse_episode(x) for x in ("A-(0,3]->B", "A-(2,5]->B-(0,4]->A", "B-(4,7]->B", "A-(30,inf]->B", "A")]
    listed = M.enumerate_occurrences(ev, episode_table(spark, eps))
    got = sorted((r["episode_id"], tuple(r["eids"])) for r in listed.collect())
    assert got == sorted((i, o) for i, e in enumerate(eps) for o in occurrences(s, e))
    assert "b2#" in listed._jdf.queryExecution().toString()


def test_occurrences_are_never_shuffled(spark):
    """Pairs of events went through a shuffle (and a sort) on their way to triples; now only events and ranges do."""
    rows = [("x", s, t + i % 2, 100 * t + i) for t, s in ((0, "A"), (5, "B"), (9, "C")) for i in range(30)]
    ev = spark.createDataFrame(rows, S.EVENTS).repartition(2)
    old = spark.conf.get("spark.sql.adaptive.enabled")
    spark.conf.set("spark.sql.adaptive.enabled", "false")  # else the plan that ran is in pieces
    try:
        listed = M.enumerate_occurrences(ev, episode_table(spark, [parse_episode("A-(0,9]->B-(0,9]->C")]))
        got = {tuple(r["eids"]) for r in listed.collect()}
        written, left = [], [listed._jdf.queryExecution().executedPlan()]
        while left:
            node = left.pop()
            if node.nodeName() == "Exchange":
                written.append(node.metrics().apply("shuffleRecordsWritten").value())
            left += [node.children().apply(i) for i in range(node.children().size())]
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", old)
    assert got == {(a, 500 + b, 900 + c) for a in range(30) for b in range(30) for c in range(30)}
    assert written and max(written) <= 2 * len(rows)


def test_long_streams_are_cut_not_copied(spark, monkeypatch):
    """Each group of candidates read the whole stream in one task; past MOST_COPIES events "auto" takes segments, with equal results."""
    from episodic.plans import mine as module

    rng = random.Random(23)
    rows = [("x", rng.choice("ABC"), t, t) for t in sorted(rng.sample(range(4_000), 1_200))]
    ev = spark.createDataFrame(rows, S.EVENTS)
    few = D.CrossoverModel(0, 0.01)
    ways, found = [], []
    for most in (10**9, 2_000):
        monkeypatch.setattr(module, "MOST_COPIES", most)
        m = mine(ev, [Interval(0, 9), Interval(9, 30)], 12, 3, model=few, batch=2)
        ways.append([x.counting for x in m.report[1:]])
        found.append(sorted(map(str, m.frequent.collect())))
    assert ways == [["episode", "episode"], ["segment", "segment"]] and found[0] == found[1]


def test_list_machines_fill_the_slots(spark, monkeypatch):
    """Few candidates made one group of list machines, so one task did all steps."""
    from episodic.plans import mine as module

    seen, real = [], module.count_episode_parallel
    monkeypatch.setattr(module, "count_episode_parallel", lambda e, c, kernel, share: seen.append((kernel, share)) or real(e, c, kernel, share))
    rng = random.Random(29)
    ev = spark.createDataFrame([("x", rng.choice("AB"), t, t) for t in range(0, 600, 2)], S.EVENTS)
    m = mine(ev, [Interval(0, 9), Interval(4, 30)], 2, 2, counting="episode", kernel="list")
    assert [k for k, _ in seen] == ["slot", "list"] and seen[0][1] == 32 and seen[1][1] < 8
    assert sorted(map(str, m.frequent.collect())) == sorted(map(str, mine(ev, [Interval(0, 9), Interval(4, 30)], 2, 2, counting="segment").frequent.collect()))


def test_mining_cuts_the_events_once(spark, monkeypatch):
    """Each pass of each level shuffled and sorted all events; now they are written in segments once."""
    from episodic.operators import segments

    placed, real = [], segments.place
    monkeypatch.setattr(segments, "place", lambda *a, **o: placed.append(1) or real(*a, **o))
    rng = random.Random(31)
    rows = [(rng.choice("xy"), rng.choice("ABC"), t // 2, t) for t in sorted(rng.sample(range(4_000), 1_200))]
    ev = spark.createDataFrame(rows, S.EVENTS)
    both = [mine(ev, [Interval(0, 9), Interval(9, 30)], 20, 4, strategy=s, counting="segment", width=w) for s, w in (("two_pass", None), ("one_pass", 200))]
    assert len(placed) == 2 and [x.size for x in both[0].report] == [1, 2, 3, 4]
    found = [sorted(map(str, m.frequent.collect())) for m in both]
    eps = both[0].frequent.filter("size > 1").select(F.monotonically_increasing_id().alias("episode_id"), "nodes", "low", "high", F.col("support").alias("n"))
    eps = spark.createDataFrame(eps.collect(), eps.schema)
    plain = count_nonoverlapped(ev, eps, engine="relational").join(eps, "episode_id")
    assert found[0] == found[1] and plain.filter("support <> n").count() == 0


def test_stitching_reads_the_events_once(spark, monkeypatch):
    """The fallback to carry maps placed all events again, and each round of joins was some jobs of its own."""
    from episodic.operators import segments, stitch

    placed, stored = [], []
    for m in (segments, stitch):
        monkeypatch.setattr(m, "place", lambda *a, real=m.place, **o: placed.append(1) or real(*a, **o))
    monkeypatch.setattr(stitch, "level_store", lambda df, name, real=stitch.level_store: stored.append(name) or real(df, name))
    rng = random.Random(37)
    rows = [(rng.choice("xy"), rng.choice("ABC"), t // 3, t) for t in sorted(rng.sample(range(9_000), 1_500))]
    ev = spark.createDataFrame(rows, S.EVENTS)
    eps = [parse_episode(x) for x in ("A-(2,9]->B", "A-(0,6]->B-(3,8]->A", "C-(0,9]->C", "B")]
    table = episode_table(spark, eps)
    got = {r["episode_id"]: (r["support"], r["matched"]) for r in count_stitched(ev, table, 24).collect()}
    assert len(placed) == 1 and len(stored) < 4 and not all(m for _, m in got.values())
    assert {i: n for i, (n, _) in got.items()} == {r["episode_id"]: r["support"] for r in count_nonoverlapped(ev, table, "relational").collect()}


def test_blocks_of_rounds_join_as_single_rounds_do():
    from episodic.operators.stitch import joined_pairs

    rng = random.Random(41)
    for _ in range(200):
        last = rng.randint(0, 20)
        rows = [(seg, k, rng.randint(0, 2), 0, rng.randint(0, 9), rng.randint(0, 2), 0) for seg in range(last + 1) for k in range(3) if rng.random() < 0.95]
        one, end = rows, last
        for _ in range(5):
            up = joined_pairs(one, end, 1)
            one, end = [(seg, *x) for _, seg, x in up], end // 2
        assert sorted(one) == sorted((seg, *x) for _, seg, x in joined_pairs(rows, last, 5))
