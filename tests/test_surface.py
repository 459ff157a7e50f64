"""SQL functions, stores, streaming, and the registry against its SQL on the smallest tables."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from episodic import registry as R
from episodic import sources as S
from episodic.functions import sql as surface
from episodic.functions.automata import list_automaton
from episodic.model import parse_episode
from episodic.streaming import replay


def test_sql_functions(spark):
    surface.register(spark)
    r = spark.sql("SELECT parse_episode('A-(5,10]->B') AS p, canonical_episode(' A -(5,10]->B') AS c").first()
    assert (r["p"]["nodes"], r["p"]["low"], r["p"]["high"], r["c"]) == (["A", "B"], [5], [10], "A-(5,10]->B")
    ev = spark.createDataFrame([("x", "A", 1, 1), ("x", "B", 3, 2), ("x", "A", 4, 3), ("x", "B", 6, 4)], S.EVENTS)
    ev.createOrReplaceTempView("ev_t")
    assert spark.sql("SELECT episode_count(sym, t, 'A-(0,5]->B') AS n FROM ev_t GROUP BY stream_key").first()["n"] == 2
    row = spark.sql("SELECT * FROM episode_occurrences(TABLE(ev_t) PARTITION BY stream_key ORDER BY (t, eid), 'A-(0,5]->B')").first()
    assert (row["support"], row["ends"]) == (2, [3, 6])


def test_store_round_trip(spark, tiny, tmp_path):
    ev = S.event_types(spark, tiny)
    S.write_events(ev, str(tmp_path / "store"), R.DAY)
    back = S.read_events(spark, str(tmp_path / "store"))
    assert back.exceptAll(ev).isEmpty() and ev.exceptAll(back).isEmpty()
    ev.write.json(str(tmp_path / "json"))
    assert S.read_events(spark, str(tmp_path / "json"), "json").count() == ev.count()


def test_streaming_equals_batch(spark, tiny, tmp_path):
    ev = S.event_types(spark, tiny).filter("t IS NOT NULL").orderBy("t").limit(400)
    rows = [tuple(r) for r in ev.collect()]
    eps = {0: parse_episode(f"view-(0,{2 * R.HOUR}]->click"), 1: parse_episode(f"click-(0,{3 * R.HOUR}]->view-(0,{3 * R.HOUR}]->click")}
    rows.append(("all", "closing", rows[-1][2] + R.DAY, -1))
    for i in range(3):  # one file a part, in order
        spark.createDataFrame(rows[i * 150 : (i + 1) * 150], S.EVENTS).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    got = {r["episode_id"]: r["support"] for r in replay(spark, str(tmp_path / "in"), eps, str(tmp_path / "out"), str(tmp_path / "state"), "1 hour").collect()}
    assert got == {i: list_automaton([r[2] for r in rows], [r[1] for r in rows], e)[0] for i, e in eps.items()}


def _rows(df):
    cols = sorted(df.columns)
    return sorted(tuple("" if v is None or v != v else str(int(v)) if isinstance(v, float) and v == int(v) else str(v) for v in r) for r in df[cols].itertuples(index=False))


@pytest.mark.parametrize("name", ["alphabet_counts", "ep2_exact", "ep3_relaxed", "ep_window_fraction", "minimal_occurrences", "supplier_stream_support", "evolution_delta", "dispatch_table", "stitch_faithful", "independent_segments"])
def test_registry_matches_sql(spark, tiny, name):
    con = duckdb.connect()
    for t in S.TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{tiny}/{t}.parquet'")
    assert _rows(R.QUERIES[name](spark, tiny).toPandas()) == _rows(con.execute(R.ORACLE[name]).df())


def test_entry(spark):
    out = entry.entry(spark)
    assert {r["size"]: r["n"] for r in out.groupBy("size").agg(F.count("*").alias("n")).collect()} == {1: 5, 2: 73, 3: 7}
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_stitch_matches_equals_its_sql_on_a_tenth():
    """At sf0.1 the plain shifts have no partner for either episode; with a machine for every first completion they have."""
    from episodic.operators.stitch import machine_tuples

    con = duckdb.connect()
    rows = con.execute("SELECT event_type, epoch_us(ts), event_id FROM '/root/testdata/sf0.1/events.parquet' ORDER BY 2, 3").fetchall()
    by = {s: tuple(np.array(x, np.int64) for x in zip(*((t, i) for y, t, i in rows if y == s))) for s in R.TYPES}
    for e in R.FEW:
        times, syms = zip(*((t, s) for s, t, _ in rows if s in e.nodes))
        segs = range((rows[0][1] - 1) // R.SEGMENT, (rows[-1][1] - 1) // R.SEGMENT + 1)
        maps = [machine_tuples(by, e, p * R.SEGMENT, (p + 1) * R.SEGMENT, True) for p in segs]
        at, total = maps[0][0][4:], maps[0][0][3]
        for m in maps[1:]:
            x = next(x for x in m if x[1:3] == at)
            at, total = x[4:], total + x[3]
        assert total == list_automaton(times, syms, e)[0]


@pytest.mark.parametrize("name", ["dispatch_table", "crossover_fit"])
def test_model_queries_read_orders(spark, tiny, name, tmp_path):
    """Other orders give another table: the queries used to fit and decide numbers of their own."""
    con = duckdb.connect()
    few = spark.read.parquet(f"{tiny}/orders.parquet").filter("o_custkey % 3 = 0 OR o_orderkey % 2 = 0")
    few.write.parquet(str(tmp_path / "orders.parquet"))
    got = []
    for d, files in ((tiny, f"{tiny}/orders.parquet"), (str(tmp_path), f"{tmp_path}/orders.parquet/*.parquet")):
        con.execute(f"CREATE OR REPLACE VIEW orders AS SELECT * FROM '{files}'")
        got.append(_rows(R.QUERIES[name](spark, d).toPandas()))
        assert got[-1] == _rows(con.execute(R.ORACLE[name]).df())
    assert got[0] != got[1]


def test_mining_from_sql_takes_segments(spark, monkeypatch):
    """The query handed a whole stream, row by row, to one worker; now no call of the table function holds more than a segment."""
    import random

    from episodic import sources as S
    from episodic.functions import sql as surface
    from episodic.functions.store import level_store
    from episodic.model import Interval
    from episodic.plans import by_table_function as T

    stored = {}
    monkeypatch.setattr(T, "level_store", lambda df, name: stored.setdefault(name, level_store(df, name)))
    rng = random.Random(43)
    ev = spark.createDataFrame([("x", rng.choice("ABC"), t // 3, t) for t in sorted(rng.sample(range(9_000), 1_500))], S.EVENTS)
    found = T.mine_by_table_function(ev, [Interval(0, 9), Interval(9, 30)], 40, 3, width=200)
    assert stored["segments"].count() > 10
    surface.register(spark)
    ev.createOrReplaceTempView("whole_stream")
    whole = spark.sql("SELECT size, episode, support FROM mine_episodes(TABLE(whole_stream) PARTITION BY stream_key ORDER BY (t, eid), '0-9,9-30', 40, 3)")
    got = sorted(map(tuple, found.select("size", R.written().alias("episode"), "support").collect()))
    assert got == sorted(map(tuple, whole.collect())) and {x[0] for x in got} == {1, 2, 3}
    monkeypatch.setattr(R, "mine_by_table_function", lambda *a: found)
    assert R.QUERIES["sql_udtf_mine"](spark, "/root/testdata/sf0.001").count() == len(got)
