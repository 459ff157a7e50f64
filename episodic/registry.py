"""The registered queries of the episode engine, each with its SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable
from itertools import product

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from episodic import oracle as O
from episodic import sources as S
from episodic.functions import sql as surface
from episodic.functions.store import level_store, work_folder
from episodic.model import Episode, Interval, episode_table, format_episode, pairs_of
from episodic.operators import measures as M
from episodic.operators.chains import latest_starts
from episodic.operators.scans import count_episode_parallel, counters, multi_machine_scan
from episodic.operators.segments import count_independent, count_nonoverlapped
from episodic.operators.stitch import segment_map, stitch
from episodic.plans import candidates as C
from episodic.plans import dispatch as D
from episodic.plans import evolve as V
from episodic.plans.by_table_function import mine_by_table_function
from episodic.plans.mine import mine, top_k_episodes
from episodic.plans.relax import count_two_pass, upper_counts

Query = Callable[[SparkSession, str], DataFrame]
SEC = 1_000_000
HOUR = 3_600 * SEC
DAY = 24 * HOUR
TYPES = ["click", "error", "purchase", "signup", "view"]
#: The fixed delay set of the workloads: 0-10, 10-30 and 30-60 minutes.
I3 = [Interval(0, 600 * SEC), Interval(600 * SEC, 1800 * SEC), Interval(1800 * SEC, 3600 * SEC)]
WIDE = [Interval(0, 3 * HOUR), Interval(3 * HOUR, 6 * HOUR), Interval(6 * HOUR, 12 * HOUR)]
THETA = 300

PAIRS = pairs_of(TYPES, I3)
TRIPLES = [Episode((a, b, c), (i, j)) for a, b, c in (("view", "click", "purchase"), ("click", "view", "click"), ("signup", "error", "view")) for i in I3 for j in I3]
QUADS = [Episode(("view", "signup", "click", "purchase"), (i, j, I3[0])) for i in I3 for j in I3]
REPEATS = [Episode(("click", "click"), (i,)) for i in I3] + [Episode(("click", "view", "click"), (i, I3[1])) for i in I3]
ALL_TRIPLES = [Episode((a, b, c), (i, j)) for a in TYPES for b in TYPES for c in TYPES for i in I3 for j in I3]
FEW = [Episode(("view", "click"), (I3[1],)), Episode(("click", "purchase", "view"), (I3[0], I3[1]))]
SHORT = [Episode(("view", "click"), (Interval(0, 120 * SEC),)), Episode(("click", "purchase", "view"), (Interval(0, 300 * SEC), Interval(0, 300 * SEC)))]
USERS = [Episode((f"u{a}", f"u{b}"), (i,)) for a in (0, 3, 7) for b in (1, 5, 9) for i in I3]
SEGMENT = 6 * HOUR


def _named(df: DataFrame, episodes: list[Episode]) -> DataFrame:
    """df with the written episode instead of its id."""
    names = df.sparkSession.createDataFrame([(i, format_episode(e)) for i, e in enumerate(episodes)], "episode_id bigint, episode string")
    return df.join(F.broadcast(names), "episode_id").drop("episode_id")


def written():
    """The written form of the columns nodes, low and high."""
    edge = F.transform(F.sequence(F.lit(1), F.size("nodes") - 1), lambda i: F.concat(F.lit("-("), F.element_at("low", i).cast("string"), F.lit(","), F.coalesce(F.element_at("high", i).cast("string"), F.lit("inf")), F.lit("]->"), F.element_at("nodes", i + 1)))
    return F.when(F.size("nodes") == 1, F.col("nodes")[0]).otherwise(F.concat(F.col("nodes")[0], F.array_join(edge, "")))


def _support(source: Callable[[SparkSession, str], DataFrame], episodes: list[Episode], **options) -> Query:
    return lambda spark, d: _named(count_nonoverlapped(source(spark, d), episode_table(spark, episodes), **options), episodes).select("episode", "support")


def _by_stream(source: Callable[[SparkSession, str], DataFrame], episodes: list[Episode]) -> Query:
    return lambda spark, d: _named(count_nonoverlapped(source(spark, d), episode_table(spark, episodes), by_stream=True), episodes).select("episode", "stream_key", "support")


QUERIES: dict[str, Query] = {}
ORACLE: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql:
            ORACLE[f.__name__] = sql
        return f

    return add


def add(name: str, f: Query, sql: str | None = None) -> None:
    QUERIES[name] = f
    if sql:
        ORACLE[name] = sql


# sizes of the alphabet and of gaps


@query("SELECT event_type AS sym, count(*) AS n FROM events GROUP BY 1")
def alphabet_counts(spark, d):
    return S.event_types(spark, d).groupBy("sym").agg(F.count("*").alias("n"))


@query(f"""WITH ev AS ({O.EVENTS["users"]}), g AS (SELECT stream_key, t - lag(t) OVER (PARTITION BY stream_key ORDER BY t, eid) AS gap FROM ev)
    SELECT stream_key, quantile_disc(gap, 0.25) AS q25, quantile_disc(gap, 0.5) AS q50, quantile_disc(gap, 0.75) AS q75, count(gap) AS n FROM g WHERE gap IS NOT NULL GROUP BY 1""")
def gap_quantiles(spark, d):
    """Gaps within each user's stream: what delay intervals are chosen by."""
    g = V.gaps(S.event_types(spark, d, by_user=True)).filter("gap IS NOT NULL")
    q = [F.expr(f"percentile_disc({p}) WITHIN GROUP (ORDER BY gap)").alias(f"q{round(100 * p)}") for p in (0.25, 0.5, 0.75)]
    return g.groupBy("stream_key").agg(*[x.cast("bigint").alias(f"q{n}") for x, n in zip(q, (25, 50, 75), strict=True)], F.count("gap").alias("n"))


# counts of listed episodes

SINGLES = [Episode((t,)) for t in TYPES]
add("ep1_support", _support(S.event_types, SINGLES), O.support_sql("types", SINGLES))
add("ep2_exact", _support(S.event_types, PAIRS), O.support_sql("types", PAIRS))
add("ep3_exact", _support(S.event_types, TRIPLES), O.support_sql("types", TRIPLES))
add("ep4_exact", _support(S.event_types, QUADS), O.support_sql("types", QUADS, asof=True))
_WALK = ("view", "signup", "click", "purchase", "error", "view", "click")
LONG = {n: [Episode(_WALK[:n], tuple(I3[(i + j) % 3] for j in range(n - 1))) for i in range(3)] + [Episode(tuple(reversed(_WALK[:n])), (I3[2],) * (n - 1))] for n in (5, 6, 7, 8) if n <= len(_WALK)}
for _n, _eps in LONG.items():
    add(f"ep{_n}_exact", _support(S.event_types, _eps), O.support_sql("types", _eps, asof=True))
OPEN = [Episode(("view", "click"), (Interval(0, None),)), Episode(("click", "purchase", "error"), (Interval(1800 * SEC, None), Interval(0, 600 * SEC))), Episode(("error", "view", "signup"), (I3[0], Interval(3600 * SEC, None)))]
add("open_ended_support", _support(S.event_types, OPEN), O.support_sql("types", OPEN, asof=True))
add("ep_repeat_symbol", _support(S.event_types, REPEATS), O.support_sql("types", REPEATS))
add("user26_pairs", _support(S.user_symbols, USERS), O.support_sql("user26", USERS))


def _relaxed(episodes: list[Episode]) -> Query:
    return lambda spark, d: _named(upper_counts(S.event_types(spark, d), episode_table(spark, episodes)), episodes).select("episode", "upper")


def _relaxed_sql(episodes: list[Episode]) -> str:
    names = ", ".join(f"('{format_episode(e)}', '{format_episode(e.relaxed)}')" for e in episodes)
    return f"WITH n(episode, relaxed) AS (VALUES {names}), r AS ({O.support_sql('types', list(dict.fromkeys(e.relaxed for e in episodes)))}) SELECT n.episode, r.support AS upper FROM n JOIN r ON n.relaxed = r.episode"


add("ep2_relaxed", _relaxed(PAIRS), _relaxed_sql(PAIRS))
add("ep3_relaxed", _relaxed(TRIPLES), _relaxed_sql(TRIPLES))


@query(f"SELECT e.episode, e.support AS exact, r.upper, r.upper >= e.support AS bounded FROM ({O.support_sql('types', PAIRS)}) e JOIN ({_relaxed_sql(PAIRS)}) r USING (episode)")
def ep2_bound_check(spark, d):
    ev, eps = S.event_types(spark, d), episode_table(spark, PAIRS)
    both = count_nonoverlapped(ev, eps).join(upper_counts(ev, eps), "episode_id")
    return _named(both, PAIRS).select("episode", F.col("support").alias("exact"), "upper", (F.col("upper") >= F.col("support")).alias("bounded"))


# the tables behind the counts


@query(f"WITH {O.chains('types', FEW)} SELECT episode, st, et FROM iv JOIN eps USING (ep)")
def latest_start_table(spark, d):
    return _named(latest_starts(S.event_types(spark, d), episode_table(spark, FEW)), FEW).select("episode", "st", "et")


@query(f"WITH {O.intervals_sql('types', FEW)} SELECT episode, rank, st, et FROM picked JOIN eps USING (ep)")
def nonoverlapped_intervals(spark, d):
    return _named(M.nonoverlapped_intervals(S.event_types(spark, d), episode_table(spark, FEW)), FEW).select("episode", "rank", "st", "et")


@query(f"WITH {O.chains('types', FEW)} SELECT episode, st, min(et) AS et FROM iv JOIN eps USING (ep) GROUP BY episode, st, se")
def minimal_occurrences(spark, d):
    return _named(M.minimal_occurrences(S.event_types(spark, d), episode_table(spark, FEW)), FEW).select("episode", "st", "et")


def _all_sql(episodes: list[Episode], count: bool) -> str:
    parts = []
    for e in episodes:
        n = len(e.nodes)
        joins = f"ev v1 JOIN ev v2 ON v2.t - v1.t > {e.edges[0].low} AND v2.t - v1.t <= {e.edges[0].high}"
        for k in range(3, n + 1):
            joins += f" JOIN ev v{k} ON v{k}.t - v{k - 1}.t > {e.edges[k - 2].low} AND v{k}.t - v{k - 1}.t <= {e.edges[k - 2].high}"
        where = " AND ".join(f"v{k}.sym = '{s}'" for k, s in enumerate(e.nodes, 1))
        cols = "CAST(count(*) AS BIGINT) AS occurrences" if count else f"concat_ws('/', {', '.join(f'v{k}.eid' for k in range(1, n + 1))}) AS events"
        parts.append(f"SELECT '{format_episode(e)}' AS episode, {cols} FROM {joins} WHERE {where}")
    return f"WITH ev AS ({O.EVENTS['types']}) " + " UNION ALL ".join(parts)


@query(_all_sql(SHORT, True))
def ep_total_occurrences(spark, d):
    return _named(M.count_all(S.event_types(spark, d), episode_table(spark, SHORT)), SHORT).select("episode", F.col("support").cast("bigint").alias("occurrences"))


@query(_all_sql(SHORT, False))
def occurrence_enumeration(spark, d):
    listed = M.enumerate_occurrences(S.event_types(spark, d), episode_table(spark, SHORT))
    names = F.array(*(F.lit(format_episode(e)) for e in SHORT))  # ids are places in the list; a join costs more than listing does
    return listed.select(F.get(names, F.col("episode_id").cast("int")).alias("episode"), F.array_join(F.col("eids").cast("array<string>"), "/").alias("events"))


WINDOW, SLIDE = 2 * HOUR, HOUR // 2


@query(f"""WITH {O.chains("types", FEW)}, b AS (SELECT CAST(floor((min(t) - {WINDOW}) / {SLIDE}.0) AS BIGINT) + 1 AS lo, CAST(floor(max(t) / {SLIDE}.0) AS BIGINT) AS hi FROM ev),
    w AS (SELECT unnest(generate_series(lo, hi)) AS i FROM b), hit AS (SELECT DISTINCT ep, i FROM iv JOIN w ON i * {SLIDE} <= st AND et < i * {SLIDE} + {WINDOW})
    SELECT episode, count(hit.i) AS hit, (SELECT hi - lo + 1 FROM b) AS windows FROM eps LEFT JOIN hit USING (ep) GROUP BY episode""")
def ep_window_fraction(spark, d):
    return _named(M.window_frequency(S.event_types(spark, d), episode_table(spark, FEW), WINDOW, SLIDE), FEW).select("episode", "hit", "windows")


# relax, then verify; mining


@query(f"SELECT r.episode, r.upper, r.upper >= {THETA} AS survived, CASE WHEN r.upper >= {THETA} THEN e.support END AS exact FROM ({_relaxed_sql(TRIPLES)}) r JOIN ({O.support_sql('types', TRIPLES)}) e USING (episode)")
def two_pass_report(spark, d):
    return _named(count_two_pass(S.event_types(spark, d), episode_table(spark, TRIPLES), THETA), TRIPLES).select("episode", "upper", "survived", "exact")


CULL = 450


@query(f"SELECT episode, upper FROM ({_relaxed_sql(TRIPLES)}) WHERE upper < {CULL}")
def culled_candidates(spark, d):
    eps = episode_table(spark, TRIPLES)
    upper = upper_counts(S.event_types(spark, d), eps)
    gone = eps.join(upper.filter(F.col("upper") >= CULL), "episode_id", "left_anti").select("episode_id")
    return _named(upper.join(gone, "episode_id"), TRIPLES).select("episode", "upper")


_LEVEL = {
    1: f"SELECT 1 AS size, episode, support FROM ({O.support_sql('types', SINGLES)}) WHERE support >= {THETA}",
    2: f"SELECT 2 AS size, episode, support FROM ({O.support_sql('types', PAIRS, asof=True)}) WHERE support >= {THETA}",
    3: f"SELECT 3 AS size, episode, support FROM ({O.support_sql('types', ALL_TRIPLES, asof=True)}) WHERE support >= {THETA}",
}
_FREQUENT = " UNION ALL ".join(_LEVEL[k] for k in (1, 2, 3))


def frequent(spark: SparkSession, d: str, theta: int = THETA, intervals: list[Interval] = I3, max_nodes: int = 3, **options) -> DataFrame:
    return mine(S.event_types(spark, d), intervals, theta, max_nodes, **options).frequent


def _level(k: int) -> Query:
    return lambda spark, d: frequent(spark, d, max_nodes=k).filter(F.col("size") == k).select("size", written().alias("episode"), "support")


for _k in (1, 2, 3):
    add(f"mine_level{_k}", _level(_k), _LEVEL[_k])


@query(_FREQUENT)
def frequent_all_levels(spark, d):
    return frequent(spark, d).select("size", written().alias("episode"), "support")


UNIFORM = I3[2]
UNIFORM_THETA = 175
_UNIFORM = {n: [Episode(x, (UNIFORM,) * (n - 1)) for x in product(TYPES, repeat=n)] for n in (2, 3, 4)}


@query(" UNION ALL ".join(f"SELECT {n} AS size, episode, support FROM ({O.support_sql('types', eps, asof=True)}) WHERE support >= {UNIFORM_THETA}" for n, eps in _UNIFORM.items()))
def mine_level4(spark, d):
    """All episodes of two to four nodes whose delays are all of 30 to 60 minutes: four levels, two passes."""
    found = frequent(spark, d, UNIFORM_THETA, [UNIFORM], 4, strategy="two_pass")
    return found.filter("size > 1").select("size", written().alias("episode"), "support")


_TWO_LEVELS = f"{_LEVEL[1]} UNION ALL {_LEVEL[2]}"
for _way, _options in {
    "mine_by_segments": {"counting": "segment"}, "mine_by_episodes": {"counting": "episode", "kernel": "list"}, "mine_stitched": {"counting": "segment", "stitching": "faithful", "width": SEGMENT},
    "mine_hybrid": {"counting": "auto"}, "mine_relational": {"counting": "segment", "engine": "relational"}, "mine_membership": {"strategy": "two_pass", "membership_only": True},
}.items():
    add(_way, lambda spark, d, o=_options: frequent(spark, d, max_nodes=2, **o).select("size", written().alias("episode"), "support"), _TWO_LEVELS)


@query(_FREQUENT)
def frequent_two_pass(spark, d):
    return frequent(spark, d, strategy="two_pass").select("size", written().alias("episode"), "support")


@query(_FREQUENT)
def frequent_one_pass(spark, d):
    return frequent(spark, d, strategy="one_pass").select("size", written().alias("episode"), "support")


@query(f"""WITH f AS ({_LEVEL[2]}), p AS (SELECT episode, split_part(episode, '-(', 1) AS a, '-(' || split_part(split_part(episode, '-(', 2), ']->', 1) || ']->' AS i, split_part(episode, ']->', 2) AS b FROM f)
    SELECT x.a || x.i || x.b || y.i || y.b AS episode FROM p x JOIN p y ON x.b = y.a""")
def candidates_level3(spark, d):
    two = frequent(spark, d, max_nodes=2).filter("size = 2")
    return C.next_candidates(two, I3, 3).select(written().alias("episode"))


@query(f"SELECT * FROM (SELECT size, episode, support, row_number() OVER (PARTITION BY size ORDER BY support DESC, episode) AS rank FROM ({_FREQUENT})) WHERE rank <= 5")
def top_k_per_level(spark, d):
    from pyspark.sql import Window

    w = Window.partitionBy("size").orderBy(F.desc("support"), "episode")
    named = frequent(spark, d).select("size", written().alias("episode"), "support")
    return named.withColumn("rank", F.row_number().over(w).cast("bigint")).filter("rank <= 5")


@query(f"""WITH f AS ({_FREQUENT}) SELECT size, split_part(episode, '-(', 1) AS first, count(*) AS episodes, max(support) AS best, CAST(grouping(size) AS INT) AS g1, CAST(grouping(split_part(episode, '-(', 1)) AS INT) AS g2
    FROM f GROUP BY CUBE (size, split_part(episode, '-(', 1))""")
def report_cube(spark, d):
    f = frequent(spark, d).select("size", F.col("nodes")[0].alias("first"), "support")
    return f.cube("size", "first").agg(F.count("*").alias("episodes"), F.max("support").alias("best"), F.grouping("size").cast("int").alias("g1"), F.grouping("first").cast("int").alias("g2"))


@query(f"""WITH f AS ({_LEVEL[2]}), p AS (SELECT split_part(episode, '-(', 1) AS src, split_part(episode, ']->', 2) AS dst, support FROM f)
    SELECT src, {", ".join(f"CAST(coalesce(max(support) FILTER (WHERE dst = '{t}'), 0) AS BIGINT) AS {t}" for t in TYPES)} FROM p GROUP BY src""")
def connection_matrix(spark, d):
    return V.connection_matrix(frequent(spark, d, max_nodes=2), TYPES)


# segments

add("segmented_exact", _support(S.event_types, PAIRS, width=SEGMENT), ORACLE["ep2_exact"])
add("relational_exact", _support(S.event_types, PAIRS, engine="relational", width=SEGMENT), ORACLE["ep2_exact"])


@query(f"SELECT episode, support, TRUE AS matched FROM ({O.support_sql('types', FEW)})")
def stitch_faithful(spark, d):
    """Stitched counts; unmatched ones would be replaced by exact ones, and say so."""
    from episodic.operators.stitch import count_stitched

    return _named(count_stitched(S.event_types(spark, d), episode_table(spark, FEW), SEGMENT, complete=True), FEW).select("episode", "support", "matched")


@query(f"""WITH n AS (SELECT max((epoch_us(ts) - 1) // {SEGMENT}) - min((epoch_us(ts) - 1) // {SEGMENT}) + 1 AS p FROM events)
    SELECT episode, 'all' AS stream_key, support AS cnt, TRUE AS matched, CAST(ceil(log2(p)) AS INT) AS rounds FROM ({O.support_sql('types', FEW)}), n""")
def stitch_matches(spark, d):
    """What the joins alone give, with their rounds: the binary logarithm of the number of segments, rounded up."""
    eps = episode_table(spark, FEW)
    tied = stitch(level_store(segment_map(S.event_types(spark, d), eps, SEGMENT, complete=True), "map-tuples"), eps, SEGMENT)
    return _named(tied, FEW).select("episode", "stream_key", "cnt", "matched", "rounds")


_CUT = f"SELECT 'all/' || ((epoch_us(ts) - 1) // {SEGMENT}) AS stream_key, event_type AS sym, epoch_us(ts) AS t, event_id AS eid FROM events"
add("independent_segments", lambda spark, d: _named(count_independent(S.event_types(spark, d), episode_table(spark, PAIRS), SEGMENT), PAIRS).select("episode", "support"), O.support_sql(_CUT, PAIRS))


@query(f"SELECT e.episode, e.support AS exact, i.support AS independent, e.support - i.support AS lost FROM ({ORACLE['ep2_exact']}) e JOIN ({ORACLE['independent_segments']}) i USING (episode)")
def segment_boundary_loss(spark, d):
    ev, eps = S.event_types(spark, d), episode_table(spark, PAIRS)
    both = count_nonoverlapped(ev, eps).join(count_independent(ev, eps, SEGMENT).withColumnRenamed("support", "independent"), "episode_id")
    return _named(both, PAIRS).select("episode", F.col("support").alias("exact"), "independent", (F.col("support") - F.col("independent")).alias("lost"))


# episode-parallel counting, scans, the dispatcher

add("episode_parallel_count", lambda spark, d: _named(count_episode_parallel(S.event_types(spark, d), episode_table(spark, TRIPLES), "list", 8), TRIPLES).select("episode", "support"), ORACLE["ep3_exact"])
add("episode_parallel_latest", lambda spark, d: _named(count_episode_parallel(S.event_types(spark, d), episode_table(spark, TRIPLES), "latest", 8), TRIPLES).select("episode", "support"), ORACLE["ep3_exact"])
add("slot_automaton_count", lambda spark, d: _named(count_episode_parallel(S.event_types(spark, d), episode_table(spark, TRIPLES), "slot", 8), TRIPLES).select("episode", F.col("support").alias("upper")), ORACLE["ep3_relaxed"])
add("multi_machine_scan", lambda spark, d: _named(multi_machine_scan(S.event_types(spark, d), episode_table(spark, TRIPLES)), TRIPLES).select("episode", "support"), ORACLE["ep3_exact"])
add(
    "multi_machine_two_pass",
    lambda spark, d: _named(multi_machine_scan(S.event_types(spark, d), episode_table(spark, TRIPLES), two_pass=True, theta=CULL), TRIPLES).select("episode", "support"),
    f"SELECT r.episode, CASE WHEN r.upper >= {CULL} THEN e.support END AS support FROM ({ORACLE['ep3_relaxed']}) r JOIN ({ORACLE['ep3_exact']}) e USING (episode)",
)


_MODEL = "SELECT regr_slope(y, x) AS a, regr_intercept(y, x) AS b FROM (SELECT 1.0 / n AS x, c / 960.0 AS y FROM (VALUES (3, 415), (4, 190), (5, 200), (6, 100), (7, 100), (8, 60)) v(n, c))"


@query(f"""WITH p AS (SELECT o_orderpriority AS sym, o_custkey, count(*) AS n FROM orders GROUP BY ALL), c AS (SELECT sym, n AS level, count(*) AS candidates FROM p WHERE n <= 9 GROUP BY ALL)
    SELECT sym, level, candidates, CASE WHEN level IN (1, 2) OR level > 8 THEN 'segment' WHEN candidates > 960 * greatest(0.01, a / level + b) THEN 'episode' ELSE 'segment' END AS counting FROM c CROSS JOIN ({_MODEL})""")
def dispatch_table(spark, d):
    """How the published model would count as many candidates of a size as there are customers with that many orders of a priority."""
    orders = S.read_table(spark, d, "orders").groupBy(F.col("o_orderpriority").alias("sym"), "o_custkey").agg(F.count("*").alias("level"))
    m = D.printed_model()
    sizes = orders.filter("level <= 9").groupBy("sym", "level").agg(F.count("*").alias("candidates")).collect()  # nine a priority at most
    rows = [(r["sym"], r["level"], r["candidates"], D.choose_counting(r["candidates"], r["level"], D.PRINTED_CAPACITY, 1, m)) for r in sizes]
    return spark.createDataFrame(rows, "sym string, level bigint, candidates bigint, counting string")


@query("""WITH s AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey), p AS (SELECT k AS n, count(*) FILTER (s.n >= k) * 1.0 / count(*) AS y FROM s CROSS JOIN (SELECT unnest(generate_series(3, 8)) AS k) GROUP BY k)
    SELECT 'reciprocal' AS form, round(regr_slope(y, 1.0 / n), 6) AS a, round(regr_intercept(y, 1.0 / n), 6) AS b, round(regr_r2(y, 1.0 / n), 6) AS r2 FROM p
    UNION ALL SELECT 'linear', round(regr_slope(y, n), 6), round(regr_intercept(y, n), 6), round(regr_r2(y, n), 6) FROM p""")
def crossover_fit(spark, d):
    """Both forms fitted on the customers whose stream of orders can hold an episode of 3 to 8 nodes, of all as the capacity."""
    streams = S.read_table(spark, d, "orders").groupBy("o_custkey").agg(F.count("*").alias("n"))
    r = streams.agg(F.count("*").alias("all"), *[F.count_if(F.col("n") >= k).alias(f"n{k}") for k in range(3, 9)]).first()
    rows = [(form, round(m.a, 6), round(m.b, 6), round(m.r2, 6)) for form in ("reciprocal", "linear") for m in [D.fit_crossover({k: r[f"n{k}"] for k in range(3, 9)}, r["all"], form)]] if r["all"] else []
    return spark.createDataFrame(rows, "form string, a double, b double, r2 double")


@query()
def work_counters(spark, d):
    ev, eps = S.event_types(spark, d), episode_table(spark, TRIPLES)
    return counters(ev, eps, "list").withColumn("kernel", F.lit("list")).unionByName(counters(ev, eps, "slot").withColumn("kernel", F.lit("slot")))


# the other tables as streams

USER_EPS = [Episode(("view", "click"), (Interval(0, 12 * HOUR),)), Episode(("click", "purchase"), (Interval(HOUR, 24 * HOUR),))]
add("user_stream_support", _by_stream(lambda s, d: S.event_types(s, d, by_user=True), USER_EPS), O.stream_support_sql("users", USER_EPS))
FLAG_EPS = [Episode(("NO", "NO"), (Interval(0, 30 * DAY),)), Episode(("RF", "AF"), (Interval(0, 30 * DAY),)), Episode(("AF", "NO", "RF"), (Interval(0, 10 * DAY), Interval(DAY, 20 * DAY)))]
add("supplier_stream_support", _by_stream(S.supplier_flags, FLAG_EPS), O.stream_support_sql("flags", FLAG_EPS))
ORDER_EPS = [Episode(("1-URGENT", "5-LOW"), (Interval(0, 200 * DAY),)), Episode(("2-HIGH", "3-MEDIUM", "1-URGENT"), (Interval(0, 300 * DAY), Interval(0, 300 * DAY)))]
add("customer_priority_support", _by_stream(S.order_priorities, ORDER_EPS), O.stream_support_sql("orders", ORDER_EPS))
BRAND_EPS = [Episode(("Brand#11", "Brand#12"), (Interval(0, 60 * DAY),)), Episode(("Brand#3", "Brand#14", "Brand#5"), (Interval(0, 60 * DAY), Interval(0, 60 * DAY)))]
add("brand_episode_support", _support(S.supplier_brands, BRAND_EPS), O.support_sql("brands", BRAND_EPS))
REGION_EPS = [Episode(("ASIA", "EUROPE"), (Interval(0, DAY),)), Episode(("AFRICA", "AMERICA", "ASIA"), (Interval(DAY, 2 * DAY), Interval(0, DAY)))]
add("region_episode_support", _support(S.region_orders, REGION_EPS), O.support_sql("regions", REGION_EPS, asof=True))
ROLE_EPS = [Episode(("user", "assistant"), (Interval(0, SEC),)), Episode(("user", "assistant", "user"), (Interval(0, SEC), Interval(0, 2 * SEC)))]
add("conversation_role_support", _support(S.conversation_roles, ROLE_EPS), O.support_sql("roles", ROLE_EPS))
WORD_EPS = [Episode(("the", "of"), (Interval(0, 5 * SEC),)), Episode(("of", "the", "and"), (Interval(0, 10 * SEC), Interval(SEC, 10 * SEC)))]
add("document_word_support", _support(S.document_words, WORD_EPS), O.support_sql("words", WORD_EPS, asof=True))
TAG_EPS = [Episode(("div", "p"), (Interval(0, 3 * SEC),)), Episode(("p", "a"), (Interval(0, 5 * SEC),))]
add("page_tag_support", _support(S.page_tags, TAG_EPS), O.support_sql("tags", TAG_EPS))
LABEL_EPS = [Episode(("l1", "l2"), (Interval(0, 5 * SEC),)), Episode(("l3", "l4", "l5"), (Interval(0, 20 * SEC), Interval(5 * SEC, 20 * SEC)))]
add("embedding_label_support", _support(S.embedding_labels, LABEL_EPS), O.support_sql("labels", LABEL_EPS))
JSON_EPS = [Episode((f"k{a}", f"k{b}"), (i,)) for a, b in ((1, 2), (3, 3)) for i in I3]
add("json_symbol_support", _support(S.json_symbols, JSON_EPS), O.support_sql("json", JSON_EPS))
VALUE_EPS = [Episode((f"view:{a}", f"click:{b}"), (I3[2],)) for a in range(4) for b in range(4)]
add("value_bucket_support", _support(S.value_symbols, VALUE_EPS), O.support_sql("values", VALUE_EPS))


@query(f"""WITH s AS ({O.stream_support_sql("words", WORD_EPS, asof=True)}) SELECT episode, CAST(coalesce(sum(support) FILTER (WHERE quality = 0), 0) AS BIGINT) AS a, CAST(coalesce(sum(support) FILTER (WHERE quality = 1), 0) AS BIGINT) AS b,
    CAST(coalesce(sum(support) FILTER (WHERE quality = 0), 0) - coalesce(sum(support) FILTER (WHERE quality = 1), 0) AS BIGINT) AS difference FROM s JOIN labels ON stream_key = CAST(doc_id AS VARCHAR) GROUP BY episode""")
def label_contrast_support(spark, d):
    counts = count_nonoverlapped(S.document_words(spark, d), episode_table(spark, WORD_EPS), by_stream=True)
    labels = S.read_table(spark, d, "labels").select(F.col("doc_id").cast("string").alias("stream_key"), "quality")
    return _named(V.contrast(counts.join(labels, "stream_key"), "quality", 0, 1), WORD_EPS).select("episode", "a", "b", "difference")


# slices


def _type_slices(spark, d):
    ev = S.read_table(spark, d, "events")
    return S.as_events(ev, "event_type", S.micros("ts"), "event_id", F.floor((F.dayofmonth("ts") - 1) / 10).cast("int"))


add("slice_supports", _by_stream(_type_slices, PAIRS), O.stream_support_sql("type_slices", PAIRS))
_DAILY = f"SELECT episode, CAST(stream_key AS BIGINT) AS slice, support FROM ({O.stream_support_sql('days', FEW)})"
add("daily_supports", lambda spark, d: _named(V.slice_supports(S.event_types(spark, d), episode_table(spark, FEW), DAY), FEW).select("episode", "slice", "support"), _DAILY)


@query(f"""WITH r AS (SELECT * FROM ({_DAILY}) WHERE support >= 20), b AS (SELECT min(slice) AS lo, max(slice) AS hi FROM r),
    j AS (SELECT coalesce(x.episode, y.episode) AS episode, coalesce(x.slice + 1, y.slice) AS slice, x.support AS before, y.support AS after FROM r x FULL JOIN r y ON x.episode = y.episode AND x.slice + 1 = y.slice)
    SELECT episode, slice, before, after, CASE WHEN before IS NULL THEN 'appears' WHEN after IS NULL THEN 'vanishes' ELSE 'persists' END AS change, coalesce(after, 0) - coalesce(before, 0) AS delta FROM j, b WHERE slice > lo AND slice <= hi""")
def evolution_delta(spark, d):
    daily = V.slice_supports(S.event_types(spark, d), episode_table(spark, FEW), DAY).filter(F.col("support") >= 20)
    return V.track_evolution(_named(daily, FEW), ["episode"])


@query(f"""WITH ev AS ({O.EVENTS["users"]}), g AS (SELECT *, CASE WHEN t - lag(t) OVER w >= {6 * HOUR} THEN 1 ELSE 0 END AS new FROM ev WINDOW w AS (PARTITION BY stream_key ORDER BY t)),
    s AS (SELECT *, sum(new) OVER (PARTITION BY stream_key ORDER BY t) AS k FROM g) SELECT stream_key, min(t) AS "start", max(t) AS "end", count(*) AS n FROM s GROUP BY stream_key, k""")
def session_bursts(spark, d):
    return V.bursts(S.event_types(spark, d, by_user=True), 6 * HOUR)


@query(f"SELECT epoch_us(ts) // {DAY} * {DAY} AS start, event_type AS sym, count(*) AS n FROM events GROUP BY ALL")
def tumbling_counts(spark, d):
    from episodic.streaming import windowed_counts

    return windowed_counts(S.event_types(spark, d), "1 day")


@query(f"SELECT (epoch_us(ts) // {DAY // 2} - k) * {DAY // 2} AS start, event_type AS sym, count(*) AS n FROM events CROSS JOIN (VALUES (0), (1)) v(k) GROUP BY ALL")
def sliding_counts(spark, d):
    from episodic.streaming import windowed_counts

    return windowed_counts(S.event_types(spark, d), "1 day", "12 hours")


# joins around the miner


@query(f"""WITH ev AS ({O.EVENTS["users"]}), c AS (SELECT * FROM ev WHERE sym = 'click'), v AS (SELECT * FROM ev WHERE sym = 'view')
    SELECT c.stream_key, c.eid, max(v.t) AS seen FROM c JOIN v ON c.stream_key = v.stream_key AND v.t < c.t AND c.t - v.t <= {6 * HOUR} GROUP BY ALL""")
def asof_pairs(spark, d):
    """The newest view before each click of a user, 6 hours back at most: an as-of join with tolerance by one window."""
    eps = [Episode(("view", "click"), (Interval(0, 6 * HOUR),))]
    table = latest_starts(S.event_types(spark, d, by_user=True), episode_table(spark, eps))
    return table.select("stream_key", F.col("ee").alias("eid"), F.col("st").alias("seen"))


@query(f"""WITH ev AS ({O.EVENTS["users"]}) SELECT a.stream_key, a.eid AS view, b.eid AS click FROM ev a JOIN ev b ON a.stream_key = b.stream_key AND a.sym = 'view' AND b.sym = 'click' AND b.t - a.t > 0 AND b.t - a.t <= {2 * HOUR}""")
def interval_join_pairs(spark, d):
    ev = S.event_types(spark, d, by_user=True)
    b = F.floor(F.col("t") / (2 * HOUR))
    a = ev.filter("sym = 'view'").select("stream_key", F.col("eid").alias("view"), F.col("t").alias("ta"), F.explode(F.array(b, b + 1)).alias("b"))
    c = ev.filter("sym = 'click'").select("stream_key", F.col("eid").alias("click"), F.col("t").alias("tb"), b.alias("b"))
    return a.join(c, ["stream_key", "b"]).filter((F.col("tb") > F.col("ta")) & (F.col("tb") - F.col("ta") <= 2 * HOUR)).select("stream_key", "view", "click")


@query("""SELECT user_id, 'bought' AS kind FROM (SELECT DISTINCT user_id FROM events) u WHERE user_id IN (SELECT user_id FROM events WHERE event_type = 'purchase' AND value > 90)
    UNION ALL SELECT user_id, 'never' FROM (SELECT DISTINCT user_id FROM events) u WHERE user_id NOT IN (SELECT user_id FROM events WHERE event_type = 'purchase' AND value > 90)""")
def semi_anti_users(spark, d):
    ev = S.read_table(spark, d, "events").select("user_id", "event_type", "value")
    users = ev.select("user_id").distinct()
    big = ev.filter("event_type = 'purchase' AND value > 90").select("user_id")
    return users.join(big, "user_id", "left_semi").withColumn("kind", F.lit("bought")).unionByName(users.join(big, "user_id", "left_anti").withColumn("kind", F.lit("never")))


_SLICED = f"SELECT episode, stream_key FROM ({O.stream_support_sql('type_slices', PAIRS)}) WHERE support >= 180"


@query(f"""WITH r AS ({_SLICED}), a AS (SELECT episode FROM r WHERE stream_key = '0'), b AS (SELECT episode FROM r WHERE stream_key = '2')
    SELECT episode, 'both' AS kind FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT episode, 'first' FROM (SELECT * FROM a EXCEPT SELECT * FROM b) UNION ALL SELECT episode, 'last' FROM (SELECT * FROM b EXCEPT SELECT * FROM a)""")
def setops_slices(spark, d):
    r = _by_stream(_type_slices, PAIRS)(spark, d).filter("support >= 180")
    a, b = (r.filter(F.col("stream_key") == k).select("episode") for k in ("0", "2"))
    kinds = ((a.intersect(b), "both"), (a.exceptAll(b), "first"), (b.exceptAll(a), "last"))
    out = None
    for df, k in kinds:
        df = df.withColumn("kind", F.lit(k))
        out = df if out is None else out.unionByName(df)
    return out


# SQL surface, streaming, generator


@query(f"WITH {O.chains('users', [USER_EPS[0]])}, g AS ({O.fold()}) SELECT episode, CAST(sum(support) AS BIGINT) AS support FROM g JOIN eps USING (ep) GROUP BY episode")
def sql_udtf_occurrences(spark, d):
    """The table function of one episode, called from SQL on each user's events."""
    surface.register(spark)
    S.event_types(spark, d, by_user=True).createOrReplaceTempView("episode_events")
    text = format_episode(USER_EPS[0])
    return spark.sql(f"SELECT episode, sum(support) AS support FROM episode_occurrences(TABLE(episode_events) PARTITION BY stream_key ORDER BY (t, eid), '{text}') GROUP BY episode")


@query(_FREQUENT)
def sql_udtf_mine(spark, d):
    """All frequent episodes by a table function on segments, called from SQL once a level."""
    return mine_by_table_function(S.event_types(spark, d), I3, THETA, 3).select("size", written().alias("episode"), "support")


@query(O.stream_support_sql("users", USER_EPS))
def sql_udaf_support(spark, d):
    """The grouped aggregate, called from SQL: a row for each user and episode."""
    surface.register(spark)
    S.event_types(spark, d, by_user=True).createOrReplaceTempView("episode_events")
    each = [f"SELECT '{format_episode(e)}' AS episode, stream_key, episode_count(sym, t, '{format_episode(e)}') AS support FROM episode_events GROUP BY stream_key" for e in USER_EPS]
    return spark.sql(f"SELECT * FROM ({' UNION ALL '.join(each)}) WHERE support > 0")


@query(f"SELECT * FROM ({O.support_sql('types', PAIRS)})")
def sql_notation(spark, d):
    """Candidates written out in SQL and read by parse_episode: their counts."""
    surface.register(spark)
    spark.createDataFrame([(i, " " + format_episode(e)) for i, e in enumerate(PAIRS)], "episode_id bigint, text string").createOrReplaceTempView("written_episodes")
    eps = spark.sql("SELECT episode_id, p.nodes, p.low, p.high FROM (SELECT episode_id, parse_episode(text) AS p FROM written_episodes)")
    names = spark.sql("SELECT episode_id, canonical_episode(text) AS episode FROM written_episodes")
    return count_nonoverlapped(S.event_types(spark, d), eps).join(names, "episode_id").select("episode", "support")


# the relational operators that users of the miner need beside it


@query("SELECT s.strategy, count(*) AS n, CAST(sum(o.o_custkey) AS BIGINT) AS keys FROM orders o JOIN customer ON o_custkey = c_custkey CROSS JOIN (VALUES ('broadcast'), ('merge'), ('shuffle_hash')) s(strategy) GROUP BY s.strategy")
def join_strategies(spark, d):
    """One equality join by each physical strategy."""
    orders, customers = S.read_table(spark, d, "orders").select("o_custkey"), S.read_table(spark, d, "customer").select("c_custkey")
    on = F.col("o_custkey") == F.col("c_custkey")
    each = [orders.join(customers.hint(h), on).agg(F.lit(h).alias("strategy"), F.count("*").alias("n"), F.sum("o_custkey").alias("keys")) for h in ("broadcast", "merge", "shuffle_hash")]
    return each[0].unionByName(each[1]).unionByName(each[2])


@query("""SELECT event_type AS sym, count(DISTINCT user_id) AS users, count(DISTINCT CAST(ts AS DATE)) AS days, round(quantile_cont(value, 0.5), 6) AS median, round(quantile_cont(value, 0.9), 6) AS q90, TRUE AS near
    FROM events GROUP BY event_type""")
def distinct_and_approximate(spark, d):
    """Distinct counts and percentiles, exact ones and sketches; `near`: the sketches are within their error."""
    ev = S.read_table(spark, d, "events")
    out = ev.groupBy(F.col("event_type").alias("sym")).agg(
        F.countDistinct("user_id").alias("users"), F.countDistinct(F.to_date("ts")).alias("days"), F.percentile("value", 0.5).alias("median"), F.percentile("value", 0.9).alias("q90"),
        F.approx_count_distinct("user_id", 0.05).alias("u"), F.percentile_approx("value", 0.5, 1_000).alias("m"), (F.max("value") - F.min("value")).alias("span"),
    )
    near = (F.abs(F.col("u") - F.col("users")) <= 0.25 * F.col("users") + 2) & (F.abs(F.col("m") - F.col("median")) <= 0.05 * F.col("span"))
    return out.select("sym", "users", "days", F.round("median", 6).alias("median"), F.round("q90", 6).alias("q90"), near.alias("near"))


@query(f"SELECT CAST(epoch_us(ts) // {DAY} AS BIGINT) AS day, event_type AS sym, count(*) AS n, CAST(grouping(epoch_us(ts) // {DAY}) AS INT) AS g1, CAST(grouping(event_type) AS INT) AS g2 FROM events GROUP BY ROLLUP (epoch_us(ts) // {DAY}, event_type)")
def report_rollup(spark, d):
    ev = S.event_types(spark, d).select(F.floor(F.col("t") / DAY).alias("day"), "sym")
    return ev.rollup("day", "sym").agg(F.count("*").alias("n"), F.grouping("day").cast("int").alias("g1"), F.grouping("sym").cast("int").alias("g2"))


_GROUPING_SETS = "SELECT event_type AS sym, user_id % 5 AS part, count(*) AS n FROM events GROUP BY GROUPING SETS ((event_type, user_id % 5), (event_type), ())"


@query(_GROUPING_SETS)
def report_grouping_sets(spark, d):
    S.read_table(spark, d, "events").select("event_type", (F.col("user_id") % 5).alias("part")).createOrReplaceTempView("typed_events")
    return spark.sql("SELECT event_type AS sym, part, count(*) AS n FROM typed_events GROUP BY GROUPING SETS ((event_type, part), (event_type), ())")


@query(f"""SELECT episode, support, rank() OVER w AS rank, dense_rank() OVER w AS dense, CAST(ntile(4) OVER v AS INT) AS quarter, round(percent_rank() OVER w, 9) AS pr, round(cume_dist() OVER w, 9) AS cd
    FROM ({O.support_sql('types', PAIRS)}) WINDOW w AS (ORDER BY support DESC), v AS (ORDER BY support DESC, episode)""")
def support_ranks(spark, d):
    """Ranking functions over the supports of the listed candidates: a bounded table."""
    from pyspark.sql import Window

    named = _named(count_nonoverlapped(S.event_types(spark, d), episode_table(spark, PAIRS)), PAIRS)
    w, v = Window.orderBy(F.desc("support")), Window.orderBy(F.desc("support"), "episode")
    return named.select(
        "episode", "support", F.rank().over(w).cast("bigint").alias("rank"), F.dense_rank().over(w).cast("bigint").alias("dense"), F.ntile(4).over(v).alias("quarter"),
        F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"),
    )


@query(f"""WITH ev AS ({O.EVENTS["users"]}) SELECT stream_key, eid, lead(t) OVER w - t AS ahead, t - lag(t) OVER w AS behind, first_value(sym) OVER f AS first, last_value(sym) OVER f AS last, nth_value(sym, 2) OVER f AS second
    FROM ev WINDOW w AS (PARTITION BY stream_key ORDER BY t, eid), f AS (PARTITION BY stream_key ORDER BY t, eid ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")
def neighbour_events(spark, d):
    """Analytic functions within each user's stream."""
    from pyspark.sql import Window

    w = Window.partitionBy("stream_key").orderBy("t", "eid")
    f = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return S.event_types(spark, d, by_user=True).select(
        "stream_key", "eid", (F.lead("t").over(w) - F.col("t")).alias("ahead"), (F.col("t") - F.lag("t").over(w)).alias("behind"), F.first("sym").over(f).alias("first"), F.last("sym").over(f).alias("last"),
        F.nth_value("sym", 2).over(f).alias("second"),
    )


@query("SELECT count(*) AS n, CAST(0 AS BIGINT) AS unordered FROM events")
def range_sorted_layout(spark, d):
    """Events dealt by ranges of time and sorted inside: how many ranges begin before the end of the one to their left."""
    from pyspark.sql import Window

    laid = S.event_types(spark, d).repartitionByRange(8, "t", "eid").sortWithinPartitions("t", "eid")
    ends = laid.groupBy(F.spark_partition_id().alias("part")).agg(F.min("t").alias("lo"), F.max("t").alias("hi"), F.count("*").alias("n"))  # a row a range
    crossed = (F.col("lo") < F.lag("hi").over(Window.orderBy("part"))).cast("bigint")
    return ends.withColumn("crossed", F.coalesce(crossed, F.lit(0))).agg(F.sum("n").alias("n"), F.sum("crossed").alias("unordered"))


@query("SELECT event_id AS eid, event_type AS sym FROM events WHERE CAST('0x' || substr(md5(CAST(event_id AS VARCHAR)), 1, 6) AS BIGINT) < 0.1 * 16777216")
def stable_sample(spark, d):
    """A tenth of the events by a hash of their id: the same rows on any number of partitions."""
    return S.stable_sample(S.event_types(spark, d), "eid", 0.1).select("eid", "sym")


@query(f"""SELECT user_id, event_id FROM events c WHERE event_type = 'click' AND EXISTS (SELECT 1 FROM events p WHERE p.user_id = c.user_id AND p.event_type = 'purchase' AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 1 DAY)""")
def exists_purchase_after_click(spark, d):
    """A correlated EXISTS in SQL, which becomes a semi-join on the user with a range condition."""
    S.read_table(spark, d, "events").select("user_id", "event_id", "event_type", "ts").createOrReplaceTempView("all_events")
    return spark.sql("""SELECT user_id, event_id FROM all_events c WHERE event_type = 'click' AND EXISTS (
        SELECT 1 FROM all_events p WHERE p.user_id = c.user_id AND p.event_type = 'purchase' AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 1 DAY)""")


@query(O.stream_support_sql("users", USER_EPS[:1]))
def sql_recursive_greedy(spark, d):
    """The greedy selection as a recursive query: each step goes to the first interval after the last accepted end.

    A step a choice, so it is for short streams (Spark bounds the depth); segments with carry maps have no such bound.
    """
    table = _named(latest_starts(S.event_types(spark, d, by_user=True), episode_table(spark, USER_EPS[:1])), USER_EPS[:1])
    table.createOrReplaceTempView("latest_start_rows")
    return spark.sql("""WITH RECURSIVE iv AS (SELECT *, row_number() OVER (PARTITION BY episode, stream_key ORDER BY et, ee) AS i FROM latest_start_rows),
        hop AS (SELECT a.episode, a.stream_key, a.i, min(b.i) AS j FROM iv a JOIN iv b ON a.episode = b.episode AND a.stream_key = b.stream_key AND (b.st > a.et OR (b.st = a.et AND b.se > a.ee)) GROUP BY a.episode, a.stream_key, a.i),
        picked AS (SELECT episode, stream_key, i FROM iv WHERE i = 1 UNION ALL SELECT p.episode, p.stream_key, h.j FROM picked p JOIN hop h ON h.episode = p.episode AND h.stream_key = p.stream_key AND h.i = p.i)
        SELECT episode, stream_key, count(*) AS support FROM picked GROUP BY episode, stream_key""")


@query(f"""WITH s AS (SELECT CAST(user_id AS VARCHAR) AS stream_key, dayofmonth(ts) <= 10 AS a, dayofmonth(ts) > 20 AS b FROM events)
    SELECT stream_key, CAST(count(*) FILTER (a) AS BIGINT) AS before, CAST(count(*) FILTER (b) AS BIGINT) AS after FROM s WHERE a OR b GROUP BY stream_key""")
def cogrouped_slices(spark, d):
    """Two slices of each user's stream side by side in one grouped kernel (cogroup): numbers of events."""
    import pyarrow as pa

    ev = S.read_table(spark, d, "events").select(F.col("user_id").cast("string").alias("stream_key"), F.dayofmonth("ts").alias("day"))

    def kernel(key, x: pa.Table, y: pa.Table) -> pa.Table:
        return pa.table({"stream_key": [key[0].as_py()], "before": [x.num_rows], "after": [y.num_rows]})

    a, b = (ev.filter(c).groupBy("stream_key") for c in ("day <= 10", "day > 20"))
    return a.cogroup(b).applyInArrow(kernel, "stream_key string, before bigint, after bigint")


# streaming


def _by_time(ev: DataFrame, folder: str, width: int, closing: int) -> None:
    """ev as a file for each slice of time, and a last one with an event that lets the watermark pass."""
    from episodic.streaming import write_days

    write_days(ev, folder, width)
    hi = ev.agg(F.max("t")).first()[0]
    ev.sparkSession.createDataFrame([("all", "closing", hi + closing, -1)], ev.schema).coalesce(1).write.mode("append").parquet(folder)


@query(O.support_sql("types", FEW))
def stream_replay_support(spark, d):
    """The events table replayed day by day: a file a day, a file a micro-batch, machines continued from stored state."""
    from episodic.streaming import replay

    root = work_folder(spark, "replay")
    _by_time(S.event_types(spark, d), f"{root}/in", DAY, 2 * DAY)
    return _named(replay(spark, f"{root}/in", dict(enumerate(FEW)), f"{root}/out", f"{root}/state"), FEW).select("episode", "support")


@query(f"SELECT event_type AS sym, epoch_us(ts) // {DAY} * {DAY} AS start, count(*) AS n FROM events GROUP BY ALL")
def stream_window_counts(spark, d):
    """Daily counts in append mode: a window leaves when the watermark has passed its end."""
    from episodic.sources import read_event_stream
    from episodic.streaming import windowed_counts

    root = work_folder(spark, "windows")
    _by_time(S.event_types(spark, d), f"{root}/in", 5 * DAY, 3 * DAY)
    counted = windowed_counts(read_event_stream(spark, f"{root}/in"), "1 day")
    q = counted.writeStream.format("parquet").outputMode("append").option("path", f"{root}/out").option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(counted.schema).parquet(f"{root}/out").filter("sym <> 'closing'")


@query(ORACLE["interval_join_pairs"])
def stream_interval_pairs(spark, d):
    """The views and clicks of a user up to two hours apart, by a join of two streams."""
    from episodic.sources import read_event_stream
    from episodic.streaming import interval_pairs

    root = work_folder(spark, "pairs")
    _by_time(S.event_types(spark, d, by_user=True), f"{root}/in", 10 * DAY, 2 * DAY)
    views, clicks = (read_event_stream(spark, f"{root}/in").filter(F.col("sym") == x) for x in ("view", "click"))
    joined = interval_pairs(views, clicks, 2 * HOUR)
    q = joined.writeStream.format("parquet").outputMode("append").option("path", f"{root}/out").option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(joined.schema).parquet(f"{root}/out")


_HELD = "epoch_us(ts) // 864000000000 = (SELECT min(epoch_us(ts) // 864000000000) FROM events)"


@query(f"""SELECT count(*) FILTER (NOT ({_HELD}) OR epoch_us(ts) >= (SELECT max(epoch_us(ts)) FROM events) - {20 * DAY}) AS on_time,
    count(*) FILTER ({_HELD} AND epoch_us(ts) < (SELECT max(epoch_us(ts)) FROM events) - {20 * DAY}) AS late FROM events""")
def stream_late_counts(spark, d):
    """The first ten-day slice arrives last: how many of its events are over twenty days behind the newest seen."""
    from episodic.streaming import split_late

    root = work_folder(spark, "late")
    ev = S.event_types(spark, d).withColumn("slice", F.floor(F.col("t") / (10 * DAY)))
    first = ev.agg(F.min("slice")).first()[0]
    for part in (ev.filter(F.col("slice") > first), ev.filter(F.col("slice") == first)):
        part.drop("slice").coalesce(1).write.mode("append").parquet(f"{root}/in")
    counted = split_late(spark, f"{root}/in", 20 * DAY, f"{root}/out", f"{root}/state")
    return counted.agg(F.sum("on_time").alias("on_time"), F.sum("late").alias("late"))


@query("SELECT count(*) AS n FROM events")
def stream_deduplicated(spark, d):
    """Every event sent twice and counted once, by ids inside the watermark."""
    from episodic.sources import read_event_stream
    from episodic.streaming import once

    root = work_folder(spark, "repeats")
    ev = S.event_types(spark, d)
    ev.unionByName(ev).coalesce(1).write.parquet(f"{root}/in")
    kept = once(read_event_stream(spark, f"{root}/in"), "40 days")
    q = kept.writeStream.format("parquet").outputMode("append").option("path", f"{root}/out").option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(kept.schema).parquet(f"{root}/out").agg(F.count("*").alias("n"))


MS = 1_000
SPIKES = [Interval(0, 5 * MS), Interval(5 * MS, 10 * MS), Interval(10 * MS, 15 * MS)]
SPIKE_THETA = 290


@query()
def synth_recovery(spark, d):
    """Mines 60 s of generated events (about 50,000) and says what became of the planted chains.

    A row for each size: how many parts of planted chains there are, how many of them mining found, how many others it
    found, and the best support of a planted and of another episode.
    """
    from episodic.sources.synth import DEFAULT_CHAINS, synth_spikes

    ev = synth_spikes(spark).persist()
    found = mine(ev, SPIKES, SPIKE_THETA, 6).frequent.filter("size > 1").select("size", written().alias("episode"), "support")
    parts = {Episode(c.nodes[i:j], c.episode.edges[i : j - 1]) for c in DEFAULT_CHAINS for i in range(len(c.nodes)) for j in range(i + 2, len(c.nodes) + 1)}
    planted = spark.createDataFrame([(len(e.nodes), format_episode(e)) for e in sorted(parts, key=format_episode)], "size int, episode string")
    both = planted.withColumn("planted", F.lit(True)).join(found, ["size", "episode"], "full_outer")
    mine_, other = F.col("planted").isNotNull(), F.col("planted").isNull()
    return both.groupBy("size").agg(
        F.count(F.when(mine_, 1)).alias("planted"), F.count(F.when(mine_ & F.col("support").isNotNull(), 1)).alias("found"), F.count(F.when(other, 1)).alias("others"),
        F.max(F.when(mine_, F.col("support"))).alias("best_planted"), F.max(F.when(other, F.col("support"))).alias("best_other"),
    )


def flagship(spark: SparkSession, d: str) -> DataFrame:
    return frequent(spark, d, 45, WIDE, 3).select("size", written().alias("episode"), "support")
