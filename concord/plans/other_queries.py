"""Hardness constructions, exact search, single-connected sets, streams and reports, with DuckDB counterparts."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from concord.functions import exact, hardness
from concord.operators import consistent as C
from concord.operators import scc as S
from concord.operators import single as O
from concord.operators import verify as V
from concord.plans.consistent_queries import ring_sql, survivors_sql
from concord.plans.entangled_queries import rings
from concord.runtime import keep, shared_dir
from concord.sources import entangled as E
from concord.sources import tables as T
from concord.streaming.arrivals import Arrivals, coordinate_stream, session_requests, window_requests

Q: dict = {}
SQL: dict[str, str] = {}

#: A formula for every four customers: each gives a clause of two literals (v true if s = 1) of two variables, by its nation.
CLAUSES = "SELECT DISTINCT c_custkey // 4 AS f, c_custkey % 4 AS j, l // 2 + 1 AS v, l % 2 AS s FROM (SELECT c_custkey, unnest([c_nationkey % 4, c_nationkey // 4 % 4]) AS l FROM customer)"
TRUTH = f"""cl AS ({CLAUSES}), n AS (SELECT f, max(v) AS m, count(DISTINCT j) AS k FROM cl GROUP BY 1),
rows AS (SELECT f, k, b FROM n, LATERAL (SELECT unnest(range(0, 1 << m)) AS b)),
fine AS (SELECT r.f, r.b, count(DISTINCT j) AS met FROM rows r JOIN cl USING (f) WHERE (r.b >> (v - 1)) & 1 = s GROUP BY 1, 2),
sat AS (SELECT n.f, m, k, coalesce(bool_or(met = k), false) AS ok FROM n LEFT JOIN fine USING (f) GROUP BY ALL)"""


def _clauses(s, d) -> DataFrame:
    c = T.table(s, d, "customer").selectExpr("cast(c_custkey div 4 as int) f", "cast(c_custkey % 4 as int) j", "explode(array(cast(c_nationkey % 4 as int), cast(c_nationkey div 4 % 4 as int))) l")
    return c.selectExpr("f", "j", "cast(l div 2 + 1 as int) v", "l % 2 s").distinct()


def _truth_table(s, d):
    """Satisfiability by all assignments of each small formula, as a join with their numbers."""
    cl = _clauses(s, d)
    n = cl.groupBy("f").agg(F.max("v").alias("m"), F.countDistinct("j").alias("k"))
    rows = n.select("f", "k", F.explode(F.sequence(F.lit(0), F.call_function("shiftleft", F.lit(1), F.col("m")) - 1)).alias("b"))
    met = rows.join(cl, "f").where(F.call_function("shiftright", F.col("b"), F.col("v") - 1).bitwiseAND(F.lit(1)) == F.col("s")).groupBy("f", "k", "b").agg(F.countDistinct("j").alias("met"))
    return n.select("f").join(met.where("met = k").select("f").distinct().withColumn("hit", F.lit(True)), "f", "left").select("f", F.coalesce("hit", F.lit(False)).alias("satisfiable"))


def _decided(s, d, name: str, decide) -> DataFrame:
    """(f, name): what an exhaustive search says of the queries of each formula. Formulas with the same clauses are decided once."""
    clauses = _clauses(s, d).groupBy("f", "j").agg(F.array_sort(F.collect_set(F.expr("v * (2 * s - 1)"))).alias("clause"))
    formulas = keep(clauses.groupBy("f").agg(F.array_sort(F.collect_set("clause")).alias("formula")))

    def run(frames):
        for pdf in frames:
            pdf[name] = [decide([[int(x) for x in c] for c in f]) for f in pdf["formula"]]
            yield pdf

    told = formulas.select("formula").distinct().repartition(32).mapInPandas(run, f"formula array<array<int>>, {name} boolean")
    return formulas.join(told, "formula").select("f", name)


def _thm_decision(s, d):
    return _decided(s, d, "coordinates", lambda f: bool(exact.exact_max(hardness.as_unsafe_set(f), hardness.BITS)))


def _thm_max(s, d):
    return _decided(s, d, "full", lambda f: len(exact.exact_max(hardness.as_safe_set(f), hardness.BITS)) == len(f) + len({abs(x) for c in f for x in c}))


Q |= {"sat_truth_table": _truth_table, "sat_thm1": _thm_decision, "sat_thm2_max": _thm_max}
SQL |= {
    "sat_truth_table": f"WITH {TRUTH} SELECT CAST(f AS INT) AS f, ok AS satisfiable FROM sat",
    "sat_thm1": f"WITH {TRUTH} SELECT CAST(f AS INT) AS f, ok AS coordinates FROM sat",
    "sat_thm2_max": f"WITH {TRUTH} SELECT CAST(f AS INT) AS f, ok AS \"full\" FROM sat",
}


def _exact_small(s, d):
    """The largest sets of the six-query example: exhaustively, and by components (which doesn't try unions of branches)."""
    eqs, cat = E.two_branches(s)
    needs = {1: [2], 2: [1], 3: [4, 1], 4: [3], 5: [6, 2], 6: [5]}
    from concord.model import Entangled, Var, atom

    queries = [Entangled(q).offer(atom("seat", q, Var("x"))).given(*[atom("seat", p, Var(f"y{p}")) for p in ps]).where(atom("flights", Var("x"), "Z")) for q, ps in needs.items()]
    best = exact.exact_max(queries, {"flights": {("long:7", "string:Z")}})
    run = S.scc_coordinate(eqs, cat)
    return run.best.select(F.lit(len(best)).cast("long").alias("exact"), F.col("n").alias("by_components"), (F.col("n") / len(best)).alias("ratio"))


Q["exact_max_small"] = _exact_small
SQL["exact_max_small"] = "SELECT 6::BIGINT AS exact, 4::BIGINT AS by_components, 4 / 6.0::DOUBLE AS ratio"


def lassos(s, d) -> DataFrame:
    """Rings of ten (users 0..49), and ten users more that each ask one ring member."""
    to = F.when(F.col("id") >= 50, (F.col("id") - 50) * 5).otherwise(F.col("id") - F.col("id") % 10 + (F.col("id") + 1) % 10)
    return E.network(s, d, s.range(60).select(F.col("id").alias("src"), to.alias("dst")), 60)


def _single(s, d):
    run = O.single_connected_coordinate(lassos(s, d), E.catalog(s, d))
    return run.sets().select("n", "members")


Q["single_connected_sets"] = _single
SQL["single_connected_sets"] = """WITH g AS (SELECT c_custkey AS q, c_custkey - c_custkey % 10 AS g FROM customer WHERE c_custkey < 50)
SELECT count(*) AS n, string_agg(q, ',' ORDER BY q) AS members FROM g GROUP BY g.g
UNION ALL SELECT count(*) + 1, string_agg(q, ',' ORDER BY q) || ',' || c_custkey FROM customer JOIN g ON g.g = (c_custkey - 50) * 5 - ((c_custkey - 50) * 5) % 10 WHERE c_custkey BETWEEN 50 AND 59 GROUP BY c_custkey"""
Q["single_connected_report"] = lambda s, d: O.is_single_connected(lassos(s, d))
SQL["single_connected_report"] = "SELECT DISTINCT c_custkey - c_custkey % 10 AS comp_id, true AS single_post, true AS one_path FROM customer WHERE c_custkey < 50"


# ---------------------------------------------------------------- streams


def _arrivals(s, d):
    """Groups of five arriving over five micro-batches: a group is answered when its last member has come."""
    folder = f"{shared_dir(s).rstrip('/')}/stream/{uuid.uuid4().hex}"
    for k in range(5):
        rings(s, d).where(F.col("qid") % 7 % 5 == k).coalesce(1).write.mode("append").parquet(f"{folder}/in")
    loop = Arrivals(s, E.catalog(s, d), f"{folder}/state")
    source = s.readStream.schema(E.EQ).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in")
    coordinate_stream(source, loop, f"{folder}/checkpoint").awaitTermination(1200)
    return loop.answers().select("batch", "set_id", "qid")


Q["stream_arrivals"] = _arrivals
SQL["stream_arrivals"] = """WITH c AS (SELECT c_custkey AS qid, c_custkey - c_custkey % 5 AS set_id, c_custkey % 7 % 5 AS turn, c_custkey % 50 <> 7 AS ok FROM customer WHERE c_custkey < 100),
g AS (SELECT set_id, max(turn) AS batch FROM c GROUP BY 1 HAVING bool_and(ok)) SELECT CAST(batch AS INT) AS batch, set_id, qid FROM c JOIN g USING (set_id)"""


def _windowed(wants: DataFrame, friends: DataFrame) -> DataFrame:
    """Sizes of the sets per (window, type, day): the window is part of the coordination attributes, so a request holds what its user wants in all windows."""
    requests = T.requests(wants.select("user").distinct(), "map('rid', cast(user as string))")
    data = wants.select(F.col("user").alias("rid"), "window_start", F.explode("wants").alias("w")).select("rid", "window_start", "w.*")
    return C.consistent_coordinate(requests, data, ("rid", "window_start", "party_type", "party_day"), ["window_start", "party_type", "party_day"], friends).sizes


def _windows(s, d):
    folder = f"{shared_dir(s).rstrip('/')}/stream/{uuid.uuid4().hex}"
    source = s.readStream.schema(T.table(s, d, "events").schema).option("pathGlobFilter", "events.parquet").parquet(d)
    shaped = source.withColumn("party_type", F.col("event_type")).withColumn("party_day", F.to_date("ts"))
    stream = window_requests(shaped, "ts", "user_id", ["party_type", "party_day"])
    stream.writeStream.outputMode("append").format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    sets = _windowed(s.read.parquet(f"{folder}/out"), T.groups_coactive(s, d, 10))
    return sets.select(F.unix_timestamp("window_start").alias("window_start"), "party_type", F.col("party_day").cast("string").alias("party_day"), "n")


Q["stream_windows"] = _windows
SQL["stream_windows"] = survivors_sql([
    "ev AS (SELECT user_id, event_type AS party_type, CAST(ts AS DATE) AS party_day, CAST(floor(epoch(ts) / 3600) * 3600 AS BIGINT) AS window_start, CAST(floor(epoch(ts) / 600) AS BIGINT) AS bucket FROM events)",
    "last AS (SELECT floor((epoch(max(ts)) - 3600) * 1000) / 1000 AS mark FROM events)",
    "done AS (SELECT ev.* FROM ev, last WHERE window_start + 3600 <= mark)",
    "data AS (SELECT DISTINCT window_start * 100000 + user_id AS rid, window_start, party_type, party_day FROM done)",
    "req AS (SELECT DISTINCT rid AS qid, 0.0 AS weight FROM data)",
    "named AS (SELECT 0::BIGINT AS qid, 0::BIGINT AS partner WHERE false)", "ask AS (SELECT qid, 'friends' AS rel, 1 AS k FROM req)",
    "pairs AS (SELECT DISTINCT a.user_id AS u, b.user_id AS f FROM ev a JOIN ev b USING (bucket) WHERE a.user_id <> b.user_id)",
    "w AS (SELECT DISTINCT window_start, user_id FROM done)",
    "fr AS (SELECT a.window_start * 100000 + u AS usr, a.window_start * 100000 + f AS friend, 'friends' AS rel FROM pairs JOIN w a ON a.user_id = u JOIN w b ON b.user_id = f AND b.window_start = a.window_start)",
], "r.qid = s.rid", ["window_start", "party_type", "party_day"]) + "SELECT window_start, party_type, CAST(party_day AS VARCHAR) AS party_day, n FROM sets"
Q["window_request_counts"] = lambda s, d: window_requests(T.table(s, d, "events"), "ts", "user_id", ["event_type"], "1 day").groupBy(F.unix_timestamp("window_start").alias("window_start")).agg(F.count("*").alias("requests"))
SQL["window_request_counts"] = "SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS window_start, count(DISTINCT user_id) AS requests FROM events GROUP BY 1"
Q["session_counts"] = lambda s, d: session_requests(T.table(s, d, "events"), "ts", "user_id", "6 hours").groupBy("user").agg(F.count("*").alias("sessions"))
SQL["session_counts"] = "SELECT user_id AS user, count(*) FILTER (p IS NULL OR ts - p >= INTERVAL 6 HOURS) AS sessions FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS p FROM events) GROUP BY 1"


# ---------------------------------------------------------------- reports


def _intersect(s, d):
    a, b = T.friends_ring(s, d, None, 3), T.friends_ring(s, d, None, 1)
    return a.exceptAll(b).intersect(a).select("user", "friend")


def _lead(s, d):
    return T.customers(s, d).select(F.col("c_custkey").alias("user"), F.lead("c_custkey", 1, -1).over(Window.partitionBy("c_nationkey").orderBy("c_custkey")).alias("next_user"))


Q |= {"friend_intersect": _intersect, "request_lead": _lead}


SQL["friend_intersect"] = f"""WITH {ring_sql(3, "a")}, {ring_sql(1, "b")}
SELECT usr AS "user", friend FROM a EXCEPT SELECT usr, friend FROM b"""
SQL["request_lead"] = "SELECT c_custkey AS user, lead(c_custkey, 1, -1) OVER (PARTITION BY c_nationkey ORDER BY c_custkey) AS next_user FROM customer"
Q["props_json"] = lambda s, d: T.table(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("long").alias("k")).agg(F.count("*").alias("n"))
SQL["props_json"] = "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1"
Q["asof_request"] = lambda s, d: T.table(s, d, "events").groupBy("user_id").agg(F.max_by("event_type", F.struct("ts", "event_id")).alias("event_type"))
SQL["asof_request"] = "SELECT user_id, arg_max(event_type, struct_pack(ts := ts, id := event_id)) AS event_type FROM events GROUP BY 1"
Q["fit_linear"] = lambda s, d: V.fit(T.table(s, d, "lineitem"), "l_quantity", "l_extendedprice").select(F.round("slope", 3).alias("slope"), F.round("r2", 6).alias("r2"))
SQL["fit_linear"] = "SELECT round(regr_slope(l_extendedprice, l_quantity), 3) AS slope, round(regr_r2(l_extendedprice, l_quantity), 6) AS r2 FROM lineitem"
