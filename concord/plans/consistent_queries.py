"""Consistent coordination on the given tables: workloads, generalisations, examples, and their DuckDB counterparts."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from concord.operators import consistent as C
from concord.operators.select import Selection, containing, first, largest, most_weight
from concord.runtime import cut, keep
from concord.sources import tables as T

Q: dict = {}
SQL: dict[str, str] = {}


# ---------------------------------------------------------------- SQL building blocks

FLIGHTS = """flights AS (SELECT o_orderkey AS flight_id, n_name AS destination, CAST(o_orderdate AS DATE) AS day, c_mktsegment AS source, o_orderpriority AS airline
  FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey)"""


def ring_sql(k: int, name: str = "fr", rel: str = "friends") -> str:
    return f"""{name}_r AS (SELECT c_custkey, c_nationkey, c_custkey // {T.CIRCLE} AS circle, row_number() OVER w - 1 AS rnk, count(*) OVER (PARTITION BY c_nationkey, c_custkey // {T.CIRCLE}) AS size
  FROM customer WINDOW w AS (PARTITION BY c_nationkey, c_custkey // {T.CIRCLE} ORDER BY c_custkey)),
{name} AS (SELECT DISTINCT a.c_custkey AS usr, b.c_custkey AS friend, '{rel}' AS rel FROM {name}_r a JOIN {name}_r b
  ON a.c_nationkey = b.c_nationkey AND a.circle = b.circle AND a.c_custkey <> b.c_custkey, range(1, {k + 1}) t(i) WHERE (a.rnk + i) % a.size = b.rnk)"""


def survivors_sql(ctes: list[str], match: str, coord: list[str]) -> str:
    """WITH clause up to ``sets``. The CTEs must define data, req(qid, weight, ...), named(qid, partner), ask(qid, rel, k), fr(usr, friend, rel)."""
    on = lambda a, b: " AND ".join(f"{a}.{x} = {b}.{x}" for x in coord)
    of = lambda a: ", ".join(f"{a}.{x}" for x in coord)
    return f"""WITH RECURSIVE {', '.join(ctes)},
able AS (SELECT * FROM req WHERE NOT EXISTS (SELECT 1 FROM ask a WHERE a.qid = req.qid AND NOT EXISTS (SELECT 1 FROM fr WHERE fr.usr = a.qid AND fr.rel = a.rel))),
place AS MATERIALIZED (SELECT row_number() OVER () AS vid, d.* FROM (SELECT DISTINCT {of('s')} FROM data s) d),
offer AS MATERIALIZED (SELECT s.*, p.vid FROM data s JOIN place p ON {on('s', 'p')}),
vq AS MATERIALIZED (SELECT DISTINCT r.qid, s.vid FROM able r JOIN offer s ON {match}),
live AS (SELECT DISTINCT qid FROM vq),
edge AS MATERIALIZED (SELECT DISTINCT n.qid AS src, n.partner AS dst, 'named' AS kind FROM named n JOIN live a ON a.qid = n.qid JOIN live b ON b.qid = n.partner
  UNION SELECT a.qid, f.friend, 'any:' || a.rel FROM ask a JOIN live l ON l.qid = a.qid JOIN fr f ON f.usr = a.qid AND f.rel = a.rel JOIN live b ON b.qid = f.friend),
need AS MATERIALIZED (SELECT qid, 'named' AS kind, count(DISTINCT partner) AS need FROM named GROUP BY 1 UNION ALL SELECT qid, 'any:' || rel, max(k) FROM ask GROUP BY 1, 2),
ahead AS (SELECT e.src, e.kind, w.vid, count(*) AS c FROM edge e JOIN vq w ON w.qid = e.dst GROUP BY ALL),
have AS MATERIALIZED (SELECT v.qid, v.vid, n.kind, coalesce(g.c, 0) - n.need AS spare FROM vq v JOIN need n ON n.qid = v.qid
  LEFT JOIN ahead g ON g.src = v.qid AND g.kind = n.kind AND g.vid = v.vid),
dead(qid, vid) USING KEY (qid, vid) AS (
  SELECT DISTINCT qid, vid FROM have WHERE spare < 0
  UNION
  SELECT DISTINCT t.qid, t.vid FROM (
      SELECT h.qid, h.vid, h.kind, any_value(h.spare) AS spare, count(*) AS lost
      FROM (SELECT DISTINCT e.src, e.kind, d.vid FROM dead d JOIN edge e ON e.dst = d.qid) x
      JOIN have h ON h.qid = x.src AND h.kind = x.kind AND h.vid = x.vid
      JOIN edge g ON g.src = x.src AND g.kind = x.kind
      JOIN recurring.dead r ON r.qid = g.dst AND r.vid = x.vid
      WHERE NOT EXISTS (SELECT 1 FROM recurring.dead o WHERE o.qid = x.src AND o.vid = x.vid)
      GROUP BY h.qid, h.vid, h.kind) t
  WHERE t.lost > t.spare),
alive AS (SELECT v.qid, v.vid FROM vq v WHERE NOT EXISTS (SELECT 1 FROM dead d WHERE d.qid = v.qid AND d.vid = v.vid)),
sets AS (SELECT {of('p')}, g.* EXCLUDE (vid) FROM (SELECT vid, count(*) AS n, sum(weight) AS weight, string_agg(a.qid, ',' ORDER BY a.qid) AS members, list(a.qid) AS ids
  FROM alive a JOIN req r ON r.qid = a.qid GROUP BY vid) g JOIN place p ON p.vid = g.vid)
"""


@dataclass
class Workload:
    """One experiment: Spark inputs and the same in SQL."""

    requests: object
    data: object
    key: C.Key
    coord: list[str]
    friends: object
    ctes: list[str]
    match: str
    order: str = "n DESC"
    select: Selection = field(default_factory=largest)
    right: object = None  # a second relation of data, joined on ``on``
    on: list[str] = field(default_factory=list)

    def run(self, spark: SparkSession, d: str, **more) -> C.Consistent:
        if self.right:
            return C.joined_coordinate(self.requests(spark, d), self.data(spark, d), self.right(spark, d), self.on, self.key, self.coord, self.friends(spark, d), self.select, **more)
        return C.consistent_coordinate(self.requests(spark, d), self.data(spark, d), self.key, self.coord, self.friends(spark, d), self.select, **more)

    def sql(self) -> str:
        return survivors_sql(self.ctes, self.match, self.coord)


def text(c: str, kind: str) -> Column:
    return F.col(c).cast("string").alias(c) if kind == "date" else F.col(c)


def shown(df: DataFrame, *columns: str) -> DataFrame:
    kinds = dict(df.dtypes)
    return df.select(*[text(c, kinds[c]) for c in columns])


def shown_sql(coord: list[str]) -> str:
    return ", ".join(f"CAST({c} AS VARCHAR) AS {c}" if c.endswith("day") else c for c in coord)


def answer(w: Workload, what: str):
    """The query of a workload. what: sets (all), best (one set and its members), assignment."""
    if what == "assignment":
        return lambda spark, d: shown(w.run(spark, d).assignment, "user", *C.keys(w.key))
    return lambda spark, d: shown(getattr(r := w.run(spark, d), what), *r.coord, "n", "members")


def register(name: str, w: Workload, what: str) -> None:
    """A workload over whole tables, and its SQL."""
    Q[name] = answer(w, what)
    if what == "sets":
        SQL[name] = w.sql() + f"SELECT {shown_sql(w.coord)}, n, members FROM sets"
    elif what == "best":
        where = f" WHERE list_contains(ids, {w.select.must})" if w.select.must is not None else ""
        SQL[name] = w.sql() + f"SELECT {shown_sql(w.coord)}, n, members FROM (SELECT * FROM sets{where} ORDER BY {w.order}{', ' if w.order else ''}{', '.join(w.coord)} LIMIT 1)"
    else:
        keys = C.keys(w.key)
        least = f"min(struct_pack({', '.join(f'{k} := s.{k}' for k in keys)}))"
        SQL[name] = w.sql() + f""", best AS (SELECT * FROM sets ORDER BY {w.order}{', ' if w.order else ''}{', '.join(w.coord)} LIMIT 1),
m AS (SELECT unnest(ids) AS qid, {', '.join(w.coord)} FROM best),
pick AS (SELECT r.qid, {least} AS k FROM m JOIN req r ON r.qid = m.qid JOIN data s ON {w.match} AND {' AND '.join(f's.{c} = m.{c}' for c in w.coord)} GROUP BY r.qid)
SELECT qid AS user, {', '.join(f'CAST(k.{x} AS VARCHAR) AS {x}' if x.endswith('day') else f'k.{x} AS {x}' for x in keys)} FROM pick"""


# ---------------------------------------------------------------- travellers

AIRLINES = "['1-URGENT','2-HIGH','3-MEDIUM','4-NOT SPECIFIED','5-LOW']"


TRAVELLERS = f"""req AS (SELECT c_custkey AS qid, c_acctbal AS weight, CASE WHEN c_custkey % 2 = 0 THEN {AIRLINES}[1 + c_custkey % 5] END AS airline,
  CASE WHEN c_custkey % 3 = 0 THEN c_mktsegment END AS source, CASE WHEN c_custkey % 7 = 0 THEN n_name END AS destination FROM customer JOIN nation ON c_nationkey = n_nationkey),
named AS (SELECT qid, qid + 1 AS partner FROM req WHERE qid % 4 = 1), ask AS (SELECT qid, 'friends' AS rel, 1 AS k FROM req WHERE qid % 4 <> 1)"""


FITS = "(r.airline IS NULL OR r.airline = s.airline) AND (r.source IS NULL OR r.source = s.source) AND (r.destination IS NULL OR r.destination = s.destination)"
DATA = "data AS (SELECT * FROM flights)"


def travel(select: Selection | None = None, order: str = "n DESC", n: int | None = None) -> Workload:
    """Travellers and flights. SQL takes every customer; n bounds the requests of scaling runs."""
    return Workload(
        lambda s, d: T.travellers(s, d, n), T.flights, "flight_id", ["destination", "day"], lambda s, d: T.friends_ring(s, d, n, 2),
        [FLIGHTS, DATA, ring_sql(2), TRAVELLERS], FITS, order, select or largest(),
    )


def _parts(spark: SparkSession, d: str, w: Workload | None = None):
    w = w or travel()
    requests, friends = w.requests(spark, d), w.friends(spark, d)
    vq = C.options(requests, w.data(spark, d), w.coord, friends)
    return w, requests, friends, vq


def _listed(spark: SparkSession, d: str):
    """Requests, friends, (qid, sig) and (sig, coordination attributes): options before they are spread over the requests of a signature."""
    w = travel()
    requests, friends = w.requests(spark, d), w.friends(spark, d)
    able = C.befriended(requests, friends)
    return w, requests, friends, C.signatures(able).select("qid", "sig"), C.option_lists(able, w.data(spark, d), w.coord)


def _options(spark, d):
    _, _, _, signed, lists = _listed(spark, d)
    return signed.join(lists.groupBy("sig").agg(F.count("*").alias("n_options")), "sig").select("qid", "n_options")


def _candidates(spark, d):
    w, _, _, _, lists = _listed(spark, d)
    return shown(C.candidates(lists, w.coord), *w.coord)


def _pruned(spark, d):
    _, requests, friends, signed, lists = _listed(spark, d)
    return C.pruned_graph(requests, friends, signed.join(lists.select("sig").distinct(), "sig", "left_semi").select("qid"))


def _gv(spark, d):
    w, _, _, signed, lists = _listed(spark, d)
    per = signed.groupBy("sig").agg(F.count("*").alias("k"))
    return shown(lists.join(per, "sig").groupBy(*w.coord).agg(F.sum("k").alias("n")), *w.coord, "n")


Q |= {"options_vq": _options, "candidates_v": _candidates, "pruned_graph": _pruned, "gv_sizes": _gv}
SQL |= {
    "options_vq": travel().sql() + "SELECT qid, count(*) AS n_options FROM vq GROUP BY 1",
    "candidates_v": travel().sql() + "SELECT DISTINCT destination, CAST(day AS VARCHAR) AS day FROM vq JOIN place USING (vid)",
    "pruned_graph": travel().sql() + "SELECT src, dst, kind FROM edge",
    "gv_sizes": travel().sql() + "SELECT destination, CAST(day AS VARCHAR) AS day, count(*) AS n FROM vq JOIN place USING (vid) GROUP BY ALL",
}
register("clean_survivors", travel(), "sets")
register("cons_flights", travel(), "best")
register("cons_assignment", travel(), "assignment")
register("cons_gold", travel(most_weight(), "weight DESC"), "best")
register("cons_vip", travel(containing(8)), "best")
register("cons_first", travel(first(), ""), "best")


def _calls(spark, d):
    r = travel().run(spark, d)
    return C.call_counts(T.travellers(spark, d), r.best).select(F.col("options").alias("option_queries"), F.col("friends").alias("friend_queries"), F.col("final").cast("long").alias("final_queries"))


Q["cons_call_counts"] = _calls
SQL["cons_call_counts"] = travel().sql() + """SELECT (SELECT count(*) FROM req) AS option_queries, (SELECT count(DISTINCT qid) FROM ask) AS friend_queries,
 CAST((SELECT max(n) FROM sets) AS BIGINT) AS final_queries"""


def _pack(spark, d):
    w = _parties()
    r = w.run(spark, d)
    return shown(C.pack_values(r, w.requests(spark, d))[0], "place", *r.coord, "n", "members")


# ---------------------------------------------------------------- scaling experiments


def _plain(n: int) -> str:
    return f"req AS (SELECT c_custkey AS qid, 0.0 AS weight FROM customer WHERE c_custkey < {n}), named AS (SELECT 0 AS qid, 0 AS partner WHERE false), ask AS (SELECT qid, 'friends' AS rel, 1 AS k FROM req)"


def _distinct(m: int) -> str:
    return f"""data AS (SELECT m.flight_id, destination, day FROM (SELECT destination, day, min(flight_id) AS flight_id FROM flights GROUP BY 1, 2) m ORDER BY flight_id LIMIT {m})"""


def complete(n: int, m: int) -> Workload:
    """n users, all friends of each other and content with any of m distinct flights: nothing can be removed (the worst case)."""
    return Workload(
        lambda s, d: T.requests(T.customers(s, d, n).withColumn("user", F.col("c_custkey"))), lambda s, d: T.flights_distinct(s, d, m), "flight_id", ["destination", "day"],
        lambda s, d: T.friends_complete(s, d, n),
        [FLIGHTS, _distinct(m), _plain(n), "fr AS (SELECT a.qid AS usr, b.qid AS friend, 'friends' AS rel FROM req a, req b WHERE a.qid <> b.qid)"], "true",
    )


def _sweep(points: list[tuple[int, int]]):
    def query(spark, d):
        out = None
        for n, m in points:
            r = complete(n, m).run(spark, d)
            row = r.sizes.agg(F.count("*").alias("n_values"), F.max("n").alias("largest"), F.min("n").alias("smallest")).select(F.lit(n).alias("users"), F.lit(m).alias("flights"), "n_values", "largest", "smallest")
            out = row if out is None else out.unionByName(row)
        return out

    sql = " UNION ALL ".join(f"SELECT * FROM ({complete(n, m).sql()} SELECT {n} AS users, {m} AS flights, count(*) AS n_values, max(n) AS largest, min(n) AS smallest FROM sets)" for n, m in points)
    return query, sql


Q["cons_vary_options"], SQL["cons_vary_options"] = _sweep([(50, 100), (50, 400), (50, 1000)])
Q["cons_vary_users"], SQL["cons_vary_users"] = _sweep([(10, 100), (50, 100), (100, 100)])


# ---------------------------------------------------------------- other applications


def _titles(spark, d):
    names = T.table(spark, d, "part").select("p_name").distinct()
    ranked = names.groupBy().agg(F.array_sort(F.collect_set("p_name")).alias("names"))  # the 64 title names
    c = T.customers(spark, d).withColumn("user", F.col("c_custkey")).join(F.broadcast(ranked), how="cross")
    return T.requests(c, "map('title', element_at(names, cast(1 + user % size(names) as int)))")


MOVIES = Workload(
    _titles, T.movies, "movie_id", ["cinema"], lambda s, d: T.friends_ring(s, d, None, 2),
    ["data AS (SELECT p_partkey AS movie_id, p_brand AS cinema, p_name AS title FROM part)", ring_sql(2),
     f"""names AS (SELECT list_sort(list(DISTINCT p_name)) AS l FROM part),
req AS (SELECT c_custkey AS qid, 0.0 AS weight, l[1 + c_custkey % len(l)] AS title FROM customer, names),
named AS (SELECT 0 AS qid, 0 AS partner WHERE false), ask AS (SELECT qid, 'friends' AS rel, 1 AS k FROM req)"""],
    "r.title = s.title",
)
register("cons_movies", MOVIES, "sets")

EVEN_AIRLINE = f"map_filter(map('airline', case when user % 2 = 0 then element_at(array('1-URGENT','2-HIGH','3-MEDIUM','4-NOT SPECIFIED','5-LOW'), cast(1 + user % 5 as int)) end), (k, v) -> v is not null)"  # noqa: F541


def _even_sql(k: int = 1, rel: str = "friends") -> str:
    return f"""req AS (SELECT c_custkey AS qid, c_acctbal AS weight, CASE WHEN c_custkey % 2 = 0 THEN {AIRLINES}[1 + c_custkey % 5] END AS airline FROM customer),
named AS (SELECT 0 AS qid, 0 AS partner WHERE false), ask AS (SELECT qid, '{rel}' AS rel, {k} AS k FROM req)"""


def _even(asks: str = T.ANY_ONE, named: str = "array()"):
    return lambda s, d: T.requests(T.customers(s, d).withColumn("user", F.col("c_custkey")), EVEN_AIRLINE, named, asks, "c_acctbal")


BY_AIRLINE = "(r.airline IS NULL OR r.airline = s.airline)"
CONCERTS = """concerts AS (SELECT DISTINCT n_name AS location, CAST(l_shipdate AS DATE) AS event_day FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey)"""
register("cons_concerts", Workload(
    _even(), lambda s, d: C.scheduled(T.flights(s, d), T.concerts(s, d), {"destination": "location"}, "day", "event_day"), "flight_id", ["destination", "day"],
    lambda s, d: T.friends_ring(s, d, None, 2),
    [FLIGHTS, CONCERTS, "data AS (SELECT * FROM flights f WHERE EXISTS (SELECT 1 FROM concerts c WHERE c.location = f.destination AND c.event_day = f.day + 1))", ring_sql(2), _even_sql()],
    BY_AIRLINE,
), "best")

register("cons_k_friends", Workload(
    _even("array(named_struct('rel', 'friends', 'k', 2))"), T.flights, "flight_id", ["destination", "day"], lambda s, d: T.friends_ring(s, d, None, 3),
    [FLIGHTS, DATA, ring_sql(3), _even_sql(2)], BY_AIRLINE,
), "best")

register("cons_two_friend_rels", Workload(
    _even("array(named_struct('rel', 'ring', 'k', 1), named_struct('rel', 'pair', 'k', 1))"), T.flights, "flight_id", ["destination", "day"],
    lambda s, d: T.friends_ring(s, d, None, 3).withColumn("rel", F.lit("ring")).unionByName(
        T.customers(s, d).select(F.col("c_custkey").alias("user"), F.expr("c_custkey ^ 1").alias("friend"), F.lit("pair").alias("rel"))),
    [FLIGHTS, DATA, ring_sql(3, "ring", "ring"), "fr AS (SELECT * FROM ring UNION ALL SELECT c_custkey, xor(c_custkey, 1), 'pair' FROM customer)",
     _even_sql().replace("ask AS (SELECT qid, 'friends' AS rel, 1 AS k FROM req)", "ask AS (SELECT qid, rel, 1 AS k FROM req, (VALUES ('ring'), ('pair')) t(rel))")],
    BY_AIRLINE,
), "best")

register("cons_multi_relation", Workload(
    _even(), T.flights, ("flight_id", "hotel_id"),
    ["destination", "day", "hotel_id"], lambda s, d: T.friends_ring(s, d, None, 2),
    [FLIGHTS, "data AS (SELECT flights.*, s_suppkey AS hotel_id FROM flights JOIN nation ON n_name = destination JOIN supplier ON s_nationkey = n_nationkey)", ring_sql(2), _even_sql()],
    BY_AIRLINE, right=lambda s, d: T.hotels(s, d).withColumnRenamed("location", "destination"), on=["destination"],
), "assignment")

register("cons_same_tuple", Workload(
    lambda s, d: _even()(s, d).withColumn("same_tuple", F.lit(True)), T.flights, "flight_id", ["destination", "day", "flight_id"], lambda s, d: T.friends_ring(s, d, None, 2),
    [FLIGHTS, DATA, ring_sql(2), _even_sql()], BY_AIRLINE,
), "best")


register("cons_named_only", Workload(
    _even(T.NO_ASK, "array(user ^ 1)"), T.flights, "flight_id", ["destination", "day"], lambda s, d: T.friends_ring(s, d, None, 1),
    [FLIGHTS, DATA, ring_sql(1), _even_sql().split(",\nnamed")[0] + ", named AS (SELECT qid, xor(qid, 1) AS partner FROM req), ask AS (SELECT 0 AS qid, '' AS rel, 0 AS k WHERE false)"],
    BY_AIRLINE,
), "sets")


def _memory(spark, d):
    m = travel().run(spark, d).memory()
    return m.select("edges", "option_rows", F.col("values"))


Q["cons_memory"] = _memory
SQL["cons_memory"] = travel().sql() + "SELECT (SELECT count(*) FROM edge) AS edges, (SELECT count(*) FROM vq) AS option_rows, (SELECT count(DISTINCT vid) FROM vq) AS values"


def _parties() -> Workload:
    return Workload(
        lambda s, d: T.requests(T.table(s, d, "events").select(F.col("user_id").alias("user")).distinct(), "map('user', cast(user as string))"), T.party_options, ("user", "party_type", "party_day"),
        ["party_type", "party_day"], lambda s, d: T.groups_coactive(s, d, 10),
        ["data AS (SELECT DISTINCT user_id AS usr, event_type AS party_type, CAST(ts AS DATE) AS party_day FROM events)",
         "b AS (SELECT DISTINCT user_id, CAST(floor(epoch(ts) / 600) AS BIGINT) AS bucket FROM events), fr AS (SELECT DISTINCT a.user_id AS usr, c.user_id AS friend, 'friends' AS rel FROM b a JOIN b c USING (bucket) WHERE a.user_id <> c.user_id)",
         "req AS (SELECT DISTINCT user_id AS qid, 0.0 AS weight FROM events), named AS (SELECT 0 AS qid, 0 AS partner WHERE false), ask AS (SELECT qid, 'friends' AS rel, 1 AS k FROM req)"],
        "r.qid = s.usr",
    )


register("cons_parties", _parties(), "sets")
Q["cons_pack_values"] = _pack


def by_rounds(spark: SparkSession, d: str, w: Workload) -> DataFrame:
    """All values of a workload, cleaned by rounds over tables."""
    w, requests, friends, vq = _parts(spark, d, w)
    vq = keep(vq)
    edges = cut(C.pruned_graph(requests, friends, vq))
    return shown(C.value_sets(C.clean(vq, edges, requests, w.coord, "rounds"), requests, w.coord), *w.coord, "n", "members")


def _removed(spark, d):
    """Requests that fall out in all rounds of cleaning."""
    w = MOVIES
    r = w.run(spark, d)
    return C.cleaning_rounds(r.nodes.join(r.patterns, "pid").select("qid", *r.coord), r.edges, w.requests(spark, d), r.coord).agg(F.coalesce(F.sum("removed"), F.lit(0)).alias("removed"))


Q |= {"clean_rounds": lambda spark, d: by_rounds(spark, d, MOVIES), "cons_cleaning": _removed}
SQL["clean_rounds"] = SQL["cons_movies"]
SQL["cons_cleaning"] = MOVIES.sql() + "SELECT count(*) AS removed FROM dead"


def _composite(spark, d):
    return shown(_parties().run(spark, d).assignment, "user", "party_type", "party_day")


Q["cons_composite_key"] = _composite
SQL["cons_composite_key"] = _parties().sql() + """, best AS (SELECT * FROM sets ORDER BY n DESC, party_type, party_day LIMIT 1)
SELECT unnest(ids) AS user, party_type, CAST(party_day AS VARCHAR) AS party_day FROM best"""


def _rollup(spark, d):
    s = travel().run(spark, d).sizes
    return s.rollup("destination", F.year("day").cast("string").alias("y")).agg(F.count("*").alias("n_sets"), F.max("n").alias("largest"))


def _topk(spark, d):
    r = travel().run(spark, d)
    return shown(largest().ranked(r.sizes, r.coord, 10), *r.coord, "n")


Q |= {"set_size_rollup": _rollup, "topk_sets": _topk}
SQL["set_size_rollup"] = travel().sql() + "SELECT destination, CAST(year(day) AS VARCHAR) AS y, count(*) AS n_sets, max(n) AS largest FROM sets GROUP BY ROLLUP (destination, CAST(year(day) AS VARCHAR))"
SQL["topk_sets"] = travel().sql() + "SELECT destination, CAST(day AS VARCHAR) AS day, n FROM sets ORDER BY n DESC, destination, day LIMIT 10"


# ---------------------------------------------------------------- literal example


def ex_movie_inputs(spark: SparkSession):
    """Four users and three cinemas: one names a partner that is no friend, three ask for any friend."""
    users = spark.createDataFrame([(1, "c"), (2, "g"), (3, "j"), (4, "w")], "user long, who string")
    own = "case who when 'c' then map('cinema', 'r', 'title', 't1') when 'g' then map('cinema', 'a', 'title', 't2') else map('title', 't3') end"
    requests = T.requests(users, own, "case who when 'c' then array(4L) else array() end", f"case who when 'c' then {T.NO_ASK} else {T.ANY_ONE} end")
    data = spark.createDataFrame([(1, "r", "t3"), (2, "a", "t3"), (3, "k", "t3"), (4, "r", "t1"), (5, "a", "t2")], "movie_id long, cinema string, title string")
    friends = spark.createDataFrame([(1, 3), (1, 2), (2, 1), (2, 3), (3, 1), (3, 4), (4, 1), (4, 2)], "user long, friend long")
    return requests, data, friends


def _ex_movies(spark, d):
    requests, data, friends = ex_movie_inputs(spark)
    return C.consistent_coordinate(requests, data, "movie_id", ["cinema"], friends).sets.select("cinema", "n", "members")


Q["ex_movies"] = _ex_movies
SQL["ex_movies"] = "SELECT * FROM (VALUES ('r', 3::BIGINT, '1,3,4'), ('a', 3::BIGINT, '2,3,4')) t(cinema, n, members)"
