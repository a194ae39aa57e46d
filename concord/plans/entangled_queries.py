"""Safe-set coordination and its graph toolkit on the given tables, with DuckDB counterparts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from concord.model import explode_atoms, validate
from concord.operators import graph as G
from concord.operators import scc as S
from concord.operators import translate as X
from concord.operators import unify as U
from concord.operators import verify as V
from concord.operators.select import containing, first, most_weight
from concord.sources import entangled as E
from concord.sources import tables as T

Q: dict = {}
SQL: dict[str, str] = {}


def edges_sql(n: int, seed: int = 0, back: int = 0) -> str:
    base = f"SELECT i AS src, (i * r * r) >> 32 AS dst FROM (SELECT i, ((((i + {seed} * 1000003) * 1103515245 + 12345) % 2147483648) >> 15) AS r FROM range(1, {n}) t(i))"
    return f"e AS MATERIALIZED ({base}" + (f" UNION SELECT dst, src FROM ({base}) WHERE src % {back} = 0" if back else "") + ")"


def reach_sql(ctes: str, nodes: str) -> str:
    """r(a, b): b reachable from a; scc(q, scc_id)."""
    return f"""WITH RECURSIVE {ctes}, nodes AS ({nodes}),
r(a, b) AS (SELECT q, q FROM nodes UNION SELECT r.a, e.dst FROM r JOIN e ON e.src = r.b),
scc AS MATERIALIZED (SELECT x.a AS q, min(x.b) AS scc_id FROM r x JOIN r y ON x.a = y.b AND x.b = y.a GROUP BY 1),
dag AS MATERIALIZED (SELECT DISTINCT s.scc_id AS src_scc, t.scc_id AS dst_scc FROM e JOIN scc s ON s.q = e.src JOIN scc t ON t.q = e.dst WHERE s.scc_id <> t.scc_id)
"""


NET = (300, 0, 10)  # users, seed, every tenth edge also backwards


def sf(spark, n=NET[0], seed=NET[1], back=NET[2]):
    return T.scale_free(spark, n, seed, back), spark.range(n).select(F.col("id").alias("qid"))


GRAPH = reach_sql(edges_sql(*NET), f"SELECT i AS q FROM range(0, {NET[0]}) t(i)")



def networks_sql(seed: int = 0, back: int = 0) -> str:
    base = f"""SELECT src, i, src - i + ((i * r * r) >> 32) AS dst FROM (SELECT src, i, ((((i + {seed} * 1000003) * 1103515245 + 12345) % 2147483648) >> 15) AS r
  FROM (SELECT CAST(c_custkey AS BIGINT) AS src, CAST(c_custkey AS BIGINT) % {T.NETWORK} AS i FROM customer) WHERE i > 0)"""
    base = f"SELECT * FROM ({base}) WHERE dst IN (SELECT c_custkey FROM customer)"
    return f"e AS MATERIALIZED (SELECT src, dst FROM ({base})" + (f" UNION SELECT dst, src FROM ({base}) WHERE i % {back} = 0" if back else "") + ")"


def nets(s, d):
    """Nodes and edges of the networks of all customers."""
    return T.customers(s, d).select(F.col("c_custkey").cast("long").alias("qid")), T.scale_free_networks(s, d, *NET[1:])


NETS = reach_sql(networks_sql(*NET[1:]), "SELECT CAST(c_custkey AS BIGINT) AS q FROM customer")


def groups(s, d, eqs: DataFrame, size: int) -> DataFrame:
    """A copy of small queries for every customer whose id is divisible by ``size``: relations are the group's own, ids count from the customer's."""
    own = lambda atoms: F.transform(atoms, lambda a: F.struct(F.concat(a["rel"], F.lit("#"), F.col("__g").cast("string")).alias("rel"), a["terms"].alias("terms")))
    g = T.customers(s, d).where(F.col("c_custkey") % size == 0).select(F.col("c_custkey").cast("long").alias("__g"))
    copies = g.join(F.broadcast(eqs), how="cross").withColumn("qid", F.col("__g") + F.col("qid"))
    return copies.select(*[own(c).alias(c) if c in ("post", "head", "body") else F.col(c) for c in eqs.columns])


def groups_sql(size: int, rows: str) -> str:
    return f"SELECT c_custkey + src AS src, post_pos, c_custkey + dst AS dst, head_pos FROM customer, (VALUES {rows}) t(src, post_pos, dst, head_pos) WHERE c_custkey % {size} = 0"


Q["ext_edges_list"] = lambda s, d: U.extended_graph(E.chain(s, d, 100))
SQL["ext_edges_list"] = "SELECT c_custkey AS src, 0 AS post_pos, c_custkey + 1 AS dst, 0 AS head_pos FROM customer WHERE c_custkey < 99"
Q["ext_edges_nested"] = lambda s, d: U.extended_graph(E.chain(s, d, 100), join="nested")
SQL["ext_edges_nested"] = SQL["ext_edges_list"]
Q["coord_edges_list"] = lambda s, d: U.coordination_graph(U.extended_graph(E.network(s, d, sf(s)[0], NET[0])))
SQL["coord_edges_list"] = f"WITH {edges_sql(*NET)} SELECT DISTINCT src, dst FROM e"
#: Customers travel in groups of four, each with the wishes of the example.
Q["ext_edges_flight_hotel"] = lambda s, d: U.extended_graph(groups(s, d, E.flight_hotel(s)[0], 4))
SQL["ext_edges_flight_hotel"] = groups_sql(4, "(1, 0, 2, 0), (2, 0, 1, 0), (2, 1, 1, 1), (3, 0, 1, 0), (3, 1, 2, 0), (4, 0, 1, 0), (4, 1, 3, 1)")


def _doubled(s, d) -> DataFrame:
    """The list with every tenth seat offered twice: whoever asks it is unsafe."""
    eqs = E.chain(s, d, 100)
    twice = eqs.where("qid % 10 = 0").withColumn("qid", F.col("qid") + 1000).withColumn("post", E.none())
    return eqs.unionByName(twice)


def _safety(s, d):
    eqs = _doubled(s, d)
    return U.safety(U.extended_graph(eqs), eqs).select("qid", "is_safe", F.coalesce("offending_post", F.lit(-1)).cast("int").alias("offending_post"))


Q["safety_report"] = _safety
SQL["safety_report"] = """SELECT c_custkey AS qid, NOT (c_custkey % 10 = 9 AND c_custkey < 99) AS is_safe, CASE WHEN c_custkey % 10 = 9 AND c_custkey < 99 THEN 0 ELSE -1 END AS offending_post FROM customer WHERE c_custkey < 100
UNION ALL SELECT c_custkey + 1000, true, -1 FROM customer WHERE c_custkey < 100 AND c_custkey % 10 = 0"""


def _unique(s, d):
    c = G.strong_components(*nets(s, d))
    return c.groupBy("comp_id").agg(F.count("*").alias("queries"), F.countDistinct("scc_id").alias("components")).withColumn("is_unique", F.col("components") == 1)


Q["unique_report"] = _unique
SQL["unique_report"] = NETS + ", u AS (SELECT src AS a, dst AS b FROM e UNION SELECT dst, src FROM e), w(a, b) AS (SELECT q, q FROM nodes UNION SELECT w.a, u.b FROM w JOIN u ON u.a = w.b), c AS (SELECT a AS q, min(b) AS comp_id FROM w GROUP BY 1) SELECT comp_id, count(*) AS queries, count(DISTINCT scc_id) AS components, count(DISTINCT scc_id) = 1 AS is_unique FROM c JOIN scc USING (q) GROUP BY 1"


def _pruned(s, d):
    """The list without its 60th user: nobody up to there can be served."""
    eqs = E.chain(s, d, 100).where("qid <> 60")
    return G.prune_unmatched(eqs, U.extended_graph(eqs))


Q["prune_unmatched"] = _pruned
SQL["prune_unmatched"] = "SELECT c_custkey AS qid FROM customer WHERE c_custkey BETWEEN 61 AND 99"
Q["weak_components_sf"] = lambda s, d: G.weak_components(T.scale_free_networks(s, d, 3).where("src % 7 <> 0")).select(F.col("node").alias("qid"), "comp_id")
SQL["weak_components_sf"] = f"WITH RECURSIVE {networks_sql(3)}, f AS (SELECT * FROM e WHERE src % 7 <> 0), u AS (SELECT src AS a, dst AS b FROM f UNION SELECT dst, src FROM f), w(a, b) AS (SELECT a, a FROM u UNION SELECT w.a, u.b FROM w JOIN u ON u.a = w.b) SELECT a AS qid, min(b) AS comp_id FROM w GROUP BY 1"
Q["scc_scale_free"] = lambda s, d: G.strong_components(*nets(s, d)).select("qid", "scc_id")
SQL["scc_scale_free"] = NETS + "SELECT q AS qid, scc_id FROM scc"
Q["scc_distributed"] = lambda s, d: G.strong_components(*reversed(sf(s)), method="fwbw").select("qid", "scc_id")
SQL["scc_distributed"] = GRAPH + "SELECT q AS qid, scc_id FROM scc"
Q["condensation_sf"] = lambda s, d: G.condense(nets(s, d)[1], G.strong_components(*nets(s, d)))
SQL["condensation_sf"] = NETS + "SELECT src_scc, dst_scc FROM dag"
Q["dag_levels_sf"] = lambda s, d: G.strong_components(*nets(s, d)).select("scc_id", F.col("level").cast("long").alias("level")).distinct()
SQL["dag_levels_sf"] = NETS + ", lv(scc_id, l) AS (SELECT DISTINCT scc_id, 0::BIGINT FROM scc UNION SELECT d.src_scc, l + 1 FROM lv JOIN dag d ON d.dst_scc = lv.scc_id) SELECT scc_id, max(l) AS level FROM lv GROUP BY 1"
Q["reach_sizes_sf"] = lambda s, d: G.reach_sets(*nets(s, d)).select("scc_id", "n")
SQL["reach_sizes_sf"] = NETS + "SELECT scc_id, count(*) AS n FROM r JOIN scc ON scc.q = r.a AND scc.scc_id = r.a GROUP BY 1"
Q["atom_table"] = lambda s, d: explode_atoms(E.chain(s, d, 50)).groupBy("role", "rel", "arity", "mask").agg(F.count("*").alias("n"))
SQL["atom_table"] = "SELECT * FROM (VALUES ('post', 'seat', 2, 1::BIGINT, 49::BIGINT), ('head', 'seat', 2, 1::BIGINT, 50::BIGINT), ('body', 'flights', 5, 0::BIGINT, 50::BIGINT)) t(role, rel, arity, mask, n)"
Q["validate_queries"] = lambda s, d: validate(_doubled(s, d).withColumn("head", F.when(F.col("qid") == 3, F.transform("body", lambda b: b)).otherwise(F.col("head"))), {"flights": T.flights(s, d)})
SQL["validate_queries"] = "SELECT 'answer_relation_in_schema' AS rule, 3::BIGINT AS qid, 'flights' AS detail"


# ---------------------------------------------------------------- coordination

SETS = """, sets AS (SELECT r.a AS scc_id, count(*) AS n, string_agg(r.b, ',' ORDER BY r.b) AS members, list(r.b) AS ids, sum(c_acctbal) AS weight
  FROM r JOIN scc ON scc.q = r.a AND scc.scc_id = r.a JOIN customer ON c_custkey = r.b JOIN sat ON sat.q = r.b GROUP BY 1 HAVING bool_and(ok))
"""


def list_sql(n: int, ok: str) -> str:
    return reach_sql(f"e AS (SELECT c_custkey AS src, c_custkey + 1 AS dst FROM customer WHERE c_custkey < {n - 1}), sat AS (SELECT c_custkey AS q, {ok} AS ok FROM customer)", f"SELECT c_custkey AS q FROM customer WHERE c_custkey < {n}") + SETS


def net_sql(ok: str = "c_custkey % 50 <> 7") -> str:
    return reach_sql(edges_sql(*NET) + f", sat AS (SELECT c_custkey AS q, {ok} AS ok FROM customer)", f"SELECT c_custkey AS q FROM customer WHERE c_custkey < {NET[0]}") + SETS


NATION_OK = "EXISTS (SELECT 1 FROM orders o JOIN customer x ON o.o_custkey = x.c_custkey WHERE x.c_nationkey = customer.c_nationkey)"
ONE = " ORDER BY n DESC, scc_id LIMIT 1"


def _best(run) -> DataFrame:
    return run.best.select("scc_id", "n", F.array_join(F.transform("ids", lambda x: x.cast("string")), ",").alias("members"))


def net(s, d, **more):
    return S.scc_coordinate(E.network(s, d, sf(s)[0], NET[0], selective=True), E.catalog(s, d), **more)


Q |= {
    "scc_list": lambda s, d: S.scc_coordinate(E.chain(s, d, 100), E.catalog(s, d)).sets().select("scc_id", "n", "members"),
    "scc_list_wave": lambda s, d: S.scc_coordinate(E.chain(s, d, 100), E.catalog(s, d), mode="wave").sets().select("scc_id", "n", "members"),
    "scc_list_sequential": lambda s, d: S.scc_coordinate(E.chain(s, d, 100), E.catalog(s, d), mode="sequential").sets().select("scc_id", "n", "members"),
    "scc_list_bisect": lambda s, d: S.scc_coordinate(E.chain(s, d, 100), E.catalog(s, d), mode="bisect").sets().select("scc_id", "n", "members"),
    "scc_list_shared": lambda s, d: _best(S.scc_coordinate(E.chain(s, d, 100, shared=True), E.catalog(s, d), {"flights": [0]})),
    "scc_selective": lambda s, d: S.scc_coordinate(E.chain(s, d, 100, selective=True), E.catalog(s, d)).sets().select("scc_id", "n", "members"),
    "scc_all_sets": lambda s, d: net(s, d).sets().select("scc_id", "n", "members"),
    "scc_scale_free_best": lambda s, d: _best(net(s, d)),
    "scc_first": lambda s, d: _best(net(s, d, select=first())),
    "scc_gold": lambda s, d: _best(net(s, d, select=most_weight())),
    "scc_vip": lambda s, d: _best(net(s, d, select=containing(100))),
    "scc_status": lambda s, d: net(s, d).nodes.groupBy("status").agg(F.count("*").alias("n")),
    "scc_social": lambda s, d: _best(S.scc_coordinate(E.social(s, d), E.catalog(s, d))),
}
SQL |= {
    "scc_list": list_sql(100, "true") + "SELECT scc_id, n, members FROM sets",
    "scc_list_wave": list_sql(100, "true") + "SELECT scc_id, n, members FROM sets",
    "scc_list_sequential": list_sql(100, "true") + "SELECT scc_id, n, members FROM sets",
    "scc_list_bisect": list_sql(100, "true") + "SELECT scc_id, n, members FROM sets",
    "scc_list_shared": list_sql(100, "true") + "SELECT scc_id, n, members FROM sets" + ONE,
    "scc_selective": list_sql(100, NATION_OK) + "SELECT scc_id, n, members FROM sets",
    "scc_all_sets": net_sql() + "SELECT scc_id, n, members FROM sets",
    "scc_scale_free_best": net_sql() + "SELECT scc_id, n, members FROM sets" + ONE,
    "scc_first": net_sql() + "SELECT scc_id, n, members FROM sets ORDER BY scc_id LIMIT 1",
    "scc_gold": net_sql() + "SELECT scc_id, n, members FROM sets ORDER BY weight DESC, scc_id LIMIT 1",
    "scc_vip": net_sql() + "SELECT scc_id, n, members FROM sets WHERE list_contains(ids, 100)" + ONE,
    "scc_status": net_sql() + """SELECT CASE WHEN own AND lost = 0 THEN 'ok' WHEN lost > 0 THEN 'successor_failed' ELSE 'no_grounding' END AS status, count(*) AS n FROM (
 SELECT s.scc_id, bool_and(k.ok) FILTER (k.scc_id = s.scc_id) AS own, count(*) FILTER (NOT k.ok AND k.scc_id <> s.scc_id) AS lost
 FROM (SELECT DISTINCT scc_id FROM scc) s JOIN r ON r.a = s.scc_id JOIN (SELECT scc.q, scc_id, ok FROM scc JOIN sat ON sat.q = scc.q) k ON k.q = r.b GROUP BY 1) GROUP BY 1""",
    "scc_social": """WITH RECURSIVE b AS (SELECT DISTINCT user_id AS u, CAST(floor(epoch(ts) / 600) AS BIGINT) AS k FROM events),
e AS MATERIALIZED (SELECT x.u AS src, min(y.u) AS dst FROM b x JOIN b y USING (k) WHERE x.u <> y.u GROUP BY 1), nodes AS (SELECT src AS q FROM e),
r(a, b) AS (SELECT q, q FROM nodes UNION SELECT r.a, e.dst FROM r JOIN e ON e.src = r.b),
scc AS (SELECT x.a AS q, min(x.b) AS scc_id FROM r x JOIN r y ON x.a = y.b AND x.b = y.a GROUP BY 1)
SELECT scc_id, count(*) AS n, string_agg(r.b, ',' ORDER BY r.b) AS members FROM r JOIN scc ON q = r.a AND scc_id = r.a GROUP BY 1""" + ONE,
}


# ---------------------------------------------------------------- baselines


def rings(s, d, n: int = 100, size: int = 5):
    """Groups of five, each member asking the next of its group: unique components."""
    e = s.range(n).select(F.col("id").alias("src"), (F.col("id") - F.col("id") % size + (F.col("id") + 1) % size).alias("dst"))
    return E.network(s, d, e, n, selective=True)


RING_SQL = "SELECT c_custkey - c_custkey % 5 AS scc_id, count(*) AS n, string_agg(c_custkey, ',' ORDER BY c_custkey) AS members FROM customer WHERE c_custkey < 100 GROUP BY 1 HAVING bool_and(c_custkey % 50 <> 7)"
def _first_found(s, d):
    return _best(S.scc_coordinate(E.network(s, d, sf(s)[0], NET[0], selective=True), E.catalog(s, d), stop_at_first=True))


Q["scc_first_found"] = _first_found
SQL["scc_first_found"] = net_sql() + "SELECT scc_id, n, members FROM sets WHERE scc_id NOT IN (SELECT src_scc FROM dag)" + ONE


def _mode_costs(s, d, n: int = 32):
    """Database queries by mode on a list whose users from 20 to 27 want what does not exist: nobody up to 27 can be served."""
    eqs = E.chain(s, d, n)
    bad = F.transform("body", lambda b: F.struct(b["rel"].alias("rel"), F.transform(b["terms"], lambda t, i: F.when(i == 1, F.struct(F.lit(None).cast("string").alias("var"), F.lit("string:nowhere").alias("const"))).otherwise(t)).alias("terms")))
    eqs = eqs.withColumn("body", F.when(F.col("qid").between(20, 27), bad).otherwise(F.col("body")))
    out = None
    for mode in ("bulk", "wave", "sequential", "bisect"):
        run = S.scc_coordinate(eqs, E.catalog(s, d), mode=mode)
        asked = run.database_queries().select(F.lit(mode).alias("mode"), "db_queries").join(F.broadcast(run.nodes.agg(F.count_if(F.col("status") == "ok").alias("sets_found"))), how="cross")
        out = asked if out is None else out.unionByName(asked)
    return out


Q["mode_costs"] = _mode_costs
#: Levels count from the last user: 0 to 3 coordinate, 4 fails. Bisection over 32 levels tries the middles of (-1, 32), (-1, 15), (-1, 7), (3, 7) and (3, 5).
SQL["mode_costs"] = """WITH c AS (SELECT c_custkey AS q, c_custkey BETWEEN 20 AND 27 AS bad FROM customer WHERE c_custkey < 32),
k AS (SELECT count(*) AS n, count(*) FILTER (q > (SELECT max(q) FROM c WHERE bad)) AS ok FROM c),
h(good, stop, tried) AS (SELECT -1, n, 0 FROM k UNION ALL SELECT CASE WHEN (good + stop) // 2 < ok THEN (good + stop) // 2 ELSE good END, CASE WHEN (good + stop) // 2 < ok THEN stop ELSE (good + stop) // 2 END, tried + 1 FROM h, k WHERE stop - good > 1)
SELECT * FROM (SELECT 'bulk' AS mode, n AS db_queries, ok AS sets_found FROM k UNION ALL SELECT 'wave', ok + 1, ok FROM k UNION ALL SELECT 'sequential', ok + 1, ok FROM k UNION ALL SELECT 'bisect', (SELECT max(tried) FROM h), ok FROM k)"""
SQL["mode_costs"] = SQL["mode_costs"].replace("WITH c AS", "WITH RECURSIVE c AS")


def _mgu(s, d):
    """Heads with repeated variables: agreeing constants are not enough."""
    from concord.model import Entangled, Var, atom, frame

    x, z = Var("x"), Var("z")
    heads = [Entangled(10).offer(atom("r", 1, z, z)), Entangled(11).offer(atom("r", 2, z, z)), Entangled(12).offer(atom("r", z, 1, 2))]
    posts = [Entangled(1).given(atom("r", x, x, 2)), Entangled(2).given(atom("r", x, Var("y"), 2)), Entangled(3).given(atom("r", x, x, x))]
    return U.extended_graph(groups(s, d, frame(s, heads + posts), 20), mode="mgu")


Q["ext_edges_mgu"] = _mgu
#: r(x,x,2) meets r(2,z,z) and r(z,1,2); r(x,y,2) all; r(x,x,x) the two with one value.
SQL["ext_edges_mgu"] = groups_sql(20, "(1, 0, 11, 0), (1, 0, 12, 0), (2, 0, 10, 0), (2, 0, 11, 0), (2, 0, 12, 0), (3, 0, 10, 0), (3, 0, 11, 0)")
Q["uniqueness_report"] = lambda s, d: S.uniqueness(rings(s, d).unionByName(E.chain(s, d, 105).where("qid >= 100")))
SQL["uniqueness_report"] = "SELECT c_custkey - c_custkey % 5 AS comp_id, count(*) AS queries, true AS is_safe, max(c_custkey) < 100 AS is_unique FROM customer WHERE c_custkey < 105 GROUP BY 1"
Q["union_of_branches"] = lambda s, d: S.union_check(S.scc_coordinate(*E.two_branches(s)), [3, 5], E.two_branches(s)[1])
SQL["union_of_branches"] = "SELECT 6::BIGINT AS n, '1,2,3,4,5,6' AS members, 'ok' AS status"
Q |= {
    "baseline_unique": lambda s, d: S.unique_coordinate(rings(s, d), E.catalog(s, d)).sets().select("scc_id", "n", "members"),
    "baseline_unique_refuses": lambda s, d: S.unique_coordinate(E.chain(s, d, 50), E.catalog(s, d)).nodes.agg(F.count("*").alias("accepted")),
    "baseline_allornothing": lambda s, d: S.unique_coordinate(E.chain(s, d, 50), E.catalog(s, d), check=False).sets().select("scc_id", "n", "members"),
    "baseline_bodies_only": lambda s, d: S.bodies_only(E.network(s, d, sf(s)[0], NET[0], True), E.catalog(s, d)).nodes.groupBy("status").agg(F.count("*").alias("n")),
}
SQL |= {
    "baseline_unique": RING_SQL,
    "baseline_unique_refuses": "SELECT 0::BIGINT AS accepted",
    "baseline_allornothing": "SELECT 0::BIGINT AS scc_id, count(*) AS n, string_agg(c_custkey, ',' ORDER BY c_custkey) AS members FROM customer WHERE c_custkey < 50",
    "baseline_bodies_only": f"SELECT CASE WHEN c_custkey % 50 <> 7 THEN 'ok' ELSE 'no_grounding' END AS status, count(*) AS n FROM customer WHERE c_custkey < {NET[0]} GROUP BY 1",
}


def _attributes(s, d):
    return {c: k for c, k in T.flights(s, d).dtypes if c != "flight_id"}


def _precoordinated(s, d):
    """Eight travellers who agree beforehand on their least friend of a small ring."""
    users = T.customers(s, d, 8).withColumn("user", F.col("c_custkey"))
    friends = T.customers(s, d, 8).select(F.col("c_custkey").alias("user"), ((F.col("c_custkey") + 1) % 4).alias("friend"))
    fixed = X.precoordinate(T.requests(users), friends)
    eqs = X.to_entangled(fixed, _attributes(s, d), "flight_id", ["destination", "day"])
    return _best(S.scc_coordinate(eqs, {"data": T.flights(s, d)}, {"data": [0]}))


Q["baseline_precoord"] = _precoordinated
SQL["baseline_precoord"] = """WITH RECURSIVE e AS (SELECT c_custkey AS src, (c_custkey + 1) % 4 AS dst FROM customer WHERE c_custkey < 8), r(a, b) AS (SELECT src, src FROM e UNION SELECT r.a, e.dst FROM r JOIN e ON e.src = r.b)
SELECT a AS scc_id, count(*) AS n, string_agg(b, ',' ORDER BY b) AS members FROM r GROUP BY 1 ORDER BY n DESC, scc_id LIMIT 1"""


def _consistency(s, d):
    """Requests in entangled form, every third with its own source asked of the partner too (then no longer consistent)."""
    users = T.customers(s, d, 30).withColumn("user", F.col("c_custkey"))
    eqs = X.to_entangled(T.requests(users, named="array((user + 1) % 30)", asks=T.NO_ASK), _attributes(s, d), "flight_id", ["destination", "day"])
    odd = F.transform("body", lambda b: F.struct(b["rel"].alias("rel"), F.transform(b["terms"], lambda t, i: F.when(i == 3, F.struct(F.lit(None).cast("string").alias("var"), F.lit("string:FURNITURE").alias("const"))).otherwise(t)).alias("terms")))
    mixed = eqs.withColumn("body", F.when(F.col("qid") % 3 == 0, odd).otherwise(F.col("body")))
    return X.consistency(mixed, "data", ["destination", "day", "source", "airline"], ["destination", "day"])


Q["consistency_report"] = _consistency
SQL["consistency_report"] = "SELECT c_custkey AS qid, true AS coordinating, false AS non_coordinating, c_custkey % 3 <> 0 AS consistent FROM customer WHERE c_custkey < 30"


def _mixed(s, d):
    """How many requests coordinate on which attributes, where every third leaves the day open."""
    users = T.customers(s, d, 30).withColumn("user", F.col("c_custkey"))
    build = lambda coord: X.to_entangled(T.requests(users, named="array((user + 1) % 30)", asks=T.NO_ASK), _attributes(s, d), "flight_id", coord)
    eqs = build(["destination", "day"]).where("qid % 3 <> 0").unionByName(build(["destination"]).where("qid % 3 = 0"))
    return X.coordination_signature(eqs, "data", ["destination", "day", "source", "airline"]).groupBy("attributes").agg(F.count("*").alias("n"))


Q["mixed_attributes"] = _mixed
SQL["mixed_attributes"] = "SELECT CASE WHEN c_custkey % 3 = 0 THEN 'destination' ELSE 'destination,day' END AS attributes, count(*) AS n FROM customer WHERE c_custkey < 30 GROUP BY 1"


def _exists(s, d):
    """The decision problem: a list, a list whose last user is missing, rings with tails."""
    from concord.operators.single import exists_coordination
    from concord.plans.other_queries import lassos

    rows = [("list", *exists_coordination(E.chain(s, d, 20), E.catalog(s, d))), ("nobody", *exists_coordination(E.chain(s, d, 20).where("qid <> 19"), E.catalog(s, d))), ("lassos", *exists_coordination(lassos(s, d), E.catalog(s, d)))]
    return s.createDataFrame(rows, "name string, found boolean, decided_by string")


Q["exists_report"] = _exists
SQL["exists_report"] = "SELECT 'list' AS name, count(*) = 20 AS found, 'safe' AS decided_by FROM customer WHERE c_custkey < 20 UNION ALL SELECT 'nobody', count(*) = 0, 'safe' FROM customer WHERE c_custkey < 0 UNION ALL SELECT 'lassos', count(*) > 0, 'safe' FROM customer WHERE c_custkey BETWEEN 0 AND 59"
SQL["exists_report"] = SQL["exists_report"].replace("SELECT 'nobody', count(*) = 0", "SELECT 'nobody', count(*) > 0")


# ---------------------------------------------------------------- verification, costs, examples


def _verified(s, d):
    eqs = E.network(s, d, sf(s)[0], NET[0], True)
    run = S.scc_coordinate(eqs, E.catalog(s, d))
    return V.verify_set(run.assignment(), eqs, E.catalog(s, d)).agg(F.count("*").alias("violations"))


Q["verify_report"] = _verified
SQL["verify_report"] = "SELECT 0::BIGINT AS violations"
Q["cost_bounds"] = lambda s, d: V.cost_report(S.scc_coordinate(E.chain(s, d, 100), E.catalog(s, d)))
SQL["cost_bounds"] = list_sql(100, "true") + """, ext AS (SELECT count(*) AS edges FROM e), q AS (SELECT count(*) AS n FROM nodes),
lv(scc_id, l) AS (SELECT DISTINCT scc_id, 0::BIGINT FROM scc UNION SELECT d.src_scc, l + 1 FROM lv JOIN dag d ON d.dst_scc = lv.scc_id),
v AS (SELECT (SELECT count(DISTINCT scc_id) FROM scc) AS c, (SELECT max(l) + 1 FROM lv) AS l, (SELECT max(n) FROM sets) AS m, (SELECT count(*) FROM sets) AS f, (SELECT edges FROM ext) AS u, (SELECT n FROM q) AS n)
SELECT unnest(['db_queries', 'components', 'levels', 'set_size', 'sets_found', 'unify_steps', 'queries', 'coverage']) AS name, unnest([c, c, l, m, f, u, n, m / n]::DOUBLE[]) AS value FROM v"""


def _example(build, **more):
    def query(s, d):
        eqs, cat = build(s)
        return S.scc_coordinate(eqs, cat, **more).nodes.select("scc_id", F.array_join(F.transform("ids", lambda x: x.cast("string")), ",").alias("members"), "status")

    return query


def _values(*rows) -> str:
    return "SELECT scc_id::BIGINT AS scc_id, members, status FROM (VALUES " + ", ".join(f"({a}, '{b}', '{c}')" for a, b, c in rows) + ") t(scc_id, members, status)"


Q |= {
    "ex_two_flyers": _example(E.two_flyers),
    "ex_flight_hotel": _example(E.flight_hotel, keys={"flights": [0], "hotels": [0]}),
    "ex_flight_hotel_multistop": _example(lambda s: E.flight_hotel(s, True)),
    "ex_band_plus_one": _example(E.band_plus_one),
    "ex_two_branches": _example(E.two_branches),
}
SQL |= {
    "ex_two_flyers": _values((1, "1,2", "ok"), (2, "2", "ok")),
    "ex_flight_hotel": _values((1, "1,2", "ok"), (3, "1,2,3", "unify_failed"), (4, "1,2,3,4", "successor_failed")),
    "ex_flight_hotel_multistop": _values((1, "1,2", "ok"), (3, "1,2,3", "ok"), (4, "1,2,3,4", "ok")),
    "ex_band_plus_one": _values((1, "1,2,3,4", "ok"), (5, "1,2,3,4,5", "ok")),
    "ex_two_branches": _values((1, "1,2", "ok"), (3, "1,2,3,4", "ok"), (5, "1,2,5,6", "ok")),
}
