"""Consistent requests: the movie example, cleaning modes, generalisations, and exhaustive search on translations."""

import random

import pytest
from pyspark.sql import functions as F

from concord.functions import exact
from concord.model import Entangled
from concord.operators import consistent as C
from concord.operators import translate as X
from concord.operators.select import containing, first
from concord.plans.consistent_queries import ex_movie_inputs
from concord.sources import tables as T

D = "/root/testdata/sf0.001"


def sets(run):
    return {tuple(r[c] for c in run.coord): r["members"] for r in run.sets.collect()}


def test_movies(spark):
    requests, data, friends = ex_movie_inputs(spark)
    run = C.consistent_coordinate(requests, data, "movie_id", ["cinema"], friends)
    vq = {}
    for r in run.vq.collect():
        vq.setdefault(r["qid"], set()).add(r["cinema"])
    assert vq == {1: {"r"}, 2: {"a"}, 3: {"r", "a", "k"}, 4: {"r", "a", "k"}}
    assert {(r["src"], r["dst"]) for r in run.edges.collect()} == {(1, 4), (2, 1), (2, 3), (3, 1), (3, 4), (4, 1), (4, 2)}
    assert sets(run) == {("r",): "1,3,4", ("a",): "2,3,4"}
    assert [r["cinema"] for r in run.best.collect()] == ["a"]
    assert {r["user"]: r["movie_id"] for r in run.assignment.collect()} == {2: 5, 3: 2, 4: 2}
    vip = C.consistent_coordinate(requests, data, "movie_id", ["cinema"], friends, containing(1))
    assert [r["cinema"] for r in vip.best.collect()] == ["r"]


@pytest.mark.parametrize("mode", ["rounds", "sequential"])
def test_cleaning_modes_agree(spark, mode):
    requests = T.travellers(spark, D, 60)
    data = T.flights(spark, D).where("month(day) <= 2")
    friends = T.friends_ring(spark, D, 60, 2)
    coord = ["destination"]
    vq = C.options(requests, data, coord, friends)
    edges = C.pruned_graph(requests, friends, vq)
    a, b = (sorted(map(tuple, C.clean(vq, edges, requests, coord, m).collect())) for m in ("local", mode))
    assert a == b and a


def small(spark, rows):
    """(user, own, named, asks) rows as requests."""
    return spark.createDataFrame([(u, u, own, named, asks, False, 1.0) for u, own, named, asks in rows], T.REQUEST)


DATA = [(1, "p", "s"), (2, "p", "t"), (3, "q", "s")]


def data(spark):
    return spark.createDataFrame(DATA, "key long, place string, kind string")


def friends_of(spark, pairs, rel="friends"):
    return spark.createDataFrame([(a, b, rel) for a, b in pairs], "user long, friend long, rel string")


def test_k_friends_cascade(spark):
    two = [("friends", 2)]
    requests = small(spark, [(1, {}, [], two), (2, {}, [], [("friends", 1)]), (3, {"place": "q"}, [], [("friends", 1)])])
    run = C.consistent_coordinate(requests, data(spark), "key", ["place"], friends_of(spark, [(1, 2), (1, 3), (2, 1), (3, 2)]))
    assert sets(run) == {("q",): "1,2,3"}  # at p user 1 has one friend only, then user 2 has none


def test_two_relations_missing_partner_named_stranger(spark):
    both = [("a", 1), ("b", 1)]
    f = friends_of(spark, [(1, 2)], "a").union(friends_of(spark, [(1, 3)], "b"))
    requests = small(spark, [(1, {}, [], both), (2, {}, [], []), (3, {"place": "q"}, [], []), (4, {}, [9], []), (5, {}, [2], [])])
    run = C.consistent_coordinate(requests, data(spark), "key", ["place"], f)
    assert sets(run) == {("p",): "2,5", ("q",): "1,2,3,5"}


def test_self_friendship_no_friends_and_first(spark):
    requests = small(spark, [(1, {}, [], [("friends", 1)])])
    mine = friends_of(spark, [(1, 1)])
    assert sets(C.consistent_coordinate(requests, data(spark), "key", ["place"], mine)) == {("p",): "1", ("q",): "1"}
    assert sets(C.consistent_coordinate(requests, data(spark), "key", ["place"], mine, allow_self=False)) == {}
    none = friends_of(spark, [(7, 8)])
    run = C.consistent_coordinate(requests, data(spark), "key", ["place"], none, first())
    assert sets(run) == {} and run.assignment.count() == 0


def test_same_tuple_and_composite_key(spark):
    requests = small(spark, [(1, {"kind": "s"}, [2], []), (2, {}, [], [])]).withColumn("same_tuple", F.lit(True))
    run = C.consistent_coordinate(requests, data(spark), ("key", "place"), ["place"], friends_of(spark, [(1, 2)]))
    assert run.coord == ["place", "key"]
    assert {tuple(r[c] for c in run.coord): r["members"] for r in run.sets.where("n = 2").collect()} == {("p", 1): "1,2", ("q", 3): "1,2"}


def test_violations(spark):
    requests = small(spark, [(1, {"colour": "x"}, [], [("friends", 0)])])
    requests = requests.union(requests.withColumn("same_tuple", F.lit(True)))
    rules = {r["rule"] for r in C.validate_requests(requests, ["place", "kind"]).collect()}
    assert rules == {"one_request_per_user", "unknown_attribute", "ask_below_one", "mixed_coordination"}


def test_two_dates_of_a_schedule(spark):
    import datetime as dt

    flights = spark.createDataFrame([(1, "x", dt.date(2024, 1, 1)), (2, "x", dt.date(2024, 1, 2))], "id long, place string, day date")
    events = spark.createDataFrame([("x", dt.date(2024, 1, 2))], "location string, event_day date")
    assert [r["id"] for r in C.scheduled(flights, events, {"place": "location"}, "day", "event_day").collect()] == [1]


def test_random_requests_against_exhaustive_search(spark):
    """A set exists for the requests exactly if their translation has one; survivor sets are coordinating sets."""
    rnd = random.Random(4)
    rows, pairs = [], []
    for g in range(40):
        users = [10 * g + i for i in range(rnd.randint(1, 3))]
        pairs += [(a, b) for a in users for b in users if a != b and rnd.random() < 0.6]
        for u in users:
            own = {k: rnd.choice(v) for k, v in (("place", "pq"), ("kind", "st")) if rnd.random() < 0.4}
            kind = rnd.random()
            rows.append((u, own, [rnd.choice(users)] if kind < 0.4 else [], [("friends", 1)] if 0.4 <= kind < 0.9 else []))
    requests, friends = small(spark, rows), friends_of(spark, pairs)
    run = C.consistent_coordinate(requests, data(spark), "key", ["place"], friends)
    survivors: dict = {}
    for r in run.survivors.collect():
        survivors.setdefault((r["qid"] // 10, r["place"]), []).append(r["qid"])
    facts = {"data": {(f"long:{a}", f"string:{b}", f"string:{c}") for a, b, c in DATA}, "friends": {(f"long:{a}", f"long:{b}") for a, b in pairs}}
    eqs: dict = {}
    flat = lambda atoms: [(a["rel"], [(t["var"], t["const"]) for t in a["terms"]]) for a in atoms]
    for r in X.to_entangled(requests, {"place": "string", "kind": "string"}, "key", ["place"]).collect():
        eqs.setdefault(r["qid"] // 10, []).append(Entangled(r["qid"], post=flat(r["post"]), head=flat(r["head"]), body=flat(r["body"])))
    hits = 0
    for g, queries in eqs.items():
        all_sets = exact.coordinating_sets(queries, facts)
        mine = [tuple(sorted(v)) for (k, _), v in survivors.items() if k == g]
        assert bool(all_sets) == bool(mine), g
        assert all(m in all_sets for m in mine)
        hits += bool(mine)
    assert 5 < hits < 40


def test_translation_refuses_many_and_detects_signatures(spark):
    requests = small(spark, [(1, {}, [], [("friends", 2)])])
    with pytest.raises(ValueError):
        X.to_entangled(requests, {"place": "string"}, "key", ["place"])
    eqs = X.to_entangled(small(spark, [(1, {}, [2], []), (2, {}, [1], [])]), {"place": "string", "kind": "string"}, "key", ["place"])
    assert {r["attributes"] for r in X.coordination_signature(eqs, "data", ["place", "kind"]).collect()} == {"place"}
    both = X.to_entangled(small(spark, [(3, {}, [1], [])]), {"place": "string", "kind": "string"}, "key", ["place", "kind"])
    assert X.coordination_signature(eqs.union(both), "data", ["place", "kind"]).select("attributes").distinct().count() == 2
    report = {r["qid"]: (r["coordinating"], r["non_coordinating"]) for r in X.consistency(eqs, "data", ["place", "kind"], ["place"]).collect()}
    assert report == {1: (True, False), 2: (True, False)}


def test_early_stop_finds_the_same_set(spark):
    requests, data, friends = T.travellers(spark, D, 60), T.flights(spark, D).where("month(day) <= 2"), T.friends_ring(spark, D, 60, 2)
    run = C.consistent_coordinate(requests, data, "flight_id", ["destination", "day"], friends)
    best, cleaned = C.largest_with_early_stop(run.vq, run.edges, requests, run.coord, 5)
    assert [tuple(r) for r in best.collect()] == [tuple(r) for r in run.best.collect()] and 0 < cleaned <= C.candidates(run.vq, run.coord).count()


def test_packing_ends_when_no_set_is_left(spark):
    places = [f"p{i}" for i in range(8)]
    table = spark.createDataFrame([(i, p, "s") for i, p in enumerate(places)], "key long, town string, kind string")
    rows, pairs = [], []
    for i, p in enumerate(places):  # a pair a place; the first user of each may also go anywhere
        rows += [(2 * i, {}, [], [("friends", 1)]), (2 * i + 1, {"town": p}, [], [("friends", 1)])]
        pairs += [(2 * i, 2 * i + 1), (2 * i + 1, 2 * i)]
    requests = small(spark, rows)
    run = C.consistent_coordinate(requests, table, "key", ["town"], friends_of(spark, pairs))
    got, rest = C.pack_values(run, requests)
    assert [(r["place"], r["members"]) for r in got.orderBy("place").collect()] == [(i, f"{2 * i},{2 * i + 1}") for i in range(8)] and rest.isEmpty()
    some, rest = C.pack_values(run, requests, 6)
    assert some.count() == 6 and {r["qid"] for r in rest.collect()} == {12, 13, 14, 15}


def test_rounds_clean_every_value(spark, tmp_path):
    from concord.plans import consistent_queries as Q

    for t in ("nation", "customer", "orders"):
        spark.read.parquet(f"{D}/{t}.parquet").where("o_orderkey % 40 = 0" if t == "orders" else "true").write.parquet(f"{tmp_path}/{t}.parquet")
    rounds = sorted(map(tuple, Q.by_rounds(spark, str(tmp_path), Q.travel()).collect()))
    local = sorted(map(tuple, Q.Q["clean_survivors"](spark, str(tmp_path)).collect()))
    assert rounds == local and len({day[:7] for _, day, _, _ in rounds}) > 1
