"""Safe sets: worked examples, graph toolkit, modes against each other, and random sets against exhaustive search."""

import random

import pytest
from pyspark.sql import functions as F

from concord.functions import exact, hardness
from concord.model import Entangled, Var, atom, frame, parse_entangled, validate
from concord.operators import graph as G
from concord.operators import scc as S
from concord.operators import unify as U
from concord.operators import verify as V
from concord.operators.single import exists_coordination, is_single_connected, single_connected_coordinate
from concord.sources import entangled as E


def statuses(run):
    return {tuple(r["ids"]): r["status"] for r in run.nodes.collect()}


def best(run):
    rows = run.best.collect()
    return tuple(rows[0]["ids"]) if rows else ()


def test_parser_and_builder_agree():
    q = parse_entangled("seat('G',x) if seat('C',x) from flights(x,'Z',7)", 1)
    assert q.head == [atom("seat", "G", Var("x"))] and q.post == [atom("seat", "C", Var("x"))] and q.body == [atom("flights", Var("x"), "Z", 7)]
    assert parse_entangled("seat('G',x)", 2).post == []
    with pytest.raises(ValueError):
        parse_entangled("seat('G' x", 3)


def test_two_flyers(spark):
    eqs, cat = E.two_flyers(spark)
    run = S.scc_coordinate(eqs, cat)
    assert best(run) == (1, 2)
    assert {(r["qid"], r["var"]): r["val"] for r in run.assignment().collect()} == {(1, "x"): "long:101", (2, "y"): "long:101"}
    assert V.verify_set(run.assignment(), eqs, cat).count() == 0
    wrong = run.assignment().withColumn("val", F.when(F.col("qid") == 1, "long:102").otherwise(F.col("val")))
    assert {r["rule"] for r in V.verify_set(wrong, eqs, cat).collect()} == {"body_not_in_data", "postcondition_unmet"}
    empty = {"flights": cat["flights"].where("false")}
    assert best(S.scc_coordinate(eqs, empty)) == ()


def test_flight_hotel(spark):
    eqs, cat = E.flight_hotel(spark)
    keyed = S.scc_coordinate(eqs, cat, {"flights": [0], "hotels": [0]})
    assert statuses(keyed) == {(1, 2): "ok", (1, 2, 3): "unify_failed", (1, 2, 3, 4): "successor_failed"}
    eqs, cat = E.flight_hotel(spark, multistop=True)
    run = S.scc_coordinate(eqs, cat)
    assert set(statuses(run).values()) == {"ok"} and best(run) == (1, 2, 3, 4)


def test_modes_agree_on_failures(spark):
    eqs, cat = E.flight_hotel(spark)
    want = {(1, 2): "ok", (1, 2, 3): "no_grounding", (1, 2, 3, 4): "successor_failed"}
    for mode in ("bulk", "wave", "sequential", "bisect"):
        assert statuses(S.scc_coordinate(eqs, cat, mode=mode)) == want, mode


def test_outsider_is_not_unique(spark):
    eqs, cat = E.band_plus_one(spark)
    assert best(S.scc_coordinate(eqs, cat)) == (1, 2, 3, 4, 5)
    assert S.unique_coordinate(eqs, cat).nodes.count() == 0
    members = eqs.where("qid < 5")
    assert best(S.unique_coordinate(members, cat)) == (1, 2, 3, 4) == best(S.scc_coordinate(members, cat))


def test_branches_and_ties(spark):
    eqs, cat = E.two_branches(spark)
    run = S.scc_coordinate(eqs, cat)
    assert best(run) == (1, 2, 3, 4)
    report = {r["name"]: r["value"] for r in V.cost_report(run).collect()}
    assert report["db_queries"] == report["components"] == 3 and report["levels"] == 2 and report["set_size"] == 4


def test_diamond_counts_once_and_dangling_is_pruned(spark):
    x = Var("x")
    needs = {1: [], 2: [1], 3: [1], 4: [2, 3], 5: [9], 6: [5]}
    eqs = frame(spark, [Entangled(q).offer(atom("seat", q, x)).given(*[atom("seat", p, Var(f"y{p}")) for p in ps]) for q, ps in needs.items()])
    run = S.scc_coordinate(eqs, {})
    assert best(run) == (1, 2, 3, 4)
    assert not {5, 6} & {q for ids in statuses(run) for q in ids}


def test_unsafe_is_refused(spark):
    eqs = frame(spark, [Entangled(1).given(atom("seat", Var("w"), Var("x"))).offer(atom("seat", 1, Var("x"))), Entangled(2).offer(atom("seat", 2, Var("x")))])
    ext = U.extended_graph(eqs)
    assert {(r["qid"], r["is_safe"]) for r in U.safety(ext, eqs).collect()} == {(1, False), (2, True)}
    with pytest.raises(ValueError, match="unsafe"):
        S.scc_coordinate(eqs, {})


def test_repeated_variables(spark):
    x = Var("x")
    eqs = frame(spark, [Entangled(1).given(atom("r", x, x)), Entangled(2).offer(atom("r", 1, 2))])
    assert U.extended_graph(eqs).count() == 1
    assert U.extended_graph(eqs, mode="mgu").count() == 0


def test_validation(spark):
    eqs = frame(spark, [Entangled(1).offer(atom("flights", 1)).where(atom("nowhere", Var("x"))), Entangled(2).offer(atom("seat", Var("z"))).where(atom("flights", 1, 2))])
    rules = {(r["rule"], r["qid"]) for r in validate(eqs, {"flights": spark.createDataFrame([(1,)], "id long")}).collect()}
    assert rules == {("answer_relation_in_schema", 1), ("unknown_body_relation", 1), ("head_variable_unbound", 2), ("body_arity", 2)}


def random_atoms(rnd, tag):
    return [rnd.choice([Var(rnd.choice("xyz")), rnd.randint(0, 2)]) for _ in range(2)]


def test_mask_join_equals_nested_loop(spark):
    rnd = random.Random(5)
    eqs = frame(spark, [Entangled(q).given(*[atom(rnd.choice("rs"), *random_atoms(rnd, q)) for _ in range(3)]).offer(*[atom(rnd.choice("rs"), *random_atoms(rnd, q)) for _ in range(2)]) for q in range(40)])
    a, b = (sorted(map(tuple, U.extended_graph(eqs, join=j).collect())) for j in ("mask", "nested"))
    assert a == b and len(a) > 100


def test_components_against_brute_force(spark):
    rnd = random.Random(1)
    pairs = [(rnd.randint(0, 79), rnd.randint(0, 79)) for _ in range(95)]
    nodes, edges = spark.range(80).withColumnRenamed("id", "qid"), spark.createDataFrame(pairs, "src long, dst long")
    reach = {a: {a} for a in range(80)}
    changed = True
    while changed:
        changed = False
        for a, b in pairs:
            for r in reach.values():
                if a in r and b not in r:
                    r.add(b)
                    changed = True
    want = {a: min(b for b in reach[a] if a in reach[b]) for a in reach}
    local = {r["qid"]: (r["scc_id"], r["level"]) for r in G.strong_components(nodes, edges).collect()}
    assert {q: s for q, (s, _) in local.items()} == want
    assert {r["qid"]: r["scc_id"] for r in G.strong_components(nodes, edges, "fwbw").collect()} == want
    dag = G.condense(edges, G.strong_components(nodes, edges))
    peeled = {r["scc_id"]: r["level"] for r in G.levels(dag, spark.createDataFrame([(s,) for s in set(want.values())], "scc_id long")).collect()}
    assert peeled == {s: lvl for s, lvl in local.values()}
    assert {r["scc_id"]: r["n"] for r in G.reach_sets(nodes, edges).collect()} == {s: len(reach[s]) for s in set(want.values())}


def test_weak_components_of_a_long_path_and_of_nothing(spark):
    path = spark.range(300).selectExpr("(id * 37) % 301 as src", "((id + 1) * 37) % 301 as dst")
    assert {r["comp_id"] for r in G.weak_components(path).collect()} == {0}
    assert G.weak_components(path.where("false")).count() == 0


DATA = {"d": {("long:0", "long:1"), ("long:1", "long:1")}}


def random_queries(rnd, base, n, safe=True, posts=2):
    """n queries of an instance of their own; safe: every postcondition names one query."""
    ids, out = [base + i for i in range(n)], []
    for q in ids:
        e = Entangled(q).offer(atom("seat", q if safe else base + rnd.randint(0, n - 1), rnd.choice([Var("x"), Var("x"), rnd.randint(0, 2)])))
        for p in rnd.sample(ids, rnd.randint(0, min(posts, n))):
            e.given(atom("seat", p, rnd.choice([Var("x"), Var("y"), rnd.randint(0, 1)])))
        if rnd.random() < 0.7:
            e.where(atom("d", Var("x"), rnd.choice([Var("z"), Var("y"), 1, 0])))
        out.append(e)
    return out


def test_random_safe_sets_against_exhaustive_search(spark):
    rnd = random.Random(11)
    groups = [random_queries(rnd, 100 * k, rnd.randint(1, 5)) for k in range(60)]
    data = spark.createDataFrame([(0, 1), (1, 1)], "a long, b long")
    eqs = frame(spark, [q for g in groups for q in g])
    run = S.scc_coordinate(eqs, {"d": data})
    found: dict = {}
    for r in run.nodes.where("status = 'ok'").collect():
        found.setdefault(r["ids"][0] // 100, []).append(tuple(r["ids"]))
    for k, g in enumerate(groups):
        sets = exact.coordinating_sets(g, DATA)
        assert bool(sets) == bool(found.get(k)), g
        assert all(s in sets for s in found.get(k, []))
    assert V.verify_set(run.assignment(), eqs, {"d": data}).count() == 0
    assert len(found) > 15


def test_single_connected_against_exhaustive_search(spark):
    rnd = random.Random(3)
    groups = []
    while len(groups) < 40:
        g = random_queries(rnd, 100 * len(groups), rnd.randint(1, 4), safe=False, posts=1)
        rep = exact.loaded(g)
        heads = {(q, h[1][0][1]) for q, e in rep.items() for h in e["head"]}
        out = {q: [d for d, c in heads for p in e["post"] if p[1][0][1] == c] for q, e in rep.items()}
        from concord.operators.single import one_path

        if one_path(sorted(out), out):
            groups.append(g)
    eqs = frame(spark, [q for g in groups for q in g])
    data = {"d": spark.createDataFrame([(0, 1), (1, 1)], "a long, b long")}
    ok = {min(r["ids"]) // 100 for r in single_connected_coordinate(eqs, data).nodes.where("status = 'ok'").collect()}
    assert ok == {k for k, g in enumerate(groups) if exact.coordinating_sets(g, DATA)}
    assert is_single_connected(eqs).where("not (single_post and one_path)").count() == 0
    assert exists_coordination(frame(spark, groups[0]), data) in ("safe", "single_connected")


FORMULAS = [[[1]], [[1], [-1]], [[1, 2], [-1, 2], [1, -2]], [[1, 2], [-1, 2], [1, -2], [-1, -2]], [[1, 2, 3], [-1, -2, -3]], [[1, 2, 3], [-1, 2, 3], [1, -2], [-2, -3]]]


@pytest.mark.parametrize("formula", FORMULAS)
def test_formulas_as_query_sets(formula):
    sat = hardness.satisfiable(formula)
    assert bool(exact.exact_max(hardness.as_unsafe_set(formula), hardness.BITS)) == sat
    safe = hardness.as_safe_set(formula)
    size = len(formula) + len({abs(x) for c in formula for x in c})
    if len(safe) <= 12:
        assert (len(exact.exact_max(safe, hardness.BITS)) == size) == sat


def test_safe_gadget_is_safe(spark):
    for f in FORMULAS:
        assert U.unsafe_queries(U.extended_graph(frame(spark, hardness.as_safe_set(f)))).count() == 0


def test_empty_inputs(spark):
    assert best(S.scc_coordinate(frame(spark, [Entangled(1)]).where("false"), {})) == ()
    assert best(S.scc_coordinate(frame(spark, [Entangled(1).offer(atom("seat", 1))]), {})) == (1,)
