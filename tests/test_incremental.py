"""Incremental unification and term unification against plain versions, and refusals."""

import json
import random

import pytest

from concord.operators import scc as S
from concord.operators.unify import terms_unify
from concord.sources import entangled as E


def random_component(rnd, n, density):
    """Queries in a chain-like graph whose terms are shared variables and two constants."""
    term = lambda *names: rnd.choice([(v, None) for v in names] + [(None, f"long:{rnd.randint(0, 1)}")])
    eqs, links = {}, {}
    for q in range(n):
        to = [d for d in range(max(0, q - 4), min(n, q + 2)) if d != q and rnd.random() < density]
        body = [("f", [("x", None), (rnd.choice(["z", "y0"]), None)])] + ([("g", [("y1", None)])] if rnd.random() < 0.5 else [])
        eqs[q] = {"post": [("seat", [(None, f"long:{d}"), term("y0", "y1")]) for d in to], "head": [("seat", [(None, f"long:{q}"), term("x", "x")])], "body": body, "weight": 0.0}
        links[q] = [(p, d, 0) for p, d in enumerate(to)]
    return eqs, links


def test_incremental_unification_agrees_with_whole_sets():
    rnd = random.Random(4)
    shape = lambda t: (len(json.loads(t)), tuple(sorted(a[0] for a in json.loads(t))))
    for _ in range(800):
        eqs, links = random_component(rnd, rnd.randint(2, 9), rnd.choice([0.15, 0.3, 0.5]))
        rows = [dict(zip(S.COLUMNS, r, strict=True)) for r in S._reach_rows(0, eqs, links, {})]
        for r in rows:
            u, found, _ = S._whole(eqs, links, r["ids"], {})
            assert r["unified"] != u.conflict
            if r["unified"]:
                held = {(shape(p["template"]), tuple(p["constants"])) for x in rows if x["scc_id"] in r["ids"] for p in x["parts"]}
                assert {(shape(t), tuple(c)) for t, c, _ in found} <= held


def test_a_list_unifies_every_edge_once():
    n = 2000
    eqs = {q: {"post": [("seat", [(None, f"long:{q + 1}"), ("y", None)])] if q < n - 1 else [], "head": [("seat", [(None, f"long:{q}"), ("x", None)])], "body": [("f", [("x", None), ("d", None)])], "weight": 0.0} for q in range(n)}
    rows = [dict(zip(S.COLUMNS, r, strict=True)) for r in S._reach_rows(0, eqs, {q: [(0, q + 1, 0)] if q < n - 1 else [] for q in range(n)}, {})]
    assert sum(r["steps"] for r in rows) == n - 1 and sum(len(r["parts"]) for r in rows) == n and max(r["n"] for r in rows) == n


def test_terms_unify_transitively():
    v, c = (lambda x: {"var": x}), (lambda x: {"const": x})
    assert not terms_unify([v("x"), v("x"), c("2")], [c("1"), v("z"), v("z")])
    assert terms_unify([v("x"), v("x"), c("2")], [c("2"), v("z"), v("z")])
    assert not terms_unify([v("x"), v("x")], [c("1"), c("2")]) and terms_unify([v("x")], [v("x")])


def test_unknown_handling_of_unsafe_queries_is_refused(spark):
    eqs, cat = E.two_flyers(spark)
    with pytest.raises(ValueError):
        S.scc_coordinate(eqs, cat, on_unsafe="whatever")
    with pytest.raises(ValueError):
        S.scc_coordinate(eqs, cat, on_unsafe="ignore")


def test_unsafe_arrivals_are_set_aside(spark, tmp_path):
    from concord.streaming.arrivals import Arrivals

    eqs, cat = E.two_flyers(spark)
    loop = Arrivals(spark, cat, str(tmp_path / "state"))
    loop(eqs.where("qid = 1"), 0)
    again = eqs.where("qid = 2").withColumn("qid", eqs["qid"] + 10)
    loop(eqs.where("qid = 2").unionByName(again), 1)
    assert {r["qid"] for r in loop.answers().collect()} == {1, 2}
    assert [(r["qid"], r["reason"]) for r in loop.refused().collect()] == [(12, "second offer")]


def test_unsafe_components_are_routed(spark):
    from concord.model import frame, parse_entangled

    texts = ["seat('u',x) if seat('a',x) from f(x,'Z')", "seat('a',x) from f(x,'Z')", "seat('a',x) from f(x,'Q')", "seat('p',x) if seat('q',x) from f(x,'Z')", "seat('q',x) from f(x,'Z')"]
    eqs = frame(spark, [parse_entangled(t, k + 1) for k, t in enumerate(texts)])
    run = S.scc_coordinate(eqs, {"f": spark.createDataFrame([(1, "Z")], "id long, city string")}, on_unsafe="route")
    assert {r["members"] for r in run.sets().collect()} == {"2", "1,2", "4,5", "5"}
