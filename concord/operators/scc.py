"""Coordination of safe query sets along their strongly connected components.

In a safe set a query needs exactly the queries its postconditions match, so a component is in a coordinating set as a whole, together with
everything it reaches. The sets tried are the reach sets of the components. A set coordinates if its queries unify and the
combined query has a grounding; the best by a criterion is returned with a witness.

Unification is incremental: from the sinks upwards each component adds its own edges to the unifier of what it reaches, so every edge is
unified once (``steps`` counts). Only where a component binds or merges variables of the components below is its set, and those above it,
unified by itself. A component keeps the parts of the combined query that hold atoms of its own; the rest it inherits, so it is
grounded if its parts are and everything below coordinates.

The modes differ in what they ground at a time: ``bulk`` (default) everything, ``wave`` the lowest level with something new,
``sequential`` one component, never above a failure; ``bisect`` tests chains by halving. Equal parts are grounded once. All give the same statuses;
the database queries that each issues logically are counted.
"""

from __future__ import annotations

import json
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from concord.operators import ground as G
from concord.operators.graph import condense_local, prune_unmatched, strong_components, tarjan, weak_components
from concord.operators.select import Selection, largest
from concord.operators.unify import extended_graph, unsafe_queries
from concord.runtime import cut, keep

#: A set: ``steps`` edges were unified for it, ``parts`` are its own, ``via`` are the edges that it uses if not all among its ids.
NODE = """comp_id long, scc_id long, level int, n long, weight double, ids array<long>, next array<long>, unified boolean, steps long,
parts array<struct<template:string,constants:array<string>>>, via array<struct<src:long,post_pos:int,dst:long,head_pos:int>>"""
COLUMNS = [c.split()[0] for c in NODE.replace("\n", " ").split(", ")]


def _terms(atoms) -> list:
    return [(a["rel"], [(t.get("var"), t.get("const")) for t in a["terms"]]) for a in atoms or []]


def _load(pdf: pd.DataFrame) -> tuple[dict, dict]:
    """{qid: query} and {qid: [(post_pos, dst, head_pos)]} of one weak component."""
    eqs, links = {}, {}
    for q, weight, text, to in zip(pdf["qid"].tolist(), pdf["weight"].tolist(), pdf["eq"].tolist(), pdf["links"].tolist(), strict=True):
        e = json.loads(text)
        eqs[q] = {"post": _terms(e.get("post")), "head": _terms(e.get("head")), "body": _terms(e.get("body")), "weight": weight or 0.0}
        links[q] = [(x["post_pos"], x["dst"], x["head_pos"]) for x in to] if to is not None else []
    return eqs, links


def node_row(comp: int, scc: int, level: int, eqs: dict, ids: list, nxt: list, unified: bool, steps: int, found: list, via: list | None = None) -> tuple:
    parts = [{"template": t, "constants": c} for t, c, _ in found]
    used = None if via is None else [dict(zip(("src", "post_pos", "dst", "head_pos"), v, strict=True)) for v in via]
    return comp, scc, level, len(ids), float(sum(eqs[q]["weight"] for q in ids)), ids, nxt, unified, steps, parts, used


def _whole(eqs: dict, links: dict, ids: list, keys: dict) -> tuple[G.Classes, list, int]:
    """Unifier, parts and steps of one set by itself."""
    edges = [(q, p, d, h) for q in ids for p, d, h in links[q]]
    u, atoms = G.unify({q: eqs[q] for q in ids}, edges, keys)
    return u, [] if u.conflict else G.parts(u, atoms), len(edges)


def _reach_rows(comp: int, eqs: dict, links: dict, keys: dict) -> list[tuple]:
    """The reach set of every component, unified from the sinks upwards."""
    out = {q: [d for _, d, _ in links[q]] for q in eqs}
    scc = tarjan(sorted(eqs), out)
    succ, level = condense_local(scc, out)
    own: dict = {}
    for q in sorted(eqs):
        own.setdefault(scc[q], []).append(q)
    grown, holding, below, alone, failed, made = G.Growing(), {}, {}, set(), set(), []
    term = lambda q, t: ("v", q, t[0]) if t[0] is not None else ("c", t[1])
    for s in sorted(succ, key=lambda c: (level[c], c)):
        below[s] = {s}.union(*(below[t] for t in succ[s]))
        ids = sorted(q for t in below[s] for q in own[t])
        if succ[s] & failed:
            failed.add(s)
            made.append(node_row(comp, s, level[s], eqs, ids, sorted(succ[s]), False, 0, []))
            continue
        fits, found, steps = True, None, 0
        if not keys and not succ[s] & alone:
            try:
                for q in own[s]:
                    for p, d, h in links[q]:
                        steps += 1
                        for a, b in zip(eqs[q]["post"][p][1], eqs[d]["head"][h][1], strict=True):
                            fits = fits and grown.equate(term(q, a), term(d, b))
                if fits:
                    atoms = [(s, rel, [term(q, t) for t in terms]) for q in own[s] for rel, terms in eqs[q]["body"]]
                    for atom in atoms:
                        for v in {t for t in atom[2] if t[0] == "v"}:
                            holding.setdefault(v, []).append(atom)
                    grown.settle([term(q, t) for q in own[s] for role in ("post", "head", "body") for _, ts in eqs[q][role] for t in ts if t[0] is not None])
                    found = G.parts(grown, G.linked_atoms(grown, atoms, holding, below[s]))
                else:
                    grown.undo()
            except G.Tightened:
                grown.undo()
                alone.add(s)
        else:
            alone.add(s)
        if s in alone:
            u, found, more = _whole(eqs, links, ids, keys)
            fits, steps = not u.conflict, steps + more
        if not fits:
            failed.add(s)
        made.append(node_row(comp, s, level[s], eqs, ids, sorted(succ[s]), fits, steps, found or []))
    return made


def _rows(comp: int, eqs: dict, links: dict, keys: dict, scope: str) -> list[tuple]:
    """The candidate sets of a component. scope: reach (per component), union (all queries), alone (each query's body)."""
    if scope == "reach":
        return _reach_rows(comp, eqs, links, keys)
    if scope == "alone":
        return [node_row(comp, q, 0, eqs, [q], [], True, 0, _whole(eqs, {q: []}, [q], keys)[1], []) for q in sorted(eqs)]
    one = len(set(tarjan(sorted(eqs), {q: [d for _, d, _ in links[q]] for q in eqs}).values())) == 1
    u, found, steps = _whole(eqs, links, sorted(eqs), keys)
    return [node_row(comp, min(eqs), 0 if one else -1, eqs, sorted(eqs), [], not u.conflict, steps, found)]


def component_rows(eqs: DataFrame, ext: DataFrame, comp: DataFrame) -> DataFrame:
    """(comp_id, qid, weight, eq, links): one row per query under its weak component."""
    links = ext.groupBy("src").agg(F.collect_list(F.struct("post_pos", "dst", "head_pos")).alias("links"))
    flat = eqs.select("qid", "weight", F.to_json(F.struct("post", "head", "body")).alias("eq"))
    rows = flat.join(links, F.col("qid") == F.col("src"), "left").join(comp, F.col("qid") == F.col("node"), "left")
    return rows.select(F.coalesce("comp_id", "qid").alias("comp_id"), "qid", "weight", "eq", "links")


def candidate_sets(rows: DataFrame, keys: dict[str, list[int]], scope: str) -> DataFrame:
    def run(pdf):
        eqs, links = _load(pdf)
        return pd.DataFrame(_rows(int(pdf["comp_id"].iloc[0]), eqs, links, keys, scope), columns=COLUMNS)

    return rows.groupBy("comp_id").applyInPandas(run, NODE)


# ---------------------------------------------------------------- grounding


def _known(each: DataFrame, known: DataFrame | None, catalog: dict, choose: str) -> DataFrame | None:
    """The parts known so far (template, constants, hit) and those of ``each``, grounded if they are new."""
    wanted = each.where("template is not null").select("template", "constants").distinct()
    wanted = cut(wanted.join(known, ["template", "constants"], "left_anti") if known is not None else wanted)
    made = G.ground_batch(wanted, catalog, choose)
    if made is None:
        return known
    told = keep(wanted.join(made.select("template", "constants", F.lit(True).alias("hit")), ["template", "constants"], "left").select("template", "constants", F.coalesce("hit", F.lit(False)).alias("hit")))
    return told if known is None else keep(known.unionByName(told))


def _parts(nodes: DataFrame) -> DataFrame:
    return nodes.select("comp_id", "scc_id", "level", F.explode_outer("parts").alias("p")).select("comp_id", "scc_id", "level", "p.template", "p.constants")


def rate(nodes: DataFrame, known: DataFrame | None, inherit: bool = True) -> DataFrame:
    """Adds the status, ``pending`` where parts are not known yet. With ``inherit`` a set above a failed one is ``successor_failed``, whatever it would be by itself."""
    each = _parts(nodes.where("unified"))
    each = each.join(known, ["template", "constants"], "left") if known is not None else each.withColumn("hit", F.lit(None).cast("boolean"))
    seen = each.where("template is not null").groupBy("scc_id").agg(F.bool_or(~F.col("hit")).alias("missed"), F.bool_or(F.col("hit").isNull()).alias("open"))
    own = F.when(~F.col("unified"), "unify_failed").when(F.coalesce("missed", F.lit(False)), "no_grounding").when(F.coalesce("open", F.lit(False)), "pending").otherwise("ok")
    rated = nodes.join(seen, "scc_id", "left").withColumn("status", own).drop("missed", "open")
    if not inherit:
        return rated
    failed = rated.where("status in ('unify_failed', 'no_grounding')").select(F.col("scc_id").alias("f"))
    lost = nodes.select("scc_id", F.explode("ids").alias("f")).where("scc_id <> f").join(failed, "f").select("scc_id", F.lit(True).alias("lost")).distinct()
    return rated.join(lost, "scc_id", "left").withColumn("status", F.when(F.col("lost"), "successor_failed").otherwise(F.col("status"))).drop("lost")


def grounded(nodes: DataFrame, catalog: dict, choose: str, mode: str = "bulk", inherit: bool = True, stop: bool = False) -> DataFrame:
    """The sets with their status; every round grounds the new parts of all pending sets, of those on the lowest level, or of one.
    With ``stop`` it ends with the first round that has found a set; what was not tried by then is ``not_tried``."""
    known = None
    while True:
        rated = keep(rate(nodes, known, inherit))
        if stop and not rated.where("status = 'ok'").isEmpty():
            return rated.withColumn("status", F.when(F.col("status") == "pending", "not_tried").otherwise(F.col("status")))
        pending = rated.where("status = 'pending'")
        if mode == "wave":
            pending = pending.join(F.broadcast(pending.agg(F.min("level").alias("level"))), "level")
        elif mode == "sequential":
            pending = pending.orderBy("level", "scc_id").limit(1)
        before = known
        known = _known(_parts(pending), known, catalog, choose)
        if known is before:
            return rated


def _bisect(nodes: DataFrame, catalog: dict, choose: str) -> tuple[DataFrame, int]:
    """Components with one node a level: reach sets are nested, so the levels that ground are a prefix, found by halving. Also the number of sets tried."""
    per = nodes.groupBy("comp_id").agg(F.max("level").alias("top"), F.count("*").alias("k"))
    if per.where("k <> top + 1").limit(1).count():
        raise ValueError("bisect needs one node a level, so that reach sets are nested")
    fits = nodes.where("not unified").groupBy("comp_id").agg(F.min("level").alias("stop"))  # unification alone bounds the prefix
    span = cut(per.join(fits, "comp_id", "left").select("comp_id", F.lit(-1).alias("good"), F.coalesce("stop", F.col("top") + 1).alias("bad")))
    known, tried = None, 0
    while tried_now := span.where("bad - good > 1").count():
        tried += tried_now
        probe = span.where("bad - good > 1").select("comp_id", F.floor((F.col("good") + F.col("bad")) / 2).cast("int").alias("at"))
        # the set at a level is everything up to it; what is known to ground already need not be asked again
        each = keep(_parts(nodes).join(probe, "comp_id").where("level <= at"))
        known = _known(each, known, catalog, choose)
        told = each.join(known, ["template", "constants"], "left") if known is not None else each.withColumn("hit", F.lit(True))
        fine = told.groupBy("comp_id", "at").agg(F.bool_and(F.col("template").isNull() | F.coalesce("hit", F.lit(False))).alias("fine"))
        span = cut(span.join(fine, "comp_id", "left").select("comp_id", F.when(F.col("fine"), F.col("at")).otherwise(F.col("good")).alias("good"), F.when(~F.col("fine"), F.col("at")).otherwise(F.col("bad")).alias("bad")))
    rated = nodes.join(span, "comp_id")
    failed = F.when(F.col("level") > F.col("bad"), "successor_failed").when(F.col("unified"), "no_grounding").otherwise("unify_failed")
    return rated.withColumn("status", F.when(F.col("level") <= F.col("good"), "ok").otherwise(failed)).drop("good", "bad"), tried


@dataclass
class Coordination:
    nodes: DataFrame  # every candidate set with its status
    best: DataFrame
    rows: DataFrame
    catalog: dict
    keys: dict
    choose: str
    mode: str = "bulk"
    tried: int | None = None  # sets that bisection has tried
    metrics: dict = field(default_factory=dict)

    def sets(self) -> DataFrame:
        """All coordinating sets found."""
        return self.nodes.where("status = 'ok'").select("scc_id", "n", "weight", "ids", F.array_join(F.transform("ids", lambda x: x.cast("string")), ",").alias("members"))

    def database_queries(self) -> DataFrame:
        """(db_queries, components): combined queries that the mode issues. ``bulk`` asks for every set that unifies, the others for none above a failure."""
        asked = F.count_if("unified") if self.mode == "bulk" else F.count_if(F.col("status").isin("ok", "no_grounding"))
        asked = asked if self.tried is None else F.lit(self.tried).cast("long")
        return self.nodes.agg(asked.alias("db_queries"), F.count("*").alias("components"))

    def assignment(self) -> DataFrame:
        """(set_id, qid, var, val): the witness of the best set. Only the queries of that set are read and unified."""
        keys = self.keys
        chosen = self.best.select("scc_id", "via", F.explode("ids").alias("qid"))
        mine = self.rows.join(F.broadcast(chosen), "qid")

        def run(pdf):
            eqs, links = _load(pdf)
            via = pdf["via"].iloc[0]
            edges = [(q, p, d, h) for q in eqs for p, d, h in links[q] if d in eqs] if via is None else [(v["src"], v["post_pos"], v["dst"], v["head_pos"]) for v in via]
            u, atoms = G.unify(eqs, edges, keys)
            place = {v: (t, c, i) for t, c, names in G.parts(u, atoms) for i, v in enumerate(names)}
            out = []
            for q, e in eqs.items():
                for var in sorted({t[0] for role in ("post", "head", "body") for _, terms in e[role] for t in terms if t[0] is not None}):
                    root = u.find(("v", q, var))
                    const = u.constant(root)
                    t, c, i = place.get(root, (None, None, None)) if const is None else (None, None, None)
                    out.append((int(pdf["scc_id"].iloc[0]), q, var, const, t, c, i))
            return pd.DataFrame(out, columns=["set_id", "qid", "var", "const", "template", "constants", "slot"])

        told = keep(mine.groupBy("scc_id").applyInPandas(run, "set_id long, qid long, var string, const string, template string, constants array<string>, slot int"))
        made = G.ground_batch(told.where("template is not null").select("template", "constants").distinct(), self.catalog, self.choose)
        if made is None:
            return told.select("set_id", "qid", "var", F.col("const").alias("val"))
        return told.join(made, ["template", "constants"], "left").select("set_id", "qid", "var", F.coalesce("const", F.get("witness", F.col("slot"))).alias("val"))


def scc_coordinate(
    eqs: DataFrame, catalog: dict[str, DataFrame], keys: dict[str, list[int]] | None = None, select: Selection | None = None,
    mode: str = "bulk", choose: str = "min", on_unsafe: str = "error", scope: str = "reach", stop_at_first: bool = False, ext: DataFrame | None = None,
) -> Coordination:
    """Best coordinating set among the reach sets of a safe set of queries, with all candidates and their statuses.

    ``keys`` declares key positions of relations, which lets contradictory sets fail without a database query. Unsafe queries are
    refused (``error``), or their weak components go to the algorithm for single-connected sets, which refuses others (``route``);
    ``ignore`` is for the whole-component baseline only, which unifies a postcondition with all its heads. ``stop_at_first`` ends at the first level (in
    ``sequential``: component) that has a coordinating set, leaving the rest untried. ``ext`` is the extended graph, if it is known.
    """
    if on_unsafe not in ("error", "route", "ignore") or (on_unsafe == "ignore" and scope != "union") or (on_unsafe == "route" and (scope, mode) != ("reach", "bulk")):
        raise ValueError(f"on_unsafe={on_unsafe!r} with scope={scope!r}, mode={mode!r}")
    keys = keys or {}
    eqs = keep(eqs)
    ext = keep(extended_graph(eqs)) if ext is None else ext
    if on_unsafe == "error" and scope != "alone":
        bad = [r["qid"] for r in unsafe_queries(ext).orderBy("qid").limit(10).collect()]
        if bad:
            raise ValueError(f"unsafe queries: {bad}")
    comp = cut(weak_components(ext if scope != "alone" else ext.where("false")))
    live = eqs if scope == "alone" else eqs.join(prune_unmatched(eqs, ext, comp), "qid", "left_semi")
    ends = live.select("qid")
    inner = ext.join(ends.withColumnRenamed("qid", "src"), "src", "left_semi").join(ends.withColumnRenamed("qid", "dst"), "dst", "left_semi")
    if scope == "alone":
        inner = inner.where("false")
    rows = keep(component_rows(live, inner, comp))
    routed = None
    if on_unsafe == "route":
        from concord.operators.single import single_sets

        odd = rows.join(unsafe_queries(inner), "qid", "left_semi").select("comp_id").distinct()
        routed = keep(single_sets(rows.join(odd, "comp_id", "left_semi")))
        every, rows = rows, rows.join(odd, "comp_id", "left_anti")
    nodes = keep(candidate_sets(rows, keys, scope))
    if scope == "union":
        nodes = nodes.where("level >= 0") if on_unsafe == "error" else nodes
    tried = None
    if mode == "bisect":
        rated, tried = _bisect(nodes, catalog, choose)
    else:
        rated = grounded(nodes, catalog, choose, "wave" if stop_at_first and mode == "bulk" else mode, stop=stop_at_first)
    if routed is not None:
        rated, rows = rated.unionByName(grounded(routed, catalog, choose, inherit=False)), every
    found = rated.where("status = 'ok'")
    if stop_at_first:  # sets that became known on the way stand behind the level that was asked for
        found = found.join(F.broadcast(found.agg(F.min("level").alias("level"))), "level").select(*rated.columns)
    best = cut((select or largest()).pick(found, ["scc_id"]))
    return Coordination(rated, best, rows, catalog, keys, choose, mode, tried)


def unique_coordinate(eqs: DataFrame, catalog: dict[str, DataFrame], keys: dict | None = None, check: bool = True) -> Coordination:
    """The earlier evaluator: one unifier and one database query over a whole weak component. With ``check`` only
    strongly connected (unique) components are taken, others are refused; without it, all or nothing."""
    return scc_coordinate(eqs, catalog, keys, scope="union", on_unsafe="error" if check else "ignore")


def uniqueness(eqs: DataFrame, ext: DataFrame | None = None) -> DataFrame:
    """(comp_id, queries, is_safe, is_unique) per weak component: unique components are safe and strongly connected."""
    ext = keep(extended_graph(eqs) if ext is None else ext)
    scc = strong_components(eqs.select("qid"), ext.select("src", "dst").distinct())
    told = scc.join(unsafe_queries(ext).withColumn("bad", F.lit(True)), "qid", "left")
    per = told.groupBy("comp_id").agg(F.count("*").alias("queries"), F.countDistinct("scc_id").alias("k"), F.count_if("bad").alias("bad"))
    return per.select("comp_id", "queries", (F.col("bad") == 0).alias("is_safe"), ((F.col("bad") == 0) & (F.col("k") == 1)).alias("is_unique"))


def union_check(run: Coordination, sets: list[int], catalog: dict[str, DataFrame]) -> DataFrame:
    """(n, members, status) of the union of some of a run's sets: whether they coordinate together, which the reach sets don't try."""
    ids = run.nodes.where(F.col("scc_id").isin(sets)).select(F.explode("ids").alias("qid")).distinct()
    rows, keys = run.rows.join(ids, "qid", "left_semi").withColumn("comp_id", F.lit(0).cast("long")), run.keys

    def one(pdf):
        eqs, links = _load(pdf)
        links = {q: [x for x in to if x[1] in eqs] for q, to in links.items()}
        u, found, steps = _whole(eqs, links, sorted(eqs), keys)
        return pd.DataFrame([node_row(0, min(eqs), 0, eqs, sorted(eqs), [], not u.conflict, steps, found)], columns=COLUMNS)

    nodes = keep(rows.groupBy("comp_id").applyInPandas(one, NODE))  # the caller's few sets
    return grounded(nodes, catalog, run.choose, inherit=False).select("n", F.array_join(F.transform("ids", lambda x: x.cast("string")), ",").alias("members"), "status")


def bodies_only(eqs: DataFrame, catalog: dict[str, DataFrame]) -> Coordination:
    """Each body by itself, partners ignored: an upper bound on who can be served."""
    return scc_coordinate(eqs, catalog, scope="alone")
