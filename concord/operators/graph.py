"""Graph operators on edge tables."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from concord.runtime import cut, keep

#: Up to so many distinct edges, components are found by one task (two arrays of longs); more are contracted over tables.
EDGES_IN_TASK = 4_000_000


def _state(edges: DataFrame) -> tuple:
    """Count and order-free checksum of an edge table (one small aggregate)."""
    row = edges.agg(
        F.count("*").alias("n"),
        F.coalesce(F.bit_xor(F.xxhash64("src", "dst")), F.lit(0)).alias("x"),
    ).first()
    return row["n"], row["x"]


def least_reachable(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, least node of the component of each): labels spread over the edges, and jump along themselves after every round."""
    nodes, ends = np.unique(np.concatenate([src, dst]), return_inverse=True)
    a, b = ends[: len(src)], ends[len(src) :]
    label = np.arange(len(nodes))
    while True:
        low = np.minimum(label[a], label[b])
        new = label.copy()
        # roots take the least label that any of their members met, so trees hook onto trees
        np.minimum.at(new, label[a], low)
        np.minimum.at(new, label[b], low)
        while not np.array_equal(new, jumped := new[new]):
            new = jumped
        if np.array_equal(new, label):
            return nodes, nodes[label]
        label = new


def _in_task(e: DataFrame) -> DataFrame:
    """Components of a small edge table: one executor task, no rows on the driver."""
    kind = e.schema["src"].dataType.simpleString()

    def run(frames: Iterator) -> Iterator:
        import pandas as pd

        parts = [(f["src"].to_numpy(), f["dst"].to_numpy()) for f in frames if len(f)]
        if parts:
            node, comp = least_reachable(*(np.concatenate(c) for c in zip(*parts, strict=True)))
            yield pd.DataFrame({"node": node, "comp_id": comp})

    return e.coalesce(1).mapInPandas(run, f"node {kind}, comp_id {kind}")


def weak_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60, in_task: int | None = None) -> DataFrame:
    """Connected components of an undirected edge table as ``(node, comp_id)``, comp_id the least node.

    Up to ``in_task`` distinct edges (``EDGES_IN_TASK``) between whole numbers are labelled by one task. More alternate large-star and
    small-star contractions: every round keeps connectivity, never grows the
    edge table beyond its size and reaches stars around each component's minimum after a number of
    rounds logarithmic in practice. Minima are hash aggregates with map-side combine, so a hub costs
    one row per task; the joins back can be split by AQE, and are never broadcast, as their sides grow with the
    edges and would pass through the driver. Nodes without any edge are not listed; null
    ends and self loops are ignored.
    """
    e = (
        edges.select(F.col(src).alias("a"), F.col(dst).alias("b"))
        .where("a <> b")
        .select(F.greatest("a", "b").alias("src"), F.least("a", "b").alias("dst"))
        .distinct()
    )
    e = cut(e)
    state = _state(e)
    if state[0] == 0:
        return e.select(F.col("src").alias("node"), F.col("dst").alias("comp_id"))
    if state[0] <= (EDGES_IN_TASK if in_task is None else in_task) and e.schema["src"].dataType.simpleString() in ("int", "bigint"):
        return cut(_in_task(e))
    for _ in range(max_rounds):
        # large star: link every larger neighbour to the least of the closed neighbourhood
        both = e.select(F.col("src").alias("u"), F.col("dst").alias("v")).unionByName(
            e.select(F.col("dst").alias("u"), F.col("src").alias("v"))
        )
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(low.hint("merge"), "u").select(F.col("v").alias("src"), F.col("m").alias("dst")).where("src <> dst").distinct()
        # small star: link smaller neighbours and the node itself to the least smaller neighbour
        least = large.groupBy("src").agg(F.min("dst").alias("m"))
        hung = large.join(least.hint("merge"), "src").select(F.col("dst").alias("s"), F.col("m").alias("d")).where("s <> d")
        nxt = cut(hung.unionByName(least.select(F.col("src").alias("s"), F.col("m").alias("d"))).select(F.col("s").alias("src"), F.col("d").alias("dst")).distinct())
        new = _state(nxt)
        e = nxt
        if new == state:
            break
        state = new
    else:
        raise RuntimeError("component contraction did not converge")
    stars = e.select(F.col("src").alias("node"), F.col("dst").alias("comp_id"))
    return stars.unionByName(e.select(F.col("dst").alias("node"), F.col("dst").alias("comp_id")).distinct())


# ---------------------------------------------------------------- directed structure

NODE = "comp_id long, qid long, scc_id long, level int"


def tarjan(nodes: list, out: dict) -> dict:
    """Strongly connected components without recursion: node -> least node of its component."""
    index: dict = {}
    low: dict = {}
    on: set = set()
    stack: list = []
    scc: dict = {}
    for root in nodes:
        if root in index:
            continue
        work = [(root, iter(out.get(root, ())))]
        index[root] = low[root] = len(index)
        stack.append(root)
        on.add(root)
        while work:
            node, it = work[-1]
            for nxt in it:
                if nxt not in index:
                    index[nxt] = low[nxt] = len(index)
                    stack.append(nxt)
                    on.add(nxt)
                    work.append((nxt, iter(out.get(nxt, ()))))
                    break
                if nxt in on:
                    low[node] = min(low[node], index[nxt])
            else:
                work.pop()
                if work:
                    low[work[-1][0]] = min(low[work[-1][0]], low[node])
                if low[node] == index[node]:
                    members = []
                    while True:
                        m = stack.pop()
                        on.discard(m)
                        members.append(m)
                        if m == node:
                            break
                    least = min(members)
                    for m in members:
                        scc[m] = least
    return scc


def condense_local(scc: dict, out: dict) -> tuple[dict, dict]:
    """(component -> successors, component -> level): level 0 has no successor, others stand above their highest one."""
    succ: dict = {s: set() for s in set(scc.values())}
    for a, targets in out.items():
        for b in targets:
            if scc[a] != scc[b]:
                succ[scc[a]].add(scc[b])
    level: dict = {}
    for root in succ:
        work = [root]
        while work:
            n = work[-1]
            waiting = [m for m in succ[n] if m not in level]
            if n not in level and waiting:
                work += waiting
            else:
                work.pop()
                level.setdefault(n, 1 + max((level[m] for m in succ[n]), default=-1))
    return succ, level


def _adjacency(pdf) -> tuple[list, dict]:
    out: dict = {}
    nodes: dict = {}
    for a, b in zip(pdf["src"].tolist(), pdf["dst"].tolist(), strict=True):
        nodes[a] = None
        if b == b and b is not None:
            b = int(b)
            nodes[b] = None
            out.setdefault(a, []).append(b)
    return sorted(nodes), out


def with_components(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(comp_id, src, dst): every edge under its weak component; a node without edges has one row with a null dst."""
    comp = weak_components(edges)
    lone = nodes.select(F.col("qid").alias("src")).join(edges.select("src").distinct(), "src", "left_anti").join(edges.select(F.col("dst").alias("src")).distinct(), "src", "left_anti")
    inside = edges.join(comp, F.col("src") == F.col("node")).select("comp_id", "src", "dst")
    return inside.unionByName(lone.select(F.col("src").alias("comp_id"), "src", F.lit(None).cast("long").alias("dst")))


def strong_components(nodes: DataFrame, edges: DataFrame, method: str = "local") -> DataFrame:
    """(comp_id, qid, scc_id, level). ``local`` runs one pass per weak component in a grouped map; ``fwbw`` trims and colours
    over the whole edge table, for components beyond one task (its level is null: see ``levels``)."""
    if method == "fwbw":
        return _fwbw(nodes, edges)

    def run(pdf):
        import pandas as pd

        ids, out = _adjacency(pdf)
        scc = tarjan(ids, out)
        _, level = condense_local(scc, out)
        comp = int(pdf["comp_id"].iloc[0])
        return pd.DataFrame([(comp, q, scc[q], level[scc[q]]) for q in ids], columns=["comp_id", "qid", "scc_id", "level"])

    return with_components(nodes, edges).groupBy("comp_id").applyInPandas(run, NODE)


def _fwbw(nodes: DataFrame, edges: DataFrame, max_rounds: int = 1000) -> DataFrame:
    """Distributed components: trim, spread the greatest id forwards as a colour, walk back from each colour's root, repeat."""
    left = cut(nodes.select("qid").distinct())
    e = cut(edges.select("src", "dst").where("src <> dst").distinct())
    done = None
    for _ in range(max_rounds):
        if left.isEmpty():
            break
        while True:  # nodes without a way in or a way out are components of their own
            inner = e.select(F.col("src").alias("qid")).intersect(e.select(F.col("dst").alias("qid")))
            trimmed = keep(left.join(inner, "qid", "left_anti").select("qid", F.col("qid").alias("scc_id")))  # united later: a scan has no constraints to carry over
            if trimmed.isEmpty():
                break
            done = trimmed if done is None else done.unionByName(trimmed)
            left = cut(left.join(trimmed, "qid", "left_anti"))
            e = cut(e.join(left.withColumnRenamed("qid", "src"), "src", "left_semi").join(left.withColumnRenamed("qid", "dst"), "dst", "left_semi"))
        if left.isEmpty():
            break
        colour = cut(left.withColumn("c", F.col("qid")))
        while True:
            via = e.join(colour.withColumnRenamed("qid", "src"), "src").groupBy(F.col("dst").alias("qid")).agg(F.max("c").alias("m"))
            nxt = cut(colour.join(via, "qid", "left").select("qid", F.greatest("c", F.coalesce("m", "c")).alias("c"), (F.coalesce("m", "c") > F.col("c")).alias("up")))
            colour = nxt.drop("up")
            if nxt.where("up").isEmpty():
                break
        reached = cut(colour.where("qid = c"))
        front = reached
        while True:  # backwards inside the colour
            step = e.join(front.withColumnsRenamed({"qid": "dst", "c": "k"}), "dst").select(F.col("src").alias("qid"), "k").distinct()
            step = step.join(colour, "qid").where("c = k").select("qid", "c").join(reached, ["qid", "c"], "left_anti")
            front = cut(step)
            if front.isEmpty():
                break
            reached = cut(reached.unionByName(front))
        found = keep(reached.join(reached.groupBy("c").agg(F.min("qid").alias("scc_id")), "c").select("qid", "scc_id"))
        done = found if done is None else done.unionByName(found)
        left = cut(left.join(found, "qid", "left_anti"))
        e = cut(e.join(left.withColumnRenamed("qid", "src"), "src", "left_semi").join(left.withColumnRenamed("qid", "dst"), "dst", "left_semi"))
    else:
        raise RuntimeError("strong components did not end within their rounds")
    if done is None:
        done = nodes.select("qid", F.col("qid").alias("scc_id")).where("false")
    comp = weak_components(edges)
    return done.join(comp, F.col("qid") == F.col("node"), "left").select(F.coalesce("comp_id", "qid").alias("comp_id"), "qid", "scc_id", F.lit(None).cast("int").alias("level"))


def condense(edges: DataFrame, scc: DataFrame) -> DataFrame:
    """(src_scc, dst_scc) of the acyclic components graph."""
    a = scc.select(F.col("qid").alias("src"), F.col("scc_id").alias("src_scc"))
    b = scc.select(F.col("qid").alias("dst"), F.col("scc_id").alias("dst_scc"))
    return edges.join(a, "src").join(b, "dst").where("src_scc <> dst_scc").select("src_scc", "dst_scc").distinct()


def levels(dag: DataFrame, nodes: DataFrame, max_rounds: int = 100_000) -> DataFrame:
    """(scc_id, level) by peeling sinks, for graphs beyond one task."""
    left, e, done, k = cut(nodes.select("scc_id").distinct()), cut(dag), None, 0
    while not left.isEmpty():
        if k >= max_rounds:
            raise RuntimeError("levels did not end within their rounds")
        sinks = cut(left.join(e.select(F.col("src_scc").alias("scc_id")).distinct(), "scc_id", "left_anti").withColumn("level", F.lit(k)))
        done = sinks if done is None else done.unionByName(sinks)
        if sinks.isEmpty():
            raise ValueError("levels need an acyclic graph")
        left = cut(left.join(sinks, "scc_id", "left_anti"))
        e = cut(e.join(sinks.select(F.col("scc_id").alias("dst_scc")), "dst_scc", "left_anti"))
        k += 1
    return done if done is not None else nodes.select("scc_id", F.lit(0).alias("level")).where("false")


def reach_sets(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(scc_id, n, members): the queries in the components reachable from each component, itself included."""

    def run(pdf):
        import pandas as pd

        ids, out = _adjacency(pdf)
        scc = tarjan(ids, out)
        succ, level = condense_local(scc, out)
        own: dict = {}
        for q in ids:
            own.setdefault(scc[q], set()).add(q)
        reach: dict = {}
        for s in sorted(succ, key=level.get):
            reach[s] = own[s].union(*(reach[t] for t in succ[s]))
        return pd.DataFrame([(s, len(r), ",".join(map(str, sorted(r)))) for s, r in reach.items()], columns=["scc_id", "n", "members"])

    return with_components(nodes, edges).groupBy("comp_id").applyInPandas(run, "scc_id long, n long, members string")


def prune_unmatched(eqs: DataFrame, ext: DataFrame, comp: DataFrame | None = None) -> DataFrame:
    """(qid) of the queries whose every postcondition keeps a head to match, to the greatest such set.

    Each weak component (``comp``, if known) is peeled in one pass with counters per postcondition.
    """
    posts = eqs.select(F.col("qid").alias("src"), F.posexplode("post").alias("post_pos", "p")).select("src", "post_pos")
    slots = posts.join(ext.select("src", "post_pos", "dst").distinct(), ["src", "post_pos"], "left")
    comp = weak_components(ext) if comp is None else comp
    dealt = slots.join(comp, F.col("src") == F.col("node"), "left").select(F.coalesce("comp_id", "src").alias("comp_id"), "src", "post_pos", "dst")

    def run(pdf):
        import pandas as pd

        left: dict = {}
        users: dict = {}
        for s, p, t in zip(pdf["src"].tolist(), pdf["post_pos"].tolist(), pdf["dst"].tolist(), strict=True):
            left.setdefault((s, p), 0)
            if t == t and t is not None:
                left[s, p] += 1
                users.setdefault(int(t), []).append((s, p))
        dead = {s for (s, _), n in left.items() if n == 0}
        queue = list(dead)
        while queue:
            for slot in users.get(queue.pop(), ()):
                left[slot] -= 1
                if left[slot] == 0 and slot[0] not in dead:
                    dead.add(slot[0])
                    queue.append(slot[0])
        return pd.DataFrame({"qid": sorted(dead)}, dtype="int64")

    return eqs.select("qid").join(dealt.groupBy("comp_id").applyInPandas(run, "qid long"), "qid", "left_anti")
