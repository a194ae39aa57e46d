"""Coordination of possibly unsafe requests that agree on a common set of attributes.

A request fixes some attributes of the data relation for itself and asks for partners (named users, or at least k friends of a
friend relation). All partners must share the values of the coordination attributes. For each candidate value
the requests that can use it form a graph, which is cleaned to its greatest set in which every request
keeps its partners; the best such set over all values wins.

Plans at scale. Requests with equal own constants share one option list (signature). The data relation is read once per
set of constrained attributes and reduced to distinct values before anything is shuffled. Values with the same signatures have
the same graph, so graphs are made and cleaned once per *pattern* (a set of signatures), and only the small table of signatures and values grows
with the data. The whole algorithm cleans by ``bits``: a request is a row of bits, one a pattern, and those of a weak component of the
graph are peeled by or, and, and threshold counts over whole rows, so all patterns are cleaned at once. Tasks give sizes and weights by pattern; members are made only
where they are asked for. Where lists or edges are too large for that, and in ``clean``, cleaning partitions by pattern: ``local`` streams sorted patterns through a task and peels a batch of them at once with
vector arithmetic, ``rounds`` keeps counters in tables and moves only what has changed, for graphs too large for a task. ``auto`` chooses
by the number of edges. Friends may also be given by groups (``user``, ``group``): all who share a group are friends. If every request asks for any one
of them, cleaning needs no pairs: whoever shares no group with another at a value falls out, and was nobody's friend there.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from functools import cached_property

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from concord.operators.graph import weak_components
from concord.operators.select import Selection, largest
from concord.runtime import cut, keep, partitions, wide_rows

Key = str | tuple[str, ...]


def keys(key: Key) -> list[str]:
    return [key] if isinstance(key, str) else list(key)


# ---------------------------------------------------------------- validation


def validate_requests(requests: DataFrame, attributes: list[str]) -> DataFrame:
    """Violations (rule, qid, detail): one request a user, known attributes only, asks of at least one friend, not both same_tuple and not."""
    twice = requests.groupBy("user").agg(F.count("*").alias("n"), F.min("qid").alias("qid")).where("n > 1").select(F.lit("one_request_per_user").alias("rule"), "qid", F.col("user").cast("string").alias("detail"))
    known = F.array(*[F.lit(a) for a in attributes])
    odd = requests.select("qid", F.explode(F.array_except(F.map_keys("own"), known)).alias("detail")).select(F.lit("unknown_attribute").alias("rule"), "qid", "detail")
    few = requests.select("qid", F.explode("any_friend").alias("a")).where("a.k < 1").select(F.lit("ask_below_one").alias("rule"), "qid", F.col("a.rel").alias("detail"))
    mixed = requests.agg(F.count_if("same_tuple").alias("s"), F.count("*").alias("n"), F.min(F.when(F.col("same_tuple"), F.col("qid"))).alias("qid")).where("s > 0 and s < n")
    return twice.unionByName(odd).unionByName(few).unionByName(mixed.select(F.lit("mixed_coordination").alias("rule"), "qid", F.lit("same_tuple").alias("detail")))


def refuse(requests: DataFrame, attributes: list[str]) -> None:
    """Raises on requests that the algorithm doesn't take."""
    wrong = validate_requests(requests, attributes).orderBy("rule", "qid").limit(5).collect()
    if wrong:
        raise ValueError(f"requests refused: {[(r['rule'], r['qid'], r['detail']) for r in wrong]}")


# ---------------------------------------------------------------- options


def signatures(requests: DataFrame) -> DataFrame:
    """(qid, sig, mask, own): requests with equal own constants share a signature."""
    entries = F.array_sort(F.map_entries("own"))
    return requests.select(
        "qid", F.to_json(entries).alias("sig"), F.array_join(F.array_sort(F.map_keys("own")), ",").alias("mask"), "own"
    )


def option_lists(requests: DataFrame, data: DataFrame, coord: list[str]) -> DataFrame:
    """(sig, coordination attributes): the distinct values that satisfy the constants of each signature."""
    sig = keep(signatures(requests).groupBy("sig", "mask").agg(F.first("own").alias("own")))
    masks = [r["mask"] for r in sig.select("mask").distinct().collect()]  # at most one per subset of the attributes
    used = sorted({a for mask in masks for a in mask.split(",") if a})
    data = data.select(*coord, *[F.col(a).cast("string").alias(f"__{a}") for a in used]).distinct()
    if len(masks) > 1:
        data = keep(data)  # else every mask would join and shuffle the relation anew
    out = None
    for mask in masks:
        fixed = [a for a in mask.split(",") if a]
        wanted = sig.where(F.col("mask") == mask).select("sig", *[F.element_at("own", F.lit(a)).alias(f"__{a}") for a in fixed])
        # distinct on constrained and coordination attributes before the join: the relation shrinks map-side
        rows = data.select(*coord, *[f"__{a}" for a in fixed]).distinct()
        part = (rows.join(wanted, [f"__{a}" for a in fixed]) if fixed else rows.join(F.broadcast(wanted), how="cross")).select("sig", *coord).distinct()
        out = part if out is None else out.unionByName(part)
    if out is None:
        return sig.select("sig", *[F.lit(None).cast(data.schema[c].dataType).alias(c) for c in coord]).where("false")
    return out


def befriended(requests: DataFrame, friends: DataFrame) -> DataFrame:
    """The requests whose every friendship ask has at least one friend in its relation (it is part of their body)."""
    asks = requests.select("qid", "user", F.explode("any_friend").alias("a")).select("qid", "user", F.col("a.rel").alias("rel"))
    known = _with_rel(friends)
    if "group" in friends.columns:
        known = known.join(known.groupBy("group", "rel").agg(F.min("user").alias("lo"), F.max("user").alias("hi")).where("lo < hi"), ["group", "rel"], "left_semi")
    lonely = asks.join(known.select("user", "rel").distinct(), ["user", "rel"], "left_anti").select("qid").distinct()
    return requests.join(lonely, "qid", "left_anti")


def options(requests: DataFrame, data: DataFrame, coord: list[str], friends: DataFrame) -> DataFrame:
    """(qid, coordination attributes): the options list of every request."""
    able = befriended(requests, friends)
    return signatures(able).select("qid", "sig").join(option_lists(able, data, coord), "sig").select("qid", *coord)


def candidates(vq: DataFrame, coord: list[str]) -> DataFrame:
    return vq.select(*coord).distinct()


def scheduled(data: DataFrame, schedule: DataFrame, on: dict[str, str], day: str, event_day: str, days_before: int = 1) -> DataFrame:
    """Data rows that serve an event of a schedule: equal places, and the day lies the given number of days before the event."""
    wanted = schedule.select(*[F.col(b).alias(a) for a, b in on.items()], F.date_sub(F.col(event_day), days_before).alias(day)).distinct()
    return data.join(wanted, [*on, day], "left_semi")


# ---------------------------------------------------------------- graphs


def _with_rel(friends: DataFrame) -> DataFrame:
    return friends if "rel" in friends.columns else friends.withColumn("rel", F.lit("friends"))


def friend_lists(requests: DataFrame, friends: DataFrame) -> DataFrame:
    """(user, rel, friend) for every ask."""
    asks = requests.select("user", F.explode("any_friend").alias("a")).select("user", F.col("a.rel").alias("rel")).distinct()
    return asks.join(_with_rel(friends), ["user", "rel"]).select("user", "rel", "friend").distinct()


def pairs(groups: DataFrame) -> DataFrame:
    """(user, friend, rel) of friends by groups: as many rows as groups have pairs."""
    known = _with_rel(groups).select("user", "group", "rel").distinct()
    return known.join(known.withColumnsRenamed({"user": "friend"}), ["group", "rel"]).where("user <> friend").select("user", "friend", "rel").distinct()


def pruned_graph(requests: DataFrame, friends: DataFrame, vq: DataFrame, allow_self: bool = True) -> DataFrame:
    """(src, dst, kind): src may coordinate with dst, as a named partner or as a friend of relation ``kind``; both ends have options."""
    live = requests.join(vq.select("qid").distinct(), "qid", "left_semi")
    to = live.select(F.col("qid").alias("dst"), F.col("user").alias("partner"))
    named = live.select(F.col("qid").alias("src"), F.explode("named").alias("partner")).join(to, "partner").select("src", "dst", F.lit("named").alias("kind"))
    who = live.select(F.col("qid").alias("src"), "user")
    friend = friend_lists(live, friends).join(who, "user").join(to, F.col("friend") == F.col("partner")).select("src", "dst", F.concat(F.lit("any:"), F.col("rel")).alias("kind"))
    out = named.unionByName(friend).distinct()
    return out if allow_self else out.where("src <> dst")


def needs(requests: DataFrame) -> DataFrame:
    """(qid, kind, need): how many partners of a kind a request must keep."""
    named = requests.select("qid", F.lit("named").alias("kind"), F.size(F.array_distinct("named")).alias("need")).where("need > 0")
    asked = requests.select("qid", F.explode("any_friend").alias("a")).select("qid", F.concat(F.lit("any:"), F.col("a.rel")).alias("kind"), F.col("a.k").alias("need"))
    return named.unionByName(asked.groupBy("qid", "kind").agg(F.max("need").alias("need")))


def subgraphs(vq: DataFrame, edges: DataFrame, coord: list[str]) -> DataFrame:
    """(coordination attributes, src, dst, kind): the pruned graph restricted to each value."""
    a = vq.select(F.col("qid").alias("src"), *coord)
    b = vq.select(F.col("qid").alias("dst"), *coord)
    return edges.join(a, "src").join(b, ["dst", *coord]).select(*coord, "src", "dst", "kind")


# ---------------------------------------------------------------- cleaning


def _ranges(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The concatenation of arange(start, start + count)."""
    ends = np.cumsum(counts)
    return np.arange(ends[-1] if len(ends) else 0) - np.repeat(ends - counts, counts) + np.repeat(starts, counts)


def _peel(value: np.ndarray, qid: np.ndarray, asks: dict[int, list]) -> np.ndarray:
    """Alive flags of the (value, qid) nodes of one partition; asks[i], for the first node i of each request, lists its (need, partner qids)."""
    n = len(value)
    ids, first, who = np.unique(qid, return_index=True, return_inverse=True)
    mine = [asks[i] for i in first]  # a request asks the same at every value
    slots = np.array([len(a) for a in mine], dtype=np.int64)
    need = np.array([x[0] for a in mine for x in a], dtype=np.int64)
    sizes = np.array([len(x[1]) for a in mine for x in a], dtype=np.int64)
    partners = np.concatenate([np.asarray(x[1], dtype=np.int64) for a in mine for x in a] or [np.zeros(0, np.int64)])
    slot_at, edge_at = np.cumsum(slots) - slots, np.cumsum(sizes) - sizes
    # the same slots for every node, and the same edges for every slot of a node
    here = _ranges(slot_at[who], slots[who])
    owner = np.repeat(np.arange(n), slots[who])
    edge = _ranges(edge_at[here], sizes[here])
    src = np.repeat(np.arange(len(here)), sizes[here])
    to = np.searchsorted(ids, partners[edge])
    known = (to < len(ids)) & (ids[np.minimum(to, len(ids) - 1)] == partners[edge])
    code = value.astype(np.int64) * len(ids) + who
    order = np.argsort(code, kind="stable")
    want = value[owner[src]].astype(np.int64) * len(ids) + to
    at = np.searchsorted(code[order], want)
    hit = known & (at < n)
    hit[hit] = code[order][at[hit]] == want[hit]
    src, dst, needed = src[hit], order[at[hit]], need[here]
    alive = np.ones(n, bool)
    while True:
        have = np.bincount(src[alive[dst]], minlength=len(here))
        bad = owner[(have < needed) & alive[owner]]
        if not len(bad):
            return alive
        alive[bad] = False


#: Up to so many edges partner lists are broadcast, and all graphs fit into tasks; batches of nodes that are peeled at once.
EDGES_IN_TASK = 4_000_000
BATCH_NODES = 200_000


def _asks(edges: DataFrame, need: DataFrame) -> DataFrame:
    """(qid, asks): needs and partner lists of every request that asks."""
    per = need.join(edges.withColumnsRenamed({"src": "qid"}), ["qid", "kind"], "left").groupBy("qid", "kind").agg(F.max("need").alias("need"), F.collect_set("dst").alias("to"))
    return per.groupBy("qid").agg(F.collect_list(F.struct("need", "to")).alias("asks"))


def _clean_local(vq: DataFrame, edges: DataFrame, need: DataFrame, coord: list[str]) -> DataFrame:
    asks, held = _asks(edges, need), None
    nodes = vq.select(*coord, "qid")
    if edges.count() <= EDGES_IN_TASK:
        table = {r["qid"]: [(x["need"], x["to"]) for x in r["asks"]] for r in asks.collect()}  # bounded by the edges
        held = vq.sparkSession.sparkContext.broadcast(table)
    else:
        nodes = nodes.join(asks, "qid", "left")
    dealt = nodes.repartition(*coord).sortWithinPartitions(*coord)

    def peeled(pdf):
        value = pdf.groupby(coord, sort=False, dropna=False).ngroup().to_numpy()
        qid = pdf["qid"].to_numpy(np.int64)
        first = np.unique(qid, return_index=True)[1]
        if held is not None:
            told = {int(i): held.value.get(int(qid[i]), []) for i in first}
        else:
            asks = pdf["asks"].to_numpy()
            told = {int(i): [] if asks[i] is None else [(x["need"], x["to"]) for x in asks[i]] for i in first}
        return pdf.loc[_peel(value, qid, told), [*coord, "qid"]]

    def run(frames):
        waiting = None
        for frame in frames:
            waiting = frame if waiting is None else pd.concat([waiting, frame], ignore_index=True)
            if len(waiting) < BATCH_NODES:
                continue
            # whole groups only: from the last change of value on, rows wait
            at, last = waiting[coord], waiting[coord].iloc[-1]
            same = np.ones(len(waiting), bool)
            for c in coord:
                same &= at[c].isna().to_numpy() if pd.isna(last[c]) else (at[c] == last[c]).to_numpy()
            begin = int(np.argmax(same))
            if begin:
                yield peeled(waiting.iloc[:begin].reset_index(drop=True))
                waiting = waiting.iloc[begin:].reset_index(drop=True)
        if waiting is not None and len(waiting):
            yield peeled(waiting)

    return dealt.mapInPandas(run, _node_schema(vq, coord))


def _node_schema(vq: DataFrame, coord: list[str]):
    return vq.select(*coord, "qid").schema


def _clean_rounds(vq: DataFrame, edges: DataFrame, need: DataFrame, coord: list[str], max_rounds: int = 10_000) -> DataFrame:
    """Counters per (value, request, kind); each round takes away what the last round's removals supported."""
    at = subgraphs(vq, edges, coord)
    have = at.groupBy(*coord, F.col("src").alias("qid"), "kind").agg(F.countDistinct("dst").alias("have"))
    slots = cut(vq.join(need, "qid").join(have, [*coord, "qid", "kind"], "left").select(*coord, "qid", "kind", "need", F.coalesce("have", F.lit(0)).alias("have")))
    dead = cut(slots.where("have < need").select(*coord, "qid").distinct())
    gone = dead
    for _ in range(max_rounds):
        if dead.isEmpty():
            break
        lost = subgraphs_of(dead, edges, coord).groupBy(*coord, "qid", "kind").agg(F.count("*").alias("lost"))
        slots = cut(slots.join(dead, [*coord, "qid"], "left_anti").join(lost, [*coord, "qid", "kind"], "left").withColumn("have", F.col("have") - F.coalesce("lost", F.lit(0))).drop("lost"))
        dead = cut(slots.where("have < need").select(*coord, "qid").distinct())
        gone = cut(gone.unionByName(dead))
    else:
        raise RuntimeError("cleaning did not end within its rounds")
    return vq.select(*coord, "qid").join(gone, [*coord, "qid"], "left_anti")


def subgraphs_of(dead: DataFrame, edges: DataFrame, coord: list[str]) -> DataFrame:
    """(coordination attributes, qid, kind) once for every supporter lost."""
    return edges.join(dead.withColumnsRenamed({"qid": "dst"}), "dst").select(*coord, F.col("src").alias("qid"), "kind", "dst").distinct()


def _clean_sequential(vq: DataFrame, edges: DataFrame, need: DataFrame, coord: list[str]) -> DataFrame:
    """One value after another (the baseline without parallelism), for small inputs."""
    spark, schema = vq.sparkSession, _node_schema(vq, coord)
    vq, edges, need = keep(vq), keep(edges), keep(need)
    found = []
    for value in candidates(vq, coord).collect():
        here = None
        for c in coord:
            same = F.col(c).eqNullSafe(F.lit(value[c]))
            here = same if here is None else here & same
        found += _clean_local(vq.where(here).coalesce(1), edges, need, coord).collect()
    return spark.createDataFrame(found, schema)


def clean(vq: DataFrame, edges: DataFrame, requests: DataFrame, coord: list[str], mode: str = "auto") -> DataFrame:
    """(coordination attributes, qid): the greatest set per value in which every request keeps its partners."""
    if mode == "auto":
        mode = "local" if edges.count() <= EDGES_IN_TASK else "rounds"
    how = {"local": _clean_local, "rounds": _clean_rounds, "sequential": _clean_sequential}[mode]
    return how(vq, edges, needs(requests), coord)


# ---------------------------------------------------------------- cleaning by groups

#: Up to so many memberships travel to the tasks, four bytes each.
MEMBERSHIPS = 16_000_000


def one_any(requests: DataFrame) -> bool:
    """Whether every request asks for any one friend of one relation and names nobody."""
    simple = "size(named) = 0 and size(any_friend) = 1 and any_friend[0].k = 1"
    return requests.where(f"not ({simple})").isEmpty() and requests.select(F.get("any_friend", 0)["rel"]).distinct().count() <= 1


class Groups:
    """Cleaning where all who share a group (a long) are friends, for requests that each ask for any one friend."""

    def __init__(self, friends: DataFrame, requests: DataFrame):
        asked = requests.select("qid", "user", F.get("any_friend", 0)["rel"].alias("rel"))
        self.members = keep(_with_rel(friends).join(asked, ["user", "rel"]).select("qid", F.col("group").cast("long").alias("group")).where("group is not null").distinct())
        self.held = self._packed() if self.members.count() <= MEMBERSHIPS else None

    def _packed(self):
        """The groups of every request in order of requests, put together from one packed row a partition."""

        def run(frames):
            pdf = pd.concat([*frames, pd.DataFrame({"qid": np.zeros(0, np.int64), "group": np.zeros(0, np.int64)})])
            pdf = pdf.sort_values("qid")
            ids, counts = np.unique(pdf["qid"].to_numpy(np.int64), return_counts=True)
            yield pd.DataFrame({"ids": [ids.tobytes()], "counts": [counts.astype(np.int32).tobytes()], "groups": [pdf["group"].to_numpy(np.int64).tobytes()]})

        spark = self.members.sparkSession
        dealt = self.members.repartition(partitions(spark), "qid")
        rows = dealt.mapInPandas(run, "ids binary, counts binary, groups binary").collect()  # at most MEMBERSHIPS numbers
        ids, counts, groups = (np.concatenate([np.frombuffer(bytes(r[c]), kind) for r in rows]) for c, kind in (("ids", np.int64), ("counts", np.int32), ("groups", np.int64)))
        known = np.unique(groups)
        groups = np.searchsorted(known, groups).astype(np.int32)
        order, starts = np.argsort(ids), np.cumsum(counts, dtype=np.int64) - counts
        return spark.sparkContext.broadcast((ids[order], starts[order], counts[order], groups, len(known)))

    def left(self, nodes: DataFrame) -> DataFrame:
        """(pid, qid) of the nodes that share a group with another of their pattern."""
        nodes, held = nodes.select("pid", "qid"), self.held
        if held is None:
            at = nodes.join(self.members, "qid")
            met = at.groupBy("pid", "group").agg(F.count("*").alias("n")).where("n > 1")
            return at.join(met, ["pid", "group"], "left_semi").select("pid", "qid").distinct()

        def run(frames):
            ids, starts, counts, groups, known = held.value
            for pdf in _groups(frames, "pid"):
                qid = pdf["qid"].to_numpy(np.int64)
                at = np.minimum(np.searchsorted(ids, qid), max(0, len(ids) - 1))
                many = np.where(ids[at] == qid, counts[at], 0) if len(ids) else np.zeros(len(qid), np.int64)
                mine = groups[_ranges(starts[at], many)] if len(ids) else groups
                if known > 4 * len(mine):
                    mine = np.unique(mine, return_inverse=True)[1]
                met = np.bincount(mine)[mine] > 1
                alive = np.bincount(np.repeat(np.arange(len(qid)), many)[met], minlength=len(qid)) > 0
                yield pdf[alive]

        dealt = nodes.repartition(partitions(nodes.sparkSession), "pid").sortWithinPartitions("pid")
        return dealt.mapInPandas(run, "pid long, qid long")


# ---------------------------------------------------------------- cleaning by bits

#: Up to so many (signature, pattern) entries travel to the tasks, four bytes each.
LISTED = 16_000_000
#: Requests that are peeled together (whole components, so it may be more), bytes of their rows of bits at a time, and patterns whose members are made together: fewer where
#: their bits would exceed so many bytes.
BUCKET, BITS, CHUNK, HELD = 2000, 1 << 26, 512, 1 << 25
#: Bytes of members that are written for one pattern before it gets tasks of its own, if it has so many values, and values to one of these. A Parquet writer holds equal texts
#: once only where its first rows are equal, as they are in a task that has one text. Bytes of members that leave a task at a time, if there are several sets of them.
ALONE, OFTEN, SHARE, SENT = 16_000_000, 64, 2000, 1 << 20


def _at_least(rows: np.ndarray, k: int) -> np.ndarray:
    """The bits that are set in at least k rows."""
    if k <= 0:
        return np.full(rows.shape[1], 255, np.uint8)
    if k > len(rows):
        return np.zeros(rows.shape[1], np.uint8)
    if k == 1:
        return np.bitwise_or.reduce(rows, axis=0)
    if k == len(rows):
        return np.bitwise_and.reduce(rows, axis=0)
    reached = [np.zeros(rows.shape[1], np.uint8) for _ in range(k)]  # [j]: set in more than j rows so far
    for r in rows:
        for j in range(k - 1, 0, -1):
            reached[j] |= reached[j - 1] & r
        reached[0] |= r
    return reached[-1]


def _peel_bits(alive: np.ndarray, slots: list[list[tuple[int, np.ndarray]]]) -> None:
    """Takes away, in place, every bit of a request (row) at which one of its slots (need, partner rows) is short, until none is."""
    users: list[list[int]] = [[] for _ in range(len(alive))]
    for i, mine in enumerate(slots):
        for _, to in mine:
            for t in to.tolist():
                users[t].append(i)
    queue, waits = [i for i, mine in enumerate(slots) if mine], [bool(mine) for mine in slots]
    while queue:
        later = []
        for i in queue:
            waits[i] = False
            left = alive[i]
            for need, to in slots[i]:
                left = left & _at_least(alive[to], need)
            if not np.array_equal(left, alive[i]):
                alive[i] = left
                for u in users[i]:
                    if not waits[u]:
                        waits[u] = True
                        later.append(u)
        queue = later


def _bucket_rows(pdf: pd.DataFrame, lists: dict[int, np.ndarray], only: np.ndarray | None):
    """Peels the requests of some components: yields (qids, pattern numbers, alive), a flag byte for each request and pattern of a block."""
    qid = pdf["qid"].to_numpy(np.int64)
    order = np.argsort(qid)
    ids = qid[order]
    sigs = pdf["sig_id"].to_numpy(np.int64)[order]
    asks = pdf["asks"].to_numpy()[order]
    slots = []
    for a in asks:
        mine = []
        for x in () if a is None else a:
            to = np.unique(np.asarray(x["to"], dtype=np.int64))
            at = np.searchsorted(ids, to)
            fine = (at < len(ids)) & (ids[np.minimum(at, len(ids) - 1)] == to)
            mine.append((int(x["need"]), at[fine]))
        slots.append(mine)
    kinds, which = np.unique(sigs, return_inverse=True)
    mine = [lists.get(int(k), np.zeros(0, np.int32)) for k in kinds]
    if only is not None:
        mine = [m[np.isin(m, only)] for m in mine]
    pids = np.unique(np.concatenate(mine)) if mine else np.zeros(0, np.int32)
    step = max(8, BITS // max(1, len(ids)) * 8)
    for low in range(0, len(pids), step):
        here = pids[low : low + step]
        held = np.zeros((len(kinds), len(here)), np.uint8)
        for k, m in enumerate(mine):
            held[k, np.searchsorted(here, m[(m >= here[0]) & (m <= here[-1])])] = 1
        alive = np.packbits(held, axis=1)[which]
        _peel_bits(alive, slots)
        for at in range(0, len(here), 4096):
            some = here[at : at + 4096]
            yield ids, order, some, np.unpackbits(alive[:, at // 8 : (at + 4096) // 8], axis=1, count=len(some))


def _texts(ids: np.ndarray):
    """The texts of ids in order, a comma behind each, in runs of equal length: yields (from, to, texts as items of fixed size)."""
    flat = ids.astype("S20")
    sizes = np.char.str_len(flat)
    cuts = [0, *(np.flatnonzero(np.diff(sizes)) + 1).tolist(), len(ids)]
    for low, high in zip(cuts, cuts[1:]):
        if low < high:
            size = int(sizes[low])
            run = np.full((high - low, size + 1), ord(","), np.uint8)
            run[:, :size] = flat[low:high].astype(f"S{size}").view(np.uint8).reshape(-1, size)
            yield low, high, run.view(f"V{size + 1}").ravel()


class Bits:
    """Cleaning of all patterns by rows of bits. ``sizes`` are made at once; members on demand, for all patterns or for some."""

    def __init__(self, signed: DataFrame, edges: DataFrame, requests: DataFrame, lists: dict[int, np.ndarray]):
        spark = signed.sparkSession
        comp = weak_components(edges)
        people = signed.join(requests.select("qid", "weight"), "qid").join(comp.withColumnRenamed("node", "qid"), "qid", "left").join(_asks(edges, needs(requests)), "qid", "left")
        count = signed.count()
        buckets = 1 + count // BUCKET
        self.chunk = min(CHUNK, max(8, 8 * HELD // max(1, count) // 8 * 8))
        self.chunks = 1 + max((int(m[-1]) for m in lists.values() if len(m)), default=0) // self.chunk
        self.people = keep(people.withColumn("bucket", F.pmod(F.xxhash64(F.coalesce("comp_id", "qid")), F.lit(buckets)).cast("int")))
        self.lists = spark.sparkContext.broadcast(lists)

    def sizes(self) -> DataFrame:
        """(pid, n, weight) of every pattern with a member. Weights are added in a fixed order, so that equal sets weigh the same."""
        mine = F.array_sort(F.collect_list(F.struct("bucket", "weight")))
        return self.partial_sizes().groupBy("pid").agg(F.sum("n").alias("n"), F.aggregate(mine, F.lit(0.0), lambda x, y: x + y["weight"]).alias("weight"))

    def partial_sizes(self) -> DataFrame:
        """(pid, bucket, n, weight): the part of every task, named by its first bucket. A row for each pattern leaves a task, not for each pattern and bucket."""
        lists = self.lists

        def run(frames):
            total, first = np.zeros((2, 0)), None
            for pdf in _groups(frames, "bucket"):
                first = int(pdf["bucket"].iloc[0]) if first is None else first
                weight = pdf["weight"].to_numpy(float)
                for _, order, pids, flags in _bucket_rows(pdf, lists.value, None):
                    own = weight[order]
                    # a null or unordered weight would spoil a product with flags of zero
                    odd = ~np.isfinite(own)
                    both = np.stack([np.ones(len(own)), np.where(odd, 0.0, own)]) @ flags.astype(float)
                    for i in np.flatnonzero(odd & pdf["weight"].notna().to_numpy()[order]):
                        both[1] += np.where(flags[i] == 1, own[i], 0.0)
                    if pids[-1] >= total.shape[1]:  # numbers of patterns have no gaps
                        total = np.pad(total, ((0, 0), (0, max(2 * total.shape[1], int(pids[-1]) + 1) - total.shape[1])))
                    total[:, pids] += both
            some = np.flatnonzero(total[0])
            yield pd.DataFrame({"pid": some, "bucket": first or 0, "n": total[0, some].astype(np.int64), "weight": total[1, some]})

        spark = self.people.sparkSession
        dealt = self.people.repartition(partitions(spark), "bucket").sortWithinPartitions("bucket")
        return dealt.mapInPandas(run, "pid long, bucket int, n long, weight double")

    def holding(self, qid: int) -> DataFrame:
        """(pid) of the patterns in which a request is left."""
        lists = self.lists

        def run(pdf):
            out = [np.zeros(0, np.int64)]
            for ids, _, pids, flags in _bucket_rows(pdf, lists.value, None):
                out.append(pids[flags[np.searchsorted(ids, qid)] == 1].astype(np.int64))
            return pd.DataFrame({"pid": np.concatenate(out)})

        mine = self.people.where(F.col("qid") == qid).select("bucket").distinct()
        return self.people.join(mine, "bucket", "left_semi").groupBy("bucket").applyInPandas(run, "pid long")

    def cleaned(self, only: list[int] | None = None) -> DataFrame:
        """(pid, qid) that are left, of all patterns or of some, one row each."""
        return self.blocks(only).select("pid", F.explode("ids").alias("qid"))

    def blocks(self, only: list[int] | None = None) -> DataFrame:
        """(pid, ids) of every bucket: the requests that are left of it."""
        lists, some = self.lists, None if only is None else np.array(only, np.int32)

        def run(frames):
            for pdf in frames:
                for ids, _, pids, flags in _bucket_rows(pdf, lists.value, some):
                    for at in range(0, len(pids), 256):
                        part = flags[:, at : at + 256]
                        yield pd.DataFrame({"pid": pids[at : at + 256].astype(np.int64), "ids": [ids[part[:, k] == 1] for k in range(part.shape[1])]})

        def whole(frames):
            return run(_groups(frames, "bucket"))

        dealt = self.people.repartition("bucket").sortWithinPartitions("bucket")
        return dealt.mapInPandas(whole, "pid long, ids array<long>").where("size(ids) > 0")

    def sets(self, shares: dict[int, int] | None = None) -> DataFrame:
        """(pid, share, members) of every pattern, ids in order. Rows of bits are shuffled, not members; a task makes the text of a pattern at a time.

        A pattern comes once, with share 0; a pattern of ``shares`` once for each of them, from tasks that have nothing else.
        """
        lists, shares, spark, width = self.lists, shares or {}, self.people.sparkSession, self.chunk
        plain, alone = max(partitions(spark), self.chunks), {}  # a chunk has a task of its own, however few partitions are set
        top = plain
        for pid, k in sorted(shares.items()):
            alone[pid], top = range(top, top + k), top + k
        apart = np.array(sorted(alone), np.int64)

        def packed(frames):
            for pdf in _groups(frames, "bucket"):
                for ids, _, pids, flags in _bucket_rows(pdf, lists.value, None):
                    for k in np.flatnonzero(np.isin(pids, apart)):
                        mine, to = ids[flags[:, k] == 1], alone[int(pids[k])]
                        if len(mine):
                            yield pd.DataFrame({"part": list(to), "chunk": int(pids[k]), "share": range(len(to)), "ids": [mine.tobytes()] * len(to), "bits": [b""] * len(to)})
                    both = ~np.isin(pids, apart)
                    for c in np.unique(pids[both] // width):
                        here = both & (pids // width == c)
                        columns = np.zeros((len(ids), width), np.uint8)
                        columns[:, pids[here] % width] = flags[:, here]
                        some = columns.any(axis=1)
                        if some.any():
                            yield pd.DataFrame({"part": [int(c) % plain], "chunk": [int(c)], "share": [-1], "ids": [ids[some].tobytes()], "bits": [np.packbits(columns[some], axis=1).tobytes()]})

        def made(pdf):
            chunk, share = int(pdf["chunk"].iloc[0]), int(pdf["share"].iloc[0])
            ids = np.concatenate([np.frombuffer(x, np.int64) for x in pdf["ids"]])
            order = np.argsort(ids, kind="stable")
            texts = list(_texts(ids[order]))
            if share >= 0:
                yield chunk, share, b"".join(run.tobytes() for _, _, run in texts)[:-1].decode()
                return
            rows = np.concatenate([np.frombuffer(x, np.uint8).reshape(-1, width // 8) for x in pdf["bits"]])
            for byte in range(width // 8):
                flags = np.unpackbits(rows[order, byte][None, :], axis=0).astype(bool)
                for k in np.flatnonzero(flags.any(axis=1)):
                    yield chunk * width + 8 * byte + int(k), 0, b"".join(run[flags[k, low:high]].tobytes() for low, high, run in texts)[:-1].decode()

        def members(frames):
            waiting, size = [], 0
            for pdf in _groups(frames, ["chunk", "share"]):
                for row in made(pdf):
                    if waiting and size + len(row[2]) > SENT:
                        yield pd.DataFrame(waiting, columns=["pid", "share", "members"])
                        waiting, size = [], 0
                    waiting.append(row)
                    size += len(row[2])
            if waiting:
                yield pd.DataFrame(waiting, columns=["pid", "share", "members"])

        dealt = self.people.repartition("bucket").sortWithinPartitions("bucket").mapInPandas(packed, "part int, chunk int, share int, ids binary, bits binary")
        return dealt.repartitionById(top, F.col("part")).sortWithinPartitions("chunk", "share").mapInPandas(members, "pid long, share int, members string")


def _groups(frames, column: str | list[str]):
    """Whole groups of a sorted column, or of several, from frames that may cut them."""
    waiting: list = []
    columns = [column] if isinstance(column, str) else column
    for frame in frames:
        for _, part in frame.groupby(column, sort=True):
            if waiting and any(waiting[-1][c].iloc[0] != part[c].iloc[0] for c in columns):
                yield pd.concat(waiting, ignore_index=True)
                waiting = []
            waiting.append(part)
    if waiting:
        yield pd.concat(waiting, ignore_index=True)


def _numbered(shapes: DataFrame) -> DataFrame:
    """Patterns with numbers pid from 0 without gaps (a row a partition reaches the driver)."""
    named = keep(shapes.withColumn("__m", F.monotonically_increasing_id()))
    part = F.shiftright("__m", 33)
    at, pairs = 0, []
    for r in sorted(named.groupBy(part.alias("p")).count().collect()):
        pairs += [F.lit(r["p"]), F.lit(at)]
        at += r["count"]
    if not pairs:
        return named.select("sigs", F.col("__m").alias("pid"))
    first = F.element_at(F.create_map(*pairs), part)
    return named.select("sigs", (first + F.col("__m").bitwiseAND(F.lit((1 << 33) - 1))).cast("long").alias("pid"))


def _listed(shapes: DataFrame) -> dict[int, np.ndarray] | None:
    """The pattern numbers of each signature, packed by tasks; None where they are too many."""
    if (shapes.agg(F.sum(F.size("sigs")).alias("n")).first()["n"] or 0) > LISTED:
        return None

    def run(pdf):
        return pd.DataFrame({"sig_id": [int(pdf["sig_id"].iloc[0])], "pids": [np.sort(pdf["pid"].to_numpy(np.int32)).tobytes()]})

    rows = shapes.select("pid", F.explode("sigs").alias("sig_id")).groupBy("sig_id").applyInPandas(run, "sig_id long, pids binary")
    return {r["sig_id"]: np.frombuffer(bytes(r["pids"]), np.int32) for r in rows.toLocalIterator()}  # at most LISTED numbers


# ---------------------------------------------------------------- whole algorithm


@dataclass
class Consistent:
    coord: list[str]
    lists: DataFrame  # (sig_id, coordination attributes): the option list of each signature
    signed: DataFrame  # (qid, sig_id)
    patterns: DataFrame  # (coordination attributes, pid): values by the set of signatures that can use them
    shapes: DataFrame  # (sigs, pid): the patterns
    edges: DataFrame
    requests: DataFrame
    per: DataFrame  # (pid, n, weight) of the patterns with a member
    bits: Bits | None  # None: ``held`` has what is left
    held: DataFrame | None
    best: DataFrame
    assignment: DataFrame
    metrics: dict = field(default_factory=dict)
    groups: Groups | None = None  # what has cleaned, where friends came by groups

    @cached_property
    def vq(self) -> DataFrame:
        """(qid, coordination attributes): all options, one row each."""
        return self.signed.join(self.lists, "sig_id").select("qid", *self.coord)

    @cached_property
    def nodes(self) -> DataFrame:
        """(pid, qid) before cleaning."""
        return self.shapes.select("pid", F.explode("sigs").alias("sig_id")).join(self.signed, "sig_id").select("pid", "qid")

    @cached_property
    def cleaned(self) -> DataFrame:
        """(pid, qid) that are left."""
        return self.held if self.bits is None else self.bits.cleaned()

    @cached_property
    def sizes(self) -> DataFrame:
        """(coordination attributes, n, weight) of every set, without its members."""
        return self.patterns.join(self.per, "pid").select(*self.coord, "n", "weight")

    @cached_property
    def sets(self) -> DataFrame:
        """(coordination attributes, n, weight, members, ids) of every set."""
        if self.bits is None:
            made = value_sets(self.held, self.requests, ["pid"])
            return made.join(self.patterns.hint("broadcast") if self.few else self.patterns, "pid").select(*self.coord, "n", "weight", "members", "ids")
        cases = [x for pid, k in self.shares.items() for x in (F.lit(pid), F.lit(k))]
        parts = F.coalesce(F.element_at(F.create_map(*cases), F.col("pid")), F.lit(1)) if cases else F.lit(1)
        values = self.patterns.withColumn("share", F.pmod(F.xxhash64(*self.coord), parts.cast("long")).cast("int"))
        values = values.groupBy("pid", "share").agg(F.collect_list(F.struct(*self.coord)).alias("__at")).join(self.per, "pid")
        most = self.per.agg(F.max("n")).first()[0] or 0
        wide_rows(self.signed.sparkSession, most * (1 + len(str(self.signed.agg(F.max(F.abs("qid"))).first()[0] or 0))))
        # compiled code, of a join or an explode, makes the rows of all values of a text before it hands on the first; functions of lambdas are not compiled, so here one row is held at a time
        made = self.bits.sets(self.shares).join(values.hint("broadcast") if self.few else values, ["pid", "share"])
        each = made.select("n", "weight", "members", F.explode(F.transform("__at", lambda x: F.struct(*[x[c].alias(c) for c in self.coord]))).alias("__at"))
        return each.select(*[F.col("__at")[c].alias(c) for c in self.coord], "n", "weight", "members", F.transform(F.split("members", ","), lambda x: x.cast("long")).alias("ids"))

    @cached_property
    def shares(self) -> dict[int, int]:
        """Patterns whose members are written so often that they need tasks of their own, and how many (at most a row for ALONE bytes of the result reaches the driver)."""
        times = self.patterns.groupBy("pid").agg(F.count("*").alias("times"))
        many = times.where(F.col("times") >= OFTEN).join(self.per, "pid").where(F.col("times") * F.col("n") * 8 > ALONE).select("pid", "times").collect()
        return {r["pid"]: min(partitions(self.patterns.sparkSession), -(-r["times"] // SHARE)) for r in many}

    @cached_property
    def few(self) -> bool:
        """Whether the values may be broadcast, so that members need not be shuffled again."""
        return self.patterns.count() <= 500_000

    @cached_property
    def survivors(self) -> DataFrame:
        """(coordination attributes, qid) left after cleaning."""
        return self.patterns.join(self.cleaned, "pid").select(*self.coord, "qid")

    def memory(self) -> DataFrame:
        """(edges, option_rows, list_rows, patterns, values): what is held, edges and options as one-at-a-time processing holds them."""
        values = self.patterns.agg(F.count("*").alias("values"))
        rows = self.signed.groupBy("sig_id").agg(F.count("*").alias("n")).join(self.lists, "sig_id").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("option_rows"), F.count("*").alias("list_rows"))
        pids = self.patterns.agg(F.countDistinct("pid").alias("patterns"))
        return self.edges.agg(F.count("*").alias("edges")).join(F.broadcast(rows), how="cross").join(F.broadcast(pids), how="cross").join(F.broadcast(values), how="cross")


def _members(ids: str) -> Column:
    return F.array_join(F.transform(ids, lambda x: x.cast("string")), ",")


def value_sets(survivors: DataFrame, requests: DataFrame, coord: list[str]) -> DataFrame:
    """(coordination attributes, n, weight, members): one set per value."""
    ids = F.array_sort(F.collect_list("qid"))
    weighed = survivors.join(requests.select("qid", "weight"), "qid")
    return weighed.groupBy(*coord).agg(F.count("*").alias("n"), F.sum("weight").alias("weight"), ids.alias("ids")).select(
        *coord, "n", "weight", _members("ids").alias("members"), "ids"
    )


def assign(best: DataFrame, requests: DataFrame, data: DataFrame, key: Key, coord: list[str]) -> DataFrame:
    """(user, key): for each member, by the user of its request, the least key that fits its own constants at the chosen value."""
    members = best.select(*coord, F.explode("ids").alias("qid")).join(signatures(requests), "qid").join(requests.select("qid", F.col("user").alias("__user")), "qid")
    near = data.join(F.broadcast(best.select(*coord)), coord, "left_semi")  # one value
    others = [k for k in keys(key) if k != "user"]
    out = None
    for mask in [r["mask"] for r in members.select("mask").distinct().collect()]:
        fixed = [a for a in mask.split(",") if a]
        some = members.where(F.col("mask") == mask).select("__user", *coord, *[F.element_at("own", F.lit(a)).alias(f"__{a}_") for a in fixed])
        rows = near.select(*dict.fromkeys([*others, *coord]), *[F.col(a).cast("string").alias(f"__{a}_") for a in fixed])
        least = some.join(rows, [*coord, *[f"__{a}_" for a in fixed]]).groupBy("__user").agg(F.min(F.struct(*others)).alias("k"))
        part = least.select(F.col("__user").alias("user"), "k.*")
        out = part if out is None else out.unionByName(part)
    return out if out is not None else members.select(F.col("__user").alias("user"), *[F.lit(None).cast(data.schema[k].dataType).alias(k) for k in others]).where("false")


def consistent_coordinate(
    requests: DataFrame, data: DataFrame, key: Key, coord: list[str], friends: DataFrame, select: Selection | None = None, mode: str = "auto", allow_self: bool = True
) -> Consistent:
    """The whole algorithm, by ``bits`` unless ``mode`` names another cleaning. Requests with ``same_tuple`` make the key a coordination attribute. Requests that break a rule of ``validate_requests`` are refused."""
    requests = keep(requests)
    refuse(requests, data.columns)
    groups = None
    if "group" in friends.columns:
        friends = keep(friends.distinct())
        groups = Groups(friends, requests) if mode == "auto" and one_any(requests) else None
    if requests.where("same_tuple").limit(1).count():
        coord = [*coord, *[k for k in keys(key) if k not in coord]]
    if "group" not in friends.columns:
        friends = keep(friends)  # asked for by bodies and by the graph
    able = keep(befriended(requests, friends))
    told = signatures(able).select("qid", "sig")
    lead = told.groupBy("sig").agg(F.min("qid").alias("sig_id"))
    lists = keep(option_lists(able, data, coord).join(lead, "sig").select("sig_id", *coord))
    signed = keep(told.join(lead, "sig").join(lists.select("sig_id").distinct(), "sig_id", "left_semi").select("qid", "sig_id"))
    edges = pruned_graph(requests, pairs(friends) if "group" in friends.columns else friends, signed, allow_self)
    edges = edges if groups else cut(edges)  # by groups nothing needs them
    by_value = keep(lists.groupBy(*coord).agg(F.sort_array(F.collect_set("sig_id")).alias("sigs")))
    shapes = keep(_numbered(by_value.select("sigs").distinct()))
    patterns = keep(by_value.join(shapes, "sigs").select(*coord, "pid"))
    select, bits, held = select or largest(), None, None
    told = _listed(shapes) if groups is None and (mode == "bits" or (mode == "auto" and edges.count() <= EDGES_IN_TASK)) else None
    if told is not None:
        bits = Bits(signed, edges, requests, told)
        per = keep(bits.sizes())
        some = per if select.must is None else per.join(bits.holding(select.must), "pid", "left_semi")
        chosen = cut(Selection(select.score).pick(patterns.join(some, "pid"), coord))  # one row
        left = bits.blocks([r["pid"] for r in chosen.select("pid").collect()]).groupBy("pid").agg(F.array_sort(F.flatten(F.collect_list("ids"))).alias("ids"))
        best = cut(chosen.join(left, "pid").select(*coord, "n", "weight", _members("ids").alias("members"), "ids"))
    else:
        nodes = keep(shapes.select("pid", F.explode("sigs").alias("sig_id")).join(signed, "sig_id").select("pid", "qid"))
        held = keep(groups.left(nodes) if groups else clean(nodes, edges, requests, ["pid"], "auto" if mode == "bits" else mode))
        per = keep(held.join(requests.select("qid", "weight"), "qid").groupBy("pid").agg(F.count("*").alias("n"), F.sum("weight").alias("weight")))
        some = per if select.must is None else per.join(held.where(F.col("qid") == select.must).select("pid"), "pid", "left_semi")
        chosen = cut(Selection(select.score).pick(patterns.join(some, "pid"), coord))  # one row
        left = held.join(F.broadcast(chosen.select("pid")), "pid", "left_semi").groupBy("pid").agg(F.array_sort(F.collect_list("qid")).alias("ids"))
        best = cut(chosen.join(left, "pid").select(*coord, "n", "weight", _members("ids").alias("members"), "ids"))
    return Consistent(coord, lists, signed, patterns, shapes, edges, requests, per, bits, held, best, assign(best, requests, data, key, coord), groups=groups)


def exists_set(requests: DataFrame, data: DataFrame, key: Key, coord: list[str], friends: DataFrame) -> bool:
    """The decision problem for consistent requests."""
    return not consistent_coordinate(requests, data, key, coord, friends).best.isEmpty()


def cleaning_rounds(vq: DataFrame, edges: DataFrame, requests: DataFrame, coord: list[str]) -> DataFrame:
    """(round, removed): requests that fall out of their values in each round of cleaning, up to the last with any."""
    left, k, out = keep(vq.select(*coord, "qid")), 0, None
    need = needs(requests)
    while True:
        have = subgraphs(left, edges, coord).groupBy(*coord, F.col("src").alias("qid"), "kind").agg(F.countDistinct("dst").alias("have"))
        short = left.join(need, "qid").join(have, [*coord, "qid", "kind"], "left").where("coalesce(have, 0) < need").select(*coord, "qid").distinct()
        short = cut(short)
        row = short.agg(F.lit(k + 1).alias("round"), F.count("*").alias("removed")).where("removed > 0")
        out = row if out is None else out.unionByName(row)
        if short.isEmpty():
            return out
        left, k = keep(left.join(short, [*coord, "qid"], "left_anti")), k + 1


def largest_with_early_stop(vq: DataFrame, edges: DataFrame, requests: DataFrame, coord: list[str], at_least: int = 256) -> tuple[DataFrame, int]:
    """The largest set (least value on ties) and how many values were cleaned for it.

    Values are taken in descending size of their uncleaned graphs, ``at_least`` of them at a time, until no later one can hold a larger set or an
    equal one that would win the tie: a set cannot outgrow its graph.
    """
    sizes = keep(vq.groupBy(*coord).agg(F.count("*").alias("__n")))
    steps = sizes.groupBy("__n").agg(F.count("*").alias("values")).orderBy(F.col("__n").desc()).collect()  # at most one row per request
    best, cleaned, k = None, 0, 0
    while k < len(steps):
        top, took = steps[k]["__n"], 0
        while k < len(steps) and took < at_least:
            took += steps[k]["values"]
            low = steps[k]["__n"]
            k += 1
        some = vq.join(sizes.where(F.col("__n").between(low, top)).select(*coord), coord, "left_semi")
        sets = value_sets(clean(some, edges, requests, coord), requests, coord)
        both = sets if best is None else best.unionByName(sets)
        best, cleaned = cut(largest().pick(both, coord)), cleaned + took
        found = best.first()
        if found and k < len(steps) and found["n"] > steps[k]["__n"]:
            break
    return best if best is not None else value_sets(vq.select(*coord, "qid"), requests, coord), cleaned


def call_counts(requests: DataFrame, best: DataFrame) -> DataFrame:
    """Database queries that one-at-a-time processing issues: option lists, friend lists, final look-ups."""
    n = requests.agg(F.count("*").alias("options"), F.count_if(F.size("any_friend") > 0).alias("friends"))
    return n.join(F.broadcast(best.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("final"))), how="cross")


def pack_values(run: Consistent, requests: DataFrame, limit: int | None = None) -> tuple[DataFrame, DataFrame]:
    """Greedy packing of disjoint users over values: the best set, then the best of what remains after its users, and so on.

    Gives the places and the remainder: (coordination attributes, qid) of the users that a further place could still take. Without
    a limit the packing ends when no set is left, so the remainder is empty; a limit asks for the first places only. Users that no later place
    can hold are dropped as soon as they fall out, since the greatest set of fewer users lies in that of more.
    """
    out, k, alive = None, 0, keep(run.cleaned.select("pid", "qid"))
    while not alive.isEmpty() and (limit is None or k < limit):
        per = alive.groupBy("pid").agg(F.count("*").alias("n"))
        chosen = cut(largest().pick(run.patterns.join(per, "pid"), run.coord))  # one row
        used = alive.join(F.broadcast(chosen.select("pid")), "pid", "left_semi").select("qid")
        ids = used.agg(F.array_sort(F.collect_list("qid")).alias("ids"))
        picked = chosen.join(ids, how="cross").select(F.lit(k).alias("place"), *run.coord, "n", _members("ids").alias("members"))
        out = cut(picked if out is None else out.unionByName(picked))
        rest = alive.join(used, "qid", "left_anti")
        alive = keep(run.groups.left(rest) if run.groups else clean(rest, run.edges, requests, ["pid"]))
        k += 1
    empty = run.best.select(F.lit(0).alias("place"), *run.coord, "n", "members").where("false")
    return out if out is not None else empty, run.patterns.join(alive, "pid").select(*run.coord, "qid")


def joined_relation(left: DataFrame, right: DataFrame, on: list[str] | Column) -> DataFrame:
    """One data relation from two, where the coordination attributes come from both."""
    return left.join(right, on)


def joined_coordinate(
    requests: DataFrame, left: DataFrame, right: DataFrame, on: list[str], key: Key, coord: list[str], friends: DataFrame, select: Selection | None = None
) -> Consistent:
    """``consistent_coordinate`` over the join of two relations.

    Where requests fix attributes of the left one only, and the coordination attributes are some of the left, the joined ones among them, and then some of
    the right, every right row of a left value has that value's set. So left values are coordinated, and right ones joined to what is asked for; the
    best set takes the least. Otherwise the relations are joined first.
    """
    others = [c for c in right.columns if c not in on]
    mine, theirs = [c for c in coord if c not in others], [c for c in coord if c in others]
    fixes = F.exists(F.map_keys("own"), lambda k: k.isin(others)) if others else F.lit(False)
    if not set(on) <= set(mine) or coord != mine + theirs or not requests.where(fixes | F.col("same_tuple")).isEmpty():
        return consistent_coordinate(requests, joined_relation(left, right, on), key, coord, friends, select)
    near = left.join(right.select(*on).distinct(), on, "left_semi")
    run = consistent_coordinate(requests, near, tuple(k for k in keys(key) if k not in others) or mine[0], mine, friends, select)
    values = right.select(*on, *theirs).distinct()
    least = values.groupBy(*on).agg(F.min(F.struct(*theirs)).alias("__m")).select(*on, "__m.*") if theirs else values
    best = cut(run.best.join(least, on).select(*coord, "n", "weight", "members", "ids"))
    here = joined_relation(left.join(F.broadcast(best.select(*mine)), mine, "left_semi"), right.join(F.broadcast(best.select(*on, *theirs)), [*on, *theirs], "left_semi"), on)
    lists, patterns = run.lists.join(values, on).select("sig_id", *coord), run.patterns.join(values, on).select(*coord, "pid")
    return replace(run, coord=coord, lists=lists, patterns=patterns, best=best, assignment=assign(best, requests, here, key, coord))
