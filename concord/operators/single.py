"""Single-connected query sets: at most one postcondition each, and at most one simple path between two queries.

Such sets may be unsafe. Every coordinating set contains a query without postcondition or a simple cycle that coordinates by itself, so
those are tested first, and each query that reaches one by its unique path gives one larger set. One combined query per set.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from concord.model import Entangled, encoded
from concord.operators import ground as G
from concord.operators import scc as S
from concord.operators.graph import weak_components
from concord.operators.select import Selection, largest
from concord.operators.unify import extended_graph, unsafe_queries
from concord.runtime import cut, keep

#: Rows a relation may have where the exhaustive search decides.
EXACT_ROWS = 200


def one_path(nodes: list, out: dict) -> bool:
    """Whether no pair of nodes has two vertex-simple paths (parallel edges count)."""
    for root in nodes:
        seen: dict = {}
        stack = [(root, (root,))]
        while stack:
            node, path = stack.pop()
            for nxt in out.get(node, ()):
                if nxt == root:
                    key = ("back", root)
                elif nxt in path:
                    continue
                else:
                    key = nxt
                if key in seen and seen[key] != (node, path):
                    return False
                seen[key] = (node, path)
                if key == nxt:
                    stack.append((nxt, (*path, nxt)))
    return True


def is_single_connected(eqs: DataFrame, ext: DataFrame | None = None) -> DataFrame:
    """(comp_id, single_post, one_path) per weak component."""
    ext = extended_graph(eqs) if ext is None else ext
    rows = S.component_rows(eqs, ext, cut(weak_components(ext)))

    def run(pdf):
        loaded, links = S._load(pdf)
        out = {q: [d for _, d, _ in links[q]] for q in loaded}
        return pd.DataFrame([(int(pdf["comp_id"].iloc[0]), all(len(e["post"]) <= 1 for e in loaded.values()), one_path(sorted(loaded), out))], columns=["comp_id", "single_post", "one_path"])

    return rows.groupBy("comp_id").applyInPandas(run, "comp_id long, single_post boolean, one_path boolean")


def _candidates(eqs: dict, links: dict) -> list[tuple[list, list]]:
    """(members, links used) of each base and of each closed path to one."""
    out = {q: sorted(links[q], key=lambda x: (x[1], x[2])) for q in eqs}
    into: dict = {}
    for q in eqs:
        for p, d, h in out[q]:
            into.setdefault(d, []).append((q, p, d, h))
    bases: dict = {}
    for q in sorted(eqs):
        if not eqs[q]["post"]:
            bases[(q,)] = ([q], [])
        for p, d, h in out[q]:  # the cycle that closes over this edge: the unique path from d back to q
            stack = [(d, [d], [(q, p, d, h)])]
            while stack:
                node, path, used = stack.pop()
                if node == q:
                    bases.setdefault(tuple(sorted(path)), (sorted(path), used))
                    break
                for p2, d2, h2 in out[node]:
                    if d2 not in path:
                        stack.append((d2, [*path, d2], [*used, (node, p2, d2, h2)]))
    made = {}
    for members, used in bases.values():
        queue = [(set(members), used, m) for m in members]
        made.setdefault(tuple(members), used)
        while queue:
            have, via, at = queue.pop()
            for link in into.get(at, ()):
                if link[0] not in have:
                    grown = have | {link[0]}
                    key = tuple(sorted(grown))
                    if key not in made:
                        made[key] = [*via, link]
                        queue.append((grown, made[key], link[0]))
    return [(list(k), v) for k, v in made.items()]


def single_sets(rows: DataFrame) -> DataFrame:
    """The sets to test in single-connected components, numbered below zero; other components are refused."""

    def run(pdf):
        loaded, links = S._load(pdf)
        comp = int(pdf["comp_id"].iloc[0])
        if any(len(e["post"]) > 1 for e in loaded.values()):
            raise ValueError(f"component {comp}: a query has several postconditions")
        if not one_path(sorted(loaded), {q: [d for _, d, _ in links[q]] for q in loaded}):
            raise ValueError(f"component {comp}: two queries are joined by several paths")
        out = []
        for k, (ids, used) in enumerate(sorted(_candidates(loaded, links))):
            u, atoms = G.unify({q: loaded[q] for q in ids}, used, {})
            found = [] if u.conflict else G.parts(u, atoms)
            out.append(S.node_row(comp, -(comp << 20) - k - 1, 0, loaded, ids, [], not u.conflict, len(used), found, used))
        return pd.DataFrame(out, columns=S.COLUMNS)

    return rows.groupBy("comp_id").applyInPandas(run, S.NODE)


def single_connected_coordinate(eqs: DataFrame, catalog: dict[str, DataFrame], select: Selection | None = None, choose: str = "min") -> S.Coordination:
    """All tested sets with their status, and the best."""
    eqs = keep(eqs)
    ext = keep(extended_graph(eqs))
    rows = keep(S.component_rows(eqs, ext, cut(weak_components(ext))))
    rated = S.grounded(keep(single_sets(rows)), catalog, choose, inherit=False)
    best = cut((select or largest()).pick(rated.where("status = 'ok'"), ["n", "ids"]))
    return S.Coordination(rated, best, rows, catalog, {}, choose)


def exists_coordination(eqs: DataFrame, catalog: dict[str, DataFrame]) -> tuple[bool, str]:
    """The decision problem: whether some set coordinates, and which algorithm has decided: ``safe``, ``single_connected`` or,
    for at most 14 queries outside these classes over relations of at most ``EXACT_ROWS`` rows, ``exact``. Larger ones are refused."""
    eqs = keep(eqs)
    ext = keep(extended_graph(eqs))
    if unsafe_queries(ext).isEmpty():
        return not S.scc_coordinate(eqs, catalog, stop_at_first=True).best.isEmpty(), "safe"
    if is_single_connected(eqs, ext).where("not (single_post and one_path)").isEmpty():
        return not single_connected_coordinate(eqs, catalog).best.isEmpty(), "single_connected"
    from concord.functions.exact import exact_max

    few = eqs.limit(15).collect()
    small = {rel: df.limit(EXACT_ROWS + 1).select(F.array(*[encoded(F.col(c), k) for c, k in df.dtypes])).collect() for rel, df in catalog.items()}
    if len(few) > 14 or any(len(r) > EXACT_ROWS for r in small.values()):
        raise ValueError("unsafe and not single-connected: only small sets can be decided")
    terms = lambda atoms: [(a["rel"], [(t["var"], t["const"]) for t in a["terms"]]) for a in atoms]
    queries = [Entangled(r["qid"], post=terms(r["post"]), head=terms(r["head"]), body=terms(r["body"])) for r in few]
    return bool(exact_max(queries, {rel: {tuple(r[0]) for r in rows} for rel, rows in small.items()})), "exact"
