"""Exhaustive answers for tiny inputs: the reference that the algorithms are tested against."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations, product

from concord.model import Entangled
from concord.operators.ground import unify

Data = dict[str, set[tuple[str, ...]]]


def loaded(queries: list[Entangled]) -> dict[int, dict]:
    return {q.qid: {"post": q.post, "head": q.head, "body": q.body} for q in queries}


def grounds(atoms: list[tuple[str, list]], data: Data, bound: dict) -> bool:
    """Whether the atoms (relation, terms) can be mapped into the data; terms are ('c', value) or variables."""
    if not atoms:
        return True
    (rel, terms), rest = atoms[0], atoms[1:]
    for row in data.get(rel, ()):
        here = dict(bound)
        if len(row) == len(terms) and all((t[1] if t[0] == "c" else here.setdefault(t, x)) == x for t, x in zip(terms, row, strict=True)) and grounds(rest, data, here):
            return True
    return False


def _choices(eqs: dict[int, dict]) -> Iterator[list[tuple]]:
    """All ways to give every postcondition a head: lists of (src, post_pos, dst, head_pos)."""
    options = []
    for q, e in eqs.items():
        for p, (rel, terms) in enumerate(e["post"]):
            fits = [(q, p, d, h) for d, o in eqs.items() for h, (r, ts) in enumerate(o["head"]) if r == rel and len(ts) == len(terms) and all(a[1] is None or b[1] is None or a[1] == b[1] for a, b in zip(terms, ts, strict=True))]
            options.append(fits)
    yield from map(list, product(*options))


def coordinates(eqs: dict[int, dict], data: Data) -> bool:
    """Whether all these queries together are a coordinating set."""
    for links in _choices(eqs):
        u, atoms = unify(eqs, links, {})
        if not u.conflict:
            flat = [(rel, [("c", c) if (c := u.constant(r := u.find(t))) is not None else r for t in terms]) for rel, terms in atoms]
            if grounds(flat, data, {}):
                return True
    return False


def coordinating_sets(queries: list[Entangled], data: Data, limit: int = 14) -> list[tuple[int, ...]]:
    """Every coordinating set, by all subsets: exponential, refused beyond ``limit`` queries."""
    if len(queries) > limit:
        raise ValueError(f"{len(queries)} queries exceed {limit}")
    eqs = loaded(queries)
    return [s for n in range(1, len(eqs) + 1) for s in combinations(sorted(eqs), n) if coordinates({q: eqs[q] for q in s}, data)]


def exact_max(queries: list[Entangled], data: Data, limit: int = 14) -> tuple[int, ...]:
    """A maximum coordinating set, or an empty tuple; the least among the largest."""
    eqs = loaded(queries)
    if len(queries) > limit:
        raise ValueError(f"{len(queries)} queries exceed {limit}")
    for n in range(len(eqs), 0, -1):
        for s in combinations(sorted(eqs), n):
            if coordinates({q: eqs[q] for q in s}, data):
                return s
    return ()
