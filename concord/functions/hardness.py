"""Formulas as query sets: generators that show where coordination is hard, used as tests.

A formula is a list of clauses, a clause a list of non-zero integers: variable number, negative if negated.
"""

from __future__ import annotations

from itertools import product

from concord.model import Entangled, Var, atom

BITS = {"bit": {("long:0",), ("long:1",)}}


def satisfiable(formula: list[list[int]]) -> bool:
    """By truth table."""
    names = sorted({abs(x) for c in formula for x in c})
    return any(all(any((x > 0) == row[abs(x)] for x in c) for c in formula) for values in product((False, True), repeat=len(names)) for row in [dict(zip(names, values, strict=True))])


def as_unsafe_set(formula: list[list[int]]) -> list[Entangled]:
    """Queries that coordinate exactly if the formula is satisfiable.

    One query wants every clause met. One per variable offers a truth value for it and wants that query. One per literal wants its truth
    value and offers the clauses that the literal meets; clauses may be offered several times, which makes the set unsafe.
    """
    names = sorted({abs(x) for c in formula for x in c})
    out = [Entangled(1).offer(atom("all_met", 1)).given(*[atom("met", j, 1) for j in range(len(formula))])]
    for v in names:
        out.append(Entangled(len(out) + 1).offer(atom("truth", v, Var("x"))).given(atom("all_met", 1)).where(atom("bit", Var("x"))))
    for v in names:
        for literal, value in ((v, 1), (-v, 0)):
            mine = [j for j, c in enumerate(formula) if literal in c]
            if mine:
                out.append(Entangled(len(out) + 1).offer(*[atom("met", j, 1) for j in mine]).given(atom("truth", v, value)))
    return out


def as_safe_set(formula: list[list[int]]) -> list[Entangled]:
    """A safe set whose largest coordinating set has a member per clause and per variable exactly if the formula is satisfiable.

    A variable's query chooses its truth value. A clause has one query per literal; the t-th wants its literal true and
    the earlier ones false, so that at most one of a clause can take part.
    """
    names = sorted({abs(x) for c in formula for x in c})
    out = [Entangled(k + 1).offer(atom("truth", v, Var("x"))).where(atom("bit", Var("x"))) for k, v in enumerate(names)]
    for j, clause in enumerate(formula):
        for t, literal in enumerate(clause):
            wants = {abs(literal): int(literal > 0)}
            clash = False
            for earlier in clause[:t]:
                value = int(earlier < 0)
                clash |= wants.get(abs(earlier), value) != value
                wants[abs(earlier)] = value
            if not clash:
                out.append(Entangled(len(out) + 1).offer(atom("met", j, 1)).given(*[atom("truth", v, b) for v, b in sorted(wants.items())]))
    return out
