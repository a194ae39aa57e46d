"""Unifying groups of queries, combining their bodies, and grounding the combined queries in batches.

A combined query is split into parts that share no variable (each is an independent existence test), and every
part is reduced to a template (its shape with constants numbered) and its constants. Equal parts of different sets are grounded
once; parts with one template are grounded in one join of a constants table with the relations. The number of jobs is
the number of templates, not of queries.
"""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from concord.model import INTEGRAL, encoded


class Classes:
    """Most general unifier as union-find over variables and constants; a class with two constants is a conflict."""

    def __init__(self):
        self.up: dict = {}
        self.value: dict = {}
        self.conflict = False

    def find(self, t):
        root = t
        while (nxt := self.up.get(root, root)) != root:
            root = nxt
        while self.up.get(t, t) != root:
            self.up[t], t = root, self.up[t]
        return root

    def term(self, qid: int, t: tuple) -> tuple:
        var, const = t
        return ("v", qid, var) if var is not None else ("c", const)

    def equate(self, a: tuple, b: tuple) -> None:
        a, b = self.find(a), self.find(b)
        if a == b:
            return
        x, y = self.constant(a), self.constant(b)
        if x is not None and y is not None and x != y:
            self.conflict = True
            return
        self.up[b] = a
        if x is None and y is not None:
            self.value[a] = y

    def constant(self, root: tuple):
        return root[1] if root[0] == "c" else self.value.get(root)


class Tightened(Exception):
    """An extension would bind or merge classes that were there before."""


class Growing:
    """One unifier for all reach sets of a component, grown from the sinks upwards.

    A node adds its own variables to the classes of what it reaches. As long as it neither binds nor merges older classes, the sets
    below keep their unifiers and sets beside it are not affected, so all share this structure; otherwise (``Tightened``) the extension is
    taken back. Unions are by size and without path compression, so that they can be undone.
    """

    def __init__(self):
        self.up: dict = {}
        self.value: dict = {}
        self.members: dict = {}
        self.old: set = set()
        self.trail: list = []

    def find(self, t):
        while (nxt := self.up.get(t, t)) != t:
            t = nxt
        return t

    def constant(self, root: tuple):
        return root[1] if root[0] == "c" else self.value.get(root)

    def equate(self, a: tuple, b: tuple) -> bool:
        """False on a conflict of constants."""
        a, b = self.find(a), self.find(b)
        if a == b:
            return True
        x, y = self.constant(a), self.constant(b)
        if x is not None and y is not None:
            return x == y
        if (a in self.old and (b in self.old or y is not None)) or (b in self.old and x is not None):
            raise Tightened
        if len(self.members.get(a, (a,))) < len(self.members.get(b, (b,))):
            a, b, x, y = b, a, y, x
        mine = self.members.setdefault(a, [a])
        self.trail.append((a, b, len(mine), x, a in self.old))
        self.up[b] = a
        mine += self.members.get(b, (b,))
        if x is None and y is not None:
            self.value[a] = y
        if b in self.old:
            self.old.add(a)
        return True

    def settle(self, variables) -> None:
        """What has been added is part of the sets above from now on."""
        self.old.update(map(self.find, variables))
        self.trail.clear()

    def undo(self) -> None:
        while self.trail:
            a, b, size, x, was_old = self.trail.pop()
            del self.up[b], self.members[a][size:]
            if x is None:
                self.value.pop(a, None)
            if not was_old:
                self.old.discard(a)


def linked_atoms(u: Growing, own: list, holding: dict, inside) -> list:
    """The atoms that share variables, directly or through others, with a node's own atoms; atoms are (node, relation, terms), ``holding``
    lists them by variable, ``inside`` tells the nodes of the set."""
    seen, out, stack, classes = set(), [], list(own), set()
    while stack:
        atom = stack.pop()
        if id(atom) in seen:
            continue
        seen.add(id(atom))
        out.append((atom[1], atom[2]))
        for t in atom[2]:
            root = u.find(t)
            if t[0] == "v" and root not in classes and u.constant(root) is None:
                classes.add(root)
                stack += [x for v in u.members.get(root, (root,)) for x in holding.get(v, ()) if x[0] in inside]
    return out


def unify(group: dict, links: list, keys: dict[str, list[int]]) -> tuple[Classes, list]:
    """Unifier and substituted body atoms (relation, class roots) of a group {qid: query}; links are (src, post_pos, dst, head_pos)."""
    u = Classes()
    for src, p, dst, h in links:
        for a, b in zip(group[src]["post"][p][1], group[dst]["head"][h][1], strict=True):
            u.equate(u.term(src, a), u.term(dst, b))
    atoms = [(rel, [u.term(q, t) for t in terms]) for q, e in group.items() for rel, terms in e["body"]]
    changed = bool(keys)
    while changed and not u.conflict:  # atoms with one key are one row: their other terms are equal
        changed, seen = False, {}
        for rel, terms in atoms:
            if rel in keys:
                key = (rel, *[u.find(terms[i]) if u.constant(u.find(terms[i])) is None else ("c", u.constant(u.find(terms[i]))) for i in keys[rel]])
                other = seen.setdefault(key, terms)
                for a, b in zip(terms, other, strict=True):
                    if u.find(a) != u.find(b):
                        u.equate(a, b)
                        changed = True
    return u, atoms


def parts(u: Classes | Growing, atoms: list) -> list[tuple[str, list[str], list]]:
    """(template, constants, class roots of the variables in template order) of each variable-disjoint part."""
    shaped = set()
    for rel, terms in atoms:
        roots = [u.find(t) for t in terms]
        shaped.add((rel, tuple(("c", c) if (c := u.constant(r)) is not None else r for r in roots)))
    listed = sorted(shaped, key=lambda a: (a[0], [str(t) for t in a[1]]))
    first: dict = {}  # variable -> an atom that holds it
    part = list(range(len(listed)))

    def top(i: int) -> int:
        while part[i] != i:
            part[i] = part[part[i]]
            i = part[i]
        return i

    for i, (_, terms) in enumerate(listed):
        for v in terms:
            if v[0] == "v":
                part[top(i)] = top(first.setdefault(v, i))
    groups: dict[int, list] = {}
    for i, atom in enumerate(listed):
        groups.setdefault(top(i), []).append(atom)
    out = []
    for g in groups.values():
        g.sort(key=lambda a: (a[0], [t[1] if t[0] == "c" else "" for t in a[1]]))
        names: dict = {}
        consts: list = []
        shape = []
        for rel, terms in g:
            line = []
            for t in terms:
                if t[0] == "c":
                    line.append(["c", len(consts)])
                    consts.append(t[1])
                else:
                    line.append(["v", names.setdefault(t, len(names))])
            shape.append([rel, line])
        out.append((json.dumps(shape), consts, list(names)))
    return out


def _decoded(c: Column, kind: str) -> Column:
    """A canonical constant as a value of a column type; null if it is of another type."""
    tag = "long" if kind in INTEGRAL else "double" if kind in ("float", "double") else "timestamp" if kind.startswith("timestamp") else kind
    body = F.substring(c, len(tag) + 2, 1 << 30)
    return F.when(F.startswith(c, F.lit(tag + ":")), (F.unhex(body) if tag == "binary" else body.cast(kind)))


def ground_batch(wanted: DataFrame, catalog: dict[str, DataFrame], choose: str = "min") -> DataFrame | None:
    """(template, constants, witness) of those distinct (template, constants) that have a grounding.

    The witness lists the variables' values in template order, in canonical form; ``min`` chooses the least row, ``any`` one.
    """
    out = None
    for row in wanted.select("template").distinct().collect():  # one per shape of a combined query
        shape = json.loads(row["template"])
        params = wanted.where(F.col("template") == row["template"]).select("constants").distinct()
        out_ = _ground(params, shape, catalog, choose).select(F.lit(row["template"]).alias("template"), "constants", "witness")
        out = out_ if out is None else out.unionByName(out_)
    return out


def _ground(params: DataFrame, shape: list, catalog: dict[str, DataFrame], choose: str) -> DataFrame:
    left = list(range(len(shape)))
    holders: dict[int, set[int]] = {}
    for i, (_, terms) in enumerate(shape):
        for t in terms:
            if t[0] == "v":
                holders.setdefault(t[1], set()).add(i)
    bound: dict[int, str] = {}
    kinds: dict[int, str] = {}
    plan, has_rows = params, False
    while left:
        # most constants first, then atoms that share variables with what is joined already
        k = max(left, key=lambda i: (any(t[0] == "v" and t[1] in bound for t in shape[i][1]), sum(t[0] == "c" for t in shape[i][1])))
        left.remove(k)
        rel, terms = shape[k]
        data = catalog[rel]
        types = [data.schema[c].dataType.simpleString() for c in data.columns]
        if len(types) != len(terms):
            raise ValueError(f"{rel} has {len(types)} columns, an atom names {len(terms)}")
        first: dict[int, int] = {}
        same = None
        for i, t in enumerate(terms):
            if t[0] == "v":
                if t[1] in first:
                    eq = data[data.columns[i]] == data[data.columns[first[t[1]]]]
                    same = eq if same is None else same & eq
                first.setdefault(t[1], i)
        rows = data.where(same) if same is not None else data
        use = [(i, t) for i, t in enumerate(terms) if t[0] == "c" or first[t[1]] == i]
        rows = rows.select(*[F.col(data.columns[i]).alias(f"r{k}_{i}") for i, _ in use])
        # variables of this atom alone are chosen within it: with the others fixed, the least row has the least of them, so joins don't multiply rows
        alone = sorted((t[1], f"r{k}_{i}") for i, t in use if t[0] == "v" and len(holders[t[1]]) == 1)
        if alone and len(shape) > 1:
            private = [name for _, name in alone]
            least = rows.groupBy(*[c for c in rows.columns if c not in private]).agg(F.min(F.struct(*private)).alias("__m")).where("__m is not null")
            rows = least.select("*", "__m.*").drop("__m")
        on = None
        fresh = {}
        for i, t in use:
            col = F.col(f"r{k}_{i}")
            if t[0] == "c":
                eq = col == _decoded(F.get("constants", t[1]), types[i])
            elif t[1] in bound:
                eq = col == F.col(bound[t[1]])
            else:
                fresh[t[1]] = (f"r{k}_{i}", types[i])
                continue
            on = eq if on is None else on & eq
        if on is None and not has_rows:
            plan = rows.join(F.broadcast(plan), how="cross")  # no constants at all: one row of parameters
        else:
            plan = plan.join(rows, on)
        for v, (name, kind) in fresh.items():
            bound[v], kinds[v] = name, kind
        has_rows = True
    names = [bound[v] for v in sorted(bound)]
    if not names:
        return plan.select("constants").distinct().withColumn("witness", F.array().cast("array<string>"))
    best = F.min(F.struct(*names)) if choose == "min" else F.any_value(F.struct(*names))
    one = plan.groupBy("constants").agg(best.alias("w"))
    return one.select("constants", F.array(*[encoded(F.col(f"w.{bound[v]}"), kinds[v]) for v in sorted(bound)]).alias("witness"))
