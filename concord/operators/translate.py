"""Between consistent requests and entangled queries, consistency tests, and pre-coordination."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from concord.operators.consistent import _with_rel
from concord.sources.entangled import made, none


def to_entangled(requests: DataFrame, attributes: dict[str, str], key: str, coord: list[str]) -> DataFrame:
    """One entangled query per request over relations ``data(key, attributes...)`` and ``friends(user, friend)``.

    attributes: name -> type, in column order without the key. Partners share the terms of the coordination attributes and have fresh
    variables elsewhere. Asks of more than one friend have no such form and are refused.
    """
    many = requests.where(F.exists("any_friend", lambda a: a["k"] > 1)).select("qid").limit(5).collect()
    if many:
        raise ValueError(f"asks of several friends cannot be written as entangled queries: {[r['qid'] for r in many]}")
    null = F.lit(None).cast("string")
    var = lambda n: F.struct(n.alias("var"), null.alias("const"))
    const = lambda x: F.struct(null.alias("var"), x.alias("const"))
    user = const(F.concat(F.lit("long:"), F.col("user").cast("string")))

    def own(a: str):
        given = F.element_at("own", F.lit(a))
        tag = "long" if attributes[a] in ("int", "bigint") else attributes[a]
        return F.when(given.isNotNull(), const(F.concat(F.lit(f"{tag}:"), given))).otherwise(var(F.lit(f"a_{a}")))

    partner = lambda i: [own(a) if a in coord else var(F.concat(F.lit(f"b_{a}_"), i.cast("string"))) for a in attributes]
    key_of = lambda i: F.when(F.col("same_tuple"), var(F.lit("x"))).otherwise(var(F.concat(F.lit("y"), i.cast("string"))))
    n_named = F.size("named")
    named_post = F.transform("named", lambda u, i: made("seat", key_of(i), const(F.concat(F.lit("long:"), u.cast("string")))))
    any_post = F.transform("any_friend", lambda a, i: made("seat", key_of(n_named + i), var(F.concat(F.lit("f"), i.cast("string")))))
    count = F.size("named") + F.size("any_friend")
    rows = F.transform(F.when(count > 0, F.sequence(F.lit(0), count - 1)).otherwise(F.array().cast("array<int>")), lambda i: made("data", key_of(i), *partner(i)))
    ties = F.transform("any_friend", lambda a, i: made("friends", user, var(F.concat(F.lit("f"), i.cast("string")))))
    body = F.concat(F.array(made("data", var(F.lit("x")), *[own(a) for a in attributes])), rows, ties)
    return requests.select(
        "qid", F.col("user").cast("string").alias("owner"), "weight", F.lit(None).cast("timestamp").alias("arrived"),
        F.concat(none(), named_post, any_post).alias("post"), F.array(made("seat", var(F.lit("x")), user)).alias("head"), body.alias("body"),
    )


def precoordinate(requests: DataFrame, friends: DataFrame) -> DataFrame:
    """The baseline that agrees beforehand: every ask of any friend becomes the least friend, by name. The set is then safe."""
    asks = requests.select("qid", "user", F.explode("any_friend").alias("a")).select("qid", "user", F.col("a.rel").alias("rel"))
    least = asks.join(_with_rel(friends), ["user", "rel"]).groupBy("qid", "rel").agg(F.min("friend").alias("friend")).groupBy("qid").agg(F.array_sort(F.collect_set("friend")).alias("fixed"), F.count("*").alias("met"))
    told = requests.join(least, "qid", "left").where(F.coalesce("met", F.lit(0)) == F.size(F.array_distinct(F.transform("any_friend", lambda a: a["rel"]))))
    return told.withColumn("named", F.concat("named", F.coalesce("fixed", F.array().cast("array<bigint>")))).withColumn("any_friend", F.array().cast(requests.schema["any_friend"].dataType)).select(*requests.columns)


def consistency(eqs: DataFrame, relation: str, attributes: list[str], coord: list[str]) -> DataFrame:
    """(qid, coordinating, non_coordinating, consistent) of queries in request form.

    The first atom over the relation is the user's own row, the others are partners'. Coordinating on A: all have equal
    terms at each attribute of A. Non-coordinating on the rest: all terms of partners there are different variables, and so is the user's own if it
    is one. The second is no negation of the first.
    """
    rows = F.transform(F.filter("body", lambda b: b["rel"] == relation), lambda b: F.slice(b["terms"], 2, len(attributes)))
    at = {a: i for i, a in enumerate(attributes)}
    column = lambda i: F.transform("rows", lambda r: F.get(r, i))

    def same(a: str):
        return F.size(F.array_distinct(column(at[a]))) <= 1

    def apart(a: str):
        mine, theirs = F.get(column(at[a]), 0), F.slice(column(at[a]), 2, 1 << 20)
        free = F.forall(theirs, lambda t: t["var"].isNotNull()) & (F.size(F.array_distinct(theirs)) == F.size(theirs))
        return free & (mine["var"].isNull() | ~F.array_contains(theirs, mine))

    rest = [a for a in attributes if a not in coord]
    every = lambda test, names: [test(a) for a in names] or [F.lit(True)]
    both = lambda tests: F.forall(F.array(*tests), lambda x: x)
    told = eqs.select("qid", rows.alias("rows")).select(
        "qid", both(every(same, coord)).alias("coordinating"), both(every(apart, coord)).alias("coord_apart"), both(every(apart, rest)).alias("rest_apart"),
    )
    return told.select("qid", "coordinating", F.col("coord_apart").alias("non_coordinating"), (F.col("coordinating") & F.col("rest_apart")).alias("consistent"))


def coordination_signature(eqs: DataFrame, relation: str, attributes: list[str]) -> DataFrame:
    """(qid, attributes): on which attributes each query coordinates; more than one signature in a set is the hard mixed case."""
    rows = F.transform(F.filter("body", lambda b: b["rel"] == relation), lambda b: F.slice(b["terms"], 2, len(attributes)))
    names = F.array(*[F.when(F.size(F.array_distinct(_column(i))) <= 1, F.lit(a)) for i, a in enumerate(attributes)])
    told = eqs.select("qid", rows.alias("rows"))
    return told.where(F.size("rows") > 1).select("qid", F.array_join(F.array_compact(names), ",").alias("attributes"))


def refuse_mixed(eqs: DataFrame, relation: str, attributes: list[str]) -> None:
    """Raises if the queries coordinate on different attributes: that case is as hard as the general one."""
    kinds = [r["attributes"] for r in coordination_signature(eqs, relation, attributes).select("attributes").distinct().limit(5).collect()]
    if len(kinds) > 1:
        raise ValueError(f"queries coordinate on different attributes: {sorted(kinds)}")


def _column(i: int):
    return F.transform("rows", lambda r: F.get(r, i))
