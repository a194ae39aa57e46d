"""Which postconditions can be met by which heads: the extended coordination graph.

Two atoms unify if they have the same relation and arity and no position with two different constants. As a join this is not
an equality, but it becomes one per pair of constant patterns: a postcondition with constants at P meets a head with
constants at H exactly if they agree on the positions of both. Patterns are few, so posts are expanded over
the head patterns of their relation, heads over the post patterns, and both are hash-joined on the pattern pair and
the shared constants.
"""

from __future__ import annotations

import json

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from concord.model import explode_atoms


def _shared(mask: str):
    """The constants of ``terms`` at the positions of a mask, as one exact key."""
    return F.to_json(F.filter(F.transform("terms", lambda t, i: F.when(F.call_function("shiftright", F.col(mask), i).bitwiseAND(F.lit(1)) == 1, t["const"])), lambda c: c.isNotNull()))


def terms_unify(post: list[dict], head: list[dict]) -> bool:
    """Whether two lists of terms have a unifier; the variables of the two are apart."""
    up: dict = {}

    def find(t):
        while t in up:
            t = up[t]
        return t

    for a, b in zip(post, head, strict=True):
        x, y = (find(("c", t["const"]) if t.get("const") is not None else (side, t["var"])) for side, t in (("p", a), ("h", b)))
        if x != y:
            if x[0] == "c" and y[0] == "c":
                return False
            up[y if x[0] == "c" else x] = x if x[0] == "c" else y
    return True


def _unify_udf():
    @F.pandas_udf("boolean")
    def told(post: pd.Series, head: pd.Series) -> pd.Series:
        return pd.Series([terms_unify(json.loads(a), json.loads(b)) for a, b in zip(post, head, strict=True)], dtype=bool)

    return told


def unifiable_pairs(posts: DataFrame, heads: DataFrame, join: str = "mask", mode: str = "positional") -> DataFrame:
    """(src, post_pos, dst, head_pos). ``join='nested'`` compares all pairs (an ablation for small inputs);
    ``mode='mgu'`` also demands that repeated variables can be equal."""
    p = posts.select(F.col("qid").alias("src"), F.col("pos").alias("post_pos"), "rel", "arity", F.col("mask").alias("pm"), "terms")
    h = heads.select(F.col("qid").alias("dst"), F.col("pos").alias("head_pos"), "rel", "arity", F.col("mask").alias("hm"), "terms")
    if join == "nested":
        h = h.withColumnRenamed("terms", "hterms")
        agree = F.forall(F.arrays_zip("terms", "hterms"), lambda z: z["terms"]["const"].isNull() | z["hterms"]["const"].isNull() | (z["terms"]["const"] == z["hterms"]["const"]))
        pairs = p.join(h, ["rel", "arity"]).where(agree)
    else:
        patterns = p.select("rel", "arity", "pm").distinct().join(h.select("rel", "arity", "hm").distinct(), ["rel", "arity"]).withColumn("both", F.col("pm").bitwiseAND(F.col("hm")))
        left = p.join(patterns, ["rel", "arity", "pm"]).withColumn("key", _shared("both"))
        right = h.join(patterns, ["rel", "arity", "hm"]).withColumn("key", _shared("both")).withColumnRenamed("terms", "hterms")
        pairs = left.join(right, ["rel", "arity", "pm", "hm", "both", "key"])
    if mode == "mgu":
        names = lambda t: F.filter(F.transform(t, lambda x: x["var"]), lambda v: v.isNotNull())
        repeats = lambda t: F.size(names(t)) > F.size(F.array_distinct(names(t)))
        again = repeats("terms") | repeats("hterms")
        # agreeing constants decide, unless a variable repeats: only those pairs go through a union-find
        odd = pairs.where(again).where(_unify_udf()(F.to_json("terms"), F.to_json("hterms")))
        pairs = pairs.where(~again).unionByName(odd)
    return pairs.select("src", "post_pos", "dst", "head_pos")


def extended_graph(eqs: DataFrame, join: str = "mask", mode: str = "positional") -> DataFrame:
    atoms = explode_atoms(eqs)
    return unifiable_pairs(atoms.where("role = 'post'"), atoms.where("role = 'head'"), join, mode)


def coordination_graph(ext: DataFrame) -> DataFrame:
    return ext.select("src", "dst").distinct()


def safety(ext: DataFrame, eqs: DataFrame) -> DataFrame:
    """(qid, is_safe, offending_post): the least postcondition with more than one matching head."""
    many = ext.groupBy("src", "post_pos").agg(F.count("*").alias("n")).where("n > 1").groupBy("src").agg(F.min("post_pos").alias("offending_post"))
    return eqs.select("qid").join(many, F.col("qid") == F.col("src"), "left").select("qid", F.col("src").isNull().alias("is_safe"), "offending_post")


def unsafe_queries(ext: DataFrame) -> DataFrame:
    return ext.groupBy("src", "post_pos").agg(F.count("*").alias("n")).where("n > 1").select(F.col("src").alias("qid")).distinct()
