"""Entangled queries: schemas, builder, text form, validation and the exploded atom table.

A query has postconditions (atoms that other queries' heads must supply), heads (answers it supplies) and a body over database
relations. Terms are variables (scoped to their query) or typed constants in one canonical string form, ``type:value``.
"""

from __future__ import annotations

import datetime as dt
import re
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

TERM = "struct<var:string,const:string>"
ATOM = f"struct<rel:string,terms:array<{TERM}>>"
EQ = f"qid long, owner string, weight double, arrived timestamp, post array<{ATOM}>, head array<{ATOM}>, body array<{ATOM}>"
INTEGRAL = ("tinyint", "smallint", "int", "bigint")


@dataclass(frozen=True)
class Var:
    name: str


def constant(value) -> str:
    """Canonical typed form of a constant."""
    if value is None:
        raise ValueError("a null is no constant")
    if isinstance(value, bool):
        return f"boolean:{str(value).lower()}"
    if isinstance(value, int):
        return f"long:{value}"
    if isinstance(value, float):
        return f"double:{value!r}"
    if isinstance(value, dt.datetime):
        return f"timestamp:{value:%Y-%m-%d %H:%M:%S}"
    if isinstance(value, dt.date):
        return f"date:{value.isoformat()}"
    if isinstance(value, bytes):
        return f"binary:{value.hex()}"
    return f"string:{value}"


def encoded(c: Column, kind: str) -> Column:
    """The same canonical form of a column."""
    if kind in INTEGRAL:
        return F.concat(F.lit("long:"), c.cast("string"))
    if kind in ("float", "double"):
        return F.concat(F.lit("double:"), c.cast("double").cast("string"))
    if kind.startswith("timestamp"):
        return F.concat(F.lit("timestamp:"), F.date_format(c, "yyyy-MM-dd HH:mm:ss"))
    if kind == "binary":
        return F.concat(F.lit("binary:"), F.lower(F.hex(c)))
    return F.concat(F.lit(f"{kind}:"), c.cast("string"))


def atom(rel: str, *terms) -> tuple:
    """An atom; ``Var`` marks variables, everything else is a constant."""
    return rel, [(t.name, None) if isinstance(t, Var) else (None, constant(t)) for t in terms]


@dataclass
class Entangled:
    """Builder: ``Entangled(1).given(post...).offer(head...).where(body...)``."""

    qid: int
    owner: str = ""
    weight: float = 0.0
    arrived: dt.datetime | None = None
    post: list = field(default_factory=list)
    head: list = field(default_factory=list)
    body: list = field(default_factory=list)

    def given(self, *atoms) -> Entangled:
        self.post += atoms
        return self

    def offer(self, *atoms) -> Entangled:
        self.head += atoms
        return self

    def where(self, *atoms) -> Entangled:
        self.body += atoms
        return self

    def row(self) -> tuple:
        return self.qid, self.owner, self.weight, self.arrived, self.post, self.head, self.body


def frame(spark: SparkSession, queries: list[Entangled]) -> DataFrame:
    return spark.createDataFrame([q.row() for q in queries], EQ)


ATOM_TEXT = re.compile(r"\s*([A-Za-z_]\w*)\s*\(([^()]*)\)\s*(?:,|$)")


def parse_atoms(text: str) -> list:
    out, at = [], 0
    text = text.strip()
    while at < len(text):
        m = ATOM_TEXT.match(text, at)
        if not m:
            raise ValueError(f"no atom at: {text[at:at + 30]!r}")
        terms = []
        for t in filter(None, (x.strip() for x in re.findall(r"'[^']*'|[^,]+", m[2]))):
            if t[0] == "'":
                terms.append(t.strip("'"))
            elif re.fullmatch(r"-?\d+", t):
                terms.append(int(t))
            else:
                terms.append(Var(t))
        out.append(atom(m[1], *terms))
        at = m.end()
    return out


def parse_entangled(text: str, qid: int) -> Entangled:
    """``head(..) if post(..) from body(..)``; quoted strings and integers are constants, names are variables; if and from are optional."""
    m = re.fullmatch(r"(.*?)(?:\bif\b(.*?))?(?:\bfrom\b(.*))?", text.strip(), re.S)
    return Entangled(qid).offer(*parse_atoms(m[1])).given(*parse_atoms(m[2] or "")).where(*parse_atoms(m[3] or ""))


def explode_atoms(eqs: DataFrame) -> DataFrame:
    """(qid, role, pos, rel, arity, mask, terms): mask has bit i set where term i is a constant."""
    out = None
    for role in ("post", "head", "body"):
        a = eqs.select("qid", F.lit(role).alias("role"), F.posexplode(role).alias("pos", "a"))
        out = a if out is None else out.unionByName(a)
    mask = F.aggregate(F.transform("a.terms", lambda t, i: F.when(t["const"].isNotNull(), F.call_function("shiftleft", F.lit(1).cast("long"), i)).otherwise(F.lit(0).cast("long"))), F.lit(0).cast("long"), lambda x, y: x + y)
    return out.select("qid", "role", "pos", F.col("a.rel").alias("rel"), F.size("a.terms").alias("arity"), mask.alias("mask"), F.col("a.terms").alias("terms"))


def validate(eqs: DataFrame, catalog: dict[str, DataFrame]) -> DataFrame:
    """Violations (rule, qid, detail): body relations unknown or of another arity, answer relations in the schema, duplicate ids."""
    spark = eqs.sparkSession
    known = spark.createDataFrame([(r, len(df.columns)) for r, df in catalog.items()], "rel string, columns int")
    a = explode_atoms(eqs).join(F.broadcast(known), "rel", "left")
    rules = {
        "unknown_body_relation": "role = 'body' and columns is null",
        "body_arity": "role = 'body' and columns <> arity",
        "answer_relation_in_schema": "role <> 'body' and columns is not null",
    }
    out = eqs.groupBy("qid").count().where("count > 1").select(F.lit("duplicate_qid").alias("rule"), "qid", F.lit("").alias("detail"))
    for rule, where in rules.items():
        out = out.unionByName(a.where(where).select(F.lit(rule).alias("rule"), "qid", F.col("rel").alias("detail")))
    loose = a.select("qid", "role", F.explode("terms").alias("t")).where("t.var is not null")
    bound = loose.where("role in ('body', 'post')").select("qid", "t.var").distinct()
    free = loose.where("role = 'head'").select("qid", "t.var").distinct().join(bound, ["qid", "var"], "left_anti")
    return out.unionByName(free.select(F.lit("head_variable_unbound").alias("rule"), "qid", F.col("var").alias("detail")))
