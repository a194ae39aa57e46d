"""Independent check of a coordinating set against its definition, and cost measures."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from concord.model import encoded


def verify_set(assignment: DataFrame, eqs: DataFrame, catalog: dict[str, DataFrame]) -> DataFrame:
    """Violations (rule, qid, detail) of (set_id, qid, var, val): unassigned variables, body atoms that are no row, postconditions without a head."""
    value = assignment.groupBy("set_id", "qid").agg(F.map_from_entries(F.collect_list(F.struct("var", "val"))).alias("h"))
    told = eqs.join(value, "qid")

    def grounded(role: str) -> DataFrame:
        g = told.select("set_id", "qid", "h", F.posexplode(role).alias("pos", "a"))
        terms = F.transform("a.terms", lambda t: F.coalesce(t["const"], F.element_at("h", t["var"])))
        return g.select("set_id", "qid", F.col("a.rel").alias("rel"), "pos", terms.alias("terms"))

    heads, posts, bodies = grounded("head"), grounded("post"), grounded("body")
    every = heads.unionByName(posts).unionByName(bodies)
    out = every.where(F.exists("terms", lambda t: t.isNull())).select(F.lit("unassigned").alias("rule"), "qid", F.col("rel").alias("detail")).distinct()
    for rel, data in catalog.items():
        rows = data.select(F.array(*[encoded(F.col(c), data.schema[c].dataType.simpleString()) for c in data.columns]).alias("terms"))
        lost = bodies.where(F.col("rel") == rel).join(rows, "terms", "left_anti")
        out = out.unionByName(lost.select(F.lit("body_not_in_data").alias("rule"), "qid", F.col("rel").alias("detail")))
    unmet = posts.join(heads.select("set_id", "rel", "terms").distinct(), ["set_id", "rel", "terms"], "left_anti")
    return out.unionByName(unmet.select(F.lit("postcondition_unmet").alias("rule"), "qid", F.col("rel").alias("detail")))


def cost_report(run) -> DataFrame:
    """(name, value): logical database queries, components, levels, unification steps, sizes and coverage of an SCC run."""
    n = run.nodes
    total = run.rows.count()
    one = n.agg(
        F.count("*").cast("double").alias("components"),
        (F.max("level") + 1).cast("double").alias("levels"),
        F.coalesce(F.max(F.when(F.col("status") == "ok", F.col("n"))), F.lit(0)).cast("double").alias("set_size"),
        F.count_if(F.col("status") == "ok").cast("double").alias("sets_found"),
        F.sum("steps").cast("double").alias("unify_steps"),
    )
    asked = run.database_queries().select(F.col("db_queries").cast("double").alias("db_queries"))
    row = one.join(F.broadcast(asked), how="cross").withColumn("queries", F.lit(float(total))).withColumn("coverage", F.col("set_size") / F.lit(float(max(total, 1))))
    return row.select(F.explode(F.create_map(*[x for c in row.columns for x in (F.lit(c), F.col(c))])).alias("name", "value"))


def timed(action) -> tuple[object, float]:
    """A result and the milliseconds its action took."""
    began = time.perf_counter()
    made = action()
    return made, (time.perf_counter() - began) * 1000


def fit(points: DataFrame, x: str, y: str) -> DataFrame:
    """(slope, intercept, r2) of a linear fit."""
    return points.agg(F.regr_slope(F.col(y), F.col(x)).alias("slope"), F.regr_intercept(F.col(y), F.col(x)).alias("intercept"), F.regr_r2(F.col(y), F.col(x)).alias("r2"))


def averaged(points: DataFrame, size: str, value: str) -> DataFrame:
    """Mean over repeated random graphs of a size."""
    return points.groupBy(size).agg(F.avg(value).alias("mean"), F.count("*").alias("graphs"))


def physical(df: DataFrame) -> dict[str, int]:
    """Operators of the physical plan by kind."""
    import re

    text = df._jdf.queryExecution().executedPlan().toString()
    return {k: len(re.findall(rf"\b{k}\b", text)) for k in ("Exchange", "SortMergeJoin", "BroadcastHashJoin", "HashAggregate", "BroadcastNestedLoopJoin", "CartesianProduct")}
