"""Workloads of entangled queries as DataFrames of the model's schema."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from concord.model import EQ, Entangled, Var, atom, frame, parse_entangled
from concord.sources import tables as T


def v(name: str) -> Column:
    return F.struct(F.lit(name).alias("var"), F.lit(None).cast("string").alias("const"))


def c(value: Column, kind: str) -> Column:
    return F.struct(F.lit(None).cast("string").alias("var"), F.concat(F.lit(f"{kind}:"), value.cast("string")).alias("const"))


def made(rel: str, *terms: Column) -> Column:
    return F.struct(F.lit(rel).alias("rel"), F.array(*terms).alias("terms"))


def none() -> Column:
    return F.array().cast(EQ.split("post ")[1].split(", head")[0])


def queries(df: DataFrame, post: Column, head: Column, body: Column, weight: Column | None = None) -> DataFrame:
    """Of a table with ``qid``: the given atoms per row."""
    return df.select(
        F.col("qid").cast("long").alias("qid"), F.col("qid").cast("string").alias("owner"), (weight if weight is not None else F.lit(0.0)).cast("double").alias("weight"),
        F.lit(None).cast("timestamp").alias("arrived"), post.alias("post"), head.alias("head"), body.alias("body"),
    )


def catalog(spark: SparkSession, d: str) -> dict[str, DataFrame]:
    return {"flights": T.flights(spark, d), "hotels": T.hotels(spark, d)}


def flight() -> list[Column]:
    return [v("x"), v("d"), v("t"), v("s"), v("a")]


def chain(spark: SparkSession, d: str, n: int, shared: bool = False, selective: bool = False) -> DataFrame:
    """List workload: each of n users asks the next, the last asks nobody; shared: all want one flight; selective: to the own nation."""
    users = T.customers(spark, d, n).join(F.broadcast(T.table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).withColumn("qid", F.col("c_custkey"))
    post = F.when(F.col("qid") < n - 1, F.array(made("seat", c(F.col("qid") + 1, "long"), v("x" if shared else "y")))).otherwise(none())
    place = c(F.col("n_name"), "string") if selective else v("d")
    return queries(users, post, F.array(made("seat", c(F.col("qid"), "long"), v("x"))), F.array(made("flights", v("x"), place, *flight()[2:])), F.col("c_acctbal"))


def network(spark: SparkSession, d: str, edges: DataFrame, n: int, selective: bool = False) -> DataFrame:
    """Each user asks its successors in a directed graph (src, dst) over 0..n-1, each for an own seat."""
    users = T.customers(spark, d, n).join(F.broadcast(T.table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).withColumn("qid", F.col("c_custkey"))
    asks = edges.distinct().groupBy(F.col("src").alias("qid")).agg(F.array_sort(F.collect_list("dst")).alias("to"))
    posts = F.transform(F.coalesce("to", F.array().cast("array<bigint>")), lambda t, i: F.struct(F.lit("seat").alias("rel"), F.array(c(t, "long"), F.struct(F.concat(F.lit("y"), i.cast("string")).alias("var"), F.lit(None).cast("string").alias("const"))).alias("terms")))
    hard = F.col("qid") % 50 == 7  # these want a flight that doesn't exist
    place = F.when(hard, c(F.lit("nowhere"), "string")).otherwise(v("d")) if selective else v("d")
    return queries(users.join(asks, "qid", "left"), posts, F.array(made("seat", c(F.col("qid"), "long"), v("x"))), F.array(made("flights", v("x"), place, *flight()[2:])), F.col("c_acctbal"))


def social(spark: SparkSession, d: str) -> DataFrame:
    """Event users, each asking its least co-active friend."""
    least = T.friends_coactive(spark, d, 10).groupBy(F.col("user").alias("qid")).agg(F.min("friend").alias("friend"))
    post = F.array(made("seat", c(F.col("friend"), "long"), v("y")))
    return queries(least, post, F.array(made("seat", c(F.col("qid"), "long"), v("x"))), F.array(made("flights", *flight())))


# ---------------------------------------------------------------- literal examples


def two_flyers(spark: SparkSession) -> tuple[DataFrame, dict]:
    texts = ["seat('u1',x) if seat('u2',x) from flights(x,'Z')", "seat('u2',y) from flights(y,'Z')"]
    return frame(spark, [parse_entangled(t, k + 1) for k, t in enumerate(texts)]), {"flights": spark.createDataFrame([(101, "Z"), (102, "Q")], "id long, city string")}


def flight_hotel(spark: SparkSession, multistop: bool = False) -> tuple[DataFrame, dict]:
    """Four users, flights and hotels; with multistop one flight serves all cities."""
    texts = [
        "seat('C',x1), room('C',x2) if seat('G',x1) from flights(x1,x), hotels(x2,x)",
        "seat('G',y1), room('G',y2) if seat('C',y1), room('C',y2) from flights(y1,'P'), hotels(y2,'P')",
        "seat('J',z1), room('J',z2) if seat('C',z1), seat('G',z1) from flights(z1,'A'), hotels(z2,'A')",
        "seat('W',w1), room('W',w2) if seat('C',w1), room('J',w2) from flights(w1,'M'), hotels(w2,'M')",
    ]
    eqs = frame(spark, [parse_entangled(t, k + 1) for k, t in enumerate(texts)])
    f = [(1, "P"), (1, "A"), (1, "M")] if multistop else [(1, "P"), (2, "A"), (3, "M")]
    h = [(11, "P"), (12, "A"), (12, "M")] if multistop else [(11, "P"), (12, "A"), (13, "M")]
    return eqs, {"flights": spark.createDataFrame(f, "id long, city string"), "hotels": spark.createDataFrame(h, "id long, city string")}


def band_plus_one(spark: SparkSession) -> tuple[DataFrame, dict]:
    """Four who each need the other three, and one outsider who needs one of them."""
    x, out = Var("x"), []
    for i in range(1, 5):
        out.append(Entangled(i).offer(atom("seat", i, x)).given(*[atom("seat", j, x) for j in range(1, 5) if j != i]).where(atom("flights", x, "Z")))
    out.append(Entangled(5).offer(atom("seat", 5, x)).given(atom("seat", 2, x)).where(atom("flights", x, "Z")))
    return frame(spark, out), {"flights": spark.createDataFrame([(7, "Z")], "id long, city string")}


def two_branches(spark: SparkSession) -> tuple[DataFrame, dict]:
    """A base pair and two pairs that each need the base."""
    needs = {1: [2], 2: [1], 3: [4, 1], 4: [3], 5: [6, 2], 6: [5]}
    out = [Entangled(q).offer(atom("seat", q, Var("x"))).given(*[atom("seat", p, Var(f"y{p}")) for p in ps]).where(atom("flights", Var("x"), "Z")) for q, ps in needs.items()]
    return frame(spark, out), {"flights": spark.createDataFrame([(7, "Z")], "id long, city string")}
