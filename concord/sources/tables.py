"""Base tables and the relations and workloads that are derived from them.

Every derived relation is a declarative plan over the base tables with integer arithmetic only, so that
any engine gives the same rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_requests(spark: SparkSession, path: str, kind: str, schema: str, **options) -> DataFrame:
    """Request or query files (json, csv, parquet, orc, jdbc) under an explicit schema."""
    reader = spark.read.format(kind).options(**options)
    if kind in ("json", "csv"):
        reader = reader.schema(schema)
    return reader.load(path) if path else reader.load()


def write_result(df: DataFrame, path: str, by: list[str] | None = None, mode: str = "errorifexists") -> None:
    """Parquet sink, optionally partitioned."""
    writer = df.write.mode(mode)
    (writer.partitionBy(*by) if by else writer).parquet(path)


# ---------------------------------------------------------------- relations


def flights(spark: SparkSession, d: str) -> DataFrame:
    """flight_id (key), destination, day, source, airline."""
    o, c, n = table(spark, d, "orders"), table(spark, d, "customer"), table(spark, d, "nation")
    return (
        o.join(c, o["o_custkey"] == c["c_custkey"])
        .join(F.broadcast(n), c["c_nationkey"] == n["n_nationkey"])
        .select(
            F.col("o_orderkey").alias("flight_id"), F.col("n_name").alias("destination"), F.to_date("o_orderdate").alias("day"),
            F.col("c_mktsegment").alias("source"), F.col("o_orderpriority").alias("airline"),
        )
    )


def flights_distinct(spark: SparkSession, d: str, n: int) -> DataFrame:
    """The first n flights, by id, among the least id of each (destination, day)."""
    f = flights(spark, d)
    least = f.groupBy("destination", "day").agg(F.min(F.struct("flight_id", "source", "airline")).alias("m"))
    return least.select("m.flight_id", "destination", "day", "m.source", "m.airline").orderBy("flight_id").limit(n)


def hotels(spark: SparkSession, d: str) -> DataFrame:
    s, n = table(spark, d, "supplier"), table(spark, d, "nation")
    return s.join(F.broadcast(n), s["s_nationkey"] == n["n_nationkey"]).select(F.col("s_suppkey").alias("hotel_id"), F.col("n_name").alias("location"))


def movies(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "part").select(F.col("p_partkey").alias("movie_id"), F.col("p_brand").alias("cinema"), F.col("p_name").alias("title"))


def concerts(spark: SparkSession, d: str) -> DataFrame:
    """Distinct (location, event_day) of a tour schedule."""
    s, n, li = table(spark, d, "supplier"), table(spark, d, "nation"), table(spark, d, "lineitem")
    place = s.join(F.broadcast(n), s["s_nationkey"] == n["n_nationkey"]).select("s_suppkey", F.col("n_name").alias("location"))
    return li.select("l_suppkey", F.to_date("l_shipdate").alias("event_day")).distinct().join(place, F.col("l_suppkey") == F.col("s_suppkey")).select("location", "event_day").distinct()


def party_options(spark: SparkSession, d: str) -> DataFrame:
    """Distinct (user, party_type, party_day) attended."""
    e = table(spark, d, "events")
    return e.select(F.col("user_id").alias("user"), F.col("event_type").alias("party_type"), F.to_date("ts").alias("party_day")).distinct()


def customers(spark: SparkSession, d: str, n: int | None = None) -> DataFrame:
    c = table(spark, d, "customer")
    return c.where(F.col("c_custkey") < n) if n is not None else c


# ---------------------------------------------------------------- friendship


def friends_complete(spark: SparkSession, d: str, n: int) -> DataFrame:
    """All ordered pairs of the first n customers: an all-pairs relation by definition, for small n only."""
    c = customers(spark, d, n).select("c_custkey")
    return c.select(F.col("c_custkey").alias("user")).join(c.select(F.col("c_custkey").alias("friend")), F.col("user") != F.col("friend"))


CIRCLE = 200


def friends_ring(spark: SparkSession, d: str, n: int | None, k: int) -> DataFrame:
    """Of the first n customers or of all, the next k around a ring inside each circle: one nation and one block of CIRCLE ids, so no ring grows with the data."""
    w = Window.partitionBy("c_nationkey", "circle")
    r = customers(spark, d, n).withColumn("circle", F.expr(f"c_custkey div {CIRCLE}")).select("c_custkey", "c_nationkey", "circle", (F.row_number().over(w.orderBy("c_custkey")) - 1).alias("rank"), F.count("*").over(w).alias("size"))
    step = r.select("c_custkey", "c_nationkey", "circle", "size", F.explode(F.expr(f"transform(sequence(1, {k}), i -> (rank + i) % size)")).alias("to"))
    other = r.select(F.col("c_custkey").alias("friend"), F.col("c_nationkey").alias("nation"), F.col("circle").alias("block"), F.col("rank").alias("at"))
    pairs = step.join(other, (step["c_nationkey"] == other["nation"]) & (step["circle"] == other["block"]) & (step["to"] == other["at"]))
    return pairs.select(F.col("c_custkey").alias("user"), "friend").where("user <> friend").distinct()


def groups_coactive(spark: SparkSession, d: str, minutes: int = 10) -> DataFrame:
    """(user, group): users by the time buckets of their events."""
    return table(spark, d, "events").select(F.col("user_id").alias("user"), (F.unix_timestamp(F.col("ts").cast("timestamp")) / (60 * minutes)).cast("long").alias("group")).distinct()


def friends_coactive(spark: SparkSession, d: str, minutes: int = 10) -> DataFrame:
    """Users with an event in the same time bucket (the buckets bound the pairs)."""
    e = groups_coactive(spark, d, minutes)
    return e.join(e.withColumnsRenamed({"user": "friend"}), "group").where("user <> friend").select("user", "friend").distinct()


def friends_copurchase(spark: SparkSession, d: str) -> DataFrame:
    """Customers whose orders share a part (a dense stress relation)."""
    o, li = table(spark, d, "orders").select("o_orderkey", "o_custkey"), table(spark, d, "lineitem").select("l_orderkey", "l_partkey")
    bought = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).select("o_custkey", "l_partkey").distinct()
    a, b = bought.select(F.col("o_custkey").alias("user"), "l_partkey"), bought.select(F.col("o_custkey").alias("friend"), "l_partkey")
    return a.join(b, "l_partkey").where("user <> friend").select("user", "friend").distinct()


def scale_free(spark: SparkSession, n: int, seed: int = 0, back_every: int = 0) -> DataFrame:
    """Directed edges (src, dst) with a power-law in-degree; every back_every-th edge also runs backwards."""
    r = F.shiftright((((F.col("id") + seed * 1000003) * F.lit(1103515245) + 12345) % F.lit(1 << 31)), 15)
    e = spark.range(1, n).select(F.col("id").alias("src"), r.alias("r")).select("src", F.shiftright(F.col("src") * F.col("r") * F.col("r"), 32).alias("dst"))
    if back_every:
        e = e.unionByName(e.where(F.col("src") % back_every == 0).select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    return e


NETWORK = 300


def scale_free_networks(spark: SparkSession, d: str, seed: int = 0, back_every: int = 0) -> DataFrame:
    """Every block of NETWORK customer ids as one ``scale_free`` network of its own, so no network grows with the data."""
    c = table(spark, d, "customer").select(F.col("c_custkey").cast("long").alias("src"), F.pmod(F.col("c_custkey").cast("long"), F.lit(NETWORK)).alias("i")).where("i > 0")
    r = F.shiftright((((F.col("i") + seed * 1000003) * F.lit(1103515245) + 12345) % F.lit(1 << 31)), 15)
    e = c.withColumn("r", r).select("src", "i", (F.col("src") - F.col("i") + F.shiftright(F.col("i") * F.col("r") * F.col("r"), 32)).alias("dst"))
    known = table(spark, d, "customer").select(F.col("c_custkey").cast("long").alias("dst")).distinct()
    e = e.join(known.hint("merge"), "dst", "left_semi").select("src", "dst", "i")
    if back_every:
        e = e.unionByName(e.where(F.col("i") % back_every == 0).select(F.col("dst").alias("src"), F.col("src").alias("dst"), "i"))
    return e.select("src", "dst")


# ---------------------------------------------------------------- consistent requests

REQUEST = "qid long, user long, own map<string,string>, named array<long>, any_friend array<struct<rel:string,k:int>>, same_tuple boolean, weight double"
ANY_ONE = "array(named_struct('rel', 'friends', 'k', 1))"
NO_ASK = "cast(array() as array<struct<rel:string,k:int>>)"


def requests(users: DataFrame, own: str = "map()", named: str = "array()", asks: str = ANY_ONE, weight: str = "0.0") -> DataFrame:
    """Requests of a table with a column ``user``, from SQL expressions for the parts."""
    return users.select(
        F.col("user").cast("long").alias("qid"), F.col("user").cast("long").alias("user"),
        F.expr(f"cast({own} as map<string,string>)").alias("own"), F.expr(f"cast({named} as array<bigint>)").alias("named"),
        F.expr(f"cast({asks} as array<struct<rel:string,k:int>>)").alias("any_friend"), F.lit(False).alias("same_tuple"),
        F.expr(f"cast({weight} as double)").alias("weight"),
    )


def travellers(spark: SparkSession, d: str, n: int | None = None) -> DataFrame:
    """Flight requests: some fix an airline, a source or a destination; some name a partner, the others ask for any friend."""
    c = customers(spark, d, n).join(F.broadcast(table(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).withColumn("user", F.col("c_custkey"))
    airlines = "element_at(array('1-URGENT','2-HIGH','3-MEDIUM','4-NOT SPECIFIED','5-LOW'), cast(1 + user % 5 as int))"
    own = (
        "map_filter(map('airline', case when user % 2 = 0 then " + airlines + " end, 'source', case when user % 3 = 0 then c_mktsegment end, "
        "'destination', case when user % 7 = 0 then n_name end), (k, v) -> v is not null)"
    )
    return requests(c, own, "case when user % 4 = 1 then array(user + 1) else array() end", f"case when user % 4 = 1 then {NO_ASK} else {ANY_ONE} end", "c_acctbal")
