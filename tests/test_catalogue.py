"""A few registered queries against DuckDB, and the entry module without the text subpackage."""

import importlib
import sys

import duckdb
import pytest
from pyspark.sql import functions as F

from concord.plans import catalogue
from concord.sources import entangled as E
from concord.streaming.arrivals import Arrivals, coordinate_stream

D = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events".split()


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{D}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", ["cons_flights", "cons_concerts", "cons_parties", "scc_selective", "stream_windows", "asof_request"])
def test_against_sql(spark, duck, name):
    got = catalogue.queries()[name](spark, D)
    columns = sorted(got.columns)
    want = duck.sql(catalogue.oracle_sql()[name]).df()
    assert sorted(want.columns) == columns
    rows = lambda df: sorted(tuple(map(str, r)) for r in df[columns].itertuples(index=False))
    assert rows(got.toPandas()) == rows(want)


def test_every_oracle_has_a_query():
    assert set(catalogue.oracle_sql()) <= set(catalogue.queries())


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() == 1


def test_entry_without_text_operators(monkeypatch):
    for name in [m for m in sys.modules if m in ("__spark_entry__", "corpus_pipeline") or m.startswith("concord.llm")]:
        monkeypatch.delitem(sys.modules, name)
    monkeypatch.setitem(sys.modules, "concord.llm", None)  # importing it fails
    entry = importlib.import_module("__spark_entry__")
    assert set(entry.queries()) == set(catalogue.queries())


def test_arrivals_keep_what_waits(spark, tmp_path):
    eqs, cat = E.two_flyers(spark)
    loop = Arrivals(spark, cat, str(tmp_path / "state"))
    eqs.where("qid = 1").write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(eqs.schema).parquet(str(tmp_path / "in"))
    coordinate_stream(stream, loop, str(tmp_path / "checkpoint")).awaitTermination(120)
    assert loop.answers().count() == 0 and [r["qid"] for r in loop.pending(1).collect()] == [1]
    loop(eqs.where("qid = 2"), 1)
    assert {r["qid"] for r in loop.answers().collect()} == {1, 2} and loop.pending(2).count() == 0
    loop(eqs.where("qid = 2"), 1)  # the same batch again
    assert {r["qid"] for r in loop.answers().collect()} == {1, 2}


def test_sql_surface(spark):
    from concord.functions import sql
    from concord.operators import scc, unify

    sql.register(spark)
    rows = spark.sql("select role, rel, size(terms) as n from parse_eq('seat(1,x) if seat(2,x) from flights(x,''Z'')')").collect()
    assert {tuple(r) for r in rows} == {("head", "seat", 2), ("post", "seat", 2), ("body", "flights", 2)}
    eqs, cat = E.two_flyers(spark)
    sql.publish(eqs, unify.extended_graph(eqs), scc.scc_coordinate(eqs, cat))
    assert spark.sql("select max(n) from eq_sets").first()[0] == 2 and spark.sql("select count(*) from eq_edges").first()[0] == 1


def test_live_interest(spark, tmp_path):
    from concord.streaming.state import live_interest

    source = spark.readStream.schema(spark.read.parquet(f"{D}/events.parquet").schema).option("pathGlobFilter", "events.parquet").parquet(D)
    out = live_interest(source, "ts", "user_id", ["event_type"], need=2, ttl_seconds=10**9)
    out.writeStream.outputMode("update").format("memory").queryName("interest").option("checkpointLocation", str(tmp_path)).trigger(availableNow=True).start().awaitTermination(120)
    want = {r[0]: r[1] for r in spark.read.parquet(f"{D}/events.parquet").groupBy("event_type").agg({"user_id": "count"}).collect()}
    users = {r["event_type"]: r["users"] for r in spark.sql("select event_type, max(users) as users from interest group by 1").collect()}
    assert set(users) == set(want) and all(2 <= n <= 15 for n in users.values())


@pytest.mark.parametrize("name", ["cons_flights", "cons_movies", "cons_two_friend_rels", "cons_named_only", "request_lead", "friend_intersect"])
def test_every_customer_is_a_request(spark, duck, tmp_path, name):
    """Over a fixture of 260 customers, in two blocks of ids."""
    table = lambda t: spark.read.parquet(f"{D}/{t}.parquet")
    for t in "nation supplier part lineitem".split():
        table(t).where("l_suppkey % 2 = 0" if t == "lineitem" else "true").write.parquet(f"{tmp_path}/{t}.parquet")
    more = table("customer").where("c_custkey < 110").withColumn("c_custkey", F.col("c_custkey") + 150)
    table("customer").unionByName(more).write.parquet(f"{tmp_path}/customer.parquet")
    table("orders").where("o_orderkey % 60 = 0").write.parquet(f"{tmp_path}/orders.parquet")
    own = duckdb.connect()
    for t in "nation supplier part lineitem customer orders".split():
        own.sql(f"create view {t} as select * from '{tmp_path}/{t}.parquet/*.parquet'")
    got, want = catalogue.queries()[name](spark, str(tmp_path)), own.sql(catalogue.oracle_sql()[name]).df()
    rows = lambda df: sorted(tuple(map(str, r)) for r in df[sorted(want.columns)].itertuples(index=False))
    assert rows(got.toPandas()) == rows(want)
