"""Friends by groups: cleaned without pairs, with the sets that the pairs give."""

import pytest
from pyspark.sql import functions as F

from concord.operators import consistent as C
from concord.sources import tables as T

COORD = ["party_type", "party_day"]


def meetings(spark, asks=T.ANY_ONE):
    users = spark.range(40).withColumnRenamed("id", "user")
    requests = T.requests(users, "map('user', cast(user as string))", "array()", asks)
    wants = users.select("user", F.expr("concat('t', user % 2)").alias("party_type"), F.expr("explode(array(date'2024-01-01', date_add(date'2024-01-02', cast(user % 4 as int))))").alias("party_day"))
    groups = users.select("user", F.expr("explode(array(user div 7, 100 + user % 11))").alias("group"))
    return requests, wants, groups.where("user <> 5")


def sets(run):
    return sorted(map(tuple, run.sets.select(*COORD, "n", "members").collect()))


@pytest.mark.parametrize(("asks", "limit"), [(T.ANY_ONE, 1 << 20), (T.ANY_ONE, 0), ("array(named_struct('rel', 'friends', 'k', 2))", 1 << 20)])
def test_groups_against_pairs(spark, monkeypatch, asks, limit):
    monkeypatch.setattr(C, "MEMBERSHIPS", limit)
    requests, wants, groups = meetings(spark, asks)
    key = ("user", *COORD)
    a = C.consistent_coordinate(requests, wants, key, COORD, groups)
    b = C.consistent_coordinate(requests, wants, key, COORD, C.pairs(groups))
    assert (a.groups is None) == ("'k', 2" in asks) and b.groups is None
    assert sets(a) == sets(b) and len(sets(a)) > 1
    assert a.best.drop("weight").collect() == b.best.drop("weight").collect()
    if a.groups is None or limit == 0:
        return
    packed = [sorted(map(tuple, C.pack_values(r, requests)[0].collect())) for r in (a, b)]
    assert packed[0] == packed[1] and len(packed[0]) > 1


def test_a_crowd_takes_no_pairs(spark):
    """20,000 users of one group have 400 million pairs."""
    users = spark.range(20_000).withColumnRenamed("id", "user")
    wants = users.select("user", F.lit("t").alias("party_type"), F.lit("d").alias("party_day"))
    requests = T.requests(users, "map('user', cast(user as string))")
    run = C.consistent_coordinate(requests, wants, ("user", *COORD), COORD, users.withColumn("group", F.lit(1).cast("long")))
    assert [r["n"] for r in run.sizes.collect()] == [20_000]
