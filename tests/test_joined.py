"""Two relations of data, coordinated without joining all their rows."""

from pyspark.sql import functions as F

from concord.operators import consistent as C
from concord.sources import tables as T

COORD = ["place", "day", "room"]


def test_joined_relation_against_plain_join(spark):
    left = spark.range(60).selectExpr("id AS key", "concat('p', id % 4) AS place", "id % 3 AS day", "concat('k', id % 5) AS kind")
    right = spark.createDataFrame([("p0", 7), ("p0", 5), ("p1", 9), ("p3", 8), ("p3", 6)], "place string, room long")
    users = spark.range(12).withColumnRenamed("id", "user")
    requests = T.requests(users, "map('kind', concat('k', user % 3))")
    friends = users.select("user", F.expr("(user + 1) % 12 AS friend"))
    a = C.joined_coordinate(requests, left, right, ["place"], ("key", "room"), COORD, friends)
    b = C.consistent_coordinate(requests, C.joined_relation(left, right, ["place"]), ("key", "room"), COORD, friends)
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert a.patterns.count() == b.patterns.count() and "p0" in {r["place"] for r in a.best.collect()}
    assert rows(a.sets.select(*COORD, "n", "members")) == rows(b.sets.select(*COORD, "n", "members"))
    assert rows(a.best.select(*COORD, "members")) == rows(b.best.select(*COORD, "members"))
    assert rows(a.assignment.select("user", "key", "room")) == rows(b.assignment.select("user", "key", "room"))
