"""Sets with many members and many values: what a task holds at a time is bounded, and the rows stay the same."""

import pytest
from pyspark.sql import functions as F

from concord import runtime
from concord.operators import consistent as C
from concord.sources import tables as T

SET = ("parquet.page.size.row.check.min", "parquet.dictionary.page.size")


@pytest.fixture
def writer(spark):
    yield lambda: [spark.conf.get(k, None) for k in SET]
    for k in SET:
        spark.conf.unset(k)


def test_bits_held_for_a_chunk_are_bounded(spark, monkeypatch):
    """Patterns are put together in fewer at a time where there are more requests; ids of any length and sign, in order."""
    users = spark.range(-60, 60).select((F.col("id") * F.col("id") * F.col("id")).alias("user"))
    data = spark.range(40).select(F.col("id").alias("key"), F.concat(F.lit("p"), F.col("id")).alias("place"), F.col("id").cast("string").alias("kind"))
    own = "map_filter(map('kind', case when user % 2 <> 0 then cast(pmod(user, 40) as string) end), (k, v) -> v is not null)"
    pairs = users.select("user", F.lit(0).cast("long").alias("friend"))
    runs = {}
    for held in (1 << 25, 300, 1):
        monkeypatch.setattr(C, "HELD", held)
        monkeypatch.setattr(C, "SENT", min(held, 500))
        run = C.consistent_coordinate(T.requests(users, own, weight="user / 8"), data, "key", ["place"], pairs)
        count = run.signed.count()
        assert run.bits.chunk % 8 == 0 and 8 <= run.bits.chunk <= max(8, min(C.CHUNK, 8 * held // count))
        runs[held] = sorted((r["place"], r["n"], r["weight"], r["members"], tuple(r["ids"])) for r in run.sets.collect())
    local = C.consistent_coordinate(T.requests(users, own, weight="user / 8"), data, "key", ["place"], pairs, mode="local")
    want = sorted((r["place"], r["n"], r["weight"], r["members"], tuple(r["ids"])) for r in local.sets.collect())
    assert len({r[3] for r in want}) > 10 and all(r == want for r in runs.values())


def test_a_task_has_one_chunk(spark, monkeypatch):
    """Where there are more chunks than partitions."""
    monkeypatch.setattr(C, "HELD", 1)
    users, given = spark.range(30).withColumnRenamed("id", "user"), spark.conf.get("spark.sql.shuffle.partitions")
    data = spark.range(30).select(F.col("id").alias("key"), F.concat(F.lit("p"), F.col("id")).alias("place"), F.col("id").cast("string").alias("kind"))
    spark.conf.set("spark.sql.shuffle.partitions", 2)
    try:
        run = C.consistent_coordinate(T.requests(users, "map('kind', cast(user as string))", asks=T.NO_ASK), data, "key", ["place"], users.select("user", F.col("user").alias("friend")))
        rows = run.bits.sets().select("members", F.spark_partition_id().alias("task"), (F.col("pid") / run.bits.chunk).cast("int").alias("chunk")).collect()
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", given)
    assert sorted(int(r["members"]) for r in rows) == list(range(30)) and run.bits.chunk == 8
    assert len({r["chunk"] for r in rows}) == len({r["task"] for r in rows}) == len({(r["chunk"], r["task"]) for r in rows}) == 4


def test_writers_are_fitted_to_wide_rows_only(spark, writer):
    runtime.wide_rows(spark, 2000)
    assert writer() == [None, None]
    spark.conf.set(SET[1], "3000000")
    runtime.wide_rows(spark, 2_000_000)
    assert writer() == ["2", "3000000"]


def test_rows_of_one_text_are_made_one_at_a_time(spark, writer, tmp_path):
    """60,000 members (1.1 MB of text) at 1,500 values: 1.7 GB of rows that no task holds, and one text in a file."""
    users = spark.range(60_000).select((F.col("id") + 10**17).alias("user"))
    data = spark.range(1500).select(F.col("id").alias("key"), F.concat(F.lit("p"), F.col("id")).alias("place"))
    friends = users.select("user", F.expr("user ^ 1").alias("friend"))
    run = C.consistent_coordinate(T.requests(users), data, "key", ["place"], friends)
    out = str(tmp_path / "sets")
    run.sets.select("place", "n", "members").write.parquet(out)
    assert sum(p.stat().st_size for p in (tmp_path / "sets").glob("*.parquet")) < 4_000_000
    want = ",".join(str(i + 10**17) for i in range(60_000))
    got = spark.read.parquet(out).groupBy("n", F.crc32("members").alias("sum"), F.length("members").alias("size")).agg(F.countDistinct("place").alias("places")).collect()
    import zlib

    assert [tuple(r) for r in got] == [(60_000, zlib.crc32(want.encode()), len(want), 1500)]
