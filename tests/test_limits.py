"""Joins and stages that grow with the data stay off the driver; results don't depend on the way chosen."""

import random

from pyspark.sql import functions as F

from concord.llm import simhash
from concord.operators import graph as G


def test_components_in_a_task_and_over_tables(spark):
    rnd = random.Random(5)
    edges = spark.createDataFrame([(rnd.randrange(300), rnd.randrange(300)) for _ in range(170)], "src long, dst long")
    one, many = (sorted(map(tuple, G.weak_components(edges, in_task=k).collect())) for k in (None, 0))
    assert one == many and len({c for _, c in one}) > 5


def test_fingerprint_joins_are_not_broadcast(spark):
    docs = spark.createDataFrame([(i, f"some words of text {i % 7} and more") for i in range(60)], "doc_id long, text string")
    for made in (simhash.near_duplicates(docs), simhash.first_of_each(docs)):
        assert made.count() >= 7
        plan = made._jdf.queryExecution().executedPlan().toString()
        assert "Broadcast" not in plan and "SortMergeJoin" in plan


def test_rows_of_bits_against_cleaning_by_pattern(spark, monkeypatch):
    from concord.operators import consistent as C
    from concord.operators.select import containing, most_weight
    from concord.sources import tables as T

    monkeypatch.setattr(C, "BUCKET", 20)
    d = "/root/testdata/sf0.001"
    requests, data = T.travellers(spark, d, 80), T.flights(spark, d).where("month(day) <= 3")
    asks = "transform(any_friend, a -> named_struct('rel', a.rel, 'k', cast(1 + user % 3 as int)))"
    requests = requests.withColumn("any_friend", F.expr(asks))
    friends = T.friends_ring(spark, d, 80, 4)
    some = C.consistent_coordinate(requests, data, "flight_id", ["destination", "day"], friends, mode="local").survivors.agg(F.max("qid")).first()[0]
    for select in (most_weight(), containing(some)):
        runs = [C.consistent_coordinate(requests, data, "flight_id", ["destination", "day"], friends, select, mode=m) for m in ("bits", "local")]
        assert runs[0].bits is not None and runs[1].bits is None
        plain = lambda df: sorted(tuple(str(x) for x in r) for r in df.collect())
        for what in ("survivors", "assignment"):
            assert plain(getattr(runs[0], what)) == plain(getattr(runs[1], what)) != []
        for what in ("sets", "best"):
            one, two = (plain(getattr(r, what).select("destination", "day", "n", F.round("weight", 6), "members", "ids")) for r in runs)
            assert one == two != []
        assert plain(runs[0].sizes.select("destination", "day", "n")) == plain(runs[1].sets.select("destination", "day", "n"))


def test_sizes_need_no_members(spark):
    """The best set of many requests over many values: what is kept are sizes by pattern, so nothing grows with requests times values."""
    from concord.operators import consistent as C
    from concord.sources import tables as T

    users = spark.range(4000).select(F.col("id").alias("user"))
    data = spark.range(1500).select(F.col("id").alias("key"), F.concat(F.lit("p"), F.col("id")).alias("place"), (F.col("id") % 997).cast("string").alias("kind"))
    own = "map_filter(map('kind', case when user % 2 = 0 then cast(user % 997 as string) end), (k, v) -> v is not null)"
    friends = spark.range(4000).select(F.col("id").alias("user"), F.expr("id ^ 1").alias("friend"))
    run = C.consistent_coordinate(T.requests(users, own), data, "key", ["place"], friends)
    # 2,000 open requests at 1,500 places, of which those live whose partner asks for the kind of the place
    assert run.bits is not None and run.best.first()["n"] == 2 * 3
    assert run.sizes.count() == 1500


def test_former_literal_queries_follow_the_given_tables(spark, tmp_path):
    """On 610 customers more than one network and many groups and formulas: as the SQL says, and with both answers where there are two."""
    import duckdb

    from concord.plans import catalogue

    d = str(tmp_path)
    for t, some in (("customer", "c_custkey < 610"), ("lineitem", "l_orderkey % 3 = 0")):
        spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet").where(some).write.parquet(f"{d}/{t}.parquet")
    duck = duckdb.connect()
    for t in ("customer", "lineitem"):
        duck.sql(f"create view {t} as select * from '{d}/{t}.parquet/*.parquet'")
    for name in "sat_truth_table sat_thm1 sat_thm2_max fit_linear ext_edges_flight_hotel ext_edges_mgu scc_scale_free weak_components_sf condensation_sf dag_levels_sf reach_sizes_sf unique_report".split():
        got, want = catalogue.queries()[name](spark, d).toPandas(), duck.sql(catalogue.oracle_sql()[name]).df()
        columns = sorted(want.columns)
        rows = [sorted(tuple(map(str, r)) for r in df[columns].itertuples(index=False)) for df in (got, want)]
        assert rows[0] == rows[1] and len(rows[0]) > (0 if name == "fit_linear" else 2), name
        if name.startswith("sat_"):
            assert len(set(got[got.columns[1]])) == 2, name


def _small_run(spark, monkeypatch, mode="auto"):
    from concord.operators import consistent as C
    from concord.sources import tables as T

    monkeypatch.setattr(C, "BUCKET", 5)
    users = spark.range(120).select(F.col("id").alias("user"))
    data = spark.range(700).select(F.col("id").alias("key"), F.concat(F.lit("p"), F.col("id")).alias("place"), F.when(F.col("id") % 7 > 0, "x").otherwise("y").alias("kind"))
    friends = spark.range(120).select(F.col("id").alias("user"), F.expr("id ^ 1").alias("friend"))
    requests = T.requests(users, "map_filter(map('kind', case when user % 2 = 0 then 'x' end), (k, v) -> v is not null)", weight="user / 8")
    return requests, data, C.consistent_coordinate(requests, data, "key", ["place"], friends, mode=mode)


def test_option_lists_read_the_relation_once(spark):
    """Several sets of constrained attributes: the joins behind the relation are not made anew for each."""
    from concord.operators import consistent as C
    from concord.sources import tables as T

    d = "/root/testdata/sf0.001"
    requests, data = T.travellers(spark, d), T.flights(spark, d)
    lists = C.option_lists(requests, data, ["destination", "day"])
    assert lists.inputFiles() and not set(lists.inputFiles()) & set(data.inputFiles())


def test_sizes_leave_a_task_once_for_each_pattern(spark, monkeypatch):
    from concord.runtime import partitions

    _, _, run = _small_run(spark, monkeypatch)
    assert run.bits.people.select("bucket").distinct().count() > partitions(spark)
    parts = run.bits.partial_sizes()
    assert parts.count() <= partitions(spark) * run.shapes.count()
    assert sorted(map(tuple, run.sizes.groupBy("n", "weight").count().collect())) == [(120, 120 * 119 / 16, 600)]


def test_values_of_one_pattern_are_written_by_several_tasks(spark, monkeypatch):
    from concord.operators import consistent as C

    monkeypatch.setattr(C, "SHARE", 200)
    monkeypatch.setattr(C, "ALONE", 60_000)
    _, _, run = _small_run(spark, monkeypatch)
    _, _, other = _small_run(spark, monkeypatch, mode="local")
    plain = lambda df: sorted((r["place"], r["n"], r["weight"], r["members"], tuple(r["ids"])) for r in df.collect())
    assert len(plain(run.sets)) == 600 and plain(run.sets) == plain(other.sets)
    # 600 places in three tasks, and nothing else in them
    tasks = run.sets.groupBy(F.spark_partition_id().alias("task")).agg(F.countDistinct("members").alias("texts")).collect()
    assert len(tasks) == 3 and {r["texts"] for r in tasks} == {1}
