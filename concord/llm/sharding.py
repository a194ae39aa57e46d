"""Balanced label propagation over linked documents, in DataFrame operations only.

Documents that share a link key are linked; keys are hyperedges, so a group of n copies costs n rows and never n * n pairs. A
document may have several keys. Every document starts with the label of its id's hash, one label a shard. In each
round every key counts the labels of its documents (with map-side combine, so one key with a third of all rows is one
row per task and label) and proposes its leading label that isn't full to its documents, or as many leading labels as it needs shards if it is larger than one. A
document with several keys follows the strongest proposal. It moves only within the quota of the target: what the shard still may take divided by
how many want to enter, as a threshold on a hash of the id, so moves under a quota need neither a sort nor a gathered
group. Targets are full at ``SLACK`` times the mean.

The propagated labels are the shards, but for the surplus: a shard with more rows than its even share gives up those with the least
support (documents without links first, then those with the fewest linked documents beside them), and these fill the shards with
room, in the order of their keys. Counts then differ by one at most (the law ``rows``). Support is ranked by a range
partitioning with a running count per partition, so a hot key is split over partitions by id.

Defined results: a null text has 16 bytes of size and is linked with the other null texts only; repeated
rows are placed one by one; null ids order first.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from concord.runtime import cut, keep, partitions

SHARDS = 40
ROUNDS = 3
SLACK = 1.5


def _part(salt: int, *columns: str) -> Column:
    """A number in [0, 1) from a hash."""
    return F.pmod(F.xxhash64(F.lit(salt), *columns), F.lit(1 << 30)) / F.lit(float(1 << 30))


def _beside(state: DataFrame, told: DataFrame, on: list[str], size: str, total: int) -> DataFrame:
    """Left join of the rows with what is told of their groups. Groups with more rows than a partition's share are fewer
    than partitions: they are broadcast, the rest is shuffled."""
    big = F.col(size) * partitions(state.sparkSession) > total
    many = F.broadcast(told.where(big))
    hot = state.join(many, on)
    rest = state.join(many.select(*on), on, "left_anti").join(told.where(~big), on, "left")
    return hot.unionByName(rest.select(*hot.columns))


def propagate(links: DataFrame, shards: int, rounds: int = ROUNDS, slack: float = SLACK, overlapping: bool = False) -> DataFrame:
    """(row, key, label) of (row, key) after quota-bound label propagation; a row without links has a null key.

    ``overlapping`` says that rows may have several keys, and so several lines here; all lines of a row have one label.
    """
    total = links.select("row").distinct().count() if overlapping else links.count()
    share = total / shards  # of a shard
    state = cut(links.withColumn("label", F.floor(_part(0, "row") * shards).cast("int")))
    for k in range(1, rounds + 1):
        held = cut(state.where("key is not null").groupBy("key", "label").agg(F.count("*").alias("n")))
        load = cut((state.dropDuplicates(["row"]) if overlapping else state).groupBy("label").agg(F.count("*").alias("load")))
        full = F.broadcast(load.where(F.col("load") >= 0.95 * slack * share).select("label", F.lit(False).alias("room")))
        # per key its leading labels, those with room before full ones unless the key needs several: at most one entry a shard
        most = held.join(full, "label", "left").groupBy("key").agg(F.sum("n").alias("size"), F.collect_list(F.struct(F.coalesce("room", F.lit(True)).alias("room"), "n", F.negative("label").alias("minus"))).alias("all"))
        need = F.greatest(F.lit(1), F.least(F.size("all"), F.ceil(F.col("size") / F.lit(max(share, 1.0))).cast("int")))
        order = F.sort_array(F.transform("all", lambda t: F.struct((t["room"] | (need > 1)).alias("room"), t["n"].alias("n"), t["minus"].alias("minus"))), False)
        by_label = lambda x, y: F.when(x["minus"] < y["minus"], 1).when(x["minus"] > y["minus"], -1).otherwise(0)  # noqa: E731  so that a row of a large key has one target in all rounds
        lead = cut(most.where("size > 1").select("key", "size", F.array_sort(F.slice(order, F.lit(1), need), by_label).alias("top")))
        outside = ~F.exists("top", lambda t: F.negative(t["minus"]) == F.col("label"))
        wish = held.join(lead, "key").where(outside)
        want = wish.select(F.explode("top").alias("t"), (F.col("n") / F.size("top")).alias("n")).groupBy(F.negative(F.col("t.minus")).alias("label")).agg(F.sum("n").alias("entering"))
        leave = wish.groupBy("label").agg(F.sum("n").alias("leaving"))
        # one row a shard; what a shard may take counts only half of those who want to leave, as they may be refused
        quota = want.join(load, "label", "left").join(leave, "label", "left").select(
            F.col("label").alias("target"),
            F.greatest(F.lit(0.0), (F.lit(slack * share) - F.coalesce("load", F.lit(0)) + F.coalesce("leaving", F.lit(0)) / 2) / F.col("entering")).alias("open"),
        )
        own = F.filter("top", lambda t: F.negative(t["minus"]) == F.col("label"))
        dealt = F.get("top", F.pmod(F.xxhash64(F.lit("top"), "row"), F.size("top")).cast("int"))
        told = _beside(state, lead, ["key"], "size", total).withColumn("best", F.when(F.size(own) > 0, F.get(own, 0)).otherwise(dealt)).drop("top", "size")
        if overlapping:
            told = told.withColumn("best", F.max("best").over(Window.partitionBy("row")))  # a row's keys are its own text's
        moved = told.withColumn("target", F.negative(F.col("best.minus"))).join(F.broadcast(quota), "target", "left")
        go = (F.col("target") != F.col("label")) & (_part(k, "row") < F.col("open"))
        state = cut(moved.select("row", "key", F.when(go, F.col("target")).otherwise(F.col("label")).alias("label")))
    return state


def level(labels: DataFrame, shards: int, rows: int, overlapping: bool = False) -> DataFrame:
    """(row, shard, slot) of (row, key, label): the label, but rows with the least support leave shards with more than their even share."""
    held = labels.where("key is not null").groupBy("key", "label").agg(F.count("*").alias("n")).where("n > 1")
    told = _beside(labels, cut(held), ["key", "label"], "n", rows).select("row", "label", F.coalesce("key", F.lit("")).alias("key"), F.coalesce("n", F.lit(0)).alias("support"))
    if overlapping:
        told = told.groupBy("row", "label").agg(F.max(F.struct("support", "key")).alias("m")).select("row", "label", "m.key", "m.support")
    placed = ranked(told.withColumn("minus", F.negative("support")), ["label", "minus", "key", "row"], "rank")
    every = labels.sparkSession.range(shards).select(F.col("id").cast("int").alias("label"))
    even = F.expr(f"cast(({rows}L * (label + 1)) div {shards} - ({rows}L * label) div {shards} as bigint)")
    count = every.join(placed.groupBy("label").agg(F.count("*").alias("n")), "label", "left").select("label", F.coalesce("n", F.lit(0)).alias("n"), even.alias("even"))
    before = Window.orderBy("label").rowsBetween(Window.unboundedPreceding, -1)  # one row a shard
    sizes = count.select(
        "label", "n", "even", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("first"),
        F.greatest(F.lit(0), F.col("even") - F.col("n")).alias("room"),
        F.coalesce(F.sum(F.greatest(F.lit(0), F.col("even") - F.col("n"))).over(before), F.lit(0)).alias("from"),
    )
    sizes = cut(sizes)
    inside = placed.join(F.broadcast(sizes.select("label", "even", "first")), "label").withColumn("slot", F.col("rank") - F.col("first"))
    stay = inside.where("slot < even").select("row", F.col("label").alias("shard"), "slot")
    spare = ranked(inside.where("slot >= even").select("row", "key"), ["key", "row"], "at")
    open_ = F.broadcast(sizes.where("room > 0").select(F.col("label").alias("shard"), "n", "from", "room"))
    filled = spare.join(open_, (F.col("at") >= F.col("from")) & (F.col("at") < F.col("from") + F.col("room")))
    return stay.unionByName(filled.select("row", "shard", (F.col("n") + F.col("at") - F.col("from")).alias("slot")))


def ranked(df: DataFrame, order: list[str], name: str) -> DataFrame:
    """The rows with their 0-based rank under a total order, without a single-task sort."""
    sorted_ = df.repartitionByRange(partitions(df.sparkSession), *order).sortWithinPartitions(*order)
    dealt = keep(sorted_.withColumn("__id", F.monotonically_increasing_id()))  # the partition above bit 33, the place inside below
    part = F.shiftright("__id", 33)
    sizes = dealt.groupBy(part.alias("__part")).agg(F.count("*").alias("n"))  # one row a partition
    before = sizes.select("__part", F.coalesce(F.sum("n").over(Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("__before"))
    inside = F.col("__id").bitwiseAND(F.lit((1 << 33) - 1))
    return dealt.withColumn("__part", part).join(F.broadcast(before), "__part").withColumn(name, F.col("__before") + inside).drop("__part", "__id", "__before")


def cut_edges(placed: DataFrame, key: str = "key") -> DataFrame:
    """Cost measure: keys with several rows, how many of them span shards, and the row pairs of a key that are split."""
    per = placed.where(F.col(key).isNotNull()).groupBy(key, "shard").agg(F.count("*").alias("n"))
    keys = per.groupBy(key).agg(F.sum("n").alias("size"), F.count("*").alias("spread"), F.sum(F.col("n") * F.col("n")).alias("squares"))
    return keys.where("size > 1").agg(
        F.count("*").alias("linked_keys"),
        F.coalesce(F.sum((F.col("spread") > 1).cast("long")), F.lit(0)).alias("cut_keys"),
        F.coalesce(F.sum(((F.col("size") * F.col("size") - F.col("squares")) / 2).cast("long")), F.lit(0)).alias("cut_pairs"),
    )


def shard(docs: DataFrame, shards: int = SHARDS, rounds: int = ROUNDS) -> DataFrame:
    """Every document with its shard and its slot there; equal texts are linked."""
    text = docs["text"].cast("string")
    light = docs.select(
        docs["doc_id"].alias("doc_id"),
        (F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + 16).alias("size"),
        F.crc32(F.coalesce(text, F.lit("")).cast("binary")).alias("text_crc32"),
        F.coalesce(F.md5(text.cast("binary")), F.lit("")).alias("key"),
    )
    light = keep(light.withColumn("row", F.monotonically_increasing_id()))
    placed = level(propagate(light.select("row", "key"), shards, rounds), shards, light.count())
    return light.join(placed, "row").select(
        "doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", F.col("slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "key",
    )
