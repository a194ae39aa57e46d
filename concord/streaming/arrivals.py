"""Streams of queries and requests.

``Arrivals`` evaluates entangled queries as they come. The queries that wait, their extended graph and their weak components are kept. A
micro-batch is matched with what waits (new against all, waiting postconditions against new heads), its edges merge the components
they touch, and only those are coordinated: the best set of each is answered and its members leave, the rest waits. Arrivals
that would make a query unsafe are set aside with the reason. The state is versioned by batch id in a shared folder, so that a batch that is run
again after a failure starts from the same state.

``window_requests`` buffers consistent requests per time window; the window is then one more coordination attribute,
so all complete windows of a micro-batch are coordinated in one run.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from concord.model import EQ, explode_atoms
from concord.operators.graph import weak_components
from concord.operators.scc import scc_coordinate
from concord.operators.select import Selection, largest
from concord.operators.unify import unifiable_pairs
from concord.runtime import cut, keep

EDGE = "src long, post_pos int, dst long, head_pos int"
MEMBER = "node long, comp_id long"


class Arrivals:
    def __init__(self, spark: SparkSession, catalog: dict[str, DataFrame], folder: str, keys: dict | None = None, select: Selection | None = None):
        self.spark, self.catalog, self.folder = spark, catalog, folder.rstrip("/")
        self.keys, self.select = keys, select or largest()

    def _exists(self, path: str) -> bool:
        p = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        return p.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(p)

    def _state(self, name: str, batch: int, schema: str) -> DataFrame:
        path = f"{self.folder}/{name}/{batch}"
        if batch == 0:
            return self.spark.createDataFrame([], schema)
        if not self._exists(f"{path}/_SUCCESS"):
            raise RuntimeError(f"no state before batch {batch}: {path}")
        return self.spark.read.schema(schema).parquet(path)

    def pending(self, batch: int) -> DataFrame:
        """The queries that wait before a batch."""
        return self._state("pending", batch, EQ)

    def _write(self, df: DataFrame, name: str, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{self.folder}/{name}/{batch}")

    def _matched(self, old: DataFrame, new: DataFrame) -> DataFrame:
        """The edges that new queries bring."""
        atoms, fresh = explode_atoms(old.unionByName(new)), explode_atoms(new)
        posts, heads = "role = 'post'", "role = 'head'"
        waiting = explode_atoms(old).where(posts)
        return keep(unifiable_pairs(fresh.where(posts), atoms.where(heads)).unionByName(unifiable_pairs(waiting, fresh.where(heads))))

    def __call__(self, arrived: DataFrame, batch: int) -> None:
        """For ``foreachBatch``: writes answers/<batch> and refused/<batch>, and the state before the next batch."""
        old, known, comp = self.pending(batch), self._state("edges", batch, EDGE), self._state("components", batch, MEMBER)
        new = keep(arrived.select(*old.columns).dropDuplicates(["qid"]).join(old.select("qid"), "qid", "left_anti").select(*old.columns))
        fresh, ids = self._matched(old, new), new.select("qid")
        # of several heads for one postcondition the waiting one counts, then the least new one; other new ones are set aside
        every = known.unionByName(fresh)
        slots = fresh.select("src", "post_pos").distinct()
        rivals = every.join(slots, ["src", "post_pos"]).join(ids.select(F.col("qid").alias("dst"), F.lit(True).alias("is_new")), "dst", "left")
        rivals = rivals.select("src", "post_pos", "dst", "head_pos", F.coalesce("is_new", F.lit(False)).alias("is_new"))
        lead = rivals.groupBy("src", "post_pos").agg(F.min(F.struct("is_new", "dst", "head_pos")).alias("m"))
        second = rivals.join(lead, ["src", "post_pos"]).where("is_new and dst <> m.dst").select(F.col("dst").alias("qid")).distinct()
        second = cut(second)
        left = rivals.join(second, F.col("dst") == F.col("qid"), "left_anti").join(second, F.col("src") == F.col("qid"), "left_anti")
        several = left.groupBy("src", "post_pos").agg(F.count("*").alias("n")).where("n > 1").select(F.col("src").alias("qid")).distinct().join(ids, "qid", "left_semi")
        refused = cut(second.withColumn("reason", F.lit("second offer")).unionByName(several.withColumn("reason", F.lit("several offers match"))))
        out = refused.select("qid")
        edges = every.join(out, F.col("src") == F.col("qid"), "left_anti").join(out, F.col("dst") == F.col("qid"), "left_anti").select("src", "post_pos", "dst", "head_pos")
        edges = keep(edges)
        taken = keep(old.unionByName(new).join(out, "qid", "left_anti").select(*old.columns))
        # components: the new edges merge those that they touch; a query without edges is one of its own
        home = taken.select(F.col("qid").alias("node")).join(comp, "node", "left").select("node", F.coalesce("comp_id", "node").alias("comp_id"))
        home = cut(home)
        a, b = home.select(F.col("node").alias("src"), F.col("comp_id").alias("ca")), home.select(F.col("node").alias("dst"), F.col("comp_id").alias("cb"))
        joined = weak_components(fresh.join(a, "src").join(b, "dst").select("ca", "cb").distinct(), "ca", "cb")
        comp = cut(home.join(joined.select(F.col("node").alias("comp_id"), F.col("comp_id").alias("to")), "comp_id", "left").select("node", F.coalesce("to", "comp_id").alias("comp_id")))
        touched = comp.join(ids.withColumnRenamed("qid", "node"), "node", "left_semi").select("comp_id").distinct()
        here = cut(comp.join(touched, "comp_id", "left_semi"))
        some = taken.join(here.select(F.col("node").alias("qid")), "qid", "left_semi").select(*old.columns)
        inner = keep(edges.join(here.select(F.col("node").alias("src")), "src", "left_semi").select("src", "post_pos", "dst", "head_pos"))
        run = scc_coordinate(some, self.catalog, self.keys, ext=inner)
        ok = run.nodes.where("status = 'ok'")
        if self.select.must is not None:
            ok = ok.where(F.array_contains("ids", F.lit(self.select.must)))
        score = F.col(self.select.score) if self.select.score else F.lit(0)
        best = ok.groupBy("comp_id").agg(F.max(F.struct(score.alias("score"), F.negative("scc_id").alias("minus"), "ids")).alias("m"))
        met = best.select(F.lit(batch).alias("batch"), F.negative(F.col("m.minus")).alias("set_id"), F.explode("m.ids").alias("qid"))
        self._write(met, "answers", batch)
        self._write(refused.withColumn("batch", F.lit(batch)), "refused", batch)
        gone = self.spark.read.parquet(f"{self.folder}/answers/{batch}").select("qid")
        rest = edges.join(gone, F.col("src") == F.col("qid"), "left_anti").join(gone, F.col("dst") == F.col("qid"), "left_anti")
        rest = keep(rest)
        # components that have lost members may have fallen apart
        torn = cut(comp.join(gone.withColumnRenamed("qid", "node"), "node", "left_semi").select("comp_id").distinct())
        stay = comp.join(gone.withColumnRenamed("qid", "node"), "node", "left_anti")
        open_ = cut(stay.join(torn, "comp_id", "left_semi").select("node"))
        again = weak_components(rest.join(open_.withColumnRenamed("node", "src"), "src", "left_semi")).withColumnRenamed("comp_id", "to")
        whole = stay.join(torn, "comp_id", "left_anti").select("node", "comp_id")
        parts = open_.join(again, "node", "left").select("node", F.coalesce("to", "node").alias("comp_id"))
        self._write(whole.unionByName(parts), "components", batch + 1)
        self._write(rest, "edges", batch + 1)
        self._write(taken.join(gone, "qid", "left_anti").select(*old.columns), "pending", batch + 1)

    def answers(self) -> DataFrame:
        """(batch, set_id, qid)"""
        return self.spark.read.parquet(f"{self.folder}/answers/*")

    def refused(self) -> DataFrame:
        """(qid, reason, batch)"""
        return self.spark.read.parquet(f"{self.folder}/refused/*")


def coordinate_stream(stream: DataFrame, coordinator: Arrivals, checkpoint: str, **trigger):
    """Start the arrival loop on a streaming DataFrame of queries."""
    return stream.writeStream.foreachBatch(coordinator).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def window_requests(events: DataFrame, time: str, user: str, wants: list[str], length: str = "1 hour", late: str = "1 hour", slide: str | None = None) -> DataFrame:
    """(window_start, user, wants): what each user asked for in each window; works on streams (append mode) and on tables.

    ``time`` is cast to a zoned timestamp, as watermarks need one. With ``slide`` windows overlap.
    """
    stamped = events.withColumn("__at", F.col(time).cast("timestamp"))
    if events.isStreaming:
        stamped = stamped.withWatermark("__at", late)
    w = F.window("__at", length, slide) if slide else F.window("__at", length)
    return stamped.groupBy(w.alias("w"), F.col(user).alias("user")).agg(F.collect_set(F.struct(*wants)).alias("wants")).select(F.col("w.start").alias("window_start"), "user", "wants")


def session_requests(events: DataFrame, time: str, user: str, gap: str = "30 minutes") -> DataFrame:
    """(session, user, events): request lifetimes as sessions."""
    stamped = events.withColumn("__at", F.col(time).cast("timestamp"))
    if events.isStreaming:
        stamped = stamped.withWatermark("__at", gap)
    return stamped.groupBy(F.session_window("__at", gap).alias("s"), F.col(user).alias("user")).agg(F.count("*").alias("events")).select(F.col("s.start").alias("session_start"), F.col("s.end").alias("session_end"), "user", "events")
