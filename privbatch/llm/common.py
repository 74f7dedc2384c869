"""Shared pieces of the training-data operators.

* ``Scratch`` cuts lineage by writing a table in the folder the cluster names in
  ``spark.checkpoint.dir`` (a folder of its own is set only where none is named).
* ``components`` finds connected components with DataFrame joins only.
* ``held_out`` is the fold rule shared by the learned operators.
"""

from __future__ import annotations

import atexit
import gc
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The shared checkpoint folder of the session.

    Where the session names none, a local session gets a temporary folder of its own; on a
    cluster that folder would be another one on every machine, so there it is an error.
    """
    named = spark.conf.get("spark.checkpoint.dir", "") or ""
    if named:
        return named.rstrip("/")
    held = spark.sparkContext.getCheckpointDir()
    if not held:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("name a folder that all machines share in spark.checkpoint.dir")
        spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="privbatch-"))
        held = spark.sparkContext.getCheckpointDir()
    return held.rstrip("/")


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    if jvm is None:
        return
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


class Scratch:
    """Tables written in the shared folder during one operator call.

    ``keep`` writes a DataFrame once and returns the table read back, so that a lost
    executor costs only the tasks that were running.  ``drop`` removes tables that no
    plan needs any more; the rest go when the driver process ends.
    """

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.root = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
        self.paths: dict[int, str] = {}
        self.n = 0
        atexit.register(self._end)

    def keep(self, df: DataFrame) -> DataFrame:
        path = f"{self.root}/{self.n}"
        self.n += 1
        df.write.mode("overwrite").parquet(path)
        back = self.spark.read.schema(df.schema).parquet(path)
        self.paths[id(back)] = path
        back._scratch_path = path
        return back

    def release(self) -> None:
        """Lets the session delete shuffle files that no plan needs any more; it does so as its driver collects garbage.

        The driver's threads hold on to the job that ended last, so a small one takes its place first.
        """
        self.spark.range(1).write.format("noop").mode("overwrite").save()
        gc.collect()
        self.spark.sparkContext._jvm.System.gc()

    def drop(self, *tables: DataFrame) -> None:
        for t in tables:
            _delete(self.spark, t._scratch_path)

    def clear(self) -> None:
        """Removes all tables, once no plan needs them."""
        _delete(self.spark, self.root)
        self.release()

    def _end(self) -> None:
        try:
            _delete(self.spark, self.root)
        except Exception:  # the JVM may be gone by then; the folder is the cluster's scratch space
            pass


def held_out(doc_id: Column) -> Column:
    """True for the documents no model may learn from: crc32 of the id as text, modulo 3, is 1."""
    return F.coalesce(F.crc32(F.encode(doc_id.cast("string"), "UTF-8")) % 3 == 1, F.lit(False))


def _settled(now: DataFrame) -> bool:
    """Whether the distinct links (u, v), v smaller, are stars: no node has two v, and none that has one is the v of another."""
    ends = now.select(F.col("u").alias("node"), F.lit(1).alias("up"), F.lit(0).alias("down"))
    ends = ends.unionByName(now.select(F.col("v").alias("node"), F.lit(0).alias("up"), F.lit(1).alias("down")))
    own = ends.groupBy("node").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
    return own.where("up > 1 OR (up = 1 AND down = 1)").isEmpty()


def components(scratch: Scratch, edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Connected components of an undirected graph, as (node, root): root is the smallest node.

    ``edges`` has two BIGINT columns a and b; loops and repeats do no harm; nodes without an
    edge to another node are not returned.  Alternates two star contractions: every node
    hands its larger neighbours to its smallest neighbour, then its smaller ones.  Each step
    is one partial aggregation and one join whose large side can be split, so a hub with a
    third of all links stays spread out.  The rounds grow with the logarithm of the longest path.
    """
    lo, hi = F.least("a", "b"), F.greatest("a", "b")
    now = scratch.keep(edges.where(F.col("a") != F.col("b")).select(hi.alias("u"), lo.alias("v")).distinct())
    for _ in range(max_rounds):
        if _settled(now):
            return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(
                now.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
            )
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        large = scratch.keep(large)
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        small = small.unionByName(least.select("u", F.col("m").alias("v"))).where("u <> v")
        small = small.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
        after = scratch.keep(small)
        scratch.drop(now, large)
        now = after
    raise RuntimeError(f"components: not settled after {max_rounds} rounds")
