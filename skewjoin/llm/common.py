"""Shared plumbing of the training-data operators: reading, staging, components, batches."""

from __future__ import annotations

import ctypes
import re
import sys
import tempfile
import uuid
import weakref
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import wordhash

# functions travel to the executors by value, so the package need not be installed there
cloudpickle.register_pickle_by_value(sys.modules[__name__.partition(".")[0]])

#: Rows of an Arrow batch: with texts of a few thousand characters the default makes batches of tens of MB.
BATCH_ROWS = 2000

#: Bytes of text that one vectorised step takes at once (a longer text is taken alone).
SLICE_BYTES = 2 << 20


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir.  Where it is unset, a local session gets a
    temporary folder; on a cluster no folder of one machine would do, so that is an error."""
    path = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not path:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="skewjoin-shared-"))
        path = spark.sparkContext.getCheckpointDir()
    return path.rstrip("/")


def stage(df: DataFrame, name: str) -> DataFrame:
    """Write df once to the shared folder and read it back: cuts the lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    _STAGED[out] = path
    return out


_STAGED: weakref.WeakKeyDictionary = weakref.WeakKeyDictionary()


def release(*frames: DataFrame) -> None:
    """Delete the files of staged frames that nothing reads any more."""
    for df in frames:
        path = _STAGED.pop(df, None)
        if path is not None:
            spark = df.sparkSession
            where = spark._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def slices(offsets: np.ndarray, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int]]:
    """Cut n texts into runs of at most `limit` bytes, one text at least."""
    n, at = len(offsets) - 1, 0
    while at < n:
        upto = int(np.searchsorted(offsets, offsets[at] + limit, side="right")) - 1
        upto = min(max(upto, at + 1), n)
        yield at, upto
        at = upto


def column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def small_batches(spark: SparkSession) -> None:
    """Lower the session's batch size (a setting that may change at any time) if it is larger."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    have = int(spark.conf.get(name))
    if have <= 0 or have > BATCH_ROWS:
        spark.conf.set(name, str(BATCH_ROWS))


def released(run: Callable) -> Callable:
    """The batch function run, giving the worker's free memory back to the system at the end of each task.

    Workers live on from stage to stage; what one stage's allocator keeps would count against the next.
    """

    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of the GNU C library only
            if trim is not None:
                trim(0)

    return wrapped


def map_batches(df: DataFrame, fn: Callable[[pa.RecordBatch], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """mapInArrow with a function of one batch; empty batches are passed over."""

    wordhash.forget()
    small_batches(df.sparkSession)

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                yield from fn(batch)

    return df.mapInArrow(released(run), schema)


#: Keys with over 1 / HUBS of all rows, and over HUB_ROWS, are joined by broadcast; there are at most HUBS of them.
#: HUB_ROWS rows of a few numbers are little for one task, and a plan without broadcasts is lighter for the driver.
HUBS, HUB_ROWS = 1000, 100_000


def hub_join(rows: DataFrame, small: DataFrame, key: str, size: str, total: int) -> DataFrame:
    """rows joined by `key` with `small`, one row a key, whose column `size` is at least the number of rows of the key.

    total: the sum of `size`.  A key with a large part of the rows would be one task of a shuffled
    join; such keys, at most HUBS, are sent to the rows instead.
    """
    bound = max(total / HUBS, HUB_ROWS)
    if total <= bound:
        return rows.join(small, key)
    hubs = F.broadcast(small.where(F.col(size) > bound))
    light = rows.join(hubs.select(key), key, "left_anti").join(small.where(F.col(size) <= bound), key)
    return rows.join(hubs, key).unionByName(light)


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component), staged: the smallest node reachable, for each node that has an edge.

    Alternating large-star and small-star rounds on the distributed edge list, each a
    groupBy of linear size, staged in the shared folder, until an edge list repeats itself
    (the rounds grow with the logarithm of the longest chain).  A node with very many
    neighbours is combined before the shuffle (min), its edges stay separate rows, and
    what it learns is sent to them, so no group is collected.  Null ends are dropped.
    """

    def both(e: DataFrame) -> DataFrame:
        return e.select("a", "b").union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))

    def digest(e: DataFrame):
        row = e.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")).first()
        return row["n"], row["h"]

    cur = (
        edges.select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b"))
        .where("a is not null and b is not null and a <> b").distinct()
    )
    cur = stage(cur, "cc")
    last = digest(cur)
    while last[0]:
        # large star: larger neighbours of every node move to its smallest neighbour
        two = both(cur)
        low = two.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"), F.count(F.lit(1)).alias("size"))
        big = hub_join(two.where("b > a"), low, "a", "size", 2 * last[0]).select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        # small star: a node and its smaller neighbours move to the smallest of them
        low2 = big.groupBy("a").agg(F.min("b").alias("m"), F.count(F.lit(1)).alias("size"))
        new = (
            hub_join(big, low2, "a", "size", last[0]).select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b")
            .union(low2.select("a", F.col("m").alias("b"))).distinct()
        )
        new = stage(new, "cc")
        release(cur)
        cur, now = new, digest(new)
        if now == last:
            break
        last = now
    node = cur.groupBy("a").agg(F.min("b").alias("component"))
    roots = cur.select("b").distinct().select(F.col("b").alias("node"), F.col("b").alias("component"))
    out = stage(node.select(F.col("a").alias("node"), "component").union(
        roots.join(node.select(F.col("a").alias("node")), "node", "left_anti")
    ), "components")
    release(cur)
    return out
