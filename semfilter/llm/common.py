"""Helpers shared by the training-data operators."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of one Arrow batch on its way to a Python worker; rows of text may be long.
BATCH_BYTES = 4 << 20

_roots: dict[str, SparkSession] = {}


def read_table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """One of the given tables, through Spark's reader only, pruned to the columns named."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def session_defaults(spark: SparkSession) -> None:
    """Runtime settings that the Python stages rely on: small Arrow batches, adaptive plans."""
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "1000")


def lean() -> None:
    """Makes a Python worker give memory back that it no longer uses; workers outlive their tasks."""
    import ctypes

    import pyarrow as pa

    pa.set_memory_pool(pa.system_memory_pool())
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library: nothing to trim
        pass


def tidy(run):
    """A step over Arrow batches whose worker gives memory back after each of them, and before and after all."""

    def lean_run(batches):
        lean()
        for out in run(batches):
            yield out
            lean()
        lean()

    return lean_run


def scratch_dir(spark: SparkSession) -> str:
    """A folder of this application below ``spark.checkpoint.dir``, which every executor shares.

    Only where that setting is absent and the master is local a temporary folder is made and set.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="semfilter-")
        spark.sparkContext.setCheckpointDir(base)
    root = f"{base.rstrip('/')}/semfilter-{spark.sparkContext.applicationId}"
    if root not in _roots:
        _roots[root] = spark
        atexit.register(_remove, root)
    return root


def _remove(root: str) -> None:
    spark = _roots.pop(root, None)
    try:
        jvm = spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(root)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    except Exception:  # the JVM may be gone already; the folder belongs to the cluster's clean-up then
        pass


def save(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` as Parquet into the shared scratch folder and read it back: lineage ends here.

    A lost executor costs at most the tasks of the job at hand, and nothing is computed twice.
    """
    spark = df.sparkSession
    path = f"{scratch_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def same(left: list[Column], right: list[Column]) -> Column:
    """Null-safe equality of two key tuples."""
    out = F.lit(True)
    for a, b in zip(left, right, strict=True):
        out = out & a.eqNullSafe(b)
    return out


def clear(name: str, taken: list[str]) -> str:
    """``name``, or with as many underscores in front as it takes to differ from the columns ``taken`` (in any case of letters)."""
    low = {c.lower() for c in taken}
    while name.lower() in low:
        name = f"_{name}"
    return name


def running_start(counts: DataFrame, group: list[str], bucket: str, n: str, out: str) -> DataFrame:
    """Adds ``out``: the sum of ``n`` over smaller buckets of the group.

    Buckets come by the million at scale, so sums run inside runs of 1024 buckets, over the
    totals of those runs, and are added; no window holds a whole large group.
    """
    from pyspark.sql import Window as W

    coarse = counts.withColumn("_run", F.shiftright(F.col(bucket), 10))
    inner = W.partitionBy(*group, "_run").orderBy(bucket).rowsBetween(W.unboundedPreceding, -1)
    fine = coarse.withColumn("_in", F.coalesce(F.sum(n).over(inner), F.lit(0)))
    outer = W.partitionBy(*group).orderBy("_run").rowsBetween(W.unboundedPreceding, -1)
    totals = coarse.groupBy(*group, "_run").agg(F.sum(n).alias("_t")).withColumn("_before", F.coalesce(F.sum("_t").over(outer), F.lit(0)))
    a, b = fine.alias("a"), totals.alias("b")
    keys = same([F.col(f"a.{k}") for k in [*group, "_run"]], [F.col(f"b.{k}") for k in [*group, "_run"]])
    return a.join(b, keys).select("a.*", (F.col("a._in") + F.col("b._before")).cast("long").alias(out)).drop("_run", "_in")


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Connected components of an undirected edge list, as ``node, component`` (smallest id).

    Alternating large-star and small-star contraction: each round is aggregations and joins of
    id pairs, written to scratch; rounds grow with the logarithm of the size. Nodes without an
    edge do not appear. Nothing but a count and a checksum per round reaches the driver.
    """
    pairs = save(edges.select(F.greatest(a, b).alias("v"), F.least(a, b).alias("u")).filter("u <> v").distinct(), "edges")
    seen = None
    while not pairs.isEmpty():
        both = pairs.select("u", "v").union(pairs.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
        large = both.join(low, "u").filter("v > u").select("v", F.col("m").alias("u")).filter("u <> v")
        least = large.groupBy("v").agg(F.min("u").alias("m"))
        star = large.join(least, "v")
        small = star.select(F.col("u").alias("v"), F.col("m").alias("u")).union(least.select("v", F.col("m").alias("u"))).filter("u <> v").distinct()
        pairs = save(small, "stars")
        mark = pairs.agg(F.count("*"), F.expr("bit_xor(xxhash64(v, u))")).first()
        if mark == seen:
            break
        seen = mark
    roots = pairs.select(F.col("v").alias("node"), F.col("u").alias("component"))
    return roots.union(roots.select(F.col("component"), F.col("component")).distinct())
