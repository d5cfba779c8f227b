"""The given tables, normalised corpora, and the shared scratch folder."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One table, read lazily; projections and filters reach the scan."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def views(spark: SparkSession, sf_dir: str, *names: str) -> None:
    """Registers tables as temporary views of this session, replacing those of another folder."""
    for name in names or TABLES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def scratch(spark: SparkSession) -> str:
    """A fresh folder below the checkpoint folder that every executor shares; it goes when the program ends. Only a local master may do without that setting."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="semfilter-")
        spark.sparkContext.setCheckpointDir(base)
    root = f"{base.rstrip('/')}/semfilter-{spark.sparkContext.applicationId}"
    if root not in _roots:
        _roots.add(root)
        atexit.register(_remove, spark, root)
    return f"{root}/{uuid.uuid4().hex}"


_roots: set[str] = set()


def _remove(spark: SparkSession, root: str) -> None:
    try:
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(root)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    except Exception:  # the JVM may be gone already; the folder belongs to the cluster's clean-up then
        pass


def save(df: DataFrame) -> DataFrame:
    """Writes a frame to scratch and reads it back; what an oracle answered is never asked again."""
    path = scratch(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def words(text):
    """Number of white-space separated words, null as none."""
    return F.coalesce(F.size(F.filter(F.split(text, r"\s+"), lambda x: x != "")), F.lit(0))


def normalise(df: DataFrame, id_col: str, text_col: str, *attrs: str) -> DataFrame:
    """A corpus: ``doc_id, text, n_tokens, attrs``; null text is an empty document, never dropped."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    packed = F.struct(*[F.col(a) for a in attrs]) if attrs else F.struct(F.lit(None).cast("string").alias("none"))
    return df.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("text"), words(text).cast("int").alias("n_tokens"), packed.alias("attrs"))


def strip_html(html):
    """Visible text of a page: script and style go with their content, tags and entities become blanks."""
    bare = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    bare = F.regexp_replace(F.regexp_replace(bare, r"<[^>]*>", " "), r"&[a-zA-Z#0-9]+;", " ")
    return F.trim(F.regexp_replace(bare, r"\s+", " "))


def corpus(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A text corpus in the shape of ``documents``: stripped pages, or one document a turn of a conversation."""
    if name == "documents":
        return table(spark, sf_dir, name)
    if name == "pages":
        text = table(spark, sf_dir, name).select(F.col("page_id").alias("doc_id"), strip_html(F.col("html")).alias("text"), F.regexp_extract("html", r'lang="?([a-z]{2})', 1).alias("lang"), F.regexp_extract("url", r"//([^/]+)", 1).alias("source"))
    elif name == "conversations":
        text = table(spark, sf_dir, name).select((F.col("conv_id") * 1000 + F.col("turn")).alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"), F.lit("").alias("lang"), F.col("role").alias("source"))
    else:
        raise ValueError(f"no text corpus {name}")
    return text.withColumn("n_chars", F.length("text").cast("long"))
