"""Reading the tables, and tables of the engine's own in the shared folder."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid
import zipfile
from collections.abc import Callable
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ngramlake.functions.text import tokens


def ship(spark: SparkSession) -> None:
    """Give this package to workers that lack it, once per application."""
    sc, root = spark.sparkContext, Path(__file__).resolve().parents[1]
    if getattr(sc, "_ngram_shipped", False) or not root.is_dir():
        return
    at = Path(tempfile.mkdtemp(prefix="ngramlake-ship-"))
    name = at / f"engine-{uuid.uuid4().hex[:8]}.zip"
    with zipfile.ZipFile(name, "w") as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, p.relative_to(root.parent))
    sc.addPyFile(str(name))
    atexit.register(shutil.rmtree, at, ignore_errors=True)
    sc._ngram_shipped = True


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; a temporary folder only where it is unset and all tasks
    run on this machine."""
    at = spark.conf.get("spark.checkpoint.dir", None) or getattr(spark, "_ngram_dir", None)
    if not at:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        at = spark._ngram_dir = "file://" + tempfile.mkdtemp(prefix="ngramlake-")
    return at


def spool(df: DataFrame, name: str, path: str | None = None, by: list[str] | None = None) -> DataFrame:
    """Write and reread: cuts the lineage at files that outlive an executor.  ``by`` are
    columns that become folders."""
    spark = df.sparkSession
    own = path is None
    path = path or f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    out = df.write.option("compression", "zstd")
    (out.partitionBy(*by) if by else out).parquet(path)
    if own:
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(where)
    return spark.read.schema(df.schema).parquet(path)


def spread(df: DataFrame) -> DataFrame:
    """An input of fewer splits than cores, dealt to all cores; others stay as they are."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


def once(spark: SparkSession, key: tuple, build: Callable[[], object]) -> object:
    """Index once, search often: what was built for a path in this application."""
    held = spark.__dict__.setdefault("_ngram_built", {})
    if key not in held:
        held[key] = build()
    return held[key]


def corpus(docs: DataFrame, id_col: str = "doc_id", text: str = "text", mode: str = "word", keep: tuple[str, ...] = (), where: Column | None = None) -> DataFrame:
    """``doc_id, tokens`` and the columns ``keep``; null text has no tokens."""
    rows = docs if where is None else docs.where(where)
    return rows.select(F.col(id_col).alias("doc_id"), *keep, F.coalesce(tokens(F.col(text), mode), F.array().cast("array<string>")).alias("tokens"))


def restrict(docs: DataFrame, labels: DataFrame, condition: Column, id_col: str = "doc_id") -> DataFrame:
    """Documents whose label row meets a condition (candidates by metadata)."""
    return docs.join(labels.where(condition).select(id_col).distinct(), id_col, "left_semi")


def read_any(spark: SparkSession, path: str, form: str, schema=None, **options) -> DataFrame:
    """Text, JSON lines, CSV, ORC or Parquet with an explicit schema."""
    r = spark.read.options(**options)
    return (r.schema(schema) if schema else r).format(form).load(path)


def hash_sample(df: DataFrame, key: str, n: int) -> DataFrame:
    """``n`` rows of least md5: the deterministic sample of big test sets (a top-k)."""
    return df.orderBy(F.md5(F.col(key).cast("string")), key).limit(n)
