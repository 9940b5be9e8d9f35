"""The kept gradient index: written once as Parquet, read by every scoring after that.

A row holds a document's labels and, for each module, its token count and summed signs; gradients under any model
follow from them row by row, so one index serves all checkpoints, query sets, masks and cohorts.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from binlens.operators import attribution as at
from binlens.sources.tables import spread, table, tokens


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one, removed at exit, only for a local master without that setting."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or getattr(spark, "_binlens_temporary", None)
    if not folder:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        made = tempfile.mkdtemp(prefix="binlens-")
        atexit.register(shutil.rmtree, made, ignore_errors=True)
        folder = spark._binlens_temporary = f"file://{made}"
    return folder.rstrip("/")


def write_index(docs: DataFrame, path: str, labels: tuple[str, ...] = ("topic", "format")) -> None:
    """``docs``: doc_id, text and labels."""
    at.sign_sums(spread(docs), ["doc_id", *labels], tokens(F.col("text"))).write.mode("overwrite").parquet(path)


def read_index(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def stamp(rows: DataFrame) -> tuple:
    """What tells one state of a file table from another: rows, files, their bytes and the last change; no column is read."""
    file = F.struct(*[F.col(f"_metadata.file_{x}").alias(x) for x in ("path", "size", "modification_time")])
    files = rows.groupBy(file.alias("f")).agg(F.count("*").alias("n"))
    return tuple(files.agg(F.sum("n"), F.count("*"), F.sum("f.size"), F.max("f.modification_time"), F.sum(F.xxhash64("f.path").cast("decimal(38,0)"))).first())


def kept(spark: SparkSession, name: str, sources: list[DataFrame], write) -> DataFrame:
    """What ``write(path)`` makes, from this session's earlier call if the sources are still the same files and what was
    made of them is still there."""
    made = spark.__dict__.setdefault("_binlens_kept", {})
    key = (name, *[stamp(s) for s in sources])
    if key in made:
        try:
            return spark.read.parquet(made[key])
        except AnalysisException:  # the folder was cleared
            del made[key]
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    write(path)
    made[key] = path
    return spark.read.parquet(path)


def corpus_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, topic, format, uni, bi) of all documents."""
    docs = table(spark, sf_dir, "documents")
    labelled = docs.select("doc_id", F.col("source").alias("topic"), F.col("lang").alias("format"), "text")
    return kept(spark, "index", [docs], lambda path: write_index(labelled, path))


def base_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The one row of the model made from all documents, kept beside their index."""
    sums = corpus_index(spark, sf_dir)
    return kept(spark, "model", [table(spark, sf_dir, "documents")], lambda path: at.model_means(sums).write.parquet(path))
