"""Helpers shared by the training-data operators."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The separators of the word contracts: space and the controls 09 to 0D.
SEPARATORS = r"[\x20\x09-\x0D]+"


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def whole_text(name: str = "text") -> Column:
    """The text with null read as empty."""
    return F.coalesce(F.col(name), F.lit(""))


def shuffle_width(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def shared_folder(spark: SparkSession) -> str:
    """The folder that the cluster names in spark.checkpoint.dir; a local one is set only in local mode where none is."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named is None:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        named = "/tmp/checkpoints"
    return named


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut the lineage through the shared folder."""
    context = df.sparkSession.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint(eager=True)


def remove_folder(spark: SparkSession, path: str) -> None:
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hadoop, True)


class Scratch:
    """Tables in the shared folder that cut the lineage as checkpoints do, packed, and are removed once nothing needs them."""

    def __init__(self, spark: SparkSession) -> None:
        self.spark, self.folder, self.held = spark, f"{shared_folder(spark)}/tables-{uuid.uuid4()}", {}

    def table(self, df: DataFrame) -> DataFrame:
        path = f"{self.folder}/{len(self.held)}"
        self.held[len(self.held)] = path
        df.write.option("compression", "zstd").parquet(path)
        kept = self.spark.read.schema(df.schema).parquet(path)
        kept._scratch_path = path
        return kept

    def drop(self, *tables: DataFrame) -> None:
        for df in tables:
            remove_folder(self.spark, df._scratch_path)

    def close(self) -> None:
        remove_folder(self.spark, self.folder)


def unused(names: list[str], name: str) -> str:
    """A column name that is not taken, in any case."""
    taken = {n.lower() for n in names}
    while name.lower() in taken:
        name += "_"
    return name


def tidy(run: Callable) -> Callable:
    """The kernel, with memory given back to the system after each task: Python workers live on and would keep it."""

    def wrapped(batches: Iterator) -> Iterator:
        try:
            yield from run(batches)
        finally:
            import ctypes

            import pyarrow as pa

            pa.default_memory_pool().release_unused()
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
            if trim is not None:
                trim(0)

    return wrapped


def content_digest(text_col: str) -> Column:
    """SHA-256 of the normalised text: a run of separators counts as one space, null as empty."""
    return F.sha2(F.regexp_replace(whole_text(text_col), SEPARATORS, " ").cast("binary"), 256)


def repeats(known: DataFrame, id_col: str, digest: str) -> tuple[bool, bool]:
    """Whether any id repeats, and whether one repeats with different texts."""
    by_id = known.groupBy(id_col).agg(F.count(F.lit(1)).alias("rows"), (F.min(digest) != F.max(digest)).alias("differ")).filter("rows > 1")
    found = by_id.agg(F.count(F.lit(1)), F.max("differ")).first()
    return found[0] > 0, bool(found[1])


def one_row_per_text(df: DataFrame, id_col: str, text_col: str, digest: str) -> DataFrame:
    """Of the rows that repeat an id and a normalised text keep the first by text and by the other columns as text, so that
    rows which tie are equal (but for maps)."""
    from pyspark.sql import Window

    nth = unused(df.columns, "nth")
    whole = F.to_json(F.struct(*[F.col(f"`{f.name}`") for f in df.schema.fields if f.name not in (text_col, digest) and "map<" not in f.dataType.simpleString()]))
    ranked = df.withColumn(nth, F.row_number().over(Window.partitionBy(id_col, digest).orderBy(text_col, F.sha2(whole, 256))))
    return ranked.filter(F.col(nth) == 1).drop(nth)
