"""What several operators share: shared storage, row plumbing, bounded collection."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors see. On one machine, where the session names none, a temporary one; elsewhere an error."""
    sc = spark.sparkContext
    folder = sc._conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        current = sc._jsc.sc().getCheckpointDir()
        if current.isDefined():
            folder = current.get()
        elif sc.master.startswith("local") and not sc.master.startswith("local-cluster"):
            folder = tempfile.mkdtemp(prefix="figmine-")
        else:
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    return folder.rstrip("/")


def stored(df: DataFrame, label: str, compression: str = "snappy") -> DataFrame:
    """``df`` written once as Parquet in the shared folder and read back: cuts the lineage and survives lost executors."""
    return Scratch(df.sparkSession).put(df, label, compression)


class Scratch:
    """Written tables of one run, each dropped as soon as nothing reads it any more."""

    def __init__(self, spark: SparkSession):
        self.spark, self.folder, self.paths = spark, shared_folder(spark), {}

    def put(self, df: DataFrame, label: str, compression: str = "zstd") -> DataFrame:
        path = f"{self.folder}/{label}-{uuid.uuid4().hex}"
        df.write.option("compression", compression).parquet(path)
        back = self.spark.read.schema(df.schema).parquet(path)
        self.paths[id(back)] = (back, path)
        return back

    def drop(self, *tables: DataFrame) -> None:
        for table in tables:
            _, path = self.paths.pop(id(table))
            where = self.spark._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(where, True)


def free_names(df: DataFrame, *names: str) -> list[str]:
    """The names, changed until no column of ``df`` has them in any case of letters."""
    taken = {c.lower() for c in df.columns}
    out = []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def bounded_batches(spark: SparkSession, rows: int = 1000) -> None:
    """Arrow batches of at most ``rows`` rows, so that long texts do not pile up in a Python worker."""
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > rows:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", rows)


def lower_ascii(col):
    """A-Z to a-z and nothing else."""
    return F.translate(col, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def remainder(doc_id, modulus: int):
    """crc32 of the id as text, modulo ``modulus``; null where the id is null."""
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % modulus
