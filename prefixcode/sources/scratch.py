"""Written intermediate tables in the folder that all executors share."""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_MADE: list[tuple[SparkSession, str]] = []


def root(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir; a local temporary one only for a local master without it."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    if not path:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        path = f"file://{tempfile.gettempdir()}/checkpoints"
    return path.rstrip("/")


def fresh(spark: SparkSession, label: str) -> str:
    path = f"{root(spark)}/{label}-{uuid.uuid4().hex}"
    _MADE.append((spark, path))
    return path


def cut(df: DataFrame, label: str) -> DataFrame:
    """Write and read back: the lineage ends in a table that survives lost executors."""
    path = fresh(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def remove(spark: SparkSession, path: str) -> None:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


_TABLES: list[tuple[SparkSession, str]] = []


def bucketed(df: DataFrame, keys: list[str], buckets: int, label: str) -> DataFrame:
    """Written as a table of buckets by the keys, sorted inside, in the shared folder: joins and groups by the
    keys need no exchange. The table's name goes with the driver."""
    spark = df.sparkSession
    name = f"pc_{label}_{uuid.uuid4().hex}"
    df.write.bucketBy(buckets, *keys).sortBy(*keys).option("path", fresh(spark, label)).saveAsTable(name)
    _TABLES.append((spark, name))
    return spark.table(name)


def _fs(spark: SparkSession, path: str) -> tuple:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), p


def listed(spark: SparkSession, path: str) -> list[str]:
    """Names in a folder, or none if it isn't there."""
    fs, p = _fs(spark, path)
    return [f.getPath().getName() for f in fs.listStatus(p)] if fs.exists(p) else []


def write_text(spark: SparkSession, path: str, text: str) -> None:
    """A small file that appears whole: written under another name, then renamed."""
    fs, p = _fs(spark, path)
    part = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{path}.part")
    out = fs.create(part, True)
    out.write(bytearray(text.encode()))
    out.close()
    if not fs.rename(part, p):
        raise OSError(f"{path} can't be written")


def read_text(spark: SparkSession, path: str) -> str:
    return "\n".join(r[0] for r in spark.read.text(path).collect())  # a small file


@atexit.register
def _clear() -> None:
    for spark, name in _TABLES:
        try:
            spark.sql(f"DROP TABLE IF EXISTS {name}")
        except Exception:  # noqa: BLE001  the session may have ended
            pass
    for spark, path in _MADE:
        try:
            remove(spark, path)
        except Exception:  # noqa: BLE001  the session may have ended
            pass
