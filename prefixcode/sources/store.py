"""Sorted runs at rest: a stepped-merge store, and sorted indexes with look-up joins.

A run is a Parquet folder with its offset column, sorted on the key in each of its files. A level that
has ``fan_in`` runs is merged into one run of the next level by the codes at rest: every row is written
once a level, and no key is compared to make its code again. What runs there are is kept beside them
in a catalogue of small numbered files, so a new driver finds them, and a batch that comes again adds
nothing.
"""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prefixcode.functions.keys import key_spec
from prefixcode.operators.derive import attach_blocks
from prefixcode.operators.sort import bucket_by, merge_packets
from prefixcode.plans.frame import CODE, OFFSET
from prefixcode.sources import scratch
from prefixcode.sources.formats import POS, positions


def write_sorted(df: DataFrame, keys: list[str], path: str, partitions: int | None = None) -> None:
    """Range-partitioned and sorted, so footers' smallest and largest keys prune files."""
    order = [k.order() for k in key_spec(keys)]
    df.repartitionByRange(*([partitions] if partitions else []), *order).sortWithinPartitions(*order).write.parquet(path)


class RunStore:
    """Runs by level, under a folder that all see. The catalogue is a few names; rows never come to the driver."""

    def __init__(self, spark: SparkSession, keys: list[str], fan_in: int = 4, path: str | None = None, buckets: int = 2):
        self.spark, self.keys, self.fan_in, self.buckets = spark, keys, fan_in, buckets
        self.path = path or scratch.fresh(spark, "store")
        self.version, self.levels, self.batches, self.rewrites = 0, [], set(), 0
        self._load()

    def _load(self) -> None:
        found = [name for name in scratch.listed(self.spark, f"{self.path}/_catalogue") if name.endswith(".json")]
        if found:
            last = max(found)
            state = json.loads(scratch.read_text(self.spark, f"{self.path}/_catalogue/{last}"))
            self.version, self.levels, self.batches, self.rewrites = int(last[:-5]), state["levels"], set(state["batches"]), state["rewrites"]

    def _save(self, gone: list[str]) -> None:
        """A new catalogue appears whole or not at all; only then do files it no longer names go."""
        self.version += 1
        text = json.dumps({"levels": self.levels, "batches": sorted(self.batches), "rewrites": self.rewrites})
        scratch.write_text(self.spark, f"{self.path}/_catalogue/{self.version:012d}.json", text)
        for name in gone:
            scratch.remove(self.spark, f"{self.path}/{name}")

    def append_run(self, df: DataFrame, batch: int | None = None) -> None:
        """Add a sorted run; a batch that was added before is ignored, so retries do no harm."""
        if batch is not None and batch in self.batches:
            return
        name = self._name("run")
        of = attach_blocks(df.withColumn("bucket", bucket_by(df, self.keys, self.buckets, "range")), self.keys, "bucket")
        self._write(positions(of).drop(CODE), name)
        gone = self._put(0, name)
        if batch is not None:
            self.batches.add(batch)
        self._save(gone)

    def _name(self, label: str) -> str:
        return scratch.fresh(self.spark, label).rsplit("/", 1)[1]

    def _write(self, df: DataFrame, name: str) -> None:
        """Rows as they come, in order in every bucket, with their place in the run: __seq."""
        df.withColumn("__seq", F.shiftleft(F.col("bucket").cast("long"), 40) + F.col(POS)).drop("bucket", POS).write.parquet(f"{self.path}/{name}")

    def _put(self, level: int, name: str) -> list[str]:
        """Runs that a merge has taken in."""
        while len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append(name)
        if len(self.levels[level]) < self.fan_in:
            return []
        parts, self.levels[level] = self.levels[level], []
        merged = self._name(f"level{level + 1}")
        self._write(self.merged(parts), merged)
        self.rewrites += 1
        return [*parts, *self._put(level + 1, merged)]

    def _read(self, names: list[str]) -> DataFrame:
        out = None
        for i, name in enumerate(names):
            x = self.spark.read.parquet(f"{self.path}/{name}").withColumn("__run", F.lit(i).cast("long"))
            out = x if out is None else out.unionByName(x)
        return out

    def merged(self, names: list[str] | None = None, counters: bool = False) -> DataFrame:
        """Runs (all) merged by the codes they were stored with: bucket, __pos, the columns, __off.

        Buckets are ranges of the first key column, so a run's first row in a bucket differs from its
        predecessor there: the stored code is right whatever the bounds, in this merge and any later one.
        """
        runs = self._read(names or [x for level in self.levels for x in level])
        return merge_packets(runs.withColumn("__bucket", bucket_by(runs, self.keys, self.buckets, "range")), self.keys, counters=counters)

    def scan(self) -> DataFrame:
        """All rows of all runs; ``merged`` has them in one order."""
        return self._read([x for level in self.levels for x in level]).drop(OFFSET, "__run", "__seq")


def build_index(df: DataFrame, keys: list[str], partitions: int, on_hash: bool = False) -> str:
    """A sorted index; gives its path. On hash values: the key is one 64-bit number, __h. The key range of
    each file is kept beside it."""
    spark = df.sparkSession
    path = scratch.fresh(spark, "index")
    at = "__h" if on_hash else keys[0]
    write_sorted(df.withColumn("__h", F.xxhash64(*keys)) if on_hash else df, ["__h"] if on_hash else keys, f"{path}/rows", partitions)
    rows = spark.read.parquet(f"{path}/rows").select(F.element_at(F.split(F.input_file_name(), "/"), -1).alias("file"), F.col(at).alias("__k"))
    rows.groupBy("file").agg(F.min("__k").alias("lo"), F.max("__k").alias("hi")).coalesce(1).write.parquet(f"{path}/ranges")  # a row for each file
    return path


def lookup_join(probe: DataFrame, probe_key: str, path: str, index_key: str, on_hash: bool = False) -> DataFrame:
    """Probe rows with their matches. Each probe finds the files whose key range holds its key; only
    those files are opened, and probes meet the rows of the files they were led to."""
    spark = probe.sparkSession
    at = "__h" if on_hash else index_key
    p = probe.withColumn("__p", F.xxhash64(probe_key) if on_hash else F.col(probe_key))
    ranges = spark.read.parquet(f"{path}/ranges").where("lo is not null")
    led = p.select("__p").distinct().join(F.broadcast(ranges), F.col("__p").between(F.col("lo"), F.col("hi"))).select("file").distinct()
    files = sorted(r["file"] for r in led.collect())  # at most a name for each file of the index
    index = spark.read.parquet(*[f"{path}/rows/{f}" for f in files]) if files else spark.read.parquet(f"{path}/rows").limit(0)
    on = F.col("__p") == F.col(at)
    if on_hash:
        on = on & (F.col(probe_key) == F.col(index_key))
    out = p.join(index, on).drop("__p")
    return out.drop("__h") if on_hash else out
