"""Where states live between batches.

Every backend folds a delta (a state of the batch) into what it holds and hands out the merged frame.  A fold may
name its version, e.g. a stream's batch id: a version that is already in the state is not folded again.
"""

from __future__ import annotations

import json
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltafold.functions.monoids import SUPPORT
from deltafold.plans.partial import Group, lineage_columns, merged
from deltafold.session import checkpoint_folder


class Files:
    """Small files and folders in any store that Spark reaches."""

    def __init__(self, spark: SparkSession, folder: str):
        jvm = spark.sparkContext._jvm
        self.make = jvm.org.apache.hadoop.fs.Path
        self.folder = folder
        self.fs = self.make(folder).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def _path(self, name: str = ""):
        return self.make(f"{self.folder}/{name}" if name else self.folder)

    def put(self, name: str, text: str) -> None:
        """Writes a file aside and renames it, so that it is there as a whole or not at all."""
        aside = self._path(f".{uuid.uuid4().hex}")
        out = self.fs.create(aside, True)
        out.write(bytearray(text.encode()))
        out.close()
        to = self._path(name)
        self.fs.mkdirs(to.getParent())
        if self.fs.exists(to):
            self.fs.delete(to, False)
        if not self.fs.rename(aside, to):
            raise OSError(f"{name} was not renamed into place")

    def get(self, name: str) -> str:
        stream = self.fs.open(self._path(name))
        try:
            return bytes(stream.readAllBytes()).decode()
        finally:
            stream.close()

    def names(self, folder: str) -> list[str]:
        path = self._path(folder)
        return [s.getPath().getName() for s in self.fs.listStatus(path)] if self.fs.exists(path) else []

    def drop(self, name: str = "") -> None:
        self.fs.delete(self._path(name), True)


class Pointers:
    """Numbered pointers, each a JSON file; the greatest number is the newest."""

    def __init__(self, files: Files, folder: str = "pointers"):
        self.files, self.folder = files, folder

    def versions(self) -> list[int]:
        return sorted(int(n[1:]) for n in self.files.names(self.folder) if n.startswith("v") and n[1:].isdigit())

    def read(self, version: int) -> dict:
        return json.loads(self.files.get(f"{self.folder}/v{version}"))

    def write(self, version: int, said: dict) -> None:
        self.files.put(f"{self.folder}/v{version}", json.dumps(said))

    def drop(self, version: int) -> None:
        self.files.drop(f"{self.folder}/v{version}")


class MemoryState:
    """Held in executors, hash-partitioned by lineage: only the delta moves.  Every ``cut_every`` versions the
    rows go to the shared folder, so a lost executor costs a bounded recomputation.  It ends with the session."""

    durable = False

    def __init__(self, spark: SparkSession, group: Group, partitions: int | None = None, cut_every: int = 8, how: str = "union"):
        self.spark, self.group, self.cut_every, self.how = spark, group, cut_every, how
        self.partitions = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
        self.version, self.folds, self.held = -1, 0, None

    def _dealt(self, df: DataFrame) -> DataFrame:
        keys = lineage_columns(df.columns)
        return df.repartition(self.partitions, *keys) if keys else df

    def fold(self, delta: DataFrame, version: int | None = None) -> DataFrame:
        version = self.version + 1 if version is None else version
        if version <= self.version:
            return self.held
        before, self.version, self.folds = self.held, version, self.folds + 1
        if before is None:
            new = self._dealt(delta)
        elif self.how == "union":
            new = merged(before.unionByName(self._dealt(delta)), self.group)
        else:
            from deltafold.operators.merge import merge_states

            new = merge_states(before, delta, lineage_columns(before.columns), dict(self.group.parts()), how="join")
        if self.folds > 1 and (self.folds - 1) % self.cut_every == 0:
            checkpoint_folder(self.spark)
            new = self._dealt(new.checkpoint(eager=True))
        self.held = new.persist()
        self.held.count()  # one job: the new version stands before the old one goes
        if before is not None:
            before.unpersist()
        return self.held

    def read(self) -> DataFrame:
        return self.held

    def close(self) -> None:
        if self.held is not None:
            self.held.unpersist()


class LayeredState:
    """Deltas are appended as files; every ``compact_every`` versions they become one layer.  A version counts
    once its pointer is written, so a batch that is replayed writes the same version again.  The last two
    versions can be restored; layers that neither needs go."""

    durable = True

    def __init__(self, spark: SparkSession, group: Group, folder: str | None = None, compact_every: int = 4):
        self.spark, self.group, self.compact_every = spark, group, compact_every
        self.folder = folder or f"{checkpoint_folder(spark)}/state-{uuid.uuid4().hex}"
        self.files = Files(spark, self.folder)
        self.pointers = Pointers(self.files)
        self.layers: list[str] = []
        self.version = -1
        self.restore(max(self.pointers.versions(), default=-1))

    def restore(self, version: int) -> None:
        """Goes back to a version; later ones are forgotten."""
        for v in self.pointers.versions():
            if v > version:
                self.pointers.drop(v)
        there = [v for v in self.pointers.versions() if v <= version]
        self.version, self.layers = version, []
        if there:
            self.layers = self.pointers.read(there[-1])["layers"]
        elif version >= 0:
            raise ValueError(f"{self.folder} has no version {version}")

    def fold(self, delta: DataFrame, version: int | None = None) -> DataFrame:
        version = self.version + 1 if version is None else version
        if version <= self.version:
            return self.read()  # a replay of a batch that was committed
        name = f"v{version}-{uuid.uuid4().hex[:8]}"  # another name for each try: nothing that a pointer names changes
        delta.write.parquet(f"{self.folder}/{name}")
        layers = [*self.layers, name]
        if len(layers) > self.compact_every:
            whole = f"c{version}-{uuid.uuid4().hex[:8]}"
            self._union(layers).write.parquet(f"{self.folder}/{whole}")
            layers = [whole]
        self.version, self.layers = version, layers
        self.pointers.write(version, {"version": version, "layers": layers})
        self._sweep()
        return self.read()

    def _sweep(self) -> None:
        versions = self.pointers.versions()
        for v in versions[:-2]:
            self.pointers.drop(v)
        needed = {x for v in versions[-2:] for x in self.pointers.read(v)["layers"]}
        for name in self.files.names(""):
            if name[0] in "vc" and name not in needed:
                self.files.drop(name)

    def _union(self, layers: list[str]) -> DataFrame:
        return merged(self.spark.read.parquet(*(f"{self.folder}/{x}" for x in layers)), self.group)

    def read(self) -> DataFrame:
        return self._union(self.layers)

    def close(self) -> None:
        self.files.drop()


class SortedBucketState:
    """Bucketed and sorted tables, one for each version: a bucket of the old version is merged with its share of
    the delta where it lies, so that only the delta moves."""

    durable = False

    def __init__(self, spark: SparkSession, group: Group, buckets: int | None = None):
        self.spark, self.group = spark, group
        self.buckets = buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
        self.name, self.version, self.folds = f"state_{uuid.uuid4().hex}", -1, 0

    def _table(self, number: int) -> str:
        return f"{self.name}_{number}"

    def merge(self, delta: DataFrame) -> DataFrame:
        """The next version: one exchange, which is on the delta."""
        keys = lineage_columns(delta.columns)
        delta = delta.repartition(self.buckets, *keys) if keys else delta
        return merged(self.read().unionByName(delta), self.group) if self.folds else delta

    def fold(self, delta: DataFrame, version: int | None = None) -> DataFrame:
        version = self.version + 1 if version is None else version
        if version <= self.version:
            return self.read()
        keys = lineage_columns(delta.columns)
        writer = self.merge(delta).write.mode("overwrite")
        (writer.bucketBy(self.buckets, *keys).sortBy(*keys) if keys else writer).saveAsTable(self._table(self.folds))
        self.version, self.folds = version, self.folds + 1
        if self.folds > 2:
            self.spark.sql(f"DROP TABLE IF EXISTS {self._table(self.folds - 3)}")
        return self.read()

    def read(self) -> DataFrame:
        return self.spark.table(self._table(self.folds - 1))

    def close(self) -> None:
        for n in (self.folds - 2, self.folds - 1):
            self.spark.sql(f"DROP TABLE IF EXISTS {self._table(n)}")


class KeyedState:
    """One file set for each bucket of lineage: a batch rewrites the buckets that it touches and no others, so the
    cost of a small batch follows its keys and not the state.  Buckets are Parquet folders; a version is the
    list of the bucket folders it consists of."""

    durable = True

    def __init__(self, spark: SparkSession, group: Group, folder: str | None = None, buckets: int = 64):
        self.spark, self.group, self.buckets = spark, group, buckets
        self.folder = folder or f"{checkpoint_folder(spark)}/state-{uuid.uuid4().hex}"
        self.files = Files(spark, self.folder)
        self.pointers = Pointers(self.files)
        self.version, self.where, self.touched = -1, {}, []
        self.restore(max(self.pointers.versions(), default=-1))

    def restore(self, version: int) -> None:
        for v in self.pointers.versions():
            if v > version:
                self.pointers.drop(v)
        there = [v for v in self.pointers.versions() if v <= version]
        said = self.pointers.read(there[-1]) if there else {"where": {}}
        self.version, self.where = version, {int(b): n for b, n in said["where"].items()}
        self.schema = None

    def _paths(self, buckets) -> list[str]:
        return [f"{self.folder}/{self.where[b]}/__bucket={b}" for b in buckets if b in self.where]

    def fold(self, delta: DataFrame, version: int | None = None) -> DataFrame:
        version = self.version + 1 if version is None else version
        if version <= self.version:
            return self.read()
        keys = lineage_columns(delta.columns)
        self.schema = delta.schema
        bucket = F.pmod(F.xxhash64(*keys), F.lit(self.buckets)).cast("int") if keys else F.lit(0)
        delta = delta.withColumn("__bucket", bucket).persist()
        mine = sorted(r[0] for r in delta.select("__bucket").distinct().collect())  # at most as many as there are buckets
        old = self._paths(mine)
        new = delta.drop("__bucket")
        if old:
            new = merged(self.spark.read.schema(self.schema).parquet(*old).unionByName(new), self.group)
        name = f"k{version}-{uuid.uuid4().hex[:8]}"
        if mine:
            new.withColumn("__bucket", bucket).repartition("__bucket").write.partitionBy("__bucket").parquet(f"{self.folder}/{name}")
        delta.unpersist()
        self.where = self.where | dict.fromkeys(mine, name)
        self.version, self.touched = version, mine
        self.pointers.write(version, {"version": version, "where": self.where})
        versions = self.pointers.versions()
        for v in versions[:-2]:
            self.pointers.drop(v)
        needed = {x for v in versions[-2:] for x in self.pointers.read(v)["where"].values()}
        for gone in self.files.names(""):
            if gone[0] == "k" and gone not in needed:
                self.files.drop(gone)
        return self.read()

    def read(self) -> DataFrame:
        paths = self._paths(sorted(self.where))
        if not paths:
            return self.spark.createDataFrame([], self.schema)
        return (self.spark.read.schema(self.schema) if self.schema else self.spark.read).parquet(*paths)

    def close(self) -> None:
        self.files.drop()


BACKENDS = {"memory": MemoryState, "layered": LayeredState, "bucketed": SortedBucketState, "keyed": KeyedState}


class StateCell:
    """A named state: ``step`` folds a delta in and returns the state."""

    def __init__(self, number: int, backend):
        self.number, self.backend = number, backend

    def step(self, delta: DataFrame, version: int | None = None) -> DataFrame:
        return self.backend.fold(delta, version)

    def check_support(self) -> None:
        """Raises where more rows were deleted than inserted."""
        if not self.backend.read().where(F.col(SUPPORT) < 0).isEmpty():
            raise ValueError(f"cell {self.number}: rows were deleted that are not there")
