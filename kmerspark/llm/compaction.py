"""Size-tiered compaction of immutable shards under a versioned manifest.

Arrivals are appended as small shards and never changed. Shards of one size tier are merged, in order of arrival,
into files of about the target size; the merged shards and the new manifest become visible together, when the
commit file of the next version appears, which the file system lets only one writer do. Readers see the shards of
the last committed manifest and nothing else. Each write has a folder of its own, which no other writer's commit
names, so what a writer that lost or died has left behind is never read. All data work is DataFrame operations.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ._state import publish, shared_dir, stored

TARGET_BYTES = 128 << 20
BASE_BYTES = 1 << 20
TIER_FACTOR = 4
MIN_RUN = 4
#: Shards that one round merges, about; more wait for the next round. Bounds the plan that is broadcast.
ROUND_SHARDS = 100_000
#: Ordinals of a segment, over which bytes are summed before the sums of the segments are.
SEGMENT = 65_536
MANIFEST = "batch string, ordinal long, generation int, n_rows long, n_bytes long"
KEY = ["batch", "ordinal"]


class ConflictError(RuntimeError):
    """Another writer committed the version first."""


class TieredStore:
    """A store of rows in immutable shards. `payload` keeps each row whole, so its column names can't clash."""

    def __init__(self, spark: SparkSession, path: str, target: int = TARGET_BYTES, base: int = BASE_BYTES, factor: int = TIER_FACTOR, min_run: int = MIN_RUN):
        self.spark, self.path, self.target, self.base, self.factor, self.min_run = spark, path, target, base, factor, min_run
        hadoop = spark._jvm.org.apache.hadoop.fs
        self._at = lambda p: hadoop.Path(f"{path}/{p}")
        self._fs = self._at("").getFileSystem(spark._jsc.hadoopConfiguration())

    def _names(self, folder: str) -> list[str]:
        return [f.getPath().getName() for f in self._fs.listStatus(self._at(folder))] if self._fs.exists(self._at(folder)) else []

    def versions(self) -> list[int]:
        """The committed versions whose manifests are there, in order."""
        return sorted(int(n) for n in self._names("commits") if n.isdigit())

    def version(self) -> int:
        """The last committed version; 0 for an empty store."""
        return max(self.versions(), default=0)

    def _commit(self, manifest: DataFrame, version: int) -> None:
        name = f"manifest-{uuid.uuid4().hex}"
        manifest.write.parquet(f"{self.path}/{name}")
        if not publish(self.spark, f"{self.path}/commits/{version:010d}", name):
            self._fs.delete(self._at(name), True)
            raise ConflictError(f"version {version} is taken")

    def _manifest_name(self, version: int) -> str:
        return self.spark.read.text(f"{self.path}/commits/{version:010d}").first()[0]

    def manifest(self, version: int | None = None) -> DataFrame:
        """A row per live shard: batch (the write it is from), ordinal (place in the order of arrival), generation, n_rows, n_bytes."""
        version = self.version() if version is None else version
        if not version:
            return self.spark.createDataFrame([], MANIFEST)
        return self.spark.read.schema(MANIFEST).parquet(f"{self.path}/{self._manifest_name(version)}")

    def _write(self, rows: DataFrame, by: str) -> str:
        """Rows (payload, weight and `by`) as shards of a new batch; equal values of `by` are one shard."""
        batch = uuid.uuid4().hex
        rows.withColumnRenamed(by, "ordinal").write.option("compression", "zstd").partitionBy("ordinal").parquet(f"{self.path}/data/batch={batch}")
        return batch

    def _batch(self, batch: str) -> DataFrame:
        path = f"{self.path}/data/batch={batch}"
        return self.spark.read.parquet(path).withColumn("ordinal", F.col("ordinal").cast("long")).withColumn("batch", F.lit(batch))

    def append(self, rows: DataFrame, arrival, weight) -> None:
        """Add rows: one shard for each value of the expression `arrival` (a long); `weight` is a row's size in bytes.

        Shards are ordered by arrival, rows without one come last. A large arrival is written by several tasks. Rows
        of a write whose commit fails belong to no version; append them again.
        """
        version = self.version()
        start = self.manifest(version).agg(F.max("ordinal")).first()[0]
        data = rows.select(F.struct(*(rows[c] for c in rows.columns)).alias("payload"), arrival.cast("long").alias("_a"), weight.cast("long").alias("weight"))
        batch = self._write(data.hint("rebalance", F.col("_a")), "_a")
        own = stored(self._batch(batch).groupBy("ordinal").agg(F.count("*").alias("n_rows"), F.sum("weight").alias("n_bytes")))
        low, high = own.agg(F.min("ordinal"), F.max("ordinal")).first()
        # The shard keeps its arrival in its folder's name; the manifest's ordinal is the arrival, moved behind what was there.
        shift = (0 if start is None else start + 1) - (0 if low is None else low)
        none = 0 if high is None else high + 1
        fresh = own.select(F.lit(f"{batch}:{shift}:{none}").alias("batch"), (F.coalesce("ordinal", F.lit(none)) + shift).cast("long").alias("ordinal"), F.lit(0).alias("generation"), "n_rows", "n_bytes")
        self._commit(self.manifest(version).unionByName(fresh), version + 1)

    def _rows(self, shards: DataFrame) -> DataFrame:
        """payload, weight, batch and ordinal of the rows of all batches that `shards` (batch, ordinal, ...) names."""
        out = None
        for name in sorted(r["batch"] for r in shards.select("batch").distinct().collect()):  # a row per write that is still live
            batch, shift, none = name.split(":")
            ordinal = (F.coalesce("ordinal", F.lit(int(none))) + int(shift)).cast("long")
            part = self._batch(batch).select("payload", "weight", F.lit(name).alias("batch"), ordinal.alias("ordinal"))
            out = part if out is None else out.unionByName(part)
        return out if out is not None else self.spark.createDataFrame([], "payload string, weight long, batch string, ordinal long")

    def read(self) -> DataFrame:
        """All live rows: payload, weight, batch, ordinal. Shards outside the manifest are left out."""
        live = self.manifest()
        return self._rows(live).join(live.select(*KEY), KEY, "left_semi")

    def plan(self) -> DataFrame:
        """batch, ordinal, run: the shards to merge, and the first ordinal of the run that each goes to.

        A shard of half the target or more is done. The others fall into tiers by powers of the factor; within a
        tier they are cut, in order of arrival, into runs of about the target size. A run is merged if it has
        `min_run` shards, or two and half the target. Bytes are summed by segments of the order first, so no task
        sees all shards of a tier.
        """
        small = self.manifest().filter(F.col("n_bytes") < self.target / 2)
        tier = F.floor(F.log(F.greatest(F.col("n_bytes") / self.base, F.lit(1.0))) / F.log(F.lit(float(self.factor))) + 1e-9)
        small = small.withColumn("tier", tier.cast("int")).withColumn("segment", F.floor(F.col("ordinal") / SEGMENT))
        sums = small.groupBy("tier", "segment").agg(F.sum("n_bytes").alias("_b"))
        earlier = F.sum("_b").over(Window.partitionBy("tier").orderBy("segment").rowsBetween(Window.unboundedPreceding, -1))
        sums = sums.select("tier", "segment", F.coalesce(earlier, F.lit(0)).alias("_before"))
        within = F.sum("n_bytes").over(Window.partitionBy("tier", "segment").orderBy("ordinal").rowsBetween(Window.unboundedPreceding, -1))
        runs = small.join(sums, ["tier", "segment"]).withColumn("cut", F.floor((F.col("_before") + F.coalesce(within, F.lit(0))) / self.target))
        own = Window.partitionBy("tier", "cut")
        runs = runs.withColumn("n", F.count("*").over(own)).withColumn("total", F.sum("n_bytes").over(own)).withColumn("run", F.min("ordinal").over(own))
        return runs.filter((F.col("n") >= self.min_run) | (F.col("n") >= 2) & (F.col("total") >= self.target / 2)).select(*KEY, "run")

    def compact(self) -> bool:
        """One round of merges, committed as one version; False if there was nothing to merge."""
        version = self.version()
        plan = stored(self.plan())
        n_shards = plan.count()
        if not n_shards:
            return False
        rounds = -(-n_shards // ROUND_SHARDS)
        if rounds > 1:  # whole runs, chosen by a hash; the others wait
            plan = stored(plan.filter(F.pmod(F.xxhash64("run"), F.lit(rounds)) == 0))
        n_runs = plan.select("run").distinct().count()
        if not n_runs:
            return False
        merged = self._rows(plan).join(F.broadcast(plan), KEY).select("payload", "weight", "run")  # about ROUND_SHARDS rows
        batch = self._write(merged.repartition(max(2 * n_runs, 2), "run"), "run")
        old = self.manifest(version)
        sums = old.join(F.broadcast(plan), KEY).groupBy("run").agg(F.max("generation").alias("g"), F.sum("n_rows").alias("n_rows"), F.sum("n_bytes").alias("n_bytes"))
        fresh = sums.select(F.lit(f"{batch}:0:-1").alias("batch"), F.col("run").alias("ordinal"), (F.col("g") + 1).alias("generation"), "n_rows", "n_bytes")
        self._commit(old.join(F.broadcast(plan), KEY, "left_anti").unionByName(fresh), version + 1)
        return True

    def vacuum(self) -> None:
        """Delete the manifests before the last version, and the shards that only they name. No reader may hold one.

        What no manifest has named yet may be another writer's next commit, and stays.
        """
        *old, last = self.versions() or [0]
        if not old:
            return
        named = None
        for v in old:
            named = self.manifest(v).select(*KEY) if named is None else named.unionByName(self.manifest(v).select(*KEY))
        live = stored(self.manifest(last).select(*KEY))
        dead = stored(named.distinct().join(live, KEY, "left_anti"))
        names = [(v, self._manifest_name(v)) for v in old]
        whole = dead.select("batch").distinct().join(live.select("batch").distinct(), "batch", "left_anti")
        for r in whole.toLocalIterator():
            self._fs.delete(self._at(f"data/batch={r['batch'].split(':')[0]}"), True)
        for r in dead.join(whole, "batch", "left_anti").toLocalIterator():
            batch, shift, none = r["batch"].split(":")
            folder = r["ordinal"] - int(shift)
            self._fs.delete(self._at(f"data/batch={batch}/ordinal={'__HIVE_DEFAULT_PARTITION__' if folder == int(none) else folder}"), True)
        for v, name in names:
            self._fs.delete(self._at(f"commits/{v:010d}"), False)
            self._fs.delete(self._at(name), True)


def compact_documents(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", per_arrival: int = 1000, path: str | None = None, **limits) -> DataFrame:
    """Store the documents as arrivals, compact until no run is left, and read all back from the manifest.

    An arrival is a run of `per_arrival` ids; rows without an id are dealt by a hash of their text. A row's size is
    the bytes of its text; null and empty texts weigh nothing, and equal rows are all kept. Returns doc_id, shard
    (its generation and ordinal), generation, shard_rows and shard_bytes of each stored row. An empty table gives an
    empty result.
    """
    spark = docs.sparkSession
    store = TieredStore(spark, path or f"{shared_dir(spark)}/tiered-{uuid.uuid4().hex}", **limits)
    rows = docs.select(docs[id_col].alias("doc_id"), *(docs[c] for c in docs.columns if c not in (id_col, "doc_id")))
    if rows.isEmpty():
        return spark.createDataFrame([], "doc_id long, shard string, generation int, shard_rows long, shard_bytes long")
    arrival = F.coalesce(F.floor(F.col("doc_id") / per_arrival), -1 - F.pmod(F.xxhash64(text_col), F.lit(64)))
    store.append(rows, arrival, F.coalesce(F.octet_length(text_col), F.lit(0)))
    while store.compact():
        store.vacuum()
    facts = store.manifest().select(*KEY, "generation", F.col("n_rows").alias("shard_rows"), F.col("n_bytes").alias("shard_bytes"))
    shard = F.concat(F.lit("g"), "generation", F.lit("-"), "ordinal").alias("shard")
    return store.read().join(facts, KEY).select("payload.doc_id", shard, "generation", "shard_rows", "shard_bytes")
