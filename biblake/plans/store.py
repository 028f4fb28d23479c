"""A lake of tables in buckets, with a manifest per version: batches are applied once, readers see whole versions."""

from __future__ import annotations

import json
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

#: Rows that a bucket holds on average before the buckets are doubled.
ROWS = 500_000


class Lake:
    """Tables under a folder that only Spark's file system needs to reach, each dealt to buckets by the hash of a key.

    A batch rewrites the buckets that its keys fall into, as files in a directory of its own, and then a manifest that names for each table the
    directory of every bucket. The manifest is the commit: without it a directory is never read. A batch id that has been applied
    is not applied again; of ids 'stream/number' only the last number of a stream is kept. The number of buckets follows the rows:
    when they hold more than ROWS on average they are doubled and the table is written anew.

    ``key`` and ``buckets`` are those of the table 'rows', which ``rows`` and ``apply`` mean if no other is named.
    """

    def __init__(self, spark: SparkSession, path: str, key: str = "key", buckets: int = 8, rows_a_bucket: int = ROWS):
        self.spark, self.path, self.key, self.buckets, self.rows_a_bucket = spark, path.rstrip("/"), key, buckets, rows_a_bucket

    def _fs(self):
        jvm = self.spark.sparkContext._jvm
        root = jvm.org.apache.hadoop.fs.Path(self.path)
        return jvm, root.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())

    def _manifests(self) -> list[str]:
        jvm, fs = self._fs()
        at = jvm.org.apache.hadoop.fs.Path(f"{self.path}/manifests")
        return sorted(s.getPath().getName() for s in fs.listStatus(at)) if fs.exists(at) else []

    def manifest(self) -> dict:
        names = [n for n in self._manifests() if n.endswith(".json")]
        if not names:
            return {"version": 0, "batches": [], "streams": {}, "tables": {}}
        lines = self.spark.read.text(f"{self.path}/manifests/{names[-1]}", wholetext=True).collect()
        return json.loads(lines[0].value)

    def _commit(self, manifest: dict) -> None:
        """Writes the next manifest under a private name and renames it; the rename fails if another writer was first."""
        jvm, fs = self._fs()
        path = jvm.org.apache.hadoop.fs.Path
        private, final = path(f"{self.path}/manifests/_{uuid.uuid4().hex}"), path(f"{self.path}/manifests/{manifest['version']:012d}.json")
        out = fs.create(private, False)
        try:
            out.write(bytearray(json.dumps(manifest).encode()))
        finally:
            out.close()
        if fs.exists(final) or not fs.rename(private, final):
            fs.delete(private, False)
            raise RuntimeError(f"version {manifest['version']} was committed by another writer")

    @staticmethod
    def _bucket(key: Column, n: int) -> Column:
        return F.pmod(F.xxhash64(key.cast("string")), F.lit(n)).cast("int")

    @staticmethod
    def _applied(known: dict, batch_id: str) -> bool:
        stream, _, n = batch_id.rpartition("/")
        return int(n) <= known["streams"].get(stream, -1) if stream and n.isdigit() else batch_id in known["batches"]

    def _read(self, table: dict, buckets: list[int] | None = None) -> DataFrame:
        """The rows of some buckets, or all: only their directories are listed and opened."""
        schema = StructType.fromJson(table["schema"])
        paths = [f"{self.path}/{d}/bucket={b}" for b, d in sorted(table["at"].items()) if buckets is None or int(b) in buckets]
        return self.spark.read.schema(schema).parquet(*paths) if paths else self.spark.createDataFrame([], schema)

    def rows(self, table: str = "rows", keys: list | None = None) -> DataFrame | None:
        """A table, or those of its rows that have one of ``keys``, read from the keys' buckets alone; None before its first batch."""
        known = self.manifest()["tables"].get(table)
        if known is None:
            return None
        if keys is None:
            return self._read(known)
        names = self.spark.createDataFrame([(k,) for k in keys], "k string" if all(isinstance(k, str) for k in keys) else "k bigint")
        hit = {r[0] for r in names.select(self._bucket(F.col("k"), known["n"])).distinct().collect()}
        return self._read(known, sorted(hit)).where(F.col(known["key"]).isin(*keys))

    def buckets_of(self, table: str, key: Column) -> Column | None:
        """The bucket that a key falls into, to prune by."""
        known = self.manifest()["tables"].get(table)
        return self._bucket(key, known["n"]) if known else None

    def touched(self, table: str, keys: DataFrame) -> DataFrame | None:
        """The rows of the buckets that the first column of ``keys`` falls into; the numbers of buckets come to the driver, never the keys."""
        known = self.manifest()["tables"].get(table)
        if known is None:
            return None
        hit = [r[0] for r in keys.select(self._bucket(F.col(keys.columns[0]), known["n"])).distinct().collect()]
        return self._read(known, hit)

    def apply(self, batch: DataFrame, batch_id: str, order: list[str] | None = None) -> bool:
        """Adds a batch to the table 'rows' (see ``commit``); False if it was applied before."""
        return self.commit(batch_id, {"rows": (batch, self.key, order)})

    def commit(self, batch_id: str, batches: dict[str, tuple[DataFrame, str, list[str] | str | None]]) -> bool:
        """Adds rows to tables, all or none: {table: (rows, key, how)}. False if the batch was applied before.

        how: 'replace' puts a row in the place of the one with its key, 'all' keeps every row beside those with its key; else the columns that rows
        with one key in the batch are ordered by (None: all of them): what is stored stays, and its gaps are filled from the first row that has a value.
        """
        known = self.manifest()
        if self._applied(known, batch_id):
            return False
        part = f"data/{uuid.uuid4().hex}"
        tables = dict(known["tables"])
        for name, (rows, key, how) in batches.items():
            tables[name] = self._written(tables.get(name), f"{part}/{name}", rows, key, how)
        stream, _, n = batch_id.rpartition("/")
        numbered = bool(stream) and n.isdigit()
        streams = {**known["streams"], stream: int(n)} if numbered else known["streams"]
        self._commit({"version": known["version"] + 1, "batches": known["batches"] if numbered else [*known["batches"], batch_id], "streams": streams, "tables": tables})
        return True

    def _written(self, table: dict | None, part: str, rows: DataFrame, key: str, how) -> dict:
        n = table["n"] if table else self.buckets
        old_n, total = n, table["rows"] if table else 0
        while total > n * self.rows_a_bucket:
            n *= 2
        names = rows.columns
        new = rows.withColumns({"_key": F.col(key), "bucket": self._bucket(F.col(key), n), "_old": F.lit(1)})
        at = {}
        if table:
            hit = None if n != old_n else [r[0] for r in new.select("bucket").distinct().collect()]
            at = {} if hit is None else {b: d for b, d in table["at"].items() if int(b) not in hit}
            old = self._read(table, hit)
            names = [*names, *(c for c in old.columns if c not in names)]
            new = new.unionByName(old.withColumns({"_key": F.col(key), "bucket": self._bucket(F.col(key), n), "_old": F.lit(0)}), allowMissingColumns=True)
        if how == "replace":
            last = F.max(F.struct("_old", *names))
            out = new.groupBy("bucket", "_key").agg(last.alias("r")).select("bucket", *[F.col("r")[c].alias(c) for c in names])
        elif how == "all":
            out = new.select("bucket", *names)
        else:
            place = F.struct("_old", *(how or names))
            picks = [F.min_by(c, F.when(F.col(c).isNotNull(), place)).alias(c) for c in names]
            out = new.groupBy("bucket", "_key").agg(*picks).drop("_key")
        out.repartition(n, "bucket").sortWithinPartitions("bucket", key).write.partitionBy("bucket").parquet(f"{self.path}/{part}")
        written = self.spark.read.schema(out.schema).parquet(f"{self.path}/{part}").groupBy("bucket").agg(F.count("*").alias("c")).collect()
        sizes = {b: table["sizes"][b] for b in at} | {str(r.bucket): r.c for r in written}
        schema = StructType([f for f in out.schema.fields if f.name != "bucket"]).jsonValue()
        return {"n": n, "key": key, "rows": sum(sizes.values()), "at": at | {str(r.bucket): part for r in written}, "sizes": sizes, "schema": schema}
