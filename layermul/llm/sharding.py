"""Sharding: append arrivals as small immutable shards, merge similarly sized runs, commit manifests.

A store is a folder. Every append writes one folder of Parquet shards and commits a manifest that
adds them; compaction takes the size tiers that hold at least `fan_in` shards, rewrites their rows
into shards of about the target size, and commits a manifest that swaps old for new. A manifest is a
JSON file named by its version, written beside and renamed into place without overwriting: of two
writers of one version one fails and retries on the next. Readers take the newest manifest, or any
older one, and never see half a commit. Files that no kept manifest names are removed by expire().

A manifest names lists, not shards. A list is an immutable JSON file with the shards of one folder and
one tier. Compaction takes whole lists, so a commit writes the lists of its own new shards and costs
as much as there are lists: the full shards of earlier commits are neither read nor written again.

Rows are written and read by DataFrame operations alone. Merging reads the shards of a tier in
splits of the target size and writes each split as one shard, without a shuffle. Folders all of whose
shards are read are named as folders, which Spark lists itself. The driver holds the lists' names and
the shards of the folder that it writes or reads in part, never rows.

Edge cases: an empty arrival commits a version without new shards; rows are kept as they are: nulls,
repeated rows, empty and very long texts (a row larger than the target has a shard of its own size);
all columns are kept, whatever their names; reading an empty store gives no rows of the given schema.
"""

from __future__ import annotations

import json
import uuid
from dataclasses import dataclass
from itertools import accumulate

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from .scratch import broadcast_if_small, fresh_path, table


@dataclass(frozen=True)
class ShardConfig:
    """target: bytes of a full shard; fan_in: shards of one tier that are merged, and the ratio of
    neighbouring tiers' sizes; retries: of a commit that lost its version to another writer."""

    target: int = 64 << 20
    fan_in: int = 4
    retries: int = 20


class CommitConflict(RuntimeError):
    """Another writer committed this version first."""


class ShardStore:
    def __init__(self, spark: SparkSession, path: str, config: ShardConfig = ShardConfig()):
        self.spark, self.path, self.config = spark, path.rstrip("/"), config
        jvm = spark._jvm
        self._root = jvm.org.apache.hadoop.fs.Path(self.path)
        self._fs = self._root.getFileSystem(spark._jsc.hadoopConfiguration())
        for part in ("manifests", "lists"):
            self._fs.mkdirs(self._at(part))

    def _at(self, name: str):
        return self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")

    # --- manifests ---

    def _read(self, name: str) -> str:
        stream = self._fs.open(self._at(name))
        try:
            return self.spark._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
        finally:
            stream.close()

    def _write(self, path, text: str) -> None:
        stream = self._fs.create(path, False)
        stream.write(bytearray(text.encode()))
        stream.close()

    def versions(self) -> list[int]:
        names = [s.getPath().getName() for s in self._fs.listStatus(self._at("manifests"))]
        return sorted(int(n[1:-5]) for n in names if n.startswith("v") and n.endswith(".json"))

    def head(self, version: int | None = None) -> dict:
        """version and lists, each a dict of list, folder, of (shards that were written to the folder),
        tier, tiers (the sizes that tier goes by), shards, bytes, most (of a shard); version 0 is the
        empty store."""
        held = self.versions() if version is None else []
        version = (held[-1] if held else 0) if version is None else version
        return json.loads(self._read(f"manifests/v{version:012d}.json")) if version else {"version": 0, "lists": []}

    def manifest(self, version: int | None = None) -> dict:
        """version and all its shards, each a dict of file, bytes."""
        now = self.head(version)
        return {"version": now["version"], "shards": [s for held in now["lists"] for s in self._shards(held)]}

    def _shards(self, held: dict) -> list[dict]:
        rows = map(json.loads, self._read(held["list"]).splitlines())
        return [{"file": f"{held['folder']}/{r['file']}", "bytes": r["bytes"]} for r in rows]

    def _listed(self, folder: str, shards: list[dict], of: int) -> list[dict]:
        """New lists of these shards of a folder."""
        tiers: dict[int, list[dict]] = {}
        for s in shards:
            tiers.setdefault(self.tier(s["bytes"]), []).append(s)
        out = []
        for tier, own in sorted(tiers.items()):
            for at in range(0, len(own), LIST_MOST):
                part, name = own[at : at + LIST_MOST], f"lists/{uuid.uuid4().hex}.json"
                rows = ({"list": name, "place": k, "file": s["file"].split("/")[-1], "bytes": s["bytes"]} for k, s in enumerate(part))
                self._write(self._at(name), "\n".join(map(json.dumps, rows)))
                sizes = [s["bytes"] for s in part]
                out.append({"list": name, "folder": folder, "of": of, "tier": tier, "tiers": self._tiers(), "shards": len(part), "bytes": sum(sizes), "most": max(sizes)})
        return out

    def _commit(self, version: int, lists: list[dict]) -> None:
        jvm = self.spark._jvm
        tmp, final = self._at(f"manifests/.{uuid.uuid4().hex}.tmp"), self._at(f"manifests/v{version:012d}.json")
        self._write(tmp, json.dumps({"version": version, "lists": lists}))
        context = jvm.org.apache.hadoop.fs.FileContext.getFileContext(self._root.toUri(), self.spark._jsc.hadoopConfiguration())
        try:
            context.rename(self._fs.makeQualified(tmp), self._fs.makeQualified(final), self.spark.sparkContext._gateway.new_array(jvm.org.apache.hadoop.fs.Options.Rename, 0))
        except Exception as e:
            self._fs.delete(tmp, False)
            if self._fs.exists(final):
                raise CommitConflict(f"version {version}") from e
            raise

    def _swap(self, gone: set[str], new: list[dict]) -> int:
        """Commit the newest manifest without the lists in gone and with the new ones."""
        for _ in range(self.config.retries):
            now = self.head()
            if not gone <= {held["list"] for held in now["lists"]}:
                raise CommitConflict("another compaction took some of these shards")
            try:
                self._commit(now["version"] + 1, [held for held in now["lists"] if held["list"] not in gone] + new)
                return now["version"] + 1
            except CommitConflict:
                continue
        raise CommitConflict(f"no version could be taken in {self.config.retries} tries")

    # --- shards ---

    def _written(self, folder: str) -> list[dict]:
        """Lists of the shards in a folder that has just been written."""
        shards = [{"file": s.getPath().getName(), "bytes": s.getLen()} for s in self._fs.listStatus(self._at(folder)) if s.getPath().getName().endswith(".parquet")]
        return self._listed(folder, shards, len(shards))

    def append(self, rows: DataFrame) -> int:
        """The rows as immutable shards, one for each of the input's partitions; the new version."""
        folder = f"shards/{uuid.uuid4().hex}"
        rows.write.option("compression", "zstd").parquet(f"{self.path}/{folder}")
        return self._swap(set(), self._written(folder))

    def _tiers(self) -> list[int]:
        return [self.config.target, self.config.fan_in]

    def tier(self, size: int) -> int:
        """0 for full shards, one more for every fan_in times smaller."""
        steps, limit = 0, self.config.target // 2
        while size < limit:
            steps, limit = steps + 1, limit // self.config.fan_in
        return steps

    def _due(self) -> list[list[dict]]:
        """Lists of small shards by tier that are to be merged. Lists that go by other sizes than this
        store's are written anew first."""
        now = self.head()["lists"]
        old = [held for held in now if held["tiers"] != self._tiers()]
        if old:
            self._swap({held["list"] for held in old}, [x for held in old for x in self._listed(held["folder"], self._shards(held), held["of"])])
            now = self.head()["lists"]
        tiers: dict[int, list[dict]] = {}
        for held in now:
            tiers.setdefault(held["tier"], []).append(held)
        return [run for t, run in sorted(tiers.items()) if t > 0 and sum(held["shards"] for held in run) >= self.config.fan_in]

    def _paths(self, lists: list[dict]) -> list[str]:
        """What to read for these lists: folders, or the shards of those that are not read whole."""
        folders: dict[str, list[dict]] = {}
        for held in lists:
            folders.setdefault(held["folder"], []).append(held)
        out = []
        for folder, own in folders.items():
            whole = sum(held["shards"] for held in own) == own[0]["of"]
            out += [f"{self.path}/{folder}"] if whole else [f"{self.path}/{s['file']}" for held in own for s in self._shards(held)]
        return out

    def compact(self) -> int:
        """One round: merge the due runs and commit; the newest version. Merged shards reach a higher
        tier and are merged again in a later round, until they are full."""
        due = self._due()
        if not due:
            return self.head()["version"]
        packed = self.spark.newSession()  # a session of its own: how files are dealt to tasks is its setting
        packed.conf.set("spark.sql.files.openCostInBytes", 0)
        packed.conf.set("spark.sql.files.minPartitionNum", 1)
        new = []
        for run in due:
            total = sum(held["bytes"] for held in run)
            shards = max(1, round(total / self.config.target))
            packed.conf.set("spark.sql.files.maxPartitionBytes", max(-(-total // shards), max(held["most"] for held in run)))
            folder = f"shards/{uuid.uuid4().hex}"
            packed.read.parquet(*self._paths(run)).write.option("compression", "zstd").parquet(f"{self.path}/{folder}")
            new += self._written(folder)
        return self._swap({held["list"] for run in due for held in run}, new)

    def compact_all(self, rounds: int = 16) -> int:
        """Rounds of compact() until none is due."""
        for _ in range(rounds):
            if not self._due():
                break
            self.compact()
        return self.head()["version"]

    def read(self, version: int | None = None, schema: StructType | None = None) -> DataFrame:
        lists = self.head(version)["lists"]
        if not lists:
            return self.spark.createDataFrame([], schema)
        reader = self.spark.read if schema is None else self.spark.read.schema(schema)
        return reader.parquet(*self._paths(lists))

    def expire(self, keep: int = 1) -> int:
        """Remove all but the newest `keep` manifests, and the lists and shards that none of these names;
        how many shards."""
        versions = self.versions()
        kept = {held["list"]: held for v in versions[-keep:] for held in self.head(v)["lists"]}
        gone = {held["list"]: held for v in versions[:-keep] for held in self.head(v)["lists"] if held["list"] not in kept}
        for v in versions[:-keep]:
            self._fs.delete(self._at(f"manifests/v{v:012d}.json"), False)
        folders: dict[str, tuple[list[dict], list[dict]]] = {held["folder"]: ([], []) for held in gone.values()}
        for side, lists in enumerate((gone, kept)):
            for held in lists.values():
                if held["folder"] in folders:
                    folders[held["folder"]][side].append(held)
        n = 0
        for folder, sides in folders.items():
            old, named = ({s["file"] for held in side for s in self._shards(held)} for side in sides)
            n += len(old - named)
            for f in [folder] if not named else old - named:
                self._fs.delete(self._at(f), not named)
        for name in gone:
            self._fs.delete(self._at(name), False)
        return n


#: Shards of a list at most.
LIST_MOST = 100_000
#: Arrivals of the query: shares of a hundred by crc32 of the id, a large one and later smaller ones.
ARRIVALS = ((0, 60), (60, 85), (85, 95), (95, 100))


def sharded(docs: DataFrame, config: ShardConfig = ShardConfig(), arrivals=ARRIVALS) -> ShardStore:
    """docs in a new store of the shared folder: arrivals appended in turn, compacted, old files removed."""
    store = ShardStore(docs.sparkSession, fresh_path(docs.sparkSession, "store"), config)
    part = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 100, F.lit(0))
    for lo, hi in arrivals:
        store.append(docs.where((part >= lo) & (part < hi)))
        store.compact()
    store.compact_all()
    store.expire()
    return store


def shard_of_rows(store: ShardStore, schema: StructType, columns: list[str]) -> DataFrame:
    """columns of every row with shard, shard_bytes, tier and version, which take the place of columns
    of the same names. Shards are numbered list by list."""
    now, told = store.head(), ["shard", "shard_bytes", "tier", "version"]
    kept = [c for c in columns if c not in told]
    if not now["lists"]:
        types = [F.lit(None).cast(t).alias(c) for c, t in zip(told, ("long", "long", "int", "long"), strict=True)]
        return store.read(schema=schema).select(*kept, *types)
    lists = sorted(now["lists"], key=lambda held: held["list"])
    ends = list(accumulate((held["shards"] for held in lists), initial=0))
    firsts = store.spark.createDataFrame([(held["list"], ends[k], held["tier"], now["version"]) for k, held in enumerate(lists)], "list string, first long, tier int, version long")
    shards = store.spark.read.schema("list string, place long, file string, bytes long").json([f"{store.path}/{held['list']}" for held in lists])
    names = shards.join(broadcast_if_small(firsts, len(lists)), "list").select("file", (F.col("first") + F.col("place")).alias("shard"), F.col("bytes").alias("shard_bytes"), "tier", "version")
    rows = store.read(schema=schema).select(F.col("_metadata.file_name").alias("file"), F.struct(*kept).alias("row"))
    return rows.join(broadcast_if_small(names, ends[-1]), "file").select("row.*", *told)


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Where every document lies: doc_id, shard (numbered list by list), its bytes, tier and the
    committed version."""
    docs = table(spark, sf_dir, "documents")
    return shard_of_rows(sharded(docs), docs.schema, ["doc_id"])
