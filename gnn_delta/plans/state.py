"""Graph state: vertices, edges, and per layer the stored aggregates and outputs; on disk by versions.

On disk (:class:`StateStore`) a table is a base plus one append-only overlay per committed batch, all
partitioned by bucket of the key; the newest version of a key counts. A batch writes only the rows it
changes and reads only the buckets it touches. Every folder has a name of its own. A manifest is a numbered
file that appears by rename and is never changed; the newest one counts, so a batch appears as a whole or
not at all, and a crash leaves the manifest before. The last batch may be committed again: it replaces
itself, and the state before it stays readable, also after compaction. Compaction folds all overlays but
the last into the buckets that they touch.
"""

from __future__ import annotations

import json
import uuid
from collections.abc import Iterable
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .scratch import settled

pinned = settled


@dataclass(frozen=True)
class GraphState:
    """edges (src, dst, w); layers[0] (vid, h0..) features, layers[l] (vid, c, s0.., h0..)."""

    vertices: DataFrame
    edges: DataFrame
    layers: list[DataFrame]
    version: int = 0

    @property
    def prunes(self) -> bool:
        """Whether tables can be read by part, so that settling the keys first pays."""
        return False

    def pinned(self, edges: bool = True) -> GraphState:
        """The same state as tables of its own, so that later plans start from it; edges stay as they are if so asked."""
        layers = [settled(x, "layer") for x in self.layers]
        return replace(self, vertices=self.vertices, edges=settled(self.edges, "edges") if edges else self.edges, layers=layers)

    def edges_from(self, senders: DataFrame) -> DataFrame:
        """A table of edges that holds all out-edges of ``senders`` (vid)."""
        return self.edges

    def layer_of(self, i: int, vids: DataFrame) -> DataFrame:
        """A table of layer rows that holds those of ``vids``."""
        return self.layers[i]

    def known(self, vids: DataFrame) -> DataFrame:
        """(vid) of a table that holds those of ``vids`` that exist."""
        return self.vertices.select("vid")


@dataclass
class BatchResult:
    state: GraphState
    affected: list[DataFrame]  # per hop: (vid)
    changed: list[DataFrame]  # per hop: (vid, old.., new..) where the strategy knows it
    inboxes: list[DataFrame] = field(default_factory=list)
    strategy: list[str] = field(default_factory=list)  # per hop
    rows: list[DataFrame] = field(default_factory=list)  # per hop from 1: the layer rows that were made anew


def overlay(old: DataFrame, new: DataFrame, key: list[str]) -> DataFrame:
    """Rows of ``new`` in place of the rows of ``old`` with the same key."""
    return old.join(new.select(*key), key, "left_anti").unionByName(new.select(*old.columns))


#: an edge or layer bucket should hold about so many rows
ROWS_PER_BUCKET = 4_000_000
#: from so many buckets on, a batch first finds out which ones it touches
PRUNE_FROM = 16
KEYS = {"edges": ["src", "dst"], "seqs": ["src", "dst"]}


class StateStore:
    """Tables edges (by src), layer0.. and vertices (by vid), seqs (by src): the last seq applied to each key."""

    def __init__(self, spark: SparkSession, path: str, buckets: int | None = None):
        self.spark, self.path, self._buckets = spark, path.rstrip("/"), buckets

    # --- files

    def _fs(self):
        target = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        return target.getFileSystem(self.spark._jsc.hadoopConfiguration())

    def _hpath(self, name: str):
        return self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")

    def _manifests(self) -> list[str]:
        fs, folder = self._fs(), self._hpath("manifests")
        if not fs.exists(folder):
            return []
        return sorted(n for n in (f.getPath().getName() for f in fs.listStatus(folder)) if n.endswith(".json"))

    def manifest(self) -> dict:
        """The newest manifest: buckets, tables, base (version and folders with their buckets), batches."""
        names = self._manifests()
        if not names:
            if self._fs().exists(self._hpath("edges")):
                raise FileNotFoundError(f"tables without a manifest in {self.path}")
            return {"number": 0, "buckets": self._buckets, "tables": {}, "base_version": -1, "bases": {}, "batches": []}
        stream = self._fs().open(self._hpath(f"manifests/{names[-1]}"))
        try:
            return json.loads(bytes(stream.readAllBytes()))
        finally:
            stream.close()

    def _publish(self, manifest: dict) -> None:
        fs = self._fs()
        manifest = {**manifest, "number": manifest["number"] + 1}
        fresh, final = self._hpath(f"manifests/{uuid.uuid4().hex}.next"), self._hpath(f"manifests/{manifest['number']:012d}.json")
        out = fs.create(fresh, True)
        out.write(bytearray(json.dumps(manifest).encode()))
        out.close()
        if fs.exists(final) or not fs.rename(fresh, final):
            raise RuntimeError(f"another writer has published {final}")
        for name in self._manifests()[:-3]:
            fs.delete(self._hpath(f"manifests/{name}"), False)

    def _delete(self, folders: Iterable[str]) -> None:
        for folder in folders:
            self._fs().delete(self._hpath(folder), True)

    # --- writing

    @property
    def buckets(self) -> int:
        if self._buckets is None:
            self._buckets = self.manifest()["buckets"]
        return self._buckets

    def bucket(self, key: str | Column) -> Column:
        return F.pmod(F.xxhash64(key), F.lit(self.buckets)).cast("int")

    def _write(self, df: DataFrame, table: str, key: str, name: str) -> str:
        folder = f"{table}/{name}-{uuid.uuid4().hex}"
        rows = df.withColumn("bucket", self.bucket(key))
        rows = rows.repartition("bucket").sortWithinPartitions("bucket", key)
        rows.write.partitionBy("bucket").parquet(f"{self.path}/{folder}")
        return folder

    def bootstrap(self, state: GraphState) -> None:
        """Write the first version; ``buckets`` follows the number of edges unless it was given."""
        if self._manifests():
            raise FileExistsError(f"{self.path} holds a state already")
        if self._buckets is None:
            self._buckets = max(16, state.edges.count() // ROWS_PER_BUCKET)
        seqs = self.spark.createDataFrame([], "src long, dst long, last_seq long")
        tables = {"edges": ("src", state.edges), **{f"layer{i}": ("vid", x) for i, x in enumerate(state.layers)}, "vertices": ("vid", state.vertices), "seqs": ("src", seqs)}
        every = list(range(self._buckets))
        bases = {name: [[self._write(df, name, key, "base"), every]] for name, (key, df) in tables.items()}
        ddl = {n: [k, df.columns, ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in df.schema)] for n, (k, df) in tables.items()}
        self._publish({"number": 0, "buckets": self._buckets, "tables": ddl, "base_version": 0, "bases": bases, "batches": []})

    def commit(self, version: int, changes: dict[str, DataFrame]) -> None:
        """Append a batch: by table the rows that are new or differ (null w: a deleted edge).

        The last batch may be committed again; an earlier one may not."""
        manifest = self.manifest()
        if version < self.last(manifest):
            raise ValueError(f"batch {version} is older than {self.last(manifest)}")
        folders = {name: self._write(df, name, manifest["tables"][name][0], f"batch{version}") for name, df in changes.items()}
        replaced = [f for v, fs in manifest["batches"] if v == version for f in fs.values()]
        self._publish({**manifest, "batches": [*(b for b in manifest["batches"] if b[0] != version), [version, folders]]})
        self._delete(replaced)

    @staticmethod
    def last(manifest: dict) -> int:
        return max([manifest["base_version"], *(v for v, _ in manifest["batches"])])

    # --- reading

    def _read(self, ddl: str, folder: str, columns: list[str]) -> DataFrame:
        return self.spark.read.schema(f"{ddl}, bucket INT").parquet(f"{self.path}/{folder}").select(*columns, "bucket")

    def _parts(self, manifest: dict, name: str, as_of: int | None, touched: list[int] | None) -> tuple[DataFrame, DataFrame | None]:
        """Base rows, and the newest row of each key that some overlay holds (both with ``bucket``)."""
        key, columns, ddl = manifest["tables"][name]
        if as_of is not None and as_of < manifest["base_version"]:
            raise ValueError(f"version {as_of} was folded into {manifest['base_version']}")
        keys = KEYS.get(name, [key])
        base = None
        for folder, buckets in manifest["bases"][name]:
            part = self._read(ddl, folder, columns)
            wanted = buckets if touched is None else [b for b in buckets if b in set(touched)]
            if len(wanted) < self.buckets:
                part = part.where(F.col("bucket").isin(wanted))
            base = part if base is None else base.unionByName(part)
        over = None
        for version, folders in manifest["batches"]:
            if name in folders and (as_of is None or version <= as_of):
                part = self._read(ddl, folders[name], columns)
                if touched is not None:
                    part = part.where(F.col("bucket").isin(touched))
                part = part.withColumn("version", F.lit(version))
                over = part if over is None else over.unionByName(part)
        if over is not None:
            rest = [c for c in [*columns, "bucket"] if c not in keys]
            newest = over.groupBy(*keys).agg(F.max_by(F.struct(*rest), "version").alias("r"))
            over = newest.select(*keys, *[F.col("r")[c].alias(c) for c in rest])
        return base, over

    def table(self, name: str, touched: list[int] | None = None, as_of: int | None = None, manifest: dict | None = None) -> DataFrame:
        """Newest rows of a table; ``touched`` prunes to some buckets, ``as_of`` reads an earlier version."""
        manifest = manifest or self.manifest()
        key, columns, _ = manifest["tables"][name]
        base, over = self._parts(manifest, name, as_of, touched)
        out = base
        if over is not None:
            out = base.join(over.select(*KEYS.get(name, [key])), KEYS.get(name, [key]), "left_anti").unionByName(over.select(*base.columns))
        if name == "edges":
            out = out.where("w is not null")
        return out.select(*columns)

    def touched(self, vids: DataFrame) -> list[int] | None:
        """The buckets of some keys (vid): at most the number of buckets. Few buckets are not worth a job."""
        if self.buckets < PRUNE_FROM:
            return None
        return sorted(r["b"] for r in vids.select(self.bucket("vid").alias("b")).distinct().collect())

    def state(self, as_of: int | None = None) -> StoredState:
        manifest = self.manifest()
        read = lambda name: self.table(name, None, as_of, manifest)
        depth = sum(1 for n in manifest["tables"] if n.startswith("layer"))
        version = self.last(manifest) if as_of is None else as_of
        return StoredState(read("vertices"), read("edges"), [read(f"layer{i}") for i in range(depth)], version, self, as_of, manifest)

    # --- compaction

    def compact(self) -> None:
        """Fold all batches but the last into the buckets that they touch."""
        manifest = self.manifest()
        if len(manifest["batches"]) < 2:
            return
        folded, kept = manifest["batches"][:-1], manifest["batches"][-1:]
        upto = folded[-1][0]
        bases, old = {}, [f for _, folders in folded for f in folders.values()]
        for name, (key, *_) in manifest["tables"].items():
            paths = [folders[name] for _, folders in folded if name in folders]
            hit = set()
            for path in paths:
                hit |= {int(x.getPath().getName().split("=")[1]) for x in self._fs().listStatus(self._hpath(path)) if "=" in x.getPath().getName()}
            if not hit:
                bases[name] = manifest["bases"][name]
                continue
            fresh = self._write(self.table(name, sorted(hit), upto), name, key, "base")
            rest = [[folder, [b for b in buckets if b not in hit]] for folder, buckets in manifest["bases"][name]]
            old += [folder for folder, buckets in rest if not buckets]
            bases[name] = [*(x for x in rest if x[1]), [fresh, sorted(hit)]]
        self._publish({**manifest, "base_version": upto, "bases": bases, "batches": kept})
        self._delete(old)


@dataclass(frozen=True)
class StoredState(GraphState):
    """A state whose tables are read by the buckets that a batch touches."""

    store: StateStore | None = None
    as_of: int | None = None
    manifest: dict | None = None

    @property
    def prunes(self) -> bool:
        return self.store.buckets >= PRUNE_FROM

    def _of(self, name: str, vids: DataFrame) -> DataFrame:
        return self.store.table(name, self.store.touched(vids), self.as_of, self.manifest)

    def edges_from(self, senders: DataFrame) -> DataFrame:
        return self._of("edges", senders)

    def layer_of(self, i: int, vids: DataFrame) -> DataFrame:
        return self._of(f"layer{i}", vids)

    def known(self, vids: DataFrame) -> DataFrame:
        return self._of("vertices", vids).select("vid")

    def seqs_of(self, vids: DataFrame) -> DataFrame:
        return self._of("seqs", vids)
