"""A versioned table of ranks: one writer, readers pinned to a version, a pointer that moves last."""

from __future__ import annotations

import json
from dataclasses import fields

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import drop_path
from .graph import Base, Snapshot
from .layers import Bucketed, RankTable


class RankStore:
    """``root/v=<n>/`` holds a version; ``root/_current/n=<n>`` marks it as complete, so a failed write is never read.

    A version may be an overlay: rows that changed, and the version they change. Reading folds overlays, newest first.
    """

    def __init__(self, spark: SparkSession, root: str, schema: str = "id bigint, rank double", key: tuple[str, ...] = ("id",)) -> None:
        self.spark, self.root, self.schema, self.key = spark, root.rstrip("/"), schema, key

    def _fs(self):
        p = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.root)
        return p.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())

    def _path(self, name: str):
        return self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}")

    def versions(self) -> list[tuple[int, int | None]]:
        """(version, the version it overlays or None), oldest first."""
        fs, at = self._fs(), self._path("_current")
        if not fs.exists(at):
            return []
        names = [s.getPath().getName() for s in fs.listStatus(at)]
        return sorted((int(a), None if b == "full" else int(b)) for a, b in (n.removeprefix("n=").split("@") for n in names if n.startswith("n=")))

    def current(self) -> int | None:
        found = self.versions()
        return found[-1][0] if found else None

    def commit(self, ranks: DataFrame, version: int, over: int | None = None) -> bool:
        """Write a version and make it current; does nothing if that version, or a later one, is current already."""
        now = self.current()
        if now is not None and now >= version:
            return False
        columns = [c.split()[0] for c in self.schema.split(", ")]
        ranks.select(*columns).write.mode("overwrite").parquet(f"{self.root}/v={version}")
        self._fs().create(self._path(f"_current/n={version}@{'full' if over is None else over}"), True).close()
        return True

    def read(self, version: int | None = None) -> DataFrame:
        found = dict(self.versions())
        at = self.current() if version is None else version
        if at is None:
            return self.spark.createDataFrame([], self.schema)
        layers, depth = None, 0
        while at is not None:
            layer = self.spark.read.schema(self.schema).parquet(f"{self.root}/v={at}").withColumn("layer", F.lit(-depth))
            layers = layer if layers is None else layers.unionByName(layer)
            at, depth = found[at], depth + 1
        columns = [c.split()[0] for c in self.schema.split(", ")]
        if depth == 1:
            return layers.select(*columns)
        newest = layers.groupBy(*self.key).agg(F.max_by(F.struct(*columns), "layer").alias("row"))
        return newest.select("row.*")

    def compact(self, version: int) -> None:
        """Fold the overlays of the current version into a full one."""
        self.commit(self.read(), version)


def _bucketed(b: Bucketed) -> dict:
    return {f.name: getattr(b, f.name) for f in fields(Bucketed) if f.name not in ("spark", "_counts")}


def manifest_of(g: Snapshot, ranks: RankTable) -> dict:
    """Where a graph and its ranks lie: bases and overlays, by path and size."""
    base = {name: _bucketed(getattr(g.base, name)) for name in ("out", "into", "degs")}
    own = {name: getattr(g, name) for name in ("n_vertices", "n_edges", "self_loops", "net_path", "n_net", "added_path", "n_added", "version")}
    return {"graph": own | {"base": base, "max_out": g.base.max_out}, "ranks": {"base": _bucketed(ranks.base), "n": ranks.n, "over_path": ranks.over_path, "n_over": ranks.n_over}}


def paths_of(manifest: dict) -> set[str]:
    """All written tables that a manifest names."""
    found = {b["path"] for b in manifest["graph"]["base"].values()} | {manifest["ranks"]["base"]["path"]}
    return found | {p for p in (manifest["graph"]["net_path"], manifest["graph"]["added_path"], manifest["ranks"]["over_path"]) if p}


def opened(spark: SparkSession, manifest: dict, home: str) -> tuple[Snapshot, RankTable]:
    read = lambda path, schema: spark.read.schema(schema).parquet(path) if path else None
    own = dict(manifest["graph"])
    base = Base(*(Bucketed(spark, **own["base"][name]) for name in ("out", "into", "degs")), own.pop("max_out"))
    del own["base"]
    g = Snapshot(base, net=read(own["net_path"], "src bigint, dst bigint, op string"), added=read(own["added_path"], "id bigint"), home=home, **own)
    r = manifest["ranks"]
    return g, RankTable(Bucketed(spark, **r["base"]), r["n"], read(r["over_path"], "id bigint, rank double"), r["over_path"], r["n_over"], home)


class Manifests:
    """Versions of a graph and its ranks under one folder: layers are written first, a version's manifest is put in place last.

    A failed write leaves files that no manifest names. Of old versions the last ``keep`` can be read; layers that none of them names are deleted.
    """

    def __init__(self, spark: SparkSession, root: str, keep: int = 2) -> None:
        self.spark, self.root, self.keep = spark, root.rstrip("/"), keep
        jvm = spark.sparkContext._jvm
        self._at = lambda name: jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}")
        self._fs = self._at("versions").getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def versions(self) -> list[int]:
        if not self._fs.exists(self._at("versions")):
            return []
        names = [s.getPath().getName() for s in self._fs.listStatus(self._at("versions"))]
        return sorted(int(n.removesuffix(".json")) for n in names if n.endswith(".json") and n[0].isdigit())

    def current(self) -> int | None:
        found = self.versions()
        return found[-1] if found else None

    def read(self, version: int) -> dict:
        return json.loads(self.spark.read.text(f"{self.root}/versions/{version}.json", wholetext=True).first()[0])

    def commit(self, version: int, manifest: dict) -> None:
        draft = self._at(f"versions/_{version}.tmp")
        out = self._fs.create(draft, True)
        out.write(bytearray(json.dumps(manifest).encode()))
        out.close()
        self._fs.rename(draft, self._at(f"versions/{version}.json"))
        self._drop_old()

    def _drop_old(self) -> None:
        found = self.versions()
        old, kept = found[: -self.keep], found[-self.keep :]
        if not old:
            return
        needed = set().union(*(paths_of(self.read(v)) for v in kept))
        for v in old:
            for path in paths_of(self.read(v)) - needed:
                drop_path(self.spark, path)
            self._fs.delete(self._at(f"versions/{v}.json"), False)
