"""Tables in buckets of a key, under small overlays: a lookup of few keys reads few buckets, and a batch of changes writes few rows."""

from __future__ import annotations

from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..session import drop_path, scratch, shared_dir

#: Rows of a bucket aimed at, and buckets at most: what a lookup sends to the driver is bounded by their number.
BUCKET_ROWS, LEAST_BUCKETS, MOST_BUCKETS = 1 << 17, 8, 1 << 16
#: Keys that a lookup may send to all tasks; more are shuffled.
BROADCAST_KEYS = 1_000_000
#: An overlay that is larger than this share of its base is folded into a new base.
FOLD_SHARE = 0.1


def buckets_for(rows: int) -> int:
    return min(MOST_BUCKETS, max(LEAST_BUCKETS, -(-rows // BUCKET_ROWS)))


def bucket_of(key: Column | str, buckets: int) -> Column:
    return F.pmod(F.xxhash64(key), F.lit(buckets)).cast("int")


def fresh_path(spark: SparkSession, name: str, home: str | None = None) -> str:
    path = scratch(spark, name)
    return path if home is None else f"{home}/{path.rsplit('/', 1)[-1]}"


def written(df: DataFrame, name: str, home: str | None = None, **measures: Column) -> tuple[DataFrame, str, dict]:
    """Write a table into the shared folder, or ``home``, and read it back; measures of it come from the same job."""
    spark = df.sparkSession
    path = fresh_path(spark, name, home)
    seen = Observation() if measures else None
    out = df if seen is None else df.observe(seen, *(c.alias(n) for n, c in measures.items()))
    out.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), path, (seen.get if seen is not None else {})


class Steps:
    """What the steps of a run write: checkpoints in the shared folder, which keep how rows are dealt and sorted, cut lineage and survive lost executors."""

    def __init__(self, spark: SparkSession) -> None:
        self.spark, self.paths = spark, []
        shared_dir(spark)

    def put(self, df: DataFrame, **measures: Column) -> tuple[DataFrame, dict]:
        seen = Observation() if measures else None
        out = df if seen is None else df.observe(seen, *(c.alias(n) for n, c in measures.items()))
        # An adaptive plan would forget how its rows are dealt and sorted.
        with settings(self.spark, spark__sql__adaptive__enabled="false"):
            out = out.checkpoint(eager=True)
        file = out._jdf.queryExecution().logical().rdd().getCheckpointFile()
        if file.isDefined():
            self.paths.append(file.get())
        return out, (seen.get if seen is not None else {})

    def drop(self, keep: list[str]) -> None:
        """Delete all but what is still read."""
        for path in self.paths:
            if path not in keep:
                drop_path(self.spark, path)
        self.paths = [p for p in self.paths if p in keep]

    @property
    def last(self) -> str:
        return self.paths[-1]


@contextmanager
def settings(spark: SparkSession, **conf: str):
    """Runtime settings for a while; names have __ for dots."""
    names = {k.replace("__", "."): v for k, v in conf.items()}
    before = {k: spark.conf.get(k, None) for k in names}
    try:
        for k, v in names.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


@dataclass
class Keys:
    """Ids to look up, counted, and the buckets they fall into."""

    ids: DataFrame
    n: int
    buckets: int
    touched: tuple[int, ...]

    @classmethod
    def of(cls, ids: DataFrame, buckets: int, steps: Steps | None = None) -> Keys:
        """Distinct ids, written once; count and buckets come with the same job."""
        table, got = (steps or Steps(ids.sparkSession)).put(ids.select("id").distinct(), n=F.count(F.lit(1)), touched=F.collect_set(bucket_of("id", buckets)))
        return cls(table, got["n"], buckets, tuple(sorted(got["touched"])))

    def semi(self, key: str) -> DataFrame:
        wanted = self.ids.select(F.col("id").alias(key))
        return F.broadcast(wanted) if self.n <= BROADCAST_KEYS else wanted


@dataclass
class Bucketed:
    """A table written once, sorted by key within buckets; a hub's rows may lie in several files."""

    spark: SparkSession
    path: str
    schema: str
    key: str
    buckets: int
    n: int
    _counts: dict[int, int] | None = field(default=None, repr=False)

    @classmethod
    def write(cls, df: DataFrame, key: str, buckets: int, name: str, home: str | None = None, rows: int | None = None) -> Bucketed:
        """``rows``: how many there are about, where that is known; few rows take few tasks."""
        spark = df.sparkSession
        path = fresh_path(spark, name, home)
        parts = int(spark.conf.get("spark.sql.shuffle.partitions", "200"))
        parts = parts if rows is None else max(1, min(parts, -(-rows // BUCKET_ROWS)))
        order = ["bucket", key, *(c for c in df.columns if c != key)]
        # A range of (bucket, key, rest) also cuts through one key's rows: no task gets a whole hub.
        seen = Observation()
        ranged = df.withColumn("bucket", bucket_of(key, buckets)).repartitionByRange(parts, *order).sortWithinPartitions(*order)
        ranged.observe(seen, F.count(F.lit(1)).alias("n")).write.partitionBy("bucket").parquet(path)
        return cls(spark, path, ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in df.schema), key, buckets, seen.get["n"])

    @property
    def columns(self) -> list[str]:
        return [c.split()[0] for c in self.schema.split(", ")]

    def _read(self) -> DataFrame:
        return self.spark.read.schema(f"{self.schema}, bucket int").parquet(self.path)

    @property
    def df(self) -> DataFrame:
        return self._read().select(*self.columns)

    def some(self, touched: tuple[int, ...]) -> DataFrame:
        """The rows of some buckets; other buckets' files are not opened."""
        if 2 * len(touched) > self.buckets:
            return self.df
        return self._read().where(F.col("bucket").isin(list(touched))).select(*self.columns)

    def of(self, keys: Keys) -> DataFrame:
        """Rows whose key is among the keys."""
        touched = keys.touched if keys.buckets == self.buckets else tuple(range(self.buckets))
        return self.some(touched).join(keys.semi(self.key), self.key, "left_semi").select(*self.columns)

    def counts(self) -> dict[int, int]:
        if self._counts is None:
            self._counts = {r["bucket"]: r["count"] for r in self._read().groupBy("bucket").count().collect()}
        return self._counts

    def scanned(self, touched: tuple[int, ...]) -> int:
        """Rows that :meth:`some` reads."""
        counts = self.counts()
        return sum(counts.values()) if 2 * len(touched) > self.buckets else sum(counts.get(b, 0) for b in touched)

    def drop(self) -> None:
        drop_path(self.spark, self.path)


class RankTable:
    """Ranks of a snapshot's vertices: a base in buckets and an overlay of the rows that changed since."""

    def __init__(self, base: Bucketed | DataFrame, n: int | None = None, over: DataFrame | None = None, over_path: str | None = None, n_over: int = 0, home: str | None = None) -> None:
        self.base, self.n, self.over, self.over_path, self.n_over, self.home = base, n, over, over_path, n_over, home

    @classmethod
    def store(cls, ranks: DataFrame, buckets: int, n: int, home: str | None = None) -> RankTable:
        return cls(Bucketed.write(ranks.select("id", "rank"), "id", buckets, "ranks", home, n), n, home=home)

    def _over(self, base: DataFrame) -> DataFrame:
        if self.over is None:
            return base
        new = self.over.select("id", F.col("rank").alias("new_rank"))
        new = F.broadcast(new) if self.n_over <= BROADCAST_KEYS else new
        return base.join(new, "id", "left").select("id", F.coalesce("new_rank", "rank").alias("rank"))

    @property
    def df(self) -> DataFrame:
        return self._over((self.base.df if isinstance(self.base, Bucketed) else self.base).select("id", "rank"))

    def of(self, keys: Keys) -> DataFrame:
        found = self.base.of(keys) if isinstance(self.base, Bucketed) else self.base.join(keys.semi("id"), "id", "left_semi").select("id", "rank")
        return self._over(found)

    def some(self, touched: tuple[int, ...], buckets: int) -> DataFrame:
        """At least the rows of some buckets."""
        if isinstance(self.base, Bucketed) and self.base.buckets == buckets:
            return self._over(self.base.some(touched))
        return self.df

    def updated(self, changed: DataFrame) -> RankTable:
        """The table after some rows (id, rank) changed: writes what has changed since the base, not all ranks."""
        rows = changed.select("id", "rank")
        if self.over is not None:
            rows = rows.unionByName(self.over.select("id", "rank").join(changed.select("id"), "id", "left_anti"))
        over, path, got = written(rows, "ranks-over", self.home, n=F.count(F.lit(1)))
        new = RankTable(self.base, self.n, over, path, got["n"], self.home)
        if isinstance(self.base, Bucketed) and self.n and got["n"] > FOLD_SHARE * self.n:
            return RankTable.store(new.df, self.base.buckets, self.n, self.home)
        return new
