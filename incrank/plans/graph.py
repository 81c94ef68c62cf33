"""Snapshots of graphs and changes between them."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import drop_path, stored
from .layers import BROADCAST_KEYS, FOLD_SHARE, Bucketed, Keys, buckets_for, written
from .kernel import own_rows
from .model import DELTA


def vertices_of(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("id")).unionByName(edges.select(F.col("dst").alias("id"))).distinct()


def static_edges(tedges: DataFrame) -> DataFrame:
    """Distinct edges of a temporal list; its self-loops go, since snapshots add their own."""
    return tedges.where("src <> dst").select("src", "dst").distinct()


def with_self_loops(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Every vertex gets an edge to itself, so that none is a dead end."""
    loops = vertices.select(F.col("id").alias("src"), F.col("id").alias("dst"))
    return edges.where("src <> dst").select("src", "dst").unionByName(loops)


def out_degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("out_deg"))


def in_degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("in_deg"))


def update_degrees(degrees: DataFrame, delta: DataFrame) -> DataFrame:
    """Degrees after a normalised batch, without a look at the edges."""
    change = delta.select(F.col("src").alias("id"), F.when(F.col("op") == "+", 1).otherwise(-1).cast("bigint").alias("out_deg"))
    return degrees.select("id", "out_deg").unionByName(change).groupBy("id").agg(F.sum("out_deg").alias("out_deg")).where("out_deg > 0")


def normalize_delta(graph: DataFrame | Snapshot, delta: DataFrame) -> DataFrame:
    """A batch as a set: self-loops go, deletions before insertions of the same edge cancel, and so does what changes nothing.

    An edge that a batch both deletes and inserts counts as inserted. The result's deletions are in the graph, its insertions
    are not. Of a snapshot, only the buckets of the batch's sources are read.
    """
    once = delta.where("src <> dst").groupBy("src", "dst").agg(F.min("op").alias("op"))  # '+' sorts before '-'
    edges = graph
    if isinstance(graph, Snapshot):
        once = stored(once, "batch")
        edges = graph.out_edges(Keys.of(once.select(F.col("src").alias("id")), graph.buckets))
    ins = once.where("op = '+'").join(edges, ["src", "dst"], "left_anti")
    dels = once.where("op = '-'").join(edges, ["src", "dst"], "left_semi")
    return ins.unionByName(dels).select("src", "dst", "op")


def apply_delta(edges: DataFrame, delta: DataFrame) -> DataFrame:
    """(E without deletions) with insertions; ``delta`` is normalised."""
    return edges.join(delta.where("op = '-'"), ["src", "dst"], "left_anti").select("src", "dst").unionByName(delta.where("op = '+'").select("src", "dst"))


def diff_snapshots(old: DataFrame, new: DataFrame) -> DataFrame:
    """Deletions = old without new, insertions = new without old."""
    gone = old.join(new, ["src", "dst"], "left_anti").select("src", "dst", F.lit("-").alias("op"))
    come = new.join(old, ["src", "dst"], "left_anti").select("src", "dst", F.lit("+").alias("op"))
    return gone.unionByName(come)


def symmetrize(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def number_rows(df: DataFrame, order: list[str], name: str = "seq") -> DataFrame:
    """Dense numbers from 1 in a total order, without a single-task window: range partitions are sorted and
    written, their sizes (one number each) added up on the driver."""
    spark = df.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions", "200"))
    ranged = stored(df.repartitionByRange(parts, *order).sortWithinPartitions(*order).withColumn("row_place", F.monotonically_increasing_id()), "ordered")
    part = F.shiftright("row_place", 33)
    counts = sorted((r["p"], r["n"]) for r in ranged.groupBy(part.alias("p")).agg(F.count(F.lit(1)).alias("n")).collect())
    before, run = {}, 0
    for p, n in counts:
        before[p] = run
        run += n
    if not before:
        return ranged.drop("row_place").withColumn(name, F.lit(0).cast("bigint"))
    first = F.element_at(F.create_map(*[F.lit(x).cast("bigint") for kv in before.items() for x in kv]), part)
    return ranged.withColumn(name, first + F.col("row_place").bitwiseAND(F.lit((1 << 33) - 1)) + 1).drop("row_place")


def successors(df: DataFrame, group: str, order: list[str], value: str, name: str) -> DataFrame:
    """Each row with its group's next ``value`` in order, for groups too large for one task: rows are numbered by range partitions,
    and a row meets the one with the next number. A group's last row has none and goes."""
    rows = number_rows(df, [group, *order], "row_number_in_all")
    after = rows.select((F.col("row_number_in_all") - 1).alias("row_number_in_all"), F.col(group).alias("group_after"), F.col(value).alias(name))
    return rows.join(after, "row_number_in_all").where(F.col(group) == F.col("group_after")).drop("row_number_in_all", "group_after")


def encode_vertices(df: DataFrame, columns: list[str], key: str = "key") -> DataFrame:
    """Dictionary (key, id) of string keys, ids dense from 0 in key order."""
    keys = df.select(F.col(columns[0]).alias(key))
    for c in columns[1:]:
        keys = keys.unionByName(df.select(F.col(c).alias(key)))
    return number_rows(keys.where(F.col(key).isNotNull()).distinct(), [key], "id").select(key, (F.col("id") - 1).alias("id"))


@dataclass
class Base:
    """Edges in two layouts, by source and by target, and vertices with their degrees, all in buckets of the same number."""

    out: Bucketed
    into: Bucketed
    degs: Bucketed
    max_out: int

    def drop(self) -> None:
        for layout in (self.out, self.into, self.degs):
            layout.drop()


@dataclass
class Snapshot:
    """A graph at one time: a base, and what has changed since.

    ``net`` has the edges that the base lacks (+) or has too many (-), ``added`` the vertices that it lacks. Both are small:
    beyond a share of the base they are folded into a new one.
    """

    base: Base
    n_vertices: int
    n_edges: int
    self_loops: bool = True
    net: DataFrame | None = None
    net_path: str | None = None
    n_net: int = 0
    added: DataFrame | None = None
    added_path: str | None = None
    n_added: int = 0
    version: int = 0
    home: str | None = None
    _laid: dict[int, DataFrame] = field(default_factory=dict, repr=False)
    _largest: dict[int, int] = field(default_factory=dict, repr=False)

    @property
    def spark(self) -> SparkSession:
        return self.base.out.spark

    @property
    def buckets(self) -> int:
        return self.base.out.buckets

    def _small(self, df: DataFrame) -> DataFrame:
        return F.broadcast(df) if self.n_net + self.n_added <= BROADCAST_KEYS else df

    def _changed(self, part: DataFrame, net: DataFrame | None) -> DataFrame:
        if net is None:
            return part
        gone = net.where("op = '-'").select("src", "dst")
        return part.join(self._small(gone), ["src", "dst"], "left_anti").unionByName(net.where("op = '+'").select("src", "dst"))

    def _net_of(self, keys: Keys, column: str) -> DataFrame | None:
        return None if self.net is None else self.net.join(keys.semi(column), column, "left_semi").select("src", "dst", "op")

    @property
    def edges(self) -> DataFrame:
        return self._changed(self.base.out.df, self.net)

    def out_edges(self, keys: Keys) -> DataFrame:
        """Edges that start at some vertices."""
        return self._changed(self.base.out.of(keys), self._net_of(keys, "src"))

    def in_edges(self, keys: Keys) -> DataFrame:
        """Edges that end at some vertices."""
        return self._changed(self.base.into.of(keys).select("src", "dst"), self._net_of(keys, "dst"))

    def _degrees(self, known: DataFrame, added: DataFrame | None) -> DataFrame:
        rows = known if added is None else known.unionByName(added.select("id", F.lit(0).cast("bigint").alias("out_deg"), F.lit(0).cast("bigint").alias("in_deg")))
        if self.net is None:
            return rows
        one = F.when(F.col("op") == "+", 1).otherwise(-1).cast("bigint")
        zero = F.lit(0).cast("bigint")
        each = self.net.select(F.col("src").alias("id"), one.alias("d_out"), zero.alias("d_in")).unionByName(self.net.select(F.col("dst").alias("id"), zero.alias("d_out"), one.alias("d_in")))
        change = each.groupBy("id").agg(F.sum("d_out").alias("d_out"), F.sum("d_in").alias("d_in"))
        plus = lambda c, d: (F.col(c) + F.coalesce(d, zero)).alias(c)
        return rows.join(self._small(change), "id", "left").select("id", plus("out_deg", "d_out"), plus("in_deg", "d_in"))

    @property
    def degrees(self) -> DataFrame:
        """id, out_deg, in_deg of all vertices."""
        return self._degrees(self.base.degs.df, self.added)

    def degrees_of(self, keys: Keys) -> DataFrame:
        added = None if self.added is None else self.added.join(keys.semi("id"), "id", "left_semi")
        return self._degrees(self.base.degs.of(keys), added)

    def degrees_in(self, touched: tuple[int, ...]) -> DataFrame:
        """At least the degrees of the vertices of some buckets."""
        return self._degrees(self.base.degs.some(touched), self.added)

    @property
    def vertices(self) -> DataFrame:
        ids = self.base.degs.df.select("id")
        return ids if self.added is None else ids.unionByName(self.added.select("id"))

    def laid(self, parts: int) -> DataFrame:
        """All edges, and each vertex's own row, dealt and sorted by source, kept for the rounds of all runs on this snapshot; lost parts are read again."""
        if parts not in self._laid:
            rows = self.edges.select("src", "dst", F.lit(False).alias("own")).unionByName(own_rows(self.vertices))
            self._laid[parts] = rows.repartition(parts, "src").sortWithinPartitions("src").persist(StorageLevel.MEMORY_AND_DISK)
        return self._laid[parts]

    def even(self, parts: int, most: int) -> bool:
        """Whether no part, of those that a hash of the id deals vertices to, has more than so many of them and of their in-edges."""
        if self.n_edges + self.n_vertices <= most:
            return True
        if parts not in self._largest:
            each = self.degrees.groupBy(F.pmod(F.hash("id"), F.lit(parts)).alias("part")).agg(F.sum(F.col("in_deg") + 1).alias("n"))
            self._largest[parts] = each.agg(F.max("n")).first()[0]
        return self._largest[parts] <= most

    def release(self) -> None:
        for laid in self._laid.values():
            laid.unpersist()
        self._laid.clear()


def snapshot(vertices: DataFrame, edges: DataFrame, self_loops: bool = True, version: int = 0, home: str | None = None) -> Snapshot:
    """A snapshot with its edges written by source and by target, and its degrees; counted while they are written."""
    ids, ids_path, _ = written(vertices.select("id").distinct(), "vertices", home)
    full = with_self_loops(edges.distinct(), ids) if self_loops else edges.select("src", "dst").distinct()
    full, _, got = written(full, "edges", home, n=F.count(F.lit(1)))
    buckets = buckets_for(got["n"])
    out = Bucketed.write(full, "src", buckets, "edges-out", home, got["n"])
    into = Bucketed.write(full.select("dst", "src"), "dst", buckets, "edges-in", home, got["n"])
    zero, one = F.lit(0).cast("bigint"), F.lit(1).cast("bigint")
    # one pass over either end of each edge and the vertices themselves, summed by id
    ends = full.select(F.explode(F.array(F.struct(F.col("src").alias("id"), one.alias("o"), zero.alias("i")), F.struct(F.col("dst").alias("id"), zero.alias("o"), one.alias("i")))).alias("end"))
    each = ends.select("end.id", "end.o", "end.i", F.lit(False).alias("vertex")).unionByName(ids.select("id", zero.alias("o"), zero.alias("i"), F.lit(True).alias("vertex")))
    known = each.groupBy("id").agg(F.sum("o").alias("out_deg"), F.sum("i").alias("in_deg"), F.max("vertex").alias("vertex")).where("vertex").drop("vertex")
    degs = Bucketed.write(known, "id", buckets, "degrees", home, got["n"])
    top = degs.df.agg(F.coalesce(F.max("out_deg"), zero)).first()[0]
    drop_path(ids.sparkSession, ids_path)
    return Snapshot(Base(out, into, degs, top), degs.n, out.n, self_loops, version=version, home=home)


def next_snapshot(g: Snapshot, delta: DataFrame, universe: str = "fixed") -> Snapshot:
    """The snapshot after a normalised batch; writes what has changed since the base, not the graph.

    fixed: changes name vertices of the graph only, any other is an error. grow: insertions bring new vertices, each with its
    self-loop where the graph has them.
    """
    ends = delta.select(F.col("src").alias("id")).unionByName(delta.select(F.col("dst").alias("id"))).distinct()
    keys = Keys.of(ends, g.buckets)
    fresh, added_path, got = written(keys.ids.join(g.degrees_of(keys).select("id"), "id", "left_anti"), "added", g.home, n=F.count(F.lit(1)))
    n_fresh = got["n"]
    if n_fresh and universe == "fixed":
        raise ValueError(f"{n_fresh} vertices of the batch are not in the graph; universe='grow' takes them in")
    rows = delta.select("src", "dst", "op")
    if n_fresh and g.self_loops:
        rows = rows.unionByName(fresh.select(F.col("id").alias("src"), F.col("id").alias("dst"), F.lit("+").alias("op")))
    change = F.coalesce(F.sum(F.when(F.col("op") == "+", 1).otherwise(-1)), F.lit(0)).cast("bigint")
    rows, rows_path, seen = written(rows, "net", g.home, n=F.count(F.lit(1)), change=change)
    net, net_path, n_net = rows, rows_path, seen["n"]
    if g.net is not None:
        # what a batch does to an edge that has changed before takes that change back
        both = rows.join(g.net.select("src", "dst"), ["src", "dst"], "left_anti").unionByName(g.net.join(rows.select("src", "dst"), ["src", "dst"], "left_anti"))
        net, net_path, got = written(both.select("src", "dst", "op"), "net", g.home, n=F.count(F.lit(1)))
        n_net = got["n"]
    added, n_added = (g.added, g.n_added)
    if n_fresh:
        if g.added is not None:
            fresh, added_path, _ = written(fresh.unionByName(g.added), "added", g.home, n=F.count(F.lit(1)))
        added, n_added = fresh, g.n_added + n_fresh
    else:
        added_path = g.added_path
    new = Snapshot(g.base, g.n_vertices + n_fresh, g.n_edges + seen["change"], g.self_loops, net, net_path, n_net, added, added_path, n_added, g.version + 1, g.home)
    return folded(new) if n_net + n_added > FOLD_SHARE * g.base.out.n else new


def folded(g: Snapshot) -> Snapshot:
    """The same graph with a base of its own; each change is folded in a bounded number of times, as the overlay grows with the base."""
    new = snapshot(g.vertices, g.edges, False, g.version, g.home)
    new.self_loops = g.self_loops
    return new


def profile(edges: DataFrame, tedges: DataFrame | None = None) -> DataFrame:
    """One row: vertices, temporal edges, edges, average degree, sinks, largest in-degree; before self-loops."""
    own = static_edges(edges)
    v = vertices_of(edges)
    sinks = v.join(own, v.id == own.src, "left_anti")
    counts = own.agg(F.count(F.lit(1)).alias("edges"))
    temporal = (tedges if tedges is not None else edges).agg(F.count(F.lit(1)).alias("temporal_edges"))
    top = in_degrees(own).agg(F.coalesce(F.max("in_deg"), F.lit(0)).alias("max_in_degree"))
    rows = v.agg(F.count(F.lit(1)).alias("vertices"))
    one = rows
    for t in (temporal, counts, sinks.agg(F.count(F.lit(1)).alias("sinks")), top):
        one = one.join(F.broadcast(t))  # one row each
    return one.withColumn("avg_degree", F.col("edges") / F.col("vertices"))


def empty_delta(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([], DELTA)
